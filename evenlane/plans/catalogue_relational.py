"""Queries of the operators around the sorts: order-based, relational, functions, sources, streams."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Window
from pyspark.sql import functions as F

from evenlane.functions.search import search_udf
from evenlane.functions.spec import Key, SortSpec
from evenlane.operators import relational as rel
from evenlane.operators.layout import Lanes, by_number
from evenlane.operators.merging import merged
from evenlane.operators.networks import bitonic_schedule
from evenlane.operators.sorts import regular_sort
from evenlane.plans.catalogue_sorts import P, R
from evenlane.shipping import ship
from evenlane.sources import tables
from evenlane.sources.tables import IDS, read
from evenlane.staging import fresh_path, stage
from evenlane.streaming import batches

QUERIES: dict[str, Callable] = {}
ORACLE_SQL: dict[str, str] = {}
_L = IDS["lineitem"]
_LS = ", ".join(_L)


def query(sql: str | None = None):
    def put(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE_SQL[f.__name__] = sql
        return f

    return put


def _sorted(spark, sf_dir, *keys, table="lineitem"):
    """In place, ties by the table's identity: ranks that do not hang on where rows lie."""
    return regular_sort(read(spark, sf_dir, table), SortSpec.of(*keys, *[c for c in IDS[table] if c not in keys]), Lanes(P, layout="inplace"), r=R)


def _dealt(spark, sf_dir, *keys, table="lineitem"):
    """In place, ties as rows lie: for results that equal keys' order does not touch."""
    return regular_sort(read(spark, sf_dir, table), SortSpec.of(*keys), Lanes(P, layout="inplace"), r=R)


def _laid(spark, sf_dir, *keys, table="lineitem"):
    """In lanes by content, whose runs are sorted before the route."""
    return regular_sort(read(spark, sf_dir, table), SortSpec.of(*keys), Lanes(P, IDS[table]), r=R)


# ----- on sorted results

_DEAR = Key("l_extendedprice", False)


@query(f"SELECT {_LS}, rank FROM (SELECT *, row_number() OVER (ORDER BY l_extendedprice DESC, {_LS}) AS rank FROM lineitem) WHERE rank <= 100")
def topk_price(spark, sf_dir):
    return rel.top_k(_sorted(spark, sf_dir, _DEAR), 100).select(*_L, "rank")


@query(f"SELECT {_LS}, rank FROM (SELECT *, row_number() OVER (PARTITION BY l_returnflag ORDER BY l_extendedprice DESC, {_LS}) AS rank FROM lineitem) WHERE rank <= 5")
def topk_per_flag(spark, sf_dir):
    """Five a group: each partition's five first, so a hot group never meets in one task whole."""
    d = read(spark, sf_dir, "lineitem").withColumn("salt", F.pmod(F.xxhash64(*_L), F.lit(64)))
    order = [F.desc("l_extendedprice"), *_L]
    few = d.withColumn("rank", F.row_number().over(Window.partitionBy("l_returnflag", "salt").orderBy(*order))).where("rank <= 5")
    return few.withColumn("rank", F.row_number().over(Window.partitionBy("l_returnflag").orderBy(*order)).cast("long")).where("rank <= 5").select(*_L, "rank")


@query(f"SELECT {_LS}, rank FROM (SELECT *, row_number() OVER (ORDER BY l_extendedprice, {_LS}) AS rank FROM lineitem) WHERE rank = 1234")
def kth_element(spark, sf_dir):
    return rel.kth(_sorted(spark, sf_dir, "l_extendedprice"), 1234).select(*_L, "rank")


@query("SELECT CAST(0.5 AS DOUBLE) AS q, quantile_disc(l_extendedprice, 0.5) AS k0 FROM lineitem")
def exact_median(spark, sf_dir):
    return rel.quantile_exact(_dealt(spark, sf_dir, "l_extendedprice"), 0.5)


@query("SELECT CAST(q AS DOUBLE) AS q, k0 FROM (SELECT 0.25 AS q, quantile_disc(l_extendedprice, 0.25) AS k0 FROM lineitem UNION ALL SELECT 0.5, quantile_disc(l_extendedprice, 0.5) FROM lineitem UNION ALL SELECT 0.75, quantile_disc(l_extendedprice, 0.75) FROM lineitem)")
def quartiles(spark, sf_dir):
    return rel.quantile_exact(_dealt(spark, sf_dir, "l_extendedprice"), 0.25, 0.5, 0.75)


@query(f"SELECT {_LS}, rank() OVER (ORDER BY l_shipdate) AS rank FROM lineitem")
def global_rank(spark, sf_dir):
    return rel.with_rank(_dealt(spark, sf_dir, "l_shipdate"), "rank").select(*_L, "rank")


@query(f"SELECT {_LS}, rank() OVER (ORDER BY l_returnflag) AS rank FROM lineitem")
def global_rank_hot_keys(spark, sf_dir):
    return rel.with_rank(_dealt(spark, sf_dir, "l_returnflag"), "rank").select(*_L, "rank")


@query(f"SELECT {_LS}, dense_rank() OVER (ORDER BY l_shipdate) AS dense_rank FROM lineitem")
def global_dense_rank(spark, sf_dir):
    return rel.with_rank(_dealt(spark, sf_dir, "l_shipdate"), "dense_rank").select(*_L, "dense_rank")


@query(f"SELECT {_LS}, CAST(sum(CAST(l_quantity AS BIGINT)) OVER (ORDER BY l_shipdate, {_LS} ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM lineitem")
def global_running_quantity(spark, sf_dir):
    return rel.running_sum(_sorted(spark, sf_dir, "l_shipdate"), "l_quantity").select(*_L, "running")


@query(f"SELECT {_LS} FROM (SELECT *, row_number() OVER (PARTITION BY l_partkey ORDER BY {_LS}) AS r FROM lineitem) WHERE r = 1")
def dedup_first_by_key(spark, sf_dir):
    return rel.first_rows(read(spark, sf_dir, "lineitem", list(_L)), ["l_partkey"], list(_L)).select(*_L)


@query(f"SELECT {_LS} FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY {_LS}) AS r FROM lineitem) WHERE r = 1")
def dedup_sorted_neighbours(spark, sf_dir):
    """The first row of each key where sorted rows meet their neighbours."""
    res = regular_sort(read(spark, sf_dir, "lineitem", list(_L)), SortSpec.of("l_suppkey"), Lanes(P, _L), r=R)
    return rel.dedup(res).select(*_L)


@query("SELECT min(doc_id) AS doc_id, md5(text) AS text_md5 FROM documents GROUP BY text")
def distinct_sorted(spark, sf_dir):
    return rel.first_rows(read(spark, sf_dir, "documents", ["doc_id", "text"]), ["text"], ["doc_id"]).select("doc_id", F.md5("text").alias("text_md5"))


@query("SELECT l_orderkey, l_linenumber, l_partkey, o_custkey, o_orderpriority FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def fenced_merge_join(spark, sf_dir):
    j = rel.fenced_join(_dealt(spark, sf_dir, "l_orderkey"), read(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderpriority"]), "o_orderkey")
    return j.select("l_orderkey", "l_linenumber", "l_partkey", "o_custkey", "o_orderpriority")


@query("SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def fenced_semi_join(spark, sf_dir):
    return rel.fenced_join(_dealt(spark, sf_dir, "l_orderkey"), read(spark, sf_dir, "orders", ["o_orderkey"], "o_orderpriority = '1-URGENT'"), "o_orderkey", "left_semi").select("l_orderkey", "l_linenumber", "l_partkey")


@query("SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE l_orderkey NOT IN (SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def fenced_anti_join(spark, sf_dir):
    return rel.fenced_join(_dealt(spark, sf_dir, "l_orderkey"), read(spark, sf_dir, "orders", ["o_orderkey"], "o_orderpriority = '1-URGENT'"), "o_orderkey", "left_anti").select("l_orderkey", "l_linenumber", "l_partkey")


@query("SELECT a.event_id AS event_id, b.event_id AS later_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def fenced_range_join(spark, sf_dir):
    right = read(spark, sf_dir, "events", ["event_id", "user_id", "ts"]).toDF("later_id", "r_user", "r_ts")
    return rel.range_join(_dealt(spark, sf_dir, "ts", table="events"), right, "r_ts", ("user_id", "r_user"), F.expr("INTERVAL 1 HOUR")).select("event_id", "later_id")


@query("SELECT p.event_id AS event_id, (SELECT max_by(v.event_id, (v.ts, v.event_id)) FROM events v WHERE v.event_type = 'view' AND v.user_id = p.user_id AND v.ts <= p.ts) AS view_id FROM events p WHERE p.event_type = 'purchase' AND EXISTS (SELECT 1 FROM events v WHERE v.event_type = 'view' AND v.user_id = p.user_id AND v.ts <= p.ts)")
def asof_events(spark, sf_dir):
    e = read(spark, sf_dir, "events", ["event_id", "user_id", "event_type", "ts"])
    out = rel.asof(e.where("event_type = 'purchase'"), e.where("event_type = 'view'").withColumn("view", F.col("event_id")), "user_id", "ts", "view", "view_id")
    return out.where("view_id is not null").select("event_id", "view_id")


@query("SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS rank FROM orders")
def merge_two_sorted(spark, sf_dir):
    o = read(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"])
    spec = SortSpec.of("o_totalprice", "o_orderkey")
    a = regular_sort(o.where("o_totalprice < 200000"), spec, Lanes(P, layout="inplace"), r=R)
    merged = stage(rel.merge_sorted(a, o.where("not o_totalprice < 200000")).withColumn("__id", F.monotonically_increasing_id()), "merged")
    part = F.shiftright("__id", 33)
    sizes = {r[0]: r[1] for r in merged.groupBy(part.alias("b")).count().collect()}
    base, total = [], 0
    for b in range(P):
        base.append(total)
        total += sizes.get(b, 0)
    return merged.select("o_orderkey", (F.array(*map(F.lit, base))[part.cast("int")] + F.col("__id").bitwiseAND(F.lit((1 << 33) - 1)) + 1).alias("rank"))


@query("SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' UNION SELECT o_custkey FROM orders WHERE o_orderstatus = 'O'")
def sorted_union(spark, sf_dir):
    o = read(spark, sf_dir, "orders", where="o_orderstatus in ('F', 'O')")
    return rel.dedup(regular_sort(o, SortSpec.of("o_custkey"), Lanes(P, layout="inplace"), r=R)).select("o_custkey")


@query("SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O'")
def sorted_intersect(spark, sf_dir):
    left = rel.dedup(regular_sort(read(spark, sf_dir, "orders", where="o_orderstatus = 'F'"), SortSpec.of("o_custkey"), Lanes(P, layout="inplace"), r=R)).select("o_custkey")
    return left.join(read(spark, sf_dir, "orders", ["o_custkey"], "o_orderstatus = 'O'"), "o_custkey", "left_semi")


@query("SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' EXCEPT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O'")
def sorted_except(spark, sf_dir):
    left = rel.dedup(regular_sort(read(spark, sf_dir, "orders", where="o_orderstatus = 'F'"), SortSpec.of("o_custkey"), Lanes(P, layout="inplace"), r=R)).select("o_custkey")
    return left.join(read(spark, sf_dir, "orders", ["o_custkey"], "o_orderstatus = 'O'"), "o_custkey", "left_anti")


@query("SELECT l_suppkey AS k0, count(*) AS n, CAST(sum(l_linenumber) AS BIGINT) AS lines FROM lineitem GROUP BY 1")
def sorted_aggregate(spark, sf_dir):
    return rel.sorted_agg(_dealt(spark, sf_dir, "l_suppkey"), n="count(*)", lines="sum(l_linenumber)")


@query("SELECT o_orderkey FROM (SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS r FROM orders) WHERE r BETWEEN 500 AND 700")
def rank_slice(spark, sf_dir):
    return rel.slice_ranks(_sorted(spark, sf_dir, "o_totalprice", table="orders"), 500, 700).select("o_orderkey")


# ----- relational operators of the engine underneath

_AGG = "count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity"
for _n, _how in (("rollup", "ROLLUP(l_returnflag, l_linestatus)"), ("cube", "CUBE(l_returnflag, l_linestatus)"), ("grouping_sets", "GROUPING SETS ((l_returnflag), (l_linestatus), ())")):
    _sql = f"SELECT coalesce(l_returnflag, '*') AS flag, coalesce(l_linestatus, '*') AS status, {_AGG} FROM lineitem GROUP BY {_how}"

    def _grouped(spark, sf_dir, sql=_sql):
        return spark.sql(sql.replace("FROM lineitem", "FROM {t}"), t=read(spark, sf_dir, "lineitem"))

    QUERIES[f"{_n}_flags"], ORACLE_SQL[f"{_n}_flags"] = _grouped, _sql

_SQL_OPS = {
    "filter_project": "SELECT o_orderkey, o_custkey * 2 AS twice, upper(o_orderpriority) AS priority FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderpriority LIKE '%URGENT%' AND o_orderstatus IN ('F', 'O') AND o_custkey IS NOT NULL",
    "left_join": "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey",
    "right_join": "SELECT p_partkey, coalesce(l_orderkey, -1) AS orderkey, coalesce(l_linenumber, -1) AS line FROM lineitem RIGHT JOIN part ON l_partkey = p_partkey AND l_quantity > 45",
    "full_join": "SELECT coalesce(a.o_custkey, b.o_custkey) AS custkey, a.n AS urgent, b.n AS low FROM (SELECT o_custkey, count(*) AS n FROM orders WHERE o_orderpriority = '1-URGENT' GROUP BY 1) a FULL JOIN (SELECT o_custkey, count(*) AS n FROM orders WHERE o_orderpriority = '5-LOW' GROUP BY 1) b ON a.o_custkey = b.o_custkey WHERE a.n IS NOT NULL AND b.n IS NOT NULL",
    "theta_join": "SELECT a.n_nationkey AS a, b.r_regionkey AS b FROM nation a JOIN region b ON a.n_regionkey < b.r_regionkey",
    "semi_join": "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)",
    "anti_join": "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)",
    "hash_aggregate": "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity, min(l_shipdate) AS first_day, max(l_extendedprice) AS dearest FROM lineitem GROUP BY 1, 2",
    "count_distinct": "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1",
    "window_ranks": "SELECT o_orderkey, CAST(row_number() OVER w AS BIGINT) AS rn, CAST(rank() OVER w AS BIGINT) AS rk, CAST(dense_rank() OVER w AS BIGINT) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS quarter, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)",
    "window_neighbours": "SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before_id, coalesce(lead(event_id) OVER w, -1) AS after_id, first_value(event_id) OVER w AS first_id, coalesce(nth_value(event_id, 2) OVER w, -1) AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "window_frames": "SELECT o_orderkey, CAST(sum(o_custkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS last_three, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS near FROM orders",
    "set_operations": "SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' INTERSECT ALL SELECT o_custkey FROM orders WHERE o_orderstatus = 'O' UNION ALL (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT' EXCEPT ALL SELECT o_custkey FROM orders WHERE o_orderpriority = '5-LOW')",
    "limit_offset": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10",
    "string_functions": "SELECT doc_id, CAST(length(text) AS BIGINT) AS chars, md5(upper(source)) AS head, md5(text) AS digest, concat_ws('-', lang, source) AS place, CAST(length(text) - length(replace(text, 'e', '')) AS BIGINT) AS letters_e FROM documents",
    "date_functions": "SELECT o_orderkey, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS STRING) AS month, CAST(extract(year FROM o_orderdate) AS INTEGER) AS year, o_orderdate + INTERVAL 3 DAY AS due FROM orders",
    "math_functions": "SELECT o_orderkey, CAST(ceil(log2(o_orderkey + 1)) AS BIGINT) AS bits, CAST(floor(sqrt(o_custkey)) AS BIGINT) AS root, greatest(o_orderkey, o_custkey) AS larger, o_orderkey % 7 AS rest FROM orders",
}
for _n, _sql in _SQL_OPS.items():

    def _by_sql(spark, sf_dir, sql=_sql):
        names = [t for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents") if f" {t}" in sql]
        views = {t: read(spark, sf_dir, t) for t in names}
        text = sql
        for t in sorted(names, key=len, reverse=True):
            for word in ("FROM ", "JOIN "):
                text = text.replace(f"{word}{t}", f"{word}{{{t}}} {t}" if not text.split(f"{word}{t}", 1)[-1].startswith((" a", " b")) else f"{word}{{{t}}}")
        return spark.sql(text, **views)

    QUERIES[f"sql_{_n}"], ORACLE_SQL[f"sql_{_n}"] = _by_sql, _sql


@query("SELECT l_partkey, p_size, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2")
def join_broadcast(spark, sf_dir):
    """The part side is broadcast where Spark's own size check lets it."""
    return read(spark, sf_dir, "lineitem", ["l_partkey"]).join(read(spark, sf_dir, "part", ["p_partkey", "p_size"]), F.col("l_partkey") == F.col("p_partkey")).groupBy("l_partkey", "p_size").agg(F.count("*").alias("n"))


for _hint in ("merge", "shuffle_hash"):

    def _hinted(spark, sf_dir, hint=_hint):
        o = read(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]).hint(hint)
        return o.join(read(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_nationkey")

    QUERIES[f"join_{_hint}"] = _hinted
    ORACLE_SQL[f"join_{_hint}"] = "SELECT o_orderkey, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey"


@query("SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY 1")
def pivot_status(spark, sf_dir):
    return read(spark, sf_dir, "orders").groupBy("o_custkey").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey")).na.fill(0)


@query("SELECT DISTINCT l_suppkey, l_linenumber FROM lineitem")
def distinct_pairs(spark, sf_dir):
    return read(spark, sf_dir, "lineitem", ["l_suppkey", "l_linenumber"]).distinct()


@query("SELECT count(DISTINCT l_partkey) AS parts, quantile_cont(l_extendedprice, 0.5) AS median, true AS hll_fits, true AS summary_fits, true AS kll_fits FROM lineitem")
def approx_measures(spark, sf_dir):
    """Sketches beside exact figures, and whether they keep their bounds: three deviations of HyperLogLog, the rank errors of two quantile summaries."""
    d = read(spark, sf_dir, "lineitem", ["l_partkey", "l_extendedprice"])
    got = d.agg(
        F.count_distinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.02).alias("hll"), F.expr("percentile(l_extendedprice, 0.5)").alias("median"),
        F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("summary"), F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(l_extendedprice), 0.5)").alias("kll"), F.count("*").alias("n"),
    ).first()
    below = d.agg(F.count_if(F.col("l_extendedprice") <= got["summary"]).alias("s"), F.count_if(F.col("l_extendedprice") <= got["kll"]).alias("k")).first()
    n = got["n"]
    row = (got["parts"], got["median"], abs(got["hll"] - got["parts"]) <= 0.06 * got["parts"], abs(below["s"] - n / 2) <= n / 10_000 + 2, abs(below["k"] - n / 2) <= 0.02 * n + 2)
    return spark.createDataFrame([row], "parts long, median double, hll_fits boolean, summary_fits boolean, kll_fits boolean")


@query("SELECT o_orderkey FROM (SELECT o_orderkey, row_number() OVER (ORDER BY md5('7|' || o_orderkey), o_orderkey) AS r FROM orders) WHERE r <= 500")
def sample_exact_rows(spark, sf_dir):
    """A sample of exact size by smallest hashes: a sampling operator, so its limit is the feature."""
    return read(spark, sf_dir, "orders", ["o_orderkey"]).orderBy(F.md5(F.concat(F.lit("7|"), F.col("o_orderkey").cast("string"))), "o_orderkey").limit(500)


@query("SELECT kind, o_orderstatus, true AS fits FROM (SELECT 'bernoulli' AS kind, o_orderstatus FROM orders UNION SELECT 'stratified', o_orderstatus FROM orders WHERE o_orderstatus IN ('F', 'O'))")
def sample_rates(spark, sf_dir):
    """Sampled shares, and whether they lie within five deviations of their rates."""
    o = read(spark, sf_dir, "orders", ["o_orderkey", "o_orderstatus"])
    rates = {"F": 0.1, "O": 0.2}
    got = o.sample(0.1, 3).withColumn("kind", F.lit("bernoulli")).union(o.sampleBy("o_orderstatus", rates, 3).withColumn("kind", F.lit("stratified"))).groupBy("kind", "o_orderstatus").count()
    rate = F.when(F.col("kind") == "bernoulli", 0.1).otherwise(F.create_map(*[F.lit(x) for kv in rates.items() for x in kv])[F.col("o_orderstatus")])
    return got.join(o.groupBy("o_orderstatus").agg(F.count("*").alias("all")), "o_orderstatus").select("kind", "o_orderstatus", (F.abs(F.col("count") - rate * F.col("all")) <= 5 * F.sqrt(rate * F.col("all"))).alias("fits"))


@query("SELECT vec_id, CAST(len(embedding) AS INTEGER) AS dims, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, round(list_max(embedding), 4) AS largest FROM embeddings")
def array_functions(spark, sf_dir):
    e = read(spark, sf_dir, "embeddings")
    return e.select("vec_id", F.size("embedding").alias("dims"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.array_max("embedding"), 4).alias("largest"))


@query("SELECT doc_id, lang || '/' || source AS place FROM documents")
def map_functions(spark, sf_dir):
    m = F.create_map(F.lit("lang"), F.col("lang"), F.lit("source"), F.col("source"))
    return read(spark, sf_dir, "documents", ["doc_id", "lang", "source"]).withColumn("m", m).select("doc_id", F.concat_ws("/", F.element_at("m", "lang"), F.element_at("m", "source")).alias("place"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.page') AS VARCHAR) AS page FROM events")
def json_functions(spark, sf_dir):
    return read(spark, sf_dir, "events", ["event_id", "props"]).select("event_id", F.get_json_object("props", "$.page").alias("page"))


# ----- Python surface


@query("SELECT bucket, count(*) AS n FROM (SELECT CAST((l_partkey >= 500) AS INTEGER) + CAST((l_partkey >= 1000) AS INTEGER) + CAST((l_partkey >= 1500) AS INTEGER) AS bucket FROM lineitem) GROUP BY bucket")
def udf_search(spark, sf_dir):
    """Fence search as a vectorised function, for engines of fences outside a sort."""
    ship(spark)
    return read(spark, sf_dir, "lineitem", ["l_partkey"]).select(search_udf([500, 1000, 1500])("l_partkey").alias("bucket")).groupBy("bucket").agg(F.count("*").alias("n"))


for _how in ("heap", "fold"):

    def _merged(spark, sf_dir, how=_how):
        """The runs that reach a bucket merged instead of sorted: one pass over blocks in lane order."""
        res = _laid(spark, sf_dir, "o_orderdate", table="orders")
        base, total = [], 0
        for n in res.bucket_sizes():
            base.append(total)
            total += n
        return merged(res, "o_orderkey", how=how).select("o_orderkey", (by_number(base, F.col("bucket")) + F.col("place") + 1).alias("rank"))

    QUERIES[f"{_how}_merge"] = _merged
    ORACLE_SQL[f"{_how}_merge"] = "SELECT o_orderkey, row_number() OVER (ORDER BY o_orderdate, o_orderkey) AS rank FROM orders"


@query("SELECT o_orderkey, o_orderstatus FROM (SELECT *, row_number() OVER (PARTITION BY o_orderstatus ORDER BY md5('5|' || o_orderkey), o_orderkey) AS r FROM orders) WHERE r <= 3")
def reservoir_sample(spark, sf_dir):
    """A seeded sample of three rows a status, the smallest hashes: of each salt first, so a group never meets in one task whole."""
    o = read(spark, sf_dir, "orders", ["o_orderkey", "o_orderstatus"]).withColumn("h", F.md5(F.concat(F.lit("5|"), F.col("o_orderkey").cast("string")))).withColumn("salt", F.substring("h", -2, 2))
    few = o.withColumn("r", F.row_number().over(Window.partitionBy("o_orderstatus", "salt").orderBy("h", "o_orderkey"))).where("r <= 3")
    return few.withColumn("r", F.row_number().over(Window.partitionBy("o_orderstatus").orderBy("h", "o_orderkey"))).where("r <= 3").select("o_orderkey", "o_orderstatus")


@query("SELECT CAST(i AS INTEGER) AS low, CAST(i + 1 AS INTEGER) AS high FROM (SELECT unnest([0, 2, 4, 6]) AS i) WHERE i % 4 = 0 UNION ALL SELECT CAST(i + 1 AS INTEGER), CAST(i AS INTEGER) FROM (SELECT unnest([2, 6]) AS i)")
def udtf_schedule(spark, sf_dir):
    """The first step of the bitonic network on 8 lanes, as a table function."""
    ship(spark)

    @F.udtf(returnType="step int, low int, high int")
    class Schedule:
        def eval(self, p: int):
            for i, (_, _, step) in enumerate(bitonic_schedule(p)):
                for a, b in step:
                    yield i, a, b

    return Schedule(F.lit(8)).where("step = 0").select("low", "high")


@query("SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY 1")
def sql_views(spark, sf_dir):
    read(spark, sf_dir, "lineitem").createOrReplaceTempView("evenlane_lineitem")
    return spark.sql("SELECT l_returnflag, count(*) AS n FROM evenlane_lineitem GROUP BY 1")


# ----- sources and sinks


@query("SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice BETWEEN 100000 AND 120000")
def fenced_range_read(spark, sf_dir):
    path = fresh_path(spark, "fenced")
    tables.write_fenced(_sorted(spark, sf_dir, "o_totalprice", table="orders"), path)
    return tables.read_range(spark, path, SortSpec.of("o_totalprice"), 100000.0, 120000.0).select("o_orderkey", "o_totalprice")


@query("SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS rank FROM orders")
def sorted_sink(spark, sf_dir):
    """The rank of every row from where it lies in the files alone: files in the order of their names, rows in the order they have."""
    path = fresh_path(spark, "sorted")
    tables.write_sorted(_sorted(spark, sf_dir, "o_totalprice", table="orders"), path)
    rows = spark.read.parquet(path).select("o_orderkey", F.col("_metadata.file_name").alias("file"), F.col("_metadata.row_index").alias("at"))
    sizes = rows.groupBy("file").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("file").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # one row a bucket
    return rows.join(sizes.select("file", before.alias("base")), "file").select("o_orderkey", (F.col("base") + F.col("at") + 1).alias("rank"))


@query("SELECT c_custkey, o_orderkey FROM customer JOIN orders ON c_custkey = o_custkey")
def bucketed_join(spark, sf_dir):
    """Two tables bucketed by the key of their join: neither side is moved by it."""
    tag = fresh_path(spark, "t").rsplit("-", 1)[1]
    tables.write_bucketed(read(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]), f"evenlane_orders_{tag}", 8, "o_custkey")
    tables.write_bucketed(read(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]), f"evenlane_customer_{tag}", 8, "c_custkey")
    o, c = spark.table(f"evenlane_orders_{tag}").hint("merge"), spark.table(f"evenlane_customer_{tag}")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


for _fmt in ("csv", "json", "orc"):

    def _formats(spark, sf_dir, fmt=_fmt):
        path = fresh_path(spark, fmt)
        tables.write_any(read(spark, sf_dir, "customer"), path, fmt)
        return tables.read_any(spark, path, fmt, ", ".join(f"{n} {t}" for n, t in read(spark, sf_dir, "customer").dtypes))

    QUERIES[f"source_{_fmt}"] = _formats
    ORACLE_SQL[f"source_{_fmt}"] = "SELECT * FROM customer"


@query("SELECT n_nationkey || ' ' || n_name AS value FROM nation")
def source_text(spark, sf_dir):
    path = fresh_path(spark, "text")
    tables.write_any(read(spark, sf_dir, "nation").select(F.concat_ws(" ", F.col("n_nationkey").cast("string"), "n_name").alias("value")), path, "text")
    return tables.read_any(spark, path, "text", "value string")


# ----- streams


_SLICE = "(event_id * 5) div {n}"


def _event_stream(spark, sf_dir, late: bool = False):
    """events in five files, as a stream of five micro-batches by event_id; with late, every seventh event comes one slice after its own."""
    path = fresh_path(spark, "slices")
    e = read(spark, sf_dir, "events", ["event_id", "user_id", "event_type", "ts", "value"]).withColumn("ts", F.col("ts").cast("timestamp"))
    at = F.expr(_SLICE.format(n=e.count()))
    at = F.least(at + F.when(F.col("event_id") % 7 == 0, 1).otherwise(0), F.lit(4)) if late else at
    staged = stage(e.withColumn("slice", at), "events")
    for i in range(5):  # one file a slice, in the order of the stream
        staged.where(F.col("slice") == i).drop("slice").coalesce(1).write.mode("append").parquet(path)
    return e, batches.file_stream(spark, path, e.schema)


@query("SELECT event_id, CAST(0 AS INTEGER) AS misplaced FROM events")
def stream_sorted_batches(spark, sf_dir):
    """Every row arrives once, with the number of bucket pairs whose keys overlap: fixed fences leave none."""
    e, stream = _event_stream(spark, sf_dir)
    spec = SortSpec.of("value")
    fences = regular_sort(e, spec, Lanes(4, ("event_id",)), r=R).fences
    out = fresh_path(spark, "stream-out")
    batches.run_once(batches.sorted_batches(stream, spec, fences, out, fresh_path(spark, "stream-cp")))
    rows = spark.read.option("recursiveFileLookup", "false").parquet(out)
    ends = rows.groupBy("bucket").agg(F.min("k0").alias("lo"), F.max("k0").alias("hi"))
    wrong = ends.alias("a").join(ends.alias("b"), F.col("a.bucket") < F.col("b.bucket")).where(F.col("a.hi") > F.col("b.lo")).count()
    return rows.select("event_id", F.lit(wrong).cast("int").alias("misplaced"))


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, count(*) AS n FROM events GROUP BY 1")
def stream_tumbling(spark, sf_dir):
    _, stream = _event_stream(spark, sf_dir)
    return batches.to_table(spark, batches.windowed(stream, "ts", "365 days", "1 hour"), "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) - to_hours(CAST(k AS BIGINT)) AS start, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1")
def stream_sliding(spark, sf_dir):
    _, stream = _event_stream(spark, sf_dir)
    return batches.to_table(spark, batches.windowed(stream, "ts", "365 days", "2 hours", "1 hour"), "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@query("""
WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 30 MINUTE <= date_trunc('milliseconds', (SELECT max(ts) FROM events) - INTERVAL 1 HOUR)""")
def stream_sessions(spark, sf_dir):
    """Sessions that the watermark has closed: those that end an hour or more before the last event."""
    _, stream = _event_stream(spark, sf_dir)
    return batches.to_table(spark, batches.sessions(stream, "ts", "user_id", "1 hour", "30 minutes"), "append").select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


@query("SELECT DISTINCT user_id FROM events")
def stream_dedup(spark, sf_dir):
    _, stream = _event_stream(spark, sf_dir)
    return batches.to_table(spark, batches.distinct_in_stream(stream, "ts", "3650 days", "user_id"), "append").select("user_id")


@query("SELECT CAST((event_id * 5) // (SELECT count(*) FROM events) AS INTEGER) AS batch, count(*) AS n, 7.0::DOUBLE AS over, true AS refreshed FROM events GROUP BY 1")
def stream_fence_drift(spark, sf_dir):
    """Event times always pass the fences of the batch before: every batch breaks the bound and takes fences of its own."""
    _, stream = _event_stream(spark, sf_dir)
    out = fresh_path(spark, "drift")
    batches.run_once(batches.drifting_fences(stream, SortSpec.of("ts"), 8, R, out, fresh_path(spark, "stream-cp")))
    return spark.read.parquet(f"{out}/report").select("batch", "n", F.coalesce("imbalance", F.lit(7.0)).alias("over"), "refreshed")


@query("SELECT CAST((event_id * 5) // (SELECT count(*) FROM events) AS INTEGER) AS batch, count(*) AS n, CAST((event_id * 5) // (SELECT count(*) FROM events) AS INTEGER) = 0 AS refreshed FROM events GROUP BY 1")
def stream_steady_fences(spark, sf_dir):
    """Values of one distribution stay within the bound: the first batch's fences hold to the end."""
    _, stream = _event_stream(spark, sf_dir)
    out = fresh_path(spark, "drift")
    batches.run_once(batches.drifting_fences(stream, SortSpec.of("hash(event_id)"), 4, 2, out, fresh_path(spark, "stream-cp")))
    return spark.read.parquet(f"{out}/report").select("batch", "n", "refreshed")


@query("""
WITH b AS (SELECT event_id, ts, least(CAST((event_id * 5) // (SELECT count(*) FROM events) AS INTEGER) + CASE WHEN event_id % 7 = 0 THEN 1 ELSE 0 END, 4) AS batch FROM events),
w AS (SELECT batch, max(max(ts)) OVER (ORDER BY batch ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) - INTERVAL 1 DAY AS mark FROM b GROUP BY batch)
SELECT b.batch, count(*) FILTER (NOT coalesce(ts < mark, false)) AS in_time, count(*) FILTER (coalesce(ts < mark, false)) AS late FROM b JOIN w USING (batch) GROUP BY b.batch""")
def stream_late_rows(spark, sf_dir):
    """Rows under a batch's watermark go out apart, as a sorted correction run of their own."""
    e, stream = _event_stream(spark, sf_dir, late=True)
    spec, out = SortSpec.of("value"), fresh_path(spark, "late")
    fences = regular_sort(e, spec, Lanes(4, layout="inplace"), r=R).fences
    batches.run_once(batches.with_corrections(stream, "ts", "1 day", spec, fences, out, fresh_path(spark, "stream-cp")))
    written = lambda kind: spark.read.option("basePath", f"{out}/{kind}").parquet(f"{out}/{kind}").groupBy("batch").agg(F.count("*").alias(kind))
    counts = written("rows").join(written("corrections"), "batch", "full").na.fill(0)
    return counts.select(F.col("batch").cast("int").alias("batch"), F.col("rows").alias("in_time"), F.col("corrections").alias("late"))
