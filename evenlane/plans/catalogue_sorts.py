"""Queries of the sorts, their steps and baselines: ranks, samples, fences, splits, offsets."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenlane.functions.spec import Key, SortSpec
from evenlane.operators import baselines, networks, prefix, sampling
from evenlane.operators.layout import Lanes, sorted_run
from evenlane.operators.sorts import SortResult, balanced_sort, classic_random_sort, iterated_sort, presorted_random_sort, regular_sort, sort_sample
from evenlane.operators.split import count_matrix, with_bucket
from evenlane.plans import oracle
from evenlane.plans.oracle import Source
from evenlane.sources.tables import IDS, read
from evenlane.staging import stage

P, R = 8, 4
QUERIES: dict[str, Callable] = {}
ORACLE_SQL: dict[str, str] = {}

def shown(df: DataFrame, table: str, spec: SortSpec, *more: str) -> DataFrame:
    return df.select(*IDS[table], *spec.names, F.col("lane").cast("int").alias("lane"), "pos", *more, "rank")


def source(table: str) -> Source:
    return Source(table, IDS[table])


def rank_query(name: str, table: str, spec: SortSpec, sort: Callable[..., SortResult], sql: str) -> None:
    def run(spark, sf_dir):
        res = sort(read(spark, sf_dir, table), spec)
        return shown(res.with_rank(), table, spec, "bucket")

    QUERIES[name], ORACLE_SQL[name] = run, sql


def regular_sql(table: str, spec: SortSpec, p: int = P, r: int = R, layout: str = "block", spacing: str = "even", tagged: bool = True, tail: str | None = None) -> str:
    return oracle.runs(source(table), spec, p, layout) + oracle.regular_sample(r * p, p, spacing) + oracle.fences(p, r * p) + oracle.buckets(tagged) + (tail or oracle.ranks(source(table), spec))


def random_sql(table: str, spec: SortSpec, s: int | None = None, seed: int = 42, tagged: bool = True, tail: str | None = None, unsorted: bool = False) -> str:
    start = oracle.unsorted_runs if unsorted else oracle.runs
    s = s or oracle.random_size(table)
    return start(source(table), spec, P) + oracle.random_sample(s, seed) + oracle.fences(P, s) + oracle.buckets(tagged) + (tail or oracle.ranks(source(table), spec))


REGULAR = {
    "regular_sort_partkey": ("lineitem", ("l_partkey",), {}),
    "regular_sort_price": ("lineitem", ("l_extendedprice",), {}),
    "regular_sort_returnflag": ("lineitem", ("l_returnflag",), {}),
    "regular_sort_constant": ("lineitem", ("1",), {}),
    "regular_sort_shipdate": ("lineitem", ("l_shipdate",), {}),
    "regular_sort_multikey": ("lineitem", ("l_returnflag", Key("l_extendedprice", False)), {}),
    "regular_sort_nulls": ("lineitem", (Key("nullif(l_linenumber, 3)", True, False),), {}),
    "regular_sort_nulls_first_desc": ("lineitem", (Key("nullif(l_linenumber, 3)", False, True),), {}),
    "regular_sort_text": ("documents", ("text",), {"p": 4}),
    "regular_sort_presorted": ("events", ("ts",), {}),
    "regular_sort_reversed": ("events", (Key("ts", False),), {}),
    "regular_sort_composite": ("conversations", ("conv_id", "turn"), {}),
    "regular_sort_priority": ("orders", ("o_orderpriority",), {}),
    "regular_sort_padded": ("orders", ("o_totalprice",), {"spacing": "padded"}),
    "regular_sort_deal": ("orders", ("o_totalprice",), {"layout": "deal"}),
    "regular_sort_radix": ("lineitem", ("l_linenumber",), {"local": "radix"}),
    "regular_sort_cmp": ("lineitem", ("l_linenumber",), {"local": "cmp"}),
    "regular_sort_spark_sample": ("orders", ("o_orderdate",), {"sample_sort": "spark"}),
    "regular_sort_bitonic_sample": ("orders", ("o_orderdate",), {"sample_sort": "bitonic"}),
    "regular_sort_tagless": ("lineitem", ("l_returnflag",), {"dup": False}),
}


def _regular(name: str, table: str, keys: tuple, options: dict) -> None:
    spec = SortSpec.of(*keys)
    p = options.get("p", P)
    layout = options.get("layout", "block")
    extra = {k: v for k, v in options.items() if k not in ("p", "layout")}
    sql = regular_sql(table, spec, p, R, layout, options.get("spacing", "even"), options.get("dup", True))
    if table == "documents":  # long texts are shown by their digest
        sql = f"SELECT doc_id, md5(k0) AS k0, lane, pos, bucket, rank FROM ({sql})"
    if "nulls" in name:
        sql = f"SELECT * REPLACE (coalesce(k0, 0) AS k0) FROM ({sql})"
    if not options.get("dup", True):
        sql = regular_sql(table, spec, p, R, layout, tagged=False, tail=oracle.ranks(source(table), spec).replace("ORDER BY kr, lane, pos", "ORDER BY bucket, kr, lane, pos"))

    def run(spark, sf_dir):
        res = regular_sort(read(spark, sf_dir, table), spec, Lanes(p, IDS[table], layout), r=R, **extra)
        out = shown(res.with_rank(), table, spec, "bucket")
        if "nulls" in name:  # null keys are shown as 0, which no key is
            out = out.withColumn("k0", F.coalesce("k0", F.lit(0)))
        return out.withColumn("k0", F.md5("k0")) if table == "documents" else out

    QUERIES[name], ORACLE_SQL[name] = run, sql


for _n, (_t, _k, _o) in REGULAR.items():
    _regular(_n, _t, _k, _o)


def _laid(sort: Callable, table: str, **options) -> Callable:
    """The sort over the table's layout by content, its sample of the method's own size."""

    def run(df, spec):
        return sort(df, spec, Lanes(P, IDS[table]), **options)

    return run


for _n, _key in (("partkey", "l_partkey"), ("price", "l_extendedprice"), ("returnflag", "l_returnflag"), ("constant", "1")):
    _spec = SortSpec.of(_key)
    rank_query(f"random_sort_{_n}", "lineitem", _spec, _laid(presorted_random_sort, "lineitem"), random_sql("lineitem", _spec))
    rank_query(f"classic_sort_{_n}", "lineitem", _spec, _laid(classic_random_sort, "lineitem"), random_sql("lineitem", _spec, unsorted=True))
rank_query("classic_sort_integer", "lineitem", SortSpec.of("l_partkey"), _laid(classic_random_sort, "lineitem", split="integer"), random_sql("lineitem", SortSpec.of("l_partkey"), unsorted=True))

_spec, _s = SortSpec.of("o_totalprice"), oracle.random_size("orders")
rank_query(
    "random_sort_two_step", "orders", _spec, _laid(presorted_random_sort, "orders", mode="two_step"),
    oracle.runs(source("orders"), _spec, P) + oracle.two_step_sample(_s, P, 42) + oracle.fences(P, None) + oracle.buckets() + oracle.ranks(source("orders"), _spec),
)
rank_query("random_sort_radix", "lineitem", SortSpec.of("l_linenumber"), _laid(presorted_random_sort, "lineitem", local="radix"), random_sql("lineitem", SortSpec.of("l_linenumber")))


def plain_rank(name: str, table: str, key: str, run_: Callable[[DataFrame, SortSpec, Lanes], SortResult | DataFrame], p: int = P, unsorted: bool = False, narrow: bool = False) -> None:
    """A query that shows ranks alone: its buckets have no SQL, or it has none."""
    spec = SortSpec.of(key)

    def run(spark, sf_dir):
        out = run_(read(spark, sf_dir, table), spec, Lanes(p, IDS[table]))
        df = out.with_rank() if isinstance(out, SortResult) else out
        return df.select("k0", F.col("lane").cast("int").alias("lane"), "pos", "rank") if narrow else shown(df, table, spec)

    start = oracle.unsorted_runs if unsorted else oracle.runs
    sql = start(source(table), spec, p) + oracle.ranks(source(table), spec, False)
    if narrow:
        sql = f"SELECT k0, lane, pos, rank FROM ({sql})"
    QUERIES[name], ORACLE_SQL[name] = run, sql


plain_rank("iterated_sort_m2", "lineitem", "l_partkey", lambda d, s, l: iterated_sort(d, s, l, 3, 2), p=9)
plain_rank("binary_rounds_sort", "orders", "o_totalprice", baselines.binary_rounds)
plain_rank("kway_rounds_sort", "orders", "o_totalprice", lambda d, s, l: baselines.kway_rounds(d, s, l, 4), p=16)
plain_rank("two_round_sort", "lineitem", "l_partkey", baselines.two_round_regular)
plain_rank("two_round_random_sort", "lineitem", "l_partkey", baselines.two_round_random)
plain_rank("tag_all_sort", "lineitem", "l_returnflag", baselines.tag_all)
plain_rank("plain_regular_sort", "orders", "o_orderkey", baselines.plain_regular)
plain_rank("sample_sort_untagged", "orders", "o_orderkey", baselines.sample_sort_untagged, unsorted=True)
plain_rank("range_exchange_sort", "orders", "o_totalprice", baselines.range_exchange)
plain_rank("comparator_sort", "orders", "o_totalprice", baselines.callback_sort)
plain_rank("sequential_sort", "orders", "o_totalprice", lambda d, s, l: baselines.sequential(d, s, IDS["orders"]), p=1)
plain_rank("sequential_radix_sort", "orders", "o_custkey", lambda d, s, l: baselines.sequential(d, s, IDS["orders"], "radix"), p=1)
plain_rank("bitonic_sort_orders", "orders", "o_totalprice", baselines.bitonic_all, narrow=True)
plain_rank("odd_even_sort_orders", "orders", "o_totalprice", baselines.odd_even_all, narrow=True)
plain_rank("radix_sort_partkey", "lineitem", "l_partkey", lambda d, s, l: networks.radix_sort(sorted_run(d, s, l)))
plain_rank("column_sort_events", "events", "value", lambda d, s, l: networks.column_sort(sorted_run(d, s, l), 4))


def in_place_rank(name: str, table: str, keys: tuple, sort: Callable[[DataFrame, SortSpec], SortResult]) -> None:
    """A query over the table's own partitions, spread over files first: keys that are unique have one rank whatever the lanes."""
    spec = SortSpec.of(*keys)

    def run(spark, sf_dir):
        spread = stage(read(spark, sf_dir, table, list(IDS[table])).repartition(6), "spread")
        return sort(spread, spec).with_rank().select(*IDS[table], "rank")

    ids = ", ".join(IDS[table])
    QUERIES[name], ORACLE_SQL[name] = run, f"SELECT {ids}, row_number() OVER (ORDER BY {spec.sql_order()}, {ids}) AS rank FROM {table}"


in_place_rank("inplace_regular_sort", "events", ("event_id % 97", "event_id"), lambda d, s: regular_sort(d, s, Lanes(P, layout="inplace")))
in_place_rank("inplace_random_sort", "events", ("event_id % 97", Key("event_id", False)), lambda d, s: presorted_random_sort(d, s, Lanes(P, layout="inplace")))
in_place_rank("inplace_iterated_sort", "events", ("event_id % 97", "event_id"), lambda d, s: iterated_sort(d, s, Lanes(16, layout="inplace"), 4, 2))
in_place_rank("advised_sort", "events", ("event_id % 97", "event_id"), lambda d, s: balanced_sort(d, s, 8))


def step(name: str, table: str, key: str, run_: Callable, sql_tail: str, random: bool = False, spacing: str = "even", s: int = R * P) -> None:
    spec = SortSpec.of(key)

    def run(spark, sf_dir):
        return run_(sorted_run(read(spark, sf_dir, table), spec, Lanes(P, IDS[table])))

    sample = oracle.random_sample(s, 42) if random else oracle.regular_sample(s, P, spacing)
    QUERIES[name], ORACLE_SQL[name] = run, oracle.runs(source(table), spec, P) + sample + sql_tail


_REAL = " SELECT coalesce(run.k0, -1) AS k0, smp.lane, smp.pos, smp.j, smp.pad FROM smp LEFT JOIN run ON run.lane = smp.lane AND run.pos = smp.pos"
_cols = lambda d: d.select(F.coalesce("k0", F.lit(-1)).alias("k0"), F.col("lane").cast("int").alias("lane"), "pos", F.col("j").cast("long").alias("j"), F.col("pad").cast("int").alias("pad"))
step("regular_sample", "lineitem", "l_partkey", lambda r: _cols(sampling.sample_regular(r, R * P)), _REAL)
step("regular_sample_padded", "lineitem", "l_partkey", lambda r: _cols(sampling.sample_regular(r, R * P, "padded")), _REAL, spacing="padded")
step("random_sample_exact", "lineitem", "l_partkey", lambda r: _cols(sampling.sample_random(r, 504)), _REAL, random=True, s=504)
QUERIES["random_sample_quotas"] = lambda spark, sf_dir: _cols(sampling.sample_random(sorted_run(read(spark, sf_dir, "lineitem"), SortSpec.of("l_partkey"), Lanes(P, IDS["lineitem"])), 504, "two_step"))
ORACLE_SQL["random_sample_quotas"] = oracle.runs(source("lineitem"), SortSpec.of("l_partkey"), P) + oracle.two_step_sample(504, P, 42) + _REAL

_RANKED = oracle.fences(P, R * P) + " SELECT run.k0, ranked.lane, ranked.pos, ranked.rk AS rank FROM ranked JOIN run ON run.lane = ranked.lane AND run.pos = ranked.pos"
for _how in ("driver", "spark", "bitonic", "odd_even", "recursive"):
    step(
        f"sample_sorted_{_how}", "lineitem", "l_partkey",
        lambda r, how=_how: sort_sample(sampling.sample_regular(r, R * P), r, how, R * P).select("k0", F.col("lane").cast("int").alias("lane"), "pos", F.col("rank").cast("long").alias("rank")), _RANKED,
    )

_FENCES = " SELECT fence.i AS i, run.k0, fence.lane, fence.pos FROM fence JOIN run ON run.lane = fence.lane AND run.pos = fence.pos"


def _fence_rows(table: str, key: str, sort: Callable):
    def run(spark, sf_dir):
        res = sort(read(spark, sf_dir, table), SortSpec.of(key))
        return res.fences.to_df(spark, res.split).select(F.col("rank").cast("long").alias("i"), "k0", "lane", "pos")

    return run


for _n, _key in (("partkey", "l_partkey"), ("returnflag", "l_returnflag")):
    QUERIES[f"fences_regular_{_n}"] = _fence_rows("lineitem", _key, lambda d, s: regular_sort(d, s, Lanes(P, IDS["lineitem"]), r=R))
    ORACLE_SQL[f"fences_regular_{_n}"] = oracle.runs(source("lineitem"), SortSpec.of(_key), P) + oracle.regular_sample(R * P, P) + oracle.fences(P, R * P) + _FENCES
    QUERIES[f"fences_random_{_n}"] = _fence_rows("lineitem", _key, _laid(presorted_random_sort, "lineitem"))
    ORACLE_SQL[f"fences_random_{_n}"] = oracle.runs(source("lineitem"), SortSpec.of(_key), P) + oracle.random_sample(oracle.random_size("lineitem"), 42) + oracle.fences(P, oracle.random_size("lineitem")) + _FENCES

_flag = SortSpec.of("l_returnflag")
for _how in ("tree", "cuts", "merge", "search"):

    def _split(spark, sf_dir, how=_how):
        res = regular_sort(read(spark, sf_dir, "lineitem"), _flag, Lanes(P, IDS["lineitem"]), r=R)
        rows = with_bucket(res.run.df.select(*IDS["lineitem"], "k0", "lane", "pos"), res.fences, how)
        return rows.select(*IDS["lineitem"], F.col("lane").cast("int").alias("lane"), "pos", F.col("bucket").cast("int").alias("bucket"))

    QUERIES[f"split_{_how}"] = _split
    ORACLE_SQL[f"split_{_how}"] = regular_sql("lineitem", _flag, tail=f" SELECT {', '.join(IDS['lineitem'])}, lane, pos, bucket FROM b")

_part = SortSpec.of("l_partkey")


def _result(spark, sf_dir) -> SortResult:
    return regular_sort(read(spark, sf_dir, "lineitem"), _part, Lanes(P, IDS["lineitem"]), r=R)


_CELLS = f", cell AS (SELECT g.bucket, h.lane, count(b.lane) AS cnt FROM (SELECT CAST(unnest(range(0, {P})) AS INTEGER) AS bucket) g CROSS JOIN (SELECT CAST(unnest(range(0, {P})) AS INTEGER) AS lane) h LEFT JOIN b ON b.bucket = g.bucket AND b.lane = h.lane GROUP BY ALL)"
_START = " SELECT bucket, lane, CAST(coalesce(sum(cnt) OVER (PARTITION BY bucket ORDER BY lane ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start FROM cell"
_int = lambda d: d.select(F.col("bucket").cast("int").alias("bucket"), F.col("lane").cast("int").alias("lane"), *[c for c in d.columns if c not in ("bucket", "lane")])
QUERIES["count_matrix"] = lambda spark, sf_dir: _int(prefix.dense(count_matrix(_result(spark, sf_dir).split), P))
ORACLE_SQL["count_matrix"] = regular_sql("lineitem", _part, tail=_CELLS + " SELECT * FROM cell")
for _n, _f in (("route_offsets", lambda c: prefix.window_offsets(prefix.dense(c, P))), ("prefix_tree", lambda c: prefix.tree_offsets(c, P, 3)), ("prefix_doubling", lambda c: prefix.doubling_offsets(c, P))):
    QUERIES[_n] = lambda spark, sf_dir, f=_f: _int(f(_result(spark, sf_dir).counts))
    ORACLE_SQL[_n] = regular_sql("lineitem", _part, tail=_CELLS + _START)


def _routed_blocks(spark, sf_dir):
    """What each bucket's partition got from each lane: one contiguous block of its run."""
    rows = _result(spark, sf_dir).routed.withColumn("at", F.spark_partition_id())
    return _int(rows.groupBy("bucket", "lane").agg(F.min("pos").alias("first_pos"), F.max("pos").alias("last_pos"), F.count("*").alias("cnt"), F.count_distinct("at").alias("partitions")))


QUERIES["routed_blocks"] = _routed_blocks
ORACLE_SQL["routed_blocks"] = regular_sql("lineitem", _part, tail=" SELECT bucket, lane, min(pos) AS first_pos, max(pos) AS last_pos, count(*) AS cnt, CAST(1 AS BIGINT) AS partitions FROM b GROUP BY bucket, lane")


