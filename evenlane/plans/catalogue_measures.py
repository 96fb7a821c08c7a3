"""Queries of bucket sizes, bounds, communication, inputs and timed workloads."""

from __future__ import annotations

import math
import time
import warnings
from collections.abc import Callable

from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec
from evenlane.operators import baselines, measure, sampling
from evenlane.operators.layout import Lanes, ordinals, sorted_run
from evenlane.operators.sorts import SortResult, classic_random_sort, iterated_sort, local_sort, presorted_random_sort, random_fences, regular_sort
from evenlane.operators.split import with_bucket
from evenlane.plans import bounds, calibrate, oracle
from evenlane.plans.catalogue_sorts import P, R, random_sql, regular_sql, source
from evenlane.plans.model import theory
from evenlane.sources.inputs import KINDS, synthetic, synthetic_sql, worst_segment
from evenlane.sources.tables import IDS, read
from evenlane.staging import stage

QUERIES: dict[str, Callable] = {}
ORACLE_SQL: dict[str, str] = {}
N_LINEITEM = 60_000  # rows of lineitem at the correctness scale; other scales have no SQL to match

FOUR = (("partkey", "l_partkey"), ("price", "l_extendedprice"), ("returnflag", "l_returnflag"), ("constant", "1"))


def sizes_query(name: str, sort: Callable[..., SortResult], sql_of: Callable[[SortSpec], str]) -> None:
    """Bucket sizes over the four keys of lineitem."""

    def run(spark, sf_dir):
        rows = []
        for label, key in FOUR:
            res = sort(read(spark, sf_dir, "lineitem"), SortSpec.of(key))
            rows += [(label, i, n) for i, n in enumerate(res.bucket_sizes())]
        return spark.createDataFrame(rows, "key_name string, bucket int, size long")

    QUERIES[name] = run
    ORACLE_SQL[name] = " UNION ALL ".join(f"SELECT '{label}' AS key_name, * FROM ({sql_of(SortSpec.of(key))})" for label, key in FOUR)


_ids = IDS["lineitem"]
for _r in (1, 2, 4, 8):
    sizes_query(f"bucket_sizes_r{_r}", lambda d, s, r=_r: regular_sort(d, s, Lanes(P, _ids), r=r), lambda s, r=_r: regular_sql("lineitem", s, r=r, tail=oracle.sizes(P)))
sizes_query("bucket_sizes_regular", lambda d, s: regular_sort(d, s, Lanes(P, _ids), r=R), lambda s: regular_sql("lineitem", s, tail=oracle.sizes(P)))
sizes_query("bucket_sizes_padded", lambda d, s: regular_sort(d, s, Lanes(P, _ids), r=R, spacing="padded"), lambda s: regular_sql("lineitem", s, spacing="padded", tail=oracle.sizes(P)))
sizes_query("bucket_sizes_deal", lambda d, s: regular_sort(d, s, Lanes(P, _ids, "deal"), r=R), lambda s: regular_sql("lineitem", s, layout="deal", tail=oracle.sizes(P)))
sizes_query("bucket_sizes_tagless", lambda d, s: regular_sort(d, s, Lanes(P, _ids), r=R, dup=False), lambda s: regular_sql("lineitem", s, tagged=False, tail=oracle.sizes(P)))
sizes_query("bucket_sizes_tag_all", lambda d, s: baselines.tag_all(d, s, Lanes(P, _ids), R), lambda s: regular_sql("lineitem", s, tail=oracle.sizes(P)))
sizes_query("bucket_sizes_plain_regular", lambda d, s: baselines.plain_regular(d, s, Lanes(P, _ids)), lambda s: regular_sql("lineitem", s, r=1, tagged=False, tail=oracle.sizes(P)))
sizes_query("bucket_sizes_random", lambda d, s: presorted_random_sort(d, s, Lanes(P, _ids)), lambda s: random_sql("lineitem", s, tail=oracle.sizes(P)))
sizes_query("bucket_sizes_random_tagless", lambda d, s: presorted_random_sort(d, s, Lanes(P, _ids), dup=False), lambda s: random_sql("lineitem", s, tagged=False, tail=oracle.sizes(P)))
sizes_query("bucket_sizes_classic", lambda d, s: classic_random_sort(d, s, Lanes(P, _ids)), lambda s: random_sql("lineitem", s, tail=oracle.sizes(P), unsorted=True))

_price = SortSpec.of("o_totalprice")


def _exchanges_sql(rows: list[tuple[str, int]]) -> str:
    return " UNION ALL ".join(f"SELECT '{m}' AS method, CAST({n} AS INTEGER) AS rounds, true AS sorted, count(*) AS n FROM orders" for m, n in rows)


_MOVING = {
    "regular": (lambda d: regular_sort(d, _price, Lanes(P, layout="inplace")), 1), "two_round_regular": (lambda d: baselines.two_round_regular(d, _price, Lanes(P, layout="inplace")), 2),
    "two_round_random": (lambda d: baselines.two_round_random(d, _price, Lanes(P, layout="inplace")), 2), "iterated 2^3": (lambda d: iterated_sort(d, _price, Lanes(8, layout="inplace"), 2, 3), 3),
    "binary rounds": (lambda d: baselines.binary_rounds(d, _price, Lanes(8, layout="inplace")), 3), "4-way rounds": (lambda d: baselines.kway_rounds(d, _price, Lanes(16, layout="inplace"), 4), 2),
    "tag_all": (lambda d: baselines.tag_all(d, _price, Lanes(P, layout="inplace")), 1),
}


def _rounds(spark, sf_dir):
    """Exchanges of all rows that each method's plans hold, whether its result is in order, and its rows."""
    orders, rows = read(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]), []
    for name, (sort, _) in _MOVING.items():
        res = sort(orders)
        rows.append((name, res.rounds, measure.is_sorted(res), res.run.n))
    return spark.createDataFrame(rows, "method string, rounds int, sorted boolean, n long")


QUERIES["rounds_by_method"] = _rounds
ORACLE_SQL["rounds_by_method"] = _exchanges_sql([(m, n) for m, (_, n) in _MOVING.items()])
_most = lambda label, value, sql: f"SELECT {label} AS {value}, max(size) AS n_max, round(max(size) * {P} / sum(size) - 1, 6) AS imbalance FROM ({sql})"


def _imbalance_by_ratio(spark, sf_dir):
    rows = []
    for r in (1, 2, 4, 8):
        s = regular_sort(read(spark, sf_dir, "orders"), _price, Lanes(P, IDS["orders"]), r=r).bucket_sizes()
        rows.append((r, max(s), round(measure.imbalance(s), 6)))
    return spark.createDataFrame(rows, "r int, n_max long, imbalance double")


QUERIES["imbalance_by_ratio"] = _imbalance_by_ratio
ORACLE_SQL["imbalance_by_ratio"] = " UNION ALL ".join(_most(f"CAST({r} AS INTEGER)", "r", regular_sql("orders", _price, r=r, tail=oracle.sizes(P))) for r in (1, 2, 4, 8))


def _imbalance_equal_samples(spark, sf_dir):
    rows = []
    for name, res in (("regular", lambda d: regular_sort(d, _price, Lanes(P, IDS["orders"]), r=R)), ("random", lambda d: presorted_random_sort(d, _price, Lanes(P, IDS["orders"]), s=R * P))):
        s = res(read(spark, sf_dir, "orders")).bucket_sizes()
        rows.append((name, max(s), round(measure.imbalance(s), 6)))
    return spark.createDataFrame(rows, "method string, n_max long, imbalance double")


QUERIES["imbalance_equal_samples"] = _imbalance_equal_samples
ORACLE_SQL["imbalance_equal_samples"] = _most("'regular'", "method", regular_sql("orders", _price, tail=oracle.sizes(P))) + " UNION ALL " + _most("'random'", "method", random_sql("orders", _price, R * P, tail=oracle.sizes(P)))

_SIZES = (12, 96, 768)  # samples a lane
_SEEDS = range(1, 21)


def _fullest(run, s: int, seed: int) -> int:
    fences = random_fences(run, s, "exact", seed)
    return with_bucket(run.df.select("k0", "lane", "pos"), fences).groupBy("bucket").count().agg(F.max("count")).first()[0]


def _imbalance_by_samples(spark, sf_dir):
    """The fullest bucket over twenty seeds, by samples a lane."""
    run = sorted_run(read(spark, sf_dir, "orders"), _price, Lanes(P, IDS["orders"]))
    rows = []
    for s in _SIZES:
        big = [_fullest(run, s, seed) for seed in _SEEDS]
        rows.append((s, len(big), min(big), max(big), round(sum(big) * P / (len(big) * run.n) - 1, 6)))
    return spark.createDataFrame(rows, "s int, seeds int, least long, most long, mean_imbalance double")


def fullest_sql(table: str, spec: SortSpec, sizes: list[int], seeds: range) -> str:
    """CTEs up to big: (s, seed, n, size), size the fullest bucket; a bucket is what lies between the global ranks of its fences."""
    return oracle.runs(source(table), spec, P) + f""", g AS (SELECT lane, pos, n, row_number() OVER (ORDER BY kr, lane, pos) AS place FROM run),
d AS (SELECT seed, place, n, row_number() OVER (PARTITION BY seed, lane ORDER BY md5(seed || '|' || lane || '|' || pos), pos) AS j FROM g, (SELECT unnest(range({seeds.start}, {seeds.stop})) AS seed)),
k AS (SELECT s, seed, n, place, row_number() OVER (PARTITION BY s, seed ORDER BY place) AS rk FROM d, (SELECT unnest({sizes}) AS s) WHERE j <= s),
f AS (SELECT s, seed, n, place FROM k WHERE rk % s = 0 AND rk < {P} * s UNION ALL SELECT DISTINCT s, seed, n, n FROM k),
big AS (SELECT s, seed, n, max(size) AS size FROM (SELECT s, seed, n, place - coalesce(lag(place) OVER (PARTITION BY s, seed ORDER BY place), 0) AS size FROM f) GROUP BY s, seed, n)"""


QUERIES["imbalance_by_samples"] = _imbalance_by_samples
ORACLE_SQL["imbalance_by_samples"] = fullest_sql("orders", _price, list(_SIZES), _SEEDS) + f" SELECT CAST(s AS INTEGER) AS s, CAST(count(*) AS INTEGER) AS seeds, min(size) AS least, max(size) AS most, round(sum(size) * {P} / (count(*) * max(n)) - 1, 6) AS mean_imbalance FROM big GROUP BY s"

_part = SortSpec.of("l_partkey")
QUERIES["h_relation"] = lambda spark, sf_dir: measure.h_relation(regular_sort(read(spark, sf_dir, "lineitem"), _part, Lanes(P, _ids), r=R))
ORACLE_SQL["h_relation"] = regular_sql(
    "lineitem", _part,
    tail=f" SELECT CAST(g.lane AS INTEGER) AS lane, (SELECT count(*) FROM b WHERE b.lane = g.lane AND b.bucket <> g.lane) AS sent, (SELECT count(*) FROM b WHERE b.bucket = g.lane AND b.lane <> g.lane) AS received FROM (SELECT unnest(range(0, {P})) AS lane) g",
)


def _sample_share(spark, sf_dir):
    n = read(spark, sf_dir, "lineitem").count()
    rows = [(n, p, R, *measure.sample_share(n, p, R)) for p in (4, 8, 16, 32)]
    return spark.createDataFrame([(*x[:4], round(x[4], 8)) for x in rows], "n long, p int, r int, samples long, share double")


QUERIES["sample_share"] = _sample_share
ORACLE_SQL["sample_share"] = f"SELECT n, CAST(p AS INTEGER) AS p, CAST({R} AS INTEGER) AS r, CAST(p * p * {R} AS BIGINT) AS samples, round(p * p * {R} / n, 8) AS share FROM (SELECT count(*) AS n FROM lineitem), (SELECT unnest([4, 8, 16, 32]) AS p)"


def _tag_overhead(spark, sf_dir):
    """Words that the plans move: with tags on samples alone, and with an address on every key."""
    rows = []
    for p in (4, 8, 16, 32):
        res = regular_sort(read(spark, sf_dir, "lineitem", list(_ids)), SortSpec.of("l_partkey"), Lanes(p, _ids), r=R)
        every = baselines.tag_all(read(spark, sf_dir, "lineitem", list(_ids)), SortSpec.of("l_partkey"), Lanes(p, _ids), R)
        rows.append((p, measure.tag_words(res, sampling.sample_regular(res.run, R * p).count()), measure.tag_words(every, 0)))
    return spark.createDataFrame(rows, "p int, words_sample_tags long, words_all_tags long")


QUERIES["tag_overhead"] = _tag_overhead
ORACLE_SQL["tag_overhead"] = f"SELECT CAST(p AS INTEGER) AS p, CAST(n + 2 * p * p * {R} AS BIGINT) AS words_sample_tags, 2 * n AS words_all_tags FROM (SELECT count(*) AS n FROM lineitem), (SELECT unnest([4, 8, 16, 32]) AS p)"


# ----- synthetic inputs


def _synthetic(spark, sf_dir, kind: str):
    rows, n = ordinals(read(spark, sf_dir, "lineitem", list(_ids)), _ids)
    return synthetic(rows, n, kind, P)


for _kind in KINDS:
    QUERIES[f"input_{_kind}"] = lambda spark, sf_dir, k=_kind: _synthetic(spark, sf_dir, k)
    ORACLE_SQL[f"input_{_kind}"] = synthetic_sql("lineitem", N_LINEITEM, _kind, P)

    _src = oracle.Source(f"(SELECT ord AS id, key FROM ({synthetic_sql('lineitem', N_LINEITEM, _kind, P)}))", ("id",))
    _key = SortSpec.of("key")

    def _sort_input(spark, sf_dir, k=_kind):
        df = _synthetic(spark, sf_dir, k).select(F.col("ord").alias("id"), "key")
        res = regular_sort(df, SortSpec.of("key"), Lanes(P, ("id",)), r=R)
        return res.with_rank().select("id", "k0", F.col("lane").cast("int").alias("lane"), "pos", "bucket", "rank")

    QUERIES[f"sort_input_{_kind}"] = _sort_input
    _head = oracle.runs(_src, _key, P) + oracle.regular_sample(R * P, P) + oracle.fences(P, R * P) + oracle.buckets()
    ORACLE_SQL[f"sort_input_{_kind}"] = _head + oracle.ranks(_src, _key)

    def _sizes_input(spark, sf_dir, k=_kind):
        rows = []
        for name, f in (("regular", lambda d: regular_sort(d, SortSpec.of("key"), Lanes(P, ("id",)), r=R)), ("random", lambda d: presorted_random_sort(d, SortSpec.of("key"), Lanes(P, ("id",))))):
            res = f(_synthetic(spark, sf_dir, k).select(F.col("ord").alias("id"), "key"))
            rows += [(name, i, x) for i, x in enumerate(res.bucket_sizes())]
        return spark.createDataFrame(rows, "method string, bucket int, size long")

    QUERIES[f"sizes_input_{_kind}"] = _sizes_input
    _s = oracle.random_size(f"({_src.sql})")
    _rand = oracle.runs(_src, _key, P) + oracle.random_sample(_s, 42) + oracle.fences(P, _s) + oracle.buckets()
    ORACLE_SQL[f"sizes_input_{_kind}"] = f"SELECT 'regular' AS method, * FROM ({_head + oracle.sizes(P)}) UNION ALL SELECT 'random' AS method, * FROM ({_rand + oracle.sizes(P)})"


def _bound_check(spark, sf_dir):
    rows = []
    for k in KINDS:
        res = regular_sort(_synthetic(spark, sf_dir, k).select(F.col("ord").alias("id"), "key"), SortSpec.of("key"), Lanes(P, ("id",)), r=R)
        n, big = res.run.n, max(res.bucket_sizes())
        exact = bounds.regular(n, P, R)
        rows.append((k, big, int(exact), bounds.regular(n, P, R, "safe"), bounds.regular(n, P, R, "printed"), big <= exact))
    return spark.createDataFrame(rows, "input string, n_max long, exact long, safe double, printed double, ok boolean")


QUERIES["bound_regular_check"] = _bound_check
_checks = []
for _kind in KINDS:
    _n = R * P * P * worst_segment(N_LINEITEM, P, R) if _kind == "worst" else N_LINEITEM
    _src = oracle.Source(f"(SELECT ord AS id, key FROM ({synthetic_sql('lineitem', N_LINEITEM, _kind, P)}))", ("id",))
    _body = oracle.runs(_src, SortSpec.of("key"), P) + oracle.regular_sample(R * P, P) + oracle.fences(P, R * P) + oracle.buckets() + oracle.sizes(P)
    _checks.append(
        f"SELECT '{_kind}' AS input, max(size) AS n_max, CAST({int(bounds.regular(_n, P, R))} AS BIGINT) AS exact, CAST({bounds.regular(_n, P, R, 'safe')} AS DOUBLE) AS safe, CAST({bounds.regular(_n, P, R, 'printed')} AS DOUBLE) AS printed, max(size) <= {int(bounds.regular(_n, P, R))} AS ok FROM ({_body})"
    )
ORACLE_SQL["bound_regular_check"] = " UNION ALL ".join(_checks)


# ----- timed workloads: rows only, since seconds have no SQL

VARIANTS = {
    "regular+radix": (regular_sort, "radix"), "regular+cmp": (regular_sort, "cmp"),
    "presorted_random+radix": (presorted_random_sort, "radix"), "presorted_random+cmp": (presorted_random_sort, "cmp"),
}
_GRID = ("uniform", "gauss", "bucket", "group", "stagger", "dupes", "worst")
_KEY = SortSpec.of("key")


def timed(res_of: Callable[[], SortResult]) -> tuple[float, SortResult]:
    """Seconds of the second of two whole sorts: sample, route and merge to the no-op sink."""
    res_of().by_keys.write.format("noop").mode("overwrite").save()
    t = time.perf_counter()
    res = res_of()
    res.by_keys.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t, res


def variant(name: str, data, spec: SortSpec, p: int) -> tuple[float, SortResult]:
    sort, local = VARIANTS[name]
    with local_sort(data.sparkSession, local):
        return timed(lambda: sort(data, spec, Lanes(p, layout="inplace"), local=local))


def one_lane(data) -> dict[str, float]:
    """Seconds of one lane's sort of the same rows in memory, the second of two, by local sort.

    With a single lane no method samples or routes, so that all variants share it.
    """
    lane, seconds = data.coalesce(1).persist(), {}
    lane.count()
    for local in dict.fromkeys(local for _, local in VARIANTS.values()):
        with local_sort(data.sparkSession, local):
            for _ in range(2):
                t = time.perf_counter()
                _KEY.add(lane).sortWithinPartitions(*_KEY.order()).write.format("noop").mode("overwrite").save()
                seconds[local] = time.perf_counter() - t
    lane.unpersist()
    return seconds


def _keys_of(spark, n: int, kind: str, p: int):
    """n synthetic keys, int as the published ones, in p partitions in memory."""
    d = synthetic(spark.range(1, n + 1, 1, p).withColumnRenamed("id", "ord"), n, kind, max(3, p) if kind == "worst" else p)
    d = stage(d.select(F.col("key").cast("int").alias("key")), "keys").persist()
    d.count()
    return d


def _grid(method, kinds=_GRID, ps=(P,), shares=(4, 2, 1), efficiency=False):
    """Seconds over inputs, sizes (shares of lineitem's rows) and lanes; efficiency against one lane's sort."""

    def run(spark, sf_dir):
        rows, whole = [], read(spark, sf_dir, "lineitem").count()
        for kind in kinds:
            for share in shares:
                n = max(1, whole // share)
                for p in ps:
                    data = _keys_of(spark, n, kind, p)
                    alone = one_lane(data) if efficiency else {}
                    for name in VARIANTS:
                        if method and not name.startswith(method):
                            continue
                        sec, res = variant(name, data, _KEY, p)
                        one = alone.get(VARIANTS[name][1], float("nan"))
                        s = res.bucket_sizes()
                        rows.append((kind, n, p, name, sec, max(s), measure.imbalance(s), calibrate.efficiency(one, sec, p)))
                    data.unpersist()
        return spark.createDataFrame(rows, "input string, n long, p int, variant string, sec double, n_max long, imbalance double, efficiency double")

    return run


QUERIES["bench_random_grid"] = _grid("presorted_random")
QUERIES["bench_regular_grid"] = _grid("regular")
QUERIES["bench_scalability"] = _grid(None, ("uniform", "worst"), (4, 8, 16), (1,), True)
QUERIES["bench_scalability_uniform"] = _grid(None, ("uniform",), (4, 8, 16), (4, 2, 1))


def _phases(method: str, local: str):
    def run(spark, sf_dir):
        rows, n = [], read(spark, sf_dir, "lineitem").count()
        for share in (2, 1):
            for p in (4, 8, 16):
                data = _keys_of(spark, n // share, "uniform", p)
                _, phases = calibrate.profile(method, data, _KEY, p, local)
                data.unpersist()
                total = sum(phases.values())
                rows += [(n // share, p, k, v, 100 * v / total, 100 * (phases["local sort"] + phases["merging"]) / total) for k, v in phases.items()]
        return spark.createDataFrame(rows, "n long, p int, phase string, sec double, pct double, sequential_pct double")

    return run


for _name, (_, _local) in VARIANTS.items():
    QUERIES[f"phase_profile_{_name.replace('+', '_')}"] = _phases(_name.split("+")[0], _local)


def _phases_beside_rival(spark, sf_dir):
    """Phases of the one-round method on uniform keys beside those of the two-round rival on the worst input."""
    rows, n = [], read(spark, sf_dir, "lineitem").count()
    for p in (4, 8, 16):
        for method, kind in (("regular", "uniform"), ("two_round_regular", "worst")):
            data = _keys_of(spark, n, kind, p)
            _, phases = calibrate.profile(method, data, _KEY, p)
            data.unpersist()
            total = sum(phases.values())
            rows += [(method, kind, p, k, v, 100 * v / total) for k, v in phases.items()]
    return spark.createDataFrame(rows, "method string, input string, p int, phase string, sec double, pct double")


QUERIES["phase_profile_rival"] = _phases_beside_rival


def _rivals(spark, sf_dir):
    rows, n = [], read(spark, sf_dir, "lineitem").count()
    for kind in ("uniform", "worst"):
        for size in (n, max(1, n * 1_000_000 // 2**20)):  # the two sizes of the direct comparison, in proportion
            data, lanes = _keys_of(spark, size, kind, P), Lanes(P, layout="inplace")
            ways = {
                "presorted_random": lambda: presorted_random_sort(data, _KEY, lanes), "regular": lambda: regular_sort(data, _KEY, lanes), "classic_random": lambda: classic_random_sort(data, _KEY, lanes),
                "plain_regular": lambda: baselines.plain_regular(data, _KEY, lanes), "two_round_regular": lambda: baselines.two_round_regular(data, _KEY, lanes), "two_round_random": lambda: baselines.two_round_random(data, _KEY, lanes),
                "tag_all": lambda: baselines.tag_all(data, _KEY, lanes),
            }
            for name, f in ways.items():
                sec, res = timed(f)
                rows.append((name, kind, size, P, res.rounds, sec, max(res.bucket_sizes())))
            t = time.perf_counter()
            data.orderBy("key").write.format("noop").mode("overwrite").save()
            rows.append(("range_exchange", kind, size, P, 1, time.perf_counter() - t, 0))
            cuts = baselines.sketch_fences(data, "key", P)
            sizes = data.groupBy(baselines.sketch_bucket("key", cuts).alias("b")).count().agg(F.max("count")).first()[0]
            rows.append(("sketch_fences", kind, size, P, 1, float("nan"), sizes))
            data.unpersist()
    return spark.createDataFrame(rows, "algorithm string, input string, n long, p int, rounds int, sec double, n_max long")


QUERIES["bench_rivals"] = _rivals


def _dup_overhead(spark, sf_dir):
    rows = []
    for label, key in FOUR:
        data = stage(read(spark, sf_dir, "lineitem", sorted({"l_orderkey", key} - {"1"})).repartition(P), "dups").persist()
        data.count()
        for name, sort in (("regular", regular_sort), ("presorted_random", presorted_random_sort)):
            on, a = timed(lambda: sort(data, SortSpec.of(key), Lanes(P, layout="inplace")))
            off, b = timed(lambda: sort(data, SortSpec.of(key), Lanes(P, layout="inplace"), dup=False))
            rows.append((label, name, on, off, measure.dup_overhead(on, off), max(a.bucket_sizes()), max(b.bucket_sizes())))
        data.unpersist()
    return spark.createDataFrame(rows, "key_name string, method string, sec_on double, sec_off double, overhead double, n_max_on long, n_max_off long")


QUERIES["bench_dup_overhead"] = _dup_overhead


def _predicted(spark, sf_dir):
    m = calibrate.measure(spark, P)
    n = read(spark, sf_dir, "lineitem").count()
    data = _keys_of(spark, n, "uniform", P)
    rows = []
    for name in ("regular+radix", "presorted_random+radix"):
        sec, _ = variant(name, data, _KEY, P)
        one, _ = variant(name, data.coalesce(1), _KEY, 1)
        rows.append((name.split("+")[0], n, P, m.l_us, m.g_us, m.rate, theory(name.split("+")[0], n, m)["efficiency"], calibrate.efficiency(one, sec, P)))
    data.unpersist()
    return spark.createDataFrame(rows, "method string, n long, p int, l_us double, g_us double, rate double, predicted double, observed double")


QUERIES["predicted_vs_observed"] = _predicted


def _observed_g(spark, sf_dir):
    rows, n = [], read(spark, sf_dir, "lineitem").count()
    for p in (4, 8, 16):
        data = _keys_of(spark, n, "uniform", p)
        res, phases = calibrate.profile("regular", data, _KEY, p)
        rows.append((p, phases["routing"], calibrate.observed_g(phases["routing"], res.bucket_sizes())))
        data.unpersist()
    return spark.createDataFrame(rows, "p int, routing_sec double, g_us double")


QUERIES["observed_g"] = _observed_g


def _calibrate(spark, sf_dir):
    """L, g and the rate from the rows of lineitem."""
    m = calibrate.measure(spark, P, keys=read(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber"]))
    return spark.createDataFrame([(m.p, m.l_us, m.g_us, m.rate, m.g_ops)], "p int, l_us double, g_us double, rate double, g_ops double")


QUERIES["calibrate"] = _calibrate


def _small_inputs(spark, sf_dir):
    """Tiny inputs, and a middling one, over many lanes: networks against sampling."""
    rows = []
    for table, key, ids in (("region", "r_regionkey", ("r_regionkey",)), ("nation", "n_nationkey", ("n_nationkey",)), ("benchmark", "item_id", ("item_id",)), ("orders", "o_totalprice", ("o_orderkey",))):
        for p in (4, 8, 16):
            df, spec, lanes = read(spark, sf_dir, table), SortSpec.of(key), Lanes(p, ids)
            with warnings.catch_warnings():
                warnings.simplefilter("ignore")
                sec, _ = timed(lambda: regular_sort(df, spec, lanes, r=1))
            rows.append((table, p, "regular", sec, 1))
            t = time.perf_counter()
            baselines.bitonic_all(df, spec, lanes).write.format("noop").mode("overwrite").save()
            rows.append((table, p, "bitonic", time.perf_counter() - t, int(math.log2(p) * (math.log2(p) + 1) / 2)))
    return spark.createDataFrame(rows, "input string, p int, method string, sec double, rounds int")


QUERIES["bench_small_inputs"] = _small_inputs

N_ORDERS = 15_000  # rows of orders at the correctness scale
_EPS, _RHO = 0.5, 1.0


def _claim_rate(spark, sf_dir):
    """How often over twenty seeds the fullest bucket passes (1 + eps) n / p with the claim's sample size."""
    run = sorted_run(read(spark, sf_dir, "orders"), _price, Lanes(P, IDS["orders"]))
    s = sampling.claim_size(run.n, P, _EPS, _RHO)
    over = sum(_fullest(run, s, seed) > (1 + _EPS) * (run.n - P + 1) / P for seed in _SEEDS)
    return spark.createDataFrame([(s, _EPS, _RHO, len(_SEEDS), over, round(bounds.claim_probability(run.n, _RHO), 9))], "s int, eps double, rho double, seeds int, violations int, allowed double")


QUERIES["claim_rate"] = _claim_rate
_claim = sampling.claim_size(N_ORDERS, P, _EPS, _RHO)
ORACLE_SQL["claim_rate"] = fullest_sql("orders", _price, [_claim], _SEEDS) + f" SELECT CAST(s AS INTEGER) AS s, CAST({_EPS} AS DOUBLE) AS eps, CAST({_RHO} AS DOUBLE) AS rho, CAST(count(*) AS INTEGER) AS seeds, CAST(count(*) FILTER (size > (1 + {_EPS}) * (n - {P} + 1) / {P}) AS INTEGER) AS violations, round(1.0 / max(n), 9) AS allowed FROM big GROUP BY s"
