"""Empty, tiny and odd inputs, and the invariants of a result."""

from __future__ import annotations

import time

import pytest
from pyspark.sql import functions as F

from evenlane.functions.spec import Key, SortSpec
from evenlane.operators import baselines, measure
from evenlane.operators import relational as rel
from evenlane.operators.fences import FenceSet
from evenlane.operators.layout import Lanes, by_number
from evenlane.operators.sampling import stride
from evenlane.operators.sorts import balanced_sort, classic_random_sort, exchanges, iterated_sort, presorted_random_sort, regular_sort
from evenlane.operators.split import with_bucket
from evenlane.plans import bounds
from evenlane.plans.advisor import choose
from evenlane.plans.model import MachineModel
from evenlane.staging import steady


def _ranks(res):
    return [(r["k0"], r["id"]) for r in sorted(res.with_rank().collect(), key=lambda r: r["rank"])]


@pytest.mark.parametrize("n", [0, 1, 3, 10])
@pytest.mark.parametrize("sort", [regular_sort, presorted_random_sort, classic_random_sort])
def test_few_rows(spark, n, sort):
    df = spark.range(n).select("id", (F.col("id") % 2).alias("v"))
    res = sort(df, SortSpec.of("v"), Lanes(4, ("id",)))
    assert _ranks(res) == sorted((i % 2, i) for i in range(n))
    assert sum(res.bucket_sizes()) == n


@pytest.mark.parametrize("p", [1, 3, 5, 6])
def test_any_number_of_lanes(spark, p):
    df = spark.range(101).select("id", (F.col("id") * 37 % 101).alias("v"))
    res = regular_sort(df, SortSpec.of("v"), Lanes(p, ("id",)), r=2)
    assert [k for k, _ in _ranks(res)] == list(range(101))
    assert max(res.bucket_sizes()) <= bounds.regular(101, p, 2)


@pytest.mark.parametrize("first", [True, False])
@pytest.mark.parametrize("asc", [True, False])
def test_nulls_and_directions(spark, asc, first):
    df = spark.range(60).select("id", F.when(F.col("id") % 3 > 0, F.col("id") % 7).alias("v"))
    res = regular_sort(df, SortSpec.of(Key("v", asc, first)), Lanes(4, ("id",)), r=2)
    got = [k for k, _ in _ranks(res)]
    kept = sorted((x for x in got if x is not None), reverse=not asc)
    nulls = [None] * 20
    assert got == (nulls + kept if first else kept + nulls)
    assert measure.is_sorted(res) and measure.is_stable(res)


def test_floats(spark):
    rows = [(i, x) for i, x in enumerate([float("nan"), float("inf"), -0.0, 0.0, float("-inf"), 1.5, float("nan"), -2.0])]
    df = spark.createDataFrame(rows, "id long, v double")
    got = [i for _, i in _ranks(regular_sort(df, SortSpec.of("v"), Lanes(3, ("id",)), r=1))]
    assert got == [4, 7, 2, 3, 5, 1, 0, 6]


def test_all_equal_keys_split_evenly(spark):
    df = spark.range(800).select("id", F.lit(1).alias("v"))
    res = regular_sort(df, SortSpec.of("v"), Lanes(8, ("id",)), r=2)
    assert res.bucket_sizes() == [100] * 8
    untagged = regular_sort(df, SortSpec.of("v"), Lanes(8, ("id",)), r=2, dup=False)
    assert max(untagged.bucket_sizes()) == 800


def test_one_bulk_exchange(spark):
    df = spark.range(100).select("id", (F.col("id") % 10).alias("v"))
    res = regular_sort(df, SortSpec.of("v"), Lanes(4, ("id",)), r=2)
    plan = res.df._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange ") == 1


def test_physical_layout_is_a_permutation(spark):
    df = spark.range(1000).select("id", F.xxhash64("id").alias("v"))
    res = regular_sort(df, SortSpec.of("v"), Lanes(5, layout="physical"), r=3)
    assert measure.checksum(res.df, "id", "v") == measure.checksum(df, "id", "v")
    assert measure.is_sorted(res)


def test_iterated_needs_a_power(spark):
    with pytest.raises(ValueError):
        iterated_sort(spark.range(10), SortSpec.of("id"), Lanes(6, ("id",)), 2, 2)


def test_rejected_types(spark):
    with pytest.raises(TypeError):
        regular_sort(spark.range(3).select("id", F.create_map("id", "id").alias("m")), SortSpec.of("m"), Lanes(2, ("id",)))
    with pytest.raises(ValueError):
        Lanes(0, ("id",))


def test_struct_and_many_types(spark):
    df = spark.range(30).select("id", (F.col("id") % 4).cast("decimal(38,10)").alias("d"), F.date_add(F.lit("2020-01-01"), F.col("id").cast("int") % 5).alias("t"), (F.col("id") % 2 == 0).alias("b"), F.md5(F.col("id").cast("string")).cast("binary").alias("x"))
    for key in ("d", "t", "b", "x"):
        res = regular_sort(df, SortSpec.of(key), Lanes(3, ("id",)), r=1)
        want = [r["id"] for r in df.orderBy(key, "id").collect()]
        assert [i for _, i in _ranks(res)] == want


# ----- lanes in place, rounds, and what the plans move


def _spread(spark, n, parts, key):
    return spark.range(0, n, 1, parts).select("id", F.expr(key).alias("v"))


@pytest.mark.parametrize("key", ["xxhash64(id) % 1000", "1", "cast(id % 3 as string)", "if(id % 5 = 0, null, id % 11)", "date_add('2020-01-01', cast(id % 9 as int))"])
@pytest.mark.parametrize("spec", [Key("v"), Key("v", False, False)])
def test_in_place(spark, key, spec):
    df = _spread(spark, 4000, 7, key)
    res = regular_sort(df, SortSpec.of(spec), Lanes(5, layout="inplace"), r=4)
    assert measure.is_sorted(res) and measure.is_stable(res)
    sizes = res.bucket_sizes()
    assert sum(sizes) == res.run.n == 4000 and max(sizes) <= 4000 / 5 * (1 + 1 / 4) + 7 * 29
    assert measure.checksum(res.by_keys, "id", "v") == measure.checksum(df, "id", "v")


def test_in_place_uneven_lanes(spark):
    """Lanes of 1 to 5,000 rows: each sample stands for equally many."""
    df = spark.range(0, 10, 1, 1).union(spark.range(10, 5010, 1, 1)).union(spark.range(5010, 5011, 1, 1)).union(spark.range(5011, 8011, 1, 1)).select("id", F.xxhash64("id").alias("v"))
    for sort in (regular_sort, presorted_random_sort, classic_random_sort):
        sizes = sort(df, SortSpec.of("v"), Lanes(8, layout="inplace")).bucket_sizes()
        assert sum(sizes) == 8011 and max(sizes) < 1.3 * 8011 / 8


def test_in_place_writes_unsteady_inputs_first(spark):
    df = spark.range(1000).repartition(4).withColumn("v", F.col("id") % 10)
    assert not steady(df) and steady(spark.range(10).where("id > 3").withColumn("v", F.lit(1)))
    res = regular_sort(df, SortSpec.of("v"), Lanes(4, layout="inplace"))
    assert steady(res.run.df) and measure.is_sorted(res)


def test_rounds_move_rows(spark):
    """The exchanges in the plans: one, two, or one a round; every round's rows are where the next one reads them."""
    df = _spread(spark, 3000, 6, "xxhash64(id) % 500")
    spec = SortSpec.of("v")
    cases = [
        (regular_sort(df, spec, Lanes(8, layout="inplace")), 1), (iterated_sort(df, spec, Lanes(8, layout="inplace"), 2, 3), 3), (iterated_sort(df, spec, Lanes(9, ("id",)), 3, 2, method="random"), 2),
        (baselines.two_round_regular(df, spec, Lanes(8, layout="inplace")), 2), (baselines.two_round_random(df, spec, Lanes(8, ("id",))), 2), (baselines.binary_rounds(df, spec, Lanes(4, layout="inplace")), 2),
        (baselines.kway_rounds(df, spec, Lanes(16, layout="inplace"), 4), 2),
    ]
    for res, rounds in cases:
        assert res.rounds == rounds and measure.is_sorted(res)
        assert measure.checksum(res.df, "id", "v") == measure.checksum(df, "id", "v")


def test_iterated_with_one_hot_key_and_empty_groups(spark):
    df = _spread(spark, 2000, 4, "if(id % 4 > 0, 7, id)")
    res = iterated_sort(df, SortSpec.of("v"), Lanes(16, layout="inplace"), 4, 2)
    assert measure.is_sorted(res) and max(res.bucket_sizes()) < 3 * 2000 / 16
    assert iterated_sort(df.where("id < 3"), SortSpec.of("v"), Lanes(16, layout="inplace"), 4, 2).with_rank().count() == 3


def test_addresses_on_every_key_double_the_words(spark):
    df = _spread(spark, 1000, 4, "id % 7")
    lanes, spec = Lanes(4, layout="inplace"), SortSpec.of("v")
    plain, every = regular_sort(df, spec, lanes, r=2), baselines.tag_all(df, spec, lanes, 2)
    assert every.bucket_sizes() == plain.bucket_sizes() and every.fences.records[0]["k1"] is not None
    assert measure.tag_words(every, 0) == 2 * 1000 and measure.tag_words(plain, 32) == 1000 + 64


def test_many_lanes_and_fences_are_planned_quickly(spark):
    p, lanes = 2000, 20_000
    records = tuple({"k0": i, "lane": 0, "pos": 0} for i in range(p - 1))
    df = spark.range(0, 5000, 1, 4).select(F.col("id").alias("k0"), F.lit(0).alias("lane"), F.lit(1).cast("long").alias("pos"))
    t = time.perf_counter()
    for spec in (SortSpec.of("k0"), SortSpec.of(Key("k0", False))):
        f = FenceSet(spec, records if spec.keys[0].asc else records[::-1])
        split = with_bucket(df, f).withColumn("base", by_number(list(range(lanes)), F.col("bucket")))
    assert time.perf_counter() - t < 2  # two plans
    got = {r["k0"]: r["bucket"] for r in split.collect()}
    assert got[0] == p - 1 and got[p - 2] == 1 and got[4999] == 0
    assert split._jdf.queryExecution().optimizedPlan().toString().count("1998") < 3
    # the sample stays under a hundredth of the rows, or 200,000
    assert all(n / stride(n, lanes, 6 * p) <= max(n / 100, 200_000) for n in (10, 1000, 10**6, 10**8, 10**12)) and stride(600_000, 8, 48) == 1562


@pytest.mark.parametrize("spec", [SortSpec.of("v"), SortSpec.of(Key("v", False, False), "w")])
def test_split_ways_agree_for_any_order(spark, spec):
    df = _spread(spark, 500, 3, "if(id % 6 = 0, null, id % 5)").withColumn("w", F.col("id") % 3)
    res = regular_sort(df, spec, Lanes(6, ("id",)), r=2)
    want = {r["id"]: r["bucket"] for r in with_bucket(res.run.df, res.fences, "tree").collect()}
    for how in ("search", "merge", "cuts"):
        assert {r["id"]: r["bucket"] for r in with_bucket(res.run.df, res.fences, how).collect()} == want


def test_boundaries_of_ranks(spark):
    """Keys that fill several buckets, begin in one and end in another, or are null."""
    df = _spread(spark, 600, 5, "case when id < 350 then 3 when id < 380 then null else id % 4 end")
    res = regular_sort(df, SortSpec.of("v"), Lanes(7, layout="inplace"))
    keys = sorted((r["v"] is not None, r["v"] or 0) for r in df.collect())
    first, kinds = {}, sorted(set(keys))
    for i, k in enumerate(keys):
        first.setdefault(k, i + 1)
    for kind, want in (("rank", first), ("dense_rank", {k: i + 1 for i, k in enumerate(kinds)})):
        got = {((r["v"] is not None, r["v"] or 0), r[kind]) for r in rel.with_rank(res, kind).collect()}
        assert got == set(want.items())
    assert rel.dedup(res).count() == len(kinds) == rel.sorted_agg(res, n="count(*)").count()
    assert {(r["k0"], r["n"]) for r in rel.sorted_agg(res, n="count(*)").collect()} == {(k[1] if k[0] else None, keys.count(k)) for k in kinds}
    assert exchanges(rel.with_rank(res)) == exchanges(rel.dedup(res)) == 1


def test_asof_across_buckets(spark):
    left = spark.createDataFrame([(i, "hot" if i % 3 else None, i * 10) for i in range(200)], "id long, u string, t long")
    right = spark.createDataFrame([("hot", 15, "a"), ("hot", 900, "b"), (None, 1, "z"), ("cold", 5, "c")], "u string, t long, x string")
    got = {r["id"]: r["m"] for r in rel.asof(left, right, "u", "t", "x", "m", p=6).collect()}
    assert got == {i: (None if i % 3 == 0 or i * 10 < 15 else "a" if i * 10 < 900 else "b") for i in range(200)}


def test_fenced_join_moves_each_side_once(spark):
    df = _spread(spark, 900, 4, "if(id % 3 > 0, 5, id % 40)")
    res = regular_sort(df, SortSpec.of("v"), Lanes(6, layout="inplace"))
    right = spark.range(30).select(F.col("id").alias("key"), (F.col("id") * 2).alias("x")).hint("merge")
    j = rel.fenced_join(res, right, "key")
    assert j.count() == df.where("v < 30").count() and exchanges(j) == 2
    assert rel.fenced_join(res, right, "key", "left_anti").count() == df.where("v >= 30").count()


def test_advice_takes_lanes_into_account(spark):
    df = _spread(spark, 2000, 4, "id % 100")
    res = balanced_sort(df, SortSpec.of("v"), 4)
    assert res.plan["method"] in ("regular", "presorted_random") and measure.is_sorted(res)
    many = choose(MachineModel(128, 762.0, 0.34), 2**36, lanes=2**20, p=2**17)
    assert many.rounds > 1 and many.k**many.rounds >= 2**17
    assert measure.is_sorted(balanced_sort(df, SortSpec.of("v"), 16, rows=300))


def test_buckets_formed_before_the_route(spark):
    """The integer sort stands in the plan before the exchange, and keeps the order of equal keys."""
    df = _spread(spark, 800, 4, "id % 9")
    res = classic_random_sort(df, SortSpec.of("v"), Lanes(4, layout="inplace"), split="integer")
    plan = res.df._jdf.queryExecution().executedPlan().toString()
    assert "Sort [bucket" in plan.split("Exchange")[1] and measure.is_sorted(res) and measure.is_stable(res)


def test_integer_buckets_of_lanes_read_in_pieces(spark):
    """A lane's file may be read by several tasks: equal keys keep their input order all the same."""
    hadoop, size = spark.sparkContext._jsc.hadoopConfiguration(), "spark.sql.files.maxPartitionBytes"
    old = spark.conf.get(size)
    hadoop.set("parquet.block.size", "262144")
    spark.conf.set(size, "262144")
    try:
        df = spark.range(40_000).selectExpr("id", "id % 3 as v", "md5(cast(id as string)) as t")
        res = classic_random_sort(df, SortSpec.of("v"), Lanes(2, ("id",)), split="integer")
        assert res.split.rdd.getNumPartitions() > 2
        got = [r["id"] for r in res.with_rank().select("id", "rank").orderBy("rank").collect()]
    finally:
        spark.conf.set(size, old)
        hadoop.unset("parquet.block.size")
    assert got == sorted(range(40_000), key=lambda i: (i % 3, i))


@pytest.mark.parametrize("network", [baselines.bitonic_all, baselines.odd_even_all])
@pytest.mark.parametrize("p", [1, 5, 8])
def test_networks_hold_no_block_in_one_value(spark, network, p):
    """Blocks of a network are rows that a task may spill, not arrays, and idle or short lanes change nothing."""
    df = spark.range(203).selectExpr("id", "nullif(id * 37 % 11, 3) as v")
    out = network(df, SortSpec.of("v"), Lanes(p, ("id",)))
    assert "collect_list" not in out._jdf.queryExecution().optimizedPlan().toString()
    rows = sorted(out.collect(), key=lambda r: r["rank"])
    assert [r["rank"] for r in rows] == list(range(1, 204))
    assert [(r["k0"], r["lane"], r["pos"]) for r in rows] == sorted(((r["k0"], r["lane"], r["pos"]) for r in rows), key=lambda x: (x[0] is not None, x))


def test_one_lane_is_timed_once_for_all_variants(spark, data, monkeypatch):
    """Every variant's efficiency rests on one sort of one lane by kind, lanes and local sort; no variant sorts on one lane by itself."""
    from evenlane.plans import catalogue_measures as cm

    sorts, asked = [], []
    monkeypatch.setattr(cm, "variant", lambda name, d, spec, p: sorts.append(p) or (2.0, regular_sort(d, spec, Lanes(p, layout="inplace"))))
    real = getattr(cm, "one_lane", None)
    monkeypatch.setattr(cm, "one_lane", lambda d: asked.append(d) or real(d), raising=False)
    rows = cm._grid(None, ("uniform",), (2,), (20,), True)(spark, data).collect()
    assert sorts == [2] * len(cm.VARIANTS) and len(asked) == 1
    assert len(rows) == len(cm.VARIANTS) and all(r["efficiency"] > 0 and r["n"] == 3000 for r in rows)
