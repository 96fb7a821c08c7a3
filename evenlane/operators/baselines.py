"""The methods that the balanced sorts are compared with; each returns a SortResult unless said."""

from __future__ import annotations

import functools

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenlane.functions.draws import draw31, text
from evenlane.functions.spec import Key, SortSpec
from evenlane.operators import networks
from evenlane.operators.fences import FenceSet
from evenlane.operators.layout import Lanes, Run, by_number, indexed, sorted_run, starts
from evenlane.operators.sorts import SortResult, classic_random_sort, exchanges, iterated_sort, lane_fences, local_run, regular_from, regular_sort
from evenlane.operators.split import with_bucket
from evenlane.shipping import ship
from evenlane.staging import stage


def plain_regular(df: DataFrame, spec: SortSpec, lanes: Lanes) -> SortResult:
    """Regular sampling without oversampling, the sample sorted in one place, repeated keys not told apart."""
    return regular_sort(df, spec, lanes, r=1, sample_sort="driver", dup=False)


def _two_rounds(run: Run, home: Column, s: int | None, how: str, seed: int, plan: dict) -> SortResult:
    """Rows move to the lanes of home, are sampled and cut there, and move on to their buckets. First tags travel with every row."""
    spec, p = run.spec, run.lanes.p
    dealt = run.df.withColumn("home", home.cast("int")).repartitionById(p, "home").drop("home")
    second = Run(stage(dealt, "round"), spec, Lanes(p, layout="inplace"), moves=run.moves + exchanges(dealt))
    fences = lane_fences(second, s, how, seed) if p > 1 else FenceSet(spec, ())
    return SortResult(second, fences, with_bucket(second.df, fences), plan)


def two_round_regular(df: DataFrame, spec: SortSpec, lanes: Lanes, r: int = 4) -> SortResult:
    """Two bulk exchanges: sorted runs are dealt round-robin over the lanes and merged, then sampled regularly and routed."""
    run = sorted_run(df, spec, lanes)
    return _two_rounds(run, F.col("pos") % lanes.p, r * lanes.p, "regular", 0, {"method": "two_round_regular", "p": lanes.p, "r": r})


def two_round_random(df: DataFrame, spec: SortSpec, lanes: Lanes, s: int | None = None, seed: int = 42) -> SortResult:
    """Two bulk exchanges: rows go to random lanes, and the fences come from random samples of what lies there."""
    run = sorted_run(df, spec, lanes)
    return _two_rounds(run, draw31(text(seed, "lane", "pos")) % lanes.p, s, "random", seed + 1, {"method": "two_round_random", "p": lanes.p, "s": s})


def sample_sort_untagged(df: DataFrame, spec: SortSpec, lanes: Lanes, s: int | None = None, seed: int = 42) -> SortResult:
    """The traditional sample sort with repeated keys left alone."""
    return classic_random_sort(df, spec, lanes, s, seed, dup=False)


def tag_all(df: DataFrame, spec: SortSpec, lanes: Lanes, r: int = 4) -> SortResult:
    """Every key is made unlike all others before the sort by its address, one word that is a key of its own.

    Runs, samples, fences and moved rows all carry and compare it: the same order with twice the words of a single key.
    """
    run = sorted_run(df, spec, lanes)
    rows = run.df.withColumn(f"k{len(spec.keys)}", F.shiftleft(F.col("lane").cast("long"), 33).bitwiseOR(F.col("pos")))
    tagged = Run(rows, SortSpec((*spec.keys, Key("address"))), lanes, run.sizes)
    out = regular_from(tagged, r, dup=False)
    out.plan |= {"method": "tag_all"}
    return out


def bitonic_all(df: DataFrame, spec: SortSpec, lanes: Lanes) -> DataFrame:
    """All rows through the bitonic network of blocks: rows (k0.., lane, pos, rank). For inputs whose lanes fit in memory."""
    run = sorted_run(df, spec, lanes)
    return networks.network_sort(run.df.select(*spec.names, "lane", "pos", F.lit(0).alias("pad")), spec, lanes.p, networks.bitonic_schedule(lanes.p)).drop("pad")


def odd_even_all(df: DataFrame, spec: SortSpec, lanes: Lanes) -> DataFrame:
    """All rows through the odd-even merging network."""
    run = sorted_run(df, spec, lanes)
    return networks.network_sort(run.df.select(*spec.names, "lane", "pos", F.lit(0).alias("pad")), spec, lanes.p, networks.odd_even_schedule(lanes.p)).drop("pad")


def binary_rounds(df: DataFrame, spec: SortSpec, lanes: Lanes, seed: int = 42) -> SortResult:
    """Parallel quicksort: lg p rounds, each splitting every group in two."""
    return iterated_sort(df, spec, lanes, 2, lanes.p.bit_length() - 1, method="random", seed=seed)


def kway_rounds(df: DataFrame, spec: SortSpec, lanes: Lanes, k: int) -> SortResult:
    """k-way splitting in lg p / lg k rounds."""
    rounds = 1
    while k**rounds < lanes.p:
        rounds += 1
    return iterated_sort(df, spec, lanes, k, rounds)


def sequential(df: DataFrame, spec: SortSpec, ids: tuple[str, ...], algo: str = "cmp") -> DataFrame:
    """One lane sorts everything: rows with their rank. The denominator of every efficiency, not for large inputs."""

    run = local_run(df, spec, Lanes(1, ids), algo)
    return run.df.withColumn("rank", F.col("pos") + 1)


def callback_sort(df: DataFrame, spec: SortSpec, lanes: Lanes) -> DataFrame:
    """Routed as usual, each bucket sorted in Python through a comparison callback: rows with their rank."""
    ship(df.sparkSession)
    res = regular_sort(df, spec, lanes)
    names, keys = spec.names, spec.keys
    base = starts(list(enumerate(res.bucket_sizes())), lanes.p)

    def compare(a: tuple, b: tuple) -> int:
        for i, k in enumerate(keys):
            x, y = a[i], b[i]
            if x is None or y is None:
                if x is None and y is None:
                    continue
                return -1 if (x is None) == k.first else 1
            if x != y:
                return (-1 if x < y else 1) * (1 if k.asc else -1)
        return (a[-2:] > b[-2:]) - (a[-2:] < b[-2:])

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = [tuple(None if v is None or v is pd.NaT else v for v in t) for t in pdf[[*names, "lane", "pos"]].itertuples(index=False)]
        order = sorted(range(len(rows)), key=functools.cmp_to_key(lambda i, j: compare(rows[i], rows[j])))
        out = pdf.iloc[order].copy()
        out["rank"] = range(1, len(out) + 1)
        return out

    rows = res.split
    ranked = rows.groupBy("bucket").applyInPandas(run, ", ".join([*[f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema], "rank long"]))
    return ranked.withColumn("rank", F.col("rank") + by_number(base, F.col("bucket")))


def range_exchange(df: DataFrame, spec: SortSpec, lanes: Lanes) -> DataFrame:
    """Spark's own global sort of the tagged run: range exchange with sampled bounds, rows with their rank."""
    run = sorted_run(df, spec, lanes)
    t, counts = indexed(run.df.repartitionByRange(lanes.p, *spec.order("lane", "pos")).sortWithinPartitions(*spec.order("lane", "pos")), "range")
    rows = [(r["__part"], r["rows"]) for r in counts.collect()]
    base = starts(rows, max([r[0] for r in rows], default=0) + 1)
    return t.withColumn("rank", by_number(base, F.col("__part")) + F.col("__at") + 1).drop("__part", "__at")


def sketch_fences(df: DataFrame, key: str, p: int, accuracy: int = 10_000) -> list:
    """Fences of one numeric key from a mergeable quantile summary, in one aggregate pass; they cannot split equal keys."""
    cuts = [i / p for i in range(1, p)]
    return df.agg(F.percentile_approx(F.expr(key), cuts, accuracy).alias("b")).first()["b"] if cuts else []


def sketch_bucket(key: str, cuts: list) -> Column:
    """The bucket of a key among fences without tags: those strictly below it."""
    return F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: c < F.expr(key))) if cuts else F.lit(0)
