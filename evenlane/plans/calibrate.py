"""Machine parameters by small measurements on the running session, and phase times of a sort."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec
from evenlane.operators.layout import Lanes, Run, sorted_run
from evenlane.operators.sorts import SortResult, lane_fences, local_sort
from evenlane.operators.split import with_bucket
from evenlane.plans.model import MachineModel, lg
from evenlane.staging import stable


def _seconds(f) -> float:
    t = time.perf_counter()
    f()
    return time.perf_counter() - t


def measure(spark: SparkSession, p: int = 8, rows: int = 400_000, keys: DataFrame | None = None) -> MachineModel:
    """L: an exchange of almost nothing. g: what a known number of words adds to it. rate: comparisons a microsecond of a local sort.

    The words are hashes of the rows of keys, dealt over p partitions in memory, or of as many numbers as rows says.
    """
    base = spark.range(p).repartitionById(p, F.col("id").cast("int"))
    sync = min(_seconds(lambda: base.write.format("noop").mode("overwrite").save()) for _ in range(3))
    data = spark.range(0, rows, 1, p).select(F.xxhash64("id").alias("x")) if keys is None else keys.select(F.xxhash64(*keys.columns).alias("x")).repartition(p).persist()
    rows = rows if keys is None else data.count()
    scan = min(_seconds(lambda: data.write.format("noop").mode("overwrite").save()) for _ in range(2))
    moved = min(_seconds(lambda: data.repartitionById(p, F.pmod("x", F.lit(p)).cast("int")).write.format("noop").mode("overwrite").save()) for _ in range(2))
    order = min(_seconds(lambda: data.sortWithinPartitions("x").write.format("noop").mode("overwrite").save()) for _ in range(2))
    if keys is not None:
        data.unpersist()
    per = max(1, rows) / p
    g_us = max(1e-4, (moved - scan - sync) * 1e6 / per)
    return MachineModel(p, sync * 1e6, g_us, max(1e-3, per * lg(per) / max(1e-6, (order - scan) * 1e6)))


PHASES = ("init", "local sort", "sampling", "extra routing", "prefix", "routing", "merging", "termination")


def _sink(df: DataFrame) -> float:
    return _seconds(lambda: df.write.format("noop").mode("overwrite").save())


def profile(method: str, df: DataFrame, spec: SortSpec, p: int, local: str = "radix", seed: int = 42) -> tuple[SortResult, dict[str, float]]:
    """(result, seconds by phase) of regular, presorted_random or two_round_regular over the partitions of df as lanes.

    Each phase starts from what the one before left in memory, and is its time less that of reading this: init reads
    the lanes, local sort orders them, sampling finds the fences, extra routing is the first round of a method with two, prefix
    counts blocks and adds them up, routing moves rows to their buckets, merging orders them there, termination gives the memory back.
    """
    spark = df.sparkSession
    held: list[DataFrame] = []

    def keep(d: DataFrame) -> tuple[DataFrame, float]:
        """(d in memory, seconds to read it from there)"""
        out = d.persist()
        held.append(out)
        out.count()
        return out, min(_sink(out) for _ in range(2))

    out = dict.fromkeys(PHASES, 0.0)
    with local_sort(spark, local):
        lanes, out["init"] = keep(stable(df, "lanes"))
        run = sorted_run(lanes, spec, Lanes(p, layout="inplace"))
        ordered = run.df.sortWithinPartitions(*spec.order())
        _sink(ordered)
        out["local sort"] = max(0.0, _sink(ordered) - out["init"])
        run.df, scan = keep(ordered)
        if method == "two_round_regular":
            dealt = run.df.withColumn("home", (F.col("pos") % p).cast("int")).repartitionById(p, "home").drop("home").sortWithinPartitions(*spec.order())
            out["extra routing"] = max(0.0, _sink(dealt) - scan)
            second, scan = keep(dealt)
            run = Run(second, spec, run.lanes, moves=1)
        how = "random" if method == "presorted_random" else "regular"
        t = _seconds(lambda: lane_fences(run, None if how == "random" else 6 * p, how, seed, presort=False))
        fences = lane_fences(run, None if how == "random" else 6 * p, how, seed, presort=False)
        out["sampling"] = t
        split, read = keep(with_bucket(run.df, fences))
        res = SortResult(run, fences, split, {"method": method, "p": p}, tagged=True)
        out["prefix"] = _seconds(lambda: res.offsets().collect())
        moved = split.drop("lane", "pos").repartitionById(p, "bucket")
        _sink(moved)
        out["routing"] = max(0.0, _sink(moved) - read)
        routed, read = keep(moved)
        out["merging"] = max(0.0, _sink(routed.sortWithinPartitions(*spec.order())) - read)

        def release() -> None:
            for d in held:
                d.unpersist()

        out["termination"] = _seconds(release)
    res = SortResult(sorted_run(df, spec, Lanes(p, layout="inplace")), fences, res.split, res.plan)
    return res, {k: v for k, v in out.items() if v or k != "extra routing"}


def observed_g(routing_s: float, sizes: list[int]) -> float:
    """Microseconds a record that the fullest bucket's routing took."""
    return routing_s * 1e6 / max(1, *sizes)


def efficiency(sequential_s: float, parallel_s: float, p: int) -> float:
    return sequential_s / (p * parallel_s) if parallel_s else float("nan")
