"""Balance, communication and correctness of a sort's result."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenlane.operators.sorts import SortResult


def imbalance(sizes: list[int]) -> float:
    """n_max p / n - 1."""
    n = sum(sizes)
    return max(sizes) * len(sizes) / n - 1 if n else 0.0


def h_relation(result: SortResult) -> DataFrame:
    """Rows (lane, sent, received): a lane keeps what already lies in its own bucket."""
    c = result.counts
    away = F.when(F.col("bucket") != F.col("lane"), F.col("cnt")).otherwise(0)
    sent = c.groupBy(F.col("lane").cast("int").alias("lane")).agg(F.sum(away).cast("long").alias("sent"))
    received = c.groupBy(F.col("bucket").cast("int").alias("lane")).agg(F.sum(away).cast("long").alias("received"))
    all_ = result.split.sparkSession.range(result.p).select(F.col("id").cast("int").alias("lane"))
    return all_.join(sent, "lane", "left").join(received, "lane", "left").na.fill(0)


def sample_share(n: int, p: int, r: int) -> tuple[int, float]:
    """(samples, share of the keys) of the regular method."""
    return p * p * r, p * p * r / n if n else 0.0


def tag_words(result: SortResult, samples: int) -> int:
    """Words of keys and addresses that the sort moves: what its routed rows carry without the payload, and the tags of its samples."""
    moved = result.by_keys.columns
    carried = sum(1 for c in moved if c in result.spec.names)
    return result.run.n * carried + (2 * samples if result.tagged else 0)


def dup_overhead(with_s: float, without_s: float) -> float:
    return with_s / without_s - 1 if without_s else float("nan")


def checksum(df: DataFrame, *cols: str) -> tuple[int, int]:
    """(rows, sum of hashes): equal for permutations of the same rows."""
    r = df.agg(F.count("*").alias("n"), F.sum(F.xxhash64(*cols).cast("decimal(38,0)")).alias("h")).first()
    return r["n"], int(r["h"] or 0)


def is_sorted(result: SortResult) -> bool:
    """Whether every partition is in order and no bucket starts below the one before ends, by (keys, lane, pos)."""
    from pyspark.sql import Window

    ranked = result.with_rank("__rank").withColumn("__at", F.expr(f"(__rank - 1) div {max(1, -(-result.run.n // result.p))}"))
    w = Window.partitionBy("__at").orderBy("__rank")
    names = [*result.spec.names, "lane", "pos"]
    want = F.row_number().over(Window.partitionBy("__at").orderBy(*result.spec.order("lane", "pos")))
    local = ranked.withColumn("__a", F.row_number().over(w)).withColumn("__b", want).where("__a <> __b").isEmpty()
    ends = ranked.groupBy("bucket").agg(F.min_by(F.struct(*names), "__rank").alias("lo"), F.max_by(F.struct(*names), "__rank").alias("hi")).orderBy("bucket").collect()
    return local and all(_before(result, a["hi"], b["lo"]) for a, b in zip(ends, ends[1:], strict=False))


def _before(result: SortResult, a, b) -> bool:
    for k, n in zip(result.spec.keys, result.spec.names, strict=True):
        x, y = a[n], b[n]
        if x == y or (x is None and y is None):
            continue
        if x is None or y is None:
            return (x is None) == k.first
        return (x < y) == k.asc
    return (a["lane"], a["pos"]) <= (b["lane"], b["pos"])


def is_stable(result: SortResult) -> bool:
    """Whether equal keys keep the order of their first places (ord, where the layout has one)."""
    from pyspark.sql import Window

    ranked = result.with_rank("__rank")
    place = "ord" if "ord" in ranked.columns else "pos"
    w = Window.partitionBy(*result.spec.names, "lane").orderBy("__rank")
    return ranked.withColumn("__before", F.lag(place).over(w)).where(F.col("__before") > F.col(place)).isEmpty()
