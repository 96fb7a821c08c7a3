"""Samples of sorted runs: regular (even or padded) and random (exact, two-step, Bernoulli)."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evenlane.functions.draws import text
from evenlane.operators.layout import MASK, Run, by_number


def regular_ratio(n: int, p: int) -> int:
    """The usual oversampling ratio of the regular method: lg lg n, rounded up."""
    return max(1, math.ceil(math.log2(max(2.0, math.log2(max(4, n))))))


def random_size(n: int, omega2: float | None = None) -> int:
    """Samples a lane of the random method: 2 w^2 lg n, with w^2 = lg n unless given."""
    lg = math.log2(max(2, n))
    return max(1, math.ceil(2 * (lg if omega2 is None else omega2) * lg))


def claim_size(total: int, k: int, eps: float, rho: float) -> int:
    """Smallest s with s >= (1 + eps)/eps^2 (2 rho ln total + ln(2 pi k^2 (k s - 1) e^(1/(3(k s - 1))))): s is on both sides, so iterate."""
    s = 1.0
    for _ in range(200):
        m = max(k * s - 1, 1e-9)
        nxt = (1 + eps) / eps**2 * (2 * rho * math.log(total) + math.log(2 * math.pi * k * k * m) + 1 / (3 * m))
        if abs(nxt - s) < 1e-9:
            break
        s = nxt
    return math.ceil(s)


#: Of n rows in place at most n / SHARE are sampled, or FEW, whichever is more.
SHARE, FEW = 100, 200_000


def stride(n: int, lanes: int, s: int) -> int:
    """Rows that a sample in place stands for: n / (lanes s), but no fewer than SHARE and FEW allow."""
    return max(1, n // max(1, lanes * s), min(SHARE, -(-n // FEW)))


def sample_lanes(run: Run, s: int | None, how: str = "regular", seed: int = 42, presort: bool = True, group: str | None = None) -> DataFrame:
    """About s samples a partition, as they lie, each for the same number x of rows: rows (k0.., lane, pos, group).

    regular: every x-th row of a partition in key order, so that a partition gives samples by its length and leaves fewer
    than x rows unseen. random: rows whose hash falls under 1 / x; s None is the method's own size. One job counts the partitions; only keys
    are read and sorted. The run learns its number of rows.
    """
    keys = run.df.select(*sample_keys(run), (F.col(group) if group else F.lit(0)).cast("int").alias("group"))
    lens = {r["at"]: r["rows"] for r in run.df.groupBy(F.spark_partition_id().alias("at")).agg(F.count("*").alias("rows")).collect()}  # one a partition
    n = sum(lens.values())
    run.total = n
    if run.inplace and not run.moves and run.sizes is None:
        run.sizes = [lens.get(i, 0) for i in range(max(lens, default=0) + 1)]
    x = stride(n, len(lens), random_size(n) if s is None else s)
    if presort:
        keys = keys.sortWithinPartitions(*(["group"] if group else []), *run.spec.order("lane", "pos"))
    if how == "random":
        u = F.xxhash64(F.lit(seed), "lane", "pos")
        return keys.where(u.bitwiseAND(F.lit(2**62 - 1)) < 2**62 // x)
    if how != "regular":
        raise ValueError(f"unknown sample {how}")
    at = F.monotonically_increasing_id().bitwiseAND(F.lit(MASK))
    return keys.withColumn("__at", at).where(F.col("__at") % x == x - 1).drop("__at")


def sample_keys(run: Run) -> list[str]:
    return [*run.spec.names, "lane", "pos"]


def sample_regular(run: Run, s: int, spacing: str = "even") -> DataFrame:
    """s samples of each lane, the last its largest key: rows (k0.., lane, pos, j, pad).

    even: sample j stands at floor((j+1) len / s) - 1, and short lanes give fewer. padded: lanes count as
    equally long and segments as x = ceil(ceil(n/p)/s); positions past the run are pads, which sort last.
    """
    if run.inplace:
        raise ValueError("lanes in place are sampled by sample_lanes")
    p, n = len(run.lengths), run.n
    size = by_number(run.lengths, F.col("lane"))
    keys = run.df.select(*sample_keys(run))
    if spacing == "even":
        # j is the segment that ends at pos, if one does
        at = F.expr(f"((pos + 1) * {s}L + __size - 1) div __size - 1")
        rows = keys.withColumn("__size", size).withColumn("j", at)
        rows = rows.where(F.expr(f"((j + 1) * __size) div {s} - 1 = pos")).drop("__size")
        # a short lane has several j with one position: they all stand there
        last = F.expr(f"((pos + 2) * {s}L - 1) div __size - 1")
        rows = rows.withColumn("__size", size).withColumn("j", F.explode(F.sequence("j", F.least(last, F.lit(s - 1).cast("long"))))).drop("__size")
        return rows.withColumn("pad", F.lit(0))
    if spacing != "padded":
        raise ValueError(f"unknown spacing {spacing}")
    x = max(1, -(-max(1, -(-n // p)) // s))
    real = keys.where(F.col("pos") % x == x - 1).withColumn("j", F.expr(f"pos div {x}L")).where(F.col("j") < s).withColumn("pad", F.lit(0))
    grid = run.df.sparkSession.range(p * s).select((F.col("id") / s).cast("int").alias("lane"), (F.col("id") % s).alias("j"))
    pads = grid.where((F.col("j") + 1) * x - 1 >= by_number(run.lengths, F.col("lane")))
    none = [F.lit(None).cast(run.df.schema[k].dataType).alias(k) for k in run.spec.names]
    return real.unionByName(pads.select(*none, "lane", ((F.col("j") + 1) * x - 1).alias("pos"), "j", F.lit(1).alias("pad")))


def lane_quotas(p: int, total: int, seed: int) -> list[int]:
    """How many of total draws fall on each lane, every draw choosing its lane at random."""
    import hashlib

    out = [0] * p
    for j in range(total):
        out[int(hashlib.md5(f"{seed}|{j}".encode()).hexdigest()[:8], 16) % 2147483648 % p] += 1
    return out


def sample_random(run: Run, s: int, mode: str = "exact", seed: int = 42) -> DataFrame:
    """About s samples of each lane without replacement: rows (k0.., lane, pos, j, pad).

    exact: the s smallest hashes of a lane. two_step: each of p s draws first chooses a lane, then that many
    of the lane's smallest hashes are taken. bernoulli: every row whose hash is under s / len.
    """
    if run.inplace:
        raise ValueError("lanes in place are sampled by sample_lanes")
    p = len(run.lengths)
    h = F.md5(text(seed, "lane", "pos"))
    keys = run.df.select(*sample_keys(run))
    quota = [s] * p if mode != "two_step" else lane_quotas(p, s * p, seed)
    u = F.conv(F.substring(h, 1, 8), 16, 10).cast("long")  # the hash's first 32 bits, in the order of the hashes
    if mode == "bernoulli":
        limit = [min(2**32, int(2**32 * q / max(1, m))) for q, m in zip(quota, run.lengths, strict=True)]
        return keys.where(u < by_number(limit, F.col("lane"))).withColumns({"j": F.lit(0).cast("long"), "pad": F.lit(0)})
    if mode not in ("exact", "two_step"):
        raise ValueError(f"unknown mode {mode}")
    # hashes under a generous limit hold the smallest ones but for a chance below 1e-9 a lane; then all rows are ranked
    limit = [min(2**32, int(2**32 * (q + 8 * math.sqrt(q) + 40) / max(1, m))) for q, m in zip(quota, run.lengths, strict=True)]
    near = keys.where(u < by_number(limit, F.col("lane")))
    want = [min(q, m) for q, m in zip(quota, run.lengths, strict=True)]
    got = {r["lane"]: r["count"] for r in near.groupBy("lane").count().collect()}
    if any(got.get(i, 0) < w for i, w in enumerate(want)):
        near = keys
    w = Window.partitionBy("lane").orderBy(h, "pos")
    ranked = near.withColumn("j", F.row_number().over(w).cast("long") - 1)
    return ranked.where(F.col("j") < by_number(quota, F.col("lane"))).withColumn("pad", F.lit(0))
