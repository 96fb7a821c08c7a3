"""Block sorting networks, radix passes and column sort."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec
from evenlane.operators.layout import Run

Step = list[tuple[int, int]]  # comparators (lane that keeps the low half, lane that keeps the high half)


def power_of_two(p: int) -> int:
    return 1 << max(0, (p - 1).bit_length())


def bitonic_schedule(p: int) -> list[tuple[int, int, Step]]:
    """(stage, distance, comparators) of Batcher's bitonic network on the next power of two of lanes."""
    q, out = power_of_two(p), []
    size = 2
    while size <= q:
        d = size // 2
        while d:
            step = []
            for i in range(q):
                j = i ^ d
                if i < j:
                    step.append((i, j) if not i & size else (j, i))
            out.append((size.bit_length() - 1, d, step))
            d //= 2
        size *= 2
    return out


def odd_even_schedule(p: int) -> list[tuple[int, int, Step]]:
    """(stage, distance, comparators) of Batcher's odd-even merging network."""
    q, out = power_of_two(p), []
    block = 1
    while block < q:
        d = block
        while d:
            step = []
            for j in range(d % block, q - d, 2 * d):
                for i in range(min(d, q - d - j)):
                    if (i + j) // (2 * block) == (i + j + d) // (2 * block):
                        step.append((i + j, i + j + d))
            out.append((block.bit_length(), d, step))
            d //= 2
        block *= 2
    return out


def network_sort(rows: DataFrame, spec: SortSpec, p: int, schedule: list[tuple[int, int, Step]]) -> DataFrame:
    """rows (k0.., lane, pos, pad) with their 1-based rank, by compare-split steps of whole blocks.

    A step brings two blocks into one partition, sorts it and gives the first half to one lane and the rest to the other. Blocks stay rows, so
    that a task may spill them; they are padded to one length with records that sort last. rows is read twice and must be the same each time.
    """
    if any(not k.asc for k in spec.keys):
        raise ValueError("networks sort ascending keys; negate a descending one")
    q, spark = power_of_two(p), rows.sparkSession
    have = {r["lane"]: r["count"] for r in rows.groupBy("lane").count().collect()}  # one a lane
    if have and max(have) >= q:
        raise ValueError(f"a row lies in lane {max(have)}, the network has {q}")
    length, ends = max(have.values(), default=1), []
    for i in range(q):
        ends.append((ends[-1] if ends else 0) + length - have.get(i, 0))
    at = sum((F.col("id") >= e).cast("int") for e in ends[:-1]) if q > 1 else F.lit(0)
    cur = rows.withColumns({"block": F.col("lane").cast("int"), "j": F.col("j") if "j" in rows.columns else F.lit(0)})
    if ends[-1]:
        cur = cur.unionByName(spark.range(ends[-1]).select(at.alias("block"), F.lit(2).alias("pad")), allowMissingColumns=True)
    order = [F.col("pad"), *spec.order("lane", "pos", "j")]
    place = F.col("block")
    for step in [step for _, _, step in schedule] or [[]]:
        idle = sorted(set(range(q)) - {x for c in step for x in c})
        homes = [*step, *[(i, i) for i in idle]]
        pair = {x: i for i, c in enumerate(homes) for x in c}
        met = cur.withColumn("pair", F.array(*[F.lit(pair[i]) for i in range(q)])[place]).drop("block", "place")
        met = met.repartitionById(len(homes), "pair").sortWithinPartitions(*order)
        low, high = (F.array(*[F.lit(c[i]) for c in homes])[F.col("pair")] for i in (0, 1))
        met = met.withColumn("place", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)))
        upper = F.col("place") >= length
        cur = met.withColumns({"block": F.when(upper, high).otherwise(low), "place": F.when(upper, F.col("place") - length).otherwise(F.col("place"))}).drop("pair")
    rank = (F.col("block").cast("long") * length + F.col("place") + 1).alias("rank")
    return cur.where("pad < 2").select(*spec.names, "lane", "pos", "pad", rank)


def radix_sort(run: Run, bits: int = 8) -> DataFrame:
    """The run's rows with their rank by (k0, lane, pos), by stable passes over digits of an integer key."""
    lo, hi = run.df.agg(F.min("k0"), F.max("k0")).first()
    key = F.col("k0").cast("long") - F.lit(lo or 0)
    passes = max(1, -(-max(1, int((hi or 0) - (lo or 0)).bit_length()) // bits))
    base = 0
    starts = []
    for x in run.lengths:
        starts.append(base)
        base += x
    cur = run.df.withColumn("at", F.array(*[F.lit(x).cast("long") for x in starts])[F.col("lane")] + F.col("pos"))
    for i in range(passes):
        digit = F.shiftright(key, i * bits).bitwiseAND(F.lit((1 << bits) - 1)).cast("int")
        cur = cur.withColumn("digit", digit)
        sizes = cur.groupBy("digit").agg(F.count("*").alias("c"))
        w = Window.orderBy("digit").rowsBetween(Window.unboundedPreceding, -1)  # at most 2^bits rows
        base_of = sizes.select("digit", F.coalesce(F.sum("c").over(w), F.lit(0)).alias("base"))
        inside = F.row_number().over(Window.partitionBy("digit").orderBy("at")) - 1
        cur = cur.withColumn("inside", inside).join(F.broadcast(base_of), "digit").withColumn("at", F.col("base") + F.col("inside")).drop("digit", "base", "inside")
    return cur.withColumn("rank", F.col("at") + 1).drop("at")


def column_sort(run: Run, cols: int) -> DataFrame:
    """The run's rows with their rank: four column sorts with fixed permutations between them.

    Needs columns of at least 2 (cols - 1)^2 rows; short inputs are padded with records that sort last.
    """
    rows = max(2 * (cols - 1) ** 2, -(-run.n // cols), 1)
    rows = -(-rows // cols) * cols
    spec = run.spec
    starts, base = [], 0
    for x in run.lengths:
        starts.append(base)
        base += x
    at = F.array(*[F.lit(x).cast("long") for x in starts])[F.col("lane")] + F.col("pos")
    real = run.df.withColumns({"at": at, "pad": F.lit(0)})
    pads = run.df.sparkSession.range(run.n, rows * cols).select(F.col("id").alias("at"), F.lit(1).alias("pad"))
    cur = real.unionByName(pads, allowMissingColumns=True)
    order = [F.col("pad"), *spec.order("lane", "pos", "at")]

    def sort_columns(d: DataFrame, size: int = rows, shift: int = 0) -> DataFrame:
        col = F.floor((F.col("at") + shift) / size).cast("long")
        w = Window.partitionBy("col").orderBy(*order)
        return d.withColumn("col", col).withColumn("at", F.greatest(F.col("col") * size - shift, F.lit(0)) + F.row_number().over(w) - 1).drop("col")

    cur = sort_columns(cur)
    cur = cur.withColumn("at", F.expr(f"(at % {cols}) * {rows} + at div {cols}"))  # read by columns, written by rows
    cur = sort_columns(cur)
    cur = cur.withColumn("at", F.expr(f"(at % {rows}) * {cols} + at div {rows}"))  # and back
    cur = sort_columns(cur)
    cur = sort_columns(cur, rows, rows // 2)  # columns shifted by half
    return cur.where("pad = 0").withColumn("rank", F.col("at") + 1).drop("at", "pad")
