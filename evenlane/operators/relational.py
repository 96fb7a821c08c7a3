"""Order-based operators on a sort's result: they reuse its fences, buckets and ranks.

Windows and groups inside buckets follow the sort's own exchange; only boundary values, one a bucket, meet on the driver.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec
from evenlane.operators.fences import FenceSet
from evenlane.operators.layout import Lanes, by_number, sorted_run, starts
from evenlane.operators.sorts import SortResult, regular_sort
from evenlane.operators.split import with_bucket, with_position
from evenlane.staging import stage


def _base(result: SortResult) -> tuple[list[int], list[int]]:
    sizes = result.bucket_sizes()
    return sizes, starts(list(enumerate(sizes)), result.p)


def slice_ranks(result: SortResult, first: int, last: int) -> DataFrame:
    """Rows with ranks first..last (1-based): only the buckets that hold them are routed."""
    sizes, base = _base(result)
    hit = [b for b in range(result.p) if sizes[b] and base[b] < last and base[b] + sizes[b] >= first]
    rows = result.split.where(F.col("bucket").isin(hit)).repartitionById(result.p, "bucket").sortWithinPartitions(*result.order)
    at = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    return rows.withColumn("rank", by_number(base, F.col("bucket")) + at + 1).where(F.col("rank").between(first, last))


def top_k(result: SortResult, k: int) -> DataFrame:
    """The first k rows: later buckets are never moved."""
    return slice_ranks(result, 1, k)


def kth(result: SortResult, k: int) -> DataFrame:
    return slice_ranks(result, k, k)


def quantile_exact(result: SortResult, *qs: float) -> DataFrame:
    """Rows (q, k0): the smallest key with at least q n rows at or before it."""
    sizes, base = _base(result)
    n = sum(sizes)
    ranks = [max(1, -int(-q * n // 1)) for q in qs]
    hit = sorted({b for b in range(result.p) for x in ranks if base[b] < x <= base[b] + sizes[b]})
    rows = result.split.select("k0", "lane", "pos", "bucket").where(F.col("bucket").isin(hit)).repartitionById(result.p, "bucket").sortWithinPartitions(*result.order)
    at = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    found = rows.select("k0", (by_number(base, F.col("bucket")) + at + 1).alias("rank")).where(F.col("rank").isin(ranks))
    wanted = F.filter(F.array(*[F.struct(F.lit(q).alias("q"), F.lit(x).cast("long").alias("r")) for q, x in zip(qs, ranks, strict=True)]), lambda x: x["r"] == F.col("rank"))
    return found.select(F.explode(wanted).alias("x"), "k0").select("x.q", "k0")


def _keys(spec: SortSpec) -> Column:
    return F.struct(*spec.names)


def _same(a: dict, b: dict, names: list[str]) -> bool:
    """Whether two fences have the same keys; NaN equals itself."""
    return all(a[n] == b[n] or (a[n] != a[n] and b[n] != b[n]) for n in names)


def _at_fence(result: SortResult, b: Column) -> Column:
    """Whether the row's keys are those of fence b (0-based); false where there is none."""
    names, f = result.spec.names, result.fences
    if not len(f):
        return F.lit(False)
    keys = F.get(f.table(result.split), b)
    out = keys.isNotNull()
    for n in names:
        out = out & keys[n].eqNullSafe(F.col(n))
    return F.coalesce(out, F.lit(False))


def _edges(result: SortResult, distinct: bool = False) -> tuple[list[int], list[int], list[int]]:
    """Per bucket: rows before it, of these the rows whose keys go on in it, and keys before it that do not go on.

    A key in several buckets is that of the fences between them, so a bucket need only count its rows at its two fences.
    """
    agg = [F.count("*").alias("rows"), F.count_if(_at_fence(result, F.col("bucket") - 1)).alias("low"), F.count_if(_at_fence(result, F.col("bucket"))).alias("high")]
    have = {r["bucket"]: r for r in result.split.groupBy("bucket").agg(*agg).collect()}  # one a bucket
    kinds = {}
    if distinct:
        kinds = {r["bucket"]: r["count"] for r in result.split.groupBy("bucket", *result.spec.names).agg(F.lit(1)).groupBy("bucket").count().collect()}
    base, carried, dense, rows, keys, before = [], [], [], 0, 0, 0
    names, f = result.spec.names, result.fences.records
    for b in range(result.p):
        r = have.get(b)
        if b and b - 1 < len(f):
            above = have.get(b - 1)
            goes_on = b > 1 and _same(f[b - 2], f[b - 1], names)
            before = (above["high"] if above else 0) + (before if goes_on else 0)
        else:
            before = 0
        shared = before if r and r["low"] else 0
        base.append(rows)
        carried.append(shared)
        dense.append(keys - (1 if shared else 0))
        rows += r["rows"] if r else 0
        keys += kinds.get(b, 0) - (1 if shared else 0)
    return base, carried, dense


def with_rank(result: SortResult, kind: str = "rank") -> DataFrame:
    """The table with a global row_number and, if asked for, rank or dense_rank: one exchange, that of the sort."""
    if kind == "row_number":
        return result.with_rank("row_number")
    if kind not in ("rank", "dense_rank"):
        raise ValueError(f"unknown rank {kind}")
    base, carried, dense = _edges(result, kind == "dense_rank")
    place = Window.partitionBy("bucket").orderBy(*result.order)
    keys = Window.partitionBy("bucket").orderBy(*result.spec.order())
    b = F.col("bucket")
    out = result.windowed.withColumn("row_number", by_number(base, b) + F.row_number().over(place))
    if kind == "dense_rank":
        return out.withColumn("dense_rank", by_number(dense, b) + F.dense_rank().over(keys))
    # a bucket's first key may have begun in buckets before
    return out.withColumn("__r", F.rank().over(keys)).withColumn("rank", by_number(base, b) + F.col("__r") - F.when(F.col("__r") == 1, by_number(carried, b)).otherwise(0)).drop("__r")


def running_sum(result: SortResult, col: str, name: str = "running") -> DataFrame:
    """The table with the sum of col over all rows up to each: bucket totals before, a window inside."""
    totals = {r["bucket"]: r["t"] for r in result.split.groupBy("bucket").agg(F.sum(F.col(col).cast("long")).alias("t")).collect()}  # one a bucket
    base = starts([(b, totals.get(b) or 0) for b in range(result.p)], result.p)
    w = Window.partitionBy("bucket").orderBy(*result.order).rowsBetween(Window.unboundedPreceding, 0)
    return result.windowed.withColumn(name, by_number(base, F.col("bucket")) + F.coalesce(F.sum(F.col(col).cast("long")).over(w), F.lit(0)))


def first_rows(df: DataFrame, keys: list[str], order: list[str]) -> DataFrame:
    """The first row of each key by order: minima combined before the one exchange, so that hot keys cost nothing."""
    rest = [c for c in df.columns if c not in keys and c not in order]
    least = F.min(F.struct(*[c for c in order if c not in keys], *rest)) if any(c not in keys for c in df.columns) else F.count("*")
    return df.groupBy(*keys).agg(least.alias("__first")).select(*[F.col(c) if c in keys else F.col("__first")[c].alias(c) for c in df.columns])


def dedup(result: SortResult) -> DataFrame:
    """The first row of each key in sorted order: a row whose key is the one before it in its bucket, or that of the bucket before, goes."""
    _, carried, _ = _edges(result)
    keys = Window.partitionBy("bucket").orderBy(*result.order)
    before = F.lag(_keys(result.spec)).over(keys)
    new = (F.row_number().over(keys) == 1) | ~before.eqNullSafe(_keys(result.spec))
    out = result.windowed.withColumns({"__new": new, "__first": F.row_number().over(keys) == 1})
    return out.where(F.col("__new") & ~(F.col("__first") & (by_number(carried, F.col("bucket")) > 0))).drop("__new", "__first")


def sorted_agg(result: SortResult, **aggs: str) -> DataFrame:
    """Groups of equal keys: aggregated where the route put them, then the few groups at fences are put together.

    aggs: name -> sum(column) or count(*).
    """
    spec = result.spec
    part = result.routed.groupBy("bucket", *spec.names).agg(*[F.expr(e).alias(n) for n, e in aggs.items()])
    edge = _at_fence(result, F.col("bucket") - 1) | _at_fence(result, F.col("bucket"))
    part = stage(part.withColumn("__edge", edge), "groups")
    torn = part.where("__edge").groupBy(*spec.names).agg(*[F.sum(n).alias(n) for n in aggs])  # at most two groups a fence
    return part.where("not __edge").select(*spec.names, *aggs).union(torn.select(*spec.names, *aggs))


def to_buckets(left: SortResult, right: DataFrame, low: Column, high: Column) -> DataFrame:
    """right in the buckets (column __bucket) that may hold first keys in [low, high], moved there: tags may have spread one key over several."""
    first = FenceSet(left.spec.prefix(1), left.fences.records, left.fences.names)
    r = with_position(right, first, "__lo", False, lambda _: low)
    r = with_position(r, first, "__hi", False, lambda _: high, inclusive=True)
    return r.withColumn("__bucket", F.explode(F.sequence("__lo", "__hi"))).drop("__lo", "__hi").repartitionById(left.p, "__bucket")


def fenced_join(left: SortResult, right: DataFrame, right_key: str, how: str = "inner") -> DataFrame:
    """left joined with right on left's first key: hot keys are cut by tag, and right's rows go to each piece.

    how: inner, left_semi, left_anti. Each side is moved once, to its buckets, and merged there.
    """
    r = to_buckets(left, right, F.col(right_key), F.col(right_key)).withColumn("__key", F.col(right_key))
    l = left.routed
    return l.join(r, (l["bucket"] == r["__bucket"]) & (l["k0"] == r["__key"]), how).drop("__bucket", "__key")


def range_join(left: SortResult, right: DataFrame, right_key: str, by: tuple[str, str], within) -> DataFrame:
    """Pairs with left.k0 < right.key <= left.k0 + within and equal by: right's rows go to every bucket their range touches."""
    r = to_buckets(left, right, F.col(right_key) - within, F.col(right_key))
    l = left.routed
    on = (l["bucket"] == r["__bucket"]) & (l[by[0]] == r[by[1]]) & (r[right_key] > l["k0"]) & (r[right_key] <= l["k0"] + within)
    return l.join(r, on).drop("__bucket")


def asof(left: DataFrame, right: DataFrame, by: str, on: str, value: str, name: str, p: int | None = None) -> DataFrame:
    """Each left row with the value of the last right row of the same by at or before it.

    Both sides are sorted together by (by, on) into p buckets, so a hot by is cut over many; what holds at a bucket's
    start, one row a bucket, is carried into it. Null values of by match nothing.
    """
    kind = dict(right.dtypes)[value]
    l = left.withColumns({"__v": F.lit(None).cast(kind), "__side": F.lit(1)})
    r = right.select(by, on, F.col(value).alias("__v"), F.lit(0).alias("__side"))
    p = p or int(left.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    res = regular_sort(l.unionByName(r, allowMissingColumns=True), SortSpec.of(by, on, "__side"), Lanes(p, layout="inplace"))
    known = F.when(F.col("__side") == 0, F.struct(F.col(by).alias("by"), F.col("__v").alias("v")))
    last = {x["bucket"]: x["m"] for x in res.split.where("__side = 0").groupBy("bucket").agg(F.max_by(F.struct(F.col(by).alias("by"), F.col("__v").alias("v")), F.struct("k0", "k1", "lane", "pos")).alias("m")).collect()}  # one a bucket
    held, rows = None, []
    for b in range(p):
        rows.append((b, *(held or (None, None)), held is not None))
        held = (last[b]["by"], last[b]["v"]) if b in last else held
    carry = left.sparkSession.createDataFrame(rows, f"__b int, __by {dict(left.dtypes)[by]}, __cv {kind}, __has boolean")
    w = Window.partitionBy("bucket").orderBy(*res.order).rowsBetween(Window.unboundedPreceding, 0)
    out = res.windowed.withColumn("__last", F.last(known, True).over(w)).where("__side = 1")
    out = out.join(F.broadcast(carry), F.col("bucket") == F.col("__b"))  # p rows
    found = F.when(F.col("__last").isNotNull(), F.when(F.col("__last.by") == F.col(by), F.col("__last.v"))).when(F.col("__by") == F.col(by), F.col("__cv"))
    return out.withColumn(name, found).select(*left.columns, name)


def merge_sorted(a: SortResult, b: DataFrame) -> DataFrame:
    """One sorted table of a's rows and b's (columns as a's input): b alone is sorted and cut, by a's fences; ties put a first."""
    run = sorted_run(b, a.spec, Lanes(a.p, layout="physical"))
    other = with_bucket(run.df.withColumn("lane", F.lit(2**31 - 1)), a.fences)
    both = a.split.withColumn("__from", F.lit(0)).unionByName(other.withColumn("__from", F.lit(1)), allowMissingColumns=True)
    return both.repartitionById(a.p, "bucket").sortWithinPartitions(*a.spec.order("__from", "lane", "pos"))
