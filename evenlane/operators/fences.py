"""Fences: every s-th record of the sorted sample, tags included, as driver records or as a stored catalogue."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec


@dataclass(frozen=True)
class FenceSet:
    """Records in order, each a dict of k0.., lane, pos; a row's bucket is the number of fences strictly below it.

    With names, one for what lies below all fences and one for what lies above each, the bucket is that name.
    """

    spec: SortSpec
    records: tuple[dict, ...]
    names: tuple[int, ...] | None = None

    def table(self, like: DataFrame) -> Column:
        """array<struct<k0.., lane, pos>> of the records in order, with the key types of like: the value of a subquery."""
        rows = self.to_df(like.sparkSession, like)
        return rows.agg(F.sort_array(F.collect_list(F.struct("rank", *self.spec.names, "lane", "pos"))).alias("f")).scalar()

    def __len__(self) -> int:
        return len(self.records)

    def to_df(self, spark, like: DataFrame) -> DataFrame:
        """The catalogue: rows (rank, k0.., lane, pos), with the key types of like."""
        fields = ", ".join(["rank int", *[f"{n} {like.schema[n].dataType.simpleString()}" for n in self.spec.names], "lane int", "pos long"])
        rows = [(i + 1, *[r[n] for n in self.spec.names], r["lane"], r["pos"]) for i, r in enumerate(self.records)]
        return spark.createDataFrame(rows, fields, verifySchema=False)

    @staticmethod
    def of(spec: SortSpec, catalogue: DataFrame) -> FenceSet:
        """The set that a catalogue holds: one row a fence, at most one a lane."""
        return FenceSet(spec, tuple({n: r[n] for n in [*spec.names, "lane", "pos"]} for r in catalogue.orderBy("rank").collect()))


def ranked_sample(sample: DataFrame, spec: SortSpec) -> DataFrame:
    """The sample with its 1-based rank, pads last. A sample has p s rows, so one window over it is small.

    Samples too large for that are sorted by the engine itself: see sorts.sort_sample.
    """
    w = Window.orderBy("pad", *spec.order("lane", "pos", "j"))
    return sample.withColumn("rank", F.row_number().over(w))


def pick(ranked: DataFrame, spec: SortSpec, p: int, s: int | None = None) -> FenceSet:
    """Fences at ranks s, 2s, ..., (p-1)s; with samples missing, at even shares of what there is."""
    if s is None:
        total = ranked.count()
        at = [max(1, (i * total) // p) for i in range(1, p)] if total else []
    else:
        at = [i * s for i in range(1, p)]
    rows = {r["rank"]: r for r in ranked.where(F.col("rank").isin(at) & (F.col("pad") == 0)).collect()} if at else {}
    return FenceSet(spec, tuple({n: rows[i][n] for n in [*spec.names, "lane", "pos"]} for i in at if i in rows))


def group_fences(sample: DataFrame, spec: SortSpec, k: int) -> dict[int, dict[int, dict]]:
    """group -> its k - 1 fences by number, from samples that stand for equally many rows: fence i is the first with i/k of the group's samples at or below.

    One window a group, each over a sample. At most one row a fence comes back.
    """
    w = Window.partitionBy("group")
    ranked = sample.withColumns({"rank": F.row_number().over(w.orderBy(*spec.order("lane", "pos"))).cast("long"), "rows": F.count("*").over(w)})
    ranked = ranked.withColumns({"hi": F.expr(f"least(rank * {k} div rows, {k - 1})"), "lo": F.expr(f"(rank - 1) * {k} div rows")})
    some = ranked.where("hi > lo").select("group", *spec.names, "lane", "pos", F.explode(F.sequence(F.col("lo") + 1, "hi")).alias("i"))
    out: dict[int, dict[int, dict]] = {}
    for r in some.collect():
        out.setdefault(r["group"], {})[r["i"]] = {n: r[n] for n in [*spec.names, "lane", "pos"]}
    return out
