"""Lanes: where the rows start, and the sorted, tagged run of each lane."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec
from evenlane.staging import discard, stable, stage

MASK = (1 << 33) - 1


@dataclass(frozen=True)
class Lanes:
    """p buckets, and the lanes that rows start in.

    block, deal and hash place rows in p lanes by content order over ids. physical deals them over p partitions
    and writes the runs. inplace takes the input's own partitions as lanes, however many and however unlike, and
    moves and writes nothing: the way for large inputs. An input that is no plain scan is written to a table first,
    so that its partitions hold the same rows at each reading.
    """

    p: int
    ids: tuple[str, ...] = ()
    layout: str = "block"

    def __post_init__(self) -> None:
        if self.p < 1:
            raise ValueError("there must be at least one lane")
        if self.layout not in ("physical", "inplace") and not self.ids:
            raise ValueError("a layout by content needs identity columns")


LITERALS = 512  # values one generated expression holds; longer lists come as the value of a subquery


def by_number(values: list[int], at: Column) -> Column:
    """values[at]: one value a partition, lane or bucket."""
    if len(values) <= LITERALS:
        return F.array(*[F.lit(v).cast("long") for v in values])[at]
    return SparkSession.active().createDataFrame([(values,)], "a array<bigint>", verifySchema=False).scalar()[at]


def partitions(df: DataFrame) -> int:
    return df._jdf.queryExecution().toRdd().getNumPartitions()


def indexed(df: DataFrame, tag: str) -> tuple[DataFrame, DataFrame]:
    """(staged df with __part and __at, rows a partition): where each row stood when df was written."""
    t = stage(df.withColumn("__id", F.monotonically_increasing_id()), tag)
    t2 = t.withColumns({"__part": F.shiftright("__id", 33).cast("int"), "__at": F.col("__id").bitwiseAND(F.lit(MASK))}).drop("__id")
    t2._staged_path = t._staged_path
    return t2, t2.groupBy("__part").agg(F.count("*").alias("rows"))


def starts(counts: list[tuple[int, int]], n: int) -> list[int]:
    """Rows before each of n partitions."""
    size = dict(counts)
    out, total = [], 0
    for i in range(n):
        out.append(total)
        total += size.get(i, 0)
    return out


def ordinals(df: DataFrame, ids: tuple[str, ...], name: str = "ord") -> tuple[DataFrame, int]:
    """(df with its 1-based position in the order of ids, number of rows): no single-partition window.

    Rows are range-partitioned and sorted; a position is the rows of lower partitions plus the local index.
    """
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    t, counts = indexed(df.repartitionByRange(n, *ids).sortWithinPartitions(*ids), "ordinals")
    rows = [(r["__part"], r["rows"]) for r in counts.collect()]  # one a partition
    base = starts(rows, max([r[0] for r in rows], default=0) + 1)
    out = t.withColumn(name, by_number(base, F.col("__part")) + F.col("__at") + 1).drop("__part", "__at")
    out._staged_path = t._staged_path
    return out, sum(r[1] for r in rows)


def lane_of(layout: str, p: int, n: int, ids: tuple[str, ...]) -> Column:
    if layout == "block":
        return F.expr(f"((ord - 1) * {p}L) div {max(n, 1)}").cast("int")
    if layout == "deal":
        return F.expr(f"(ord - 1) % {p}").cast("int")
    if layout == "hash":
        return F.expr(f"cast(conv(substr(md5(concat_ws('|', {', '.join(ids)})), 1, 8), 16, 10) as bigint) % {p}").cast("int")
    raise ValueError(f"unknown layout {layout}")


@dataclass
class Run:
    """The tagged input: rows with k0.., lane, pos, and the rows of each lane.

    Layouts by content and physical ones hold sorted runs in a table, pos being the place in the run. In
    place, pos is the place in the input partition: nothing is sorted before the sample asks for it, and (key, lane, pos)
    is the same stable order. moves counts the exchanges of rows since they lay in their first lanes.
    """

    df: DataFrame
    spec: SortSpec
    lanes: Lanes
    sizes: list[int] | None = None
    moves: int = 0
    total: int | None = None

    @property
    def lengths(self) -> list[int]:
        if self.sizes is None:
            counts = {r["lane"]: r["rows"] for r in self.df.groupBy("lane").agg(F.count("*").alias("rows")).collect()}  # one a lane
            self.sizes = [counts.get(i, 0) for i in range(max(counts, default=0) + 1)]
        return self.sizes

    @property
    def inplace(self) -> bool:
        return self.lanes.layout == "inplace"

    @property
    def n(self) -> int:
        return sum(self.lengths) if self.total is None else self.total

    def discard(self) -> None:
        discard(self.df)


def in_place(keyed: DataFrame) -> DataFrame:
    """Rows with lane and pos: the partition and the place in it."""
    d = keyed.withColumn("__id", F.monotonically_increasing_id())
    return d.withColumns({"lane": F.shiftright("__id", 33).cast("int"), "pos": F.col("__id").bitwiseAND(F.lit(MASK))}).drop("__id")


def sorted_run(df: DataFrame, spec: SortSpec, lanes: Lanes, presort: bool = True) -> Run:
    """Place the rows in lanes, sort each lane stably, and tag every row with (lane, pos).

    A layout in place takes no shuffle and defers the sort, a physical one takes one shuffle, one by content two. Without presort, pos is
    the input order of the lane.
    """
    if lanes.layout == "inplace":
        return Run(in_place(spec.add(stable(df, "input"))), spec, lanes)
    keyed = spec.add(df)
    if lanes.layout == "physical":
        placed, order = keyed.repartition(lanes.p), spec.order() if presort else []
        dealt = placed.sortWithinPartitions(*order) if order else placed
    else:
        placed, n = ordinals(keyed, lanes.ids)
        placed = placed.withColumn("lane", lane_of(lanes.layout, lanes.p, n, lanes.ids))
        dealt = placed.repartitionById(lanes.p, "lane").sortWithinPartitions(*(spec.order("ord") if presort else [F.col("ord")])).drop("lane")
    t, counts = indexed(dealt, "run")
    size = {r["__part"]: r["rows"] for r in counts.collect()}
    out = t.withColumnsRenamed({"__part": "lane", "__at": "pos"})
    out._staged_path = t._staged_path
    return Run(out, spec, lanes, [size.get(i, 0) for i in range(lanes.p)])
