"""Buckets of rows: the number of fences strictly below each, in four ways that agree."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec
from evenlane.operators.fences import FenceSet
from evenlane.operators.layout import by_number

TREE_LIMIT = 256  # fences one generated expression holds; more go through search


def tree(fences: FenceSet, tagged: bool = True, row: Callable[[str], Column] = F.col, inclusive: bool = False) -> Column:
    """A balanced decision: lg p comparisons a row, in generated code."""

    def node(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(fences.names[lo] if fences.names else lo)
        mid = (lo + hi) // 2
        return F.when(fences.spec.below(fences.records[mid], tagged, row, inclusive), node(mid + 1, hi)).otherwise(node(lo, mid))

    return node(0, len(fences)).cast("int")


def tree_text(fences: FenceSet, df: DataFrame, tagged: bool = True) -> str | None:
    """The same decision as SQL text, where the key types have plain literals."""
    kinds = {n: df.schema[n].dataType for n in [*fences.spec.names, "lane", "pos"]}
    tests = [fences.spec.below_text(f, kinds, tagged) for f in fences.records]
    if None in tests:
        return None

    def node(lo: int, hi: int) -> str:
        if lo == hi:
            return str(fences.names[lo] if fences.names else lo)
        mid = (lo + hi) // 2
        return f"if({tests[mid]}, {node(mid + 1, hi)}, {node(lo, mid)})"

    return f"cast({node(0, len(fences))} as int)"


def search(fences: FenceSet, tagged: bool = True, row: Callable[[str], Column] = F.col, inclusive: bool = False) -> Column:
    """Binary search of the row among the fences in the column __fences: for any number of them and any order of keys."""
    steps = max(1, math.ceil(math.log2(len(fences) + 1)))
    state = F.struct(F.lit(0).alias("lo"), F.lit(len(fences)).alias("hi"))

    def step(s: Column, _: Column) -> Column:
        mid = F.shiftright(s["lo"] + s["hi"], 1).cast("int")
        open_ = s["lo"] < s["hi"]
        below = open_ & fences.spec.below(F.get(F.col("__fences"), mid), tagged, row, inclusive)
        return F.struct(F.when(below, mid + 1).otherwise(s["lo"]).alias("lo"), F.when(open_ & ~below, mid).otherwise(s["hi"]).alias("hi"))

    return F.aggregate(F.sequence(F.lit(0), F.lit(steps)), state, step, lambda s: s["lo"])


def with_position(df: DataFrame, fences: FenceSet, name: str, tagged: bool = True, row: Callable[[str], Column] = F.col, inclusive: bool = False, how: str = "tree") -> DataFrame:
    """df with the number of fences strictly below (inclusive: or at) a row's keys, by decisions or, for many fences, by search.

    Searched fences come as the value of a subquery, read once and sent with the tasks: p - 1 records.
    """
    if not len(fences):
        return df.withColumn(name, F.lit(fences.names[0] if fences.names else 0))
    if how == "tree" and len(fences) <= TREE_LIMIT:
        text = tree_text(fences, df, tagged) if row is F.col and not inclusive else None
        return df.withColumn(name, F.expr(text) if text else tree(fences, tagged, row, inclusive))
    like = df if row is F.col else df.select(*[row(n).alias(n) for n in fences.spec.names], F.lit(0).alias("lane"), F.lit(0).cast("long").alias("pos"))
    out = df.withColumn("__fences", fences.table(like)).withColumn(name, search(fences, tagged, row, inclusive)).drop("__fences")
    return out.withColumn(name, by_number(list(fences.names), F.col(name)).cast("int")) if fences.names else out


def with_bucket(df: DataFrame, fences: FenceSet, how: str = "tree", tagged: bool = True) -> DataFrame:
    """df (k0.., lane, pos) with its bucket.

    tree: generated decisions, or search for many fences. search: per-row binary search. cuts: first position of every bucket in
    each run, then the interval that holds pos. merge: the fences join each run, and a running count follows them.
    """
    if not len(fences):
        return with_position(df, fences, "bucket")
    if how in ("tree", "search"):
        return with_position(df, fences, "bucket", tagged, how=how)
    if how == "cuts":
        own = with_position(df, fences, "i", tagged).select("lane", "pos", "i")
        firsts = own.groupBy("lane", "i").agg(F.min("pos").alias("cut")).where("i > 0")
        # a bucket without rows in the run begins where the next one does
        table = firsts.groupBy("lane").agg(F.sort_array(F.collect_list(F.struct("i", "cut"))).alias("at"))  # at most p - 1 cuts a lane
        table = table.select("lane", F.flatten(F.transform("at", lambda x, j: F.array_repeat(x["cut"], x["i"] - F.when(j > 0, F.get(F.col("at"), j - 1)["i"]).otherwise(F.lit(0))))).alias("cuts"))
        j = df.join(table, "lane", "left")
        return j.withColumn("bucket", F.coalesce(F.size(F.filter("cuts", lambda c: c <= F.col("pos"))), F.lit(0)).cast("int")).drop("cuts")
    if how == "merge":
        spec: SortSpec = fences.spec
        lanes = df.select("lane").distinct().withColumn("f", F.explode(fences.table(df)))
        marks = lanes.select("lane", *[F.col("f")[n].alias(n) for n in spec.names], (F.col("f")["lane"] if tagged else F.lit(2**31 - 1)).alias("t_lane"), F.col("f")["pos"].alias("t_pos"), F.lit(1).alias("mark"))
        rows = df.withColumns({"t_lane": F.col("lane"), "t_pos": F.col("pos"), "mark": F.lit(0)})
        w = Window.partitionBy("lane").orderBy(*spec.order("t_lane", "t_pos", "mark")).rowsBetween(Window.unboundedPreceding, 0)
        both = rows.unionByName(marks, allowMissingColumns=True)
        return both.withColumn("bucket", F.sum("mark").over(w).cast("int")).where("mark = 0").drop("t_lane", "t_pos", "mark")
    raise ValueError(f"unknown way {how}")


def count_matrix(split: DataFrame) -> DataFrame:
    """Rows (bucket, lane, cnt) of the cells that are not empty."""
    return split.groupBy("bucket", "lane").agg(F.count("*").alias("cnt"))
