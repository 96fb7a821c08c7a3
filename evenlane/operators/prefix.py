"""Prefix sums over the count matrix: where each lane's block starts in its bucket, in three ways that agree."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def dense(counts: DataFrame, p: int) -> DataFrame:
    """The count matrix with its empty cells."""
    spark = counts.sparkSession
    cells = spark.range(p * p).select((F.col("id") / p).cast("int").alias("bucket"), (F.col("id") % p).cast("int").alias("lane"))
    return cells.join(counts, ["bucket", "lane"], "left").select("bucket", "lane", F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"))


def window_offsets(counts: DataFrame) -> DataFrame:
    """Rows (bucket, lane, start): the usual way, one small window a bucket."""
    w = Window.partitionBy("bucket").orderBy("lane").rowsBetween(Window.unboundedPreceding, -1)
    return counts.select("bucket", "lane", F.coalesce(F.sum("cnt").over(w), F.lit(0)).alias("start"))


def tree_offsets(counts: DataFrame, p: int, t: int = 2) -> DataFrame:
    """Up a t-ary tree of lanes with sums of blocks, and down again with what lies left of each block."""
    levels = [dense(counts, p).select("bucket", F.col("lane").alias("node"), F.col("cnt").alias("total"))]
    width = p
    while width > 1:
        width = -(-width // t)
        levels.append(levels[-1].groupBy("bucket", F.expr(f"node div {t}").cast("int").alias("node")).agg(F.sum("total").alias("total")))
    start = levels[-1].select("bucket", "node", F.lit(0).cast("long").alias("start"))
    for level in reversed(levels[:-1]):
        kids = level.withColumn("up", F.expr(f"node div {t}").cast("int"))
        left = kids.alias("a").join(kids.alias("b"), (F.col("a.bucket") == F.col("b.bucket")) & (F.col("a.up") == F.col("b.up")) & (F.col("b.node") < F.col("a.node")), "left")
        before = left.groupBy(F.col("a.bucket").alias("bucket"), F.col("a.node").alias("node"), F.col("a.up").alias("up")).agg(F.coalesce(F.sum("b.total"), F.lit(0)).alias("before"))
        above = start.select("bucket", F.col("node").alias("up"), "start")
        start = before.join(above, ["bucket", "up"]).select("bucket", "node", (F.col("start") + F.col("before")).alias("start"))
    return start.select("bucket", F.col("node").alias("lane"), "start")


def doubling_offsets(counts: DataFrame, p: int) -> DataFrame:
    """Inclusive sums by doubling distances, lg p steps, then one lane back."""
    cur = dense(counts, p).withColumn("sum", F.col("cnt"))
    d = 1
    while d < p:
        back = cur.select("bucket", (F.col("lane") + d).alias("lane"), F.col("sum").alias("more"))
        cur = cur.join(back, ["bucket", "lane"], "left").select("bucket", "lane", "cnt", (F.col("sum") + F.coalesce("more", F.lit(0))).alias("sum"))
        d *= 2
    return cur.select("bucket", "lane", (F.col("sum") - F.col("cnt")).alias("start"))
