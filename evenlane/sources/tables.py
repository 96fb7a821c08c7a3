"""Reads, sinks and the fence catalogue."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec
from evenlane.operators.fences import FenceSet

#: Identity columns of the given tables: a lineitem row is known by all of its columns.
IDS: dict[str, tuple[str, ...]] = {
    "lineitem": ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"),
    "orders": ("o_orderkey",),
    "events": ("event_id",),
    "documents": ("doc_id",),
    "conversations": ("conv_id", "turn"),
    "customer": ("c_custkey",),
    "part": ("p_partkey",),
}


def read(spark: SparkSession, directory: str, table: str, columns: list[str] | None = None, where: str | None = None) -> DataFrame:
    """A Parquet table, columns pruned and the filter pushed to the scan."""
    df = spark.read.parquet(f"{directory}/{table}.parquet")
    df = df.where(where) if where else df
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    """CSV, JSON, ORC, text or Parquet under a stated schema: nothing is inferred."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def write_sorted(result, path: str) -> None:
    """The sorted table, one file a bucket, file order being bucket order."""
    result.df.write.mode("overwrite").parquet(path)


def write_fenced(result, path: str) -> None:
    """The table partitioned by bucket, and its fences beside it: range reads then touch few buckets."""
    result.df.write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/rows")
    result.fences.to_df(result.split.sparkSession, result.split).coalesce(1).write.mode("overwrite").parquet(f"{path}/fences")


def read_range(spark: SparkSession, path: str, spec: SortSpec, lo, hi) -> DataFrame:
    """Rows of a fenced table whose first key (ascending) lies in [lo, hi]: the fences choose the buckets."""
    fences = FenceSet.of(spec, spark.read.parquet(f"{path}/fences"))
    keys = [f["k0"] for f in fences.records]
    first = sum(1 for k in keys if k is not None and k < lo)
    last = sum(1 for k in keys if k is not None and k <= hi)
    return spark.read.parquet(f"{path}/rows").where(F.col("bucket").between(first, last) & F.col("k0").between(lo, hi))


def write_bucketed(df: DataFrame, table: str, n: int, *cols: str) -> None:
    """A Spark table bucketed and sorted by cols, for joins without a shuffle."""
    df.write.mode("overwrite").bucketBy(n, *cols).sortBy(*cols).saveAsTable(table)


def write_any(df: DataFrame, path: str, fmt: str, **options) -> None:
    df.write.mode("overwrite").format(fmt).options(**options).save(path)
