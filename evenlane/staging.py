"""Tables in the cluster's shared folder: they cut lineage and survive lost executors."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN_DIRS: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder (spark.checkpoint.dir); where it is unset, as in tests, a temporary one, which only local sessions share."""
    base = spark.conf.get("spark.checkpoint.dir", "") or ""
    if base:
        return f"{base.rstrip('/')}/evenlane/{spark.sparkContext.applicationId}"
    app = spark.sparkContext.applicationId
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    if app not in _OWN_DIRS:
        _OWN_DIRS[app] = tempfile.mkdtemp(prefix="evenlane-")
        atexit.register(shutil.rmtree, _OWN_DIRS[app], True)
    return f"file://{_OWN_DIRS[app]}"


def fresh_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex[:12]}"


def stage(df: DataFrame, tag: str) -> DataFrame:
    """Write df to the shared folder and read it back."""
    path = fresh_path(df.sparkSession, tag)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._staged_path = path
    return out


#: Plan nodes that give the same rows in the same partitions at each reading, so long as the files stay.
_STEADY = ("Project", "Filter", "LogicalRelation", "DataSourceV2ScanRelation", "Range", "LocalRelation", "Union", "Generate", "LogicalRDD", "OneRowRelation", "SubqueryAlias")


def steady(df: DataFrame) -> bool:
    """Whether df is a plain scan: places of rows in its partitions can be computed again."""

    def plain(node) -> bool:
        name = node.nodeName().split()[0]
        if name == "InMemoryRelation":
            return "Exchange" not in node.cachedPlan().toString()
        kids = node.children()
        return (name in _STEADY or "Scan" in name) and all(plain(kids.apply(i)) for i in range(kids.size()))

    return plain(df._jdf.queryExecution().optimizedPlan())


def stable(df: DataFrame, tag: str) -> DataFrame:
    """df itself where it is a plain scan, else a table of it: for what reads rows by their places more than once."""
    return df if steady(df) else stage(df, tag)


def _delete(spark: SparkSession, path: str) -> None:
    sc = spark.sparkContext
    where = sc._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(sc._jsc.hadoopConfiguration()).delete(where, True)


def discard(df: DataFrame) -> None:
    """Delete a staged table that nothing will read again."""
    path = getattr(df, "_staged_path", None)
    if path:
        _delete(df.sparkSession, path)


def clear(spark: SparkSession) -> None:
    """Delete all that this application staged: to be called once its results are written elsewhere."""
    _delete(spark, shared_dir(spark))
