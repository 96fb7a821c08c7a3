"""Structured Streaming around the sorts: sorted micro-batches, windows, drift of fences, late rows.

Results go to tables in the shared folder, one directory a micro-batch: a batch that is run again after a failure replaces its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec
from evenlane.operators.fences import FenceSet
from evenlane.operators.layout import Lanes
from evenlane.operators.measure import imbalance
from evenlane.operators.sorts import regular_sort
from evenlane.operators.split import with_bucket
from evenlane.staging import fresh_path


def bucketed(batch: DataFrame, spec: SortSpec, fences: FenceSet) -> DataFrame:
    keyed = spec.add(batch).withColumns({"lane": F.lit(0), "pos": F.lit(0).cast("long")})
    return with_bucket(keyed, fences, tagged=False).drop("lane", "pos")


def write_batch(batch: DataFrame, spec: SortSpec, fences: FenceSet, path: str) -> None:
    """Route a batch by the fences, sort it, and write it by bucket."""
    rows = bucketed(batch, spec, fences).repartitionById(len(fences) + 1, "bucket").sortWithinPartitions(*spec.order())
    rows.write.mode("overwrite").partitionBy("bucket").parquet(path)


def sorted_batches(stream: DataFrame, spec: SortSpec, fences: FenceSet, out_path: str, checkpoint: str):
    """Route every micro-batch by fixed fences, sort it, and append it to its buckets under out_path.

    A reader merges the batches of a bucket.
    """

    def put(batch: DataFrame, batch_id: int) -> None:
        write_batch(batch, spec, fences, f"{out_path}/batch={batch_id}")

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint)


def run_once(writer) -> None:
    """Process what there is and stop."""
    query = writer.trigger(availableNow=True).start()
    query.awaitTermination()


def file_stream(spark: SparkSession, path: str, schema, files_each: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_each).parquet(path)


def windowed(stream: DataFrame, ts: str, watermark: str, size: str, slide: str | None = None) -> DataFrame:
    """Counts and sums by tumbling or sliding windows."""
    return stream.withWatermark(ts, watermark).groupBy(F.window(ts, size, slide)).agg(F.count("*").alias("n"), F.sum("value").alias("value"))


def sessions(stream: DataFrame, ts: str, by: str, watermark: str, gap: str) -> DataFrame:
    return stream.withWatermark(ts, watermark).groupBy(F.session_window(ts, gap), by).agg(F.count("*").alias("n"))


def distinct_in_stream(stream: DataFrame, ts: str, watermark: str, *keys: str) -> DataFrame:
    """The first row of each key within the watermark."""
    return stream.withWatermark(ts, watermark).dropDuplicatesWithinWatermark(list(keys))


def _restore(spark: SparkSession, path: str, batch_id: int) -> DataFrame | None:
    """The table that an earlier batch left under path, the last one before batch_id."""
    for i in range(batch_id - 1, -1, -1):
        where = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/batch={i}/_SUCCESS")
        if where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where):
            return spark.read.parquet(f"{path}/batch={i}")
    return None


def drifting_fences(stream: DataFrame, spec: SortSpec, p: int, r: int, out_path: str, checkpoint: str):
    """Sort micro-batches by fences that follow the data.

    A batch whose fullest bucket passes (1 + 1/r) of its share under the fences in force takes fences of its own, which hold
    from then on. Tables under out_path, each by batch: rows, fences (those in force after it) and report (batch, n, imbalance under
    the fences before it, refreshed). Fences are read back from their table, so a restarted stream goes on with them.
    """

    def put(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        held = batch.persist()
        try:
            n = held.count()
            old = _restore(spark, f"{out_path}/fences", batch_id)
            fences = FenceSet.of(spec, old) if old is not None else None
            before = None
            if fences is not None and n:
                sizes = {x["bucket"]: x["count"] for x in bucketed(held, spec, fences).groupBy("bucket").count().collect()}  # one a bucket
                before = imbalance([sizes.get(b, 0) for b in range(p)])
            refreshed = bool(n) and (before is None or before > 1 / r)
            if refreshed:
                fences = regular_sort(held, spec, Lanes(p, layout="inplace"), r=r).fences
            if fences is None:
                return
            write_batch(held, spec, fences, f"{out_path}/rows/batch={batch_id}")
            fences.to_df(spark, spec.add(held)).coalesce(1).write.mode("overwrite").parquet(f"{out_path}/fences/batch={batch_id}")
            report = spark.createDataFrame([(batch_id, n, before, refreshed)], "batch int, n long, imbalance double, refreshed boolean")
            report.coalesce(1).write.mode("overwrite").parquet(f"{out_path}/report/id={batch_id}")
        finally:
            held.unpersist()

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint)


def with_corrections(stream: DataFrame, ts: str, delay: str, spec: SortSpec, fences: FenceSet, out_path: str, checkpoint: str):
    """Sort micro-batches with a watermark; rows older than it, which stateful operators would drop, go out as sorted correction runs.

    The watermark of a batch is the largest ts of the batches before it less delay. Tables under out_path, by batch: rows,
    corrections, and report (batch, in_time, late, until), from which a restarted stream takes its watermark.
    """

    def put(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        old = _restore(spark, f"{out_path}/report", batch_id)
        until = old.first()["until"] if old is not None else None
        late = (F.col(ts) < F.lit(until) - F.expr(f"interval {delay}")) if until is not None else F.lit(False)
        held = batch.withColumn("__late", F.coalesce(late, F.lit(False))).persist()
        try:
            write_batch(held.where("not __late").drop("__late"), spec, fences, f"{out_path}/rows/batch={batch_id}")
            write_batch(held.where("__late").drop("__late"), spec, fences, f"{out_path}/corrections/batch={batch_id}")
            facts = held.agg(F.count_if(~F.col("__late")).alias("in_time"), F.count_if("__late").alias("late"), F.max(ts).alias("m"))
            facts = facts.select(F.lit(batch_id).alias("batch"), "in_time", "late", F.greatest("m", F.lit(until).cast(dict(facts.dtypes)["m"])).alias("until"))
            facts.coalesce(1).write.mode("overwrite").parquet(f"{out_path}/report/batch={batch_id}")
        finally:
            held.unpersist()

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint)


def to_table(spark: SparkSession, stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream over what there is into a table in the shared folder, and return it: all that was appended, or the last complete result."""
    path, seen = fresh_path(spark, "stream-table"), []

    def put(batch: DataFrame, batch_id: int) -> None:
        seen.append(batch_id)
        batch.write.mode("overwrite").parquet(f"{path}/id={batch_id}")

    run_once(stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", fresh_path(spark, "stream")))
    if not seen:
        return spark.createDataFrame([], stream.schema)
    paths = [f"{path}/id={i}" for i in (sorted(set(seen)) if mode == "append" else [max(seen)])]
    return spark.read.schema(stream.schema).parquet(*paths)
