"""Exact top-k by distributed histogram selection.

Queries and candidates are packed into blocks; every query block meets every candidate block once and
scores all of it. A block hands on each query's k best scores of its own, since no other of its rows can
be among the k best of all. Per query, a histogram of these scores over the range still in question is summed over
all blocks; it locates the bucket of the kth value, the next level refines that bucket, and once it is one
value wide all rows above it are kept, with as many of those equal to it, by smallest id, as are missing.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evenlane.llm.common import ship, trimmed
from evenlane.staging import discard, stage

LEVEL_BITS = 12


def quantised(rows: DataFrame, id_col: str, vector_col: str, scale: int = 256) -> DataFrame:
    """A table of rows (row, id, v): v is floor(scale * x) of each component, row a number of the row's own.

    Vectors null or with null or non-finite parts are left out; empty ones, and rows that share an id or have
    none, stay.
    """
    v = F.col(vector_col)
    fine = ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    whole = rows.where(v.isNotNull() & fine)
    return stage(whole.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).cast("long").alias("id"), F.transform(v, lambda x: F.floor(x.cast("double") * scale)).alias("v")), "top-vectors")


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(flat) else np.zeros((len(column), 0), np.int64)


def _scores(q: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Exact inner products as int64: in doubles where no sum can pass 2^53."""
    if q.shape[1] * float(np.abs(q).max(initial=0)) * float(np.abs(c).max(initial=0)) < 2**53:
        return np.rint(q.astype(np.float64) @ c.astype(np.float64).T).astype(np.int64)
    return q @ c.T


def _best(k: int):
    """Each query's k best candidates of a block: by score, then smallest id (null last), then row."""
    schema = pa.schema([("q", pa.int64()), ("row", pa.int64()), ("id", pa.int64()), ("score", pa.int64())])

    def run(batches):
        for b in batches:
            for i in range(b.num_rows):
                qs, cs = b.column("qs").slice(i, 1).flatten(), b.column("cs").slice(i, 1).flatten()
                asked, rows, ids = qs.field(0).to_numpy(), cs.field(0).to_numpy(), cs.field(1)
                none = np.asarray(ids.is_null())
                names = ids.fill_null(0).to_numpy()
                order = np.lexsort((rows, names, none))  # ties fall in this order
                place = np.empty(len(order), np.int64)
                place[order] = np.arange(len(order))
                s = _scores(_matrix(qs.field(1)), _matrix(cs.field(2)))
                out_q, out_at = [], []
                for j, q in enumerate(asked):
                    at = np.flatnonzero(rows != q)
                    if len(at) > k:
                        least = np.partition(s[j][at], len(at) - k)[len(at) - k]
                        over, tie = at[s[j][at] > least], at[s[j][at] == least]
                        at = np.concatenate([over, tie[np.argsort(place[tie], kind="stable")[: k - len(over)]]])
                    out_q.append(np.full(len(at), j))
                    out_at.append(at)
                j, at = np.concatenate(out_q), np.concatenate(out_at)
                yield pa.RecordBatch.from_arrays([pa.array(asked[j]), pa.array(rows[at]), ids.take(pa.array(at)), pa.array(s[j, at])], schema=schema)

    return trimmed(run)


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, query_block: int = 256, block: int = 2048) -> DataFrame:
    """Rows (query_id, rank, vec_id, score): for each query row its k highest inner products.

    Both inputs are tables from quantised(), queries usually a part of vectors: a row is no candidate for
    itself, and every other row is, whatever its id. Fewer than k candidates give fewer rows; ties go to
    the smaller id, null ids last; vectors of unlike length are never compared. Empty vectors score 0.
    """
    spark = vectors.sparkSession
    ship(spark)
    n, m = vectors.count(), queries.count()
    n_blocks, n_groups = max(1, -(-n // block)), max(1, -(-m // query_block))
    # a block's name holds its dimension; blocks of candidates stay where they are, and the smaller blocks of queries go to each of them
    named = lambda number: F.concat_ws("/", number.cast("string"), F.size("v").cast("string"))
    packed = vectors.groupBy(named(F.pmod(F.xxhash64("row"), F.lit(n_blocks))).alias("g")).agg(F.collect_list(F.struct("row", "id", "v")).alias("cs"))
    asked = queries.groupBy(F.pmod(F.xxhash64("row"), F.lit(n_groups)).alias("h"), F.size("v").alias("dim")).agg(F.collect_list(F.struct("row", "v")).alias("qs"))
    sent = asked.withColumn("b", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n_blocks - 1).cast("long")))).select(F.concat_ws("/", F.col("b").cast("string"), F.col("dim").cast("string")).alias("g"), "qs")
    tasks = max(1, min(20_000, 2 * n_blocks))
    met = sent.repartition(tasks, "g").join(packed.repartition(tasks, "g"), "g").select("qs", "cs")
    best = stage(met.mapInArrow(_best(k), "q long, row long, id long, score long"), "top-best")

    reach = best.agg(F.min("score").alias("lo"), F.max("score").alias("hi")).first()
    low = reach["lo"] or 0
    bits = max(1, ((reach["hi"] or 0) - low + 1).bit_length())
    state = queries.select(F.col("row").alias("q"), F.lit(low).cast("long").alias("lo"), F.lit(k).alias("rem"))
    while bits > 0:
        width = max(0, bits - LEVEL_BITS)
        inside = best.join(state, "q").where((F.col("score") >= F.col("lo")) & (F.col("score") - F.col("lo") < F.lit(1 << bits)))
        counts = inside.groupBy("q", F.shiftright(F.col("score") - F.col("lo"), width).alias("bucket")).agg(F.count("*").alias("n"))
        lists = counts.groupBy("q").agg(F.sort_array(F.collect_list(F.struct("bucket", "n")), asc=False).alias("h"))  # at most 2^LEVEL_BITS a query
        # walk down the buckets: the one where the count reaches rem, and what is left to find in it
        found = F.expr("aggregate(h, named_struct('left', cast(rem as bigint), 'b', cast(null as bigint)), (a, x) -> case when a.b is not null then a when a.left - x.n <= 0 then named_struct('left', a.left, 'b', x.bucket) else named_struct('left', a.left - x.n, 'b', cast(null as bigint)) end)")
        old = state
        j = state.join(lists, "q", "left").withColumn("f", found)
        # without a bucket there are too few candidates: everything from the bottom of the range on is wanted
        hit = F.col("f.b").isNotNull()
        state = stage(j.select("q", F.when(hit, F.col("lo") + F.col("f.b") * F.lit(1 << width)).otherwise(F.col("lo")).cast("long").alias("lo"), F.when(hit, F.col("f.left")).otherwise(F.col("rem")).cast("int").alias("rem")), "top-state")
        discard(old)
        bits = width
    kept = best.join(state, "q").where(F.col("score") >= F.col("lo")).join(queries.select(F.col("row").alias("q"), F.col("id").alias("query_id")), "q")
    w = Window.partitionBy("q").orderBy(F.desc("score"), F.asc_nulls_last("id"), "row")
    return kept.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", F.col("id").alias("vec_id"), "score")


def top_k_query(spark, sf_dir: str) -> DataFrame:
    v = quantised(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), "vec_id", "embedding")
    return top_k(v, v.where("id % 50 = 0"))


TOP_K_SQL = """
WITH v AS (SELECT row_number() OVER () AS r, vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.r AS q, q.vec_id AS query_id, c.r, c.vec_id AS vec_id, CAST(coalesce(list_sum(list_transform(list_zip(q.e, c.e), lambda p: p[1] * p[2])), 0) AS BIGINT) AS score
  FROM v q JOIN v c ON q.r <> c.r AND len(q.e) = len(c.e) WHERE q.vec_id % 50 = 0)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY score DESC, vec_id NULLS LAST, r) AS rank FROM s) WHERE rank <= 5
"""
