"""Token counts through a digest cache: only texts that no earlier run has counted are encoded.

The cache is a Parquet table of (tokenizer digest, content digest, count). A run looks its distinct
content digests up, encodes one text of each miss, appends the new counts, and joins counts to rows.
Content is normalised by turning null into the empty text and nothing else, since any other change could change the count.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenlane.llm.common import ship, trimmed
from evenlane.llm.tokenizing import default_path
from evenlane.staging import discard, fresh_path, stage

CACHE = "tokenizer binary, content binary, n_tokens long"
_LOADED: dict[str, object] = {}
#: Misses whose digests take at most so many bytes are broadcast, so that only their texts move.
BROADCAST_BYTES = 4_000_000


def tokenizer_digest(path: str) -> bytes:
    with open(path, "rb") as f:
        return hashlib.sha256(f.read()).digest()


def _counter(path: str):
    if path not in _LOADED:
        if path.endswith(".model"):
            import sentencepiece

            sp = sentencepiece.SentencePieceProcessor(model_file=path)
            _LOADED[path] = lambda texts: [len(x) for x in sp.encode(texts, num_threads=1)]
        else:
            from evenlane.llm.tokenizing import encoder

            _LOADED[path] = lambda texts: [len(x) for x in encoder(path).encode(texts)]
    return _LOADED[path]


def _encode(path: str, version: bytes):
    schema = pa.schema([("tokenizer", pa.binary()), ("content", pa.binary()), ("n_tokens", pa.int64())])

    def run(batches):
        count = _counter(path)
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                b = whole.slice(at, 512)
                n = count(b.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([pa.array([version] * len(n), pa.binary()), b.column(0), pa.array(n, pa.int64())], schema=schema)

    return trimmed(run)


def read_cache(spark: SparkSession, cache_path: str) -> DataFrame:
    """The cache, empty where no run has written it yet."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(cache_path)
    if not where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where):
        return spark.createDataFrame([], CACHE)
    return spark.read.schema(CACHE).parquet(cache_path)


def token_counts(docs: DataFrame, cache_path: str, tokenizer_path: str | None = None, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, n_bytes, n_tokens, over_limit), one for each input row; appends to the cache.

    Null and empty texts count alike. Repeated rows and copies are encoded once. A null doc_id stays
    null; an empty table gives an empty result and appends nothing. Other columns are ignored. Two runs
    that append the same digest are harmless: lookups take one count of each.
    """
    spark = docs.sparkSession
    ship(spark)
    path = tokenizer_path or default_path("piece_bpe_32k.model")
    version = tokenizer_digest(path)
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    src = src.withColumn("content", F.unhex(F.sha2("text", 256)))
    seen = stage(src.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), "content"), "count-digests")
    mine = F.col("tokenizer") == F.lit(version)
    misses = stage(seen.select("content").distinct().join(read_cache(spark, cache_path).where(mine), "content", "left_anti"), "count-misses")
    n = misses.count()
    if n:
        texts = src.select("content", "text")
        if 48 * n <= BROADCAST_BYTES:
            one = texts.join(F.broadcast(misses), "content", "left_semi").groupBy("content").agg(F.first("text").alias("text"))
        else:
            one = texts.groupBy("content").agg(F.first("text").alias("text")).join(misses, "content", "left_semi")
        one.mapInArrow(_encode(path, version), CACHE).write.mode("append").parquet(cache_path)
    discard(misses)
    wanted = seen.select("content").distinct()
    known = stage(read_cache(spark, cache_path).where(mine).join(wanted, "content", "left_semi").groupBy("content").agg(F.min("n_tokens").alias("n_tokens")), "count-known")
    return seen.join(known, "content").select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))


def token_counts_query(spark, sf_dir: str) -> DataFrame:
    """Counts with a cache of this run's own, so that every distinct text is encoded here."""
    return token_counts(spark.read.parquet(f"{sf_dir}/documents.parquet"), fresh_path(spark, "count-cache"))
