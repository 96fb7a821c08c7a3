"""Packing of documents into training sequences along a space-filling curve.

Each document's token counts are projected by a fixed pseudo-random sign matrix to a few dimensions;
the Hilbert key of the quantised point, continued by a hash of the doc_id so that copies spread over
the range, orders the corpus. Ranges of that order with about equally many ids are packed independently: the ids run on
end to end, cut wherever a sequence is full, and what is left at a partition's end goes into sequences
whose lengths are powers of two, which need no padding.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenlane.llm.common import mix64, ship, trimmed
from evenlane.llm.token_files import id_blobs, partitions_for, widen
from evenlane.llm.tokenizing import default_path, encoder
from evenlane.staging import stage

U64 = np.uint64
DIMS, BITS = 4, 8
_SIGNS: dict[int, np.ndarray] = {}


def projection(ids: list[np.ndarray], end: int, dims: int = DIMS, bits: int = BITS) -> np.ndarray:
    """Quantised points (documents x dims): mean sign vector of the ids and the end id, scaled by a fixed factor."""
    sizes = np.array([len(x) + 1 for x in ids], np.int64)
    stops = np.cumsum(sizes)
    flat = np.full(int(stops[-1]), end, np.int64)
    inner = np.ones(len(flat), bool)
    inner[stops - 1] = False
    flat[inner] = np.concatenate(ids)
    top = int(flat.max()) + 1
    if dims not in _SIGNS or _SIGNS[dims].shape[1] < top:
        h = mix64(np.arange(max(top, 65_536), dtype=U64)[:, None] * U64(dims) + np.arange(dims, dtype=U64)[None, :] + U64(0x9E3779B97F4A7C15))
        _SIGNS[dims] = np.ascontiguousarray((1 - 2 * (h >> U64(63)).astype(np.int8)).astype(np.int8).T)
    mean = np.stack([np.add.reduceat(_SIGNS[dims][d][flat], stops - sizes, dtype=np.int64) for d in range(dims)], 1) / sizes[:, None]
    side = 1 << bits
    return np.clip((mean * 1.5 + 0.5) * side, 0, side - 1).astype(np.int64)


def hilbert_key(points: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Hilbert index of integer points (n x dims), each coordinate of the given bits."""
    x = points.astype(np.int64).T.copy()
    dims = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        p = q - 1
        for i in range(dims):
            high = (x[i] & q) != 0
            swap = np.where(high, 0, (x[0] ^ x[i]) & p)
            x[0] ^= np.where(high, p, swap)
            if i:
                x[i] ^= swap
        q >>= 1
    for i in range(1, dims):
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    q = 1 << (bits - 1)
    while q > 1:
        t ^= np.where((x[-1] & q) != 0, q - 1, 0)
        q >>= 1
    x ^= t
    key = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(dims):
            key = (key << 1) | ((x[i] >> b) & 1)
    return key


def _keyed(path: str, end: int):
    schema = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("key", pa.int64()), ("ids", pa.binary())])
    spread = 62 - DIMS * BITS

    def run(batches):
        enc = encoder(path)
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                b = whole.slice(at, 1024)
                ids = enc.encode_column(b.column(1))
                counts, blobs = id_blobs(ids, end)
                names = b.column(0).fill_null(-1).to_numpy().astype(np.int64).view(U64)
                tail = (mix64(names * U64(0x9E3779B97F4A7C15)) >> U64(64 - spread)).astype(np.int64)
                key = (hilbert_key(projection(ids, end)) << spread) | tail
                yield pa.RecordBatch.from_arrays([b.column(0), counts, pa.array(key), blobs], schema=schema)

    return trimmed(run)


def key_bounds(rows: DataFrame, n: int, unit: int = 1024) -> list[int]:
    """Up to n - 1 keys that cut the rows (key, n) into ranges of like numbers of ids.

    A row weighs its ids: it stands floor((ids + its hash mod unit) / unit) times in a mergeable quantile summary.
    """
    if n < 2:
        return []
    times = F.expr(f"cast((n + pmod(xxhash64(key), {unit})) div {unit} as int)")
    weighed = rows.select("key", F.explode(F.array_repeat(F.lit(0), times)))
    found = weighed.agg(F.percentile_approx("key", [i / n for i in range(1, n)], 10 * n).alias("b")).first()["b"]
    return sorted(set(found or []))


def place(key: str, bounds: list[int]) -> Column:
    """How many of the sorted bounds lie below the key, by binary search."""
    if not bounds:
        return F.lit(0)
    steps = len(bounds).bit_length()
    state = F.struct(F.lit(0).alias("lo"), F.lit(len(bounds)).alias("hi"))

    def step(s: Column, _: Column) -> Column:
        mid = F.shiftright(s["lo"] + s["hi"], 1)
        open_ = s["lo"] < s["hi"]
        below = open_ & (F.get(F.lit(bounds), mid) < F.col(key))
        return F.struct(F.when(below, mid + 1).otherwise(s["lo"]).alias("lo"), F.when(open_ & ~below, mid).otherwise(s["hi"]).alias("hi"))

    return F.aggregate(F.sequence(F.lit(0), F.lit(steps)), state, step, lambda s: s["lo"])


def _packed(length: int):
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64())])

    def run(batches):
        base, local = 0, 0
        #: The open sequence's pieces: its sequences' lengths are known only when it fills or the input ends.
        held: list[tuple] = []
        used = 0

        def rows(pieces: list[tuple], cuts: list[int]):
            """Place pieces end to end into sequences of the given lengths."""
            nonlocal local
            out = [[] for _ in schema]
            room, offset, left = cuts[0], 0, cuts[1:]
            for doc, start, ids, total in pieces:
                while len(ids):
                    take = min(room, len(ids))
                    part = ids[:take]
                    for c, v in zip(out, (doc, start, take, zlib.crc32(part.tobytes()), total, base + local, offset), strict=True):
                        c.append(v)
                    ids, start, room, offset = ids[take:], start + take, room - take, offset + take
                    if not room:
                        local += 1
                        room, offset, left = (left[0] if left else 0), 0, left[1:]
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, schema, strict=True)], schema=schema)

        for b in batches:
            ready: list[tuple] = []
            if b.num_rows:
                base = b.column(4)[0].as_py() << 32  # a partition holds one shard
            for doc, blob in zip(b.column(0).to_pylist(), b.column(3).to_pylist(), strict=True):
                ids = widen(blob)
                held.append((doc, 0, ids, len(ids)))
                used += len(ids)
            whole = used // length
            if whole:
                need = whole * length
                while need:
                    doc, start, ids, total = held[0]
                    if len(ids) <= need:
                        ready.append(held.pop(0))
                        need -= len(ids)
                    else:
                        ready.append((doc, start, ids[:need], total))
                        held[0] = (doc, start + need, ids[need:], total)
                        need = 0
                used -= whole * length
                yield rows(ready, [length] * whole)
        if used:
            yield rows(held, [1 << k for k in range(used.bit_length() - 1, -1, -1) if used >> k & 1])

    return trimmed(run)


def pack(docs: DataFrame, tokenizer_path: str | None = None, end: int = 2, length: int = 4096, shard_ids: int = 4_000_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset), one a piece.

    Null text counts as empty and packs the end id alone; repeated rows are packed each; a null doc_id
    stays null; an empty table packs nothing. Other columns are ignored. A sequence is full, or its
    length is a power of two; sequence_id holds the range's number in its upper half.
    """
    ship(docs.sparkSession)
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    rows = stage(src.mapInArrow(_keyed(tokenizer_path or default_path("word_bpe_49k.json"), end), "doc_id long, n long, key long, ids binary"), "pack-ids")
    total = rows.agg(F.sum("n")).first()[0] or 0
    bounds = key_bounds(rows, partitions_for(total, shard_ids))
    dealt = rows.withColumn("shard", place("key", bounds)).repartitionById(len(bounds) + 1, "shard").sortWithinPartitions("key", "doc_id", F.crc32("ids"))
    return dealt.mapInArrow(_packed(length), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")


def packing_query(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
