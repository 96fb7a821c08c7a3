"""Token-id files compressed by a Re-Pair grammar, a block at a time, with random access.

A shard is one range of doc_id, its bounds approximate quantiles of that column, nulls first; rows whose doc_id is a bound are dealt
over all shards that it touches, so that a frequent doc_id fills several. Blocks hold whole runs of ids in doc_id order.
In each block the frequent adjacent pairs become nonterminals, round after round until none is left: a round counts
all pairs, gives the frequent ones names, and replaces every occurrence that no more frequent pair
overlaps. A block stores the rules, how many ids each nonterminal stands for, and the remaining
symbols, so that ids [a, b) are decoded from the symbols that cover them alone.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evenlane.llm.common import ship, trimmed
from evenlane.llm.tokenizing import default_path, encoder
from evenlane.staging import fresh_path

MAGIC = b"RPB1"
HEAD = struct.Struct("<4sIIIIB")  # magic, ids, terminals, rules, symbols, bytes a symbol
#: A pair must occur so often to get a rule: a rule costs 12 bytes, each replacement saves a symbol of 2.
LEAST = 6
COUNTER_BITS = 20
EXACT_BELOW = 60_000  # so few places are counted by sorting them
_MULTIPLIERS = (0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F, 0x165667B1)


def _pairs_exactly(a: np.ndarray, b: np.ndarray, least: int) -> tuple[np.ndarray, int, np.ndarray]:
    """(rank of each pair, number of ranks, whether the pair is frequent): ranks by falling count; rarer pairs have the number of ranks."""
    key = (a.astype(np.uint64) << np.uint64(32)) | b
    pairs, inverse, counts = np.unique(key, return_inverse=True, return_counts=True)
    good = np.flatnonzero(counts >= least)
    order = good[np.lexsort((good, -counts[good]))]
    rank = np.full(len(pairs), len(order), np.int32)
    rank[order] = np.arange(len(order), dtype=np.int32)
    rank = rank[inverse]
    return rank, len(order), rank < len(order)


def _pairs_by_hash(a: np.ndarray, b: np.ndarray, least: int, turn: int) -> tuple[np.ndarray, int, np.ndarray]:
    """The same from 2^COUNTER_BITS hashed counters: of pairs that share a counter one has the rank, the others wait and count as frequent."""
    m = [np.uint32(_MULTIPLIERS[(turn + i) % len(_MULTIPLIERS)]) for i in (0, 1)]
    h = ((a * m[0] + b * m[1]) >> np.uint32(32 - COUNTER_BITS)).astype(np.int32)
    counts = np.bincount(h, minlength=1 << COUNTER_BITS)
    good = np.flatnonzero(counts >= least)
    good = good[np.lexsort((good, -counts[good]))]
    none = len(good)
    rank_of = np.full(1 << COUNTER_BITS, none, np.int32)
    rank_of[good] = np.arange(none, dtype=np.int32)
    rank = rank_of[h]
    frequent = rank < none
    at = np.flatnonzero(frequent)
    stands = np.zeros(none, np.int64)
    stands[rank[at]] = at
    rep = stands[rank[at]]
    rank[at[(a[at] != a[rep]) | (b[at] != b[rep])]] = none
    return rank, none, frequent


def re_pair(ids: np.ndarray, least: int = LEAST, rounds: int | None = None) -> tuple[int, np.ndarray, np.ndarray]:
    """(first nonterminal, rules as rows of two symbols, remaining symbols) of ids.

    Rounds go on until no pair occurs least times or more. A round takes all frequent pairs at once: an
    occurrence is replaced where its pair ranks before both neighbours' pairs. Only places whose pair was frequent or has a
    symbol of the last round are counted again, since other counts cannot grow. Many places are counted by hashes that
    change from round to round; few, or those where hashes find nothing, exactly, which also decides that no pair is left.
    rounds, if given, ends the grammar earlier.
    """
    first = int(ids.max()) + 1 if len(ids) else 0
    seq = ids.astype(np.uint32)
    rules: list[np.ndarray] = []
    name, turn, stuck = first, 0, False
    alive = np.ones(max(0, len(seq) - 1), bool)
    while len(seq) > 1 and (rounds is None or turn < rounds):
        at = np.flatnonzero(alive)
        a, b = seq[at], seq[at + 1]
        exact = stuck or len(at) < EXACT_BELOW
        rank, none, frequent = _pairs_exactly(a, b, least) if exact else _pairs_by_hash(a, b, least, turn)
        alive[at[~frequent]] = False
        mine = rank < none
        at, rank = at[mine], rank[mine]
        # an occurrence is taken where its pair ranks before both neighbours; of a run of one pair, every second from the first
        place = np.full(len(seq) + 1, none, np.int32)
        place[at + 1] = rank
        taken = (rank < place[at]) & (rank <= place[at + 2])
        ok, rank = at[taken], rank[taken]
        if len(ok):
            apart = np.concatenate([[True], np.diff(ok) > 1])
            ok, rank = ok[apart], rank[apart]
        keep = np.bincount(rank, minlength=none) >= (least + 1) // 2
        ok, rank = ok[keep[rank]], rank[keep[rank]]
        turn += 1
        if not len(ok):
            if exact:
                break
            stuck = True
            continue
        stuck = False
        stands = np.zeros(none, np.int64)
        stands[rank] = ok
        new = np.zeros(none, np.uint32)
        new[keep] = name + np.arange(int(keep.sum()), dtype=np.uint32)
        rules.append(np.stack([seq[stands[keep]], seq[stands[keep] + 1]], 1))
        name += int(keep.sum())
        seq[ok] = new[rank]
        alive[ok] = True
        alive[np.maximum(ok - 1, 0)] = True
        stays = np.ones(len(seq), bool)
        stays[ok + 1] = False
        alive = alive[stays[:-1]] if stays[-1] else alive[stays[:-1]][:-1]
        seq = seq[stays]
    table = np.concatenate(rules) if rules else np.empty((0, 2), np.uint32)
    return first, table, seq


def expansion_lengths(first: int, rules: np.ndarray) -> np.ndarray:
    """How many ids each nonterminal stands for; rules only name earlier ones."""
    size = np.ones(len(rules), np.int64)
    for i, (a, b) in enumerate(rules.tolist()):
        size[i] = (size[a - first] if a >= first else 1) + (size[b - first] if b >= first else 1)
    return size


def pack_block(ids: np.ndarray) -> bytes:
    first, rules, body = re_pair(ids)
    wide = 2 if first + len(rules) <= 65_536 else 4
    kind = f"<u{wide}"
    sizes = expansion_lengths(first, rules).astype("<u4")
    raw = rules.astype("<u4").tobytes() + sizes.tobytes() + body.astype(kind).tobytes()
    return HEAD.pack(MAGIC, len(ids), first, len(rules), len(body), wide) + zstandard.ZstdCompressor(level=1).compress(raw)


def unpack_block(block: bytes, start: int = 0, stop: int | None = None) -> np.ndarray:
    """Ids [start, stop) of a block, expanded from the symbols that cover them."""
    magic, n, first, k, m, wide = HEAD.unpack_from(block)
    if magic != MAGIC:
        raise ValueError("not a token block")
    stop = n if stop is None else min(stop, n)
    raw = zstandard.ZstdDecompressor().decompress(block[HEAD.size :], max_output_size=12 * k + wide * m)
    rules = np.frombuffer(raw, "<u4", 2 * k).reshape(-1, 2)
    sizes = np.frombuffer(raw, "<u4", k, 8 * k)
    seq = np.frombuffer(raw, f"<u{wide}", m, 12 * k).astype(np.uint32)
    lengths = np.ones(m, np.int64)
    big = seq >= first
    lengths[big] = sizes[seq[big] - first]
    ends = np.cumsum(lengths)
    a = int(np.searchsorted(ends, start, side="right"))
    b = int(np.searchsorted(ends, stop, side="left")) + 1
    skip = start - (int(ends[a - 1]) if a else 0)
    seq = seq[a:b]
    if (stop - start) * 8 > n:
        return _expanded_by_table(seq, first, rules, sizes)[skip : skip + stop - start]
    return _expanded(seq, first, rules)[skip : skip + stop - start]


def _expanded(seq: np.ndarray, first: int, rules: np.ndarray) -> np.ndarray:
    """The ids that symbols stand for, a level at a time."""
    while len(seq) and (big := seq >= first).any():
        out = np.repeat(seq, 1 + big)
        at = np.flatnonzero(big) + np.arange(int(big.sum()))
        pair = rules[seq[big] - first]
        out[at], out[at + 1] = pair[:, 0], pair[:, 1]
        seq = out
    return seq


def _expanded_by_table(seq: np.ndarray, first: int, rules: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The same for long stretches: every rule is expanded once, and symbols copy their part."""
    if not len(rules):
        return seq
    flat = _expanded(np.arange(first, first + len(rules), dtype=np.uint32), first, rules)
    begin = np.cumsum(sizes, dtype=np.int64) - sizes
    big = seq >= first
    which = np.where(big, seq, first) - first
    lengths = np.where(big, sizes[which], 1).astype(np.int64)
    ends = np.cumsum(lengths)
    source = np.repeat(np.where(big, begin[which], 0) - (ends - lengths), lengths)
    source += np.arange(len(source))
    out = np.repeat(seq, lengths)
    inside = np.repeat(big, lengths)
    out[inside] = flat[source[inside]]
    return out


def id_blobs(encoded: list[np.ndarray], end: int) -> tuple[pa.Array, pa.Array]:
    """(counts, blobs) of ids with the end id: two bytes an id, or a marker byte and four where one is large."""
    blobs, counts = [], []
    tail2, tail4 = np.array([end], "<u2").tobytes() if end < 65_536 else b"", np.array([end], "<u4").tobytes()
    for x in encoded:
        wide = end >= 65_536 or (len(x) and int(x.max()) >= 65_536)
        blobs.append(b"\xff" + x.astype("<u4").tobytes() + tail4 if wide else x.astype("<u2").tobytes() + tail2)
        counts.append(len(x) + 1)
    return pa.array(counts, pa.int64()), pa.array(blobs, pa.binary())


NULL_ID = -(2**63)  # where rows without a doc_id stand among the bounds


def _ids(path: str, end: int, bounds: np.ndarray):
    schema = pa.schema([("shard", pa.int32()), ("doc_id", pa.int64()), ("ids", pa.binary())])

    def run(batches):
        enc = encoder(path, 21)
        turn = 0
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                b = whole.slice(at, 1024)
                _, blobs = id_blobs(enc.encode_column(b.column(1)), end)
                ids = b.column(0).fill_null(NULL_ID).to_numpy(zero_copy_only=False)
                low, high = np.searchsorted(bounds, ids, side="left"), np.searchsorted(bounds, ids, side="right")
                shard = low + (turn + np.arange(len(ids))) % (high - low + 1)
                turn += len(ids)
                yield pa.RecordBatch.from_arrays([pa.array(shard.astype(np.int32)), b.column(0), blobs], schema=schema)

    return trimmed(run)


def widen(blob: bytes) -> np.ndarray:
    """uint32 ids from a staged blob: two bytes an id, or a marker byte and four."""
    return np.frombuffer(blob[1:], "<u4") if len(blob) % 2 else np.frombuffer(blob, "<u2").astype("<u4")


def partitions_for(total: int, each: int, most: int = 20_000) -> int:
    return max(1, min(most, -(-total // each)))


def _blocks(block_ids: int):
    schema = pa.schema([("shard", pa.int32()), ("block", pa.int32()), ("block_start", pa.int64()), ("n_ids", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("lengths", pa.list_(pa.int64())), ("data", pa.binary())])

    def run(batches):
        shard, block, start = None, 0, 0
        docs, sizes, held, n = [], [], [], 0

        def flush():
            nonlocal block, start, docs, sizes, held, n
            row = [[shard], [block], [start], [n], [docs], [sizes], [pack_block(np.concatenate(held))]]
            block, start, docs, sizes, held, n = block + 1, start + n, [], [], [], 0
            return pa.RecordBatch.from_arrays([pa.array(v, f.type) for v, f in zip(row, schema, strict=True)], schema=schema)

        for b in batches:
            for k, d, blob in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                if k != shard:
                    if docs:
                        yield flush()
                    shard, block, start = k, 0, 0
                ids = widen(blob)
                docs.append(d)
                sizes.append(len(ids))
                held.append(ids)
                n += len(ids)
                if n >= block_ids:
                    yield flush()
        if docs:
            yield flush()

    return trimmed(run)


BLOCKS = "shard int, block int, block_start long, n_ids long, doc_ids array<long>, lengths array<long>, data binary"
INDEX = "doc_id long, shard int, block int, at long, n_tokens long"


def write_token_files(docs: DataFrame, out_path: str, tokenizer_path: str | None = None, end: int = 2, shard_docs: int = 4_096, block_ids: int = 1 << 20, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Write the ids of docs to out_path/blocks in ascending doc_id order, nulls first, and an index to out_path/index.

    One row of the blocks is one block (its shard, number, first id within the shard, ids, documents and
    their lengths, and the packed data); one row of the index says where a document begins in its block. A document
    never spans blocks; one longer than block_ids makes a larger block. Repeated doc_ids keep one entry for
    each row. Other columns are ignored, whatever their names. An empty table writes no blocks. Beyond 20,000 shards' worth of
    documents shards grow; a task still holds no more than one block.
    """
    ship(docs.sparkSession)
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    n = partitions_for(src.count(), shard_docs)
    cuts = [i / n for i in range(1, n)]
    bounds = src.agg(F.percentile_approx(F.coalesce("doc_id", F.lit(NULL_ID)), cuts, 10 * n).alias("b")).first()["b"] if cuts else None
    rows = src.mapInArrow(_ids(tokenizer_path or default_path("byte_bpe_50k.json"), end, np.array(bounds or [], np.int64)), "shard int, doc_id long, ids binary")
    dealt = rows.repartitionById(n, "shard").sortWithinPartitions("shard", "doc_id")
    dealt.mapInArrow(_blocks(block_ids), BLOCKS).write.parquet(f"{out_path}/blocks")
    files = docs.sparkSession.read.schema(BLOCKS).parquet(f"{out_path}/blocks")
    files.select("shard", "block", "doc_ids", "lengths").mapInArrow(_index, INDEX).write.parquet(f"{out_path}/index")


def _index(batches):
    schema = pa.schema([("doc_id", pa.int64()), ("shard", pa.int32()), ("block", pa.int32()), ("at", pa.int64()), ("n_tokens", pa.int64())])
    for b in batches:
        for shard, block, docs, sizes in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
            n = np.array(sizes, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array([shard] * len(docs), pa.int32()), pa.array([block] * len(docs), pa.int32()), pa.array(np.cumsum(n) - n), pa.array(n)], schema=schema)


def _read(batches):
    schema = pa.schema([("shard", pa.int32()), ("doc_id", pa.int64()), ("at", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])
    for b in batches:
        for shard, at, docs, sizes, data in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
            ids = unpack_block(data)
            ends = np.cumsum(np.array(sizes, np.int64))
            starts = ends - np.array(sizes, np.int64)
            raw = memoryview(ids.astype("<u4").tobytes())
            crc = [zlib.crc32(raw[4 * s : 4 * e]) for s, e in zip(starts.tolist(), ends.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array([shard] * len(docs), pa.int32()), pa.array(docs, pa.int64()), pa.array(starts + at), pa.array(sizes, pa.int64()), pa.array(crc, pa.int64())], schema=schema)


def read_token_files(spark, path: str) -> DataFrame:
    """Rows (doc_id, start, n_tokens, ids_crc32) decoded from the files; start counts all ids before."""
    ship(spark)
    files = spark.read.schema(BLOCKS).parquet(f"{path}/blocks")
    shards = files.groupBy("shard").agg(F.sum("n_ids").alias("ids"))
    before = F.sum("ids").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1))  # at most one row a shard
    offsets = shards.select("shard", F.coalesce(before, F.lit(0)).alias("base"))
    docs = files.select("shard", "block_start", "doc_ids", "lengths", "data").mapInArrow(_read, "shard int, doc_id long, at long, n_tokens long, ids_crc32 long")
    return docs.join(offsets, "shard").select("doc_id", (F.col("base") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")


def ids_of(spark, path: str, doc_id: int) -> list[np.ndarray]:
    """Random access: the ids of every entry of one document, each expanded from the symbols of its block that cover it.

    The index names the blocks, its files' ranges of doc_id skip those without the document, and only these blocks are read.
    """
    hits = spark.read.schema(INDEX).parquet(f"{path}/index").where(F.col("doc_id") == doc_id).orderBy("shard", "block", "at").collect()
    blocks = spark.read.schema(BLOCKS).parquet(f"{path}/blocks").select("shard", "block", "data")
    out, name, data = [], None, b""
    for r in hits:
        if (r.shard, r.block) != name:
            name = (r.shard, r.block)
            data = bytes(blocks.where((F.col("shard") == r.shard) & (F.col("block") == r.block)).first().data)
        out.append(unpack_block(data, r["at"], r["at"] + r.n_tokens))
    return out


def token_files_query(spark, sf_dir: str) -> DataFrame:
    path = fresh_path(spark, "token-files")
    write_token_files(spark.read.parquet(f"{sf_dir}/documents.parquet"), path)
    return read_token_files(spark, path)
