"""Unigram encoding and decoding with sentence pieces, by Viterbi over a double-array trie.

Pieces come from a SentencePiece model file; their log scores are either the file's or Zipf estimates
from their rank (files made for merging store ranks, which are no log probabilities). No piece of a
usual model holds a white-space marker after another character, so the best path of a text is the best
paths of its segments, each a run of markers and what follows it; distinct segments are searched once
a worker, many side by side, and models with other pieces have whole texts searched.
"""

from __future__ import annotations

import math
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenlane.llm.common import ship, trimmed
from evenlane.llm.tokenizing import default_path

MARK = "▁"
UNKNOWN_PENALTY = 10.0  # fixed value: how far below the worst piece an unknown character scores
_SEGMENT = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+")
_LOADED: dict[tuple, PieceModel] = {}


def double_array(keys: list[bytes], values: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(base, check, value) of a trie: node s has child t = base[s] + byte + 1 where check[t] = s; value -1: no key ends here."""
    trie: list[dict[int, int]] = [{}]
    ends: list[int] = [-1]
    for k, v in zip(keys, values, strict=True):
        at = 0
        for c in k:
            nxt = trie[at].get(c)
            if nxt is None:
                nxt = trie[at][c] = len(trie)
                trie.append({})
                ends.append(-1)
            at = nxt
        ends[at] = v
    size = 2 * len(trie) + 1024
    base, check, value = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
    used = bytearray(size)
    used[0] = 1
    value[0] = ends[0]
    low = 1
    queue = [(0, 0)]
    for node, at in queue:
        if not trie[node]:
            continue
        codes = sorted(trie[node])
        while used[low]:
            low += 1
        first, b = codes[0], max(low - codes[0] - 1, 0)
        tries = 0
        while any(used[b + c + 1] for c in codes):
            b += 1
            tries += 1
            if tries > 400 and len(codes) > 1:  # a crowded stretch: start later, at a free cell
                low += 64
                b, tries = max(low - first - 1, b), 0
            if b + 258 > size:
                size *= 2
                base, check, value = np.resize(base, size), np.append(check, np.full(size - len(check), -1, np.int32)), np.append(value, np.full(size - len(value), -1, np.int32))
                used.extend(bytes(size - len(used)))
        base[at] = b
        for c in codes:
            t = b + c + 1
            used[t], check[t], value[t] = 1, at, ends[trie[node][c]]
            queue.append((trie[node][c], t))
    return base, check, value


class PieceModel:
    """Pieces, scores and their trie for one model file."""

    def __init__(self, path: str, scores: str = "zipf", keep: int = 600_000, longest: int = 64) -> None:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.vocab_size()
        self.pieces = [sp.id_to_piece(i) for i in range(n)]
        plain = [i for i in range(n) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        if scores == "zipf":
            total = math.log(sum(1 / (r + 2) for r in range(len(plain))))
            self.scores = np.zeros(n, np.float32)
            self.scores[plain] = [-math.log(r + 2) - total for r in range(len(plain))]
        else:
            self.scores = np.array([sp.get_score(i) for i in range(n)], np.float32)
        self.unknown_score = np.float32(self.scores[plain].min() - UNKNOWN_PENALTY)
        self.byte_ids = {int(self.pieces[i][1:-1], 16): i for i in range(n) if sp.is_byte(i)}
        self.byte_of = np.full(n, -1, np.int64)
        for b, i in self.byte_ids.items():
            self.byte_of[i] = b
        self.unk = sp.unk_id()
        self.control = {i for i in range(n) if sp.is_control(i)}
        self.base, self.check, self.value = double_array([self.pieces[i].encode() for i in plain], plain)
        self.depth = max(len(self.pieces[i].encode()) for i in plain)
        self.by_segment = not any(MARK in p.lstrip(MARK) for p in (self.pieces[i] for i in plain))
        self.keep, self.longest = keep, longest
        self.cache: dict[str, bytes] = {}

    def viterbi(self, texts: list[bytes]) -> list[list[int]]:
        """Best paths of normalised texts, all advanced together one byte at a time."""
        n = len(texts)
        lengths = np.array([len(t) for t in texts], np.int64)
        width = int(lengths.max(initial=0))
        codes = np.zeros((n, width + 1), np.int32)
        flat = np.frombuffer(b"".join(texts), np.uint8)
        codes[np.repeat(np.arange(n), lengths), np.arange(len(flat)) - np.repeat(np.cumsum(lengths) - lengths, lengths)] = flat
        best = np.full((n, width + 1), -np.inf, np.float32)
        best[:, 0] = 0
        back, last = np.zeros((n, width + 1), np.int64), np.full((n, width + 1), -1, np.int64)
        head = codes[:, :-1] if width else codes
        size = np.where(head < 0x80, 1, np.where(head < 0xE0, 2, np.where(head < 0xF0, 3, 4)))
        for s in range(width):
            rows = np.flatnonzero((s < lengths) & ((codes[:, s] & 0xC0) != 0x80))
            if not len(rows):
                continue
            one = size[rows, s]
            single = np.zeros(len(rows), bool)
            live, node = np.arange(len(rows)), np.zeros(len(rows), np.int64)
            start = best[rows, s]
            for e in range(s + 1, min(width, s + self.depth) + 1):
                on = lengths[rows[live]] >= e
                live, node = live[on], node[on]
                if not len(live):
                    break
                nxt = self.base[node] + codes[rows[live], e - 1] + 1
                on = (nxt < len(self.check)) & (self.check[np.minimum(nxt, len(self.check) - 1)] == node)
                live, node = live[on], nxt[on].astype(np.int64)
                v = self.value[node]
                hit = np.flatnonzero(v >= 0)
                if len(hit):
                    r = rows[live[hit]]
                    got = start[live[hit]] + self.scores[v[hit]]
                    single[live[hit][one[live[hit]] == e - s]] = True
                    up = got > best[r, e]
                    r, got, v = r[up], got[up], v[hit][up]
                    best[r, e], back[r, e], last[r, e] = got, s, v
            bad = np.flatnonzero(~single)
            if len(bad):
                r, e = rows[bad], s + one[bad]
                got = start[bad] + self.unknown_score
                up = got > best[r, e]
                r, e, got = r[up], e[up], got[up]
                best[r, e], back[r, e], last[r, e] = got, s, self.unk
        out = []
        for i, t in enumerate(texts):
            path, at = [], len(t)
            while at:
                s, v = int(back[i, at]), int(last[i, at])
                if v == self.unk and self.byte_ids:
                    path.extend(self.byte_ids[b] for b in reversed(t[s:at]))
                else:
                    path.append(v)
                at = s
            out.append(path[::-1])
        return out

    def _search(self, segments: list[str]) -> list[bytes]:
        """Ids of segments as little-endian 32-bit bytes, in groups of like length."""
        coded = [s.encode() for s in segments]
        order = sorted(range(len(coded)), key=lambda i: len(coded[i]))
        out: list[bytes] = [b""] * len(coded)
        at = 0
        while at < len(order):
            stop = at + 1
            while stop < len(order) and (stop - at + 1) * (len(coded[order[stop]]) + 1) <= 400_000:
                stop += 1
            group = order[at:stop]
            for i, ids in zip(group, self.viterbi([coded[i] for i in group]), strict=True):
                out[i] = np.array(ids, "<u4").tobytes()
            at = stop
        return out

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        if len(self.cache) > self.keep:
            self.cache.clear()
        cache = self.cache
        split, missing = [], set()
        for t in texts:
            t = MARK + t.replace(" ", MARK) if t else ""
            parts = (_SEGMENT.findall(t) if self.by_segment else [t]) if t else []
            split.append(parts)
            missing.update(parts)
        names = sorted(p for p in missing if p not in cache)
        extra: dict[str, bytes] = {}
        for p, ids in zip(names, self._search(names), strict=True):
            (cache if len(p) <= self.longest else extra)[p] = ids
        return [np.frombuffer(b"".join([cache[p] if p in cache else extra[p] for p in parts] if extra else map(cache.__getitem__, parts)), "<u4") for parts in split]

    def decode(self, ids: np.ndarray) -> str:
        """Text of ids: markers become spaces, the first one goes, byte pieces join into UTF-8."""
        out: list[str] = []
        run = bytearray()
        for i, b in zip(ids.tolist(), self.byte_of[ids].tolist(), strict=True):
            if b >= 0:
                run.append(b)
                continue
            if run:
                out.append(run.decode("utf-8", "replace"))
                run.clear()
            if i not in self.control:
                out.append(" ⁇ " if i == self.unk else self.pieces[i])
        if run:
            out.append(run.decode("utf-8", "replace"))
        text = "".join(out).replace(MARK, " ")
        return text[1:] if text.startswith(" ") else text


def model(path: str, scores: str = "zipf") -> PieceModel:
    if (path, scores) not in _LOADED:
        _LOADED[path, scores] = PieceModel(path, scores)
    return _LOADED[path, scores]


def _coded(path: str, scores: str):
    schema = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32()))])

    def run(batches):
        m = model(path, scores)
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                b = whole.slice(at, 512)
                ids = m.encode([t or "" for t in b.column(1).to_pylist()])
                offsets = np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32)
                flat = np.concatenate([*ids, np.empty(0, "<u4")]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], schema=schema)

    return trimmed(run)


def encode_pieces(docs: DataFrame, path: str | None = None, scores: str = "zipf", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, ids). Null and empty texts have no ids; rows with a null id or repeated are coded alike."""
    ship(docs.sparkSession)
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return src.mapInArrow(_coded(path or default_path("piece_bpe_32k.model"), scores), "doc_id long, ids array<int>")


def decode_pieces(coded: DataFrame, path: str | None = None, scores: str = "zipf") -> DataFrame:
    """Rows (doc_id, text) of rows (doc_id, ids); a null list gives a null text."""
    ship(coded.sparkSession)
    where = path or default_path("piece_bpe_32k.model")
    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string())])

    def run(batches):
        m = model(where, scores)
        for b in batches:
            texts = [None if x is None else m.decode(np.array(x, np.int64)) for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], schema=schema)

    return coded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def _checked(path: str, scores: str):
    schema = pa.schema([("doc_id", pa.int64()), ("n_ids", pa.int64()), ("n_byte_ids", pa.int64()), ("ids_crc32", pa.int64()), ("decoded_sha256", pa.string()), ("round_trip", pa.bool_())])

    def run(batches):
        import hashlib

        m = model(path, scores)
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                b = whole.slice(at, 512)
                texts = [t or "" for t in b.column(1).to_pylist()]
                rows = []
                for t, ids in zip(texts, m.encode(texts), strict=True):
                    back = m.decode(ids)
                    rows.append((len(ids), int((m.byte_of[ids] >= 0).sum()), zlib.crc32(ids.tobytes()), hashlib.sha256(back.encode()).hexdigest(), back == t.replace(MARK, " ")))
                cols = list(zip(*rows, strict=True)) or [[]] * 5
                yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(c, f.type) for c, f in zip(cols, list(schema)[1:], strict=True)]], schema=schema)

    return trimmed(run)


def sentence_pieces_query(spark, sf_dir: str) -> DataFrame:
    """Ids of every document, summed up, and whether they decode to the text again."""
    ship(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    schema = "doc_id long, n_ids long, n_byte_ids long, ids_crc32 long, decoded_sha256 string, round_trip boolean"
    return docs.mapInArrow(_checked(default_path("piece_bpe_32k.model"), "zipf"), schema)
