"""Token ids of whole texts with public tokenizer files, as the library gives them.

Byte-pair merges never cross pre-tokens, so each distinct pre-token goes to the library once a worker
and is looked up after that. Texts of plain characters (ASCII without apostrophes, Latin letters) are
cut into pre-tokens on the Arrow buffer with array operations, and looked up by a 64-bit hash in an
open-addressing table of bounded size. All other texts, and those that hold a special token's string,
go to the library whole.
"""

from __future__ import annotations

import os

import numpy as np
import pyarrow as pa

from evenlane.llm.common import mix64

U64 = np.uint64
CHUNK = 1 << 20  # bytes of text worked on at once, if no single text is longer
_LOADED: dict[tuple[str, int], PieceTable] = {}

# Byte classes: white space, letter, digit, other; 9 marks bytes that make a text not plain.
_SPACE, _LETTER, _DIGIT, _OTHER, _ODD = 0, 1, 2, 3, 9
_CLASS = np.full(256, _ODD, np.uint8)
_CLASS[33:127] = _OTHER
_CLASS[48:58] = _DIGIT
for _a, _b in ((65, 91), (97, 123), (0x80, 0xC0), (0xC3, 0xC6)):  # with C3 to C5, letters U+00C0 to U+017F
    _CLASS[_a:_b] = _LETTER
_CLASS[[9, 10, 13, 32]] = _SPACE
_CLASS[39] = _ODD


def default_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class IdTable:
    """Open addressing from 64-bit keys to runs of ids, cleared when more than half full."""

    def __init__(self, bits: int = 20) -> None:
        self.bits = bits
        self.clear()

    def clear(self) -> None:
        size = 1 << self.bits
        self.keys, self.start, self.count = np.zeros(size, U64), np.zeros(size, np.int32), np.zeros(size, np.int32)
        self.ids, self.used, self.filled = np.zeros(1 << 18, np.uint32), 0, 0

    def find(self, h: np.ndarray) -> np.ndarray:
        """Slot of each key, -1 where it is missing."""
        mask = U64((1 << self.bits) - 1)
        slot = (h & mask).astype(np.int64)
        got = self.keys[slot]
        out = np.where(got == h, slot, -1)
        left = np.flatnonzero((got != h) & (got != 0))
        while len(left):
            slot[left] = (slot[left] + 1) & int(mask)
            got = self.keys[slot[left]]
            same = got == h[left]
            out[left[same]] = slot[left[same]]
            left = left[~same & (got != 0)]
        return out

    def add(self, h: np.ndarray, ids: np.ndarray, counts: np.ndarray) -> None:
        """Insert distinct new keys with their runs, laid end to end in ids."""
        need = self.filled + len(ids)
        if need > len(self.ids):
            self.ids = np.concatenate([self.ids[: self.filled], np.zeros(max(need, 2 * len(self.ids)) - self.filled, np.uint32)])
        self.ids[self.filled : need] = ids
        starts = self.filled + np.cumsum(counts) - counts
        self.filled = need
        self.used += len(h)
        mask = (1 << self.bits) - 1
        todo, slot = np.arange(len(h)), (h & U64(mask)).astype(np.int64)
        while len(todo):
            free = self.keys[slot[todo]] == 0
            t = todo[free]
            self.keys[slot[t]] = h[t]  # of several keys for one slot the last one stays
            won = t[self.keys[slot[t]] == h[t]]
            self.start[slot[won]], self.count[slot[won]] = starts[won], counts[won]
            done = np.zeros(len(h), bool)
            done[won] = True
            todo = todo[~done[todo]]
            slot[todo] = (slot[todo] + 1) & mask


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    r, inverse = 0x9E3779B97F4A7C15, pow(0x9E3779B97F4A7C15, -1, 1 << 64)
    out = []
    for x in (r, inverse):
        p = np.ones(n, U64)
        filled = 1
        while filled < n:
            m = min(filled, n - filled)
            p[filled : filled + m] = p[:m] * U64(pow(x, filled, 1 << 64))
            filled += m
        out.append(p)
    return out[0], out[1]


class PieceTable:
    """Encoder for one tokenizers file."""

    def __init__(self, path: str, bits: int = 20) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.special = [x.content.encode() for x in self.tokenizer.get_added_tokens_decoder().values()]
        # byte-level pre-tokenisation keeps a space with the next word; the splitting kind drops white space
        self.glued = type(self.tokenizer.pre_tokenizer).__name__ == "ByteLevel"
        self.table = IdTable(bits)
        self.byte_hash = mix64(np.arange(1, 257, dtype=U64) * U64(0xD6E8FEB86659FD93))
        if not self.glued:  # letters are lower-cased before anything else
            self.byte_hash[65:91] = self.byte_hash[97:123]
        self.powers = _powers(CHUNK + 1)

    def _whole(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _pieces(self, buf: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Starts and ends of the pre-tokens of plain texts laid end to end; first: where the texts start."""
        n = len(buf)
        kind = _CLASS[buf]
        edge = np.ones(n, bool)
        edge[1:] = kind[1:] != kind[:-1]
        edge[first] = True
        if not self.glued:
            edge |= kind == _DIGIT
            start = np.flatnonzero(edge)
            end = np.append(start[1:], n)
            word = kind[start] != _SPACE
            return start[word], end[word]
        head = np.zeros(n + 1, bool)
        head[first] = True
        head = head[:n]
        begin = edge & (kind != _SPACE)
        after_space = np.zeros(n, bool)
        after_space[1:] = (buf[:-1] == 32) & ~head[1:]
        mark = edge & ~(begin & after_space)
        # of white space before a word the last character stands apart: alone, or as the word's space
        last = np.flatnonzero(begin[1:] & (kind[:-1] == _SPACE) & ~head[1:])
        mark[last] = True
        start = np.flatnonzero(mark)
        return start, np.append(start[1:], n)

    def _learn(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of distinct pre-tokens, end to end, and how many each has; plain words go as one text."""
        texts = [w.decode() for w in words]
        ids: list[np.ndarray | None] = [None] * len(texts)
        run = [i for i, t in enumerate(texts) if (t[1:].isalpha() if self.glued else t.isalpha()) and (not self.glued or t[0] == " ")]
        for at in range(0, len(run), 4000):
            part = run[at : at + 4000]
            e = self.tokenizer.encode(("" if self.glued else " ").join(texts[i] for i in part), add_special_tokens=False)
            of, got = np.array(e.word_ids, np.int64), np.array(e.ids, np.uint32)
            cuts = np.flatnonzero(np.diff(of)) + 1
            if len(cuts) + 1 == len(part):
                for i, x in zip(part, np.split(got, cuts), strict=True):
                    ids[i] = x
        rest = [i for i, x in enumerate(ids) if x is None]
        for i, x in zip(rest, self._whole([texts[i] for i in rest]) if rest else [], strict=True):
            ids[i] = x
        return np.concatenate([*ids, np.empty(0, np.uint32)]), np.array([len(x) for x in ids], np.int64)

    def _plain(self, buf: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of non-empty plain texts laid end to end, and how many each has."""
        first = np.concatenate([[0], ends[:-1]])
        start, end = self._pieces(buf, first)
        power, inverse = self.powers if len(buf) <= CHUNK else _powers(len(buf) + 1)
        total = np.zeros(len(buf) + 1, U64)
        np.cumsum(self.byte_hash[buf] * power[: len(buf)], out=total[1:])
        h = mix64((total[end] - total[start]) * inverse[start] + (end - start).astype(U64))
        h[h == 0] = U64(1)
        if self.table.used > 1 << (self.table.bits - 1):
            self.table.clear()
        slot = self.table.find(h)
        lost = np.flatnonzero(slot < 0)
        if len(lost):
            new, at = np.unique(h[lost], return_index=True)
            raw = buf.tobytes()
            words = [raw[a:b] for a, b in zip(start[lost[at]].tolist(), end[lost[at]].tolist(), strict=True)]
            self.table.add(new, *self._learn(words))
            slot[lost] = self.table.find(h[lost])
        count = self.table.count[slot].astype(np.int64)
        stop = np.cumsum(count)
        ids = self.table.ids[np.repeat(self.table.start[slot] - (stop - count), count) + np.arange(int(stop[-1]) if len(stop) else 0)]
        before = np.concatenate([[0], stop])
        return ids, np.diff(before[np.append(np.searchsorted(start, first), len(start))])

    def encode_column(self, column: pa.Array) -> list[np.ndarray]:
        """Ids (uint32) of each text, null as empty, without begin, end or added special tokens."""
        column = column.fill_null("").cast(pa.large_string())
        n = len(column)
        offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
        data = np.frombuffer(column.buffers()[2] or b"", np.uint8)
        out: list[np.ndarray] = [np.empty(0, np.uint32)] * n
        at = 0
        while at < n:
            stop = max(at + 1, int(np.searchsorted(offsets, offsets[at] + CHUNK, side="right")) - 1)
            buf = data[offsets[at] : offsets[stop]]
            size = np.diff(offsets[at : stop + 1])
            if len(buf):
                odd = np.concatenate([[0], np.cumsum(self._odd(buf))])
                edges = offsets[at : stop + 1] - offsets[at]
                plain = odd[edges[1:]] == odd[edges[:-1]]
                raw = buf.tobytes()
                for s in self.special:
                    if s in raw:
                        plain &= ~np.array([s in raw[a:b] for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)])
                odd_ones = np.flatnonzero(~plain)
                if len(odd_ones):
                    for i, ids in zip(odd_ones, self._whole([raw[edges[i] : edges[i + 1]].decode() for i in odd_ones]), strict=True):
                        out[at + i] = ids
                good = np.flatnonzero(plain & (size > 0))
                if len(good):
                    text = buf if len(good) == len(size) else buf[np.repeat(plain, size)]
                    ids, counts = self._plain(text, np.cumsum(size[good]))
                    for i, x in zip(good, np.split(ids, np.cumsum(counts)[:-1]), strict=True):
                        out[at + i] = x
            at = stop
        return out

    def _odd(self, buf: np.ndarray) -> np.ndarray:
        odd = _CLASS[buf] == _ODD
        sign = (buf[1:] == 0x97) | (buf[1:] == 0xB7)  # multiplication and division signs among the letters
        odd[1:] |= sign & (buf[:-1] == 0xC3)
        odd[1:] |= (buf[1:] == 0xB0) & (buf[:-1] == 0xC4)  # dotted capital I, whose lower case is two characters
        return odd

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        return self.encode_column(pa.array(texts, pa.string()))


def encoder(path: str, bits: int = 20) -> PieceTable:
    """The encoder of a file with a table of 2^bits slots, one a worker process."""
    if (path, bits) not in _LOADED:
        _LOADED[path, bits] = PieceTable(path, bits)
    return _LOADED[path, bits]
