"""Helpers that the training-data operators share: staging in the shared folder, shipping, components."""

from __future__ import annotations

import contextlib
import ctypes

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenlane.shipping import ship
from evenlane.staging import discard, stage


def trimmed(run):
    """run for mapInArrow, giving freed memory back to the system at the end of each partition."""

    def inner(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(OSError, AttributeError):  # another C library than glibc
                ctypes.CDLL(None).malloc_trim(0)

    return inner


def free_name(taken: list[str], name: str) -> str:
    """name, with underscores added until no column of taken has it (Spark ignores case)."""
    have = {c.lower() for c in taken}
    while name.lower() in have:
        name += "_"
    return name


def by_place(df: DataFrame) -> DataFrame:
    """df with its columns named c0, c1, ...: names of one's own, beginning with "__", cannot clash with them."""
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))])


def utf8(column: pa.Array) -> list[bytes]:
    """Values of a string column as UTF-8 bytes, null as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return [x or b"" for x in column.cast(kind).to_pylist()]


class _WordHash(dict):
    """64-bit hashes of words, worked out at first sight."""

    def __missing__(self, w: bytes) -> int:
        if len(self) > 150_000:
            self.clear()
        h = self[w] = xxhash.xxh3_64_intdigest(w)
        return h


WORD_HASHES = _WordHash()


def mix64(x: np.ndarray) -> np.ndarray:
    """A public 64-bit finaliser (splitmix64 step), elementwise over uint64."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _forest(batches):
    """Reduce the edges of one partition to a spanning forest of its smallest ids."""
    parent: dict[int, int] = {}

    def find(x: int) -> int:
        root = x
        while (up := parent.get(root, root)) != root:
            root = up
        while (up := parent.get(x, x)) != root:
            parent[x] = root
            x = up
        return root

    for b in batches:
        for u, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            a, c = find(u), find(v)
            if a != c:
                parent[max(a, c)] = min(a, c)
    keys = list(parent)
    roots = [find(k) for k in keys]
    kept = [(k, r) for k, r in zip(keys, roots, strict=True) if k != r]
    for i in range(0, len(kept), 50_000):
        part = kept[i : i + 50_000]
        yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in part], pa.int64()), pa.array([x[1] for x in part], pa.int64())], ["u", "v"])


def components(edges: DataFrame, max_rounds: int = 50) -> DataFrame:
    """Connected components of edges (u, v): rows (node, component), component the smallest node.

    Alternates two star contractions until the edge set no longer changes; each round is a
    table in the shared folder. Nodes without edges are absent.
    """
    ship(edges.sparkSession)
    schema = "u long, v long"

    def star(e: DataFrame, large: bool) -> DataFrame:
        both = e if not large else e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        j = both.join(low, "u")
        if large:
            return j.where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v"))
        return j.select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v"))).where("u <> v")

    def same(a: DataFrame, b: DataFrame) -> bool:
        """Whether two tables of distinct edges hold the same ones."""
        return a.count() == b.count() and a.join(b, ["u", "v"], "left_anti").isEmpty()

    e = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v")
    e = stage(e.mapInArrow(_forest, schema).distinct(), "cc")
    for _ in range(max_rounds):
        if e.isEmpty():
            break
        grown = stage(star(e, True).distinct().mapInArrow(_forest, schema), "cc")
        nxt = stage(star(grown.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")), False).distinct(), "cc")
        discard(grown)
        settled = same(nxt, e)
        discard(e)
        e = nxt
        if settled:
            break
    else:
        raise RuntimeError("components did not settle")
    return e.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("component"))
