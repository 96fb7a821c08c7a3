"""Merging the sorted blocks that reach a bucket, instead of sorting it: by a heap, or fold by fold."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from evenlane.operators.sorts import SortResult
from evenlane.shipping import ship


def heap_order(runs: list[np.ndarray]) -> np.ndarray:
    """The stable order of all rows of several ascending runs, laid end to end, by a heap over the runs' heads."""
    starts = np.cumsum([0, *[len(r) for r in runs]])
    tagged = [zip(r.tolist(), range(a, a + len(r)), strict=True) for r, a in zip(runs, starts, strict=False)]
    return np.fromiter((i for _, i in heapq.merge(*tagged)), np.int64, int(starts[-1]))


def fold_order(runs: list[np.ndarray]) -> np.ndarray:
    """The same by merging neighbours in pairs, lg(runs) times: each pass moves every row once."""
    starts = np.cumsum([0, *[len(r) for r in runs]])
    parts = [(r, np.arange(a, a + len(r))) for r, a in zip(runs, starts, strict=False)]
    while len(parts) > 1:
        merged = []
        for (a, i), (b, j) in zip(parts[::2], parts[1::2], strict=False):
            at_b = np.searchsorted(a, b, side="right") + np.arange(len(b))  # equal keys: the earlier run first
            out, order = np.empty(len(a) + len(b), np.result_type(a, b)), np.empty(len(a) + len(b), np.int64)
            from_a = np.ones(len(out), bool)
            from_a[at_b] = False
            out[at_b], order[at_b] = b, j
            out[from_a], order[from_a] = a, i
            merged.append((out, order))
        parts = merged + ([parts[-1]] if len(parts) % 2 else [])
    return parts[0][1] if parts else np.empty(0, np.int64)


def merged(result: SortResult, *columns: str, how: str = "heap") -> DataFrame:
    """Rows (bucket, place, columns...) of a result with a single ascending number, date or time as key and no nulls, place 0-based in its bucket.

    The routed blocks are read in the order of lanes, each sorted as its run is, and merged in Python; a bucket
    must fit in a worker's memory. For runs that are sorted before the route: layouts by content and physical ones.
    """
    if result.run.inplace:
        raise ValueError("lanes in place have no sorted runs to merge")
    ship(result.split.sparkSession)
    order = {"heap": heap_order, "fold": fold_order}[how]
    blocks = result.routed.sortWithinPartitions("lane", "pos").select("bucket", "k0", "lane", *columns)
    kinds = dict(blocks.dtypes)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        parts = [f for f in frames if len(f)]
        if not parts:
            return
        rows = pd.concat(parts, ignore_index=True)
        cuts = np.flatnonzero(np.diff(rows["lane"].to_numpy())) + 1
        out = rows.iloc[order(np.split(rows["k0"].to_numpy(), cuts))]
        yield pd.DataFrame({"bucket": out["bucket"].to_numpy(), "place": np.arange(len(out)), **{c: out[c].to_numpy() for c in columns}})

    return blocks.mapInPandas(run, ", ".join(["bucket int", "place long", *[f"{c} {kinds[c]}" for c in columns]]))
