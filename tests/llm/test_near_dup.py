from __future__ import annotations

import random

import numpy as np
import pytest

from evenlane.llm.common import components
from evenlane.llm.near_dup import NEAR_DUP_SQL, NearDupParams, estimate, minhashes, near_dup_query, near_duplicates, odd_sketches, shingles
from tests.compare import assert_same, tables


def brute(docs: list[tuple]) -> list[tuple]:
    sets = {}
    for i, (_, t) in enumerate(docs):
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w)} if 0 < len(w) < 5 else {tuple(w[j : j + 5]) for j in range(len(w) - 4)}
    parent = list(range(len(docs)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in sets:
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * both >= 75 * len(sets[i] | sets[j]):
                parent[find(i)] = find(j)
    low = {}
    for i in sets:
        low[find(i)] = min(low.get(find(i), docs[i][0]), docs[i][0])
    return sorted((d, len(sets[i]), low[find(i)], low[find(i)] == d) for i, (d, _) in enumerate(docs))


def test_against_brute_force(spark):
    rng = random.Random(3)
    words = [f"w{i}" for i in range(300)]
    docs, n = [], 0
    for _ in range(25):
        base = [rng.choice(words) for _ in range(rng.choice([3, 8, 60, 200]))]
        for _ in range(rng.choice([1, 1, 4, 12])):
            copy = list(base)
            for _ in range(rng.randrange(4)):
                copy[rng.randrange(len(copy))] = rng.choice(words)
            docs.append((n, " ".join(copy).upper() if n % 5 == 0 else "\n".join(copy)))
            n += 1
    docs += [(n, None), (n + 1, ""), (n + 2, " \t\n"), (n + 3, "one two"), (n + 4, "One TWO"), (n + 5, "É é"), (n + 6, "é é"), (n + 7, "x " * 30_000)]
    rng.shuffle(docs)
    got = near_duplicates(spark.createDataFrame(docs, "doc_id long, text string"))
    assert sorted(map(tuple, got.collect())) == brute(docs)


def test_blocks_and_no_first_links(spark):
    """Buckets cut into small blocks, and every link left to the full search."""
    rng = random.Random(5)
    base = [f"w{rng.randrange(500)}" for _ in range(120)]
    docs = []
    for i in range(60):
        copy = list(base)
        for _ in range(3):
            copy[rng.randrange(120)] = f"v{rng.randrange(500)}"
        docs.append((i, " ".join(copy)))
    got = near_duplicates(spark.createDataFrame(docs, "doc_id long, text string"), params=NearDupParams(block=7, best=1, tries=1))
    assert sorted(map(tuple, got.collect())) == brute(docs)


def test_edges(spark):
    df = spark.createDataFrame([(1, "a b c", "x"), (1, "a b c", "y"), (None, "a b c", "z"), (2, "a b c", None)], "doc_id long, text string, kept string")
    got = sorted(near_duplicates(df).collect(), key=str)
    assert [(r.doc_id, r.component_id, r.kept) for r in got if r.doc_id is None] == [(None, 1, False)]
    assert [(r.doc_id, r.component_id, r.kept) for r in got if r.doc_id is not None] == [(1, 1, True), (1, 1, True), (2, 1, False)]
    assert near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_sql(spark, data):
    assert_same(near_dup_query(spark, data), tables(data), NEAR_DUP_SQL)


def test_sketch_estimates():
    rng = np.random.default_rng(1)
    p = NearDupParams()
    u = rng.integers(0, 2**63, 400, dtype=np.uint64)
    m = minhashes(np.concatenate([u[:350], u[50:]]), np.array([0, 350]), p.samples)
    s = odd_sketches(m, p.bits)
    x = int(np.bitwise_count(s[0] ^ s[1]).sum())
    assert abs(float(estimate(np.array([x]), p.samples, p.bits)[0]) - 0.75) < 0.12


def test_shingles():
    assert len(shingles(b"a b c d e f")) == 2
    assert len(shingles(b"a b")) == 1 and len(shingles(b" \n")) == 0
    assert (shingles(b"A B c d E f") == shingles(b"a b\tc d e f")).all()


@pytest.mark.parametrize("n", [2, 50])
def test_components(spark, n):
    rng = random.Random(n)
    edges = [(i, i + 1) for i in range(n)] + [(100 + rng.randrange(30), 100 + rng.randrange(30)) for _ in range(25)]
    parent = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in edges:
        x, y = find(a), find(b)
        parent[max(x, y)] = min(x, y)
    want = {x: find(x) for a, b in edges for x in (a, b) if find(x) != x}
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "u long, v long").repartition(4)).collect()}
    assert {k: v for k, v in got.items() if k != v} == want
