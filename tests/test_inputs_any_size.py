"""Inputs and bounds beside plain Python on tables whose size is not the one written out in their SQL."""

from __future__ import annotations

import bisect
import math
from hashlib import md5

import duckdb
import pytest

from evenlane.queries import QUERIES

SMALL = "/root/testdata/sf0.001"
P, R, TOP = 8, 4, 2**31


def rows_of(table: str) -> int:
    return duckdb.execute(f"select count(*) from '{SMALL}/{table}.parquet'").fetchall()[0][0]


def draw(*parts) -> int:
    return int(md5("|".join(map(str, parts)).encode()).hexdigest()[:8], 16) % TOP


def halving(level: float, left: int, at: int) -> int:
    """The level that place at of left places holds: half hold the first, half of the rest the next, and so on."""
    before = 0
    while left > 1 and at >= before + left // 2:
        before, left, level = before + left // 2, left - left // 2, level - 1
    return math.floor(level)


def key(kind: str, n: int, ord_: int, lane: int, pos: int, length: int) -> int:
    h, width = [draw(21 + 1001 * lane, ord_, j) for j in range(4)], TOP // P
    if kind == "uniform":
        return h[0]
    if kind == "gauss":
        return sum(h) // 4
    if kind == "bucket":
        return pos * P // length * width + h[0] % width
    if kind == "group":
        return (lane // 2 * 2 + P // 2 + pos * 2 // length) % P * width + h[0] % width
    if kind == "stagger":
        return (2 * lane + 1 if lane < P // 2 else lane - P // 2) * width + h[0] % width
    if kind == "dupes":
        if lane < P - 1:
            return halving(math.log2(n), P, lane)
        inner = next((j for j in range(8) if pos < length - length // 2 ** (j + 1)), 8)
        return max(0, math.floor(math.log2(n) - math.log2(P) - inner))
    if kind == "zipf":
        return 64 // (1 + h[0] % 64)
    if kind == "random_dupes":
        return h[0] % (1 + draw(21 + 1001 * lane, 0, 9) % 32)
    if kind == "equal":
        return 1
    x = n // (R * P * P)  # worst
    each, more = divmod(R * P, P - 1)
    below = (each + (lane <= more)) * x
    if lane == 0:
        return TOP // 4 + pos
    if pos < below:
        return lane * 1_000_000 + pos
    return TOP // 4 - 1_000_000 + lane * 10_000 + pos - below if pos < below + x - 1 else TOP // 2 + lane * 1_000_000 + pos


def made(kind: str) -> list[tuple[int, int, int, int]]:
    """Rows (ord, lane, pos0, key) for all rows of lineitem; the worst input ends at the last whole segment."""
    n = rows_of("lineitem")
    n = n // (R * P * P) * R * P * P if kind == "worst" else n
    first = [-(-lane * n // P) for lane in range(P + 1)]
    return [(i + 1, i * P // n, i - first[i * P // n], key(kind, n, i + 1, i * P // n, i - first[i * P // n], first[i * P // n + 1] - first[i * P // n])) for i in range(n)]


@pytest.mark.parametrize("kind", ["bucket", "dupes", "equal", "gauss", "group", "random_dupes", "stagger", "uniform", "worst", "zipf"])
def test_input_has_all_rows(spark, kind):
    got = sorted(map(tuple, QUERIES[f"input_{kind}"](spark, SMALL).select("ord", "lane", "pos0", "key").collect()))
    assert got == made(kind)


def lanes(keyed: list[tuple]) -> list[list[tuple]]:
    """Sorted lanes of (key, lane, pos) over (place in the input, key)."""
    n = len(keyed)
    runs = [sorted((k, i) for i, k in keyed if i * P // n == lane) for lane in range(P)]
    return [[(k, lane, pos) for pos, (k, _) in enumerate(run)] for lane, run in enumerate(runs)]


def bucket_sizes(runs: list[list[tuple]], sample: list[tuple], s: int) -> list[int]:
    """Rows a bucket: every s-th of the sorted sample is a fence, and a bucket is what lies up to its fence."""
    fences, sizes = sorted(sample)[s - 1 :: s][: P - 1], [0] * P
    for run in runs:
        for row in run:
            sizes[bisect.bisect_left(fences, row)] += 1
    return sizes


def regular(runs: list[list[tuple]]) -> list[int]:
    s = R * P
    return bucket_sizes(runs, [run[(j + 1) * len(run) // s - 1] for run in runs for j in range(s)], s)


def drawn(runs: list[list[tuple]], s: int, seed: int) -> list[int]:
    sample = [row for run in runs for row in sorted(run, key=lambda row: (md5(f"{seed}|{row[1]}|{row[2]}".encode()).hexdigest(), row[2]))[:s]]
    return bucket_sizes(runs, sample, s)


def test_sizes_of_all_rows(spark):
    runs = lanes([(o - 1, k) for o, _, _, k in made("bucket")])
    n = rows_of("lineitem")
    want = {("regular", i): x for i, x in enumerate(regular(runs))} | {("random", i): x for i, x in enumerate(drawn(runs, math.ceil(2 * math.log2(n) ** 2), 42))}
    got = {(r.method, r.bucket): r["size"] for r in QUERIES["sizes_input_bucket"](spark, SMALL).collect()}
    assert got == want and sum(got.values()) == 2 * n


def test_bound_of_all_rows(spark):
    got = {r.input: r for r in QUERIES["bound_regular_check"](spark, SMALL).collect()}
    assert len(got) == 10
    for kind, r in got.items():
        rows = made(kind)
        n, x = len(rows), -(-(-(-len(rows) // P)) // (R * P))
        assert r.n_max == max(regular(lanes([(o - 1, k) for o, _, _, k in rows])))
        assert (r.exact, r.safe, r.printed, r.ok) == ((R * P + P - 1) * x, (1 + 1 / R) * n / P + (R + 1) * P, (1 + 1 / R) * n / P + R * P, True)
        if kind == "worst":
            assert r.n_max == R * P * x + (P - 1) * (x - 1)


def test_claim_rate_of_all_rows(spark):
    prices = [x[0] for x in duckdb.execute(f"select o_totalprice from '{SMALL}/orders.parquet' order by o_orderkey").fetchall()]
    runs, n, eps = lanes(list(enumerate(prices))), len(prices), 0.5

    def enough(s: int) -> bool:
        m = P * s - 1
        return s >= (1 + eps) / eps**2 * (2 * math.log(n) + math.log(2 * math.pi * P * P * m) + 1 / (3 * m))

    s = next(s for s in range(1, n) if enough(s))
    over = sum(max(drawn(runs, s, seed)) > (1 + eps) * (n - P + 1) / P for seed in range(1, 21))
    (r,) = QUERIES["claim_rate"](spark, SMALL).collect()
    assert tuple(r) == (s, eps, 1.0, 20, over, round(1 / n, 9))
