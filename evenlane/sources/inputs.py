"""The benchmark's synthetic inputs, as functions of a row's ordinal: reproducible, and the same in Spark and SQL.

Each has n keys in p lanes of the block layout; pos0 is the position in the lane. Random draws are md5 of
(21 + 1001 lane, ord, draw), 31 bits.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

TOP = 2**31


@dataclass(frozen=True)
class Dialect:
    """How the two engines write a draw and an integer division."""

    spark: bool

    def draw(self, j: int) -> str:
        x = f"concat_ws('|', 21 + 1001 * lane, ord, {j})"
        return f"(cast(conv(substr(md5({x}), 1, 8), 16, 10) as bigint) % 2147483648)" if self.spark else f"(('0x' || substr(md5({x}), 1, 8))::BIGINT % 2147483648)"

    def div(self, a: str, b: str) -> str:
        return f"(({a}) div ({b}))" if self.spark else f"(({a}) // ({b}))"


def expression(kind: str, n: int | str, p: int, d: Dialect, g: int = 2, seg: tuple[int, int] | None = None) -> str:
    """The key as SQL over (ord, lane, pos0, len): len is the lane's length."""
    h = [d.draw(j) for j in range(6)]
    width = TOP // p
    block = d.div(f"pos0 * {p}", "greatest(len, 1)")  # which p-th of the lane
    if kind == "uniform":
        return h[0]
    if kind == "gauss":
        return d.div(" + ".join(h[:4]), "4")
    if kind == "bucket":
        return f"{block} * {width} + {h[0]} % {width}"
    if kind == "group":
        part = d.div(f"pos0 * {g}", "greatest(len, 1)")
        return f"(({d.div('lane', str(g))}) * {g} + {p // 2} + {part}) % {p} * {width} + {h[0]} % {width}"
    if kind == "stagger":
        return f"(CASE WHEN lane < {p // 2} THEN 2 * lane + 1 ELSE lane - {p // 2} END) * {width} + {h[0]} % {width}"
    if kind == "dupes":
        # lane shares 1/2, 1/4, ... hold lg(n), lg(n/2), ...; the last lane goes on halving inside itself
        lg = math.log2(max(2, n))
        cases, left, at, i = [], p, 0, 0
        while left > 1:
            at += left // 2
            left -= left // 2
            cases.append(f"WHEN lane < {at} THEN {math.floor(lg - i)}")
            i += 1
        inner = " ".join(f"WHEN pos0 < len - {d.div('len', str(2 ** (j + 1)))} THEN {max(0, math.floor(lg - i - j))}" for j in range(8))
        return f"CASE {' '.join(cases)} ELSE CASE {inner} ELSE {max(0, math.floor(lg - i - 8))} END END"
    if kind == "worst":
        # lane 0 fills one bucket; each other lane hides x - 1 keys below the bucket's last fence
        r, x = seg
        s = r * p
        each, more = s // (p - 1), s % (p - 1)
        below = f"({each} + CASE WHEN lane <= {more} THEN 1 ELSE 0 END) * {x}"
        return f"CASE WHEN lane = 0 THEN {TOP // 4} + pos0 WHEN pos0 < {below} THEN lane * 1000000 + pos0 WHEN pos0 < {below} + {x - 1} THEN {TOP // 4} - 1000000 + lane * 10000 + pos0 - {below} ELSE {TOP // 2} + lane * 1000000 + pos0 END"
    if kind == "zipf":
        return d.div("64", f"1 + {h[0]} % 64")
    if kind == "random_dupes":
        return f"({h[0]} % (1 + {d.draw(9).replace('ord, 9', '0, 9')} % 32))"
    if kind == "equal":
        return "1"
    raise ValueError(f"unknown input {kind}")


KINDS = ("uniform", "gauss", "bucket", "group", "stagger", "dupes", "worst", "zipf", "random_dupes", "equal")


def worst_segment(n: int, p: int, r: int) -> int:
    return max(1, n // (r * p * p))


def synthetic(ordinals: DataFrame, n: int, kind: str, p: int, r: int = 4) -> DataFrame:
    """Rows (ord, lane, pos0, key) over rows with ord = 1..n. The worst input takes only the r p p x first ordinals."""
    seg = None
    if kind == "worst":
        if p < 3:
            raise ValueError("the worst input needs three lanes or more")
        x = worst_segment(n, p, r)
        n, seg = r * p * p * x, (r, x)
    d = ordinals.select("ord").where(F.col("ord") <= n)
    d = d.withColumn("lane", F.expr(f"cast(((ord - 1) * {p}) div {max(1, n)} as int)"))
    first = f"((lane * {n}L + {p} - 1) div {p})"
    after = f"(((lane + 1) * {n}L + {p} - 1) div {p})"
    d = d.withColumns({"pos0": F.expr(f"ord - 1 - {first}"), "len": F.expr(f"{after} - {first}")})
    return d.withColumn("key", F.expr(expression(kind, n, p, Dialect(True), seg=seg)).cast("long")).select("ord", "lane", "pos0", "key")


def synthetic_sql(table: str, n_sql: int, kind: str, p: int, r: int = 4) -> str:
    """The same rows in DuckDB over a table of n_sql rows."""
    n, seg = n_sql, None
    if kind == "worst":
        x = worst_segment(n, p, r)
        n, seg = r * p * p * x, (r, x)
    first = f"((lane * {n} + {p} - 1) // {p})"
    after = f"(((lane + 1) * {n} + {p} - 1) // {p})"
    key = expression(kind, n, p, Dialect(False), seg=seg)
    return f"""SELECT ord, lane, pos0, CAST({key} AS BIGINT) AS key FROM (SELECT *, ord - 1 - {first} AS pos0, {after} - {first} AS len FROM
  (SELECT ord, CAST(((ord - 1) * {p}) // {max(1, n)} AS INTEGER) AS lane FROM (SELECT row_number() OVER () AS ord FROM {table}) WHERE ord <= {n}))"""
