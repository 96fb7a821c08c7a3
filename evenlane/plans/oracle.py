"""DuckDB SQL for the sorts' steps, built from the same parameters as the Spark plans.

Keys are replaced by their dense rank in the wanted order, so that one integer comparison stands for
directions, null placement and several keys.
"""

from __future__ import annotations

from dataclasses import dataclass

from evenlane.functions.spec import SortSpec


@dataclass(frozen=True)
class Source:
    """A table or subquery with its identity columns."""

    sql: str
    ids: tuple[str, ...]


def runs(src: Source, spec: SortSpec, p: int, layout: str = "block") -> str:
    """CTEs up to run: ids, k0.., kr (dense rank of the keys), ord, lane, pos, len, n."""
    keys = ", ".join(f"{k.expr} AS k{i}" for i, k in enumerate(spec.keys))
    lane = {"block": f"((ord - 1) * {p}) // greatest(n, 1)", "deal": f"(ord - 1) % {p}"}[layout]
    return f"""WITH o AS (SELECT {", ".join(src.ids)}, {keys}, dense_rank() OVER (ORDER BY {spec.sql_order()}) AS kr,
  row_number() OVER (ORDER BY {", ".join(src.ids)}) AS ord, count(*) OVER () AS n FROM {src.sql}),
l AS (SELECT *, CAST({lane} AS INTEGER) AS lane FROM o),
run AS (SELECT *, row_number() OVER (PARTITION BY lane ORDER BY kr, ord) - 1 AS pos, count(*) OVER (PARTITION BY lane) AS len FROM l)"""


def unsorted_runs(src: Source, spec: SortSpec, p: int) -> str:
    """As runs, but pos is the input order of the lane."""
    return runs(src, spec, p).replace("ORDER BY kr, ord) - 1 AS pos", "ORDER BY ord) - 1 AS pos")


def regular_sample(s: int, p: int, spacing: str = "even") -> str:
    """CTE smp: kr, lane, pos, j, pad."""
    if spacing == "even":
        return f""", smp AS (SELECT run.kr, run.lane, run.pos, g.j, 0 AS pad FROM run JOIN (SELECT unnest(range(0, {s})) AS j) g ON run.pos = ((g.j + 1) * run.len) // {s} - 1)"""
    return f""", seg AS (SELECT greatest(1, CAST(ceil(ceil(max(n) / {p}) / {s}) AS BIGINT)) AS x FROM run),
grid AS (SELECT CAST(lane AS INTEGER) AS lane, j, (j + 1) * x - 1 AS pos FROM seg, (SELECT unnest(range(0, {p})) AS lane), (SELECT unnest(range(0, {s})) AS j)),
smp AS (SELECT r.kr, g.lane, g.pos, g.j, CASE WHEN r.kr IS NULL THEN 1 ELSE 0 END AS pad FROM grid g LEFT JOIN run r ON r.lane = g.lane AND r.pos = g.pos)"""


def random_size(table: str) -> str:
    """The random method's samples a lane, from the table's own rows."""
    return f"(SELECT CAST(ceil(2 * log2(count(*)) ** 2) AS BIGINT) FROM {table})"


def random_sample(s: int | str, seed: int) -> str:
    return f""", smp AS (SELECT kr, lane, pos, j, 0 AS pad FROM (SELECT *, row_number() OVER (PARTITION BY lane ORDER BY md5('{seed}|' || lane || '|' || pos), pos) - 1 AS j FROM run) WHERE j < {s})"""


def two_step_sample(s: int | str, p: int, seed: int) -> str:
    return f""", quota AS (SELECT CAST(('0x' || substr(md5('{seed}|' || j), 1, 8))::BIGINT % 2147483648 % {p} AS INTEGER) AS lane, count(*) AS q FROM (SELECT unnest(range(0, CAST({s} * {p} AS BIGINT))) AS j) GROUP BY 1),
smp AS (SELECT kr, lane, pos, j, 0 AS pad FROM (SELECT *, row_number() OVER (PARTITION BY lane ORDER BY md5('{seed}|' || lane || '|' || pos), pos) - 1 AS j FROM run) JOIN quota USING (lane) WHERE j < q)"""


def fences(p: int, s: int | str | None) -> str:
    """CTEs ranked and fence: i, kr, lane, pos."""
    at = f"rk % {s} = 0 AND rk < {p} * {s}" if s else f"rk IN (SELECT greatest(1, (i * (SELECT count(*) FROM smp)) // {p}) FROM (SELECT unnest(range(1, {p})) AS i))"
    return f""", ranked AS (SELECT *, row_number() OVER (ORDER BY pad, kr, lane, pos, j) AS rk FROM smp),
fence AS (SELECT row_number() OVER (ORDER BY rk) AS i, kr, lane, pos FROM ranked WHERE {at} AND pad = 0)"""


def buckets(tagged: bool = True) -> str:
    """CTE b: the run with bucket."""
    tags = " OR (f.kr = run.kr AND (f.lane < run.lane OR (f.lane = run.lane AND f.pos < run.pos)))" if tagged else ""
    return f""", b AS (SELECT run.*, CAST((SELECT count(*) FROM fence f WHERE f.kr < run.kr{tags}) AS INTEGER) AS bucket FROM run)"""


def ranks(src: Source, spec: SortSpec, with_bucket: bool = True) -> str:
    keys = ", ".join(f"k{i}" for i in range(len(spec.keys)))
    cols = ", ".join([*src.ids, keys, "lane", "pos", *(["bucket"] if with_bucket else [])])
    return f" SELECT {cols}, row_number() OVER (ORDER BY kr, lane, pos) AS rank FROM {'b' if with_bucket else 'run'}"


def sizes(p: int) -> str:
    return f" SELECT CAST(g.bucket AS INTEGER) AS bucket, count(b.bucket) AS size FROM (SELECT unnest(range(0, {p})) AS bucket) g LEFT JOIN b ON b.bucket = g.bucket GROUP BY g.bucket"
