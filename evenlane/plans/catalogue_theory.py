"""Queries of the cost model: efficiencies, broadcast and prefix costs, schedules, ledgers, regimes."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec
from evenlane.operators.networks import bitonic_schedule, odd_even_schedule
from evenlane.operators.layout import Lanes
from evenlane.operators.sampling import claim_size
from evenlane.operators.sorts import regular_sort
from evenlane.plans import advisor, model, oracle
from evenlane.plans.model import MACHINES, RATE, MachineModel
from evenlane.sources.tables import IDS, read

QUERIES: dict[str, Callable] = {}
ORACLE_SQL: dict[str, str] = {}

_VALUES = ", ".join(f"({p}, {l}, {g})" for p, l, g in MACHINES)
_GRID = f"(SELECT CAST(p AS INTEGER) AS p, CAST(l AS DOUBLE) * {RATE} AS l, CAST(g AS DOUBLE) * {RATE} AS g, n, log2(p) AS lgp, log2(n) AS lgn FROM (VALUES {_VALUES}) m(p, l, g), (SELECT CAST(2 AS BIGINT) ** unnest(range(20, 27)) AS n))"
_TERMS = {
    "regular": ("1 + lgp / (w * lgn)", "(1 + 1 / w) * g / lgn + p * l * lgp ** 2 / (2 * n * lgn)", "CAST(greatest(1, ceil(log2(lgn))) AS DOUBLE)"),
    "presorted_random": ("1 + lgp / (w * lgn) + 2 * p * w ** 2 * lgp ** 2 / n", "(1 + 1 / w) * g / lgn + g * p * w ** 2 * lgp ** 2 / n + p * l * lgp ** 2 / (2 * n * lgn)", "sqrt(lgn)"),
    "classic_random": ("1 + 1 / w + 1 / lgn + 2 * p ** 2 * w ** 2 * lgp / n", "g * p ** 2 * w ** 2 / n + g / lgn", "sqrt(lgn)"),
}


_KEYS = "(SELECT count(l_extendedprice) FROM lineitem)"


def keys_of(spark, sf_dir: str, table: str = "lineitem", key: str = "l_extendedprice") -> int:
    """Rows of a table that have a key to sort by."""
    return read(spark, sf_dir, table, [key]).agg(F.count(key)).first()[0]


def _theory(method: str):
    def run(spark, sf_dir):
        rows = []
        for p, l, g in MACHINES:
            for e in range(20, 27):
                t = model.theory(method, 2**e, MachineModel(p, l, g))
                rows.append((2**e, p, round(t["pi"], 6), round(t["mu"], 6), round(t["efficiency"], 6)))
        return spark.createDataFrame(rows, "n long, p int, pi double, mu double, efficiency double")

    return run


for _m, (_pi, _mu, _w) in _TERMS.items():
    QUERIES[f"theory_{_m}"] = _theory(_m)
    ORACLE_SQL[f"theory_{_m}"] = f"SELECT CAST(n AS BIGINT) AS n, p, round({_pi}, 6) AS pi, round({_mu}, 6) AS mu, round(1 / (({_pi}) + ({_mu})), 6) AS efficiency FROM (SELECT *, {_w} AS w FROM {_GRID})"


def _costs(cost, depth, words):
    """Costs by arity on each machine; words(spark, sf_dir) tells the words to send."""

    def run(spark, sf_dir):
        rows, n = [], words(spark, sf_dir)
        for p, l, g in MACHINES:
            m = MachineModel(p, l, g)
            rows += [(p, t, depth(p, t), round(cost(n, p, m.l_ops, m.g_ops, t), 4)) for t in range(2, p + 1)]
        return spark.createDataFrame(rows, "p int, t int, h int, cost double")

    return run


_ARITIES = f"(SELECT *, CAST(unnest(range(2, p + 1)) AS INTEGER) AS t FROM (SELECT CAST(p AS INTEGER) AS p, CAST(l AS DOUBLE) * {RATE} AS l, CAST(g AS DOUBLE) * {RATE} AS g FROM (VALUES {_VALUES}) m(p, l, g)))"


def _broadcast_sql(words: str) -> str:
    return f"""
WITH a AS (SELECT *, (SELECT CAST(min(k) AS INTEGER) FROM (SELECT unnest(range(1, 9)) AS k) WHERE (CAST(t AS BIGINT) ** (k + 1) - 1) / (t - 1) >= p) AS h, {words} AS n FROM {_ARITIES}),
b AS (SELECT *, CAST(ceil(n / h) AS BIGINT) AS x FROM a)
SELECT p, t, h, round((ceil(n / x) + h - 1) * greatest(l, g * t * x), 4) AS cost FROM b"""


def _prefix_sql(words: str) -> str:
    return f"""
WITH a AS (SELECT *, (SELECT CAST(min(k) AS INTEGER) FROM (SELECT unnest(range(1, 9)) AS k) WHERE CAST(t AS BIGINT) ** k >= p) AS h, {words} AS n FROM {_ARITIES}),
b AS (SELECT *, CAST(ceil(n / h) AS BIGINT) AS x FROM a)
SELECT p, t, h, round(2 * (ceil(n / x) + h - 1) * greatest(l, t * x) + 2 * (ceil(n / x) + h - 1) * greatest(l, 2 * g * t * x), 4) AS cost FROM b"""


def _distinct(column: str):
    """The number of distinct values of a column of lineitem."""

    def words(spark, sf_dir):
        n = read(spark, sf_dir, "lineitem", [column]).agg(F.count_distinct(column)).first()[0]
        return n

    return words


QUERIES["cost_broadcast_table"] = _costs(model.cost_broadcast, model.broadcast_depth, _distinct("l_partkey"))
ORACLE_SQL["cost_broadcast_table"] = _broadcast_sql("(SELECT count(DISTINCT l_partkey) FROM lineitem)")
QUERIES["cost_prefix_table"] = _costs(model.cost_prefix, model.prefix_depth, _distinct("l_shipdate"))
ORACLE_SQL["cost_prefix_table"] = _prefix_sql("(SELECT count(DISTINCT l_shipdate) FROM lineitem)")


def _traced_sql(schedule: str) -> str:
    """A schedule's comparators with the keys that their two lanes hold afterwards, from the largest price of each lane of lineitem."""
    return f"""WITH RECURSIVE comps AS ({schedule}),
lanes AS (SELECT i, coalesce(max(l_extendedprice), 0) AS v FROM (SELECT unnest(range(0, 16)) AS i) g LEFT JOIN lineitem ON l_orderkey % 16 = i GROUP BY i),
roles AS (SELECT step, low_lane AS i, high_lane AS o, 1 AS low FROM comps UNION ALL SELECT step, high_lane, low_lane, 0 FROM comps),
moves AS (SELECT s.step, list(coalesce(r.o, g.i) ORDER BY g.i) AS o, list(coalesce(r.low, 1) ORDER BY g.i) AS low
  FROM (SELECT DISTINCT step FROM comps) s CROSS JOIN (SELECT unnest(range(0, 16)) AS i) g LEFT JOIN roles r ON r.step = s.step AND r.i = g.i GROUP BY s.step),
run AS (SELECT 0 AS step, (SELECT list(v ORDER BY i) FROM lanes) AS v
  UNION ALL SELECT CAST(run.step + 1 AS INTEGER), [CASE WHEN m.low[k] = 1 THEN least(run.v[k], run.v[m.o[k] + 1]) ELSE greatest(run.v[k], run.v[m.o[k] + 1]) END for k in range(1, 17)] FROM run JOIN moves m ON m.step = run.step)
SELECT c.*, CAST(run.v[c.low_lane + 1] AS DOUBLE) AS low_key, CAST(run.v[c.high_lane + 1] AS DOUBLE) AS high_key FROM comps c JOIN run ON run.step = c.step + 1"""


def _traced(steps):
    def run(spark, sf_dir):
        items = read(spark, sf_dir, "lineitem", ["l_orderkey", "l_extendedprice"])
        top = {r["lane"]: r["k"] for r in items.groupBy((F.col("l_orderkey") % 16).alias("lane")).agg(F.max("l_extendedprice").alias("k")).collect()}  # one a lane
        held, rows = [float(top.get(i) or 0) for i in range(16)], []
        for i, (stage, d, step) in enumerate(steps(16)):
            for a, b in step:
                held[a], held[b] = min(held[a], held[b]), max(held[a], held[b])
                rows.append((i, stage, d, a, b, held[a], held[b]))
        return spark.createDataFrame(rows, "step int, stage int, distance int, low_lane int, high_lane int, low_key double, high_key double")

    return run


QUERIES["bitonic_schedule_table"] = _traced(bitonic_schedule)
ORACLE_SQL["bitonic_schedule_table"] = _traced_sql("""
WITH s AS (SELECT k AS stage, j, row_number() OVER (ORDER BY k, j DESC) - 1 AS step FROM (SELECT unnest(range(1, 5)) AS k), (SELECT unnest(range(0, 4)) AS j) WHERE j < k),
c AS (SELECT step, stage, 1 << j AS d, i, xor(i, 1 << j) AS o, (i & (1 << stage)) = 0 AS up FROM s, (SELECT unnest(range(0, 16)) AS i))
SELECT CAST(step AS INTEGER) AS step, CAST(stage AS INTEGER) AS stage, CAST(d AS INTEGER) AS distance, CAST(CASE WHEN up THEN i ELSE o END AS INTEGER) AS low_lane,
  CAST(CASE WHEN up THEN o ELSE i END AS INTEGER) AS high_lane FROM c WHERE i < o""")
QUERIES["odd_even_schedule_table"] = _traced(odd_even_schedule)
ORACLE_SQL["odd_even_schedule_table"] = _traced_sql("""
WITH s AS (SELECT k, m, row_number() OVER (ORDER BY k, m DESC) - 1 AS step FROM (SELECT unnest(range(0, 4)) AS k), (SELECT unnest(range(0, 4)) AS m) WHERE m <= k),
c AS (SELECT *, CAST(1 AS BIGINT) << k AS block, CAST(1 AS BIGINT) << m AS d FROM s, (SELECT unnest(range(0, 16)) AS lo))
SELECT CAST(step AS INTEGER) AS step, CAST(k + 1 AS INTEGER) AS stage, CAST(d AS INTEGER) AS distance, CAST(lo AS INTEGER) AS low_lane, CAST(lo + d AS INTEGER) AS high_lane FROM c
WHERE lo + d < 16 AND lo >= d % block AND (lo - d % block) % (2 * d) < d AND lo // (2 * block) = (lo + d) // (2 * block)""")
_PRICE = SortSpec.of("o_totalprice")
_FENCES = oracle.runs(oracle.Source("orders", IDS["orders"]), _PRICE, 16) + oracle.regular_sample(64, 16) + oracle.fences(16, 64)
ORACLE_SQL["broadcast_schedule_table"] = f"""{_FENCES},
words AS (SELECT (i - 1) // 5 AS piece, CAST(min(k0) AS DOUBLE) AS first_fence, CAST(max(k0) AS DOUBLE) AS last_fence FROM fence JOIN run USING (lane, pos) GROUP BY 1),
s AS (SELECT CAST((CASE WHEN sender = 0 THEN 0 WHEN sender < 4 THEN 1 ELSE 2 END) + piece AS INTEGER) AS step, CAST(sender AS INTEGER) AS sender, CAST(receiver AS INTEGER) AS receiver, CAST(piece AS INTEGER) AS piece
FROM (SELECT (c - 1) // 3 AS sender, c AS receiver FROM (SELECT unnest(range(1, 16)) AS c)), (SELECT unnest(range(0, 3)) AS piece))
SELECT s.*, first_fence, last_fence FROM s JOIN words USING (piece)"""
ORACLE_SQL["prefix_schedule_table"] = """
WITH u AS (SELECT 0 AS s, i, i - i % 4 AS head FROM (SELECT unnest(range(0, 16)) AS i) WHERE i % 4 <> 0 UNION ALL SELECT 1, i, 0 FROM (SELECT unnest([4, 8, 12]) AS i)),
size AS (SELECT l_partkey % 16 AS lane, count(*) AS c FROM lineitem GROUP BY 1),
m AS (SELECT 'up' AS sweep, CAST(s AS INTEGER) AS step, CAST(i AS INTEGER) AS sender, CAST(head AS INTEGER) AS receiver FROM u
UNION ALL SELECT 'down', CAST(3 - s AS INTEGER), CAST(head AS INTEGER), CAST(i AS INTEGER) FROM u)
SELECT m.*, CAST(coalesce((SELECT sum(c) FROM size WHERE CASE WHEN m.sweep = 'up' THEN lane >= m.sender AND lane < m.sender + 4 ** m.step ELSE lane < m.receiver END), 0) AS BIGINT) AS words FROM m"""


def _broadcast_schedule(spark, sf_dir):
    """The fences of orders on their way from one of 16 lanes to all, and the first and last of each piece."""
    fences = [float(f["k0"]) for f in regular_sort(read(spark, sf_dir, "orders"), _PRICE, Lanes(16, IDS["orders"]), r=4).fences.records]
    piece = -(-len(fences) // model.broadcast_depth(16, 3))
    rows = [(*x, fences[x[3] * piece], fences[min(len(fences), (x[3] + 1) * piece) - 1]) for x in model.broadcast_schedule(len(fences), 16, 3)]
    return spark.createDataFrame(rows, "step int, sender int, receiver int, piece int, first_fence double, last_fence double")


QUERIES["broadcast_schedule_table"] = _broadcast_schedule


def _prefix_schedule(spark, sf_dir):
    """Sums of the rows of lineitem by lane: what each message holds, the sum of a block on its way up, of all before a lane on its way down."""
    lanes = read(spark, sf_dir, "lineitem", ["l_partkey"]).groupBy((F.col("l_partkey") % 16).alias("lane")).count()
    have = {r["lane"]: r["count"] for r in lanes.collect()}  # one a lane
    size = [have.get(i, 0) for i in range(16)]
    rows = [(s, i, a, b, sum(size[a : a + 4**i]) if s == "up" else sum(size[:b])) for s, i, a, b in model.prefix_schedule(16, 4)]
    return spark.createDataFrame(rows, "sweep string, step int, sender int, receiver int, words long")


QUERIES["prefix_schedule_table"] = _prefix_schedule


def _claim(spark, sf_dir):
    n = keys_of(spark, sf_dir)
    rows = [(k, e, r, claim_size(n, k, e, r)) for k in (8, 32, 128) for e in (0.1, 0.2, 0.5) for r in (1.0, 2.0)]
    return spark.createDataFrame(rows, "k int, eps double, rho double, s int")


QUERIES["claim_sample_size"] = _claim
ORACLE_SQL["claim_sample_size"] = """
WITH RECURSIVE g(n, k, eps, rho, i, s) AS (
  SELECT (SELECT count(l_extendedprice) FROM lineitem), CAST(k AS INTEGER), CAST(eps AS DOUBLE), CAST(rho AS DOUBLE), 0, CAST(1 AS DOUBLE) FROM (SELECT unnest([8, 32, 128]) AS k), (SELECT unnest([0.1, 0.2, 0.5]) AS eps), (SELECT unnest([1.0, 2.0]) AS rho)
  UNION ALL SELECT n, k, eps, rho, i + 1, (1 + eps) / (eps * eps) * (2 * rho * ln(n) + ln(2 * pi() * k * k * (k * s - 1)) + 1 / (3 * (k * s - 1))) FROM g WHERE i < 100)
SELECT k, eps, rho, CAST(ceil(s) AS INTEGER) AS s FROM g WHERE i = 100"""


def _ledger(method: str):
    def run(spark, sf_dir):
        p, l, g = MACHINES[0]
        n = spark.read.parquet(f"{sf_dir}/lineitem.parquet").count()
        rows = [(*x[:3], *[round(float(y), 3) for y in x[3:]]) for x in model.ledger(method, n, MachineModel(p, l, g))]
        return spark.createDataFrame(rows, "step int, name string, kind string, x_ops double, h_words double, predicted_charge double")

    return run


def _ledger_sql(method: str) -> str:
    """The supersteps of a sort on the first machine, from the table's rows: a lane's operations, its words, and what they cost."""
    p, l, g = MACHINES[0]
    lgp = p.bit_length() - 1
    l, g = l * RATE, g * RATE
    tree = lambda words, cost: f"(SELECT min({cost}) FROM (SELECT t, h, CAST(ceil({words} / h) AS BIGINT) AS x FROM (SELECT t, {{h}} AS h FROM (SELECT unnest(range(2, {p + 1})) AS t))))"
    spread = tree(3 * (p - 1), f"(ceil({3 * (p - 1)} / x) + h - 1) * greatest({l}, {g} * t * x)").replace("{h}", f"(SELECT min(k) FROM (SELECT unnest(range(1, 9)) AS k) WHERE (CAST(t AS BIGINT) ** (k + 1) - 1) / (t - 1) >= {p})")
    scan = tree(p, f"2 * (ceil({p} / x) + h - 1) * (greatest({l}, t * x) + greatest({l}, 2 * {g} * t * x))").replace("{h}", f"(SELECT min(k) FROM (SELECT unnest(range(1, 9)) AS k) WHERE CAST(t AS BIGINT) ** k >= {p})")
    if method == "classic_random":
        rows = [("sample", "comp", "s", "s"), ("gather sample", "comm", "0", f"s * {p}"), ("sort sample", "comp", f"s * {p} * log2(s * {p})", "0"), ("broadcast fences", "comm", "0", str(p)), ("split", "comp", f"per * {lgp + 1}", "0"), ("route", "comm", "0", "big"), ("final sort", "comp", "big * log2(per)", "0")]
    else:
        rows = [("local sort", "comp", "per * log2(per)", "0"), ("sample", "comp", "s", "0"), ("sample sort", "comp", "s * log2(s)", "0")] + [(f"compare-split {i + 1}", "comm", "2 * s", "3 * s") for i in range(lgp * (lgp + 1) // 2)]
        rows += [("gather fences", "comm", "0", str(3 * (p - 1))), ("broadcast fences", "sync", "0", f"{spread} / {g}"), ("split", "comp", f"{p} * log2(per)", "0"), ("prefix", "sync", "0", f"{scan} / {g}"), ("route", "comm", "0", "big"), ("merge", "comp", f"big * {lgp}", "0")]
    s, big = (f"{4 * p}", f"(1 + 1 / 4) * per + {4 * p}") if method == "regular" else ("ceil(2 * lgn ** 2)", "(1 + 1 / sqrt(lgn)) * per")
    parts = " UNION ALL ".join(f"SELECT {i + 1} AS step, '{n}' AS name, '{k}' AS kind, CAST({x} AS DOUBLE) AS x, CAST({h} AS DOUBLE) AS h FROM f" for i, (n, k, x, h) in enumerate(rows))
    return f"""WITH c AS (SELECT CAST(count(*) AS DOUBLE) AS n, log2(count(*)) AS lgn FROM lineitem), e AS (SELECT *, n / {p} AS per FROM c), f AS (SELECT *, CAST({s} AS DOUBLE) AS s, CAST({big} AS DOUBLE) AS big FROM e)
SELECT CAST(step AS INTEGER) AS step, name, kind, round(x, 3) AS x_ops, round(h, 3) AS h_words, round(greatest({l}, x + {g} * h), 3) AS predicted_charge FROM ({parts})"""


for _m in _TERMS:
    QUERIES[f"ledger_{_m}"] = _ledger(_m)
    ORACLE_SQL[f"ledger_{_m}"] = _ledger_sql(_m)


def _regimes(spark, sf_dir):
    rows = [(2**e, 2**f, *model.regime(2**e, 2**f)) for e in (16, 20, 24, 30) for f in (4, 8, 12, 14)]
    return spark.createDataFrame(rows, "n long, p long, slack string, rounds int")


QUERIES["regime_table"] = _regimes
ORACLE_SQL["regime_table"] = """
SELECT n, p, CASE WHEN p * p <= n THEN 'square' WHEN p >= n THEN 'none' WHEN p <= n / log2(n) ** 2 THEN 'polynomial' ELSE 'near-linear' END AS slack,
  CAST(CASE WHEN p * p <= n THEN 1 WHEN p >= n THEN 0 ELSE ceil(log2(n) / log2(n / p)) END AS INTEGER) AS rounds
FROM (SELECT CAST(2 AS BIGINT) << (e - 1) AS n, CAST(2 AS BIGINT) << (f - 1) AS p FROM (SELECT unnest([16, 20, 24, 30]) AS e), (SELECT unnest([4, 8, 12, 14]) AS f))"""


def _superstep(spark, sf_dir):
    rows = []
    for p, l, g in MACHINES:
        m = MachineModel(p, l, g)
        rows += [(p, x, h, round(m.superstep(x, h), 4), round(m.h_relation(h), 4)) for x in (0, 1000, 100_000) for h in (0, 100, 10_000)]
    return spark.createDataFrame(rows, "p int, x int, h int, charge double, routing double")


QUERIES["superstep_ledger"] = _superstep
ORACLE_SQL["superstep_ledger"] = f"SELECT CAST(p AS INTEGER) AS p, CAST(x AS INTEGER) AS x, CAST(h AS INTEGER) AS h, round(greatest(CAST(l AS DOUBLE) * {RATE}, x + CAST(g AS DOUBLE) * {RATE} * h), 4) AS charge, round(greatest(CAST(l AS DOUBLE) * {RATE}, CAST(g AS DOUBLE) * {RATE} * h), 4) AS routing FROM (VALUES {_VALUES}) m(p, l, g), (SELECT unnest([0, 1000, 100000]) AS x), (SELECT unnest([0, 100, 10000]) AS h)"


def _earlier(spark, sf_dir):
    n = keys_of(spark, sf_dir)
    rows = [(p, *r) for p, l, g in MACHINES for r in model.earlier_results(n, p, MachineModel(p, l, g))]
    return spark.createDataFrame([(a, b, round(float(c), 2), round(float(d), 2), e) for a, b, c, d, e in rows], "p int, method string, computation double, communication double, note string")


QUERIES["earlier_results"] = _earlier
_STAR = "CASE WHEN {x} <= 1 THEN 0 WHEN log2({x}) <= 1 THEN 1 WHEN log2(log2({x})) <= 1 THEN 2 WHEN log2(log2(log2({x}))) <= 1 THEN 3 WHEN log2(log2(log2(log2({x})))) <= 1 THEN 4 ELSE 5 END"
_EARLIER = (
    ("log-depth network", "per * lgn", "g * per * lgp + l * lgp", "constants of no practical size"),
    ("column sort", "z ** 3.42 * per * log2(per)", "g * z ** 3.42 * per + l * z ** 3.42", "n at least p"),
    ("cube sort", "cube * per * log2(per)", "cube * (g * per + l)", "the power of 25 can be avoided"),
    ("first randomised", "per * lgn", "g * z * per + l * z", "with high probability"),
    ("first deterministic", "(floor(z * (1 - 1 / z)) + 1) * per * lgn", "g * z * per + l * z", "bound with a floor factor"),
    ("improved deterministic", "3 * per * lgn", "g * z * per + l * z", "alpha = 1"),
    ("merge sort", "per * lgn", "g * z * per + l * z", "large constants"),
    ("randomised for more lanes", "per * lgn", "g * z * per + l * z", "fails less often, needs low L and g"),
    ("shared memory, a processor a key", "lgn", "0", "moves are free there; not optimal run as it is"),
)
ORACLE_SQL["earlier_results"] = f"""
WITH m AS (SELECT CAST(p AS INTEGER) AS p, CAST(l AS DOUBLE) * {RATE} AS l, CAST(g AS DOUBLE) * {RATE} AS g, CAST({_KEYS} AS DOUBLE) AS n FROM (VALUES {_VALUES}) m(p, l, g)),
b AS (SELECT *, n / p AS per, log2(n) AS lgn, log2(p) AS lgp, log2(n) / log2(n / p) AS z FROM m),
c AS (SELECT *, 25.0::DOUBLE ** ({_STAR.format(x="n")} - {_STAR.format(x="per")}) * z ** 2 AS cube FROM b)
""" + " UNION ALL ".join(f"SELECT p, '{a}' AS method, round(CAST({x} AS DOUBLE), 2) AS computation, round(CAST({y} AS DOUBLE), 2) AS communication, '{z}' AS note FROM c" for a, x, y, z in _EARLIER)


_ADVISED = (("lineitem", "l_extendedprice"), ("orders", "o_totalprice"), ("events", "event_id"), ("part", "p_partkey"))


def _advice(spark, sf_dir):
    """The plan for each table by one of its columns, on each machine."""
    rows, sizes = [], {t: keys_of(spark, sf_dir, t, c) for t, c in _ADVISED}
    for p, l, g in MACHINES:
        for table, n in sizes.items():
            a = advisor.choose(MachineModel(p, l, g), n)
            rows.append((table, n, p, a.method, a.ratio, a.rounds, a.k, a.sample_sort, a.split, a.broadcast_t, a.prefix_t, a.sync_ok))
    return spark.createDataFrame(rows, "table_name string, n long, p int, method string, ratio int, rounds int, k int, sample_sort string, split string, broadcast_t int, prefix_t int, sync_ok boolean")


QUERIES["advisor_table"] = _advice
_SIZED = " UNION ALL ".join(f"SELECT '{t}' AS table_name, count({c}) AS n FROM {t}" for t, c in _ADVISED)
ORACLE_SQL["advisor_table"] = f"""
WITH m AS (SELECT CAST(p AS INTEGER) AS p, CAST(l AS DOUBLE) * {RATE} AS l, CAST(g AS DOUBLE) * {RATE} AS g, log2(p) AS lgp, table_name, n, log2(n) AS lgn FROM (VALUES {_VALUES}) m(p, l, g), ({_SIZED})),
a AS (SELECT *, greatest(1, ceil(log2(lgn))) AS r, ceil(2 * lgn * lgn) AS rs FROM m),
b AS (SELECT *, p * p * r * r <= n / lgn AS reg, NOT (2 * p * lgn * lgn >= n / 2 OR p * p > n / (sqrt(lgn) * lgn)) AS rnd FROM a),
c AS (SELECT *, CASE WHEN reg OR rnd THEN 1 WHEN CAST(p AS BIGINT) * p <= n OR p >= n THEN 2 ELSE greatest(2, ceil(lgn / log2(n / p))) END AS rounds, CASE WHEN reg THEN r * p ELSE rs END AS s FROM b),
d AS (SELECT *, greatest(l, g * s * p) + s * p * log2(s * p) AS gather, lgp * (lgp + 1) / 2 * greatest(l, g * s + 2 * s) AS network FROM c),
bt AS (SELECT p, arg_min(t, cost * 1000 + t * 1e-6) AS t FROM ({_broadcast_sql("p - 1")}) GROUP BY p),
pt AS (SELECT p, arg_min(t, cost * 1000 + t * 1e-6) AS t FROM ({_prefix_sql("p")}) GROUP BY p)
SELECT table_name, n, d.p AS p, CASE WHEN reg OR rounds > 1 THEN 'regular' ELSE 'presorted_random' END AS method, CAST(CASE WHEN reg OR rounds > 1 THEN r ELSE s END AS INTEGER) AS ratio, CAST(rounds AS INTEGER) AS rounds,
  CAST(CASE WHEN rounds = 1 THEN d.p ELSE greatest(2, round(d.p ** (1.0 / rounds) + 0.499)) END AS INTEGER) AS k, CASE WHEN gather <= network THEN 'driver' WHEN s * d.p > 2000000 THEN 'spark' ELSE 'bitonic' END AS sample_sort,
  CASE WHEN d.p <= 257 THEN 'tree' ELSE 'search' END AS split, CAST(bt.t AS INTEGER) AS broadcast_t, CAST(pt.t AS INTEGER) AS prefix_t, l <= 2 * n / (d.p * lgp ** 2) AS sync_ok
FROM d JOIN bt ON bt.p = d.p JOIN pt ON pt.p = d.p"""

_GROWTH = (1, 3, 8, 20, 36)  # powers of the rows of lineitem


def _optimality(spark, sf_dir):
    """pi and mu as inputs grow from the rows of lineitem on, at a fixed machine: the limits that make a method one-optimal."""
    p, l, g = MACHINES[1]
    n = float(keys_of(spark, sf_dir))
    rows = []
    for m in _TERMS:
        t = [model.theory(m, n**e, MachineModel(p, l, g)) for e in _GROWTH]
        c, falls = model.optimality([x["pi"] for x in t], [x["mu"] for x in t])
        rows.append((m, round(c, 6), falls))
    return spark.createDataFrame(rows, "method string, last_pi double, mu_falls boolean")


QUERIES["optimality_table"] = _optimality
_p, _l, _g = MACHINES[1]
ORACLE_SQL["optimality_table"] = " UNION ALL ".join(
    f"SELECT '{m}' AS method, round(arg_max(pi, e), 6) AS last_pi, min(coalesce(mu <= before, true)) AND arg_max(mu, e) <= 0.1 * arg_min(mu, e) AS mu_falls FROM (SELECT e, pi, mu, lag(mu) OVER (ORDER BY e) AS before FROM (SELECT e, {pi} AS pi, {mu} AS mu FROM (SELECT *, {w} AS w FROM (SELECT e, CAST({_p} AS DOUBLE) AS p, {_l * RATE} AS l, {_g * RATE} AS g, CAST(2 AS DOUBLE) ** e AS n, log2({_p}) AS lgp, CAST(e AS DOUBLE) AS lgn FROM (SELECT log2({_KEYS}) * m AS e FROM (SELECT unnest({list(_GROWTH)}) AS m))))))"
    for m, (pi, mu, w) in _TERMS.items()
)


# Published phase seconds (local sort, sampling, prefix, routing, merging, total) on 64 lanes, 8M uniform keys.
_PHASES = {"random_radix": (0.277, 0.011, 0.003, 0.036, 0.198, 0.527), "random_cmp": (0.311, 0.010, 0.003, 0.038, 0.197, 0.561), "regular_radix": (0.277, 0.008, 0.003, 0.038, 0.192, 0.520), "regular_cmp": (0.310, 0.008, 0.003, 0.037, 0.192, 0.553)}
_NAMES = ("local sort", "sampling", "prefix", "routing", "merging")


def _published_shares(spark, sf_dir):
    """Shares of the published phases, what sequential work takes, and g from the routing time of the fullest lane's keys; expected_sec is a phase's time at the same rate for the rows of lineitem."""
    rows, n = [], keys_of(spark, sf_dir)
    for v, x in _PHASES.items():
        g = x[3] * 1e6 / (1.15 * 2**23 / 64)
        rows += [(v, name, round(100 * t / x[-1], 2), round(100 * (x[0] + x[4]) / x[-1], 2), round(g, 4), round(t * n / 2**23, 6)) for name, t in zip(_NAMES, x, strict=False)]
    return spark.createDataFrame(rows, "variant string, phase string, pct double, sequential_pct double, g_us double, expected_sec double")


QUERIES["published_phase_shares"] = _published_shares
_rows = ", ".join(f"('{v}', {', '.join(map(str, x))})" for v, x in _PHASES.items())
ORACLE_SQL["published_phase_shares"] = f"""
WITH v(variant, a, b, c, d, e, total) AS (VALUES {_rows}),
u AS (SELECT variant, unnest({list(_NAMES)}) AS phase, unnest([a, b, c, d, e]::DOUBLE[]) AS t, a::DOUBLE + e::DOUBLE AS seq, d::DOUBLE AS d, total::DOUBLE AS total FROM v)
SELECT variant, phase, round(100 * t / total, 2) AS pct, round(100 * seq / total, 2) AS sequential_pct, round(d * 1e6 / (1.15 * 8388608 / 64), 4) AS g_us, round(t * {_KEYS} / 8388608, 6) AS expected_sec FROM u"""
