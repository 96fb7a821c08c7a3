"""Secret scan with built-in functions only: fixed patterns, then sliding-window entropy per character class.

A pattern's matches come from one extract and one split, whose piece lengths give code-point positions.
Candidate runs of a character class are walked once: the sum of c * log2(c) over the window's character
counts changes by one incoming and one outgoing character, so each step looks up the counts of these two and
moves the sum by two terms. Windows at or above the class's entropy mark the span from the first to the last of them.
Key classes come on top, one for each alphabet that keys are drawn from: a window of 16 characters for
runs of 16 to 23 and one of 24 for longer runs, hot from three standard deviations under the entropy that
a window of uniformly random characters of that alphabet has. A run of letters and digits is marked whole.
Entropy spans that an allow-list pattern covers are dropped; of those that touch spans of the fixed patterns, what lies outside these stays.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenlane.llm.common import by_place, free_name

# The patterns of the base kinds, with the shortest length of what counts.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ASSIGN_LEAST = 12
ACCESS = "AKIA[A-Z0-9]{14,}"  # runs of 18 and more, the prefix included
HEX = "[0-9a-f]{16,}"
KINDS = ("assign", "access", "hex", "entropy")


@dataclass(frozen=True)
class CharClass:
    """Runs of alphabet of at least window characters; a window is hot at bits or more of entropy.

    With whole, a hot window marks its run from end to end; runs longer than longest or without a match
    of one of needs are no candidates.
    """

    name: str
    pattern: str
    alphabet: str
    window: int
    bits: float
    whole: bool = False
    longest: int | None = None
    needs: tuple[str, ...] = ()


_UPPER, _LOWER, _DIGITS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz", "0123456789"
CLASSES = (
    CharClass("base64", "[A-Za-z0-9+/_=-]{24,}", _UPPER + _LOWER + _DIGITS + "+/_=-", 24, 4.1),
    CharClass("hexupper", "[0-9A-F]{24,}", _DIGITS + "ABCDEF", 24, 3.2),
)
KEY_WINDOWS = (16, 24)
LEFT_LEAST = KEY_WINDOWS[0]  # what base spans leave of a hot span counts from this length on


def likely_bits(symbols: int, window: int) -> float:
    """Entropy that lies three standard deviations under the mean of a window of uniformly random symbols.

    Mean and variance are exact for the sum of c * log2(c), over the binomial count of one symbol and the
    joint counts of two.
    """
    f = [0.0, *[c * math.log2(c) for c in range(1, window + 1)]]
    p, rest = 1 / symbols, 1 - 2 / symbols
    one = [math.comb(window, c) * p**c * (1 - p) ** (window - c) for c in range(window + 1)]
    both = sum(math.comb(window, c) * math.comb(window - c, d) * p ** (c + d) * rest ** (window - c - d) * f[c] * f[d] for c in range(2, window + 1) for d in range(2, window - c + 1))
    mean = symbols * sum(x * y for x, y in zip(one, f, strict=True))
    var = symbols * sum(x * y * y for x, y in zip(one, f, strict=True)) + symbols * (symbols - 1) * both - mean**2
    return math.log2(window) - (mean + 3 * math.sqrt(var)) / window


def key_classes(name: str, chars: str, alphabet: str, symbols: int, whole: bool = True, needs: tuple[str, ...] = ()) -> tuple[CharClass, ...]:
    """A class for each window of KEY_WINDOWS over runs of chars, of keys with so many symbols."""
    least, wide = KEY_WINDOWS
    return tuple(CharClass(f"{name}{w}", f"[{chars}]{{{least},}}", alphabet, w, likely_bits(symbols, w), whole, wide - 1 if w < wide else None, needs) for w in KEY_WINDOWS)


#: Alphabets of bare keys. With joining signs, a run needs both cases and a digit: paths and joined words have runs too.
KEY_CLASSES = (
    *key_classes("lower", "a-z0-9", _LOWER + _DIGITS, 36),
    *key_classes("upper", "A-Z0-9", _UPPER + _DIGITS, 36),
    *key_classes("base32", "A-Z2-7", _UPPER + "234567", 32),
    *key_classes("hexupper", "0-9A-F", _DIGITS + "ABCDEF", 16),
    *key_classes("mixed", "A-Za-z0-9", _UPPER + _LOWER + _DIGITS, 62),
    *key_classes("base64", "A-Za-z0-9+/_=-", _UPPER + _LOWER + _DIGITS + "+/_=-", 64, False, ("[a-z]", "[A-Z]", "[0-9]")),
)
#: In a run of under 24 characters, a word and a number of up to four digits is a name, not a key.
NAMED = "^(?=.{16,23}$)[A-Za-z]?([a-z]+|[A-Z]+)[0-9]{1,4}$"
#: Candidates that one of these matches as a whole or, without anchors, in part are left alone.
ALLOW = (
    "^[A-Za-z]+([+/_=-]+[A-Za-z]+)*[+/_=-]*$",
    "^[0-9+/_=-]+$",
    "^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$",
    "(?i)example|placeholder|changeme|xxxxxx",
)


def weights(window: int) -> list[int]:
    """round(1000 * c * log2(c)) for counts c = 0 .. window."""
    return [0, *[round(1000 * c * math.log2(c)) for c in range(1, window + 1)]]


def most(c: CharClass) -> int:
    """The largest sum of weights of a hot window."""
    return math.floor(1000 * c.window * (math.log2(c.window) - c.bits))


CHUNK = 256  # matches whose places are summed up in one growing array


def located(matches: Column, pieces: Column, values: Column) -> Column:
    """array<struct<start, end, value>> from a pattern's matches, the pieces between them, and a group of each.

    Places are running sums of lengths: chunk by chunk, then over the chunks, so that no array as long as the matches grows step by step.
    """
    empty = F.from_json(F.lit("[]"), "array<struct<start:int,end:int,value:string>>")
    state = F.struct(F.lit(0).alias("at"), empty.alias("out"))

    def step(s: Column, x: Column) -> Column:
        start = s["at"] + F.length(x["p"])
        end = start + F.length(x["m"])
        return F.struct(end.alias("at"), F.concat(s["out"], F.array(F.struct(start.alias("start"), end.alias("end"), x["v"].alias("value")))).alias("out"))

    def chunk(i: Column) -> Column:
        rows = F.arrays_zip(F.slice(pieces, i * CHUNK + 1, F.lit(CHUNK)).alias("p"), F.slice(matches, i * CHUNK + 1, F.lit(CHUNK)).alias("m"), F.slice(values, i * CHUNK + 1, F.lit(CHUNK)).alias("v"))
        # one piece more than matches: the last has none, and no match
        return F.aggregate(F.filter(rows, lambda x: x["m"].isNotNull()), state, step)

    parts = F.transform(F.sequence(F.lit(0), F.floor((F.size(matches) - 1) / CHUNK).cast("int")), chunk)
    none = F.from_json(F.lit("[]"), "array<int>")
    base = F.aggregate(parts, F.struct(F.lit(0).alias("at"), none.alias("out")), lambda s, x: F.struct((s["at"] + x["at"]).alias("at"), F.concat(s["out"], F.array(s["at"])).alias("out")), lambda s: s["out"])
    moved = F.flatten(F.transform(F.arrays_zip(parts.alias("x"), base.alias("b")), lambda z: F.transform(z["x"]["out"], lambda y: F.struct((y["start"] + z["b"]).alias("start"), (y["end"] + z["b"]).alias("end"), y["value"].alias("value")))))
    few = F.aggregate(F.arrays_zip(F.slice(pieces, 1, F.size(matches)).alias("p"), matches.alias("m"), values.alias("v")), state, step, lambda s: s["out"])
    return F.when(F.size(matches) == 0, empty).when(F.size(matches) <= CHUNK, few).otherwise(moved)


def hot_range(s: Column, c: CharClass) -> Column:
    """struct<first, last>: starts of the first and last hot window in the run s (0-based; null without any)."""
    table = F.array(*map(F.lit, weights(c.window)))
    w = c.window

    def walk(chars: Column) -> Column:
        state = F.struct(F.lit(0).alias("sum"), F.lit(None).cast("int").alias("first"), F.lit(None).cast("int").alias("last"))

        def step(a: Column, i: Column) -> Column:
            before = F.slice(chars, F.greatest(i - w, F.lit(1)), F.least(i - 1, F.lit(w)))  # the window that i comes into
            new, old = chars[i - 1], F.when(i > w, before[0])
            n_new = F.size(F.filter(before, lambda x: x == new))
            n_old = F.size(F.filter(before, lambda x: x == old))
            gain = table[n_new + 1] - table[n_new]
            loss = F.when(i > w, table[n_old - 1] - table[n_old]).otherwise(0)
            total = a["sum"] + F.when(F.coalesce(new == old, F.lit(False)), 0).otherwise(gain + loss)
            hot = (i >= w) & (total <= most(c))
            return F.struct(total.alias("sum"), F.coalesce(a["first"], F.when(hot, i - w)).alias("first"), F.when(hot, i - w).otherwise(a["last"]).alias("last"))

        return F.aggregate(F.sequence(F.lit(1), F.size(chars)), state, step, lambda a: F.struct(a["first"].alias("first"), a["last"].alias("last")))

    # the characters once, as an array: places in text are found by counting from its start
    return F.transform(F.array(F.split(s, "")), walk)[0]


def _hot_spans(runs: Column, c: CharClass, allow: tuple[str, ...]) -> Column:
    """array<struct<start, end>> of the hot ranges that no allow-list pattern matches, in their run as a whole or in themselves."""
    whole = [a for a in allow if c.whole or a.startswith("^")]

    def fits(x: Column) -> Column:
        fit = ~F.greatest(*[x["value"].rlike(a) for a in (*whole, "^$", "^$")]) & (F.length(x["value"]) >= c.window)
        fit = fit & (F.length(x["value"]) <= c.longest) if c.longest else fit
        for n in c.needs:
            fit = fit & x["value"].rlike(n)
        return fit

    wild = F.filter(runs, fits)
    if c.whole:
        kept = F.filter(wild, lambda x: hot_range(x["value"], c)["first"].isNotNull())
        return F.transform(kept, lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end")))
    ranged = F.transform(wild, lambda x: F.struct(x["start"].alias("start"), x["value"].alias("value"), hot_range(x["value"], c).alias("r")))
    part = lambda x: F.call_function("substring", x["value"], x["r"]["first"] + 1, x["r"]["last"] + c.window - x["r"]["first"])
    ranged = F.filter(ranged, lambda x: x["r"]["first"].isNotNull() & ~F.greatest(*[part(x).rlike(a) for a in (*allow, "^$", "^$")]))
    return F.transform(ranged, lambda x: F.struct((x["start"] + x["r"]["first"]).alias("start"), (x["start"] + x["r"]["last"] + c.window).alias("end")))


def _clear_of(span: Column, base: Column) -> Column:
    """array<struct<start, end>>: what the base spans, in order, leave of span, in pieces of the shortest window or more."""
    inside = F.filter(base, lambda b: (b["start"] < span["end"]) & (span["start"] < b["end"]))
    none = F.from_json(F.lit("[]"), "array<struct<start:int,end:int>>")
    piece = lambda a, b: F.array(F.struct(a.alias("start"), b.alias("end")))

    def step(s: Column, b: Column) -> Column:
        return F.struct(F.greatest(s["at"], b["end"]).alias("at"), F.concat(s["out"], piece(s["at"], b["start"])).alias("out"))

    cut = F.aggregate(inside, F.struct(span["start"].alias("at"), none.alias("out")), step, lambda s: F.concat(s["out"], piece(s["at"], span["end"])))
    return F.filter(cut, lambda x: x["end"] - x["start"] >= LEFT_LEAST)


def scanned(docs: DataFrame, text: Column, classes: tuple[CharClass, ...] = CLASSES, allow: tuple[str, ...] = ALLOW, keys: tuple[CharClass, ...] = KEY_CLASSES) -> DataFrame:
    """docs (names without "__") with __spans."""
    d = docs.withColumn("__t", F.coalesce(text, F.lit("")))
    runs = {r: f"class{i}" for i, r in enumerate(dict.fromkeys(c.pattern for c in (*classes, *keys)))}
    plan = [("assign", ASSIGN, 2), ("access", ACCESS, 0), ("hex", HEX, 0), *[(n, r, 0) for r, n in runs.items()]]
    d = d.withColumns({f"__m_{n}": F.regexp_extract_all("__t", F.lit(r), F.lit(0)) for n, r, _ in plan})
    none = F.array().cast("array<string>")
    some = lambda n, x: F.when(F.size(f"__m_{n}") > 0, x).otherwise(none)
    d = d.withColumns({f"__p_{n}": some(n, F.split("__t", r, -1)) for n, r, _ in plan})
    d = d.withColumn("__g_assign", some("assign", F.regexp_extract_all("__t", F.lit(ASSIGN), F.lit(2))))
    d = d.withColumns({f"__l_{n}": located(F.col(f"__m_{n}"), F.col(f"__p_{n}"), F.col("__g_assign" if n == "assign" else f"__m_{n}")) for n, _, _ in plan})
    d = d.withColumn("__l_assign", F.filter("__l_assign", lambda x: F.length(x["value"]) >= ASSIGN_LEAST))

    def spans(kind: int, col: Column) -> Column:
        return F.transform(col, lambda x: F.struct(x["start"].alias("start"), F.lit(kind).alias("kind"), x["end"].alias("end"), F.lit(KINDS[kind]).alias("name")))

    d = d.withColumn("__base", F.array_sort(F.concat(*[spans(i, F.col(f"__l_{KINDS[i]}")) for i in range(3)])))
    hot = [_hot_spans(F.col(f"__l_{runs[c.pattern]}"), c, a) for cs, a in ((classes, allow), (keys, (*allow, NAMED))) for c in cs]
    d = d.withColumn("__hot", F.array_distinct(F.concat(*hot)) if hot else F.from_json(F.lit("[]"), "array<struct<start:int,end:int>>"))
    d = d.withColumn("__hot", F.filter("__hot", lambda h: ~F.exists("__hot", lambda g: (g != h) & (g["start"] <= h["start"]) & (h["end"] <= g["end"]))))
    d = d.withColumn("__hot", F.array_distinct(F.flatten(F.transform("__hot", lambda h: _clear_of(h, F.col("__base"))))))
    d = d.withColumn("__spans", F.array_sort(F.concat("__base", spans(3, F.col("__hot")))))
    return d.select(*docs.columns, "__spans")


def find_secrets(docs: DataFrame, text_col: str = "text", classes: tuple[CharClass, ...] = CLASSES, allow: tuple[str, ...] = ALLOW, keys: tuple[CharClass, ...] = KEY_CLASSES) -> DataFrame:
    """docs with __spans: array<struct<start, kind, end, name>> in order of start, then kind.

    kind is the index in KINDS; start and end are code points, end exclusive. Null text counts as empty
    and has no spans; repeated rows and empty tables need nothing special; input columns pass through whatever their
    names, and where the input has a column __spans, the new one gets underscores at its end.
    """
    d = scanned(by_place(docs), F.col(f"c{docs.columns.index(text_col)}"), classes, allow, keys)
    return d.toDF(*docs.columns, free_name(docs.columns, "__spans"))


def listed(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda x: F.concat_ws(":", x["name"], x["start"].cast("string"), x["end"].cast("string"))))


def redact(docs: DataFrame, text_col: str = "text", mark: str = "[SECRET]") -> DataFrame:
    """docs with every span of find_secrets replaced by mark; other documents and columns unchanged."""
    text = f"c{docs.columns.index(text_col)}"
    t = F.col(text)
    d = scanned(by_place(docs), t)
    cut = lambda a, n: F.call_function("substring", t, a, n)
    state = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(s: Column, x: Column) -> Column:
        apart = x["start"] >= s["at"]
        more = F.when(apart, F.concat(s["out"], cut(s["at"] + 1, x["start"] - s["at"]), F.lit(mark))).otherwise(s["out"])
        return F.struct(F.greatest(s["at"], x["end"]).alias("at"), more.alias("out"))

    clean = F.aggregate("__spans", state, step, lambda s: F.concat(s["out"], cut(s["at"] + 1, F.length(t))))
    return d.withColumn(text, F.when(F.size("__spans") > 0, clean).otherwise(t)).drop("__spans").toDF(*docs.columns)


def secrets_query(spark, sf_dir: str) -> DataFrame:
    d = scanned(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), F.col("text"))
    base = F.filter("__spans", lambda x: x["kind"] < 3)
    count = lambda k: F.size(F.filter("__spans", lambda x: x["kind"] == k)).cast("long").alias(f"n_{KINDS[k]}")
    return d.select("doc_id", count(0), count(1), count(2), F.sha2(listed(base), 256).alias("base_sha256"), listed(F.col("__spans")).alias("spans"))


def _secrets_sql() -> str:
    parts = []
    for n, (kind, pattern) in enumerate([("assign", ASSIGN), ("access", ACCESS), ("hex", HEX)]):
        q = pattern.replace("'", "''")
        group = f"regexp_extract_all(text, '{q}', 2)" if kind == "assign" else "m"
        least = ASSIGN_LEAST if kind == "assign" else 0
        parts.append(f"""SELECT doc_id, {n} AS kind, '{kind}' AS name, CAST(list_sum(list_transform(p[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(m[1:i - 1], lambda x: length(x))), 0) AS BIGINT) AS s, length(m[i]) AS n
    FROM (SELECT *, unnest(range(1, len(m) + 1)) AS i FROM (SELECT doc_id, m, {group} AS g, string_split_regex(text, '{q}') AS p FROM (SELECT *, regexp_extract_all(text, '{q}') AS m FROM d) WHERE len(m) > 0)) WHERE length(g[i]) >= {least}""")
    patterns = list(dict.fromkeys(c.pattern for c in (*CLASSES, *KEY_CLASSES)))
    cands = [
        f"""SELECT doc_id, {k} AS pat, m[i] AS v, CAST(list_sum(list_transform(p[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(m[1:i - 1], lambda x: length(x))), 0) AS BIGINT) AS s
    FROM (SELECT *, unnest(range(1, len(m) + 1)) AS i FROM (SELECT doc_id, m, string_split_regex(text, '{r}') AS p FROM (SELECT *, regexp_extract_all(text, '{r}') AS m FROM d) WHERE len(m) > 0))"""
        for k, r in enumerate(patterns)
    ]
    named = f"(length(v) BETWEEN {KEY_WINDOWS[0]} AND {KEY_WINDOWS[1] - 1} AND regexp_matches(v, '{NAMED.replace('(?=.{16,23}$)', '')}'))"
    walks = []
    for i, c in enumerate((*CLASSES, *KEY_CLASSES)):
        key = i >= len(CLASSES)
        allowed = lambda v, pats, key=key: " OR ".join([f"regexp_matches({v}, '{a}')" for a in pats] + ([named.replace("(v", f"({v}")] if key else []))
        more = f" AND length(v) <= {c.longest}" if c.longest else ""
        more += "".join(f" AND regexp_matches(v, '{n}')" for n in c.needs)
        whole = [a for a in ALLOW if c.whole or a.startswith("^")]
        hot = f"""SELECT doc_id, s, v, min(i) AS a, max(i) AS b FROM (
    SELECT doc_id, s, v, i, sum({weights(c.window)}[n + 1]) AS total FROM (
      SELECT doc_id, s, v, i, ch, count(*) AS n FROM (SELECT doc_id, s, v, i, unnest(string_split(substr(v, CAST(i + 1 AS BIGINT), {c.window}), '')) AS ch
        FROM (SELECT *, unnest(range(0, length(v) - {c.window} + 1)) AS i FROM cand WHERE pat = {patterns.index(c.pattern)} AND length(v) >= {c.window}{more} AND NOT ({allowed("v", whole)}))) GROUP BY ALL) GROUP BY doc_id, s, v, i) WHERE total <= {most(c)} GROUP BY doc_id, s, v"""
        if c.whole:
            walks.append(f"SELECT doc_id, s, s + length(v) AS e FROM ({hot})")
        else:
            walks.append(f"SELECT doc_id, s + a AS s, s + b + {c.window} AS e FROM (SELECT doc_id, s, a, b, substr(v, CAST(a + 1 AS BIGINT), CAST(b + {c.window} - a AS BIGINT)) AS v FROM ({hot})) WHERE NOT ({allowed('v', ALLOW)})")
    return rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
base AS (SELECT doc_id, kind, name, s, s + n AS e FROM ({" UNION ALL ".join(parts)})),
cand AS ({" UNION ALL ".join(cands)}),
hot AS (SELECT DISTINCT doc_id, s, e FROM ({" UNION ALL ".join(walks)})),
outer_ AS (SELECT h.* FROM hot h WHERE NOT EXISTS (SELECT 1 FROM hot g WHERE g.doc_id = h.doc_id AND g.s <= h.s AND h.e <= g.e AND (g.s <> h.s OR g.e <> h.e))),
begin_ AS (SELECT doc_id, s AS a, e FROM outer_ UNION SELECT h.doc_id, b.e, h.e FROM outer_ h JOIN base b ON b.doc_id = h.doc_id AND b.e > h.s AND b.e < h.e),
piece AS (SELECT doc_id, a, least(e, coalesce((SELECT min(b.s) FROM base b WHERE b.doc_id = x.doc_id AND b.s > x.a), e)) AS e FROM begin_ x
  WHERE NOT EXISTS (SELECT 1 FROM base b WHERE b.doc_id = x.doc_id AND b.s <= x.a AND x.a < b.e)),
free AS (SELECT DISTINCT doc_id, a AS s, e FROM piece WHERE e - a >= {LEFT_LEAST}),
every AS (SELECT * FROM base UNION ALL SELECT doc_id, 3, 'entropy', s, e FROM free)
SELECT d.doc_id, count(*) FILTER (kind = 0) AS n_assign, count(*) FILTER (kind = 1) AS n_access, count(*) FILTER (kind = 2) AS n_hex,
  sha256(coalesce(string_agg(name || ':' || s || ':' || e, ',' ORDER BY s, kind, e) FILTER (kind < 3), '')) AS base_sha256,
  coalesce(string_agg(name || ':' || s || ':' || e, ',' ORDER BY s, kind, e), '') AS spans
FROM d LEFT JOIN every USING (doc_id) GROUP BY d.doc_id
"""


SECRETS_SQL = _secrets_sql()
