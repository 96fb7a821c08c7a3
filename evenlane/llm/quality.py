"""Quality rules with thresholds learnt from mergeable quantile sketches per language and source.

Fixed base rules come first (too few words, too many repeated 5-word windows). Documents that pass
them feed deterministic log-linear sketches, one per (language, source, feature): a sketch is a map
from bucket to count, so sketches merge by adding counts, and groups roll up into languages and
into the whole table. A limit comes from quantiles alone: the median plus a multiple of the distance from the
10th percentile to it, or, from below, the median less a multiple of the distance to the 90th. Junk lies on the far
side, so half of a group may be junk without moving the near one.

A group's quantiles are weighed with its language's as n rows against `weight`, and the language's
likewise with the table's: small groups lean on their parents, large ones go by their own. Where more than half of a
group is junk its own limit is worthless, so no upper limit passes the parent's median by more than
twice the distance that the parent's own limit does. The spread that is left even where all quantiles agree is that of
chance: a document's count may pass what its limit's rate makes likely for a text of its length by three
deviations and one.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenlane.llm.common import WORD_HASHES, by_place, free_name, mix64, ship, trimmed, utf8
from evenlane.staging import stage

U64 = np.uint64
SYMBOLS = b"#*$%&|<>"
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_adjacent", "n_caps")
#: The two counts behind a feature, and its units: thousandths, word_length in tenths of a character.
FEATURES = {
    "symbols": ("n_symbols", "word_chars", 1000), "dup_lines": ("n_dup_lines", "n_lines", 1000), "adjacent": ("n_adjacent", "n_words", 1000),
    "caps": ("n_caps", "word_chars", 1000), "word_length": ("word_chars", "n_words", 10),
}  # fmt: skip


@dataclass(frozen=True)
class QualityParams:
    min_words: int = 10
    repeat_percent: int = 20
    window: int = 5
    spread: int = 4
    weight: int = 100  # rows that a group's parent counts for


def _repeated(words: list[bytes], k: int) -> int:
    """Words inside k-word windows that occur twice or more in the text."""
    n = len(words)
    if n <= k:
        return 0
    h = np.fromiter(map(WORD_HASHES.__getitem__, words), U64, n)
    acc = h[: n - k + 1].copy()
    for i in range(1, k):
        acc = mix64(acc * U64(0x9E3779B97F4A7C15) + h[i : n - k + 1 + i])
    order = np.argsort(acc, kind="stable")
    s = acc[order]
    same = s[1:] == s[:-1]
    if not same.any():
        return 0
    twice = np.zeros(len(s), bool)
    twice[1:] |= same
    twice[:-1] |= same
    mark = np.zeros(n + 1, np.int64)
    at = order[twice]
    mark[at] += 1
    np.subtract.at(mark, at + k, 1)
    return int(np.count_nonzero(np.cumsum(mark[:n])))


def count_text(text: bytes, window: int = 5) -> tuple[int, ...]:
    """The counts named in COUNTS for one text."""
    words = text.split()
    joined = b"".join(words)
    chars = len(joined.decode("utf-8", "replace"))
    symbols = len(text) - len(text.translate(None, SYMBOLS))
    caps = len(joined) - len(joined.translate(None, b"ABCDEFGHIJKLMNOPQRSTUVWXYZ"))
    lines = [x for x in text.split(b"\n") if x and not x.isspace()]
    adjacent = sum(map(bytes.__eq__, words, words[1:])) if len(words) > 1 else 0
    return len(words), chars, symbols, len(lines) - len(set(lines)), _repeated(words, window), len(lines), adjacent, caps


def _counted(text_at: int, window: int, keep_text: bool):
    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                b = whole.slice(at, 512)
                rows = [count_text(t, window) for t in utf8(b.column(text_at))]
                values = np.array(rows, np.int64).reshape(-1, len(COUNTS))
                counts = pa.StructArray.from_arrays([pa.array(values[:, i]) for i in range(len(COUNTS))], names=list(COUNTS))
                kept = [i for i in range(b.num_columns) if keep_text or i != text_at]
                yield pa.RecordBatch.from_arrays([*[b.column(i) for i in kept], counts], names=[*[b.schema.names[i] for i in kept], "__counts"])

    return trimmed(run)


def with_counts(docs: DataFrame, text_col: str, window: int = 5, keep_text: bool = True) -> DataFrame:
    """docs, with or without its texts, with a struct column __counts of the counts of each text."""
    ship(docs.sparkSession)
    at = docs.columns.index(text_col)
    out = ", ".join(f"{n} {t}" for i, (n, t) in enumerate(docs.dtypes) if keep_text or i != at)
    schema = out + ", __counts struct<" + ",".join(f"{c}:bigint" for c in COUNTS) + ">"
    return docs.mapInArrow(_counted(at, window, keep_text), schema)


def base_failed(p: QualityParams, c: str = "__counts") -> Column:
    return (F.col(f"{c}.n_words") < p.min_words) | (100 * F.col(f"{c}.n_repeat_words") > p.repeat_percent * F.col(f"{c}.n_words"))


def feature_values(c: str = "__counts") -> dict[str, Column]:
    return {f: F.expr(f"{unit} * {c}.{k} div greatest({c}.{n}, 1)") for f, (k, n, unit) in FEATURES.items()}


def fits(feature: str, up: Column, down: Column, c: str = "__counts") -> Column:
    """Whether a text's count is likely under limits in hundredths of the feature's units.

    Counts of events spread like the root of their mean, sums of word lengths like the mean length times
    the root of the number of words: short texts pass with what would be junk in long ones.
    """
    k, n, unit = FEATURES[feature]
    k, n = F.col(f"{c}.{k}").cast("double"), F.col(f"{c}.{n}").cast("double")
    mean = up * n / F.lit(100.0 * unit)
    if feature != "word_length":
        return k <= mean + 3 * F.sqrt(mean + 1) + 1
    least = down * n / F.lit(100.0 * unit)
    return (k <= mean + 3 * up / F.lit(100.0 * unit) * F.sqrt(n) + 1) & (k >= least - 3 * down / F.lit(100.0 * unit) * F.sqrt(n) - 1)


def bucket(v: Column) -> Column:
    """Log-linear bucket, named by its smallest value: exact below 128, then 64 to an octave."""
    shift = F.greatest(F.length(F.conv(v.cast("string"), 10, 2)) - 7, F.lit(0))
    return F.call_function("shiftleft", F.call_function("shiftright", v, shift), shift)


def limits(counted: DataFrame, p: QualityParams, lang: str, source: str) -> DataFrame:
    """Rows (lang, source, limits): for each feature the upper and lower limit in hundredths of its units, from merged sketches."""
    f = feature_values()
    rows = counted.where(~base_failed(p)).select(
        F.coalesce(F.col(lang), F.lit("")).alias("lang"), F.coalesce(F.col(source), F.lit("")).alias("source"),
        F.explode(F.array(*[F.struct(F.lit(k).alias("feature"), bucket(v).alias("bucket")) for k, v in f.items()])).alias("x"),
    )  # fmt: skip
    sketch = stage(rows.groupBy("lang", "source", F.col("x.feature").alias("feature"), F.col("x.bucket").alias("bucket")).agg(F.count("*").alias("n")), "quality-sketch")

    def quantiles(keys: list[str], name: str) -> DataFrame:
        merged = sketch.groupBy(*keys, "feature", "bucket").agg(F.sum("n").alias("n"))
        lists = merged.groupBy(*keys, "feature").agg(F.sum("n").alias("total"), F.array_sort(F.collect_list(F.struct("bucket", "n"))).alias("s"))
        at = lambda q: F.expr(f"100 * aggregate(s, named_struct('c', 0L, 'v', cast(null as bigint)), (a, x) -> named_struct('c', a.c + x.n, 'v', case when a.v is null and 100 * (a.c + x.n) >= {q} * total then x.bucket else a.v end), a -> a.v)")  # noqa: E731
        return lists.select(*keys, "feature", F.col("total").alias(f"{name}_n"), F.struct(at(10).alias("low"), at(50).alias("mid"), at(90).alias("high")).alias(name))

    j = quantiles(["lang", "source"], "own").join(quantiles(["lang"], "of"), ["lang", "feature"]).join(quantiles([], "all"), "feature")
    mix = lambda n, a, b: F.struct(*[F.expr(f"({n} * {a}.{x} + {p.weight} * {b}.{x}) div ({n} + {p.weight})").alias(x) for x in ("low", "mid", "high")])  # noqa: E731
    j = j.withColumn("of", mix("of_n", "of", "all")).withColumn("own", mix("own_n", "own", "of"))
    own, of, whole = F.col("own"), F.col("of"), F.col("all")
    beyond = lambda q, times: q["mid"] + times * p.spread * (q["mid"] - q["low"])  # noqa: E731
    up = F.least(beyond(own, 1), beyond(of, 2), beyond(whole, 2))
    down = F.greatest(own["mid"] - p.spread * (own["high"] - own["mid"]), F.lit(0))
    return j.groupBy("lang", "source").agg(F.map_from_entries(F.collect_list(F.struct("feature", F.struct(up.cast("double").alias("up"), down.cast("double").alias("down"))))).alias("limits"))


def judged(docs: DataFrame, p: QualityParams, lang: str, source: str, text: str, keep_text: bool) -> DataFrame:
    """docs (names without "__") with __counts, __base_failed and __kept; each text is counted once, into a table."""
    counted = stage(with_counts(docs, text, p.window, keep_text), "quality-counts")
    lim = stage(limits(counted, p, lang, source), "quality-limits").toDF("__lang", "__source", "__limits")
    on = (F.coalesce(F.col(lang), F.lit("")) == F.col("__lang")) & (F.coalesce(F.col(source), F.lit("")) == F.col("__source"))
    fine = F.lit(True)
    for k in FEATURES:
        fine &= fits(k, F.col("__limits")[k]["up"], F.col("__limits")[k]["down"])
    j = counted.withColumn("__base_failed", base_failed(p)).join(lim, on, "left")
    return j.withColumn("__kept", ~F.col("__base_failed") & F.coalesce(fine, F.lit(True))).drop("__lang", "__source", "__limits")


def quality_verdicts(docs: DataFrame, params: QualityParams | None = None, text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """docs with __counts, __base_failed and __kept.

    Null or empty text has no words and fails the base rules; null languages and sources form the group
    of the empty string; repeated rows are judged alike; an empty table gives an empty result. Input
    columns pass through whatever their names; a new name that the input has gets underscores at its end.
    """
    at = {c: f"c{i}" for i, c in enumerate(docs.columns)}
    out = judged(by_place(docs), params or QualityParams(), at[lang_col], at[source_col], at[text_col], True)
    return out.toDF(*docs.columns, *[free_name(docs.columns, c) for c in ("__counts", "__base_failed", "__kept")])


def good_documents(docs: DataFrame, params: QualityParams | None = None) -> DataFrame:
    """The rows of docs that are kept, with its columns text, lang and source judged."""
    out = quality_verdicts(docs, params)
    return out.where(F.col(out.columns[-1])).select(*docs.columns)


def quality_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang", "source")
    v = judged(docs, QualityParams(), "lang", "source", "text", False)
    c = F.col("__counts")
    return v.select("doc_id", *[c[k].alias(k) for k in COUNTS[:5]], F.col("__base_failed").alias("base_failed"), F.col("__kept").alias("kept"))


def _quality_sql(p: QualityParams) -> str:
    feats = ", ".join(f"CAST({unit} * {k} // greatest({n}, 1) AS BIGINT) AS {f}" for f, (k, n, unit) in FEATURES.items())
    quant = "100 * min(CASE WHEN 100 * cum >= {q} * total THEN b END)"
    qs = ", ".join(f"CAST({quant.format(q=q)} AS BIGINT) AS {name}" for q, name in ((10, "low"), (50, "mid"), (90, "high")))
    level = lambda name, keys: f"""{name}_m AS (SELECT {keys} feature, b, sum(n) AS n FROM sk GROUP BY {keys} feature, b),
{name}_c AS (SELECT *, sum(n) OVER (PARTITION BY {keys} feature ORDER BY b) AS cum, sum(n) OVER (PARTITION BY {keys} feature) AS total FROM {name}_m),
{name} AS (SELECT {keys} feature, CAST(total AS BIGINT) AS total, {qs} FROM {name}_c GROUP BY {keys} feature, total)"""  # noqa: E731
    mix = lambda n, a, b: ", ".join(f"({n} * {a}.{x} + {p.weight} * {b}.{x}) // ({n} + {p.weight}) AS {x}" for x in ("low", "mid", "high"))  # noqa: E731
    beyond = lambda q, times: f"{q}.mid + {times * p.spread} * ({q}.mid - {q}.low)"  # noqa: E731
    checks = []
    for f, (k, n, unit) in FEATURES.items():
        up, down = f"lw.{f}_up", f"lw.{f}_down"
        mean, k, n = f"{up} * CAST(f.{n} AS DOUBLE) / {100.0 * unit}", f"CAST(f.{k} AS DOUBLE)", f"CAST(f.{n} AS DOUBLE)"
        if f == "word_length":
            checks.append(f"{k} <= {mean} + 3 * {up} / {100.0 * unit} * sqrt({n}) + 1 AND {k} >= {down} * {n} / {100.0 * unit} - 3 * {down} / {100.0 * unit} * sqrt({n}) - 1")
        else:
            checks.append(f"{k} <= {mean} + 3 * sqrt({mean} + 1) + 1")
    return rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, coalesce(lang, '') AS lang, coalesce(source, '') AS source FROM documents),
w AS (SELECT *, regexp_extract_all(text, '[^ 	-]+') AS ws,
  list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^ 	-]')) AS ls FROM d),
g AS (SELECT doc_id, unnest(range(1, len(ws) - 3)) AS i, ws FROM w WHERE len(ws) >= 5),
h AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, ws[i:i + 4]) AS n FROM g),
r AS (SELECT doc_id, count(DISTINCT j) AS n_repeat FROM (SELECT doc_id, unnest(range(i, i + 5)) AS j FROM h WHERE n > 1) GROUP BY doc_id),
c AS (SELECT w.doc_id, lang, source, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
  CAST(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
  CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) AS n_dup_lines, CAST(coalesce(r.n_repeat, 0) AS BIGINT) AS n_repeat_words,
  CAST(len(ls) AS BIGINT) AS n_lines, CAST(len(list_filter(range(1, len(ws)), lambda i: ws[i] = ws[i + 1])) AS BIGINT) AS n_adjacent,
  CAST(length(text) - length(regexp_replace(text, '[A-Z]', '', 'g')) AS BIGINT) AS n_caps FROM w LEFT JOIN r USING (doc_id)),
f AS (SELECT *, n_words < {p.min_words} OR 100 * n_repeat_words > {p.repeat_percent} * n_words AS base_failed, {feats} FROM c),
v AS (SELECT lang, source, feature, value, greatest(length(bin(value)) - 7, 0) AS s
  FROM (UNPIVOT (SELECT lang, source, {", ".join(FEATURES)} FROM f WHERE NOT base_failed) ON {", ".join(FEATURES)} INTO NAME feature VALUE value)),
sk AS (SELECT lang, source, feature, (value >> s) << s AS b, count(*) AS n FROM v GROUP BY ALL),
{level("own", "lang, source,")},
{level("bl", "lang,")},
{level("al", "")},
ml AS (SELECT bl.lang, bl.feature, {mix("bl.total", "bl", "al")} FROM bl JOIN al USING (feature)),
mo AS (SELECT own.lang, own.source, own.feature, {mix("own.total", "own", "ml")} FROM own JOIN ml ON own.lang = ml.lang AND own.feature = ml.feature),
l AS (SELECT mo.lang, mo.source, mo.feature, CAST(least({beyond("mo", 1)}, {beyond("ml", 2)}, {beyond("al", 2)}) AS DOUBLE) AS up,
  CAST(greatest(mo.mid - {p.spread} * (mo.high - mo.mid), 0) AS DOUBLE) AS down
  FROM mo JOIN ml ON mo.lang = ml.lang AND mo.feature = ml.feature JOIN al ON al.feature = mo.feature),
lw AS (SELECT lang, source, {", ".join(f"max(up) FILTER (feature = '{f}') AS {f}_up, max(down) FILTER (feature = '{f}') AS {f}_down" for f in FEATURES)} FROM l GROUP BY lang, source)
SELECT f.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND coalesce({" AND ".join(checks)}, true) AS kept
FROM f LEFT JOIN lw ON f.lang = lw.lang AND f.source = lw.source
"""


QUALITY_SQL = _quality_sql(QualityParams())
