"""URL verdicts with built-in functions only: host and path rules first, then a logistic regression.

The model sees hashed character trigrams of host and path; it is fitted on a small labelled table of URLs
and its weights, scaled to integers, become one array literal of fixed size in the plan.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import lru_cache

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenlane.llm.common import by_place, free_name

BUCKETS = 4096
MAX_LABELS = 10_000  # rows of the labelled table that a fit may take: it runs on the driver
SCALE = 1000
_PRIMES = (7919, 104_729, 1_299_709, 15_485_863)

# The rules (host, path, verdict).
RULES = (("com", "/en/", "block"), ("example.com", "/en/7", "allow"), ("net", "/de/", "allow"), ("example.net", "/de/8", "block"), ("org", "/es/", "block"))

# The labelled table: common words of the names of advertising, adult, gambling, drug, piracy, fraud and link-selling sites, and of other sites.
BAD_WORDS = (
    "ads", "adserver", "adclick", "banner", "popup", "popunder", "tracker", "tracking", "clicks", "affiliate", "sponsor", "adult", "porn", "xxx", "sex", "sexy", "nude", "cams", "webcam", "escort", "dating", "hookup",
    "casino", "poker", "jackpot", "slots", "betting", "bets", "gamble", "roulette", "lotto", "pills", "viagra", "cialis", "pharma", "pharmacy", "steroid", "cheap", "discount", "replica", "warez", "crack", "cracked", "keygen", "serial",
    "torrent", "pirate", "phish", "malware", "hacked", "spam", "spammer", "linkfarm", "backlink", "seo", "payday", "loans", "credit", "rich", "bitcoin", "doubler", "giveaway", "winner", "prize", "freebie",
)
GOOD_WORDS = (
    "news", "daily", "times", "journal", "post", "herald", "press", "university", "college", "school", "campus", "library", "museum", "archive", "gallery", "theatre", "wiki", "docs", "manual", "help", "support", "developer", "code", "open",
    "forum", "community", "blog", "diary", "recipes", "kitchen", "cooking", "garden", "flowers", "travel", "hotel", "railway", "airport", "music", "concert", "film", "cinema", "books", "reading", "poetry", "science", "physics", "nature",
    "health", "clinic", "hospital", "city", "town", "council", "gov", "parks", "weather", "sports", "football", "tennis", "cycling", "auto", "design", "photo", "studio", "craft", "furniture", "bakery", "coffee", "family", "parents",
)
_FRONTS, _ENDS = ("", "www.", "m.", "blog.", "shop."), (".com/", ".org/index.html", ".net/page/3", ".info/a?id=7", ".com/2019/04/title", ".org/en/")


def invented(n: int) -> list[str]:
    """n names of no meaning, syllable by syllable from a fixed sequence: most sites have such a name, and they are good."""
    out, x = [], 12_345
    for i in range(n):
        name = ""
        for _ in range(2 + i % 3):
            x = (1_103_515_245 * x + 12_345) % 2**31
            name += "bcdfghjklmnprstvwyz"[(x >> 16) % 19] + "aeiou"[(x >> 8) % 5] + ("", "n", "r", "s", "l")[(x >> 24) % 5]
        out.append(name)
    return out


def labelled(bad: tuple[str, ...] = BAD_WORDS, good: tuple[str, ...] = GOOD_WORDS, names: int = 240) -> tuple[tuple[str, int], ...]:
    """(url, 1 for bad): hosts of one word, of two, and of an invented name with a word; fronts and ends fall on both kinds alike."""
    made = invented(names)
    hosts = []
    for words, y in ((bad, 1), (good, 0)):
        for i, w in enumerate(words):
            hosts += [(w, y), (f"{w}-{words[(i + 7) % len(words)]}", y), (f"{w}{words[(i + 17) % len(words)]}", y), (f"{made[(3 * i + 1) % names]}-{w}", y), (f"{w}{made[(5 * i + 2) % names]}", y)]
    hosts += [(h, 0) for h in made] + [(f"{a}-{b}", 0) for a, b in zip(made, made[9:], strict=False)]
    return tuple((f"https://{_FRONTS[i % 5]}{h}{_ENDS[i % 6]}", y) for i, (h, y) in enumerate(hosts))


def split_url(url: str | None) -> tuple[str, str]:
    """Host and path as the plan gets them."""
    at = (url or "").find("://")
    if at < 0:
        return "", ""
    rest = url[at + 3 :]
    end = min([i for i in map(rest.find, "/?#") if i >= 0], default=len(rest))
    host, tail = rest[:end], rest[end:]
    stop = min([i for i in map(tail.find, "?#") if i >= 0], default=len(tail))
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host), tail[:stop]


def grams(host: str, path: str) -> list[int]:
    """Bucket of every trigram of the marked host and path."""
    out = []
    for field, s in enumerate((f"^{host}$", f"^{path}$"), 1):
        c = list(map(ord, s))
        out += [(a * _PRIMES[0] + b * _PRIMES[1] + d * _PRIMES[2] + field * _PRIMES[3]) % BUCKETS for a, b, d in zip(c, c[1:], c[2:], strict=False)]
    return out


@dataclass(frozen=True)
class UrlModel:
    """Integer weights; a URL is bad if their sum over its trigrams, plus the bias a trigram, is over 0."""

    weights: tuple[int, ...]
    bias: int

    def score(self, host: str, path: str) -> int:
        g = grams(host, path)
        return sum(self.weights[i] for i in g) + self.bias * len(g)


@lru_cache(maxsize=8)
def fit(labels: tuple[tuple[str, int], ...] | None = None, epochs: int = 120, rate: float = 40.0, decay: float = 1e-5) -> UrlModel:
    """Logistic regression on mean trigram counts by full gradient steps, both classes weighing alike."""
    labels = labelled() if labels is None else labels
    if not 0 < len(labels) <= MAX_LABELS:
        raise ValueError(f"the labelled table must hold 1 to {MAX_LABELS} rows")
    rows = []
    for url, y in labels:
        g = grams(*split_url(url))
        if g:
            rows.append((g, y, 1.0 / len(g)))
    total = {y: max(1, sum(r[1] == y for r in rows)) for y in (0, 1)}
    w, b = [0.0] * BUCKETS, 0.0
    for _ in range(epochs):
        step, sb = {}, 0.0
        for g, y, s in rows:
            z = b + s * sum(w[i] for i in g)
            e = (y - 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))) / total[y]
            sb += e
            for i in g:
                step[i] = step.get(i, 0.0) + e * s
        for i, v in step.items():
            w[i] = w[i] * (1 - rate * decay) + rate * v
        b += 0.5 * sb
    return UrlModel(tuple(round(SCALE * x) for x in w), round(SCALE * b))


def host_path(url: Column) -> tuple[Column, Column]:
    at = F.call_function("instr", url, F.lit("://"))
    rest = F.when(at > 0, F.call_function("substring", url, at + 3)).otherwise("")
    host = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(F.call_function("substring", rest, F.length(host) + 1), "^[^?#]*", 0)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def model_score(host: Column, path: Column, m: UrlModel) -> Column:
    table = F.array(*map(F.lit, m.weights))

    def part(s: Column, field: int) -> Column:
        codes = F.transform(F.regexp_extract_all(F.concat(F.lit("^"), s, F.lit("$")), F.lit("(?s)."), F.lit(0)), lambda c: F.ascii(c).cast("long"))
        # state: the two codes before, how many there were, and the sum over the trigrams so far
        state = F.struct(F.lit(0).cast("long").alias("a"), F.lit(0).cast("long").alias("b"), F.lit(0).alias("n"), F.lit(0).cast("long").alias("sum"))

        def step(t: Column, c: Column) -> Column:
            at = F.pmod(t["a"] * _PRIMES[0] + t["b"] * _PRIMES[1] + c * _PRIMES[2] + field * _PRIMES[3], F.lit(BUCKETS)).cast("int")
            return F.struct(t["b"].alias("a"), c.alias("b"), (t["n"] + 1).alias("n"), (t["sum"] + F.when(t["n"] >= 2, table[at] + m.bias).otherwise(0)).alias("sum"))

        return F.aggregate(codes, state, step, lambda t: t["sum"])

    return part(host, 1) + part(path, 2)


def judged(pages: DataFrame, url: Column, rules, model: UrlModel) -> DataFrame:
    """pages (names without "__") with __host, __path, __rule and __verdict."""
    host, path = host_path(url)
    d = pages.withColumns({"__host": F.coalesce(host, F.lit("")), "__path": F.coalesce(path, F.lit(""))})
    fitting = [(h + p, v, ((F.col("__host") == h) | F.col("__host").endswith("." + h)) & F.col("__path").startswith(p)) for h, p, v in sorted(rules, key=lambda r: (-len(r[0] + r[1]), r))]
    pick = lambda k: F.coalesce(*[F.when(x[2], F.lit(x[k])) for x in fitting]) if fitting else F.lit(None).cast("string")
    d = d.withColumn("__rule", pick(0))
    learnt = F.when(model_score(F.col("__host"), F.col("__path"), model) > 0, "block").otherwise("allow")
    return d.withColumn("__verdict", F.coalesce(pick(1), learnt))


def filter_urls(pages: DataFrame, url_col: str = "url", rules=RULES, model: UrlModel | None = None) -> DataFrame:
    """pages with __host, __path, __rule and __verdict.

    Null URLs and those without "://" have an empty host and path and go to the model. Among fitting
    rules the longest (host and path together) wins. Repeated rows are judged alike; an empty table gives an
    empty result. Input columns pass through whatever their names; a new name that the input has gets
    underscores at its end.
    """
    out = judged(by_place(pages), F.col(f"c{pages.columns.index(url_col)}"), rules, model or fit())
    return out.toDF(*pages.columns, *[free_name(pages.columns, c) for c in ("__host", "__path", "__rule", "__verdict")])


def url_filter_query(spark, sf_dir: str) -> DataFrame:
    d = judged(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url"), F.col("url"), RULES, fit())
    return d.select("page_id", F.col("__host").alias("host"), F.col("__path").alias("path"), F.col("__rule").alias("rule"), F.col("__verdict").alias("verdict"))


def url_filter_sql() -> str:
    m = fit()
    rules = sorted(RULES, key=lambda r: (-len(r[0] + r[1]), r))
    case = lambda k: "CASE " + " ".join(f"WHEN (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}') THEN '{(h + p, v)[k]}'" for h, p, v in rules) + " END"
    return f"""
WITH a AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
b AS (SELECT page_id, rest, regexp_extract(rest, '^[^/?#]*', 0) AS h FROM a),
c AS (SELECT page_id, translate(h, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(substr(rest, length(h) + 1), '^[^?#]*', 0) AS path FROM b),
g AS (SELECT page_id, f, unnest(range(1, length(s) - 1)) AS i, s FROM (
  SELECT page_id, 1 AS f, '^' || host || '$' AS s FROM c UNION ALL SELECT page_id, 2, '^' || path || '$' FROM c)),
w AS (SELECT page_id, sum({list(m.weights)}[CAST((unicode(substr(s, i, 1)) * {_PRIMES[0]} + unicode(substr(s, i + 1, 1)) * {_PRIMES[1]}
  + unicode(substr(s, i + 2, 1)) * {_PRIMES[2]} + f * {_PRIMES[3]}) % {BUCKETS} + 1 AS BIGINT)] + {m.bias}) AS score FROM (SELECT page_id, CAST(f AS BIGINT) AS f, CAST(i AS BIGINT) AS i, s FROM g) GROUP BY page_id)
SELECT c.page_id, host, path, {case(0)} AS rule, coalesce({case(1)}, CASE WHEN coalesce(score, 0) > 0 THEN 'block' ELSE 'allow' END) AS verdict
FROM c LEFT JOIN w USING (page_id)
"""
