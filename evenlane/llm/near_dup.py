"""Near-duplicate detection: MinHash bands propose pairs, odd sketches screen them, full sets confirm.

Plan
1. One Arrow pass per document: distinct 5-word shingles (64-bit), a 128-bit digest of the set,
   MinHash band keys, and an odd sketch (MinHash samples folded into a parity bitmap).
2. Equal sets collapse to their smallest doc_id, so groups of copies never meet in a bucket.
3. Every band bucket names a pseudo-random centre, the same one wherever it occurs, and pairs its
   members with it: linear in rows, and about one pair a document in a tight group.
   Sketch XOR population counts drop hopeless pairs, full sets confirm the rest, components follow.
4. Only buckets that still hold several components are searched in full, in blocks of bounded size,
   on sketches; first for each member's best partners, twice, then for all that remain. For the
   latter, members without any promising partner leave, and the others compare sketches of five times
   the samples. Pairs inside one component are skipped, since they cannot change the result.

Missed links: a pair at similarity s shares no band with probability (1 - s^4)^36, 1e-6 at 0.75 and
3e-9 at 0.8; the sketch screens keep a pair of similarity 0.75 unless its estimate is off by more
than 4.2 standard deviations (measured: 0.026 and 0.0105). There is no cap on partners.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenlane.llm.common import WORD_HASHES, by_place, components, mix64, ship, trimmed, utf8
from evenlane.staging import discard, stable, stage

U64 = np.uint64
SALTS = 64


@dataclass(frozen=True)
class NearDupParams:
    words: int = 5
    num: int = 75  # linked when 100 * intersection >= num * union
    bands: int = 36
    rows: int = 4
    samples: int = 384  # MinHash samples folded into the sketch; the bands use the first of them
    bits: int = 1024
    screen: float = 0.64  # sketch estimates below this are dropped without reading full sets
    deep_samples: int = 2048
    deep_bits: int = 8192
    deep_screen: float = 0.705
    best: int = 4  # partners of a member and bucket in each of the first full searches
    tries: int = 2  # such searches
    block: int = 1_000  # members of a bucket compared in one task


def shingles(text: bytes, k: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the k-word shingles; shorter texts give one, empty ones none."""
    words = text.lower().split()  # bytes: A-Z only, and white space is \\x20 \\x09-\\x0D only
    n = len(words)
    if n == 0:
        return np.empty(0, U64)
    h = np.fromiter(map(WORD_HASHES.__getitem__, words), U64, n)
    if n < k:
        return np.array([xxhash.xxh3_64_intdigest(h.tobytes(), seed=n)], U64)
    acc = h[: n - k + 1].copy()
    for i in range(1, k):
        acc = mix64(acc * U64(0x9E3779B97F4A7C15) + h[i : n - k + 1 + i])
    return np.unique(acc)


def _coefficients(samples: int) -> tuple[np.ndarray, np.ndarray]:
    x = mix64(np.arange(1, 2 * samples + 1, dtype=U64) * U64(0x9E3779B97F4A7C15))
    return (x[:samples] >> U64(32)).astype(np.uint32) | np.uint32(1), (x[samples:] >> U64(32)).astype(np.uint32)


def minhashes(flat: np.ndarray, starts: np.ndarray, samples: int) -> np.ndarray:
    """MinHash samples of the non-empty sets laid end to end in flat: samples x sets, uint32."""
    a, b = _coefficients(samples)
    base = (flat >> U64(32)).astype(np.uint32)
    out = np.empty((samples, len(starts)), np.uint32)
    v = np.empty_like(base)
    for j in range(samples):
        np.bitwise_xor(base, b[j], out=v)
        np.multiply(v, a[j], out=v)
        out[j] = np.minimum.reduceat(v, starts)
    return out


def odd_sketches(mins: np.ndarray, bits: int) -> np.ndarray:
    """Parity bitmaps (sets x bits/8 bytes): each sample, with its index, flips one bit."""
    samples, n = mins.shape
    salt = (np.arange(samples, dtype=U64) << U64(32))[:, None]
    where = (mix64((mins.astype(U64) | salt) * U64(0x9E3779B97F4A7C15)) % U64(bits)).astype(np.int64)
    where += np.arange(n, dtype=np.int64)[None, :] * bits
    parity = (np.bincount(where.ravel(), minlength=n * bits) & 1).astype(np.uint8)
    return np.packbits(parity.reshape(n, bits), axis=1)


def band_keys(mins: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """One 64-bit key a band and set (sets x bands)."""
    acc = np.repeat(np.arange(1, bands + 1, dtype=U64)[:, None], mins.shape[1], 1)
    m = mins[: bands * rows].reshape(bands, rows, -1)
    for r in range(rows):
        acc = mix64(acc * U64(0x9E3779B97F4A7C15) + m[:, r].astype(U64))
    return acc.T.view(np.int64)


def estimate(xor_bits: np.ndarray, samples: int, bits: int) -> np.ndarray:
    """Similarity from the population count of two sketches' XOR."""
    odd = np.minimum(1 - 2.0 * xor_bits / bits, 1.0)
    differ = np.log(np.maximum(odd, 1e-9)) / np.log(1 - 2.0 / bits)
    return 1 - differ / (2.0 * samples)


def largest_xor(samples: int, bits: int, screen: float) -> int:
    """The largest XOR population count whose estimate still passes the screen."""
    return int(np.searchsorted(-estimate(np.arange(bits + 1), samples, bits), -screen, side="right")) - 1


def _features(p: NearDupParams):
    schema = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("hi", pa.int64()), ("lo", pa.int64()), ("bands", pa.list_(pa.int64())), ("sketch", pa.binary())])

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                b = whole.slice(at, 256)
                sets = [shingles(t, p.words) for t in utf8(b.column(1))]
                n = np.array([len(s) for s in sets], np.int64)
                full = np.flatnonzero(n)
                sketch, keys = [None] * len(sets), [None] * len(sets)
                if len(full):
                    flat = np.concatenate([sets[i] for i in full])
                    starts = np.concatenate([[0], np.cumsum(n[full])[:-1]])
                    mins = minhashes(flat, starts, p.samples)
                    for i, s, k in zip(full, odd_sketches(mins, p.bits), band_keys(mins, p.bands, p.rows), strict=True):
                        sketch[i], keys[i] = s.tobytes(), k
                d = [xxhash.xxh3_128_digest(s.tobytes()) for s in sets]
                d = np.frombuffer(b"".join(d), np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n), pa.array(d[:, 0]), pa.array(d[:, 1]), pa.array(keys, pa.list_(pa.int64())), pa.array(sketch, pa.binary())], schema=schema)

    return trimmed(run)


def _sets(p: NearDupParams):
    schema = pa.schema([("doc_id", pa.int64()), ("shingles", pa.list_(pa.int64())), ("deep", pa.binary())])

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                b = whole.slice(at, 256)
                sets = [shingles(t, p.words) for t in utf8(b.column(1))]
                offsets = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
                values = np.concatenate([*sets, np.empty(0, U64)])
                deep = [None] * len(sets)
                full = np.flatnonzero(np.diff(offsets))
                if len(full):
                    mins = minhashes(values, offsets[:-1][full], p.deep_samples)
                    for i, x in zip(full, odd_sketches(mins, p.deep_bits), strict=True):
                        deep[i] = x.tobytes()
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(values.view(np.int64)))
                yield pa.RecordBatch.from_arrays([b.column(0), lists, pa.array(deep, pa.binary())], schema=schema)

    return trimmed(run)


def xor_count(a: Column, b: Column) -> Column:
    """Population count of the XOR of two arrays of longs."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)


def _search(limit: int, best: int | None, mark: bool = False):
    """Pairs of different components inside blocks of buckets, by XOR of sketches; rows sorted by (key, part).

    Emits each member's best pairs within the limit, or, where best is None, all of them, each in the
    first band that it shares alone; or with mark, instead of pairs, the rows of the members in any.
    """
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def hits(rows: pa.Table):
        """(row, its partners' rows) over the members that have partners."""
        ids = rows.column("doc_id").to_numpy()
        comp = rows.column("component").to_numpy()
        side = rows.column("side").to_numpy()
        bits = np.frombuffer(b"".join(rows.column("sketch").to_pylist()), U64).reshape(len(ids), -1)
        if best is None and not mark:
            bands = rows.column("bands").combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
            band = int(np.argmax(bands[0] == rows.column("key")[0].as_py()))
        names, comp = np.unique(comp, return_inverse=True)
        if len(names) < 2:
            return
        sizes = np.bincount(comp)
        # every pair of components is seen from the smaller one, ties from the lower name
        order = np.lexsort((np.arange(len(sizes)), sizes))
        rank = np.empty(len(sizes), np.int64)
        rank[order] = np.arange(len(sizes))
        turn = rank[comp]
        by = np.argsort(turn, kind="stable")
        ids, turn, side, bits = ids[by], turn[by], side[by], bits[by]
        ends = np.searchsorted(turn, turn, side="right")
        for i in range(len(ids)):
            e = ends[i]
            if e == len(ids):
                break
            x = np.bitwise_count(bits[e:] ^ bits[i]).sum(1)
            ok = x <= limit
            if side[i]:
                ok &= side[e:] != side[i]
            hit = np.flatnonzero(ok)
            if not len(hit):
                continue
            if best is not None and len(hit) > best:
                hit = hit[np.lexsort((ids[e:][hit], x[hit]))[:best]]
            js = by[e:][hit]
            if best is None and not mark and band:
                js = js[~(bands[js, :band] == bands[by[i], :band]).any(1)]
            if len(js):
                yield by[i], js

    def results(rows: pa.Table):
        if mark:
            seen = np.zeros(rows.num_rows, bool)
            for i, js in hits(rows):
                seen[i] = True
                seen[js] = True
            if seen.any():
                yield from rows.filter(pa.array(seen)).drop_columns(["sketch", "bands"]).to_batches()
            return
        ids = rows.column("doc_id").to_numpy()
        for i, js in hits(rows):
            lo, hi = np.minimum(ids[i], ids[js]), np.maximum(ids[i], ids[js])
            for s in range(0, len(lo), 50_000):
                yield pa.RecordBatch.from_arrays([pa.array(lo[s : s + 50_000]), pa.array(hi[s : s + 50_000])], schema=schema)

    def run(batches):
        held: list[pa.Table] = []
        name = None

        def flush():
            if held and sum(t.num_rows for t in held) > 1:
                yield from results(pa.concat_tables(held).combine_chunks())

        for b in batches:
            if not b.num_rows:
                continue
            k, q = b.column("key").to_numpy(), b.column("part").to_numpy()
            cuts = np.flatnonzero((k[1:] != k[:-1]) | (q[1:] != q[:-1])) + 1
            for s, e in zip([0, *cuts], [*cuts, len(k)], strict=True):
                if (k[s], q[s]) != name:
                    yield from flush()
                    held, name = [], (k[s], q[s])
                held.append(pa.Table.from_batches([b.slice(s, e - s)]))
        yield from flush()

    return trimmed(run)


def groups(src: DataFrame, p: NearDupParams) -> DataFrame:
    """Rows (doc_id, n, group) for rows (doc_id, text) of distinct long doc_ids: group is null where a text is like no other."""
    ship(src.sparkSession)
    feats = stage(src.mapInArrow(_features(p), "doc_id long, n long, hi long, lo long, bands array<long>, sketch binary"), "dup-features")

    classes = feats.where("n > 0").groupBy("hi", "lo").agg(F.min("doc_id").alias("rep"), F.count("*").alias("rows"))
    many = stage(classes.where("rows > 1").select("hi", "lo", "rep"), "dup-classes")
    reps = feats.where("n > 0").join(many, ["hi", "lo"], "left").where("rep is null or rep = doc_id")
    banded = reps.select("doc_id", F.explode("bands").alias("key"))

    buckets = banded.groupBy("key").agg(F.min(F.struct(F.xxhash64("doc_id").alias("h"), F.col("doc_id").alias("center"))).alias("c"), F.count("*").alias("size"))
    buckets = buckets.where("size > 1").select("key", F.col("c.center").alias("center"), "size")
    members = stage(banded.join(buckets, "key"), "dup-members")
    busy = members.select("doc_id").distinct()
    words = [F.conv(F.hex(F.substring("sketch", 8 * i + 1, 8)), 16, -10).cast("long") for i in range(p.bits // 64)]
    sketches = stage(reps.join(busy, "doc_id", "left_semi").select("doc_id", "sketch", "bands", F.array(*words).alias("words")), "dup-sketches")

    limit = largest_xor(p.samples, p.bits, p.screen)
    a, b = sketches.select(F.col("doc_id").alias("a"), F.col("words").alias("wa")), sketches.select(F.col("doc_id").alias("b"), F.col("words").alias("wb"))
    pairs = members.where("doc_id <> center").select(F.least("doc_id", "center").alias("a"), F.greatest("doc_id", "center").alias("b")).distinct()
    pairs = stage(pairs.join(a, "a").join(b, "b").where(xor_count(F.col("wa"), F.col("wb")) <= limit).select("a", "b"), "dup-pairs")

    full: dict[str, DataFrame] = {}

    def confirm(pairs: DataFrame) -> DataFrame:
        """Pairs whose full shingle sets reach the threshold, as (u, v)."""
        if "sets" not in full:
            text = src.join(busy, "doc_id", "left_semi")
            full["sets"] = stage(text.mapInArrow(_sets(p), "doc_id long, shingles array<long>, deep binary"), "dup-sets")
        s = full["sets"]
        j = pairs.join(s.select(F.col("doc_id").alias("a"), F.col("shingles").alias("sa")), "a").join(s.select(F.col("doc_id").alias("b"), F.col("shingles").alias("sb")), "b")
        both = F.size(F.array_intersect("sa", "sb")).cast("long")
        return j.withColumn("both", both).where(100 * F.col("both") >= p.num * (F.size("sa") + F.size("sb") - F.col("both"))).select(F.col("a").alias("u"), F.col("b").alias("v"))

    links = stage(confirm(pairs), "dup-links")
    labels = stage(components(links), "dup-labels")
    tried = pairs
    parts = F.ceil(F.col("size") / p.block).cast("int")
    own = F.pmod(F.xxhash64("doc_id"), parts).cast("int")
    cell = F.transform(F.sequence(F.lit(0), parts - 1), lambda i: F.struct((F.least(own, i) * parts + F.greatest(own, i)).alias("part"), F.when(i == own, 0).when(own < i, 1).otherwise(2).alias("side")))
    place = ["key", "part", "side", "doc_id", "component"]

    def together(rows: DataFrame, sketch: DataFrame) -> DataFrame:
        return rows.join(sketch, "doc_id").select(*place, "sketch", "bands").repartition("key", "part").sortWithinPartitions("key", "part")

    for best in (*[p.best] * p.tries, None):
        named = members.join(labels.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
        named = stage(named.select("key", "doc_id", "component", "size"), "dup-named")
        mixed = named.groupBy("key").agg(F.min("component").alias("c0"), F.max("component").alias("c1")).where("c0 <> c1").select("key")
        rows = named.join(mixed, "key", "left_semi").withColumn("cell", F.explode(cell)).select("*", "cell.part", "cell.side")
        rows = together(rows, sketches.select("doc_id", "sketch", F.array().cast("array<long>").alias("bands")))
        if best is None:
            rows = stage(rows.mapInArrow(_search(limit, None, True), "key long, part int, side int, doc_id long, component long"), "dup-marked")
            rows = together(rows, full["sets"].select("doc_id", F.col("deep").alias("sketch")).join(sketches.select("doc_id", "bands"), "doc_id"))
            search = _search(largest_xor(p.deep_samples, p.deep_bits, p.deep_screen), None)
        else:
            search = _search(limit, best)
        found = rows.mapInArrow(search, "a long, b long").distinct().join(tried, ["a", "b"], "left_anti")
        found = stage(found, "dup-pairs")
        more = stage(confirm(found), "dup-links")
        discard(named)
        tried = tried.union(found)
        if not more.isEmpty():
            old = labels
            links = links.union(more)
            labels = stage(components(links), "dup-labels")
            discard(old)

    labels = labels.union(labels.select(F.col("component").alias("node"), "component").distinct())  # a component's smallest node is no node of labels
    best_of = many.join(labels, many.rep == labels.node, "left").select("hi", "lo", F.coalesce("component", "rep").alias("component"))
    single = reps.where("rep is null").select("hi", "lo", "doc_id").join(labels, F.col("doc_id") == labels.node).select("hi", "lo", "component")
    root = stage(best_of.union(single).distinct(), "dup-root")
    for t in (full.get("sets"), members, sketches):
        if t is not None:
            discard(t)
    return feats.select("doc_id", "n", "hi", "lo").join(root, ["hi", "lo"], "left").select("doc_id", "n", F.when(F.col("n") > 0, F.col("component")).alias("group"))


def with_row(docs: DataFrame) -> DataFrame:
    """docs with a long __row of its own for each row: ids may be null or repeated. docs must read the same rows each time."""
    return docs.withColumn("__row", F.monotonically_increasing_id())


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", params: NearDupParams | None = None) -> DataFrame:
    """Rows (doc_id, n_shingles, component_id, kept), one for each input row.

    Null or wordless text: no shingles, linked with nothing, kept. Every row is a document of its own, so
    rows that repeat an id are judged by their own texts; the component is the smallest id among the
    linked rows (null if all are null), and a row without an id is not kept. An empty table gives an empty
    result. Other columns are ignored, whatever their names.
    """
    src = stable(with_row(docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))), "dup-rows")
    found = groups(src.select(F.col("__row").alias("doc_id"), "text"), params or NearDupParams())
    named = stage(found.withColumnRenamed("doc_id", "__row").join(src.select("__row", "id"), "__row"), "dup-groups")
    linked, alone = named.where("group is not null"), named.where("group is null").withColumn("component", F.col("id"))
    low = linked.groupBy("group").agg(F.min("id").alias("component"))
    # a large group meets its smallest id in as many places as there are salts
    salted = low.withColumn("salt", F.explode(F.array(*map(F.lit, range(SALTS)))))
    out = linked.withColumn("salt", F.pmod(F.xxhash64("__row"), F.lit(SALTS)).cast("int")).join(salted, ["group", "salt"]).select(*alone.columns).union(alone)
    return out.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("component").alias("component_id"), F.coalesce(F.col("component") == F.col("id"), F.lit(False)).alias("kept"))


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", params: NearDupParams | None = None) -> DataFrame:
    """docs with one row of each group of near copies: the one of the smallest id (null ids last), of equal ids any one row."""
    inner = stable(with_row(by_place(docs)), "dup-rows")
    at = {c: f"c{i}" for i, c in enumerate(docs.columns)}
    found = stage(groups(inner.select(F.col("__row").alias("doc_id"), F.col(at[text_col]).alias("text")), params or NearDupParams()), "dup-groups")
    linked = found.where("group is not null").withColumnRenamed("doc_id", "__row").join(inner.select("__row", F.col(at[id_col]).alias("id")), "__row")
    first = linked.groupBy("group").agg(F.min(F.struct(F.col("id").isNull().alias("none"), "id", "__row")).alias("m"))
    gone = linked.select("__row").join(first.select(F.col("m.__row").alias("__row")), "__row", "left_anti")  # by row: a large group is no hot key
    return inner.join(gone, "__row", "left_anti").drop("__row").toDF(*docs.columns)


def near_dup_query(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))


NEAR_DUP_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents
), g AS (
  SELECT doc_id, list_distinct(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
    ELSE list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' ')) END) AS s FROM w
), c AS (SELECT s, min(doc_id) AS rep FROM (SELECT doc_id, list_sort(s) AS s FROM g WHERE len(s) > 0) GROUP BY s
), x AS (SELECT rep, len(s) AS n, unnest(s) AS h FROM c
), p AS (SELECT a.rep AS a, b.rep AS b FROM x a JOIN x b ON a.h = b.h AND a.rep < b.rep
  GROUP BY a.rep, b.rep, a.n, b.n HAVING 100 * count(*) >= 75 * (a.n + b.n - count(*))
), e AS (SELECT a, b FROM p UNION SELECT b, a FROM p
), r(node, low) AS (SELECT rep, rep FROM c UNION SELECT e.b, r.low FROM r JOIN e ON e.a = r.node
), m AS (SELECT node, min(low) AS component FROM r GROUP BY node)
SELECT g.doc_id, CAST(len(g.s) AS BIGINT) AS n_shingles, coalesce(m.component, g.doc_id) AS component_id,
  coalesce(m.component, g.doc_id) = g.doc_id AS kept
FROM g LEFT JOIN c ON list_sort(g.s) = c.s LEFT JOIN m ON m.node = c.rep
"""
