from __future__ import annotations

import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from evenlane.llm.near_dup import near_duplicates
from evenlane.llm.quality import quality_verdicts
from evenlane.llm.secrets import find_secrets
from evenlane.llm.topk import TOP_K_SQL, quantised, top_k, top_k_query
from tests.compare import assert_same, tables
from tests.llm.test_near_dup import brute


def test_top_k_sql(spark, data):
    assert_same(top_k_query(spark, data), tables(data), TOP_K_SQL)


@pytest.mark.parametrize(("n", "k", "low"), [(3, 5, -2), (200, 5, 0), (300, 7, -1000), (50, 1, 10**6)])
def test_top_k_against_numpy(spark, n, k, low):
    rng = np.random.default_rng(n)
    v = rng.integers(low, low + 3 if low >= 0 and low < 100 else low + 1500, (n, 4)) / 4
    rows = [(i, [float(x) for x in v[i]]) for i in range(n)] + [(n, None), (n + 1, [1.0, None, 2.0, 3.0]), (n + 2, [float("nan")] * 4), (n + 3, [float("inf")] * 4), (n + 4, []), (n + 5, [1.0])]
    q = quantised(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), "vec_id", "embedding")
    got = sorted(map(tuple, top_k(q, q.where("id % 10 = 0 and size(v) = 4"), k, query_block=4, block=32).collect()))
    e = np.floor(256 * v.astype(np.float32).astype(np.float64)).astype(np.int64)
    want = []
    for i in range(0, n, 10):
        s = e @ e[i]
        order = sorted((j for j in range(n) if j != i), key=lambda j: (-s[j], j))[:k]
        want += [(i, r + 1, j, int(s[j])) for r, j in enumerate(order)]
    assert got == sorted(want)


def test_top_k_of_nothing(spark):
    q = quantised(spark.createDataFrame([], "vec_id long, embedding array<float>"), "vec_id", "embedding")
    assert top_k(q, q).count() == 0


def _docs(spark):
    rng = random.Random(12)
    words = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 8))) for _ in range(400)]
    texts = [" ".join(rng.choice(words) for _ in range(rng.randint(12, 90))) for _ in range(120)]
    texts += texts[:10] + [t + " extra" for t in texts[10:20]] + ["short one", "", None, " ".join(f"{w}###" for w in texts[3].split()), " ".join(texts[7].split()[::-1]) + " password=abcdefghijklmnop end"]
    rows = [(i, t, "en", f"s{i % 3}", len(t or "")) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")


def test_pipeline_against_brute_force(spark, tmp_path):
    docs = _docs(spark)
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    src = {r.doc_id: r for r in docs.collect()}
    good = {r.doc_id for r in quality_verdicts(docs).where("__kept").collect()}
    assert good and not good & {140, 141, 142, 143}
    kept = {r[0] for r in brute([(i, src[i].text) for i in sorted(good)]) if r[3]}
    spans = {r.doc_id: r["__spans"] for r in find_secrets(docs).collect()}

    def clean(i: int) -> str:
        t, out, at = src[i].text, "", 0
        for s in spans[i]:
            if s.start >= at:
                out += t[at : s.start] + "[SECRET]"
            at = max(at, s.end)
        return out + t[at:]

    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    ids = {i: np.array(tok.encode(clean(i), add_special_tokens=False).ids + [2], "<u4") for i in kept}
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert {r.doc_id for r in got} == kept and any("SECRET" in clean(i) for i in kept)
    total = dict.fromkeys(ids, 0)
    for r in got:
        assert zlib.crc32(ids[r.doc_id][r.start : r.start + r.length].tobytes()) == r.ids_crc32
        total[r.doc_id] += r.length
    assert total == {i: len(x) for i, x in ids.items()}


def test_stages_keep_the_columns(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet").limit(60)
    for _, f in corpus_pipeline.STAGES[:-1]:
        assert f(spark, docs, data).columns == docs.columns


def test_near_dup_stage_keeps_one_of_each(spark):
    rows = [
        (1, "a b c d e f", "en", "s", 11), (1, "a b c d e f", "en", "s", 11), (2, "a b c d e f", "en", "s", 11), (1, "quite another text than that", "en", "s", 3), (None, "x y", "en", "s", 3), (None, "x y", "en", "t", 3),
        (5, "", "en", "s", 0), (5, "", "en", "s", 0), (6, None, "en", "s", 0),
    ]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = corpus_pipeline.near_dup(spark, docs, "").collect()
    assert sorted(((r.doc_id is None, r.doc_id or 0), r.text or "") for r in got) == [
        ((False, 1), "a b c d e f"), ((False, 1), "quite another text than that"), ((False, 5), ""), ((False, 5), ""), ((False, 6), ""), ((True, 0), "x y")
    ]
    every = near_duplicates(docs).collect()
    assert len(every) == 9 and {(r.component_id, r.kept) for r in every if r.doc_id == 2} == {(1, False)}


def test_top_k_of_repeated_and_null_ids(spark, tmp_path):
    """Every row but the query's own is a candidate, whatever its id."""
    rng = np.random.default_rng(3)
    v = rng.integers(-3, 4, (40, 3)) / 2
    rows = [(i // 2 if i % 7 else None, [float(x) for x in v[i]], "x") for i in range(40)] + [(0, [], "x"), (50, [], "x")]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label string").coalesce(1).write.parquet(f"{tmp_path}/e")
    import shutil

    shutil.copy(next(iter((tmp_path / "e").glob("*.parquet"))), tmp_path / "embeddings.parquet")
    df = top_k_query(spark, str(tmp_path))
    con = tables(str(tmp_path))
    assert_same(df, con, TOP_K_SQL)
    assert df.groupBy("query_id", "vec_id").count().where("count > 1").count() > 0 and df.where("query_id = 50").count() == 1
