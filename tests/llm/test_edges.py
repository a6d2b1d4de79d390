"""Defined results of all operators on empty tables, nulls, very long texts and ties; models against plain versions."""

import math
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from tricount.llm import decontam, extraction, langid, packing, quality, secrets, sharding, topk, toxicity
from tricount.llm.common import bitmap, fold

PATH = public_tokenizers.path("word_bpe_49k.json")
DOC = "doc_id long, text string, lang string, source string, n_chars long, score double, rank int"


@pytest.fixture(scope="module")
def few(spark):
    rows = [(1, "the house by the river was old and the garden wild " * 3, "en"), (2, "das haus am fluss war alt und der garten wild " * 3, "de"), (3, None, "en"), (4, "", None), (5, "the and und der " * 60_000, "en")]
    return spark.createDataFrame([(i, t, x, "s", 0, 0.5, 1) for i, t, x in rows], DOC).repartition(2).cache()


@pytest.fixture(scope="module")
def models(spark, few):
    labels = spark.createDataFrame([(1, 1, 0), (2, 0, 1), (3, None, None), (4, 0, 0), (5, 1, 0)], "doc_id long, quality int, toxic int")
    learn = F.lit(True)
    return {"lang": langid.train(few, learn), "toxic": toxicity.train(few, labels, learn), "quality": quality.train(few, labels, learn)}


def test_empty_tables(spark, few, models):
    none = few.limit(0)
    pages = spark.createDataFrame([], "page_id long, url string, html string, text string")
    made = [extraction.extract(pages), sharding.shard_documents(none, 3), secrets.secret_digests(none), secrets.redact_secrets(none), langid.identify(none, models["lang"]), toxicity.score_documents(none, models["toxic"]), quality.score_documents(none, models["quality"]), quality.keep_good(none, models["quality"]), packing.pack_documents(none, PATH, 64)]
    assert [df.count() for df in made] == [0] * len(made)


def test_nulls_and_long_texts(few, models):
    scored = {r.doc_id: r.score for r in toxicity.score_documents(few, models["toxic"]).collect()}
    good = {r.doc_id: r.score for r in quality.score_documents(few, models["quality"]).collect()}
    assert set(scored) == set(good) == {1, 2, 3, 4, 5} and all(0 <= s <= 1 for s in [*scored.values(), *good.values()])
    assert scored[3] == scored[4] and good[3] == good[4]
    kept = quality.keep_good(few, models["quality"])
    assert kept.columns == few.columns and {r.doc_id for r in kept.collect()} == {i for i, s in good.items() if s >= 0.3}


def test_labelled_rows_are_bounded(spark):
    """Ids that repeat, also with other texts, give one row each."""
    docs = spark.createDataFrame([(i % 3, f"text {i % 4}") for i in range(40)], "doc_id long, text string")
    labels = spark.createDataFrame([(0, 1), (1, 0), (2, 1), (2, 0), (7, 1)], "doc_id long, toxic int")
    rows = toxicity.labelled(docs, labels, "toxic", F.lit(True), 10).collect()
    assert sorted((r.doc_id, r.y) for r in rows) == [(0, 1), (1, 0), (2, 1)]
    assert toxicity.labelled(docs, labels, "toxic", F.lit(True), 2).count() <= 2


def test_bitmap(spark):
    rng = np.random.default_rng(1)
    numbers = [int(x) for x in rng.integers(0, 1 << 60, 500)]
    bits = bitmap(spark.createDataFrame([(x,) for x in numbers], "h long").repartition(3), lambda h: h & 4095, 4096)
    assert set(np.flatnonzero(np.unpackbits(bits, bitorder="little")).tolist()) == {x & 4095 for x in numbers}


def plain_vector(text, idf):
    """TF-IDF of hashed byte 2- and 3-grams, word by word."""
    raw = (" " + text.lower() + " ").encode()
    kept = bytes(b if b >= 128 or chr(b).isalpha() else 32 for b in raw)
    while b"  " in kept:
        kept = kept.replace(b"  ", b" ")
    n = {}
    for size in (2, 3):
        for i in range(len(kept) - size + 1):
            code = 0
            for byte in kept[i : i + size]:
                code = (code * 65599 + byte) % 2**32
            slot = code * 2654435761 % 2**32 >> 19
            n[slot] = n.get(slot, 0) + 1
    v = np.zeros(langid.DIM)
    for k, c in n.items():
        v[k] = (1 + math.log(c)) * idf[k]
    return v / (np.linalg.norm(v) or 1)


def test_language_against_plain_cosines(few, spark):
    texts = ["the old house by the river", "das alte haus am fluss", "The, garden! 12 was wild", "und der wald", "a"]
    model = langid.train(few, F.lit(True), clusters=1)
    for text, (lang, score, _) in zip(texts, model.predict(texts), strict=True):
        cos = model.centroids @ plain_vector(text, model.idf)
        assert lang == model.langs[int(cos.argmax())] and abs(score - max(0.0, cos.max())) < 1e-4
    # One cluster: the centroid is the mean of the sample's vectors; idf counts texts.
    rows = {r.doc_id: r.text for r in few.collect()}
    de = plain_vector(rows[2], model.idf)
    assert np.abs(model.centroids[model.langs.index("de")] - de).max() < 1e-3
    seen = sum(plain_vector(rows[i], np.ones(langid.DIM)) > 0 for i in (1, 2, 5))
    assert np.allclose(model.idf, np.log(4 / (1 + seen)) + 1, atol=1e-5)
    tie = langid.LanguageModel(model.idf, np.stack([model.centroids[0]] * 2), ("aa", "bb"), np.zeros(2))
    assert tie.predict(["the house"])[0][0] == "aa"


def test_log_count_ratios_by_hand():
    sets, y = [np.array([1, 2]), np.array([2, 3]), np.array([3])], np.array([1, 0, 0])
    r = quality.log_ratios(sets, y)
    n = quality.BUCKETS
    p, q = {1: 2, 2: 2, 3: 1}, {1: 1, 2: 2, 3: 3}
    for k in (1, 2, 3):
        assert abs(r[k] - (math.log(p[k] / (n + 2)) - math.log(q[k] / (n + 3)))) < 1e-9
    assert r[4] == 0


def test_dual_descent_reaches_the_primal_optimum():
    rng = np.random.default_rng(6)
    sets = [np.flatnonzero(rng.random(8) < 0.5) for _ in range(30)]
    y = (rng.random(30) < 0.4).astype(int)
    r = np.zeros(quality.BUCKETS)
    r[:8] = rng.normal(size=8)
    w, bias = quality.dual_descent(sets, y, r, epochs=5000)
    x = np.zeros((30, 9))
    for i, s in enumerate(sets):
        x[i, s] = r[s] / (np.linalg.norm(r[s]) or 1)
    x[:, 8] = 1
    sign = np.where(y > 0, 1.0, -1.0)
    cost = np.where(y > 0, 15 / max(1, y.sum()), 15 / max(1, (1 - y).sum()))
    value = lambda v: 0.5 * v @ v + cost @ np.maximum(0, 1 - sign * (x @ v))
    best = np.array([*w[:8], bias])
    for scale in (1e-3, 1e-2, 0.1, 1.0):
        for _ in range(400):
            assert value(best) <= value(best + scale * rng.normal(size=9)) + 5e-3


def test_gumbel_fit_and_evidence():
    rng = np.random.default_rng(3)
    sizes = rng.integers(50, 2000, 4000)
    best = np.log(0.02 * sizes) / 0.7 - np.log(-np.log(rng.random(4000))) / 0.7
    lam, log_k = toxicity.gumbel_fit(best - np.log(sizes) / 0.7 + np.log(300) / 0.7, np.full(4000, 300))
    assert abs(lam - 0.7) < 0.05 and abs(log_k - math.log(0.02)) < 0.3
    model = toxicity.ToxicModel(np.ones(2), 2.0, math.log(0.5), 1.0, 0.0)
    # Expected chance segments K n exp(-lambda s): those below one count by how far they fall.
    want = sum(v for v in (2.0 * s - math.log(0.5 * 10) for s in (3.0, 0.2, 1.5)) if v > 0)
    assert abs(model.evidence(10, [(0, 1, 3.0), (2, 3, 0.2), (4, 5, 1.5)]) - want) < 1e-9
    assert model.evidence(10, []) == -20.0 and abs(model.evidence(10, [(0, 1, 0.1)]) - (0.2 - math.log(5))) < 1e-9


def test_rare_tokens_take_their_stems():
    assert toxicity.buckets("abc") == [toxicity.bucket("abc")] and len(toxicity.buckets("abcdefgh")) == 4
    weights = np.zeros(toxicity.BUCKETS, dtype=np.float32)
    weights[toxicity.bucket("^abcde")] = 2.0
    weights[toxicity.bucket("abcdefgh")] = -1.0
    table = toxicity.ToxicModel(weights, 1.0, 0.0, 1.0, 0.0).word_table()
    assert [round(table[w] + toxicity.DRIFT, 6) for w in ("abcdefgh", "abcdezz", "abcd")] == [-1.0, 2.0, 0.0]


def test_packed_ids_checksums(few):
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(PATH)
    texts = {r.doc_id: r.text or "" for r in few.collect()}
    for r in packing.pack_documents(few.where("doc_id < 5"), PATH, 16).collect():
        ids = [*tokenizer.encode(texts[r.doc_id], add_special_tokens=False).ids, 1][r.start : r.start + r.length]
        assert r.ids_crc32 == zlib.crc32(np.array(ids, dtype="<u4").tobytes())


def test_longest_first_needs_no_more_bins_than_plain_fullest_fill():
    rng = np.random.default_rng(12)
    for _ in range(20):
        counts = {}
        for x in np.minimum(64, 1 + rng.exponential(14, 400).astype(int)).tolist():
            counts[x] = counts.get(x, 0) + 1
        plain, left = 0, dict(counts)
        while left:
            for x in packing.fullest(left, 64):
                left[x] -= 1
                if not left[x]:
                    del left[x]
            plain += 1
        assert sum(n for _, n in packing.plan_bins(counts, 64)) <= plain


def test_hot_windows_and_repeated_items(spark):
    """One passage in most documents, several items with the same words: every link comes out, once."""
    item = "the narrow lane behind the mill leads down past two quiet ponds to the chapel on the hill"
    docs = spark.createDataFrame([(i, f"number {i} {item} and so on" if i % 4 else f"other words {i}", "en", "s", 0, 0.5, 1) for i in range(80)], DOC)
    items = spark.createDataFrame([(k, item) for k in range(3)], "item_id long, text string")
    rows = [(r.doc_id, r.item_id) for r in decontam.leaks(docs, items).collect()]
    assert sorted(rows) == [(i, k) for i in range(80) if i % 4 for k in range(3)]


def test_top_k_of_one_row_and_all_equal(spark):
    one = spark.createDataFrame([(0, [1.0])], "vec_id long, embedding array<float>")
    assert topk.top_k(one, F.col("vec_id") % 50 == 0).count() == 0
    same = spark.createDataFrame([(i, [1.0, -1.0]) for i in range(60)], "vec_id long, embedding array<float>")
    got = sorted(map(tuple, topk.top_k(same, F.col("vec_id") % 50 == 0, k=3).collect()))
    assert got == [(q, k + 1, v, 2 * 65536) for q in (0, 50) for k, v in enumerate([x for x in range(4) if x != q][:3])]


def test_models_without_rows(spark, few):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {r.score for r in toxicity.score_documents(few, toxicity.train(few, labels, fold("doc_id", 4) != 2)).collect()} == {0.0}
