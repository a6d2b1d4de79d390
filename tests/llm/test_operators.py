"""The operators on small tables with nulls, empties, repeats, ties and clashing names, against brute force."""

import importlib
import random
import re

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from test_jaccard import kept

from tricount.llm import components, decontam, extraction, langid, packing, quality, secrets, sharding, simhash, topk, toxicity
from tricount.llm.common import fold

PATH = public_tokenizers.path("word_bpe_49k.json")
DOC = "doc_id long, text string, lang string, source string, n_chars long, score double, rank int"


def table(spark, rows):
    return spark.createDataFrame([(i, t, x, "s", len(t) if t else None, 0.5, 1) for i, t, x in rows], DOC).repartition(3)


@pytest.fixture(scope="module")
def docs(spark):
    rng = random.Random(1)
    words = ["alpha", "beta", "gamma", "delta", "eps", "zeta", "eta", "theta", "iota", "kappa"]
    long = [" ".join(rng.choice(words) for _ in range(200)) for _ in range(6)]
    rows = [(i, t, "en") for i, t in enumerate(long)] + [(10, long[0], "en"), (11, long[1] + " omega", "en"), (12, None, None), (13, "", "de"), (14, "   \n", None), (15, "é" * 30_000, "fr"), (15, "é" * 30_000, "fr"), (None, "no id", "en"), (16, "12 34", "en")]
    return table(spark, rows).cache()


def test_sharding(docs):
    rows = sharding.shard_documents(docs, 5).collect()
    assert len(rows) == docs.count()
    for s in {r.shard for r in rows}:
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(sum(r.shard == s for r in rows)))
    assert all(r.grown_shard in (r.shard, 5) for r in rows)
    assert {r.size for r in rows if r.doc_id in (12, 13)} == {8}
    assert {r.text_crc32 for r in rows if r.doc_id in (12, 13)} == {0}


def test_weighted_sharding(spark):
    rows = sharding.assign_shards(spark.range(6000), "id", 3, [1.0, 2.0, 3.0]).groupBy("shard").count().collect()
    assert {r["shard"]: round(r["count"] / 1000) for r in rows} == {0: 1, 1: 2, 2: 3}
    with pytest.raises(ValueError):
        sharding.assign_shards(spark.range(1), "id", 2, [1.0])


def test_packing(docs):
    rows = packing.pack_documents(docs, PATH, capacity=256).collect()
    coder, want = packing._Ids(PATH), []
    for r in docs.collect():
        n = len(coder.of(r.text, 1)) // 4
        want += [(r.doc_id if r.doc_id is not None else -1, k, a, min(256, n - a)) for k, a in enumerate(range(0, n, 256))]
    assert sorted((r.doc_id if r.doc_id is not None else -1, r.piece, r.start, r.length) for r in rows) == sorted(want)
    ends = {}
    for r in sorted(rows, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == ends.get(r.sequence_id, 0)
        ends[r.sequence_id] = r.offset + r.length
    assert max(ends.values()) <= 256


def test_secrets(spark):
    key = "token = 'abcdefgh12345678'"
    d = table(spark, [(1, f"é {key} end", "en"), (2, None, None), (3, "", None), (4, "AKIA" + "A" * 12, "en")])
    rows = {r.doc_id: r for r in secrets.secret_digests(d).collect()}
    assert rows[1].spans == f"assign:2:{2 + len(key) - 1}" and rows[1].n_assign == 1 and rows[4].n_access == 1
    assert rows[2].base_sha256 == rows[3].base_sha256 and rows[2].spans == ""
    masked = secrets.redact_secrets(d)
    assert masked.columns == d.columns
    got = {r.doc_id: (r.text, r.n_chars) for r in masked.collect()}
    assert got[1] == ("é [SECRET]' end", 15) and got[2] == (None, None) and got[3] == ("", None)


def test_components(spark):
    rng = random.Random(2)
    pairs = [(rng.randrange(300), rng.randrange(300)) for _ in range(160)] + [(1000 + i, 1001 + i) for i in range(40)] + [(2000, 2000 + i) for i in range(1, 50)]
    up = {}

    def find(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    links = spark.createDataFrame(pairs, "a long, b long")
    want = {x: find(x) for p in pairs for x in p if p[0] != p[1]}
    assert dict(components.components(links).collect()) == want
    before, components.PER_TASK = components.PER_TASK, 16
    try:
        assert dict(components.components(links).collect()) == want
    finally:
        components.PER_TASK = before
    assert components.components(links.limit(0)).count() == 0


def test_few_links_take_no_rounds(spark):
    """A path of 3,000 nodes is finished by one task, without a round of jobs."""
    path = list(range(3000))
    random.Random(8).shuffle(path)
    links = spark.createDataFrame(list(zip(path[:-1], path[1:], strict=True)), "a long, b long")
    assert [tuple(r) for r in components.components(links, rounds=0).orderBy("node").collect()] == [(x, 0) for x in range(3000)]


def test_near_duplicates(docs, spark):
    rows = simhash.near_duplicates(docs).collect()
    prints = [(r.doc_id, simhash.fingerprint_of(r.text)) for r in docs.collect()]
    assert sorted((str(r.doc_id), int(r.fingerprint, 16)) for r in rows) == sorted((str(i), f) for i, f in prints)
    group = {r.doc_id: r.component_id for r in rows}
    assert group[10] == 0 and group[12] == group[13] == group[14] == 12
    kept = simhash.without_near_duplicates(docs)
    ids = [r.doc_id for r in kept.collect()]
    assert ids.count(15) == 1 and 10 not in ids and None in ids and kept.columns == docs.columns
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


@pytest.mark.parametrize(("bits", "tally"), [(1, 8), (2, 8), (2, 256)])
def test_links_of_dense_postings(spark, bits, tally, monkeypatch):
    """Fingerprints that share six bytes, or any four: postings of many entries, tallied or split, against all pairs."""
    monkeypatch.setattr(simhash, "TALLY", tally)
    rng = random.Random(3)
    dense = {0x1122334455660000 | rng.randrange(1 << 16) for _ in range(400)}
    sparse = {rng.randrange(1 << 63) for _ in range(50)}
    near = {x ^ 1 << rng.randrange(63) ^ 1 << rng.randrange(63) for x in sparse for _ in range(4)}
    four = {0x7700660055004400 | sum(rng.randrange(4) << 16 * k for k in range(4)) for _ in range(120)}
    fps = sorted(dense | sparse | near | four)
    got = {(r.a, r.b) for r in simhash.fingerprint_links(spark.createDataFrame([(x,) for x in fps], "fp long"), bits).collect()}
    assert got == {(a, b) for i, a in enumerate(fps) for b in fps[i + 1 :] if (a ^ b).bit_count() <= bits}


def brute_top(rows, k=5, every=50):
    """(query_id, rank, vec_id, score) by all pairs of rows."""
    kept = [(i, np.floor(256 * np.array(v, dtype=np.float64)).astype(object)) for i, v in rows if v is not None and i is not None and all(x is not None and np.isfinite(x) for x in v)]
    out = []
    for n, (i, q) in enumerate(kept):
        if i % every == 0:
            met = sorted((-sum(int(a) * int(b) for a, b in zip(q, v, strict=True)), j) for m, (j, v) in enumerate(kept) if m != n and len(v) == len(q))
            out += [(i, r + 1, j, -s) for r, (s, j) in enumerate(met[:k])]
    return sorted(out)


@pytest.mark.parametrize("partitions", [1, 4])
def test_top_k(spark, partitions):
    rng = np.random.default_rng(5)
    x = np.round(rng.normal(size=(700, 10)), 2).astype(np.float32)
    x[100:160] = x[100]  # many equal vectors
    rows = [(int(i), [float(v) for v in r]) for i, r in enumerate(x)] + [(9001, None), (9050, [1.0, None]), (9100, [float("nan")] * 10), (0, [float(v) for v in x[0]]), (9150, [1.0, 2.0]), (None, [1.0, 2.0]), (9160, [0.5, 3.0])]
    d = spark.createDataFrame([(i, v, 1) for i, v in rows], "vec_id long, embedding array<float>, score int").repartition(partitions)
    got = sorted(map(tuple, topk.top_k(d, F.col("vec_id") % 50 == 0).collect()))
    assert got == brute_top(rows)
    assert topk.top_k(spark.createDataFrame([], "vec_id long, embedding array<float>"), F.col("vec_id") % 50 == 0).count() == 0


def test_top_k_of_rows_that_repeat_an_id(spark):
    """Every row is a candidate, also those of an id that occurs again with another vector, or of the query's own id."""
    rows = [(0, [1.0, 0.0]), (1, [1.0, 1.0]), (1, [5.0, 0.0]), (2, [0.5, 0.0]), (2, [0.25, 9.0]), (50, [2.0, 1.0]), (50, [0.0, 1.0])]
    d = spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(3)
    got = sorted(map(tuple, topk.top_k(d, F.col("vec_id") % 50 == 0).collect()))
    assert got == brute_top(rows) and got[0] == (0, 1, 1, 5 * 65536)


def test_top_k_reads_less_than_all(spark, sf):
    """Fewer partial scores than queries x candidates x lists."""
    d = spark.read.parquet(f"{sf}/embeddings.parquet")
    seen = spark.sparkContext.accumulator(0)
    n = d.count()
    got = sorted(map(tuple, topk.top_k(d, F.col("vec_id") % 50 == 0, seen=seen).collect()))
    assert got == brute_top([(r.vec_id, r.embedding) for r in d.collect()])
    asked = d.where("vec_id % 50 = 0").count()
    assert 0 < seen.value < asked * n * 8


ITEM = "Anna walked slowly down to the old river bank and counted 12 grey ducks that swam near the bridge while Tom waited"


def test_decontamination(spark):
    filler = "quiet mornings bring fresh bread and long letters from distant friends"
    changed = ITEM.replace("12", "47").replace("Tom", "Paul")
    clash = (ITEM + ". Then Tom met Tom").replace("Tom waited", "Paul waited")
    d = table(spark, [(1, f"{filler}. {ITEM}. {filler}.", "en"), (2, f"{filler}. {changed}. {filler}", "en"), (3, filler, "en"), (4, " ".join(ITEM.split()[:9]), "en"), (5, None, None), (6, "", "en"), (7, ITEM.upper(), "en"), (None, ITEM, "en"), (8, clash, "en")])
    b = spark.createDataFrame([(1, ITEM, 0.1), (2, None, 0.2), (3, "", 0.3), (1, ITEM, 0.4)], "item_id long, text string, share double")
    got = {r.doc_id for r in decontam.leaks(d, b).collect()}
    assert {1, 2, None, 8} <= got and not got & {3, 4, 5, 6}
    left = decontam.without_leaks(d, b)
    assert {r.doc_id for r in left.collect()} >= {3, 4, 5, 6, None} and left.columns == d.columns
    assert decontam.leaks(d.limit(0), b).count() == 0 == decontam.leaks(d, b.limit(0)).count()


def test_slot_consistency(spark):
    """A value of the item may not stand against two values of the document."""
    item = "then Bob gave Carl the small red ball because Bob liked red things and then Bob went home to sleep"
    same, mixed = item.replace("Bob", "Zoe"), item.replace("Bob gave", "Zoe gave").replace("Bob went", "Ann went")
    d = table(spark, [(1, f"we saw that {same}", "en"), (2, f"we saw that {mixed}", "en")])
    b = spark.createDataFrame([(1, f"we saw that {item}")], "item_id long, text string")
    assert [r.doc_id for r in decontam.leaks(d, b).collect()] == [1]


def test_extraction_table(spark):
    pages = spark.createDataFrame([(1, "u", None, "x"), (2, None, "", "x"), (3, "u", "<article><p>Some text here.</p></article>", "x")], "page_id long, url string, html string, text string")
    got = {r.page_id: (r.text, r.n_chars) for r in extraction.extract(pages).collect()}
    assert got == {1: ("", 0), 2: ("", 0), 3: ("Some text here.", 15)}


@pytest.mark.parametrize("task", ["lang", "toxic", "quality"])
def test_models_on_labelled_tables(spark, task):
    rng = random.Random(9)
    en, de = ["the", "and", "was", "with", "house", "river"], ["der", "und", "nicht", "mit", "haus", "fluss"]
    rows, marks = [], []
    for i in range(240):
        words = [rng.choice(en if i % 2 else de) for _ in range(30)]
        toxic, bad = i % 5 == 0, i % 3 == 0
        if toxic:
            words[5:5] = [rng.choice(["idiot", "moron"]) for _ in range(3)]
        text = " ".join(w.upper() + "!!" for w in words) if bad else " ".join(words)
        rows.append((i, text, "en" if i % 2 else "de"))
        marks.append((i, int(not bad), int(toxic)))
    rows += [(900, None, "en"), (901, "", None), (902, "12 !", "de")]
    d = table(spark, rows)
    labels = spark.createDataFrame([*marks, (0, None, None), (5000, 1, 1)], "doc_id long, quality int, toxic int")
    learn = fold("doc_id", 4) != 2
    truth = {i: (q, t) for i, q, t in marks}
    if task == "lang":
        got = {r.doc_id: r for r in langid.identify(d, langid.train(d, learn, per_lang=50)).collect()}
        assert all(got[i].lang_pred == ("en" if i % 2 else "de") for i in truth)
        assert all(got[i].lang_pred == "und" and got[i].score == 0 for i in (900, 901, 902))
        empty = langid.train(d.limit(0), learn)
        assert {r.lang_pred for r in langid.identify(d, empty).collect()} == {"und"}
        return
    module, k = (toxicity, 1) if task == "toxic" else (quality, 0)
    got = {r.doc_id: r for r in module.score_documents(d, module.train(d, labels, learn)).collect()}
    assert len(got) == len(rows) and all(0 <= r.score <= 1 for r in got.values())
    assert np.mean([got[i].predicted == v[k] for i, v in truth.items()]) > 0.95
    none = module.score_documents(d, module.train(d, labels.limit(0), learn)).collect()
    assert len(none) == len(rows)


def leaked(text, items):
    """Whether 0.8 of an item's windows of five template words occur in the text (the items have no slots that vary)."""

    def grams(t):
        _, code, kind = decontam.Templates().of(t)
        n, w = len(code), min(5, len(code))
        return {tuple(code[i : i + w].tolist()): None for i in range(n - w + 1) if w and (kind[i : i + w] == 0).sum() >= min(2, w)}

    own = grams(text)
    return any(len(g) and sum(x in own for x in g) >= 0.8 * len(g) for g in map(grams, items))


def test_pipeline_against_brute_force(spark, sf):
    pipeline = importlib.import_module("corpus_pipeline")
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    items = [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    model = quality.train(docs, spark.read.parquet(f"{sf}/labels.parquet"), fold("doc_id", 5) != 0)
    table_ = quality.word_codes()
    now = docs
    for name, stage in pipeline.STAGES[:-1]:
        before = {r.doc_id: r for r in now.collect()}
        now = stage(spark, now, sf).cache()
        assert now.columns == docs.columns, name
        after = {r.doc_id: r for r in now.collect()}
        if name.startswith("quality"):
            want = {i for i, r in before.items() if model.score(quality.features(r.text, table_)) >= 0.3}
        elif name.startswith("SimHash"):
            want = kept([(i, r.text) for i, r in before.items()])
        elif name.startswith("benchmark"):
            want = {i for i, r in before.items() if not leaked(r.text, items)}
        else:
            want = set(before)
            for i, r in before.items():
                if not any(m for rule in secrets.BASE_RULES for m in re.finditer(rule.pattern, r.text) if m.end(rule.group) - m.start(rule.group) >= rule.least):
                    assert after[i].text == r.text
                else:
                    assert "[SECRET]" in after[i].text and len(after[i].text) == after[i].n_chars
        assert set(after) == want, name
    packed = pipeline.STAGES[-1][1](spark, now, sf).collect()
    assert {r.doc_id for r in packed} == {r.doc_id for r in now.collect()}
