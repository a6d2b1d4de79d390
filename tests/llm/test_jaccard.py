"""The near-duplicate stage against brute-force Jaccard similarity of five-word shingles."""

import importlib
import random
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from tricount.llm import jaccard, simhash

DOC = "doc_id long, text string, lang string, source string, n_chars long, score double, rank int"


def grams(text):
    w = (text or "").encode().lower().split()
    k = min(5, len(w))
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if w else frozenset()


def kept(rows):
    """The smallest id of each group linked by Jaccard >= 0.8, by all pairs."""
    sets = [(i, grams(t)) for i, t in rows]
    group = {i: i for i, _ in sets}

    def find(x):
        while group[x] != x:
            x = group[x]
        return x

    for n, (i, a) in enumerate(sets):
        for j, b in sets[n + 1 :]:
            if 5 * len(a & b) >= 4 * len(a | b):
                x, y = sorted((find(i), find(j)))
                group[y] = x
    return {i for i, _ in sets if find(i) == i}


def cases():
    rng = random.Random(5)
    word = lambda: f"w{rng.randrange(4000)}"
    out = []
    for _ in range(6):  # families of near copies: chains of edits, and edits of one text around the bound
        base = [word() for _ in range(rng.choice((30, 120, 300)))]
        chain = base
        for _ in range(25):
            chain = list(chain)
            chain[rng.randrange(len(chain))] = word()
            out.append(" ".join(chain))
            far = list(base)
            for _ in range(rng.randrange(1, 1 + len(base) // 25)):
                far[rng.randrange(len(far))] = word()
            out.append(" ".join(far))
    passage = [word() for _ in range(40)]
    out += [" ".join(passage + [word() for _ in range(rng.randrange(0, 15))]) for _ in range(70)]
    out += [" ".join(word() for _ in range(80)) for _ in range(60)] + [None, "", " ", "one two", "One  two", "two one"]
    rng.shuffle(out)
    return list(enumerate(out))


@pytest.mark.parametrize("source", ["cases", "sf"])
def test_stage_equals_brute_force(spark, sf, source):
    stage = dict(importlib.import_module("corpus_pipeline").STAGES)["SimHash near-dedup"]
    if source == "cases":
        docs = spark.createDataFrame([(i, t, "en", "s", 0, 0.5, 1) for i, t in cases()], DOC).repartition(3)
    else:
        docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    got = [r.doc_id for r in stage(spark, docs, sf).collect()]
    want = kept(rows)
    assert len(got) == len(set(got)) and set(got) == want and len(want) < len(rows)


def test_odd_rows(spark):
    text = " ".join(map(str, range(50)))
    docs = spark.createDataFrame([(None, text, "en", "s", 0, 0.5, 1), (3, text, "en", "s", 0, 0.5, 1), (2, text + " x", "en", "s", 0, 0.5, 1), (7, "a", "en", "s", 0, 0.5, 1), (7, "b", "en", "s", 0, 0.5, 1)], DOC)
    left = jaccard.without_similar(docs)
    assert left.columns == docs.columns and sorted(str(r.doc_id) for r in left.collect()) == ["2", "7", "7", "None"]
    assert jaccard.similar_groups(docs.limit(0)).count() == 0


@pytest.mark.parametrize(("stage", "partitions"), [("jaccard", 3), ("simhash", 1), ("simhash", 8)])
def test_rows_that_repeat_an_id_are_judged_by_their_texts(spark, partitions, stage):
    """Eight texts that share nothing under one id all stay; copies under one id leave one row, the same whatever the partitions."""
    rng = random.Random(4)
    texts = [" ".join(f"v{rng.randrange(10**6)}" for _ in range(40)) for _ in range(8)]
    other = " ".join(f"u{k}" for k in range(40))
    rows = [(5, t, "en", "s", 0, 0.5, 1) for t in texts] + [(6, texts[0], "en", "t", 0, 0.5, 1)] + [(9, other, "en", "x" * k, k, 0.5, 1) for k in range(4)]
    docs = spark.createDataFrame(rows, DOC).repartition(partitions)
    got = (jaccard.without_similar if stage == "jaccard" else simhash.without_near_duplicates)(docs).collect()
    assert sorted(r.text for r in got if r.doc_id == 5) == sorted(texts) and not [r for r in got if r.doc_id == 6]
    row = F.struct(*docs.columns)
    assert [r.n_chars for r in got if r.doc_id == 9] == [docs.where("doc_id = 9").orderBy(F.xxhash64(row)).first().n_chars]


def test_postings_of_the_same_nodes_are_one(spark):
    """Texts that share a passage meet once with the number of its postings, not at each of its shingles; the groups stay."""
    passage = " ".join(f"p{i}" for i in range(40))
    texts = [f"{passage} " + " ".join(f"t{k}x{i}" for i in range(1 + k)) for k in range(3)] + ["alone with other words of its own here"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    postings = jaccard._postings(jaccard.shingle_sets(docs, 5, Fraction("0.8"), 42))
    rows = jaccard._shared_postings(postings).collect()
    shared = postings.groupBy("h").agg(F.count("*").alias("n"), F.sort_array(F.collect_list("node")).alias("nodes")).where("n > 1").collect()
    assert len({r.h for r in rows}) == len({tuple(r.nodes) for r in shared}) < len(shared)
    assert sum(r.times for r in rows) == sum(r.n for r in shared)
    groups = {r.doc_id: r.component_id for r in jaccard.similar_groups(docs).collect()}
    assert groups == {0: 0, 1: 0, 2: 0, 3: 3}


def test_near_copies_below_the_bound_are_told_apart_by_parity(spark):
    """Edits of one text of 400 shingles, few of them similar to each other: hardly a pair that does not link is looked at."""
    rng = random.Random(6)
    base = [f"b{i}" for i in range(400)]
    texts = []
    for k in range(60):
        far = list(base)
        for at in rng.sample(range(400), 8 + k % 12):
            far[at] = f"e{k}x{at}"
        texts.append(" ".join(far))
    sets = [jaccard.shingle_set(t) for t in texts]
    maps = [np.frombuffer(jaccard.parity(x), dtype=np.uint64) for x in sets]
    false = 0
    for i, x in enumerate(sets):
        for j in range(i):
            apart, both = int(np.bitwise_count(maps[i] ^ maps[j]).sum()), len(x) + len(sets[j])
            assert apart <= both - 2 * len(np.intersect1d(x, sets[j]))
            false += 9 * apart <= both and 9 * (both - 2 * len(np.intersect1d(x, sets[j]))) > both
    assert false < 60 * 59 / 2 / 10
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    groups = jaccard.similar_groups(docs).where("doc_id = component_id").collect()
    assert {r.doc_id for r in groups} == kept(list(enumerate(texts)))
