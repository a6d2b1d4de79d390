"""Kernels of the training-data operators against plain versions, without Spark."""

import itertools
import random
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
from xxhash import xxh64_intdigest

from tricount.llm import decontam, extraction, langid, packing, quality, secrets, simhash, topk, toxicity
from tricount.llm.common import WordTable

PATH = public_tokenizers.path("word_bpe_49k.json")


def test_ids_equal_the_tokenizer():
    coder, rng = packing._Ids(PATH), random.Random(3)
    signs = [chr(c) for c in range(256)] + ["’", "Σ", "İ", "é", "́", "漢", " ", "<|endoftext|>", "😀", "'S", "'ll", "١"]
    for _ in range(3000):
        text = "".join(rng.choice(signs) for _ in range(rng.randint(0, 25)))
        assert coder.of(text, 1) == np.asarray([*coder.tokenizer.encode(text, add_special_tokens=False).ids, 1], dtype="<u4").tobytes()


def test_fullest_is_the_best_sum():
    rng = random.Random(5)
    for _ in range(200):
        lengths = [rng.randint(1, 30) for _ in range(rng.randint(0, 9))]
        counts = {x: lengths.count(x) for x in lengths}
        best = max(sum(c) for n in range(len(lengths) + 1) for c in itertools.combinations(lengths, n) if sum(c) <= 40)
        chosen = packing.fullest(counts, 40)
        assert sum(chosen) == best and all(chosen.count(x) <= counts[x] for x in chosen)


def test_plan_places_every_piece_once():
    rng = random.Random(6)
    counts = {}
    for _ in range(3000):
        x = min(64, 1 + int(rng.expovariate(1 / 15)))
        counts[x] = counts.get(x, 0) + 1
    plan = packing.plan_bins(counts, 64)
    places = packing._Places(plan)
    bins = {}
    for x, n in counts.items():
        for rank in range(n):
            b, at = places.of(x, rank)
            bins.setdefault(b, []).append((at, x))
    for spans in bins.values():
        end = 0
        for at, x in sorted(spans):
            assert at == end
            end += x
        assert end <= 64
    assert len(bins) <= 1.01 * sum(x * n for x, n in counts.items()) / 64 + 1


def test_trigram_queries_are_necessary():
    for rule in secrets.BASE_RULES + secrets.MORE_RULES:
        query = secrets.trigram_query(rule.pattern)
        assert bool(query) == (rule.kind != "hex")
    assert secrets.trigram_query("ab|abcd") == []
    assert secrets.trigram_query("abc+d?") == [] or secrets.trigram_query("abc+d?")


def plain_spans(text):
    out = []
    for k, rule in enumerate(secrets.BASE_RULES + secrets.MORE_RULES):
        for m in re.finditer(rule.pattern, text, re.ASCII):
            if m.end(rule.group) - m.start(rule.group) >= rule.least:
                out.append((m.start(), k, m.end()))
    return sorted(out)


def test_scanner_equals_full_scan():
    rng = random.Random(7)
    parts = ["password", "PassWd", "ſecret", "secret", "token", "api_key", "APIKEY", '"', "'", ":", "=", " ", "é", "\n", "0123456789abcdef" * 2, "AKIA", "ABCDEFGH1234", "-----BEGIN RSA PRIVATE KEY-----", "ghp_", "a" * 40, "eyJhbGci.eyJzdWIi.c2lnbmF0dXJl", "x"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 12))) for _ in range(400)] + ["", "x" * 3_000_000 + " token = abcdefgh"]
    assert secrets.Scanner(secrets.BASE_RULES + secrets.MORE_RULES).spans(texts) == [plain_spans(t) for t in texts]


def test_fingerprint_equals_definition():
    for text in ("", " \t\n", "One", "a b", "A b C d e f a b c", "é É x y z\x0bq", "w " * 50_000):
        words = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), text.encode()))
        grams = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
        hashes = [xxh64_intdigest(g, 42) for g in grams]
        assert simhash.fingerprint_of(text) == sum(1 << j for j in range(64) if 2 * sum(h >> j & 1 for h in hashes) > len(hashes))
    assert simhash.fingerprint_of(None) == 0


def test_segments_equal_recursive_definition():
    """The maximal segments: the best one, then the same to its left and right."""

    def plain(w, at=0):
        best = max(((sum(w[i:j]), -i, j) for i in range(len(w)) for j in range(i + 1, len(w) + 1)), default=(0, 0, 0), key=lambda x: x[0])
        if best[0] <= 0:
            return []
        i, j = -best[1], best[2]
        return plain(w[:i], at) + [(at + i, at + j)] + plain(w[j:], at + j)

    rng = random.Random(8)
    for _ in range(300):
        w = [rng.choice([-3, -2, -1, 1, 2, 3]) + rng.random() * 1e-3 for _ in range(rng.randint(0, 14))]
        assert [(a, b) for a, b, _ in toxicity.segments(np.array(w))] == plain(w)


def test_log_odds_and_logistic():
    toxic, other = np.array([50.0, 5, *[500] * 10, 0]), np.array([0.0, 50, *[5000] * 10, 0])
    w = toxicity.log_odds(toxic, other)
    assert w[0] > 1 and not w[1:].any()
    assert not toxicity.log_odds(np.zeros(3), other[:3]).any()
    slope, shift = toxicity.logistic(np.array([0.0, 1, 2, 3] * 20), np.array([0.0, 0, 1, 1] * 20))
    assert slope > 0 and -shift / slope == pytest.approx(1.5, abs=0.1)
    assert toxicity.logistic(np.array([1.0]), np.array([0.0])) == (0.0, -20.0)


def test_quality_fit_separates_and_survives_one_class():
    table = WordTable(quality._codes)
    good = [f"the cat number {i} sat on a mat." for i in range(60)]
    bad = [f"BUY!! NOW!! OFFER{i}!! $$$ ***" for i in range(60)]
    sets = [quality.features(t, table) for pair in zip(good, bad, strict=True) for t in pair]
    model = quality.fit(sets, np.array([1, 0] * 60))
    assert model.score(quality.features("the dog sat on a mat.", table)) > 0.5 > model.score(quality.features("CHEAP!! NOW!! ***", table))
    assert quality.fit([], np.array([], dtype=int)).score(sets[0]) > 0.9
    assert quality.fit(sets[:2], np.array([0, 0])).score(sets[0]) < 0.1
    assert len(quality.features("", table)) == 0 == len(quality.features(None, table))


def test_ngrams_and_letters():
    assert langid.ngram_counts("Abc").sum() == langid.ngram_counts("abc").sum() == 4 + 3
    assert (langid.ngram_counts("a  1 b") == langid.ngram_counts("a b")).all()
    long = "lorem ipsum " * 200_000
    assert langid.ngram_counts(long).sum() == 2 * len(long.strip()) + 1
    assert langid.has_letter("1é") and not langid.has_letter("12 !") and not langid.has_letter(None)


def plain_templates(text):
    """Template words one by one."""
    out, start = [], True
    for chunk in (text or "").replace("\t", " ").replace("\r", "\n").replace("\n", " \n ").split(" "):
        if chunk == "\n":
            start = True
            continue
        word, value, kind, ends = decontam.canonical(chunk)
        if word:
            before = bool(out) and out[-1][1] == decontam._NUM
            if kind == decontam._NAME and start:
                word, kind = value, decontam._PLAIN
            elif kind == decontam._UNIT:
                word, kind = ("<unit>", kind) if before else (word, decontam._PLAIN)
            out.append((word, kind))
            start = False
        start = start or ends
    return out


def test_templates_equal_word_by_word():
    texts = ["Anna buys 3 kg of rice. How much is it?", "buys 12.5 km,\nthen Bob runs $5 or 7%", "", "...", "A. B c.\rD", "He (said) “No”. Yes"]
    t = decontam.Templates()
    for text in texts:
        _, code, kind = t.of(text)
        assert list(zip(code.tolist(), kind.tolist(), strict=True)) == [(zlib.crc32(w.encode()), k) for w, k in plain_templates(text)]


def test_extraction_by_cases():
    model = extraction.default_model()
    page = '<html><head><title>T</title><script>var t="</p>";</script></head><body><nav><ul><li><a href="/a">A</a></ul></nav><!-- x --><div class="ad">Buy now.</div><article><h1>Head &amp; more</h1><p>One\n two<br>three&nbsp;four.<p>Five <b>six</b>seven.</article><div class="comments"><p>First!</p></div><footer>&copy; me</footer></body></html>'
    assert model.text(page) == "Head & more\nOne two three four.\nFive sixseven."
    assert model.text(None) == model.text("") == ""
    assert model.text("<" * 2000) is not None and model.text('<p title="unclosed>text' * 50) is not None
    wrong = total = 0
    for source, gold in extraction.labelled_pages(60, seed=5):
        found = extraction.blocks(source)
        got = model.best([extraction.block_features(b, k, len(found)) for k, b in enumerate(found)])
        wrong += sum(a != b for a, b in zip(got, gold, strict=True))
        total += len(gold)
    assert wrong < 0.02 * total


def test_viterbi_equals_all_paths():
    rng = np.random.default_rng(4)
    crf = extraction.Crf({str(i): i for i in range(5)}, rng.normal(size=(5, 2)), rng.normal(size=(2, 2)), rng.normal(size=2))
    found = [[str(i) for i in range(5) if rng.random() < 0.5] for _ in range(7)]

    def score(path):
        e = sum(crf.state[int(f), s] for fs, s in zip(found, path, strict=True) for f in fs)
        return e + crf.start[path[0]] + sum(crf.move[a, b] for a, b in zip(path[:-1], path[1:], strict=True))

    assert crf.best(found) == list(max(itertools.product((0, 1), repeat=7), key=score))


def test_best_of_ties():
    ids, scores = np.array([5, 1, 3, 2, 9]), np.array([7, 7, 9, 7, 1])
    query = np.array([0, 0, 0, 0, 1])
    assert sorted(ids[topk.best(query, ids, scores, 3)].tolist()) == [1, 2, 3, 9]
    assert len(topk.best(query[:0], ids[:0], scores[:0], 3)) == 0


@pytest.mark.parametrize("wide", [False, True])
def test_meeting_of_lists_equals_all_sums(wide):
    """Sums of at least the cutoff, with fewer partial scores than all; beyond 2^53 in integers."""
    rng = np.random.default_rng(8)
    x, q = rng.normal(0, 60, (900, 64)).round().astype(np.int64), rng.normal(0, 60, (90, 64)).round().astype(np.int64)
    x *= rng.integers(1, 6, (900, 1))
    if wide:
        x <<= 21
        q <<= 21
    cut = lambda v: [v[:, a:b] for a, b in topk._edges(64, 8)]
    want = x @ q.T
    low = np.sort(want, axis=0)[-5].astype(float)
    low[3] = -np.inf
    e, i, total, computed = topk.meet(cut(x), cut(q), low)
    fine = want >= np.where(np.isfinite(low), low, -2.0**62)[None, :]
    assert set(zip(e.tolist(), i.tolist(), strict=True)) == set(zip(*(v.tolist() for v in np.nonzero(fine)), strict=True))
    assert (total == want[e, i]).all()
    assert computed == 8 * want.size if wide else computed < 7 * want.size
