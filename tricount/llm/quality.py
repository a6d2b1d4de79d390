"""Quality classification with naive Bayes support vectors.

Features are indicators of word n-grams (one and two words) and of the shapes of words and of pairs of neighbours,
hashed into a table of fixed size. Each indicator is scaled by its log-count ratio between good and bad texts; a
linear hinge-loss model is fitted to the scaled indicators, normalised to length one, by dual coordinate descent on a
bounded sample of labelled rows; a logistic curve fitted on a held-back part of that sample gives probabilities.

The model is BUCKETS numbers whatever the data.

Defined results: a null or empty text has no feature and gets the score of margin bias; labels that are null are not
learned from; an id with several labels counts as good if one of them is; with labels of one kind only, that kind
is predicted, and with none score is 1 (nothing is rejected); an empty table gives an empty table; other columns are
ignored.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass
from zlib import crc32

import numpy as np
from pyspark.sql import DataFrame

from .common import WordTable, arrow_map
from .toxicity import labelled, logistic

#: Hashed features; a power of two.
BUCKETS = 1 << 18
#: Words whose features are computed at once; bounds the memory for a very long text.
CHUNK = 1 << 16
_SHAPES = ((re.compile(r"[^\W\d_]+"), lambda m: "A" if m[0].isupper() and len(m[0]) > 1 else "a"), (re.compile(r"\d+"), lambda m: "0"))
_RUN = re.compile(r"(.)\1+")


def shape(word: str) -> str:
    """Letters as a or A, digits as 0, longer runs of a sign as two."""
    bare = word.rstrip(".,;:")
    if bare.isalpha() and len(word) - len(bare) < 3:  # most words
        return ("A" if bare.isupper() and len(bare) > 1 else "a") + word[len(bare) :]
    for pattern, put in _SHAPES:
        word = pattern.sub(put, word)
    return _RUN.sub(r"\1\1", word)


def _codes(word: str) -> int:
    """32 bits for the word and 32 for its shape, in one integer."""
    return crc32(word.lower().encode("utf-8", "replace")) << 32 | crc32(shape(word).encode("utf-8", "replace"))


def word_codes() -> WordTable:
    return WordTable(_codes)


def _hashed(x: np.ndarray, salt: int) -> np.ndarray:
    x = (x + np.uint64(salt)) * np.uint64(0x9E3779B97F4A7C15)
    return (x >> np.uint64(64 - 18)).astype(np.int64)


_SEEN = np.zeros(BUCKETS, dtype=bool)


def features(text: str | None, table: WordTable) -> np.ndarray:
    """Sorted distinct feature numbers of a text."""
    words = (text or "").split()
    table.trim()
    for at in range(0, len(words), CHUNK):
        codes = np.fromiter(map(table.__getitem__, words[at : at + CHUNK + 1]), dtype=np.uint64)
        word, form = codes >> np.uint64(32), codes & np.uint64(0xFFFFFFFF)
        m = np.uint64(0x100000001B3)
        same = word[1:] == word[:-1]
        pair = np.where(same, np.uint64(7), word[:-1] * m ^ word[1:])  # a repeated word is one feature, whichever word
        for salt, x in enumerate((word, pair, form, form[:-1] * m ^ form[1:]), 1):
            _SEEN[_hashed(x, salt)] = True
    found = np.flatnonzero(_SEEN)
    _SEEN[found] = False
    return found


def log_ratios(sets: list[np.ndarray], y: np.ndarray, alpha: float = 1.0) -> np.ndarray:
    """Log-count ratio of each feature between the classes, smoothed by alpha; 0 for a feature never seen."""
    n = np.zeros((2, BUCKETS))
    for s, k in zip(sets, y, strict=True):
        n[int(k), s] += 1
    p, q = n[1] + alpha, n[0] + alpha
    r = np.log(p / p.sum()) - np.log(q / q.sum())
    return np.where(n.sum(axis=0) > 0, r, 0.0)


def dual_descent(sets: list[np.ndarray], y: np.ndarray, r: np.ndarray, cost: float = 1.0, epochs: int = 8, seed: int = 7) -> tuple[np.ndarray, float]:
    """Weights and bias of the L1-loss support vector machine on rows r[set] / |r[set]|, by dual coordinate descent."""
    sign = np.where(y > 0, 1.0, -1.0)
    rows = [r[s] / (np.linalg.norm(r[s]) or 1.0) for s in sets]
    square = np.array([float(x @ x) + 1.0 for x in rows])  # the bias is a constant feature of one
    share = np.array([0.5 / max(1, int((y <= 0).sum())), 0.5 / max(1, int((y > 0).sum()))]) * len(y)
    limit = cost * share[(y > 0).astype(int)]  # both classes weigh the same
    w, bias, alpha = np.zeros(BUCKETS), 0.0, np.zeros(len(sets))
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in rng.permutation(len(sets)):
            s, x = sets[i], rows[i]
            g = sign[i] * (float(w[s] @ x) + bias) - 1.0
            new = min(max(alpha[i] - g / square[i], 0.0), limit[i])
            d = (new - alpha[i]) * sign[i]
            if d:
                w[s] += d * x
                bias += d
                alpha[i] = new
                moved = max(moved, abs(d))
        if moved < 1e-3:
            break
    return w, bias


@dataclass(frozen=True)
class QualityModel:
    ratios: np.ndarray
    weights: np.ndarray
    bias: float
    slope: float
    shift: float

    def margin(self, found: np.ndarray) -> float:
        x = self.ratios[found]
        return float(x @ self.weights[found]) / (float(np.sqrt(x @ x)) or 1.0) + self.bias

    def score(self, found: np.ndarray) -> float:
        return 1 / (1 + math.exp(-max(-50.0, min(50.0, self.slope * self.margin(found) + self.shift))))


def fit(sets: list[np.ndarray], y: np.ndarray) -> QualityModel:
    """Fit on four fifths of the rows, the logistic curve on the others."""
    zero = np.zeros(BUCKETS, dtype=np.float32)
    if not len(y) or y.min() == y.max():
        return QualityModel(zero, zero, 0.0, 0.0, 50.0 if not len(y) or y[0] > 0 else -50.0)
    back = np.arange(len(y)) % 5 == 4
    if y[~back].min() == y[~back].max():
        back[:] = False
    own = [s for s, b in zip(sets, back, strict=True) if not b]
    r = log_ratios(own, y[~back])
    w, bias = dual_descent(own, y[~back], r)
    model = QualityModel(r.astype(np.float32), w.astype(np.float32), bias, 1.0, 0.0)
    judged = back if back.any() else ~back
    margins = np.array([model.margin(s) for s, b in zip(sets, judged, strict=True) if b])
    slope, shift = logistic(margins, y[judged].astype(float))
    return QualityModel(model.ratios, model.weights, bias, slope, shift)


def train(docs: DataFrame, labels: DataFrame, learn, most: int = 8_000) -> QualityModel:
    """Learn from at most ``most`` labelled rows for which ``learn`` (on doc_id) holds; their feature sets reach the driver."""
    sample = labelled(docs, labels, "quality", learn, most)

    def rows(table, ids, texts, ys):
        return {"doc_id": ids, "y": ys, "found": [features(t, table).astype("<u4").tobytes() for t in texts]}

    made = arrow_map(sample, "doc_id long, y int, found binary", rows, start=word_codes).toArrow().sort_by("doc_id")
    sets = [np.frombuffer(b.as_py(), dtype="<u4").astype(np.int64) for b in made.column("found")]
    return fit(sets, made.column("y").to_numpy())


def score_documents(docs: DataFrame, model: QualityModel, threshold: float = 0.3) -> DataFrame:
    """doc_id, score and predicted of every document."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def rows(table, ids, texts):
        scores = [held.value.score(features(t, table)) for t in texts]
        return {"doc_id": ids, "score": scores, "predicted": [int(s >= threshold) for s in scores]}

    return arrow_map(docs.select("doc_id", "text"), "doc_id long, score double, predicted int", rows, start=word_codes)


def keep_good(docs: DataFrame, model: QualityModel, threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs`` whose score reaches the threshold, all columns as they were."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    names = docs.columns
    ddl = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)

    def rows(table, *columns):
        keep = [held.value.score(features(t, table)) >= threshold for t in columns[names.index("text")]]
        return {n: [v for v, k in zip(c, keep, strict=True) if k] for n, c in zip(names, columns, strict=True)}

    return arrow_map(docs, ddl, rows, start=word_codes)
