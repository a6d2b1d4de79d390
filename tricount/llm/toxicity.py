"""Toxic passages by maximum-scoring segments.

Every token has a log-odds weight between toxic and other labelled texts, with an informative Dirichlet prior from
both together. A token counts once a text, so that a few long texts don't decide. A token that is too rare to be
significant takes the weight of its longest significant stem (its first 6, 5 or 4 letters, counted alike); tokens
without any are neutral, and a small drift makes neutral text fall.
One linear scan of a text then finds all its maximal scoring segments: the toxic passages. Scores of the best segment
of clean texts follow an extreme-value law in the number of tokens; it turns segment scores into expected numbers
of such segments by chance, and a logistic curve fitted on labelled texts turns the evidence of all significant
segments into a probability.

Tokens are hashed into a table of fixed size, so the counts that are gathered and the model that is broadcast have
a fixed size too.

Defined results: a null or empty text has no segment and the score of no evidence; rows that repeat a doc_id among
the labels count as toxic if one of them is; labels that are null are not learned from; without labels of both kinds
all scores are 0; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass
from zlib import crc32

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordTable, arrow_fold, arrow_map

#: Hashed tokens; a power of two.
BUCKETS = 1 << 20
#: Letters of the stems that a rare token falls back on.
STEMS = (6, 5, 4)
#: Fall of the score at a neutral token.
DRIFT = 0.05
_TOKEN = re.compile(r"\w+")


def tokens(text: str | None) -> list[str]:
    return _TOKEN.findall((text or "").lower())


def bucket(token: str) -> int:
    return crc32(token.encode("utf-8", "replace")) & (BUCKETS - 1)


def buckets(token: str) -> list[int]:
    """The buckets of a token and of its stems, the longest first."""
    return [bucket(token), *(bucket("^" + token[:k]) for k in STEMS if len(token) > k)]


def log_odds(toxic: np.ndarray, other: np.ndarray, prior: float = 0.1, sure: float = 1.96, least: float = 1.0) -> np.ndarray:
    """Log-odds of each token with a Dirichlet prior of ``prior`` times all tokens, spread as in both classes.

    What is returned is the bound towards zero, ``sure`` standard errors in; 0 where that falls below ``least``.
    """
    n1, n0 = toxic.sum(), other.sum()
    if not n1 or not n0:
        return np.zeros(len(toxic))
    a = prior * (toxic + other)
    seen = a > 0
    out = np.zeros(len(toxic))
    t, o, p = toxic[seen] + a[seen], other[seen] + a[seen], prior * (n1 + n0)
    delta = np.log(t / (n1 + p - t)) - np.log(o / (n0 + p - o))
    bound = np.abs(delta) - sure * np.sqrt(1 / t + 1 / o)
    out[seen] = np.where(bound >= least, np.sign(delta) * bound, 0.0)
    return out


def segments(weights: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (start, end, score) of a sequence of weights, in one pass.

    Neighbours of one sign are merged first. Kept candidates form a list; a new positive run looks back for the last
    candidate that starts lower, and either stands alone or swallows everything since; pointers to the candidate
    looked up before keep the work linear.
    """
    if not len(weights) or weights.max() <= 0:
        return []
    positive = weights > 0
    edge = np.flatnonzero(positive[1:] != positive[:-1]) + 1
    starts = np.concatenate([[0], edge])
    sums = np.add.reduceat(weights, starts)
    ends = np.concatenate([edge, [len(weights)]])
    kept: list[list] = []  # start, end, level before, level after, index of the last candidate with a lower level before
    level = 0.0
    for s, e, x in zip(starts.tolist(), ends.tolist(), sums.tolist(), strict=True):
        if x <= 0:
            level += x
            continue
        new = [s, e, level, level + x, -1]
        level += x
        while True:
            j = len(kept) - 1
            while j >= 0 and kept[j][2] >= new[2]:
                j = kept[j][4]
            new[4] = j
            if j < 0 or kept[j][3] >= new[3]:
                break
            new = [kept[j][0], new[1], kept[j][2], new[3], kept[j][4]]
            del kept[j:]
        kept.append(new)
    return [(k[0], k[1], k[3] - k[2]) for k in kept]


def gumbel_fit(best: np.ndarray, sizes: np.ndarray) -> tuple[float, float]:
    """lambda and log K of P(best >= x) = 1 - exp(-K n exp(-lambda x)), by moments of the best scores."""
    if len(best) < 2:
        return 1.0, 0.0
    spread = max(float(np.std(best)), 0.5)
    lam = math.pi / math.sqrt(6) / spread
    return lam, float(lam * np.mean(best) - 0.5772156649 - np.mean(np.log(np.maximum(sizes, 1))))


@dataclass(frozen=True)
class ToxicModel:
    weights: np.ndarray
    lam: float
    log_k: float
    slope: float
    shift: float

    def word_table(self) -> WordTable:
        return WordTable(lambda w: next((float(self.weights[b]) for b in buckets(w) if self.weights[b]), 0.0) - DRIFT)

    def found(self, text: str | None, table: WordTable | None = None) -> tuple[int, list[tuple[int, int, float]]]:
        """Number of tokens, and the segments in tokens."""
        table = self.word_table() if table is None else table
        table.trim()
        words = tokens(text)
        return len(words), segments(np.fromiter(map(table.__getitem__, words), dtype=np.float64, count=len(words)))

    def evidence(self, n: int, found: list[tuple[int, int, float]]) -> float:
        """Sum over segments of how far the expected number of such chance segments, K n exp(-lambda s), falls below one; at most 60."""
        base = self.log_k + math.log(max(n, 1))
        values = [self.lam * s - base for _, _, s in found]
        return min(60.0, sum(v for v in values if v > 0)) if values and max(values) > 0 else max([-20.0, *values])

    def score(self, n: int, found: list[tuple[int, int, float]]) -> float:
        if not self.weights.any():
            return 0.0
        return 1 / (1 + math.exp(-max(-50.0, min(50.0, self.slope * self.evidence(n, found) + self.shift))))


def logistic(x: np.ndarray, y: np.ndarray, rounds: int = 50) -> tuple[float, float]:
    """Slope and shift of a logistic curve, by damped Newton steps with a little ridge; labels are softened."""
    n1, n0 = y.sum(), (1 - y).sum()
    if not n1 or not n0:
        return 0.0, 20.0 if n1 else -20.0
    t = np.where(y > 0, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    scale = float(np.std(x)) or 1.0
    z = np.stack([x / scale, np.ones_like(x)], axis=1)
    w = np.array([0.0, math.log(n1 / n0)])

    def loss(w):
        m = z @ w
        return float(np.sum(np.logaddexp(0, m) - t * m) + 1e-3 * w[0] ** 2)

    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -50, 50)))
        g = z.T @ (p - t) + np.array([2e-3 * w[0], 0])
        h = (z * (p * (1 - p))[:, None]).T @ z + np.diag([2e-3, 1e-6])
        step, size, now = np.linalg.solve(h, g), 1.0, loss(w)
        while size > 1e-4 and loss(w - size * step) > now:
            size /= 2
        w = w - size * step
        if abs(size * step).max() < 1e-6:
            break
    return float(w[0] / scale), float(w[1])


def labelled(docs: DataFrame, labels: DataFrame, label: str, learn, most: int) -> DataFrame:
    """doc_id, text and y of at most ``most`` labelled ids for which ``learn`` holds: those whose ids hash lowest.

    One row an id, so ``most`` bounds the rows too: of texts that repeat an id, the one of the least digest.
    """
    marks = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
    chosen = marks.where(learn).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")  # ``most`` ids at most
    return rows.groupBy("doc_id", "y").agg(F.min_by("text", F.xxhash64("text")).alias("text")).select("doc_id", "text", "y")


def train(docs: DataFrame, labels: DataFrame, learn, most: int = 40_000) -> ToxicModel:
    """Learn from at most ``most`` labelled rows for which ``learn`` (on doc_id) holds."""
    sample = labelled(docs, labels, "toxic", learn, most)

    def start():
        return {"n": np.zeros((2, BUCKETS), dtype=np.int64), "words": WordTable(buckets)}

    def add(state, texts, ys):
        for t, y in zip(texts, ys, strict=True):
            state["words"].trim()
            at = np.fromiter({b for w in set(tokens(t)) for b in state["words"][w]}, dtype=np.int64)
            state["n"][int(y > 0), at] += 1

    def end(state):
        at = np.flatnonzero(state["n"].sum(axis=0))
        return {"slot": at, "toxic": state["n"][1, at], "other": state["n"][0, at]}

    # One row per bucket at most: BUCKETS rows, summed on the executors; only those seen in a toxic text or often matter.
    counted = arrow_fold(sample.select("text", "y"), "slot int, toxic long, other long", start, add, end).groupBy("slot").agg(F.sum("toxic").alias("toxic"), F.sum("other").alias("other"))
    n = np.zeros((2, BUCKETS))
    for batch in counted.toArrow().to_batches():
        slot = batch.column(0).to_numpy()
        n[1, slot], n[0, slot] = batch.column(1).to_numpy(), batch.column(2).to_numpy()
    raw = ToxicModel(log_odds(n[1], n[0]).astype(np.float32), 1.0, 0.0, 1.0, 0.0)
    held = docs.sparkSession.sparkContext.broadcast(raw)

    def scan(table, texts, ys):
        made = [held.value.found(t, table) for t in texts]
        return {"y": ys, "n": [m[0] for m in made], "scores": [[s for _, _, s in m[1]] for m in made]}

    rows = arrow_map(sample.select("text", "y"), "y int, n long, scores array<double>", scan, start=lambda: held.value.word_table()).toArrow()
    y, sizes = rows.column("y").to_numpy() > 0, rows.column("n").to_numpy()
    scores = rows.column("scores").to_pylist()
    best = np.array([max(s, default=0.0) for s in scores])
    lam, log_k = gumbel_fit(best[~y], sizes[~y])
    model = ToxicModel(raw.weights, lam, log_k, 1.0, 0.0)
    x = np.array([model.evidence(int(n), [(0, 0, v) for v in s]) for n, s in zip(sizes, scores, strict=True)])
    slope, shift = logistic(x, y.astype(float)) if len(y) else (0.0, -20.0)
    return ToxicModel(raw.weights, lam, log_k, slope, shift)


def score_documents(docs: DataFrame, model: ToxicModel, threshold: float = 0.3) -> DataFrame:
    """doc_id, score, predicted, the number of significant segments and the best one (in tokens) of every document."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def rows(table, ids, texts):
        made = [held.value.found(t, table) for t in texts]
        scores = [held.value.score(*m) for m in made]
        top = [max(m[1], key=lambda s: s[2], default=None) for m in made]
        line = [held.value.log_k + math.log(max(m[0], 1)) for m in made]
        return {
            "doc_id": ids, "score": scores, "predicted": [int(s >= threshold) for s in scores],
            "n_segments": [sum(held.value.lam * s > b for _, _, s in m[1]) for m, b in zip(made, line, strict=True)],
            "best_start": [t and t[0] for t in top], "best_end": [t and t[1] for t in top],
        }

    return arrow_map(docs.select("doc_id", "text"), "doc_id long, score double, predicted int, n_segments int, best_start long, best_end long", rows, start=lambda: held.value.word_table())
