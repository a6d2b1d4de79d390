"""Nearest-centroid language identification.

A text becomes a vector of hashed byte 2- and 3-grams of its lower-cased letters, weighted by 1 + log(tf) times idf
and normalised to length one. Each language has several centroids, the means of clusters found by spherical k-means
on a bounded sample of its training texts; document frequencies come from all training texts. The language of the
centroid with the largest cosine is predicted; a text farther from that centroid than nearly all of its own sample
is marked as rejected.

The model has a bounded size: at most LANGUAGES x clusters x DIM numbers.

Defined results: a null text or one without a letter is "und" with score 0; rows without a language are not learned
from; without training texts every row is "und"; ties go to the language first in the alphabet; repeated rows get
equal results; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import arrow_fold, arrow_map

#: Hashed dimensions; a power of two.
DIM = 1 << 13
#: Bytes that are turned into n-grams at once.
CHUNK = 1 << 20
#: Languages that a model may hold.
LANGUAGES = 1024
#: Lanes in which a language's rows are ranked for the sample.
LANES = 16
_SPACE = np.arange(256, dtype=np.uint8)
_SPACE[[b for b in range(128) if not chr(b).isalpha()]] = 32


def has_letter(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


def ngram_counts(text: str | None) -> np.ndarray:
    """Counts of the hashed 2- and 3-grams; runs of what isn't a letter count as one space."""
    raw = np.frombuffer((" " + (text or "").lower() + " ").encode("utf-8", "replace"), dtype=np.uint8)
    b = _SPACE[raw]
    b = b[np.concatenate([[True], (b[1:] != 32) | (b[:-1] != 32)])]
    total = np.zeros(DIM, dtype=np.int64)
    for at in range(0, max(1, len(b) - 1), CHUNK):
        x = b[at : at + CHUNK + 2].astype(np.uint32)
        for n, stop in ((2, min(CHUNK, len(x) - 1)), (3, min(CHUNK, len(x) - 2))):
            if stop > 0:
                code = x[:stop] * np.uint32(65599) + x[1 : stop + 1]
                if n == 3:
                    code = code * np.uint32(65599) + x[2 : stop + 2]
                code *= np.uint32(2654435761)
                total += np.bincount(code >> np.uint32(32 - 13), minlength=DIM)
    return total


def _vectors(texts: list, idf: np.ndarray) -> np.ndarray:
    out = np.zeros((len(texts), DIM), dtype=np.float32)
    for i, t in enumerate(texts):
        c = ngram_counts(t)
        k = np.flatnonzero(c)
        out[i, k] = (1 + np.log(c[k])) * idf[k]
    norm = np.linalg.norm(out, axis=1, keepdims=True)
    return out / np.where(norm > 0, norm, 1)


@dataclass(frozen=True)
class LanguageModel:
    """idf, unit centroids, and for each centroid its language and the smallest cosine that isn't rejected."""

    idf: np.ndarray
    centroids: np.ndarray
    langs: tuple[str, ...]
    least: np.ndarray

    def predict(self, texts: list) -> list[tuple[str, float, bool]]:
        out = []
        for at in range(0, len(texts), 64):
            part = texts[at : at + 64]
            cos = _vectors(part, self.idf) @ self.centroids.T if len(self.langs) else np.zeros((len(part), 0))
            for t, row in zip(part, cos, strict=True):
                if not len(row) or not has_letter(t):
                    out.append(("und", 0.0, True))
                    continue
                k = int(np.argmax(row))
                out.append((self.langs[k], float(min(1.0, max(0.0, row[k]))), bool(row[k] < self.least[k])))
        return out


def _clusters(x: np.ndarray, k: int, rounds: int = 12) -> tuple[np.ndarray, np.ndarray]:
    """Spherical k-means from spread seeds; the unit centroids, and each row's cosine with its own, by centroid."""
    seeds = [0]
    while len(seeds) < min(k, len(x)):
        near = (x @ x[seeds].T).max(axis=1)
        far = int(np.argmin(near))
        if near[far] > 0.9999:
            break
        seeds.append(far)
    c = x[seeds].copy()
    for _ in range(rounds):
        own = (x @ c.T).argmax(axis=1)
        for j in range(len(c)):
            if (own == j).any():
                mean = x[own == j].sum(axis=0)
                c[j] = mean / (np.linalg.norm(mean) or 1)
    return c, x @ c.T


def train(docs: DataFrame, learn: Column, per_lang: int = 300, clusters: int = 3, strict: float = 0.005) -> LanguageModel:
    """Learn from the rows for which ``learn`` holds, with a non-null lang and a letter.

    per_lang bounds the clustering sample of each language (rows of the smallest hashes of the id, rounded up to the lanes); document frequencies
    are taken over all rows. strict is the share of a centroid's sample that it would reject.
    """
    rows = docs.where(learn & F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "lang", "text")

    def add(state, texts):
        for t in texts:
            if has_letter(t):
                state["df"] += ngram_counts(t) > 0
                state["n"][0] += 1

    def end(state):
        return {"slot": [*range(DIM), DIM], "df": [*state["df"].tolist(), int(state["n"][0])]}

    # A partition sends DIM + 1 counts whatever its size; they are summed on the executors.
    partial = arrow_fold(rows.select("text"), "slot int, df long", lambda: {"df": np.zeros(DIM, dtype=np.int64), "n": np.zeros(1, dtype=np.int64)}, add, end)
    counts = dict(partial.groupBy("slot").agg(F.sum("df")).collect())
    n = counts.get(DIM, 0)
    idf = np.log((1 + n) / (1 + np.array([counts.get(k, 0) for k in range(DIM)], dtype=np.float64))).astype(np.float32) + np.float32(1)

    if rows.select("lang").distinct().limit(LANGUAGES + 1).count() > LANGUAGES:
        raise ValueError(f"more than {LANGUAGES} languages")
    # A language may hold most rows: it is ranked in lanes by hash, each of which gives its share of the sample. Equal
    # rows of one id count once, so the sample is bounded by rows.
    hashed = rows.select("doc_id", "lang", F.xxhash64("text").alias("_t"), F.xxhash64("doc_id").alias("_h")).distinct().withColumn("_lane", F.pmod("_h", F.lit(LANES)))
    order = Window.partitionBy("lang", "_lane").orderBy("_h", "doc_id", "_t")
    key = ["doc_id", "lang", "_t"]
    chosen = hashed.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= -(-per_lang // LANES)).select(key)  # LANGUAGES x (per_lang + LANES) rows at most
    sample = rows.withColumn("_t", F.xxhash64("text")).join(F.broadcast(chosen), key).groupBy(key).agg(F.min("text").alias("text")).select("lang", "text")

    def vectors(langs, texts):
        kept = [(x, t) for x, t in zip(langs, texts, strict=True) if has_letter(t)]
        return {"lang": [x for x, _ in kept], "v": [r.astype("<f2").tobytes() for r in _vectors([t for _, t in kept], idf)]}

    by: dict[str, list] = {}
    for lang, v in arrow_map(sample, "lang string, v binary", vectors).toLocalIterator():
        by.setdefault(lang, []).append(bytes(v))
    centroids, langs, least = [], [], []
    for lang in sorted(by):
        x = np.stack([np.frombuffer(v, dtype="<f2") for v in sorted(by[lang])]).astype(np.float32)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        c, cos = _clusters(x, clusters)
        own = cos.argmax(axis=1)
        for j in range(len(c)):
            if (own == j).any():
                centroids.append(c[j])
                langs.append(lang)
                least.append(float(np.quantile(cos[own == j, j], strict)))
    return LanguageModel(idf, np.array(centroids, dtype=np.float32).reshape(-1, DIM), tuple(langs), np.array(least))


def identify(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, lang_pred, score (cosine with the nearest centroid) and rejected (too far from it) of every document."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def rows(ids, texts):
        made = held.value.predict(texts)
        return {"doc_id": ids, "lang_pred": [m[0] for m in made], "score": [m[1] for m in made], "rejected": [m[2] for m in made]}

    return arrow_map(docs.select("doc_id", "text"), "doc_id long, lang_pred string, score double, rejected boolean", rows)
