"""Baselines in the style of MapReduce, from the public literature: two-paths, and buckets of nodes in triples or pairs."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import partial
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import exact, packed
from .graph import both_ways, mix, mixed
from .orient import orient


def two_paths(edges: DataFrame, oriented: bool = False) -> DataFrame:
    """v, u, w: pairs of neighbours at each node; oriented: only of higher neighbours in degree order."""
    near = orient(edges) if oriented else both_ways(edges)
    a = near.select(F.col("src").alias("v"), F.col("dst").alias("u"))
    b = near.select(F.col("src").alias("v"), F.col("dst").alias("w"))
    return a.join(b, "v").where("u < w")


def count_two_paths(edges: DataFrame, oriented: bool = False) -> DataFrame:
    """Two-paths that an edge closes: three for each triangle, or one if oriented."""
    closed = exact.closed_paths(orient(edges) if oriented else both_ways(edges), edges)
    return closed.agg(F.expr(f"coalesce(sum(n), 0) div {1 if oriented else 3}").alias("triangles"))


def bucketed(edges: DataFrame, rho: int, seed: int = 42) -> DataFrame:
    """Edges with the buckets bs, bd of their ends."""
    return edges.select("src", "dst", (mix(F.col("src"), seed) % rho).cast("int").alias("bs"), (mix(F.col("dst"), seed) % rho).cast("int").alias("bd"))


def triple_copies(edges: DataFrame, rho: int, seed: int = 42) -> DataFrame:
    """One copy of each edge for every triple i < j < k of buckets that has both of its ends'."""
    if rho < 3:
        raise ValueError("three buckets at least")
    all3 = F.array(*(F.array(*map(F.lit, k)) for k in combinations(range(rho), 3)))
    return bucketed(edges, rho, seed).withColumn("key", F.explode(F.filter(all3, lambda t: F.array_contains(t, F.col("bs")) & F.array_contains(t, F.col("bd")))))


def _closed(copies: DataFrame, keys: list[tuple[int, ...]], rho: int, seed: int) -> DataFrame:
    """kinds (distinct buckets of a triangle), found: how often such triangles a < b < c are met over all reducers.

    Each reducer's edges are a network of their own: beside each other under shifted ids they are one, whose lists meet in blocks.
    So a reducer's edges need not fit a task, and no two-path is moved.
    """
    n = (copies.agg(F.max("dst")).collect()[0][0] or 0) + 1
    place = F.array_position(F.array(*(F.array(*map(F.lit, k)) for k in keys)), F.col("key")) - 1

    def counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = np.zeros(4, dtype=np.int64)
        for corners in exact._corners(batches):
            x, y, z = (mixed(c % n, seed) % rho for c in corners)
            found += np.bincount(1 + (y != x) + ((z != x) & (z != y)), minlength=4)
        some = np.flatnonzero(found)
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array(found[some], pa.int64())], names=["kinds", "found"])

    beside = copies.select((place * n + F.col("src")).alias("src"), (place * n + F.col("dst")).alias("dst"))
    return exact._sent(beside).mapInArrow(counts, "kinds int, found long").groupBy("kinds").agg(F.sum("found").alias("found"))


def _reduced(bucket: np.ndarray, keys: list[tuple[int, ...]], found: np.ndarray, a: int, b: np.ndarray, shared: Callable, kind: int) -> None:
    """Every reducer looks at its own copies of the edges of a, and at the common neighbours in one of its buckets."""
    first, second, last = int(bucket[a]), bucket[b], kind
    for key in keys:
        if first in key and last in key:
            for some, ones in shared(np.flatnonzero(np.isin(second, key))):
                kinds = 1 + (second[some] != first) + ((last != first) & (last != second[some]))
                found += np.bincount(kinds, np.add.reduce(ones, axis=1, dtype=np.uint32), 4).astype(np.int64)


def _closed_dense(dense: packed.Packed, keys: list[tuple[int, ...]], rho: int, seed: int) -> DataFrame:
    """What ``_closed`` gives, in a dense network: copies are made where an edge is stored; none is moved."""
    bucket = mixed(np.arange(dense.n), seed) % rho
    met = packed.common(dense, np.arange(dense.n), partial(_reduced, bucket, keys), 4, columns=[np.flatnonzero(bucket == q) for q in range(rho)])
    return met.select(F.col("id").cast("int").alias("kinds"), F.col("n").alias("found"))


def bucket_triple_counts(edges: DataFrame, rho: int, seed: int = 42) -> DataFrame:
    """kinds (distinct buckets of a triangle), found: how often such triangles are met over all reducers."""
    dense = packed.of(edges)
    if dense is not None and dense.names is None and rho >= 3:
        return _closed_dense(dense, list(combinations(range(rho), 3)), rho, seed)
    return _closed(triple_copies(edges, rho, seed), list(combinations(range(rho), 3)), rho, seed)


def count_bucket_triples(edges: DataFrame, rho: int = 4, seed: int = 42) -> DataFrame:
    """A triangle over three buckets is met once, over two rho - 2 times, over one C(rho - 1, 2) times; sums are divided by that."""
    times = F.when(F.col("kinds") == 3, 1).when(F.col("kinds") == 2, rho - 2).otherwise((rho - 1) * (rho - 2) // 2)
    found = bucket_triple_counts(edges, rho, seed).select((F.col("found") / times).alias("w"))
    return found.agg(F.coalesce(F.round(F.sum("w")), F.lit(0)).cast("long").alias("triangles"))


def count_bucket_pairs_triples(edges: DataFrame, rho: int = 4, seed: int = 42) -> DataFrame:
    """Pairs of buckets find triangles over one or two buckets, triples only those over three; one-bucket triangles are met rho - 1 times."""
    cut = bucketed(edges, rho, seed)
    two_of = list(combinations(range(rho), 2))
    pairs = F.array(*(F.array(*map(F.lit, k)) for k in two_of))
    two = cut.withColumn("key", F.explode(F.filter(pairs, lambda t: F.array_contains(t, F.col("bs")) & F.array_contains(t, F.col("bd")))))
    three = triple_copies(cut.where("bs <> bd").select("src", "dst"), rho, seed)
    low = _closed(two, two_of, rho, seed).select((F.col("found") / F.when(F.col("kinds") == 2, 1).otherwise(rho - 1)).alias("w"))
    high = _closed(three, list(combinations(range(rho), 3)), rho, seed).where("kinds = 3").select(F.col("found").cast("double").alias("w"))
    return low.unionByName(high).agg(F.coalesce(F.round(F.sum("w")), F.lit(0)).cast("long").alias("triangles"))
