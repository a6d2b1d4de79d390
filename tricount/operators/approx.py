"""Approximate counts: sampled wedges, sparsified edges, and a bounded reservoir. All picks are deterministic hashes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .exact import count_intersect
from .graph import both_ways, mix
from .mapreduce import two_paths

#: Hash values run from 0 to RANGE - 1.
RANGE = 1 << 32


def edge_hash(seed: int):
    """32 bits for an edge, from both ends in turn."""
    return mix((mix(F.col("src"), seed) + F.col("dst")) % (1 << 31), seed + 1)


def sparsify(edges: DataFrame, p: float = 0.5, seed: int = 42) -> DataFrame:
    """kept edges, their triangles, and the estimate triangles / p^3."""
    kept = edges.where(edge_hash(seed) < int(p * RANGE))
    n = kept.agg(F.count(F.lit(1)).alias("kept"))
    return count_intersect(kept).join(F.broadcast(n)).select("kept", "triangles", F.round(F.col("triangles") / (p**3), 6).alias("estimate"))


def stream_sample(edges: DataFrame, memory: int = 50_000, seed: int = 42) -> DataFrame:
    """The ``memory`` edges of lowest priority, as a reservoir keeps them; the estimate divides by the chance that three edges stay."""
    m = edges.count()
    held = edges.withColumn("h", edge_hash(seed)).orderBy("h", "src", "dst").limit(memory).select("src", "dst")
    k = min(memory, m)
    scale = 1.0 if k >= m else (m * (m - 1.0) * (m - 2.0)) / max(1.0, k * (k - 1.0) * (k - 2.0))
    return count_intersect(held).select(F.lit(k).cast("long").alias("kept"), "triangles", F.round(F.col("triangles") * scale, 6).alias("estimate"))


def wedge_sample(edges: DataFrame, share: float = 0.05, seed: int = 42) -> DataFrame:
    """wedges in all, probed, closed, the estimate (three closed wedges to a triangle) and its standard error.

    A wedge is probed if the hash of its three nodes falls below ``share``: each wedge has the same chance.
    """
    pick = mix((mix((mix(F.col("v"), seed) + F.col("u")) % (1 << 31), seed) + F.col("w")) % (1 << 31), seed)
    deg = both_ways(edges).groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    total = deg.agg(F.coalesce(F.sum(F.expr("d * (d - 1) div 2")), F.lit(0)).alias("wedges"))
    probed = two_paths(edges).where(pick < int(share * RANGE))
    closing = edges.select(F.col("src").alias("u"), F.col("dst").alias("w"), F.lit(1).alias("hit"))
    seen = probed.join(closing, ["u", "w"], "left").agg(F.count(F.lit(1)).alias("probed"), F.coalesce(F.sum("hit"), F.lit(0)).alias("closed"))
    rate = F.col("closed") / F.greatest("probed", F.lit(1))
    return seen.join(F.broadcast(total)).select(
        "wedges", "probed", "closed", F.round(rate * F.col("wedges") / 3, 6).alias("estimate"),
        F.round(F.col("wedges") / 3 * F.sqrt(rate * (1 - rate) / F.greatest("probed", F.lit(1))), 6).alias("stderr"),
    )


def compared(estimate: DataFrame, edges: DataFrame) -> DataFrame:
    """The estimate beside the exact count, with the relative error."""
    exact = count_intersect(edges).withColumnRenamed("triangles", "exact")
    return estimate.join(F.broadcast(exact)).withColumn("error", F.round(F.abs(F.col("estimate") - F.col("exact")) / F.greatest("exact", F.lit(1)), 6))
