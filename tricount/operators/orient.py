"""Degrees, orientation along a total order, and oriented neighbour lists."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import remove, stored
from . import packed
from .graph import both_ways, held, mix, mixed, together

ORDERS = ("degree", "id", "random")


def degrees(edges: DataFrame) -> DataFrame:
    """id, deg of every node that has an edge."""
    dense = packed.of(edges)
    if dense is not None and dense.names is None:
        return packed.degrees(dense)
    ends = edges.select(F.explode(F.array("src", "dst")).alias("id"))
    return ends.groupBy("id").agg(F.count(F.lit(1)).alias("deg"))


def _by_degree(edges: DataFrame, deg: pa.Table) -> DataFrame:
    """Arcs in the order of degree by degrees that every task holds; deg: id, deg by id."""
    sent = edges.sparkSession.sparkContext.broadcast(tuple(deg.column(k).to_numpy() for k in range(2)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, deg = sent.value
        dense = len(ids) and ids[0] == 0 and ids[-1] == len(ids) - 1
        for batch in together(batches):
            a, b = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(2))
            da, db = (deg[x if dense else np.searchsorted(ids, x)] for x in (a, b))
            low = (da < db) | ((da == db) & (a < b))
            yield pa.RecordBatch.from_arrays([pa.array(np.where(low, a, b), pa.int64()), pa.array(np.where(low, b, a), pa.int64())], names=["src", "dst"])

    return edges.select("src", "dst").mapInArrow(run, "src long, dst long")


def orient(edges: DataFrame, order: str = "degree", seed: int = 42) -> DataFrame:
    """Arcs src -> dst from the lower to the higher end in the order: degree (ties by id), id, or a hash of the id.

    Degree order needs the degree of both ends. Up to ``graph.HELD`` nodes every task holds the degrees and no edge moves;
    beyond, there are two equi-joins with the table of degrees, whose hot ends Spark splits. The other orders need neither.
    """
    if order == "id":
        return edges.select("src", "dst")
    if order == "random":
        low = F.struct(mix(F.col("src"), seed), F.col("src")) < F.struct(mix(F.col("dst"), seed), F.col("dst"))
        named = edges
    elif order == "degree":
        deg, path = stored(degrees(edges))
        few = held(deg, "id")
        if few is not None:
            remove(edges.sparkSession, [path])
            return _by_degree(edges, few)
        named = edges.join(deg.select(F.col("id").alias("src"), F.col("deg").alias("ds")), "src").join(deg.select(F.col("id").alias("dst"), F.col("deg").alias("dd")), "dst")
        low = F.struct("ds", "src") < F.struct("dd", "dst")
    else:
        raise ValueError(f"no such order: {order}")
    return named.select(F.when(low, F.col("src")).otherwise(F.col("dst")).alias("src"), F.when(low, F.col("dst")).otherwise(F.col("src")).alias("dst"))


def ranks(dense: packed.Packed, order: str = "degree", seed: int = 42) -> np.ndarray:
    """Each id's place in the order; ``orient`` has edges rise in it."""
    ids = np.arange(dense.n)
    if order == "id":
        return ids
    if order not in ORDERS:
        raise ValueError(f"no such order: {order}")
    out = np.empty_like(ids)
    out[np.lexsort((ids, packed.held_degrees(dense) if order == "degree" else mixed(ids, seed)))] = ids
    return out


def lists(arcs: DataFrame) -> DataFrame:
    """id and its sorted higher neighbours, for nodes that have some. Under degree order a list has at most sqrt(2m) entries."""
    return arcs.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))


def adjacency(edges: DataFrame, order: str = "degree") -> DataFrame:
    """id, deg, eff, nbrs of every node, also of those whose list is empty."""
    near = both_ways(edges)
    if order == "degree":
        deg = degrees(edges)
        arcs = orient(edges, order)
        full = deg.join(lists(arcs), "id", "left")
    else:
        arcs = orient(edges, order)
        full = near.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("deg")).join(lists(arcs), "id", "left")
    nbrs = F.coalesce("nbrs", F.array().cast("array<bigint>"))
    return full.select("id", "deg", F.size(nbrs).cast("long").alias("eff"), nbrs.alias("nbrs"))


def node_table(edges: DataFrame, order: str = "degree", arcs: DataFrame | None = None) -> DataFrame:
    """id, deg, eff: degrees and effective degrees (entries of the oriented list). ``arcs``: those of ``orient``, if they are at hand."""
    arcs = orient(edges, order) if arcs is None else arcs
    eff = arcs.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("eff"))
    return degrees(edges).join(eff, "id", "left").select("id", "deg", F.coalesce("eff", F.lit(0).cast("long")).alias("eff"))
