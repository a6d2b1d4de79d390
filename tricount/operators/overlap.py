"""Overlapping blocks: each holds the lists of its core nodes and of all their higher neighbours, and counts alone."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from .exact import by_block
from .exchange import Owned


def build(owned: Owned, mode: str = "full") -> DataFrame:
    """part, id, is_core, nbrs. full: members bring their whole lists; induced: only entries that are in the block too."""
    core = owned.nodes.select("part", "id", F.lit(True).alias("is_core"), "nbrs")
    members = owned.nodes.select("part", F.explode("nbrs").alias("id")).distinct()
    outside = members.join(owned.nodes.select("part", "id"), ["part", "id"], "left_anti")
    # Lists take far more room in memory than in their files, by which Spark would judge that they can be broadcast.
    copies = outside.join(owned.nodes.select("id", "nbrs").hint("merge"), "id").select("part", "id", F.lit(False).alias("is_core"), "nbrs")
    if mode == "full":
        return core.unionByName(copies)
    if mode != "induced":
        raise ValueError(f"no such mode: {mode}")
    inside = core.select("part", F.col("id").alias("w")).unionByName(outside.select("part", F.col("id").alias("w")))
    kept = copies.select("part", "id", F.explode("nbrs").alias("w")).join(inside, ["part", "w"], "left_semi").groupBy("part", "id").agg(F.sort_array(F.collect_list("w")).alias("kept"))
    return core.unionByName(copies.drop("nbrs").join(kept, ["part", "id"], "left").select("part", "id", "is_core", F.coalesce("kept", F.array().cast("array<bigint>")).alias("nbrs")))


def sizes(blocks: DataFrame) -> DataFrame:
    """part, v_count, e_count: nodes known to the block (held or named in a core list) and list entries held."""
    return blocks.groupBy("part").agg(F.count(F.lit(1)).alias("v_count"), F.sum(F.size("nbrs").cast("long")).alias("e_count"))


def count(blocks: DataFrame) -> DataFrame:
    """part, triangles: intersections for core nodes against lists that the block holds; nothing is sent."""
    blocks = cut(blocks)
    held = blocks.where("size(nbrs) > 0").select(F.col("part").alias("dest"), F.lit(0).alias("kind"), F.col("id").alias("src"), "nbrs")
    core = blocks.where("is_core and size(nbrs) > 1").select(F.col("part").alias("dest"), F.lit(1).alias("kind"), F.col("id").alias("src"), "nbrs")
    met = held.unionByName(core).repartition("dest").sortWithinPartitions("dest", "kind", "src").mapInArrow(by_block, "part int, n long")
    found = met.groupBy("part").agg(F.sum("n").alias("n"))
    return blocks.select("part").distinct().join(found, "part", "left").select("part", F.coalesce("n", F.lit(0).cast("long")).alias("triangles"))
