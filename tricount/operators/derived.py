"""Quantities that rest on triangles: per-node counts, clustering, transitivity, edge support, trusses, triangle components."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from .exact import corner_counts, count_intersect, edges_among_neighbours, list_triangles
from .graph import both_ways
from .orient import degrees


def node_triangles(edges: DataFrame) -> DataFrame:
    """id, triangles of every node, zeros included."""
    return degrees(edges).select("id").join(corner_counts(edges), "id", "left").select("id", F.coalesce("n", F.lit(0).cast("long")).alias("triangles"))


def node_triangles_def(edges: DataFrame) -> DataFrame:
    """The same by the definition: edges among the neighbours."""
    met = edges_among_neighbours(edges).select("id", F.expr("n div 2").alias("n"))
    return degrees(edges).select("id").join(met, "id", "left").select("id", F.coalesce("n", F.lit(0).cast("long")).alias("triangles"))


def local_clustering(edges: DataFrame) -> DataFrame:
    """id, clustering: closed pairs of neighbours over all of them; 0 below degree two."""
    d = F.col("deg")
    return node_triangles(edges).join(degrees(edges), "id").select("id", F.when(d > 1, F.round(2 * F.col("triangles") / (d * (d - 1)), 6)).otherwise(0.0).alias("clustering"))


def average_clustering(edges: DataFrame) -> DataFrame:
    d = F.col("deg")
    each = node_triangles(edges).join(degrees(edges), "id").select(F.when(d > 1, 2 * F.col("triangles") / (d * (d - 1))).otherwise(0.0).alias("c"))
    return each.agg(F.round(F.avg("c"), 6).alias("clustering"))


def transitivity(edges: DataFrame) -> DataFrame:
    """Three times the triangles over the two-paths."""
    paths = degrees(edges).agg(F.sum(F.expr("deg * (deg - 1) div 2")).alias("paths"))
    found = count_intersect(edges)
    return found.join(F.broadcast(paths)).select("triangles", "paths", F.round(3 * F.col("triangles") / F.col("paths"), 6).alias("transitivity"))


def _sides(triangles: DataFrame) -> DataFrame:
    side = lambda x, y: F.struct(F.least(x, y).alias("src"), F.greatest(x, y).alias("dst"))
    return triangles.select("a", "b", "c", F.explode(F.array(side("a", "b"), side("b", "c"), side("a", "c"))).alias("e")).select("a", "b", "c", "e.src", "e.dst")


def edge_support(edges: DataFrame) -> DataFrame:
    """src, dst, support: triangles over each edge, zeros included."""
    met = _sides(list_triangles(edges)).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
    return edges.join(met, ["src", "dst"], "left").select("src", "dst", F.coalesce("n", F.lit(0).cast("long")).alias("support"))


def k_truss(edges: DataFrame, k: int, rounds: int = 100) -> DataFrame:
    """The largest set of edges each in k - 2 triangles of the set, by dropping weak edges until none is left."""
    now = cut(edges)
    m = now.count()
    for _ in range(rounds):
        now = cut(edge_support(now).where(F.col("support") >= k - 2).select("src", "dst"))
        left = now.count()
        if left == m:
            return now
        m = left
    raise RuntimeError(f"not settled in {rounds} rounds")


def connected_components(links: DataFrame, rounds: int = 100) -> DataFrame:
    """node, component (smallest node reachable) of a table of links a, b: labels fall to the neighbours' least, then jump."""
    near = cut(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct())
    now = cut(near.select(F.col("a").alias("node")).distinct().withColumn("component", F.col("node")))
    last = None
    for _ in range(rounds):
        heard = near.join(now.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node")).agg(F.min("component").alias("m"))
        low = now.join(heard, "node").select("node", F.least("component", "m").alias("component"))
        jump = low.select(F.col("node").alias("component"), F.col("component").alias("further"))
        now = cut(low.join(jump, "component", "left").select("node", F.coalesce("further", "component").alias("component")))
        seen = now.agg(F.sum(F.xxhash64("component").cast("decimal(38,0)"))).collect()[0][0]
        if seen == last:
            return now
        last = seen
    raise RuntimeError(f"not settled in {rounds} rounds")


def triangle_components(edges: DataFrame) -> DataFrame:
    """src, dst, triangles, nodes: triangles joined by shared edges; a component is named by its smallest edge."""
    found = cut(list_triangles(edges))
    sides = _sides(found)
    name = lambda x, y: F.struct(F.least(x, y).alias("src"), F.greatest(x, y).alias("dst"))
    first, second, third = name("a", "b"), name("b", "c"), name("a", "c")
    links = found.select(F.explode(F.array(F.struct(first.alias("a"), second.alias("b")), F.struct(second.alias("a"), third.alias("b")))).alias("l")).select("l.a", "l.b")
    group = connected_components(links)
    of = sides.select("a", "b", "c", name("src", "dst").alias("node")).join(group, "node")
    each = of.groupBy("component").agg(F.countDistinct("a", "b", "c").alias("triangles"))
    nodes = of.select("component", F.explode(F.array("a", "b", "c")).alias("id")).distinct().groupBy("component").agg(F.count(F.lit(1)).alias("nodes"))
    return each.join(nodes, "component").select("component.src", "component.dst", "triangles", "nodes")


def closure_candidates(edges: DataFrame) -> DataFrame:
    """u, w, paths: pairs that share neighbours but no edge, with the number they share."""
    near = both_ways(edges)
    a, b = near.select(F.col("src").alias("v"), F.col("dst").alias("u")), near.select(F.col("src").alias("v"), F.col("dst").alias("w"))
    open_ = a.join(b, "v").where("u < w").groupBy("u", "w").agg(F.count(F.lit(1)).alias("paths"))
    return open_.join(edges.select(F.col("src").alias("u"), F.col("dst").alias("w")), ["u", "w"], "left_anti")


