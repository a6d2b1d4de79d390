"""Estimated cost of each node, the functions by which ids are cut into blocks and tasks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .orient import node_table, orient

COSTS = ("unit", "degree", "owner", "surrogate", "effective")


def arc_costs(edges: DataFrame, order: str = "degree", arcs: DataFrame | None = None) -> DataFrame:
    """src, dst, work: the sum of the effective degrees of both ends, what one intersection takes."""
    arcs = orient(edges, order) if arcs is None else arcs
    eff = arcs.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("eff"))
    eff = arcs.select(F.explode(F.array("src", "dst")).alias("id")).distinct().join(eff, "id", "left").select("id", F.coalesce("eff", F.lit(0).cast("long")).alias("eff"))
    a = eff.select(F.col("id").alias("src"), F.col("eff").alias("_a"))
    b = eff.select(F.col("id").alias("dst"), F.col("eff").alias("_b"))
    return arcs.join(a, "src").join(b, "dst").select("src", "dst", (F.col("_a") + F.col("_b")).alias("work"))


def node_cost(edges: DataFrame, kind: str, order: str = "degree", expr: str | None = None, arcs: DataFrame | None = None) -> DataFrame:
    """id, f for every node.

    unit: 1; degree: the degree; effective: the length of the oriented list; owner: the work of the arcs that leave
    the node; surrogate: the work of the arcs that enter it, as their intersections run where the higher end is;
    custom: a SQL expression over id, deg and eff. ``arcs``: those of ``orient``, if they are at hand.
    """
    nodes = node_table(edges, order, arcs)
    if kind in ("owner", "surrogate"):
        end = "src" if kind == "owner" else "dst"
        work = arc_costs(edges, order, arcs).groupBy(F.col(end).alias("id")).agg(F.sum("work").alias("f"))
        return nodes.select("id").join(work, "id", "left").select("id", F.coalesce("f", F.lit(0).cast("long")).alias("f"))
    f = {"unit": F.lit(1), "degree": F.col("deg"), "effective": F.col("eff"), "custom": F.expr(expr) if expr else None}.get(kind)
    if f is None:
        raise ValueError(f"no such cost: {kind}")
    return nodes.select("id", f.cast("long").alias("f"))
