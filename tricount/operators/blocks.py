"""Consecutive blocks of ids with nearly equal cost."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .graph import CHUNK

BIG = "decimal(38,0)"


def prefix(cost: DataFrame) -> DataFrame:
    """id, f, before (sum over smaller ids), upto (with its own) and total.

    Sums run inside chunks of ids and are shifted by the chunks before; only the table of chunk sums is ordered as a
    whole. Sums are decimals: at 10^12 arcs they can pass 2^63.
    """
    chunked = cost.select("id", "f", F.expr(f"id div {CHUNK}").alias("_chunk"))
    sums = chunked.groupBy("_chunk").agg(F.sum(F.col("f").cast(BIG)).cast(BIG).alias("_sum"))
    whole = Window.orderBy("_chunk")
    starts = sums.select("_chunk", (F.sum("_sum").over(whole.rowsBetween(Window.unboundedPreceding, 0)) - F.col("_sum")).cast(BIG).alias("_start"), F.sum("_sum").over(whole.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).cast(BIG).alias("total"))
    inside = Window.partitionBy("_chunk").orderBy("id").rowsBetween(Window.unboundedPreceding, 0)
    run = chunked.withColumn("_run", F.sum(F.col("f").cast(BIG)).over(inside)).join(starts, "_chunk")
    return run.select("id", "f", (F.col("_start") + F.col("_run") - F.col("f")).cast(BIG).alias("before"), (F.col("_start") + F.col("_run")).cast(BIG).alias("upto"), "total")


def assign(cost: DataFrame, parts: int) -> DataFrame:
    """id, f, part: the block of each id. A node goes where the middle of its cost falls; blocks may be empty."""
    if parts < 1:
        raise ValueError("at least one block is needed")
    run = prefix(cost)
    n = run.agg(F.count(F.lit(1)).alias("_n"))
    middle = F.expr(f"cast(((before + upto) * {parts}) div (2 * total) as int)")
    return run.join(F.broadcast(n)).select("id", "f", F.least(F.lit(parts - 1), F.when(F.col("total") > 0, middle).otherwise(F.expr(f"cast((id * {parts}) div _n as int)"))).alias("part"))


def balanced_blocks(cost: DataFrame, parts: int) -> DataFrame:
    """part, lo, hi, nodes, cost of every block that has nodes: at most ``parts`` rows."""
    return assign(cost, parts).groupBy("part").agg(F.min("id").alias("lo"), F.max("id").alias("hi"), F.count(F.lit(1)).alias("nodes"), F.sum(F.col("f").cast(BIG)).cast(BIG).alias("cost"))


def half_point(cost: DataFrame) -> DataFrame:
    """The smallest t with at least half of the cost on ids below t."""
    return prefix(cost).where("2 * upto >= total").agg((F.min("id") + 1).alias("half"))
