"""Preferential-attachment networks without communication: every edge slot follows its own chain of copies."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .graph import canonicalize, mix, number

#: Copies that a slot may follow; a chain halves its chance at each step, so none comes near.
STEPS = 64


def pa(spark: SparkSession, n: int, d: int, seed: int = 42) -> DataFrame:
    """Canonical edges of PA(n, d)."""
    if n < 2:
        raise ValueError("n >= 2 and d >= 2 are needed")
    return attached(spark.range(n), d, seed)


def pa_over(keys: DataFrame, d: int, seed: int = 42) -> DataFrame:
    """Canonical edges of a PA network whose nodes are the values of the one column, in their order."""
    name = keys.columns[0]
    return attached(number(keys.where(F.col(name).isNotNull()).distinct(), [name]).select("id"), d, seed)


def attached(nodes: DataFrame, d: int, seed: int = 42) -> DataFrame:
    """Canonical edges of a PA network over nodes with dense ids, d div 2 edges from each.

    Edge j joins slots 2j and 2j+1. An even slot s holds node s div 2k (k = d div 2); an odd slot holds what slot
    mix(s) mod s holds. Loops and repeats go, so there are a little fewer than nd/2 edges.
    """
    k = d // 2
    if k < 1:
        raise ValueError("n >= 2 and d >= 2 are needed")
    step = lambda s: F.when(s % 2 == 1, mix(s, seed) % s).otherwise(s)
    slot = F.aggregate(F.sequence(F.lit(1), F.lit(STEPS)), F.col("odd"), lambda s, _: step(s))
    edges = nodes.select(F.explode(F.sequence(F.col("id") * k, F.col("id") * k + (k - 1))).alias("id"))
    rows = edges.select((F.col("id") * 2).alias("even"), (F.col("id") * 2 + 1).alias("odd")).select("even", slot.alias("slot"))
    node = lambda c: F.expr(f"{c} div {2 * k}")
    checked = rows.where(F.col("slot") % 2 == 0)
    return canonicalize(checked.select(node("even").alias("src"), node("slot").alias("dst")))


def pa_slots_left(spark: SparkSession, n: int, d: int, seed: int = 42) -> int:
    """Slots whose chain is longer than STEPS (expected: none)."""
    k = d // 2
    step = lambda s: F.when(s % 2 == 1, mix(s, seed) % s).otherwise(s)
    slot = F.aggregate(F.sequence(F.lit(1), F.lit(STEPS)), F.col("id") * 2 + 1, lambda s, _: step(s))
    return spark.range(n * k).select(slot.alias("slot")).where("slot % 2 = 1").count()


def complete(spark: SparkSession, n: int) -> DataFrame:
    """All pairs of n nodes, from one sequence per node."""
    return spark.range(n).select(F.col("id").alias("src"), F.explode(F.sequence(F.col("id") + 1, F.lit(n))).alias("dst")).where(f"dst < {n}")
