"""Choice of method before a plan is built, from cheap statistics of the network."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import exact
from ..operators.dynamic import REPLICATE
from ..operators.graph import both_ways
from ..operators.orient import node_table


@dataclass(frozen=True)
class Statistics:
    """Nodes, edges, two-paths under the degree order, work of the intersections, and the longest list."""

    n: int
    m: int
    paths: int
    work: int
    longest: int


def statistics(edges: DataFrame) -> Statistics:
    """One pass over the node table: sums only."""
    t = node_table(edges).agg(F.count(F.lit(1)), F.sum("eff"), F.sum(F.expr("cast(eff as decimal(38,0)) * (eff - 1) / 2")), F.sum(F.expr("cast(eff as decimal(38,0)) * deg")), F.max("eff")).collect()[0]
    return Statistics(*(int(x or 0) for x in t))


@dataclass(frozen=True)
class Choice:
    kernel: str
    order: str
    method: str
    why: str

    def count(self, edges: DataFrame) -> DataFrame:
        return exact.count_closure(edges, self.order) if self.kernel == "closure" else exact.count_intersect(edges, self.order)


def choose(edges: DataFrame) -> Choice:
    """closure shuffles a row per oriented two-path, intersect a list per arc: take what moves less; replicate small networks."""
    s = statistics(edges)
    kernel = "closure" if 2 * s.paths < s.work else "intersect"
    method = "replicated tasks" if s.m <= REPLICATE else "non-overlapping blocks, surrogate exchange"
    return Choice(kernel, "degree", method, f"{s.paths} oriented two-paths against {s.work} list entries; {s.m} arcs; longest list {s.longest}")


def explain(edges: DataFrame) -> str:
    c = choose(edges)
    return f"{c.method}; kernel {c.kernel} in {c.order} order: {c.why}"


def unordered_rows(edges: DataFrame) -> int:
    """Rows that node-centred counting would make: what the order saves."""
    d = both_ways(edges).groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    return int(d.agg(F.sum(F.expr("cast(d as decimal(38,0)) * (d - 1)"))).collect()[0][0] or 0)
