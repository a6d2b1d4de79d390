"""Counting by tasks: the network on every executor, idle slots pull the next task. Spark's scheduler is the coordinator."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from . import tasks
from .cost import node_cost
from .exchange import common_entries
from .orient import orient

#: Arcs up to which the network is replicated (8 bytes each, and 8 for each node); beyond, the same tasks run over a shuffle.
REPLICATE = 20_000_000
#: Nodes of a task whose lists are looked at together.
NODES = 1024


def replicate(arcs: DataFrame, n: int):
    """The oriented lists as offsets and targets on every executor. Only below the checked bound."""
    rows = arcs.toArrow()
    src, dst = rows.column("src").to_numpy(), rows.column("dst").to_numpy()
    by = np.lexsort((dst, src))
    offsets = np.zeros(n + 1, dtype=np.int64)
    np.cumsum(np.bincount(src, minlength=n), out=offsets[1:])
    return arcs.sparkSession.sparkContext.broadcast((offsets, dst[by]))


def count_range(offsets: np.ndarray, targets: np.ndarray, v: int, t: int) -> int:
    """Triangles of the task of t ids from v: the lists of its nodes against those of their higher neighbours, so many nodes at once."""
    ids = np.arange(len(offsets) - 1)
    total = 0
    for a in range(v, min(v + t, len(ids)), NODES):
        b = min(a + NODES, v + t, len(ids))
        total += common_entries(ids, offsets, targets, offsets[a : b + 1] - offsets[a], targets[offsets[a] : offsets[b]])
    return total


def count(edges: DataFrame, processors: int, cost: str = "degree", granularity: str = "shrinking", queue: int | None = None, mode: str = "auto") -> DataFrame:
    """seq, v, t, triangles of each task. mode: replicate, shuffle, or auto (by the number of arcs)."""
    spark = edges.sparkSession
    arcs = orient(edges)
    table = tasks.table(spark, node_cost(edges, cost), processors, granularity, queue)
    if mode == "auto":
        mode = "replicate" if edges.count() <= REPLICATE else "shuffle"
    if mode == "shuffle":
        return _shuffled(edges, arcs, table)
    n = edges.agg(F.max("dst")).collect()[0][0] or 0
    held = replicate(arcs, int(n) + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        offsets, targets = held.value
        for batch in batches:
            seq, v, t = (batch.column(k).to_pylist() for k in range(3))
            found = [count_range(offsets, targets, a, b) for a, b in zip(v, t, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(seq, pa.int32()), pa.array(v, pa.int64()), pa.array(t, pa.int64()), pa.array(found, pa.int64())], names=["seq", "v", "t", "triangles"])

    # One Spark task for each of ours, in the order in which they are handed out.
    dealt = table.select("seq", "v", "t").repartitionById(max(1, table.count()), "seq")
    return dealt.mapInArrow(run, "seq int, v long, t long, triangles long")


def _shuffled(edges: DataFrame, arcs: DataFrame, table: DataFrame) -> DataFrame:
    """The same tasks without replication: counts are summed by node first, then by the task whose range holds the node."""
    from .exact import list_counts

    each = list_counts(edges).withColumnRenamed("id", "v")
    spans = table.select("seq", F.col("v").alias("low"), (F.col("v") + F.col("t") - 1).alias("high"))  # a few rows for each worker
    found = each.join(F.broadcast(spans), F.col("v").between(F.col("low"), F.col("high"))).groupBy("seq").agg(F.sum("n").alias("n"))
    return table.select("seq", "v", "t").join(found, "seq", "left").select("seq", "v", "t", F.coalesce("n", F.lit(0).cast("long")).alias("triangles"))


def work(edges: DataFrame, table: DataFrame, kind: str = "owner") -> list[int]:
    """What each task really takes: the work of the arcs that leave its ids."""
    cost = node_cost(edges, kind).select("id", "f")
    spans = table.select("seq", "v", (F.col("v") + F.col("t") - 1).alias("last"))
    rows = cost.join(F.broadcast(spans), F.col("id").between(F.col("v"), F.col("last"))).groupBy("seq").agg(F.sum("f").alias("w"))
    return [int(r.w or 0) for r in table.select("seq").join(rows, "seq", "left").orderBy("seq").collect()]


def replay(edges: DataFrame, processors: int, cost: str = "degree", granularity: str = "shrinking", queue: int | None = None) -> DataFrame:
    """worker, tasks, busy, idle on a clock that runs by the work of the tasks."""
    table = tasks.table(edges.sparkSession, node_cost(edges, cost), processors, granularity, queue)
    w = work(edges, table)
    first = table.where("phase = 'initial'").count()
    log, idle = tasks.replay(w, processors - 1, first)
    end = max((x[3] for x in log), default=0)
    rows = [(k, sum(x[1] == k for x in log), end - idle[k], idle[k]) for k in range(processors - 1)]
    return edges.sparkSession.createDataFrame(rows, "worker int, tasks int, busy long, idle long")


def sweep(edges: DataFrame, processors: list[int], costs: tuple[str, ...] = ("unit", "degree"), granularities: tuple[str, ...] = ("static", "shrinking")) -> DataFrame:
    """cost, granularity, processors, tasks, makespan, idle, speedup of the replayed method, for every combination.

    idle is summed over the workers; speedup is the whole work over the makespan. One pass over the network for each
    cost: what reaches the driver are sums over at most ``tasks.UNITS`` units.
    """
    arcs = cut(orient(edges))
    done = tasks.collected(node_cost(edges, "owner", arcs=arcs))
    rows = []
    for cost in costs:
        c = tasks.collected(node_cost(edges, cost, arcs=arcs))
        for p in processors:
            for kind in granularities:
                planned = tasks.plan(c, p, kind)
                log, idle = tasks.replay([done.size(a, b) for _, a, b in planned], p - 1, sum(x[0] == "initial" for x in planned))
                end = max((x[3] for x in log), default=0)
                rows.append((cost, kind, p, len(planned), end, sum(idle), round(done.upto[-1] / end, 4) if end else 0.0))
    return edges.sparkSession.createDataFrame(rows, "cost string, granularity string, processors int, tasks int, makespan long, idle long, speedup double")
