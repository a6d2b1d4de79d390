"""Connected components of a table of links, by alternating large-star and small-star rounds.

Each round keeps the components, moves every node's links to the smallest node it has seen and is one or two
shuffles over the links that remain; the number of rounds grows with the logarithm of the longest path. Links are
written to the shared folder between rounds and never reach the driver. As soon as they are few enough for one task,
one task finishes them: rounds of small jobs cost the driver more than they do.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import remove
from .common import stored


def _hub(links: DataFrame, large: bool) -> DataFrame:
    """One star round. large: a node links its larger neighbours to its least one; small: its smaller ones and itself."""
    if large:
        near = links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    else:
        near = links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = near.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    met = near.join(least, "a")
    moved = met.where(F.col("b") > F.col("a") if large else F.col("b") != F.col("m")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    if not large:
        moved = moved.unionByName(least.select("a", F.col("m").alias("b")))
    return moved.where("a != b").distinct()


#: Links that one task may hold; a table of no more links is finished by one task.
PER_TASK = 1 << 20


def _dealt(links: DataFrame, n: int) -> DataFrame:
    """``links`` in as many partitions as their number asks for."""
    return links.coalesce(max(1, -(-n // PER_TASK)))


def labels(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of the links a, b and the smallest node that each reaches."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        # Heads of linked nodes take the lesser label, then every node goes on to its head.
        p, q = label[x], label[y]
        apart = p != q
        if not apart.any():
            return nodes, nodes[label]
        np.minimum.at(label, np.maximum(p, q)[apart], np.minimum(p, q)[apart])
        while (label != label[label]).any():
            label = label[label]


def _finished(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held = [[c.to_numpy() for c in batch.columns] for batch in batches if batch.num_rows]
    if held:
        found = labels(*(np.concatenate(x) for x in zip(*held, strict=True)))
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in found], names=["node", "component"])


def components(links: DataFrame, rounds: int = 50) -> DataFrame:
    """(node, component) for every node of ``links`` (a, b); component is the smallest node reachable.

    Loops and repeated links are ignored; an empty table gives an empty table.
    """
    spark = links.sparkSession
    old: list[str] = []
    now = stored(links.where("a != b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")), old)
    mark = (now.count(),)
    for _ in range(rounds):
        if mark[0] <= PER_TASK:
            break
        new: list[str] = []
        now = stored(_hub(_hub(_dealt(now, mark[0]), large=True), large=False), new)
        # A forest of stars that both rounds leave alone is the end; sums of hashes tell whether anything moved.
        seen = tuple(_dealt(now, mark[0]).agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.sum(F.xxhash64("b", "a").cast("decimal(38,0)"))).collect()[0])
        remove(spark, old)
        old = new
        if seen == mark:
            break
        mark = seen
    else:
        if mark[0] > PER_TASK:
            raise RuntimeError(f"components did not settle in {rounds} rounds")
    if mark[0] <= PER_TASK:
        done = stored(now.coalesce(1).mapInArrow(_finished, "node long, component long"))
        remove(spark, old)
        return done
    stars = _dealt(now, mark[0])
    return stars.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(stars.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
