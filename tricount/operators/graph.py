"""Canonical edges and dense labels."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import cut, remove, stored
from . import packed

#: Consecutive ids that prefix sums take together.
CHUNK = 1 << 16
#: Nodes, and bytes of their keys, up to which a value for each node is held by every task, so that edges needn't move to get it.
HELD, HELD_BYTES = 1 << 22, 1 << 26
#: Edges that are looked up together.
TOGETHER = 1 << 20


def canonicalize(edges: DataFrame) -> DataFrame:
    """Distinct undirected edges with src < dst; loops, reversed pairs, repeats and nulls go."""
    pairs = edges.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
    return pairs.distinct()


def both_ways(edges: DataFrame) -> DataFrame:
    """Each edge in both directions, from one scan."""
    ends = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return edges.select(F.explode(ends).alias("e")).select("e.src", "e.dst")


def endpoints(edges: DataFrame, name: str = "id") -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias(name)).distinct()


def number(keys: DataFrame, order: list[str], into: str = "id") -> DataFrame:
    """``keys`` (rows distinct in ``order``) with dense numbers from 0 in that order.

    Rows are range-partitioned by sampled bounds, which keeps partitions even whatever the keys, and written once; ranks inside a
    partition are shifted by the sizes of the partitions before. Only the table of these sizes is ordered as a whole.
    """
    n = max(1, int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = cut(keys.repartitionByRange(n, *order).withColumn("_chunk", F.spark_partition_id()))
    before = Window.orderBy("_chunk").rowsBetween(Window.unboundedPreceding, -1)
    starts = dealt.groupBy("_chunk").agg(F.count(F.lit(1)).alias("_n")).select("_chunk", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    rank = F.row_number().over(Window.partitionBy("_chunk").orderBy(*order)) - 1
    return dealt.withColumn("_rank", rank).join(F.broadcast(starts), "_chunk").withColumn(into, (F.col("_start") + F.col("_rank")).cast("long")).drop("_chunk", "_rank", "_start")


def held(nodes: DataFrame, key: str, order: str | None = None) -> pa.Table | None:
    """``nodes`` (a row for each) in the order of a column, ``key`` unless told otherwise, if they are few enough to be held by every task; else None."""
    n, size = nodes.agg(F.count(F.lit(1)), F.sum(F.octet_length(F.col(key).cast("string")))).collect()[0]
    return nodes.toArrow().sort_by(order or key).combine_chunks() if n <= HELD and (size or 0) <= HELD_BYTES else None


def together(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about TOGETHER."""
    kept: list[pa.RecordBatch] = []
    for batch in batches:
        kept.append(batch)
        if sum(b.num_rows for b in kept) >= TOGETHER:
            yield from pa.Table.from_batches(kept).combine_chunks().to_batches()
            kept = []
    if kept:
        yield from pa.Table.from_batches(kept).combine_chunks().to_batches()


def _named(edges: DataFrame, keys: pa.Array) -> DataFrame:
    """Edges with the places of their keys in ``keys``, which every task holds: no edge moves."""
    sent = edges.sparkSession.sparkContext.broadcast(keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in together(batches):
            a, b = (pc.index_in(batch.column(k), value_set=sent.value.cast(batch.column(k).type)).cast(pa.int64()).to_numpy(zero_copy_only=False) for k in range(2))
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b), pa.int64()), pa.array(np.maximum(a, b), pa.int64())], names=["src", "dst"])

    return edges.select("src", "dst").mapInArrow(run, "src long, dst long")


def relabel(edges: DataFrame, how: str = "natural", seed: int = 42) -> DataFrame:
    """Canonical edges over dense ids, stored; how: natural (by key), hashed (by a hash of the key) or degree (by degree, then key).

    Up to HELD nodes every task holds their keys in the order of ids; beyond, edges are joined with them. Edges that are packed stay so:
    their ids are in the order of their keys.
    """
    dense = packed.of(edges)
    if dense is None:
        edges, path = stored(edges)
    elif how == "natural":
        return packed.view(packed.Packed(dense.rows, dense.n))
    keys = endpoints(edges, "key") if dense is None else packed.keys(dense)
    if how == "natural":
        named = number(keys, ["key"])
    elif how == "hashed":
        named = number(keys.withColumn("h", mix(F.xxhash64("key").bitwiseAND(F.lit((1 << 31) - 1)), seed)), ["h", "key"]).drop("h")
    elif how == "degree":
        named = number(both_ways(edges).groupBy(F.col("src").alias("key")).agg(F.count(F.lit(1)).alias("n")) if dense is None else packed.degrees(dense).toDF("key", "n"), ["n", "key"]).drop("n")
    else:
        raise ValueError(f"no such labelling: {how}")
    if dense is not None:
        return packed.relabelled(dense, named.toArrow().sort_by("key").column("id").to_numpy())
    few = held(named, "key", "id")
    if few is not None:
        out = cut(_named(edges, few.column("key").combine_chunks()))
    else:
        named = cut(named)
        a, b = named.select(F.col("key").alias("src"), F.col("id").alias("_a")), named.select(F.col("key").alias("dst"), F.col("id").alias("_b"))
        half, between = stored(edges.join(a, "src").select("dst", "_a"))  # the shuffle of one end goes before that of the other comes
        remove(edges.sparkSession, [path])
        path = between
        out = cut(half.join(b, "dst").select(F.least("_a", "_b").alias("src"), F.greatest("_a", "_b").alias("dst")))
    remove(out.sparkSession, [path])
    return out


# The constants of the integer mixer that generators and samplers share with their SQL.
SPREAD, TURN = 2654435761, 73244475


def mix(x: Column, seed: int = 42) -> Column:
    """32 well-mixed bits of a number below 2^31, in 63-bit integer arithmetic."""
    low = F.lit((1 << 32) - 1)
    x = (x * F.lit(SPREAD) + F.lit(seed)).bitwiseAND(low)
    for _ in range(2):
        x = (x.bitwiseXOR(F.shiftright(x, 16)) * F.lit(TURN)).bitwiseAND(low)
    return x.bitwiseXOR(F.shiftright(x, 16))


def mixed(x: np.ndarray, seed: int = 42) -> np.ndarray:
    """The same of an array."""
    low = np.uint64((1 << 32) - 1)
    x = (x.astype(np.uint64) * np.uint64(SPREAD) + np.uint64(seed)) & low
    for _ in range(2):
        x = ((x ^ (x >> np.uint64(16))) * np.uint64(TURN)) & low
    return (x ^ (x >> np.uint64(16))).astype(np.int64)


def mix_sql(x: str, seed: int = 42) -> str:
    """The same in SQL for DuckDB."""
    x = f"(({x} * {SPREAD} + {seed}) & 4294967295)"
    for _ in range(2):
        x = f"((xor({x}, {x} >> 16) * {TURN}) & 4294967295)"
    return f"xor({x}, {x} >> 16)"
