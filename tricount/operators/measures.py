"""Space, traffic, load, idle time, scaling and intermediate rows of the methods."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut as stored
from . import overlap
from .blocks import assign, prefix
from .cost import arc_costs, node_cost
from .exchange import Owned, build, sizes
from .graph import both_ways
from .mapreduce import triple_copies
from .orient import degrees, node_table, orient

#: Bytes of a node or a list entry in the model of memory.
BYTES = 8


def summary(edges: DataFrame) -> DataFrame:
    """n, m, average degree 2m/n, median, 99th percentile and largest degree."""
    d = degrees(edges)
    return d.agg(F.count(F.lit(1)).alias("n"), F.expr("cast(sum(deg) div 2 as bigint)").alias("m"), F.round(F.sum("deg") / F.count(F.lit(1)), 4).alias("avg_deg"), F.round(F.percentile("deg", 0.5), 4).alias("p50"), F.round(F.percentile("deg", 0.99), 4).alias("p99"), F.max("deg").alias("max_deg"))


def degree_histogram(edges: DataFrame) -> DataFrame:
    return degrees(edges).groupBy("deg").agg(F.count(F.lit(1)).alias("nodes"))


def space(blocks: DataFrame) -> DataFrame:
    """part, v_count, e_count, bytes for a table of block sizes."""
    return blocks.select("part", "v_count", "e_count", ((F.col("v_count") + F.col("e_count")) * BYTES).alias("bytes"))


def space_ratio(edges: DataFrame, parts: int, own: str = "surrogate", other: str = "owner") -> DataFrame:
    """Largest block of the non-overlapping method and of the overlapping one, each under its own cuts, in bytes, and their ratio."""
    mine = space(sizes(build(edges, parts, own))).agg(F.max("bytes").alias("nonoverlap"))
    theirs = space(overlap.sizes(overlap.build(build(edges, parts, other)))).agg(F.max("bytes").alias("overlapping"))
    return mine.join(F.broadcast(theirs)).withColumn("ratio", F.round(F.col("overlapping") / F.col("nonoverlap"), 4))


def load(edges: DataFrame, parts: int, cut: str, at: str = "surrogate") -> DataFrame:
    """part, work: intersections by the block that runs them (surrogate: owner of the higher end; owner: of the lower)."""
    owner = assign(node_cost(edges, cut), parts).select("id", "part")
    end = "dst" if at == "surrogate" else "src"
    done = arc_costs(edges).groupBy(F.col(end).alias("id")).agg(F.sum("work").alias("work"))
    return owner.join(done, "id", "left").groupBy("part").agg(F.coalesce(F.sum("work"), F.lit(0)).cast("long").alias("work"))


def imbalance(loads: DataFrame, parts: int) -> DataFrame:
    """Largest load over the mean (parts x max / total) and the speedup that the largest load allows (total / max)."""
    return loads.agg(F.max("work").alias("most"), F.sum("work").alias("total")).select("most", "total", F.round(F.col("most") * parts / F.col("total"), 4).alias("imbalance"), F.round(F.col("total") / F.col("most"), 4).alias("speedup"))


def modelled_speedup(edges: DataFrame, parts: list[int], cuts: tuple[str, ...] = ("unit", "degree", "owner", "surrogate")) -> DataFrame:
    """cut, parts, speedup for each cost function and number of blocks."""
    out = None
    for cut in cuts:
        for p in parts:
            row = imbalance(load(edges, p, cut), p).select(F.lit(cut).alias("cut"), F.lit(p).alias("parts"), "imbalance", "speedup")
            out = row if out is None else out.unionByName(row)
    return out


def redundancy(owned: Owned) -> DataFrame:
    """Replies of the direct scheme, messages of the surrogate scheme, and their ratio."""
    cross = owned.arcs.where("pv <> pu")
    return cross.agg(F.count(F.lit(1)).alias("direct"), F.countDistinct("v", "pu").alias("surrogate")).withColumn("ratio", F.round(F.col("direct") / F.col("surrogate"), 4))


def intermediate_rows(edges: DataFrame, rho: int = 4) -> DataFrame:
    """method, rows that the baselines put between their stages. Two-paths are counted from degrees, not formed."""
    near = both_ways(edges).groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    high = orient(edges).groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    pairs = lambda t, name: t.agg(F.lit(name).alias("method"), F.coalesce(F.sum(F.expr("d * (d - 1) div 2")), F.lit(0)).cast("long").alias("rows"))
    copies = triple_copies(edges, rho).agg(F.lit("bucket_triples").alias("method"), F.count(F.lit(1)).alias("rows"))
    return pairs(near, "two_paths").unionByName(pairs(high, "two_paths_oriented")).unionByName(copies)


def complexity_terms(owned: Owned) -> DataFrame:
    """Largest block (nodes and arcs), largest degree and list, and the largest work of a block: what its intersections and its messages take."""
    eff = owned.nodes.select("id", "eff")
    arcs = owned.arcs.join(eff.withColumnRenamed("id", "v").withColumnRenamed("eff", "ev"), "v").join(eff.withColumnRenamed("id", "u").withColumnRenamed("eff", "eu"), "u")
    done = arcs.groupBy(F.col("pu").alias("part")).agg(F.sum(F.col("ev") + F.col("eu")).alias("w"))
    sent = arcs.where("pv <> pu").select("v", "pv", "pu", "ev").distinct().groupBy(F.col("pv").alias("part")).agg(F.sum("ev").alias("w"))
    work = done.unionByName(sent).groupBy("part").agg(F.sum("w").alias("w")).agg(F.max("w").alias("work"))
    top = sizes(owned).agg(F.max(F.col("v_count") + F.col("e_count")).alias("block"))
    return top.join(F.broadcast(owned.nodes.agg(F.max("deg").alias("d_max"), F.max("eff").alias("eff_max")))).join(F.broadcast(work))


# Sweeps over the number of blocks: one pass over the arcs for all numbers ----------------------------------------------


def _owners(cost: DataFrame, parts: list[int]) -> DataFrame:
    """parts, id, part: the block of each id for each number of blocks, by the rule of ``blocks.assign``."""
    run = prefix(cost)
    n = run.agg(F.count(F.lit(1)).alias("_n"))
    middle = F.expr("cast(((before + upto) * parts) div (2 * total) as int)")
    plain = F.expr("cast((id * parts) div _n as int)")
    spread = run.join(F.broadcast(n)).select("id", "before", "upto", "total", "_n", F.explode(F.array(*map(F.lit, parts))).alias("parts"))
    return spread.select("parts", "id", F.least(F.col("parts") - 1, F.when(F.col("total") > 0, middle).otherwise(plain)).alias("part"))


def _starts(cost: DataFrame, parts: list[int]) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """For each number of blocks, the first ids of the blocks that have nodes, and which blocks these are. At most the sum of ``parts`` rows reach the driver."""
    rows = _owners(cost, parts).groupBy("parts", "part").agg(F.min("id").alias("low")).collect()
    return {p: tuple(np.array(x, dtype=np.int64) for x in zip(*sorted((r.low, r.part) for r in rows if r.parts == p), strict=True)) for p in parts} if rows else {}


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, ...]]:
    """The columns of rows in order, such that all rows of one first column come together."""
    kept: list[list[np.ndarray]] = []
    for batch in batches:
        columns = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
        if not len(columns[0]):
            continue
        last = int(np.argmax(columns[0] == columns[0][-1]))  # its rows may go on in the next batch
        if kept and (last or kept[-1][0][-1] != columns[0][0]):
            whole = [[c[:last] for c in columns]] if last else []
            yield tuple(np.concatenate(x) for x in zip(*kept, *whole, strict=True))
            kept = []
        elif last:
            yield tuple(c[:last] for c in columns)
        kept.append([c[last:] for c in columns])
    if kept:
        yield tuple(np.concatenate(x) for x in zip(*kept, strict=True))


def scheme_speedup(edges: DataFrame, parts: list[int]) -> DataFrame:
    """scheme, parts, most, speedup of the direct, surrogate and overlapping methods, modelled.

    A block's time is the work of its intersections and, for each message that it sends or gets, one and the entries
    carried. direct asks and is answered once per crossing edge; surrogate ships a list once per block; overlapping
    sends nothing and is cut by its own cost. Speedup is the whole work over the largest time.

    Blocks are consecutive ids, so their first ids tell where an arc's ends are: one pass over the arcs, grouped by their
    lower end, adds up all times for all numbers of blocks, and no row is made for an arc and a number of blocks.
    """
    arcs = stored(orient(edges))
    mine, theirs = (_starts(node_cost(edges, k, arcs=arcs), parts) for k in ("surrogate", "owner"))
    eff = arcs.groupBy(F.col("src").alias("dst")).agg(F.count(F.lit(1)).alias("eu"))
    rows = arcs.join(eff, "dst", "left").select("src", "dst", F.coalesce("eu", F.lit(0).cast("long")).alias("eu"))

    def times(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = {(s, p): np.zeros(p, dtype=np.int64) for s in ("direct", "surrogate", "overlapping") for p in parts}
        for v, u, eu in _runs(batches):
            first = np.concatenate([[True], v[1:] != v[:-1]])
            ev = np.diff(np.append(np.flatnonzero(first), len(v)))[np.cumsum(first) - 1]
            for p in parts:
                (low, named), (other, others) = mine[p], theirs[p]
                pv, pu = (named[np.searchsorted(low, x, "right") - 1] for x in (v, u))
                np.add.at(sums["overlapping", p], others[np.searchsorted(other, v, "right") - 1], ev + eu)
                np.add.at(sums["direct", p], pv, ev + eu)
                np.add.at(sums["surrogate", p], pu, ev + eu)
                cross = pv != pu
                once = cross & (first | np.concatenate([[True], pu[1:] != pu[:-1]]))  # entries are in order, so those of a block come together
                for at in (pv, pu):
                    np.add.at(sums["direct", p], at[cross], 2 + eu[cross])
                    np.add.at(sums["surrogate", p], at[once], 1 + ev[once])
        for (s, p), t in sums.items():
            some = np.flatnonzero(t)
            yield pa.RecordBatch.from_arrays([pa.array([s] * len(some), pa.string()), pa.array([p] * len(some), pa.int32()), pa.array(some, pa.int32()), pa.array(t[some], pa.int64())], names=["scheme", "parts", "part", "t"])

    each = rows.repartition("src").sortWithinPartitions("src", "dst").mapInArrow(times, "scheme string, parts int, part int, t long")
    found = stored(each.groupBy("scheme", "parts", "part").agg(F.sum("t").alias("t")))
    total = found.where((F.col("scheme") == "overlapping") & (F.col("parts") == parts[0])).agg(F.sum("t").alias("total"))  # it sends nothing: the whole work
    most = found.groupBy("scheme", "parts").agg(F.max("t").alias("most"))
    return most.join(F.broadcast(total)).select("scheme", "parts", "most", F.round(F.col("total") / F.col("most"), 4).alias("speedup"))


def memory(edges: DataFrame, parts: list[int]) -> DataFrame:
    """parts, nonoverlap, overlapping, ratio: bytes of the largest block of both methods, each under its own cuts."""
    arcs = stored(orient(edges))
    eff = node_table(edges, arcs=arcs).select("id", "eff")

    def blocks(cut: str) -> tuple[DataFrame, DataFrame]:
        """(parts, part, id) known to each block, and the same of the arcs that leave its own nodes."""
        owner = stored(_owners(node_cost(edges, cut, arcs=arcs), parts))
        leaving = owner.join(arcs.withColumnRenamed("src", "id"), "id")
        return owner.unionByName(leaving.select("parts", F.col("dst").alias("id"), "part")).distinct(), leaving

    known, leaving = blocks("surrogate")
    count = lambda df, name: df.groupBy("parts", "part").agg(F.count(F.lit(1)).alias(name))
    mine = count(known, "v").join(count(leaving, "e"), ["parts", "part"], "left").groupBy("parts").agg(F.max((F.col("v") + F.coalesce("e", F.lit(0))) * BYTES).alias("nonoverlap"))
    held, _ = blocks("owner")
    theirs = held.join(eff, "id").groupBy("parts", "part").agg(((F.count(F.lit(1)) + F.sum("eff")) * BYTES).alias("b")).groupBy("parts").agg(F.max("b").alias("overlapping"))
    return mine.join(theirs, "parts").select("parts", "nonoverlap", "overlapping", F.round(F.col("overlapping") / F.col("nonoverlap"), 4).alias("ratio"))
