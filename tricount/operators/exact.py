"""Exact triangle counts: the kernel on sorted oriented lists, its relational form, and the plain ways it improves on."""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from . import packed, tasks
from .exchange import CHUNK, looked_up
from .graph import both_ways, endpoints
from .orient import lists, orient, ranks

#: Entries of the lists of a block, about: what a task holds while lists that are sent to it stream past.
ENTRIES = 1 << 20
#: Units of ids by which blocks are cut.
UNITS = 4096


def _one(rows: DataFrame, value) -> DataFrame:
    return rows.agg(F.coalesce(F.sum(value), F.lit(0)).cast("long").alias("triangles"))


def _sent(arcs: DataFrame, held: DataFrame | None = None) -> DataFrame:
    """dest, kind, src, nbrs: each node's list at its own block (kind 0) and once at each block that has some of its entries (1).

    Blocks are consecutive ids with about ENTRIES entries. A list crosses once for each block, not once for each arc.
    held: the arcs whose lists the blocks hold, if those are not ``arcs`` themselves.
    """
    own = cut(lists(arcs if held is None else held))
    c = tasks.collected(own.select("id", F.size("nbrs").alias("f")), UNITS)
    parts = max(1, -(-c.upto[-1] // ENTRIES))
    share = [x * parts // max(1, c.upto[-1]) for x in c.upto[:-1]]
    firsts = np.array([u * c.step for u in range(1, len(share)) if share[u] != share[u - 1]], dtype=np.int64)
    parts = len(firsts) + 1

    def run(batches: Iterator[pa.RecordBatch], own: bool = True, to_others: bool = True) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                batch = whole.slice(at, 1024)
                ids, held = batch.column(0).to_numpy(), batch.column(1)
                size = np.diff(held.offsets.to_numpy())
                named = np.searchsorted(firsts, held.flatten().to_numpy(zero_copy_only=False), "right")
                rows, to = np.divmod(np.unique(np.repeat(np.arange(len(ids)), size) * parts + named), parts)
                rows, to = rows[(size[rows] > 1) & to_others], to[(size[rows] > 1) & to_others]
                home = np.arange(len(ids) if own else 0)
                index = np.concatenate([home, rows])
                dest = np.concatenate([np.searchsorted(firsts, ids[home], "right"), to])
                kind = np.repeat([0, 1], [len(home), len(rows)])
                full = np.cumsum(size[index]) // ENTRIES  # lists of many entries leave a few at a time
                for k in np.split(np.arange(len(index)), np.flatnonzero(np.diff(full)) + 1):
                    columns = [pa.array(dest[k], pa.int32()), pa.array(kind[k], pa.int32()), pa.array(ids[index[k]], pa.int64()), held.take(pa.array(index[k]))]
                    yield pa.RecordBatch.from_arrays(columns, names=["dest", "kind", "src", "nbrs"])

    ddl = "dest int, kind int, src long, nbrs array<bigint>"
    if held is None:
        sent = own.select("id", "nbrs").mapInArrow(run, ddl)
    else:
        sent = own.select("id", "nbrs").mapInArrow(partial(run, to_others=False), ddl).unionByName(lists(arcs).mapInArrow(partial(run, own=False), ddl))
    return sent.repartitionById(parts, "dest").sortWithinPartitions("dest", "kind", "src")


def _opened(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    """A block, its own lists (ids, offsets, entries), and lists that were sent to it: their src, offsets and entries."""
    held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    now, block = None, None
    for batch in batches:
        dest, kind, src = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(3))
        offsets, flat = batch.column(3).offsets.to_numpy().astype(np.int64), batch.column(3).values.to_numpy(zero_copy_only=False)
        edge = np.flatnonzero((dest[1:] != dest[:-1]) | (kind[1:] != kind[:-1])) + 1
        for a, b in zip([0, *edge.tolist()], [*edge.tolist(), len(dest)], strict=True):
            if a == b:
                continue
            if dest[a] != now:
                now, held, block = dest[a], [], None
            part = flat[offsets[a] : offsets[b]]
            if kind[a] == 0:
                held.append((src[a:b].copy(), np.diff(offsets[a : b + 1]), part.copy()))
                continue
            if block is None:
                ids, sizes, entries = (np.concatenate([h[k] for h in held]) if held else np.empty(0, dtype=np.int64) for k in range(3))
                block = ids, np.concatenate([[0], np.cumsum(sizes)]), entries
            yield now, block, src[a:b], offsets[a : b + 1] - offsets[a], part


def _arrived(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    """A block, src of lists that were sent to it, ids of the block's own lists, and what ``looked_up`` gives of them."""
    for now, block, src, sent, flat in _opened(batches):
        for found in looked_up(*block, sent, flat):
            yield now, src, block[0], *found


def _paired(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """v, u, nv, nu where the list of v meets that of u; rows of about ENTRIES entries at once."""
    for _, (ids, offsets, entries), src, sent, flat in _opened(batches):
        if not len(ids) or not len(flat):
            continue
        number = np.repeat(np.arange(len(src)), np.diff(sent))
        place = np.minimum(np.searchsorted(ids, flat), len(ids) - 1)
        own = ids[place] == flat
        number, place = number[own], place[own]
        mine = pa.ListArray.from_arrays(pa.array(sent, pa.int32()), pa.array(flat, pa.int64()))
        theirs = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(entries, pa.int64()))
        full = np.cumsum(np.diff(sent)[number] + np.diff(offsets)[place]) // ENTRIES
        for k in np.split(np.arange(len(number)), np.flatnonzero(np.diff(full)) + 1):
            columns = [pa.array(src[number[k]], pa.int64()), pa.array(ids[place[k]], pa.int64()), mine.take(pa.array(number[k])), theirs.take(pa.array(place[k]))]
            yield pa.RecordBatch.from_arrays(columns, names=["v", "u", "nv", "nu"])


def paired_lists(edges: DataFrame, order: str = "degree") -> DataFrame:
    """v, u, nv, nu for each oriented edge whose ends both have lists, the former of two entries or more. Pairs are formed where blocks of lists meet; none is moved."""
    return _sent(orient(edges, order)).mapInArrow(_paired, "v long, u long, nv array<bigint>, nu array<bigint>")


def _corners(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    for _, src, ids, number, place, n, entries, hit in _arrived(batches):
        pair = np.repeat(np.arange(len(n)), n)[hit]
        if len(pair):
            yield src[number[pair]], ids[place[pair]], entries[hit]


def _totals(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = sum(int(np.count_nonzero(found[-1])) for found in _arrived(batches))
    yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], names=["n"])


def by_block(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """part, n: what is found in each block of rows dest, kind, src, nbrs in order."""
    for now, *_, hit in _arrived(batches):
        yield pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([np.count_nonzero(hit)], pa.int64())], names=["part", "n"])


def _closed_paths(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """How many pairs u < w of each list that was sent, u of the block, the block's lists have. About CHUNK pairs are formed at once."""
    total = 0
    for _, (ids, offsets, entries), src, sent, flat in _opened(batches):
        if not len(ids) or not len(flat):
            continue
        place = np.minimum(np.searchsorted(ids, flat), len(ids) - 1)
        first = np.flatnonzero(ids[place] == flat)
        later = np.repeat(sent[1:], np.diff(sent))[first] - first - 1
        first, later = first[later > 0], later[later > 0]
        base = int(max(flat.max(), entries.max(initial=0))) + 1
        if base * len(ids) >= 1 << 62:  # ids too large for joint keys: their ranks stand for them
            ranks = np.unique(np.concatenate([flat, entries]))
            base, flat, entries = len(ranks), np.searchsorted(ranks, flat), np.searchsorted(ranks, entries)
        keys = np.repeat(np.arange(len(ids)) * base, np.diff(offsets)) + entries
        if not len(first) or not len(keys):
            continue
        made = np.cumsum(later) // CHUNK
        for k in np.split(np.arange(len(first)), np.flatnonzero(np.diff(made)) + 1):
            u, n = first[k], later[k]
            w = np.repeat(u + 1 - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            asked = np.repeat(place[u] * base, n) + flat[w]
            total += int(np.count_nonzero(keys[np.minimum(np.searchsorted(keys, asked), len(keys) - 1)] == asked))
    yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], names=["n"])


def closed_paths(arcs: DataFrame, edges: DataFrame) -> DataFrame:
    """n: the two-paths over each src of ``arcs`` that an edge closes, in rows to be added up. They are formed where the edges of their lower end are held; none is moved."""
    return _sent(arcs, edges).mapInArrow(_closed_paths, "n long")


def _triangles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for corners in _corners(batches):
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in corners], names=["a", "b", "c"])


def _by_node(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for corners in _corners(batches):
        ids, n = np.unique(np.concatenate(corners), return_counts=True)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(n, pa.int64())], names=["id", "n"])


def _by_list(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for _, src, _, number, _, n, _, hit in _arrived(batches):
        met = np.bincount(number, np.add.reduceat(hit.astype(np.int64), np.cumsum(n) - n), len(src)).astype(np.int64)
        some = np.flatnonzero(met)
        yield pa.RecordBatch.from_arrays([pa.array(src[some], pa.int64()), pa.array(met[some], pa.int64())], names=["id", "n"])


def list_counts(edges: DataFrame) -> DataFrame:
    """id, n: the common entries of each node's oriented list and those of its entries, for nodes that have some."""
    return _sent(orient(edges)).mapInArrow(_by_list, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))


def edges_among_neighbours(edges: DataFrame) -> DataFrame:
    """id, n: the edges among each node's neighbours, each met from both of its ends, for nodes that have some."""
    dense = packed.of(edges)
    if dense is not None and dense.names is None:
        return packed.common(dense, np.arange(dense.n), packed.see_ends, dense.n, full=True)
    return _sent(both_ways(edges)).mapInArrow(_by_list, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))


def _merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sizes of the intersections of two columns of sorted lists, by merging."""
    for batch in batches:
        (fa, oa), (fb, ob) = ((c.values.to_numpy(), c.offsets.to_numpy()) for c in batch.columns)
        total = sum(len(np.intersect1d(fa[oa[i] : oa[i + 1]], fb[ob[i] : ob[i + 1]], assume_unique=True)) for i in range(batch.num_rows))
        yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], names=["n"])


def count_intersect(edges: DataFrame, order: str = "degree", kernel: str = "gallop") -> DataFrame:
    """Sum over oriented edges of the common entries of both ends' lists.

    kernel: gallop (binary search, where blocks of lists meet; in a dense network lists are bits and no list moves), or pair by pair, with both lists in a row: hash (Spark's own) or merge.
    """
    dense = packed.of(edges)
    if kernel == "gallop" and dense is not None:
        return _one(packed.common(dense, ranks(dense, order), packed.see_all, 1), "n")
    if kernel == "gallop":
        return _one(_sent(orient(edges, order)).mapInArrow(_totals, "n long"), "n")
    pairs = paired_lists(edges, order)
    if kernel == "hash":
        return _one(pairs, F.size(F.array_intersect("nv", "nu")))
    if kernel != "merge":
        raise ValueError(f"no such kernel: {kernel}")
    return _one(pairs.select("nv", "nu").mapInArrow(_merged, "n long"), "n")


def count_ordered(edges: DataFrame, order: str = "id") -> DataFrame:
    """Any total order counts each triangle once; only the work differs."""
    return count_intersect(edges, order)


def list_triangles(edges: DataFrame, order: str = "degree") -> DataFrame:
    """a, b, c of every triangle, rising in the order: oriented two-paths that an arc closes. Two-paths are made where blocks of lists meet; none is moved."""
    return _sent(orient(edges, order)).mapInArrow(_triangles, "a long, b long, c long")


def corner_counts(edges: DataFrame, order: str = "degree") -> DataFrame:
    """id, n: the triangles at each node that has some, added up before they move."""
    return _sent(orient(edges, order)).mapInArrow(_by_node, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))


def count_closure(edges: DataFrame, order: str = "degree") -> DataFrame:
    return _one(list_triangles(edges, order), F.lit(1))


def count_node_centred(edges: DataFrame, raw: bool = False) -> DataFrame:
    """Edges among each node's neighbours, in every order: each triangle is met six times (``raw``), then divided."""
    dense = packed.of(edges)
    if dense is not None:  # both ends of an edge have the same common neighbours: they are looked at once, and met from both
        six = _one(packed.common(dense, np.arange(dense.n), packed.see_all, 1, full=True), F.col("n") * 2).withColumnRenamed("triangles", "met")
        return six if raw else six.select(F.expr("met div 6").alias("triangles"))
    six = _one(_sent(both_ways(edges)).mapInArrow(_totals, "n long"), "n").withColumnRenamed("triangles", "met")
    return six if raw else six.select(F.expr("met div 6").alias("triangles"))


def count_all_triples(edges: DataFrame, most: int = 400) -> DataFrame:
    """Look at every triple of nodes; refused beyond ``most`` nodes, where it would make n^3 / 6 rows."""
    nodes = endpoints(edges)
    if nodes.count() > most:
        raise ValueError(f"more than {most} nodes")
    edge = lambda x, y: edges.select(F.col("src").alias(x), F.col("dst").alias(y))
    a, b, c = (nodes.select(F.col("id").alias(x)) for x in "abc")
    triples = a.join(b, F.col("a") < F.col("b")).join(c, F.col("b") < F.col("c"))
    return _one(triples.join(edge("a", "b"), ["a", "b"], "left_semi").join(edge("b", "c"), ["b", "c"], "left_semi").join(edge("a", "c"), ["a", "c"], "left_semi"), F.lit(1))


def count_matrix(edges: DataFrame) -> DataFrame:
    """Trace of the cubed adjacency matrix over six, with the square kept as a sparse table."""
    near = both_ways(edges)
    square = near.select(F.col("src").alias("i"), F.col("dst").alias("k")).join(near.select(F.col("src").alias("k"), F.col("dst").alias("j")), "k").groupBy("i", "j").agg(F.count(F.lit(1)).alias("n"))
    trace = square.join(near.select(F.col("src").alias("j"), F.col("dst").alias("i")), ["i", "j"]).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("t"))
    return trace.select(F.expr("t div 6").alias("triangles"))
