"""Exact top-k by inner product with a three-phase uniform threshold.

The components are cut into m lists of neighbouring dimensions, each stored apart; an entry's score is the sum of its
m partial scores.

1. Gather the heads: of each block of vectors and each list, the HEAD entries of largest norm are packed into a small
   table. Its exact scores give every query a k-th best score, which is a safe cutoff.
2. With the cutoff, the lists are read one after the other. If a sum reaches the cutoff, one of its m parts is at
   least cutoff / m, and no list can add more than the product of the norms. So an entry stays in question only while a
   part of it was, or can still be, at least cutoff / m, and while what is left can lift it to the cutoff.
3. For the entries that are still in question once they are few, the remaining partial scores are resolved one by
   one, and what reaches the cutoff competes for the k places. The cutoff of a query rises within a task as better
   entries are found there.

Queries and vectors are packed into blocks of fixed size, and blocks into the cells of a grid: each block of queries
meets each block of vectors once, in a task of bounded size. Blocks of vectors are copied only to those rows of the grid
whose cutoffs they can reach. A block sends at most k rows for a query, so a vector that occurs very often sends no
more than others. Ties go to the smaller id.

Defined results: vectors that are null or hold null or non-finite components take no part, as queries and as
candidates, nor do null ids; a query meets the vectors of its own length; every row is a query or candidate of its own,
so rows that repeat an id (or a whole vector) meet each other, and a query that occurs twice has its rows twice; a query
without candidates has no row; empty tables give empty tables; other columns are ignored. Scores are exact while the
sum of products stays below 2^63.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.accumulators import Accumulator
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import schema_of, stored

#: Vectors of a block of candidates, queries of a block of queries, and blocks of a kind in a cell of the grid.
BLOCK, QUERIES, CELL = 2048, 512, 32
#: Entries that a block gives to the head of each list, and entries that are looked at before cutoffs rise.
HEAD, STEP = 2, 256
#: Share of the pairs up to which remaining partial scores are resolved pair by pair.
FEW = 0.5
#: Rows of the grid up to which their bounds are broadcast (some 100 bytes each).
ACROSS = 100_000
PACKED = "dim int, nums array<long>, ids array<long>, lists array<binary>, tops array<double>"
FOUND = "query_num long, query_id long, vec_id long, score long"


def quantised(vectors: DataFrame, scale: int = 256) -> DataFrame:
    """num (of the row, any distinct numbers), vec_id and floor(scale * x) of each component as LONG, for the rows that take part."""
    fine = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < F.lit(float("inf"))))
    whole = F.transform("embedding", lambda x: F.floor(F.lit(float(scale)) * x.cast("double")).cast("long"))
    rows = vectors.where(F.col("embedding").isNotNull() & F.col("vec_id").isNotNull()).where((F.size("embedding") > 0) & fine)
    return rows.select(F.monotonically_increasing_id().alias("num"), "vec_id", whole.alias("v"))


def _edges(dim: int, lists: int) -> list[tuple[int, int]]:
    cuts = np.linspace(0, dim, min(lists, dim) + 1).astype(int).tolist()
    return list(zip(cuts[:-1], cuts[1:], strict=True))


def _norms(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.float64)
    return np.sqrt(np.einsum("ij,ij->i", x, x))


def _coded(x: np.ndarray) -> bytes:
    """The numbers in the narrowest width that holds them all, after one byte that names it."""
    for width in (2, 4):
        if -(1 << 8 * width - 1) <= x.min(initial=0) and x.max(initial=0) < 1 << 8 * width - 1:
            return bytes([width]) + x.astype(f"<i{width}").tobytes()
    return bytes([8]) + x.astype("<i8").tobytes()


def _decoded(raw: bytes, n: int) -> np.ndarray:
    return np.frombuffer(raw, dtype=f"<i{raw[0]}", offset=1).reshape(n, -1)


class _Packer:
    """Gathers vectors of one length and gives them out in blocks of at most ``most``, one binary per list."""

    def __init__(self, most: int, lists: int):
        self.most, self.lists = most, lists
        self.held: dict[int, list[tuple]] = {}

    def add(self, dim: int, num: int, vec_id: int, v: np.ndarray) -> Iterator[pa.RecordBatch]:
        rows = self.held.setdefault(dim, [])
        rows.append((num, vec_id, v))
        if len(rows) >= self.most:
            yield self.block(dim)

    def block(self, dim: int) -> pa.RecordBatch:
        nums, ids, vs = zip(*self.held.pop(dim), strict=True)
        x = np.stack(vs)
        parts = [x[:, a:b] for a, b in _edges(dim, self.lists)]
        made = [[dim], [nums], [ids], [[_coded(p) for p in parts]], [[float(_norms(p).max()) for p in parts]]]
        types = [pa.int32(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.binary()), pa.list_(pa.float64())]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(made, types, strict=True)], names=[c.split()[0] for c in PACKED.split(", ")])

    def rest(self) -> Iterator[pa.RecordBatch]:
        for dim in list(self.held):
            yield self.block(dim)


def _packed(rows: DataFrame, most: int, lists: int) -> DataFrame:
    """Blocks of at most ``most`` vectors of one length."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = _Packer(most, lists)
        for batch in batches:
            flat, offsets = batch.column(2).values.to_numpy(zero_copy_only=False), batch.column(2).offsets.to_numpy()
            for num, vec, a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
                yield from packer.add(b - a, num, vec, flat[a:b].copy())
        yield from packer.rest()

    return rows.select("num", "vec_id", "v").mapInArrow(run, schema_of(PACKED))


def _heads(blocks: DataFrame, lists: int) -> DataFrame:
    """The heads of all lists of all blocks, whole vectors, in blocks of their own."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = _Packer(BLOCK, lists)
        for batch in batches:
            for at in range(batch.num_rows):
                row = batch.slice(at, 1).to_pylist()[0]
                n = len(row["ids"])
                parts = [_decoded(p, n) for p in row["lists"]]
                lead = np.unique(np.concatenate([np.argsort(-_norms(p), kind="stable")[:HEAD] for p in parts]))
                x = np.concatenate([p.astype(np.int64) for p in parts], axis=1)
                for k in lead.tolist():
                    yield from packer.add(row["dim"], row["nums"][k], row["ids"][k], x[k])
        yield from packer.rest()

    return blocks.mapInArrow(run, schema_of(PACKED))


def meet(x: list[np.ndarray], q: list[np.ndarray], low: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Entries and queries whose sum of partial scores is at least the query's ``low``, the sums, and how many partial scores were computed.

    x and q hold one matrix per list; low is -inf where there is no cutoff.
    """
    m, n, k = len(x), len(x[0]), len(q[0])
    size = max(float(np.abs(p).max(initial=0)) for p in x) * max(float(np.abs(p).max(initial=0)) for p in q) * sum(p.shape[1] for p in x)
    if size >= 2.0**53:  # too large for doubles: all parts, in integers
        total = sum(a.astype(np.int64) @ b.astype(np.int64).T for a, b in zip(x, q, strict=True))
        e, i = np.nonzero(total >= np.where(np.isfinite(low), low, np.iinfo(np.int64).min).astype(np.int64)[None, :])
        return e, i, total[e, i], m * n * k
    x, q = [p.astype(np.float64) for p in x], [p.astype(np.float64) for p in q]
    reach = np.ceil(low / m)  # parts are whole numbers
    a, b = np.stack([_norms(p) for p in x]), np.stack([_norms(p) for p in q])
    # What the lists from j on can add in all, and the most that one of them can: products of norms, with room for rounding.
    left = [np.sqrt((v[j:] ** 2).sum(axis=0)) for v in (a, b) for j in range(m + 1)]
    most = [v[j:].max(axis=0, initial=0.0) for v in (a, b) for j in range(m + 1)]
    room = 1 + 1e-9
    part = x[0] @ q[0].T
    total, enough, done = part, part >= reach, 1
    computed = n * k
    while done < m:
        alive = total + np.outer(left[done], left[m + 1 + done] * room) + 1e-6 >= low
        alive &= enough | (np.outer(most[done], most[m + 1 + done] * room) + 1e-6 >= reach)
        if np.count_nonzero(alive) <= FEW * alive.size:
            break
        part = x[done] @ q[done].T
        total = total + part
        enough = enough | (part >= reach)
        computed += n * k
        done += 1
    else:
        e, i = np.nonzero(enough & (total >= low))
        return e, i, total[e, i].astype(np.int64), computed
    e, i = np.nonzero(alive)
    total, enough = total[e, i], enough[e, i]
    for j in range(done, m):
        part = np.concatenate([np.einsum("ij,ij->i", x[j][e[at : at + 65536]], q[j][i[at : at + 65536]]) for at in range(0, len(e), 65536)]) if len(e) else np.empty(0)
        computed += len(e)
        total, enough = total + part, enough | (part >= reach[i])
        alive = total + left[j + 1][e] * left[m + 2 + j][i] * room + 1e-6 >= low[i]
        alive &= enough | (most[j + 1][e] * most[m + 2 + j][i] * room + 1e-6 >= reach[i])
        e, i, total, enough = e[alive], i[alive], total[alive], enough[alive]
    fine = enough & (total >= low[i])
    return e[fine], i[fine], total[fine].astype(np.int64), computed


def best(i: np.ndarray, ids: np.ndarray, total: np.ndarray, k: int) -> np.ndarray:
    """Positions of the k highest totals of each query, ties to smaller ids."""
    by = np.lexsort((ids, -total, i))
    of = i[by]
    first = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]])) if len(of) else np.empty(0, dtype=np.int64)
    start = np.repeat(first, np.diff(np.concatenate([first, [len(of)]])))
    return by[np.arange(len(of)) - start < k]


def _score(met: DataFrame, k: int, seen: Accumulator | None) -> DataFrame:
    """Rows of a block of queries and one of vectors -> at most k entries a query that reach the query's cutoff."""
    schema = schema_of(FOUND)
    names = schema.names

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}  # the k best sums of each query so far in this task, by block of queries
        for batch in batches:
            for at in range(batch.num_rows):
                row = batch.slice(at, 1).to_pylist()[0]
                nums, ids = np.array(row["nums"], dtype=np.int64), np.array(row["ids"], dtype=np.int64)
                asked, who = np.array(row["q_nums"], dtype=np.int64), np.array(row["q_ids"], dtype=np.int64)
                low = np.array([-np.inf if c is None else float(c) for c in row["cutoffs"] or [None] * len(asked)])
                top = held.setdefault(int(asked[0]), np.full((len(asked), k), -np.inf))
                x, q = [_decoded(p, len(ids)) for p in row["lists"]], [_decoded(p, len(asked)) for p in row["q_lists"]]
                found = []
                for first in range(0, len(ids), STEP):
                    e, i, total, computed = meet([p[first : first + STEP] for p in x], q, np.maximum(low, top[:, 0]))
                    if seen is not None:
                        seen.add(computed)
                    e += first
                    other = nums[e] != asked[i]
                    e, i, total = e[other], i[other], total[other]
                    won = best(i, ids[e], total, k)
                    e, i, total = e[won], i[won], total[won]
                    for one in np.unique(i).tolist():
                        top[one] = np.sort(np.concatenate([top[one], total[i == one]]))[-k:]
                    found.append((e, i, total))
                e, i, total = (np.concatenate(c) for c in zip(*found, strict=True))
                won = best(i, ids[e], total, k)
                e, i, total = e[won], i[won], total[won]
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (asked[i], who[i], ids[e], total)], names=names)

    return met.mapInArrow(run, schema)


def _ranked(rows: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_num").orderBy(F.desc("score"), "vec_id")
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def top_k(vectors: DataFrame, is_query: Column, k: int = 5, scale: int = 256, lists: int = 8, seen: Accumulator | None = None) -> DataFrame:
    """query_id, rank, vec_id, score: the k best other rows of each row for which ``is_query`` holds.

    seen: if given, is raised by the number of partial scores that were computed.
    """
    rows = stored(quantised(vectors, scale))
    blocks = stored(_packed(rows, BLOCK, lists))
    heads = stored(_heads(blocks, lists))
    queries = stored(_packed(rows.where(is_query), QUERIES, lists).select("dim", F.col("nums").alias("q_nums"), F.col("ids").alias("q_ids"), F.col("lists").alias("q_lists"), F.col("tops").alias("q_tops"), F.lit(None).cast("array<long>").alias("cutoffs")))
    n_queries = queries.count()
    across = max(1, -(-n_queries // CELL))

    def meeting(asked: DataFrame, side: DataFrame) -> DataFrame:
        """Each block of queries with each block of vectors of its length, by cells of the grid."""
        down = max(1, -(-side.count() // CELL))
        asked = asked.withColumn("across", F.pmod(F.xxhash64("q_nums"), F.lit(across)).cast("int"))
        # What a row of the grid asks for: the least cutoff, and its largest norms by list.
        low = F.when(F.exists("cutoffs", lambda c: c.isNull()) | F.col("cutoffs").isNull(), F.lit(float("-inf"))).otherwise(F.array_min("cutoffs").cast("double"))
        each = asked.select("dim", "across", low.alias("low"), F.posexplode("q_tops").alias("list", "top")).groupBy("dim", "across", "list").agg(F.min("low").alias("low"), F.max("top").alias("top"))
        bounds = each.groupBy("dim", "across").agg(F.min("low").alias("low"), F.transform(F.sort_array(F.collect_list(F.struct("list", "top"))), lambda s: s["top"]).alias("asked_tops"))
        most = F.aggregate(F.zip_with("tops", "asked_tops", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
        spread = side.withColumn("down", F.pmod(F.xxhash64("nums"), F.lit(down)))
        placed = spread.join(F.broadcast(bounds) if across <= ACROSS else bounds, "dim").where(most * (1 + 1e-9) + 1 >= F.col("low")).drop("low", "asked_tops", "tops")
        copied = asked.drop("q_tops").withColumn("down", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(down - 1).cast("long"))))
        return copied.join(placed, ["dim", "across", "down"])

    first = _ranked(_score(meeting(queries, heads), k, seen), k)
    kth = first.groupBy("query_num").agg(F.min("score").alias("low"), F.count(F.lit(1)).alias("n")).where(F.col("n") == k).select("query_num", "low")
    each = queries.select(F.xxhash64("q_nums").alias("q"), F.posexplode("q_nums").alias("place", "query_num")).join(kth, "query_num", "left")
    cut = each.groupBy("q").agg(F.transform(F.sort_array(F.collect_list(F.struct("place", "low"))), lambda x: x["low"]).alias("cutoffs"))
    asked = stored(queries.drop("cutoffs").withColumn("q", F.xxhash64("q_nums")).join(cut, "q").drop("q"))
    return _ranked(_score(meeting(asked, blocks), k, seen), k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
