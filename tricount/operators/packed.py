"""Dense networks in few bytes: edges as compressed gaps, and common neighbours from tables of bits, some columns at a time.

Dense: at least one in ``GAP`` of all pairs of nodes is an edge, among at most NODES nodes. There, lists that cross once for
each block would cross to nearly all blocks. So no edge and no list moves: edges stay where they are stored, and every task gets
the bits of some columns of the adjacency table at a time, looks at its own edges there, and drops them.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from functools import partial
from weakref import WeakKeyDictionary

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut, many_tasks, stored

#: Nodes, and pairs of nodes to an edge, up to which a network is held as bits.
NODES, GAP = 1 << 18, 64
#: Bits of a table that a task holds, and tables whose bits the driver holds, packed.
BITS, TABLES = 1 << 28, 4
#: Pairs of a block, about, and pairs that are formed at once.
PAIRS, CHUNK = 1 << 25, 1 << 19
#: Words that are looked at together.
WORDS = 1 << 15
#: Packed rows of a file, at most.
RECORDS = 8


class Packed:
    """Edges a, b over ids 0 .. n - 1, each in one direction: ``rows`` (edges: packed a * n + b); names: the keys of the ids in order, if these are not the ids."""

    def __init__(self, rows: DataFrame, n: int, names: pa.Array | None = None):
        self.rows, self.n, self.names = rows, n, names


_OF: WeakKeyDictionary[DataFrame, Packed] = WeakKeyDictionary()


def of(edges: DataFrame) -> Packed | None:
    """How the edges that ``view`` gave are stored."""
    return _OF.get(edges)


def pack(keys: np.ndarray) -> bytes:
    """Rising numbers as compressed gaps: a byte for each, and eight more for wide ones."""
    gaps = np.diff(keys, prepend=0)
    wide = gaps[gaps >= 255].astype(np.int64)
    plain = np.minimum(gaps, 255).astype(np.uint8).tobytes() + wide.tobytes()
    return np.array([len(keys), len(wide)], dtype=np.int64).tobytes() + pa.compress(plain, codec="zstd", asbytes=True)


def unpack(blob: bytes) -> np.ndarray:
    n, wide = np.frombuffer(blob, dtype=np.int64, count=2).tolist()
    plain = pa.decompress(blob[16:], n + 8 * wide, codec="zstd", asbytes=True)
    gaps = np.frombuffer(plain, dtype=np.uint8, count=n).astype(np.int64)
    gaps[gaps == 255] = np.frombuffer(plain, dtype=np.int64, offset=n)
    return np.cumsum(gaps)


def _opened(batches: Iterator[pa.RecordBatch], n: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """a, b of the edges of each row."""
    for batch in batches:
        for blob in batch.column(0):
            yield np.divmod(unpack(blob.as_py()), n)


def _binary(blobs: list[bytes]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(blobs, pa.binary())], names=["edges"])


def view(p: Packed) -> DataFrame:
    """The edges as rows src < dst, by their names if they have some."""
    n, names = p.n, p.names

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for a, b in _opened(batches, n):
            for at in range(0, len(a), 1 << 18):
                ends = (f(a[at : at + (1 << 18)], b[at : at + (1 << 18)]) for f in (np.minimum, np.maximum))
                yield pa.RecordBatch.from_arrays([pa.array(x) if names is None else names.take(pa.array(x)) for x in ends], names=["src", "dst"])

    kind = "long" if names is None else p.rows.sparkSession.createDataFrame(pa.table({"k": names[:1]})).schema["k"].dataType.simpleString()
    out = p.rows.mapInArrow(run, f"src {kind}, dst {kind}")
    _OF[out] = p
    return out


def keys(p: Packed) -> DataFrame:
    """key of every node."""
    spark = p.rows.sparkSession
    return spark.range(p.n).toDF("key") if p.names is None else spark.createDataFrame(pa.table({"key": p.names}))


def _summed(rows: DataFrame, run: Callable) -> DataFrame:
    """id, n of what ``run`` finds for each id, added up in each task first."""
    return rows.mapInArrow(run, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))


def _found(found: np.ndarray) -> pa.RecordBatch:
    some = np.flatnonzero(found)
    return pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array(found[some], pa.int64())], names=["id", "n"])


def degrees(p: Packed) -> DataFrame:
    """id, deg of every node."""
    n = p.n

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = np.zeros(n, dtype=np.int64)
        for a, b in _opened(batches, n):
            found += np.bincount(a, minlength=n) + np.bincount(b, minlength=n)
        yield _found(found)

    return _summed(p.rows, run).withColumnRenamed("n", "deg")


def held_degrees(p: Packed) -> np.ndarray:
    """Degrees by id."""
    deg = degrees(p).toArrow()
    out = np.zeros(p.n, dtype=np.int64)
    out[deg.column("id").to_numpy()] = deg.column("deg").to_numpy()
    return out


def relabelled(p: Packed, ids: np.ndarray) -> DataFrame:
    """The edges with ``ids`` in place of their ids, stored. Rows stay rows, so that gaps stay small: an edge may be stored from its higher end."""
    n, sent = p.n, p.rows.sparkSession.sparkContext.broadcast(ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for a, b in _opened(batches, n):
            yield _binary([pack(np.sort(sent.value[a] * n + sent.value[b]))])

    return view(Packed(stored(p.rows.mapInArrow(run, "edges binary"), RECORDS)[0], n))


# Pairs of a group ----------------------------------------------------------------------------------------------------


def _set(table: np.ndarray, places: np.ndarray) -> None:
    """Set bits of a table of bytes; places rise."""
    byte = places >> 3
    first = np.flatnonzero(np.diff(byte, prepend=-1))
    if len(first):
        table[byte[first]] |= np.bitwise_or.reduceat((1 << (places & 7)).astype(np.uint8), first)


def _members(batches: Iterator[pa.RecordBatch], names: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """group, id of the members of some groups in order, and how many come later in the same group."""
    for whole in batches:
        for at in range(0, whole.num_rows, 4096):
            lists = whole.column(0).slice(at, 4096)
            size = np.diff(lists.offsets.to_numpy())
            ids = pc.index_in(lists.flatten(), value_set=names).to_numpy(zero_copy_only=False).astype(np.int64)
            ends = np.repeat(np.cumsum(size), size)
            yield np.repeat(np.arange(len(size)), size), ids, ends - np.arange(len(ids)) - 1


def pairs(groups: DataFrame, names: pa.Array) -> DataFrame | None:
    """src, dst: the distinct pairs of members of a group, stored, or None if they may not be dense; groups: m, sorted lists of two members or more; names: all members in order.

    A group's list goes to each block of ids that has some of its members, cut off below; pairs are formed there.
    """
    n = len(names)
    spark = groups.sparkSession
    if not 0 < n <= NODES:
        return None
    named = spark.sparkContext.broadcast(names)

    def weigh(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = np.zeros(n, dtype=np.int64)
        for _, ids, later in _members(batches, named.value):
            found += np.bincount(ids, later, n).astype(np.int64)
        yield _found(found)

    each = _summed(groups, weigh).toArrow()  # at most NODES rows
    weight = np.zeros(n, dtype=np.int64)
    weight[each.column("id").to_numpy()] = each.column("n").to_numpy()
    if int(weight.sum()) * 2 * GAP < n * n:
        return None
    wide = -(-n // 8) * 8
    firsts, made = [0], 0
    for i, w in enumerate(weight.tolist()):
        if i > firsts[-1] and (made + w > PAIRS or (i - firsts[-1] + 1) * wide > BITS):
            firsts.append(i)
            made = 0
        made += w
    parts, ends = len(firsts), [*firsts[1:], n]
    starts = np.array(firsts[1:], dtype=np.int64)

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group, ids, later in _members(batches, named.value):
            block = np.searchsorted(starts, ids, "right")
            for d in np.unique(block[later > 0]).tolist():
                has = np.zeros(group[-1] + 1, dtype=bool)
                has[group[(block == d) & (later > 0)]] = True
                blob = pack((group * n + ids)[has[group] & (block >= d)])
                yield pa.RecordBatch.from_arrays([pa.array([d], pa.int32()), pa.array([blob], pa.binary())], names=["dest", "lists"])

    def form(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables: dict[int, np.ndarray] = {}
        for batch in batches:
            for d, blob in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                low, high = firsts[d], ends[d]
                if d not in tables:
                    for done in list(tables):  # rows come block by block
                        yield from rows(done, tables.pop(done))
                    tables[d] = np.zeros((high - low) * wide // 8, dtype=np.uint8)
                group, ids = np.divmod(unpack(blob.as_py()), n)
                own = np.flatnonzero(ids < high)
                later = np.searchsorted(group, group[own], "right") - own - 1
                own, later = own[later > 0], later[later > 0]
                for k in np.split(np.arange(len(own)), np.flatnonzero(np.diff(np.cumsum(later) // CHUNK)) + 1):
                    u, c = own[k], later[k]
                    w = np.repeat(u + 1 - (np.cumsum(c) - c), c) + np.arange(int(c.sum()))
                    _set(tables[d], np.sort(np.repeat((ids[u] - low) * wide, c) + ids[w]))
        for done in list(tables):
            yield from rows(done, tables.pop(done))

    def rows(d: int, table: np.ndarray) -> Iterator[pa.RecordBatch]:
        step = max(1, (1 << 22) // wide)
        for r in range(0, ends[d] - firsts[d], step):
            row, col = np.divmod(np.flatnonzero(np.unpackbits(table[r * wide // 8 : (r + step) * wide // 8], bitorder="little")), wide)
            if len(row):
                yield _binary([pack((firsts[d] + r + row) * n + col)])

    sent = groups.mapInArrow(send, "dest int, lists binary").repartitionById(parts, "dest").sortWithinPartitions("dest")
    return view(Packed(stored(sent.mapInArrow(form, "edges binary"), RECORDS)[0], n, names))


# Common neighbours ---------------------------------------------------------------------------------------------------

_TABLE: dict[str, np.ndarray] = {}


def _table(tag: str, sent: Broadcast, rows: int, words: int) -> np.ndarray:
    """The bits of a round, kept for the other tasks of this process."""
    if tag not in _TABLE:
        _TABLE.clear()
        table = np.zeros(rows * words, dtype=np.uint64)
        for blob in sent.value:
            _set(table.view(np.uint8), unpack(blob))
        _TABLE[tag] = table.reshape(rows, words)
    return _TABLE[tag]


def _rounds(n: int, full: bool, columns: np.ndarray) -> Iterator[np.ndarray]:
    """``columns`` (ranks that rise), some at a time, so that a table of them fits BITS: its rows are all ranks (full), or those below its last column."""
    at = 0
    while at < len(columns):
        k = min(len(columns) - at, max(64, BITS // n // 64 * 64))
        while not full and at + k < len(columns) and (int(columns[min(at + k + 63, len(columns) - 1)]) + 1) * (k + 64) <= BITS:
            k = min(k + 64, len(columns) - at)
        yield columns[at : at + k]
        at += k


def common(p: Packed, rank: np.ndarray, see: Callable, size: int, full: bool = False, columns: list[np.ndarray] | None = None) -> DataFrame:
    """id, n: what ``see`` adds to an array of ``size`` for the common neighbours of the ends of every edge.

    full: all of them; else those that rank above both ends. ``see`` gets the array (found), the place in ``columns`` (sets of ranks; all ranks, unless
    told otherwise) of the columns that are looked at (kind), an id a, ids b that have edges with it, and a function of places in b (shared), which gives
    the common neighbours in runs: places, and counts by words.
    """
    n, spark = p.n, p.rows.sparkSession
    ranked = spark.sparkContext.broadcast(rank)
    rounds = [(kind, part) for kind, among in enumerate([np.arange(n)] if columns is None else columns) for part in _rounds(n, full, among)]
    out: DataFrame | None = None
    for at in range(0, len(rounds), TABLES):
        some = rounds[at : at + TABLES]
        widths = [-(-len(part) // 64) for _, part in some]
        tables = _bits(p, ranked, [part for _, part in some], widths, full)
        for (kind, part), words, blobs in zip(some, widths, tables, strict=True):
            got = _looked_at(p, ranked, blobs, n if full else int(part[-1]) + 1, words, partial(see, kind=kind), size)
            out = got if out is None else out.unionByName(got)
    ranked.destroy()
    return out.groupBy("id").agg(F.sum("n").alias("n"))


def _bits(p: Packed, ranked: Broadcast, parts: list[np.ndarray], widths: list[int], full: bool) -> list[list[bytes]]:
    """The packed bits of some tables, at most BITS each: for the ranks of the lower ends (full: of all), the columns of each part."""
    n, spark = p.n, p.rows.sparkSession
    place, which = np.zeros(n, dtype=np.int64), np.full(n, -1, dtype=np.int64)
    for k, part in enumerate(parts):
        place[part], which[part] = np.arange(len(part)), k
    placed = spark.sparkContext.broadcast((place, which))

    def take(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place, which = placed.value
        for a, b in _opened(batches, n):
            x, y = ranked.value[a], ranked.value[b]
            ways = [(x, y), (y, x)] if full else [(np.minimum(x, y), np.maximum(x, y))]
            of = [which[col] for _, col in ways]
            for k, words in enumerate(widths):
                bits = np.concatenate([row[o == k] * (64 * words) + place[col[o == k]] for (row, col), o in zip(ways, of, strict=True)])
                if len(bits):
                    yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([pack(np.sort(bits))], pa.binary())], names=["k", "bits"])

    with many_tasks(spark):
        got = p.rows.mapInArrow(take, "k int, bits binary").toArrow()
    placed.destroy()
    return [got.filter(pc.equal(got.column("k"), k)).column("bits").to_pylist() for k in range(len(parts))]


def _looked_at(p: Packed, ranked: Broadcast, blobs: list[bytes], rows: int, words: int, see: Callable, size: int) -> DataFrame:
    """id, n: what ``see`` finds in one table, stored."""
    n, spark = p.n, p.rows.sparkSession
    sent, tag, step = spark.sparkContext.broadcast(blobs), uuid.uuid4().hex, max(1, WORDS // words)

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, found = _table(tag, sent, rows, words), np.zeros(size, dtype=np.int64)
        both, ones = np.empty((step, words), dtype=np.uint64), np.empty((step, words), dtype=np.uint8)

        def shared(own: np.ndarray, y: np.ndarray, k: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
            for at in range(0, len(k), step):
                some = k[at : at + step]
                np.take(table, y[some], axis=0, out=both[: len(some)], mode="clip")
                np.bitwise_and(both[: len(some)], own, out=both[: len(some)])
                yield some, np.bitwise_count(both[: len(some)], out=ones[: len(some)])

        for a, b in _opened(batches, n):
            x, y = ranked.value[a], ranked.value[b]
            keep = np.flatnonzero(np.maximum(x, y) < rows)
            a, b, x, y = a[keep], b[keep], x[keep], y[keep]
            edge = [*np.flatnonzero(np.diff(a, prepend=-1)).tolist(), len(a)]
            for i, j in zip(edge, edge[1:], strict=False):
                see(found, a=int(a[i]), b=b[i:j], shared=partial(shared, table[x[i]], y[i:j]))
        yield _found(found)

    with many_tasks(spark):
        got = cut(_summed(p.rows, look))
    sent.destroy()
    return got


def see_all(found: np.ndarray, a: int, b: np.ndarray, shared: Callable, kind: int) -> None:
    """All common neighbours of an edge, in one sum."""
    for _, ones in shared(np.arange(len(b))):
        found[0] += int(np.add.reduce(ones, axis=None, dtype=np.uint32))


def see_ends(found: np.ndarray, a: int, b: np.ndarray, shared: Callable, kind: int) -> None:
    """Those of an edge at both of its ends."""
    for some, ones in shared(np.arange(len(b))):
        n = np.add.reduce(ones, axis=1, dtype=np.uint32)
        found[a] += int(n.sum())
        found[b[some]] += n
