"""Non-overlapping blocks and the four ways of bringing lists of different blocks together.

A block owns the oriented lists of its ids, so each edge is in one block. An oriented edge v -> u inside a block is
counted there. For an edge that crosses, either u's list comes to v's block (direct: once per edge; cached: once per
block; scan: once per block, then every list of the block is searched for u), or v's list goes once to each block that
owns some of its entries, whose owner does the intersections (surrogate). A shuffled row is a message; the end of the stage
takes the place of completion notices.

A node's row holds the blocks of its entries beside them, so the surrogate's messages are made without a join, and each
crosses the network once, as one list. It is opened only where it arrives: the lists of a block come first and are held as
two arrays, the messages stream past them in Arrow batches. A block has to fit a task; more blocks make them smaller.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import cut
from .blocks import assign
from .cost import node_cost
from .orient import degrees, orient

#: Entries of lists that are looked up at once in the lists of messages.
CHUNK = 1 << 20

SCHEMES = ("direct", "cached", "scan", "surrogate")


class Owned:
    """A network cut into blocks: ``nodes`` (id, deg, eff, nbrs, blocks of the nbrs, part) and ``arcs`` (v, u, pv, pu)."""

    def __init__(self, nodes: DataFrame, arcs: DataFrame, parts: int):
        self.nodes, self.arcs, self.parts = nodes, arcs, parts

    def lists(self, name: str) -> DataFrame:
        return self.nodes.where("eff > 0").select(F.col("id").alias(name), F.col("nbrs").alias(f"n{name}"))


def build(edges: DataFrame, parts: int, cost: str = "surrogate", order: str = "degree") -> Owned:
    """Cut by the cost into ``parts`` blocks. Owners, lists and arcs are written once, as every scheme reads them several times."""
    oriented = cut(orient(edges, order))
    owner = cut(assign(node_cost(edges, cost, order, arcs=oriented), parts).select("id", "part"))
    a = owner.select(F.col("id").alias("v"), F.col("part").alias("pv"))
    b = owner.select(F.col("id").alias("u"), F.col("part").alias("pu"))
    arcs = cut(oriented.select(F.col("src").alias("v"), F.col("dst").alias("u")).join(a, "v").join(b, "u").select("v", "u", "pv", "pu"))
    entries = arcs.groupBy(F.col("v").alias("id")).agg(F.sort_array(F.collect_list(F.struct("u", "pu"))).alias("x"))
    full = degrees(edges).join(owner, "id").join(entries, "id", "left")
    nbrs = F.coalesce(F.col("x")["u"], F.array().cast("array<bigint>"))
    nodes = full.select("id", "deg", F.size(nbrs).cast("long").alias("eff"), nbrs.alias("nbrs"), F.coalesce(F.col("x")["pu"], F.array().cast("array<int>")).alias("blocks"), "part")
    return Owned(cut(nodes), arcs, parts)


def sizes(owned: Owned) -> DataFrame:
    """part, v_count (owned nodes and members of their lists) and e_count (arcs that leave owned nodes)."""
    e = owned.nodes.groupBy("part").agg(F.sum("eff").alias("e_count"))
    members = owned.nodes.select("part", F.explode(F.array_union(F.array("id"), "nbrs")).alias("id")).distinct()
    v = members.groupBy("part").agg(F.count(F.lit(1)).alias("v_count"))
    return v.join(e, "part").select("part", "v_count", "e_count")


def messages(owned: Owned, dedupe: str = "last") -> DataFrame:
    """dest, src, nbrs of the surrogate scheme's data messages, from the rows of the nodes alone.

    last: a list is sent when the block of an entry differs from that of the entry before it; enough as lists are sorted
    and blocks consecutive. set: the distinct blocks of the entries; the same rows. none: one message per crossing
    edge, which then carries that edge's u.
    """
    crossing = owned.nodes.where("eff > 0")
    if dedupe == "none":
        sent = crossing.select(F.col("id").alias("src"), "nbrs", "part", F.explode(F.arrays_zip("nbrs", "blocks")).alias("e")).where("e.blocks <> part")
        return sent.select(F.col("e.blocks").alias("dest"), "src", "nbrs", F.col("e.nbrs").alias("u"))
    if dedupe == "set":
        to = F.array_distinct("blocks")
    elif dedupe == "last":
        to = F.filter("blocks", lambda x, i: (i == 0) | (x != F.element_at("blocks", F.greatest(i, F.lit(1)))))
    else:
        raise ValueError(f"no such guard: {dedupe}")
    return crossing.select(F.explode(to).alias("dest"), F.col("id").alias("src"), "nbrs", "part").where("dest <> part").select("dest", "src", "nbrs")


def _common(rows: DataFrame, part: str) -> DataFrame:
    return rows.groupBy(F.col(part).alias("part")).agg(F.sum(F.size(F.array_intersect("nv", "nu"))).alias("n"))


def _named(ids: np.ndarray, sent: np.ndarray, flat: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """number, place: each list that was sent, and the held lists of the ids that it names."""
    number = np.repeat(np.arange(len(sent) - 1), np.diff(sent))
    place = np.minimum(np.searchsorted(ids, flat), len(ids) - 1)
    own = ids[place] == flat
    return number[own], place[own]


def _looked_at(number: np.ndarray, place: np.ndarray, offsets: np.ndarray, entries: np.ndarray, sent: np.ndarray, flat: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
    """What ``looked_up`` gives, for pairs of lists that are told; ``number`` rises."""
    keep = np.flatnonzero(offsets[place + 1] > offsets[place])
    number, place = number[keep], place[keep]
    if not len(place) or not len(flat):
        return
    base = int(max(flat.max(), entries.max(initial=0))) + 1
    if len(sent) > 2 and base * len(sent) >= 1 << 62:  # ids too large for joint keys: halve the messages
        half = (len(sent) - 1) // 2
        at, cut_at = int(sent[half]), int(np.searchsorted(number, half))
        yield from _looked_at(number[:cut_at], place[:cut_at], offsets, entries, sent[: half + 1], flat[:at])
        for first, *rest in _looked_at(number[cut_at:] - half, place[cut_at:], offsets, entries, sent[half:] - at, flat[at:]):
            yield first + half, *rest
        return
    keys = np.repeat(np.arange(len(sent) - 1) * base, np.diff(sent)) + flat
    size = offsets[place + 1] - offsets[place]
    ends = np.cumsum(size)
    first = 0
    while first < len(place):
        last = max(first + 1, int(np.searchsorted(ends, (ends[first - 1] if first else 0) + CHUNK, "right")))
        n = size[first:last]
        start = np.repeat(offsets[place[first:last]] - (np.cumsum(n) - n), n)
        held = entries[start + np.arange(int(n.sum()))]
        asked = held + np.repeat(number[first:last] * base, n)
        at = np.minimum(np.searchsorted(keys, asked), len(keys) - 1)
        yield number[first:last], place[first:last], n, held, keys[at] == asked
        first = last


def looked_up(ids: np.ndarray, offsets: np.ndarray, entries: np.ndarray, sent: np.ndarray, flat: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
    """Each list that was sent (``flat`` from ``sent``) against the held lists (``entries`` from ``offsets``) of the ids it names.

    Gives, for so many of these pairs at once: the number of the sent list, the place of the held one and its size by pair, the
    entries of the held ones, and which of them the sent one has too. All lists are sorted. At most about CHUNK entries are looked up at once.
    """
    if len(flat) and len(ids):
        yield from _looked_at(*_named(ids, sent, flat), offsets, entries, sent, flat)


def common_entries(ids: np.ndarray, offsets: np.ndarray, entries: np.ndarray, sent: np.ndarray, flat: np.ndarray) -> int:
    """Common entries of each list that was sent and the held lists of the ids it names."""
    return sum(int(np.count_nonzero(hit)) for *_, hit in looked_up(ids, offsets, entries, sent, flat))


def _met(batches: Iterator[pa.RecordBatch], meets: str = "named") -> Iterator[pa.RecordBatch]:
    """Rows of blocks in order, a block's own lists (kind 0) before its messages (1): what is found inside and with messages.

    meets: the block's lists that a message is for. named: those of the ids in the list that it brings; naming: those
    that have the id whose list it brings (its src); asked: that of its src alone.
    """
    held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    block, by_entry = None, None
    now, inside, outside = None, 0, 0

    def closed():
        """The block's lists as ids, offsets and entries; its inner triangles are counted on the way."""
        ids = np.concatenate([h[0] for h in held]) if held else np.empty(0, dtype=np.int64)
        entries = np.concatenate([h[2] for h in held]) if held else np.empty(0, dtype=np.int64)
        offsets = np.concatenate([[0], np.cumsum(np.concatenate([h[1] for h in held]))]) if held else np.zeros(1, dtype=np.int64)
        held.clear()
        return ids, offsets, entries

    def inner(block):
        ids, offsets, entries = block
        return sum(common_entries(ids, offsets, entries, offsets[a : a + 4097] - offsets[a], entries[offsets[a] : offsets[min(a + 4096, len(ids))]]) for a in range(0, len(ids), 4096))

    def out():
        return pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([inside], pa.int64()), pa.array([outside], pa.int64())], names=["part", "l", "r"])

    for batch in batches:
        dest, kind, src = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(3))
        offsets, flat = batch.column(3).offsets.to_numpy().astype(np.int64), batch.column(3).values.to_numpy(zero_copy_only=False)
        edge = np.flatnonzero((dest[1:] != dest[:-1]) | (kind[1:] != kind[:-1])) + 1
        for a, b in zip([0, *edge.tolist()], [*edge.tolist(), len(dest)], strict=True):
            if a == b:
                continue
            if dest[a] != now:
                if now is not None:
                    block = block or closed()
                    inside += inner(block)
                    yield out()
                now, inside, outside, block, by_entry = int(dest[a]), 0, 0, None, None
            part = flat[offsets[a] : offsets[b]]
            if kind[a] == 0:
                held.append((src[a:b].copy(), np.diff(offsets[a : b + 1]), part.copy()))
            else:
                block = block or closed()
                ids, starts, entries = block
                sent = offsets[a : b + 1] - offsets[a]
                if meets == "named":
                    outside += common_entries(*block, sent, part)
                    continue
                if not len(ids):
                    continue
                if meets == "naming":
                    if by_entry is None:
                        order = np.argsort(entries, kind="stable")
                        by_entry = entries[order], np.repeat(np.arange(len(ids)), np.diff(starts))[order]
                    low, high = (np.searchsorted(by_entry[0], src[a:b], side) for side in ("left", "right"))
                    n = high - low
                    number, place = np.repeat(np.arange(b - a), n), by_entry[1][np.repeat(low - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))]
                else:
                    place = np.minimum(np.searchsorted(ids, src[a:b]), len(ids) - 1)
                    number = np.flatnonzero(ids[place] == src[a:b])
                    place = place[number]
                outside += sum(int(np.count_nonzero(hit)) for *_, hit in _looked_at(number, place, starts, entries, sent, part))
    if now is not None:
        block = block or closed()
        inside += inner(block)
        yield out()


def receive(owned: Owned, sent: DataFrame | None, meets: str = "named") -> DataFrame:
    """part, l (triangles inside the block) and r (those that its owner finds in the lists it is sent).

    One shuffle: every message moves once to the block that it is for, and so do the block's own lists.
    """
    rows = owned.nodes.where("eff > 0").select(F.col("part").alias("dest"), F.lit(0).alias("kind"), F.col("id").alias("src"), "nbrs")
    if sent is not None:
        rows = rows.unionByName(sent.select("dest", F.lit(1).alias("kind"), "src", "nbrs"))
    return rows.repartitionById(owned.parts, "dest").sortWithinPartitions("dest", "kind", "src").mapInArrow(partial(_met, meets=meets), "part int, l long, r long")


def count(owned: Owned, scheme: str = "surrogate", dedupe: str = "last") -> DataFrame:
    """part, local_triangles, remote_triangles, triangles. Crossing edges count for v's block, with surrogate for u's."""
    cross = owned.arcs.where("pv <> pu")
    zero = F.lit(0).cast("long")
    parts = owned.nodes.select("part").distinct()
    replied = owned.lists("u").withColumnRenamed("nu", "nbrs")
    if scheme == "surrogate" and dedupe != "none":
        both = receive(owned, messages(owned, dedupe))
    elif scheme == "surrogate":  # each message carries one edge's u: its list is met with u's alone
        both = receive(owned, messages(owned, dedupe).select("dest", F.col("u").alias("src"), "nbrs"), "asked")
    elif scheme == "direct":  # request to u's owner, reply to v's
        both = receive(owned, cross.join(replied, "u").select(F.col("pv").alias("dest"), F.col("v").alias("src"), "nbrs"), "asked")
    elif scheme == "cached":  # a reply serves all of the block's lists that have u
        both = receive(owned, cross.select("pv", "u").distinct().join(replied, "u").select(F.col("pv").alias("dest"), F.col("u").alias("src"), "nbrs"), "naming")
    elif scheme == "scan":
        fetched = cross.select("pv", "u").distinct().join(owned.lists("u"), "u")
        held = owned.nodes.where("eff > 0").select(F.col("part").alias("pv"), F.col("nbrs").alias("nv"))
        remote = _common(fetched.join(held, "pv").where(F.array_contains("nv", F.col("u"))), "pv").withColumnRenamed("n", "r")
        both = receive(owned, None).drop("r").join(remote, "part", "left")
    else:
        raise ValueError(f"no such scheme: {scheme}")
    found = parts.join(both, "part", "left").select("part", F.coalesce("l", zero).alias("l"), F.coalesce("r", zero).alias("r"))
    return found.select("part", F.col("l").alias("local_triangles"), F.col("r").alias("remote_triangles"), (F.col("l") + F.col("r")).alias("triangles"))


def traffic(owned: Owned, by_part: bool = False) -> DataFrame:
    """scheme, messages, elements (and the sending part): what crosses between blocks.

    direct and cached send a request and a reply; requests carry no list. scan fetches as cached does.
    """
    eff = owned.nodes.select("id", "eff")
    cross = owned.arcs.where("pv <> pu")
    keys = ["part"] if by_part else []
    n, none = F.count(F.lit(1)), F.lit(0).cast("long")

    def added(rows: DataFrame, scheme: str) -> DataFrame:
        out = rows.groupBy(*keys) if keys else rows
        return out.agg(F.coalesce(F.sum("m"), none).alias("messages"), F.coalesce(F.sum("x"), none).alias("elements")).select(F.lit(scheme).alias("scheme"), *keys, "messages", "elements")

    def asked(rows: DataFrame) -> DataFrame:
        sent = rows.join(eff.withColumnRenamed("id", "u"), "u")
        ask = sent.groupBy(F.col("pv").alias("part")).agg(n.alias("m"), F.lit(0).cast("long").alias("x"))
        return ask.unionByName(sent.groupBy(F.col("pu").alias("part")).agg(n.alias("m"), F.sum("eff").alias("x")))

    once = cross.select("pv", "u", "pu").distinct()
    ship = cross.select("v", "pv", "pu").distinct().join(eff.withColumnRenamed("id", "v"), "v").groupBy(F.col("pv").alias("part")).agg(n.alias("m"), F.sum("eff").alias("x"))
    return added(asked(cross), "direct").unionByName(added(asked(once), "cached")).unionByName(added(asked(once), "scan")).unionByName(added(ship, "surrogate"))


def completions(owner: DataFrame) -> DataFrame:
    """part, messages: the notices of completion, one from each block that owns nodes to each other one. A shuffle stage ends without them."""
    parts = owner.select("part").distinct()
    others = parts.agg((F.count(F.lit(1)) - 1).alias("messages"))  # one row
    return parts.join(F.broadcast(others)).select("part", "messages")


def choose(owned: Owned) -> DataFrame:
    """The scheme with the fewest elements among those that hold no more than a block (direct, surrogate), and among all."""
    rows = traffic(owned).where("scheme <> 'scan'")
    best = lambda cond: F.min_by(F.when(cond, F.col("scheme")), F.when(cond, F.struct("elements", "messages")))
    return rows.agg(best(F.col("scheme") != "cached").alias("bounded"), best(F.lit(True)).alias("any"))
