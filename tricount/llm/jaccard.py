"""Near duplicates by the Jaccard similarity of word shingles: an exact join by prefixes, then components.

A text is the set of its shingles' 64-bit hashes; texts of equal sets are one node. In any fixed order of shingles, two
sets whose similarity reaches ``least`` share at least k shingles among the first n - ceil(least * n) + k of each (k up to
ceil(least * n)), so only those are posted, and only pairs that meet k times are looked at. The order puts crowded
shingles last. Which ones are crowded is told by a bitmap from an eighth of the texts: it moves work, never a result.

Postings that hold the same nodes are one that counts so many times: a shared passage is met once, not at each of its
shingles. Inside a posting, pairs are held against bounds that no link can fail (sizes, and the parity of the shingles in 1024
cells, whose difference is at most that of the sets); what remains is compared set by set. A first round compares each
large posting with one pivot, PIVOTS in all for postings of the same nodes, as near copies need not all be near one of them; the second forms pairs only of nodes that are not yet in one component, so a large group
of near copies does not become all of its pairs. The first round also takes what the SimHash index links: texts of equal
fingerprints with one of them, and one text of each two fingerprints that it finds near. Few pairs of similarity 0.8
differ in only two bits, so the fingerprints alone would lose links, which the join by prefixes then finds.

Defined results: null and empty texts are copies of each other; a text shorter than a shingle is one shingle; a null
doc_id links but never heads a group; rows that repeat a doc_id are judged by their own texts; an empty table gives an
empty table; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, bitmap, schema_of, stored
from .components import components
from .simhash import CHUNK, fingerprint_links, fingerprint_of_hashes, keep_heads, shingle_hashes, with_text_key

#: Cells of a set's parity map, and bits of the bitmaps of marked numbers (4 MB); powers of two.
CELLS, BITS = 1024, 1 << 25
#: Rows of a posting that is worth a pivot, and pivots of postings that hold the same nodes; the latter a power of two.
LARGE, PIVOTS = 16, 16


def shingle_set(text: str | None, shingle: int = 5, seed: int = 42) -> np.ndarray:
    """Sorted distinct hashes of the text's word shingles."""
    parts = [np.unique(p) for p in shingle_hashes(text, shingle, seed)]
    return np.unique(np.concatenate(parts)) if parts else np.empty(0, dtype=np.uint64)


def parity(found: np.ndarray) -> bytes:
    """For each cell, whether an odd number of the set's hashes fall into it."""
    odd = np.bincount((found >> np.uint64(65 - CELLS.bit_length())).astype(np.int64), minlength=CELLS) & 1
    return np.packbits(odd.astype(np.uint8)).tobytes()


def shared_least(n: int, least: Fraction) -> int:
    """How many shingles of its prefix a set of n has to share with a similar one."""
    return min(1 + n // 20, -(-least.numerator * n // least.denominator))


def _digest(found: np.ndarray, seed: int) -> int:
    from xxhash import xxh64_intdigest

    x = xxh64_intdigest(found.astype("<u8").tobytes(), seed)
    return x - (1 << 64) if x >> 63 else x


def shingle_sets(docs: DataFrame, shingle: int, least: Fraction, seed: int) -> DataFrame:
    """doc_id, key (of the text), node (a digest of the set), n, odd (parity map), fp (fingerprint) and prefix (the posted hashes, as bytes)."""
    eighth = docs.where(F.pmod(F.xxhash64("text"), F.lit(8)) == 0).select("text")

    def sampled(texts):
        sets = [shingle_set(t, shingle, seed) for t in texts]
        return {"h": np.concatenate(sets).view(np.int64), "node": np.repeat(np.array([_digest(x, seed) for x in sets], dtype=np.int64), [len(x) for x in sets])}

    crowded = arrow_map(eighth, "h long, node long", sampled).groupBy("h").agg(F.min("node").alias("a"), F.max("node").alias("b")).where("a < b").select("h")
    held = docs.sparkSession.sparkContext.broadcast(_bitmap(crowded))

    def prefix(x):
        k = len(x) - -(-least.numerator * len(x) // least.denominator) + shared_least(len(x), least)
        return x[np.argsort(_marked(held.value, x), kind="stable")][:k].astype("<u8").tobytes()

    def rows(ids, texts, keys):
        sets = [shingle_set(t, shingle, seed) for t in texts]
        prints = np.array([fingerprint_of_hashes(x[at : at + CHUNK] for at in range(0, len(x), CHUNK)) for x in sets], dtype=np.uint64)
        return {"doc_id": ids, "key": keys, "node": [_digest(x, seed) for x in sets], "n": [len(x) for x in sets], "odd": [parity(x) for x in sets], "fp": prints.view(np.int64), "prefix": [prefix(x) for x in sets]}

    return arrow_map(with_text_key(docs), "doc_id long, key long, node long, n int, odd binary, fp long, prefix binary", rows)


def _cell(x: np.ndarray) -> np.ndarray:
    return (x.view(np.uint64) & np.uint64(BITS - 1)).astype(np.int64)


def _bitmap(numbers: DataFrame) -> np.ndarray:
    """A bitmap of fixed size in which every number of the one column is marked."""
    return bitmap(numbers, _cell, BITS)


def _marked(bits: np.ndarray, x: np.ndarray) -> np.ndarray:
    c = _cell(x)
    return (bits[c >> 3] >> (c & 7).astype(np.uint8) & 1).astype(bool)


def _postings(sets: DataFrame) -> DataFrame:
    """(h, node): the prefix of every node."""

    def rows(nodes, raw):
        return {"h": np.concatenate([np.frombuffer(b, dtype="<i8") for b in raw]), "node": np.repeat(np.array(nodes, dtype=np.int64), [len(b) // 8 for b in raw])}

    return arrow_map(sets.select("node", "prefix"), "h long, node long", rows).distinct()


def _by_posting(rows: DataFrame, ddl: str, each) -> DataFrame:
    """Run ``each`` on the arrays of many whole postings (first column h, in order) and gather what it gives."""
    schema = schema_of(ddl)
    names = [f.name for f in schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def found(t):
            columns = [np.frombuffer(b"".join(c.to_pylist()), dtype=np.uint64).reshape(len(c), -1) if pa.types.is_binary(c.type) else c.to_numpy() for c in t.columns]
            for made in each(*columns):
                if len(made[0]):
                    yield made

        def sent(t):
            held, size = [], 0
            for made in found(t):
                held.append(made)
                size += len(made[0])
                if size >= 1 << 16:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*held, strict=True)], names=names)
                    held, size = [], 0
            if held:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*held, strict=True)], names=names)

        kept: list[pa.Table] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            h = batch.column(0).to_numpy()
            whole = int(np.argmax(h == h[-1]))  # the last posting may go on in the next batch
            t = pa.Table.from_batches([batch])
            if whole or (kept and kept[-1].column(0)[-1].as_py() != int(h[0])):
                if kept and not whole:
                    yield from sent(pa.concat_tables(kept))
                    kept = []
                elif whole:
                    yield from sent(pa.concat_tables([*kept, t.slice(0, whole)]))
                    kept = []
            kept.append(t.slice(whole))
        if kept:
            yield from sent(pa.concat_tables(kept))

    return rows.repartition("h").sortWithinPartitions("h").mapInArrow(run, schema)


def _bounds(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where each posting starts and ends."""
    edge = np.flatnonzero(h[1:] != h[:-1]) + 1
    return np.concatenate([[0], edge]), np.concatenate([edge, [len(h)]])


def _shared(h: np.ndarray, node: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The rows of the postings of two rows or more, under a number that the posting's nodes make."""
    start, end = _bounds(h)
    mixed = node.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    mixed = (mixed ^ (mixed >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    made = np.add.reduceat(mixed ^ (mixed >> np.uint64(32)), start).view(np.int64)
    size = end - start
    held = np.repeat(size > 1, size)
    yield np.repeat(made, size)[held], node[held]


def _shared_postings(postings: DataFrame) -> DataFrame:
    """(h, node, times): the postings of two rows or more; those that hold the same nodes are one, met so many times.

    Texts that share a passage meet at each of its shingles, at postings of the same nodes. Should different nodes make
    one number, their postings are one of them all, with all of their pairs and more.
    """
    return _by_posting(postings, "h long, node long", _shared).groupBy("h", "node").agg(F.count(F.lit(1)).alias("times"))


def _pairs(posted: DataFrame, least: Fraction, pivot: bool) -> DataFrame:
    """(a, b), a < b: pairs of nodes of different groups that no bound rules out; pivot: only with one node of each large posting."""
    p, q = least.numerator, least.denominator

    def made(node, n, odd, times, i, j):
        # J >= p/q asks that the sets differ in at most (q-p)/(q+p) of the sum of their sizes.
        apart = np.bitwise_count(odd[i] ^ odd[j]).sum(axis=1, dtype=np.int64)
        ok = apart * (p + q) <= (q - p) * (n[i] + n[j])
        i, j = i[ok], j[ok]
        size = np.minimum(n[i], n[j])
        return np.minimum(node[i], node[j]), np.maximum(node[i], node[j]), np.minimum(1 + size // 20, -(-p * size // q)), np.maximum(times[i], times[j])

    def with_pivot(h, node, n, odd, times, group):
        n = n.astype(np.int64)
        start, end = _bounds(h)
        large = end - start >= LARGE
        for s, e in zip(start[large].tolist(), end[large].tolist(), strict=True):
            # Few pivots serve all the postings of one group.
            u = node[s:e].view(np.uint64)
            mixed = (u ^ (np.uint64(int(h[s]) & (PIVOTS - 1)) << np.uint64(65 - PIVOTS.bit_length()))) * np.uint64(0x9E3779B97F4A7C15)
            lead = s + int(np.argmin(mixed))
            j = np.arange(s, e)
            j = j[(group[j] != group[lead]) & (q * np.minimum(n[j], n[lead]) >= p * np.maximum(n[j], n[lead]))]
            yield made(node, n, odd, times, np.full(len(j), lead), j)

    def all_pairs(h, node, n, odd, times, group):
        # Postings of one group have no pair to look at.
        start, end = _bounds(h)
        rows = np.flatnonzero(np.repeat(np.minimum.reduceat(group, start) != np.maximum.reduceat(group, start), end - start))
        rows = rows[np.lexsort((n[rows], h[rows]))]
        h, node, n, odd, times, group = h[rows], node[rows], n[rows].astype(np.int64), odd[rows], times[rows], group[rows]
        # Each row meets the row d places on, for all postings at once. Rows of a posting stand by size: one that meets a set too large for it is done.
        i = np.arange(len(h))
        for d in range(1, len(h)):
            i = i[i + d < len(h)]
            i = i[(h[i] == h[i + d]) & (p * n[i + d] <= q * n[i])]
            if not len(i):
                return
            other = i[group[i] != group[i + d]]
            yield made(node, n, odd, times, other, other + d)

    met = _by_posting(posted.select("h", "node", "n", "odd", "times", "group"), "a long, b long, need long, times long", with_pivot if pivot else all_pairs)
    if pivot:
        return met.select("a", "b").distinct()
    return met.groupBy("a", "b").agg(F.sum("times").alias("met"), F.max("need").alias("need")).where("met >= need").select("a", "b")


def _verified(pairs: DataFrame, docs: DataFrame, nodes: DataFrame, least: Fraction, shingle: int, seed: int) -> DataFrame:
    """The pairs whose similarity reaches ``least``; the sets are made again, from the texts that the pairs need."""
    pairs = stored(pairs)
    p, q = least.numerator, least.denominator
    wanted = pairs.select("a").union(pairs.select("b")).distinct().withColumnRenamed("a", "node")
    heads = nodes.join(wanted, "node").select("head")
    context = pairs.sparkSession.sparkContext
    ids_held, held = context.broadcast(_bitmap(heads.where("head is not null"))), context.broadcast(_bitmap(wanted))

    def touched(ids, texts):
        out = {"node": [], "found": []}
        known = _marked(ids_held.value, np.array([i or 0 for i in ids], dtype=np.int64)).tolist()
        for i, t, k in zip(ids, texts, known, strict=True):
            if k or i is None:
                x = shingle_set(t, shingle, seed)
                node = _digest(x, seed)
                if _marked(held.value, np.array([node], dtype=np.int64))[0]:
                    out["node"].append(node)
                    out["found"].append(x.astype("<u8").tobytes())
        return out

    made = arrow_map(docs.select("doc_id", "text"), "node long, found binary", touched)
    own = stored(made.groupBy("node").agg(F.first("found").alias("found")))
    both = pairs.join(own.select(F.col("node").alias("a"), F.col("found").alias("x")), "a").join(own.select(F.col("node").alias("b"), F.col("found").alias("y")), "b")

    def rows(a, b, xs, ys):
        keep = []
        for k, (x, y) in enumerate(zip(xs, ys, strict=True)):
            x, y = np.frombuffer(x, dtype="<u8"), np.frombuffer(y, dtype="<u8")
            common = len(np.intersect1d(x, y, assume_unique=True))
            if q * common >= p * (len(x) + len(y) - common):
                keep.append(k)
        return {"a": [a[k] for k in keep], "b": [b[k] for k in keep]}

    return arrow_map(both.select("a", "b", "x", "y"), "a long, b long", rows)


def _near_fingerprints(nodes: DataFrame) -> DataFrame:
    """(a, b), a < b: each node with the least one of its fingerprint, and the least ones of fingerprints that the SimHash index links."""
    lead = stored(nodes.groupBy("fp").agg(F.min("node").alias("lead")))
    same = nodes.join(lead, "fp").where("node <> lead").select(F.col("lead").alias("a"), F.col("node").alias("b"))
    links = fingerprint_links(lead.select("fp")).distinct()
    near = links.join(lead.withColumnRenamed("lead", "x"), F.col("a") == F.col("fp")).drop("fp").join(lead.withColumnRenamed("lead", "y"), F.col("b") == F.col("fp"))
    return same.unionByName(near.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")))


def _groups(docs: DataFrame, shingle: int, least: str, seed: int) -> tuple[DataFrame, DataFrame]:
    """The rows (doc_id, key, node, ..) and (node, component)."""
    bound = Fraction(least)
    if not 0 < bound <= 1:
        raise ValueError("least must be above 0 and at most 1")
    sets = stored(shingle_sets(docs, shingle, bound, seed))
    nodes = stored(sets.groupBy("node").agg(F.min("doc_id").alias("head"), F.max("n").alias("n"), F.max("odd").alias("odd"), F.max("fp").alias("fp")))
    posted = stored(_shared_postings(_postings(sets)).join(nodes.select("node", "n", "odd"), "node").select("h", "node", "n", "odd", "times"))
    verified = lambda pairs: _verified(pairs, docs, nodes, bound, shingle, seed)
    pivots = _pairs(posted.withColumn("group", F.col("node")), bound, pivot=True)
    links = stored(verified(pivots.unionByName(_near_fingerprints(nodes)).distinct()))
    first = components(links).withColumnRenamed("component", "group")
    grouped = posted.join(first, "node", "left").withColumn("group", F.coalesce("group", "node"))
    groups = components(links.unionByName(verified(_pairs(grouped, bound, pivot=False))))
    return sets, nodes.select("node").join(groups, "node", "left").select("node", F.coalesce("component", "node").alias("component"))


def similar_groups(docs: DataFrame, shingle: int = 5, least: str = "0.8", seed: int = 42) -> DataFrame:
    """doc_id and component_id, the smallest doc_id that links of similarity ``least`` or more reach."""
    sets, named = _groups(docs, shingle, least, seed)
    rows = sets.select("doc_id", "node").join(named, "node")
    return rows.join(rows.groupBy("component").agg(F.min("doc_id").alias("component_id")), "component").select("doc_id", "component_id")


def without_similar(docs: DataFrame, shingle: int = 5, least: str = "0.8", seed: int = 42) -> DataFrame:
    """One row of ``docs`` for each group, the one with the smallest doc_id; rows without a doc_id stay."""
    sets, named = _groups(docs, shingle, least, seed)
    return keep_heads(docs, sets.select("doc_id", "key", "node").join(named, "node").select("doc_id", "key", "component"))
