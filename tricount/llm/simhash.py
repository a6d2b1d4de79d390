"""SimHash near-duplicates through a byte-position inverted index with count filtering.

A fingerprint has eight bytes. Fingerprints that differ in at most d bits share at least 8 - d of their bytes at the
same positions: the guaranteed minimum of matches. With eight postings of one byte each, every posting would hold a
256th of all fingerprints and the tallies would grow with the square of their number. The index therefore posts bytes
four at a time: the positions form four fields of two bytes, of which at least two are whole if two bytes differ, so each
*distinct* fingerprint is posted under the bytes of every two fields (six postings). For the pairs of a posting the
shared positional bytes are tallied over all eight positions, pairs that reach the minimum are retained, and their
bits are compared.

A posting of more than TALLY fingerprints is split by further positions until the minimum is reached: what meets there
differs only in d bytes, so a posting holds at most 256^d fingerprints whatever the data, and those within d bits are
found by flipping bits of those bytes; no pair is formed that is not a link.

Equal fingerprints (copies) are one node; components run over distinct fingerprints.

Defined results: null and empty texts have fingerprint zero and link like any other; repeated rows are copies; rows that
repeat a doc_id with other texts are judged by their own texts; an empty table gives an empty table; other columns
are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, schema_of, stored
from .components import components

#: Shingles that are hashed before their bits are counted; bounds the memory for a very long text.
CHUNK = 1 << 15
BYTES = 8
#: Fingerprints of a posting whose pairs are tallied; larger ones are split.
TALLY = 256


def shingle_hashes(text: str | None, shingle: int, seed: int) -> Iterator[np.ndarray]:
    """The hashes of the text's word shingles in order, CHUNK at a time; a shorter text is one shingle."""
    from xxhash import xxh64_intdigest

    words = (text or "").encode("utf-8").lower().split()
    if not words:
        return
    joined = memoryview(b" ".join(words))
    starts = np.zeros(len(words) + 1, dtype=np.int64)
    np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1, out=starts[1:])
    k = min(shingle, len(words))
    lo, hi = starts[: len(words) - k + 1].tolist(), (starts[k:] - 1).tolist()
    for at in range(0, len(lo), CHUNK):
        yield np.array([xxh64_intdigest(joined[a:b], seed) for a, b in zip(lo[at : at + CHUNK], hi[at : at + CHUNK], strict=True)], dtype="<u8")


def fingerprint_of_hashes(parts: Iterator[np.ndarray]) -> int:
    """A bit is set if more than half of the hashes set it."""
    total, n = np.zeros(64, dtype=np.int64), 0
    for part in parts:
        bits = np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        total += bits.sum(axis=0, dtype=np.int64)
        n += len(part)
    return sum(1 << j for j in np.flatnonzero(2 * total > n).tolist())


def fingerprint_of(text: str | None, shingle: int = 3, seed: int = 42) -> int:
    """64-bit SimHash of the text's word shingles, repeats included."""
    return fingerprint_of_hashes(shingle_hashes(text, shingle, seed))


def fingerprints(docs: DataFrame, shingle: int = 3, seed: int = 42) -> DataFrame:
    """doc_id and its fingerprint as a signed LONG."""

    def rows(ids, texts):
        made = np.array([fingerprint_of(t, shingle, seed) for t in texts], dtype=np.uint64)
        return {"doc_id": ids, "fp": made.view(np.int64)}

    return arrow_map(docs.select("doc_id", "text"), "doc_id long, fp long", rows)


def _flips(free: tuple[int, ...], bits: int) -> np.ndarray:
    """All masks of 1 to ``bits`` set bits inside the free byte positions."""
    places = [8 * p + j for p in free for j in range(8)]
    return np.array([sum(1 << j for j in c) for n in range(1, bits + 1) for c in combinations(places, n)], dtype=np.uint64)


def _links_of(fps: np.ndarray, flips: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of the posting's fingerprints (sorted, distinct) that one of the masks turns into each other."""
    left, right = [], []
    for at in range(0, len(fps), 4096):
        part = fps[at : at + 4096]
        other = part[:, None] ^ flips[None, :]
        where = np.minimum(np.searchsorted(fps, other), len(fps) - 1)
        hit = (fps[where] == other) & (other > part[:, None])
        i, j = np.nonzero(hit)
        left.append(part[i])
        right.append(other[i, j])
    return np.concatenate(left), np.concatenate(right)


def shared_bytes(x: np.ndarray) -> np.ndarray:
    """How many positional bytes two fingerprints share, from their exclusive or."""
    return (np.ascontiguousarray(x).view(np.uint8).reshape(-1, BYTES) == 0).sum(axis=1)


def _kept(free: tuple[int, ...]) -> int:
    """The mask of all byte positions but ``free``, as a signed LONG."""
    mask = ~sum(255 << 8 * p for p in free) & (1 << 64) - 1
    return mask - (1 << 64) if mask >> 63 else mask


def _posted(rows: DataFrame, frees: list[tuple[int, ...]], numbers: list[int] | None = None) -> DataFrame:
    """fp, choice, held: each fingerprint under the bytes it holds outside each of ``frees``."""
    keys = [F.struct(F.lit(n).alias("choice"), F.col("fp").bitwiseAND(F.lit(_kept(f)).cast("long")).alias("held")) for n, f in zip(numbers or range(len(frees)), frees, strict=True)]
    return rows.select("fp", F.explode(F.array(*keys)).alias("k")).select("fp", "k.choice", "k.held")


def _in_postings(posted: DataFrame, each) -> DataFrame:
    """(a, b) of what ``each`` (choice, sorted fingerprints) finds in the postings of three fingerprints or more; ``each`` of pairs in one go."""
    schema = schema_of("a long, b long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by choice and held bytes; the last posting of a batch may go on in the next one."""
        none = np.empty(0, dtype=np.uint64)
        kept = (none.astype(np.int64), none.view(np.int64), none)

        def found(choice, held, fp):
            if not len(fp):
                return
            edge = np.flatnonzero((choice[1:] != choice[:-1]) | (held[1:] != held[:-1])) + 1
            start = np.concatenate([[0], edge])
            end = np.concatenate([edge, [len(fp)]])
            size = end - start
            two = start[size == 2]
            pairs = [each(None, np.stack([np.minimum(fp[two], fp[two + 1]), np.maximum(fp[two], fp[two + 1])]))]
            pairs += [each(int(choice[s]), np.sort(fp[s:e])) for s, e in zip(start[size > 2].tolist(), end[size > 2].tolist(), strict=True)]
            a, b = (np.concatenate(x) for x in zip(*pairs, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

        for batch in batches:
            choice, held, fp = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(3))
            choice, held, fp = (np.concatenate(x) for x in zip(kept, (choice.astype(np.int64), held, fp.view(np.uint64)), strict=True))
            if not len(fp):
                continue
            last = (choice == choice[-1]) & (held == held[-1])
            whole = int(np.argmax(last))
            yield from found(choice[:whole], held[:whole], fp[:whole])
            kept = (choice[whole:], held[whole:], fp[whole:])
        yield from found(*kept)

    dealt = posted.select("choice", "held", "fp").repartition("choice", "held").sortWithinPartitions("choice", "held")
    return dealt.mapInArrow(run, schema)


def fingerprint_links(distinct: DataFrame, bits: int = 2) -> DataFrame:
    """(a, b) of distinct fingerprints ``fp`` that differ in 1 to ``bits`` bits. A link may come more than once."""
    if not 1 <= bits <= 2:
        raise ValueError("postings are bounded for one or two bits")
    least = BYTES - bits
    fields = [(p, p + 1) for p in range(0, BYTES, 2)]
    frees = [a + b for a, b in combinations(fields, 2)]
    posted = stored(_posted(distinct, frees))
    large = stored(posted.groupBy("choice", "held").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > TALLY).select("choice", "held"))

    def tallied(choice, fps):
        """Pairs that share the least number of bytes, then those that differ in few bits; a posting of two comes as columns."""
        if choice is None:
            one, two = fps
        else:
            i, j = np.triu_indices(len(fps), 1)
            one, two = fps[i], fps[j]
        enough = shared_bytes(one ^ two) >= least
        one, two = one[enough], two[enough]
        near = np.bitwise_count(one ^ two) <= bits
        return one[near], two[near]

    small = _in_postings(posted.join(large, ["choice", "held"], "left_anti"), tallied)
    # Large postings, split by the positions that are left: fps of one posting share the least number of bytes.
    whole = posted.join(large, ["choice", "held"], "left_semi")
    narrow = list(combinations(range(BYTES), bits))
    masks = [_flips(free, bits) for free in narrow]
    split = None
    for n, free in enumerate(frees):
        of = [k for k, f in enumerate(narrow) if set(f) <= set(free)]
        part = _posted(whole.where(F.col("choice") == n), [narrow[k] for k in of], of)
        split = part if split is None else split.unionByName(part)

    def flipped(choice, fps):
        if choice is None:
            near = np.bitwise_count(fps[0] ^ fps[1]) <= bits
            return fps[0][near], fps[1][near]
        return _links_of(fps, masks[choice])

    return small.unionByName(_in_postings(split.distinct(), flipped))


def near_duplicates(docs: DataFrame, shingle: int = 3, bits: int = 2, seed: int = 42) -> DataFrame:
    """doc_id, fingerprint (16 hexadecimal digits) and component_id, the smallest doc_id that links reach."""
    prints = stored(fingerprints(docs, shingle, seed))
    heads = stored(prints.groupBy("fp").agg(F.min("doc_id").alias("head")))
    groups = components(fingerprint_links(heads.select("fp"), bits))
    named = heads.join(groups.withColumnRenamed("node", "fp"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    least = named.groupBy("component").agg(F.min("head").alias("component_id"))
    return (
        prints.join(named.join(least, "component").select("fp", "component_id"), "fp")
        .select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
    )


def with_text_key(docs: DataFrame) -> DataFrame:
    """doc_id, text and key, a digest of the text: what tells rows of one doc_id apart."""
    return docs.select("doc_id", "text", F.xxhash64("text").alias("key"))


def keep_heads(docs: DataFrame, groups: DataFrame) -> DataFrame:
    """One row of ``docs`` for each component of ``groups`` (doc_id, key, component): the one with the smallest doc_id, then key.

    Rows that are equal in doc_id and text are copies: the one whose other columns have the least digest stays. Rows without a doc_id stay.
    """
    heads = groups.where("doc_id is not null").groupBy("component").agg(F.min(F.struct("doc_id", "key")).alias("head")).select("head.doc_id", F.col("head.key").alias("_key"))
    keyed = docs.where("doc_id is not null").withColumn("_key", F.xxhash64("text"))
    kept = keyed.join(heads, ["doc_id", "_key"], "left_semi")
    again = keyed.groupBy("doc_id", "_key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("doc_id", "_key")
    single = kept.join(again, ["doc_id", "_key"], "left_anti").select(docs.columns)
    # Repeats are settled by an aggregate that combines before the shuffle, however many there are.
    row = F.struct(*(F.col(f"`{c}`") for c in docs.columns))
    double = kept.join(again, ["doc_id", "_key"], "left_semi").groupBy("doc_id", "_key").agg(F.min_by(row, F.xxhash64(row)).alias("row")).select("row.*")
    return single.unionByName(double).unionByName(docs.where("doc_id is null"))


def without_near_duplicates(docs: DataFrame, shingle: int = 3, bits: int = 2, seed: int = 42) -> DataFrame:
    """One row of ``docs`` for each group of texts whose fingerprints link."""
    keyed = with_text_key(docs)

    def rows(ids, texts, keys):
        made = np.array([fingerprint_of(t, shingle, seed) for t in texts], dtype=np.uint64)
        return {"doc_id": ids, "key": keys, "fp": made.view(np.int64)}

    prints = stored(arrow_map(keyed, "doc_id long, key long, fp long", rows))
    groups = components(fingerprint_links(prints.select("fp").distinct(), bits))
    named = prints.join(groups.withColumnRenamed("node", "fp"), "fp", "left").select("doc_id", "key", F.coalesce("component", "fp").alias("component"))
    return keep_heads(docs, named)
