"""Minimum-bin-slack packing of tokenised documents into sequences of fixed length.

Per bin, a bitset over the lengths still available tells which fills are reachable; the fullest one is taken. Each bin
starts with the longest length left (the usual form of the heuristic): a plain fullest fill uses up short lengths early and
leaves long ones to bins of their own, and needs no fewer bins (tests/llm compares both). A
combination stays the fullest while its lengths last, so it is repeated until one of them runs out: the number of
steps depends on the number of different lengths (at most the capacity), not on the number of documents.

Only the histogram of lengths (at most one row per length) reaches the driver, and only the plan, bounded by the
capacity as well, is broadcast. Everything about single documents stays distributed.

Defined results: a null text is empty and gives the end mark alone; repeated rows are packed as often as they
occur; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from bisect import bisect_right
from itertools import chain

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import WordTable, arrow_map, stored

#: Pieces of one length are ranked within so many lanes, so that a common length doesn't meet in one task.
LANES = 256
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


# Letters, digits and white space of Latin-1, as the tokenizer's expressions class them.
_LETTER, _DIGIT, _WHITE = "a-zA-Z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\xff", "0-9\xb2\xb3\xb9\xbc-\xbe", " \t-\r\x85\xa0"
_UNIT = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{_LETTER}]+|[{_DIGIT}]|[^{_WHITE}{_LETTER}{_DIGIT}]+")
_OTHER = re.compile("[^\x00-\xff]|<\\|")


class _Ids:
    """Token ids of whole texts as little-endian 32-bit bytes.

    The tokenizer drops white space, lower-cases, and encodes each run of letters, digit and run of other signs by
    itself. Texts of Latin-1 without special marks are split that way here, so that its model is asked once for each
    different unit; other texts go through the whole tokenizer, chunk by chunk between blanks.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.units = WordTable(self._unit, most=600_000)
        self.chunks = WordTable(self._chunk, most=100_000)
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        hidden = iter(range(256, 512))
        self.byte = {b: chr(b if b in shown else next(hidden)) for b in range(256)}  # a sign for each byte, as byte-level models have it

    def _unit(self, unit: str) -> bytes:
        signs = unit if unit.isascii() and unit.isprintable() else "".join(map(self.byte.__getitem__, unit.encode()))
        return b"".join([t.id.to_bytes(4, "little") for t in self.model.tokenize(signs)])

    def _chunk(self, chunk: str) -> bytes:
        if not _OTHER.search(chunk):
            return b"".join(map(self.units.__getitem__, _UNIT.findall(chunk.lower())))
        return np.asarray(self.tokenizer.encode(chunk, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def of(self, text: str | None, end: int) -> bytes:
        text = text or ""
        self.units.trim()
        self.chunks.trim()
        if _OTHER.search(text):
            parts = map(self.chunks.__getitem__, text.replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" "))
        else:
            parts = map(self.units.__getitem__, _UNIT.findall(text.lower()))
        return b"".join(chain(parts, (end.to_bytes(4, "little"),)))


def token_pieces(docs: DataFrame, tokenizer: str, capacity: int = 4096, end: int = 1, with_ids: bool = False) -> DataFrame:
    """One row per piece of at most ``capacity`` ids; only longer documents are cut. with_ids adds the ids as bytes."""
    step = 4 * capacity

    def pieces(coder, ids, texts):
        out = {k: [] for k in ("doc_id", "piece", "start", "length", "ids_crc32", "ids")}
        for doc, text in zip(ids, texts, strict=True):
            data = coder.of(text, end)
            for k, at in enumerate(range(0, len(data), step)):
                part = data[at : at + step]
                out["doc_id"].append(doc)
                out["piece"].append(k)
                out["start"].append(at // 4)
                out["length"].append(len(part) // 4)
                out["ids_crc32"].append(zlib.crc32(part))
                out["ids"].append(part)
        return out

    return arrow_map(docs.select("doc_id", "text"), PIECES + ", ids binary" * with_ids, pieces, start=lambda: _Ids(tokenizer))


def fullest(counts: dict[int, int], room: int) -> list[int]:
    """Lengths (each at most as often as counted) whose sum comes closest to ``room`` from below; longer lengths are tried first.

    Bit s of a state says that sum s is reachable with the lengths so far. A count c is split into 1, 2, 4, .. copies.
    """
    items: list[tuple[int, int]] = []
    states, reach, mask, goal = [], 1, (1 << (room + 1)) - 1, 1 << room
    for length in sorted((x for x, c in counts.items() if c > 0 and x <= room), reverse=True):
        left, copies = min(counts[length], room // length), 1
        while left > 0:
            take = min(copies, left)
            states.append(reach)
            items.append((length, take))
            reach |= (reach << (length * take)) & mask
            left -= take
            copies *= 2
        if reach & goal:
            break
    fill = reach.bit_length() - 1
    chosen: list[int] = []
    for (length, take), before in zip(reversed(items), reversed(states), strict=True):
        if not before >> fill & 1:
            chosen += [length] * take
            fill -= length * take
    return chosen


def plan_bins(counts: dict[int, int], capacity: int) -> list[tuple[list[int], int]]:
    """(lengths of a bin, number of such bins) for a histogram of lengths; each bin holds the longest length left, then the fullest rest."""
    left = {x: c for x, c in counts.items() if c > 0}
    plan = []
    while left:
        first = max(left)
        left[first] -= 1
        rest = fullest(left, capacity - first)
        left[first] += 1
        pattern = sorted([first, *rest], reverse=True)
        need = {x: pattern.count(x) for x in set(pattern)}
        times = min(left[x] // n for x, n in need.items())
        plan.append((pattern, times))
        for x, n in need.items():
            left[x] -= n * times
            if not left[x]:
                del left[x]
    return plan


class _Places:
    """Where the rank-th piece of a length goes: ranks are dealt to the runs of equal bins in the order of the plan."""

    def __init__(self, plan: list[tuple[list[int], int]]):
        self.runs: dict[int, tuple[list[int], list[tuple[int, int, int]]]] = {}
        used: dict[int, int] = {}
        base = 0
        for pattern, times in plan:
            at = 0
            for length in dict.fromkeys(pattern):
                each = pattern.count(length)
                starts, places = self.runs.setdefault(length, ([], []))
                starts.append(used.get(length, 0))
                places.append((base, each, at))
                used[length] = used.get(length, 0) + each * times
                at += each * length
            base += times

    def of(self, length: int, rank: int) -> tuple[int, int]:
        starts, places = self.runs[length]
        k = bisect_right(starts, rank) - 1
        base, each, at = places[k]
        turn, place = divmod(rank - starts[k], each)
        return base + turn, at + place * length


def pack(pieces: DataFrame, capacity: int = 4096) -> DataFrame:
    """``pieces`` (stored, with length and doc_id, piece) with sequence_id and offset of each."""
    spark = pieces.sparkSession
    laned = pieces.withColumn("_lane", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(LANES)).cast("int"))
    sizes = laned.groupBy("length", "_lane").agg(F.count(F.lit(1)).alias("_n"))
    counts = {r[0]: r[1] for r in sizes.groupBy("length").agg(F.sum("_n")).collect()}  # at most `capacity` rows
    if any(x > capacity for x in counts):
        raise ValueError("a piece is longer than the capacity")
    before = Window.partitionBy("length").orderBy("_lane").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("length", "_lane", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    within = Window.partitionBy("length", "_lane").orderBy("doc_id", "piece", "ids_crc32")
    ranked = laned.withColumn("_rank", F.row_number().over(within) - 1).join(starts, ["length", "_lane"]).withColumn("_rank", F.col("_rank") + F.col("_start"))
    places = spark.sparkContext.broadcast(_Places(plan_bins(counts, capacity)))

    def put(doc_id, piece, start, length, ids_crc32, rank):
        where = [places.value.of(x, r) for x, r in zip(length, rank, strict=True)]
        return {"doc_id": doc_id, "piece": piece, "start": start, "length": length, "ids_crc32": ids_crc32, "sequence_id": [w[0] for w in where], "offset": [w[1] for w in where]}

    return arrow_map(ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "_rank"), PIECES + ", sequence_id long, offset long", put)


def pack_documents(docs: DataFrame, tokenizer: str, capacity: int = 4096, end: int = 1) -> DataFrame:
    """Tokenise, cut and pack ``docs``: one row per piece with its place."""
    return pack(stored(token_pieces(docs, tokenizer, capacity, end)), capacity)
