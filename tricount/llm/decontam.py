"""Benchmark decontamination by template canonicalisation.

Words are lower-cased and stripped of outer punctuation; numbers, units and names become typed placeholders, so a
question and the same question with other values give the same template. Windows of template words are hashed. The
windows of the documents pass a Bloom filter of the benchmark's windows (a bitmap of fixed size), and those that
remain are hash-joined with the benchmark's windows. For a document and an item, hits on one diagonal (document place
minus item place) are an alignment; it counts if its slots are consistent: a value of the item always stands against
the same value of the document. An item is leaked into a document if the windows that its consistent alignments
cover are at least the wanted share of the item's windows.

Windows with fewer than two plain words say too little and are left out, on both sides. A capitalised word that starts
a sentence may be a name or not: windows that hold one are hashed under both readings. An item without any usable
template window is matched by its literal words.

Defined results: a null or empty text has no window; an item with fewer words than a window is one window of all of
its words and is found as such; items without any word match nothing; repeated rows of one doc_id count as one
document, repeated item_ids as one item; empty tables give empty tables; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from zlib import crc32

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordTable, arrow_map, bitmap

#: Words of a window, and the share of an item's windows that makes a leak.
WINDOW, SHARE = 5, 0.8
#: Bits of the Bloom filter, a power of two: 4 MB whatever the benchmark's size.
BITS = 1 << 25
#: Lanes of the join of windows.
SALT = 16

# Words that are units beside a number, and signs of currency and share.
UNITS = frozenset("mm cm m km in inch inches ft feet yd mile miles mg g kg t oz lb lbs ml l cl gal s sec secs second seconds min mins minute minutes h hr hrs hour hours day days week weeks month months year years hz khz mhz ghz w kw mw v kv a ma j kj cal kcal k c f pa kpa bar psi mph kmh kph eur usd gbp euro euros dollar dollars pound pounds cent cents percent degree degrees".split())
SIGNS = "$€£¥%°"

_NUMBER = re.compile(rf"([{SIGNS}]?)([+-]?\d[\d.,:/]*)([^\W\d_]*|[{SIGNS}])$")
_EDGE = re.compile(r"^[^\w$€£¥+-]+|[^\w%°$€£]+$")
_ENDS = (".", "!", "?", ":", "…")
_PLAIN, _NAME, _NUM, _UNIT = range(4)
#: Readings of a text.
WORD, NAME, LITERAL = range(3)


def canonical(word: str) -> tuple[str, str, int, bool]:
    """(template word, slot value, kind, ends a sentence) of a chunk without white space; template word "" if nothing is left.

    A capitalised word is a name here; at the start of a sentence the caller takes its lower-cased form.
    """
    bare = word.rstrip(".,;!?")
    if bare.isalpha():  # most words
        ends, m = word[len(bare) :].endswith(_ENDS), None
    else:
        ends = word.rstrip("\"')]}»”’").endswith(_ENDS)
        bare = _EDGE.sub("", word)
        if not any(map(str.isalnum, bare)):
            return "", "", _PLAIN, ends
        m = _NUMBER.match(bare)
    if m and (not m[3] or m[3].lower() in UNITS or m[3] in SIGNS):
        return "<unit>" * bool(m[1]) + "<num>" + "<unit>" * bool(m[3]), bare.rstrip(".,:/").lower(), _NUM, ends
    low = bare.lower()
    if bare[0].isupper() and len(bare) > 1 and not bare.isupper():
        return "<name>", low, _NAME, ends
    if low in UNITS:
        return low, low, _UNIT, ends
    return low, "", _PLAIN, ends


class Templates:
    """Template words of texts by way of a table of known chunks: (code inside a sentence, code at its start, flags, code of the word as it stands)."""

    def __init__(self):
        self.known = WordTable(self._number, most=300_000)
        self.codes = np.zeros((1 << 12, 4), dtype=np.int64)
        self.used, self.new = 0, []

    def _number(self, word: str) -> int:
        """The row of ``codes`` that a new chunk will get."""
        bare = word.rstrip(".,;!?")
        if bare.islower() and bare.isalpha() and bare not in UNITS:  # a plain word, as most are
            raw = bare.encode("utf-8", "replace")
            code = crc32(raw) or 1
            self.new.append((code, code, 8 * word[len(bare) :].endswith(_ENDS), crc32(raw, _LITERAL)))
        else:
            self.new.append(self._codes(word))
        return self.used + len(self.new) - 1

    def _rows(self, chunks: list[str]) -> np.ndarray:
        """The codes of a text's chunks."""
        if self.used > self.known.most:
            self.known.clear()
            self.used = 0
        rows = np.fromiter(map(self.known.__getitem__, chunks), dtype=np.int64, count=len(chunks))
        if self.new:
            end = self.used + len(self.new)
            if end > len(self.codes):
                self.codes = np.concatenate([self.codes, np.zeros((max(end, len(self.codes)), 4), dtype=np.int64)])
            self.codes[self.used : end] = self.new
            self.used = end
            self.new.clear()
        return self.codes[rows]

    @staticmethod
    def _codes(word: str) -> tuple[int, int, int, int]:
        shown, value, kind, ends = canonical(word)
        if not shown:
            return 0, 0, 4 | 8 * (ends or word == "\n"), 0
        inside = crc32(shown.encode("utf-8", "replace")) or 1
        start = crc32(value.encode("utf-8", "replace")) or 1 if kind == _NAME else inside
        return inside, start, kind | 8 * ends, crc32((value or shown).encode("utf-8", "replace"), _LITERAL)

    def of(self, text: str | None) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Chunks that give template words, their codes, and their kinds; a capitalised word that starts a sentence is a plain word."""
        chunks, place, readings = self.readings(text)
        return [chunks[p] for p in place.tolist()], *readings[WORD]

    def readings(self, text: str | None) -> tuple[list[str], np.ndarray, list[tuple[np.ndarray, np.ndarray]]]:
        """The chunks, the places of those that give template words, and their codes and kinds by reading: WORD, NAME (a capitalised word that starts a sentence is a name) and LITERAL (no placeholders)."""
        chunks = (text or "").replace("\t", " ").replace("\r", "\n").replace("\n", " \n ").split(" ")
        got = self._rows(chunks)
        ends = (got[:, 2] & 8) > 0
        words = (got[:, 2] & 4) == 0
        words &= got[:, 0] != 0
        # A word starts a sentence if a sentence ended since the word before it.
        ended = np.cumsum(ends)
        place = np.flatnonzero(words)
        first = np.ones(len(place), dtype=bool)
        if len(place) > 1:
            first[1:] = (ended[place[1:] - 1] - (ended[place[:-1]] - ends[place[:-1]])) > 0
        kind = got[place, 2] & 3
        code = np.where(first, got[place, 1], got[place, 0])
        # A word of measure is a unit only beside a number.
        beside = np.zeros(len(place), dtype=bool)
        if len(place) > 1:
            beside[1:] |= kind[:-1] == _NUM
        unit = (kind == _UNIT) & beside
        named = np.where(unit, _UNIT_CODE, got[place, 0])
        code = np.where(unit, _UNIT_CODE, code)
        kind = np.where((kind == _UNIT) & ~unit, _PLAIN, kind)
        plain = np.where((kind == _NAME) & first, _PLAIN, kind)
        return chunks, place, [(code, plain), (named, kind), (got[place, 3], np.zeros(len(place), dtype=np.int64))]


_UNIT_CODE = crc32(b"<unit>")
#: Literal words are hashed behind a sign of their own.
_LITERAL = crc32(b"=")
_M = np.uint64(0x9E3779B97F4A7C15)


def windows(code: np.ndarray, kind: np.ndarray, width: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """(places, hashes) of the windows with at least two plain words; a shorter text is one window."""
    if not len(code):
        return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
    width = min(width, len(code))
    n = len(code) - width + 1
    h = np.full(n, width, dtype=np.uint64)
    plain = np.zeros(n, dtype=np.int64)
    with np.errstate(over="ignore"):
        for j in range(width):
            h = (h ^ code[j : j + n].astype(np.uint64)) * _M
            h ^= h >> np.uint64(29)
            plain += kind[j : j + n] == _PLAIN
    keep = np.flatnonzero(plain >= min(2, width))
    return keep, h[keep].view(np.int64)


def _read_windows(readings: list[tuple[np.ndarray, np.ndarray]], width: int, literal: bool) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(reading, places, hashes): windows of template words; those that hold a sentence's capitalised first word also with that word as a name; if asked for, of literal words."""
    code, kind = readings[WORD]
    yield WORD, *windows(code, kind, width)
    other, named = readings[NAME]
    changed = np.concatenate([[0], np.cumsum(kind != named)])
    if changed[-1]:
        places, hashes = windows(other, named, width)
        held = changed[np.minimum(places + width, len(code))] > changed[places]
        yield NAME, places[held], hashes[held]
    if literal:
        yield LITERAL, *windows(*readings[LITERAL], width)


def _slots(chunks: list[str], place: np.ndarray, kind: np.ndarray, at: int, width: int) -> list[str]:
    """The values of a window's slots, by place in the window."""
    words = [chunks[p] for p in place[at : at + width].tolist()]
    return [f"{j}:{canonical(w)[1] or w.lower()}" for j, w in enumerate(words) if kind[at + j] != _PLAIN]


def _bits(h: np.ndarray) -> np.ndarray:
    """Two places in the filter for each hash."""
    u = h.view(np.uint64)
    return np.stack([u & np.uint64(BITS - 1), (u >> np.uint64(32)) & np.uint64(BITS - 1)]).astype(np.int64)


def _passing(bits: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Which hashes have both of their places marked; few pass the first, so the second is looked up for those only."""
    u = h.view(np.uint64)
    for shift in (np.uint64(0), np.uint64(32)):
        at = ((u >> shift) & np.uint64(BITS - 1)).view(np.int64)
        marked = np.flatnonzero(bits[at >> 3] >> (at & 7).astype(np.uint8) & 1)
        left, u = (marked, u[marked]) if not shift else (left[marked], u)
    return left


_WINDOW_DDL = "id long, place int, hash long, width int, reading int, slots array<string>"


def benchmark_windows(benchmark: DataFrame, width: int = WINDOW) -> DataFrame:
    """item_id, place, hash, width, reading and slots of all windows of the items."""

    def rows(templates, ids, texts):
        out = {k: [] for k in ("id", "place", "hash", "width", "reading", "slots")}
        for item, text in zip(ids, texts, strict=True):
            chunks, words, readings = templates.readings(text)
            own = min(width, len(words))
            literal = not len(windows(*readings[WORD], width)[0])  # no window says enough: the words as they stand
            for reading, places, hashes in _read_windows(readings, width, literal):
                for at, h in zip(places.tolist(), hashes.tolist(), strict=True):
                    for k, v in zip(out, (item, at, h, own, reading, _slots(chunks, words, readings[reading][1], at, own)), strict=True):
                        out[k].append(v)
        return out

    return arrow_map(benchmark.select("item_id", "text"), _WINDOW_DDL, rows, start=Templates).withColumnRenamed("id", "item_id").dropDuplicates(["item_id", "place", "reading"])


def document_hits(docs: DataFrame, filter_bits: np.ndarray, widths: list[int], literal: bool = False) -> DataFrame:
    """id, place, hash, width, reading and slots of the windows of the documents that pass the filter; texts stay where they are."""
    held = docs.sparkSession.sparkContext.broadcast(filter_bits)

    def rows(templates, ids, texts):
        out = {k: [] for k in ("id", "place", "hash", "width", "reading", "slots")}
        bits = held.value
        for doc, text in zip(ids, texts, strict=True):
            chunks, words, readings = templates.readings(text)
            for w in (w for w in widths if w <= len(words)):
                for reading, places, hashes in _read_windows(readings, w, literal):
                    hit = _passing(bits, hashes)
                    for at, h in zip(places[hit].tolist(), hashes[hit].tolist(), strict=True):
                        for k, v in zip(out, (doc, at, h, w, reading, _slots(chunks, words, readings[reading][1], at, w)), strict=True):
                            out[k].append(v)
        return out

    return arrow_map(docs.select("doc_id", "text"), _WINDOW_DDL, rows, start=Templates)


def leaks(docs: DataFrame, benchmark: DataFrame, width: int = WINDOW, share: float = SHARE) -> DataFrame:
    """doc_id, item_id, n_windows (of the item), n_matched and share for every leaked item of every document."""
    items = benchmark.select("item_id", "text").where("item_id is not null")
    grams = benchmark_windows(items, width)
    sizes = grams.groupBy("item_id").agg(F.countDistinct("place").alias("n_windows"))

    bits = bitmap(grams.select("hash"), lambda h: _bits(h).ravel(), BITS)
    widths = sorted(r[0] for r in grams.select("width").distinct().collect())  # at most ``width`` values
    literal = bool(grams.where(F.col("reading") == LITERAL).head(1))
    hits = document_hits(docs, bits, widths, literal)

    # The join is on the hash. A window may stand in a third of all documents: their side is dealt to SALT lanes by
    # document, and the benchmark's side, far smaller, is in every lane.
    lane = F.pmod(F.xxhash64("doc_id", "at"), F.lit(SALT)).cast("int")
    held = grams.select("item_id", "place", "hash", "width", F.col("reading").alias("item_reading"), F.col("slots").alias("item_slots"), F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))).alias("lane"))
    met = hits.withColumnRenamed("id", "doc_id").withColumnRenamed("place", "at").withColumn("lane", lane).join(held, ["hash", "width", "lane"])
    met = met.where((F.col("reading") == LITERAL) == (F.col("item_reading") == LITERAL))
    met = met.withColumn("diagonal", F.col("at") - F.col("place"))
    # Slots of one alignment: every value of the item against the values of the document.
    value = lambda slot: F.regexp_replace(slot, "^[0-9]+:", "")
    pairs = F.zip_with("item_slots", "slots", lambda i, d: F.struct(value(i).alias("item"), value(d).alias("doc")))
    met = met.withColumn("pair", F.when(F.size("slots") == F.size("item_slots"), pairs))
    # Windows in which a first word is read as a name count if their slots agree with all others; else those without count alone.
    sure = (F.col("reading") != NAME) & (F.col("item_reading") != NAME)

    def gathered(name, seen):
        pair = F.when(seen, F.col("pair"))
        return [F.collect_set(F.when(seen, F.col("place"))).alias(f"places{name}"), F.array_distinct(F.flatten(F.collect_set(pair))).alias(f"pairs{name}"), F.coalesce(F.bool_and(F.when(seen, F.col("pair").isNotNull())), F.lit(True)).alias(f"whole{name}")]

    aligned = met.groupBy("doc_id", "item_id", "diagonal").agg(*gathered("", F.lit(True)), *gathered("_sure", sure))
    fine = lambda name: F.col(f"whole{name}") & (F.size(F.array_distinct(F.transform(f"pairs{name}", lambda p: p["item"]))) == F.size(f"pairs{name}"))
    chosen = aligned.withColumn("places", F.when(fine(""), F.col("places")).when(fine("_sure"), F.col("places_sure"))).where("places is not null")
    found = chosen.groupBy("doc_id", "item_id").agg(F.size(F.array_distinct(F.flatten(F.collect_list("places")))).alias("n_matched"))
    out = found.join(sizes, "item_id").withColumn("share", F.col("n_matched") / F.col("n_windows")).where(F.col("share") >= share)
    return out.select("doc_id", "item_id", F.col("n_windows").cast("int").alias("n_windows"), "n_matched", "share")


def without_leaks(docs: DataFrame, benchmark: DataFrame, width: int = WINDOW, share: float = SHARE) -> DataFrame:
    """The rows of ``docs`` into which no item leaked; rows with a null doc_id stay."""
    found = leaks(docs, benchmark, width, share).select("doc_id").distinct()
    return docs.join(found, "doc_id", "left_anti").select(docs.columns)
