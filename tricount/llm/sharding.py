"""Rendezvous hashing of stable record keys over weighted shards.

Every shard scores every key; the best score wins. A new shard can only win keys for itself, so growing by one
shard moves about 1/(n+1) of the keys and none between old shards. All of it is DataFrame expressions.

Defined results: a null key hashes as the text "null"; a null text has size 8 and the checksum of the empty
text; repeated keys share a shard and get different slots; ties of score go to the smaller shard; an empty
table gives an empty table; other columns of the input are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Slots are numbered within (shard, lane): so many lanes share the work of a shard. The table of lane sizes has
#: at most shards x LANES rows, whatever the input.
LANES = 1024
_M32 = (1 << 32) - 1
_MIX = 73244475


def _mixed(x: Column) -> Column:
    """Two rounds of xor-shift and multiply on 32 bits held in a LONG (products stay below 2^63)."""
    for _ in range(2):
        x = (x.bitwiseXOR(F.shiftrightunsigned(x, 16)) * F.lit(_MIX)).bitwiseAND(F.lit(_M32))
    return x.bitwiseXOR(F.shiftrightunsigned(x, 16))


def key_digest(key: Column) -> Column:
    """32 stable bits of a key: the head of the MD5 of its text, so any engine can repeat it."""
    text = F.coalesce(key.cast("string"), F.lit("null"))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def shard_scores(digest: Column, weights: list[float]) -> list[Column]:
    """One score per shard; larger is better. Equal weights compare integers, others -weight / ln(u)."""
    drawn = [_mixed((digest + F.lit((s + 1) * 2654435761 & _M32)).bitwiseAND(F.lit(_M32))) for s in range(len(weights))]
    if len(set(weights)) == 1:
        return drawn
    return [-F.lit(float(w)) / F.log((x.cast("double") + 0.5) / float(1 << 32)) for x, w in zip(drawn, weights, strict=True)]


def _best(scores: list[Column]) -> Column:
    pick = F.struct(scores[0].alias("score"), F.lit(0).alias("order"))
    rest = [F.struct(x.alias("score"), F.lit(-s).alias("order")) for s, x in enumerate(scores) if s]
    return -(F.greatest(pick, *rest) if rest else pick)["order"]


def assign_shards(df: DataFrame, key: str, shards: int, weights: list[float] | None = None, into: str = "shard") -> DataFrame:
    """``df`` with the shard of each row's key in column ``into``."""
    weights = weights or [1.0] * shards
    if shards < 1 or len(weights) != shards or not all(w > 0 and math.isfinite(w) for w in weights):
        raise ValueError("one positive weight per shard is needed")
    return df.withColumn(into, _best(shard_scores(key_digest(F.col(key)), weights)).cast("int"))


def number_slots(df: DataFrame, group: str, lane: Column, order: list[str]) -> DataFrame:
    """``df`` with a gapless ``slot`` from 0 in each group, by ``lane`` (a small number that spreads rows) and then ``order``.

    Rows are ranked inside lanes and shifted by the sizes of the lanes before, so no group meets in one task.
    """
    laned = df.withColumn("_lane", lane)
    before = Window.partitionBy(group).orderBy("_lane").rowsBetween(Window.unboundedPreceding, -1)
    sizes = laned.groupBy(group, "_lane").agg(F.count(F.lit(1)).alias("_n"))
    starts = sizes.select(group, "_lane", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    within = Window.partitionBy(group, "_lane").orderBy(*order)
    ranked = laned.withColumn("_rank", F.row_number().over(within) - 1)
    return ranked.join(starts, [group, "_lane"]).withColumn("slot", (F.col("_start") + F.col("_rank")).cast("long")).drop("_lane", "_rank", "_start")


def shard_documents(docs: DataFrame, shards: int = 24, weights: list[float] | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard: ``docs`` over ``shards`` shards, and over one more of weight 1."""
    text = F.coalesce(F.col("text"), F.lit(""))
    weights = weights or [1.0] * shards
    rows = docs.select("doc_id", (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    rows = assign_shards(rows, "doc_id", shards, weights)
    rows = assign_shards(rows, "doc_id", shards + 1, [*weights, 1.0], into="grown_shard")
    lane = (_mixed(key_digest(F.col("doc_id")).bitwiseXOR(F.col("text_crc32"))) % LANES).cast("int")
    rows = number_slots(rows, "shard", lane, ["doc_id", "text_crc32", "size"])
    return rows.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")
