"""Networks over the given tables; each function returns canonical edges on dense ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import remove, stored
from ..sources import table
from . import packed
from .graph import canonicalize, held, number, relabel

#: Offsets that keep the kinds of nodes apart in one id space.
PART, SUPPLIER = 1_000_000, 2_000_000


def _together(groups: DataFrame, by: list[str], member: str) -> DataFrame:
    """Pairs of distinct members of one group; groups are small (lines of an order, users of a minute). Each row moves once, to its group."""
    return _paired(_lists(groups, by, member))


def _lists(groups: DataFrame, by: list[str], member: str) -> DataFrame:
    return groups.select(*by, member).dropna().repartition(*by).groupBy(*by).agg(F.sort_array(F.collect_set(member)).alias("m")).select("m")


def _paired(g: DataFrame) -> DataFrame:
    first = g.select("m", F.posexplode("m").alias("i", "src"))
    return first.select("src", F.explode(F.slice("m", F.col("i") + 2, F.size("m"))).alias("dst")).distinct()


def _together_dense(groups: DataFrame, by: list[str], member: str) -> DataFrame:
    """The same of groups that may link a large share of all pairs of members: then the lists of groups move, not the pairs."""
    g, path = stored(_lists(groups, by, member).where("size(m) > 1"))
    members = held(number(g.select(F.explode("m").alias("key")).distinct(), ["key"]), "key", "id")
    pairs = None if members is None else packed.pairs(g, members.column("key").combine_chunks())
    if pairs is None:
        return _paired(g)
    remove(groups.sparkSession, [path])
    return pairs


def _orders_lines(spark: SparkSession, folder: str) -> DataFrame:
    lines = table(spark, folder, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    return lines.join(table(spark, folder, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")


def part(spark: SparkSession, folder: str) -> DataFrame:
    """Parts in one order."""
    return relabel(_together(table(spark, folder, "lineitem"), ["l_orderkey"], "l_partkey"))


def supp(spark: SparkSession, folder: str) -> DataFrame:
    """Suppliers in one order."""
    return relabel(_together(table(spark, folder, "lineitem"), ["l_orderkey"], "l_suppkey"))


def cust(spark: SparkSession, folder: str) -> DataFrame:
    """Customers who bought one part from one supplier."""
    return relabel(_together(_orders_lines(spark, folder), ["l_partkey", "l_suppkey"], "o_custkey"))


def star(spark: SparkSession, folder: str) -> DataFrame:
    """Customer-part, customer-supplier and part-supplier links."""
    c, p, s = F.col("o_custkey"), F.col("l_partkey") + PART, F.col("l_suppkey") + SUPPLIER
    links = F.array(F.struct(c.alias("src"), p.alias("dst")), F.struct(c.alias("src"), s.alias("dst")), F.struct(p.alias("src"), s.alias("dst")))
    # Many parts reach the numbers of suppliers, so a link can come in both directions, or as a loop.
    return relabel(canonicalize(_orders_lines(spark, folder).select(F.explode(links).alias("e")).select("e.src", "e.dst")))


def bip(spark: SparkSession, folder: str) -> DataFrame:
    """Customer-part links only."""
    return relabel(canonicalize(_orders_lines(spark, folder).select(F.col("o_custkey").alias("src"), (F.col("l_partkey") + PART).alias("dst"))))


def words(docs: DataFrame) -> DataFrame:
    """doc_id and the ASCII words of each English document, case kept."""
    return docs.where("lang = 'en'").select("doc_id", F.regexp_extract_all("text", F.lit("[a-zA-Z]+"), F.lit(0)).alias("w"))


def token(spark: SparkSession, folder: str) -> DataFrame:
    """Adjacent words of English documents."""
    w = words(table(spark, folder, "documents")).where("size(w) >= 2")
    pairs = w.select(F.explode(F.zip_with(F.expr("slice(w, 1, size(w) - 1)"), F.expr("slice(w, 2, size(w) - 1)"), lambda a, b: F.struct(a.alias("src"), b.alias("dst")))).alias("p"))
    named = pairs.select("p.src", "p.dst")
    return relabel(canonicalize(named))


def user(spark: SparkSession, folder: str) -> DataFrame:
    """Users active in one minute."""
    seen = table(spark, folder, "events").select(F.date_trunc("minute", "ts").alias("minute"), "user_id")
    return relabel(_together_dense(seen, ["minute"], "user_id"))


def following(events: DataFrame) -> DataFrame:
    """Each event's user and the next event's user in the order of (ts, event_id), hour by hour; hours are chained by their ends."""
    hourly = events.select(F.date_trunc("hour", "ts").alias("hour"), "ts", "event_id", "user_id")
    inside = Window.partitionBy("hour").orderBy("ts", "event_id")
    near = hourly.select(F.col("user_id").alias("src"), F.lead("user_id").over(inside).alias("dst")).where("dst is not null")
    ends = hourly.groupBy("hour").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
    across = ends.select(F.col("last").alias("src"), F.lead("first").over(Window.orderBy("hour")).alias("dst")).where("dst is not null")
    return near.unionByName(across)


def next_(spark: SparkSession, folder: str) -> DataFrame:
    """Users of consecutive events."""
    return relabel(canonicalize(following(table(spark, folder, "events"))))


def link(spark: SparkSession, folder: str) -> DataFrame:
    """Pages and the targets of their links."""
    pages = table(spark, folder, "pages")
    hrefs = pages.select(F.concat(F.lit("page:"), "page_id").alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("t"))
    return relabel(canonicalize(hrefs.select("src", F.concat(F.lit("href:"), "t").alias("dst"))))


def doc(spark: SparkSession, folder: str, low: int = 2, high: int = 50) -> DataFrame:
    """English documents that share a five-word shingle which ``low`` to ``high`` documents hold."""
    w = words(table(spark, folder, "documents")).where("size(w) >= 5")
    grams = w.select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.array_join(F.slice("w", i, F.lit(5)), " ")))).alias("g"))
    held = grams.groupBy("g").agg(F.count(F.lit(1)).alias("n")).where(F.col("n").between(low, high)).select("g")
    return relabel(_together(grams.join(held, "g"), ["g"], "doc_id"))


def emb(spark: SparkSession, folder: str, least: float = 0.25) -> DataFrame:
    """Vectors with cosine above ``least``, block against block of vectors (small tables only: it compares all pairs)."""
    rows = table(spark, folder, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    unit = rows.select("vec_id", "v", F.sqrt(dot("v", "v")).alias("r"))
    other = unit.select(F.col("vec_id").alias("dst"), F.col("v").alias("w"), F.col("r").alias("q"))
    close = unit.join(other, F.col("vec_id") < F.col("dst")).where(dot("v", "w") > F.lit(least) * F.col("r") * F.col("q"))
    return relabel(close.select(F.col("vec_id").alias("src"), "dst"))


GRAPHS = {"part": part, "star": star, "token": token, "user": user, "next": next_, "supp": supp, "cust": cust, "bip": bip, "link": link, "doc": doc}
