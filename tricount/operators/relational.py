"""Relational operators around the methods, each as a query over the given tables with its SQL.

Outputs are integers, texts or rounded numbers, so that any engine gives the same rows.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources import register_views, table

Query = Callable[[SparkSession, str], DataFrame]
OPS: dict[str, tuple[Query, str | None]] = {}


def op(sql: str | None):
    """Register the function as op_<name> with its SQL."""

    def keep(f: Query) -> Query:
        OPS[f"op_{f.__name__.strip('_')}"] = (f, sql)
        return f

    return keep


def same(name: str, sql: str, tables: str) -> None:
    """An operator whose Spark form is the same SQL over views; Catalyst plans it as it does the DataFrame form."""

    def run(spark: SparkSession, folder: str) -> DataFrame:
        register_views(spark, folder, tables.split())
        return spark.sql(sql)

    run.__name__ = name
    OPS[f"op_{name}"] = (run, sql)


@op("SELECT l_partkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_shipdate < TIMESTAMP '1998-01-01 00:00:00'")
def filter_pushdown(spark, folder):
    return table(spark, folder, "lineitem").where("l_quantity between 10 and 20 and l_returnflag in ('A', 'R') and l_shipdate < timestamp_ntz'1998-01-01 00:00:00'").select("l_partkey", "l_quantity")


@op("SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'low' ELSE 'high' END AS kind, c_mktsegment LIKE 'B%' AS b FROM customer")
def case_like(spark, folder):
    return table(spark, folder, "customer").select("c_custkey", F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 5000, "low").otherwise("high").alias("kind"), F.col("c_mktsegment").like("B%").alias("b"))


@op("SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey")
def join_inner(spark, folder):
    return table(spark, folder, "orders").join(table(spark, folder, "customer"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name")


@op("SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def join_broadcast(spark, folder):
    """nation has a fixed 25 rows."""
    return table(spark, folder, "customer").join(F.broadcast(table(spark, folder, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


@op("SELECT p_partkey, count(l_partkey) AS lines FROM part LEFT JOIN lineitem ON p_partkey = l_partkey GROUP BY p_partkey")
def join_left(spark, folder):
    lines = table(spark, folder, "lineitem").groupBy("l_partkey").agg(F.count(F.lit(1)).alias("n"))
    return table(spark, folder, "part").join(lines, F.col("p_partkey") == F.col("l_partkey"), "left").select("p_partkey", F.coalesce("n", F.lit(0).cast("long")).alias("lines"))


@op("SELECT coalesce(doc_id, vec_id) AS id, doc_id IS NOT NULL AS d, vec_id IS NOT NULL AS v FROM documents FULL JOIN embeddings ON doc_id = vec_id")
def join_full(spark, folder):
    a, b = table(spark, folder, "documents").select("doc_id"), table(spark, folder, "embeddings").select("vec_id")
    return a.join(b, F.col("doc_id") == F.col("vec_id"), "full").select(F.coalesce("doc_id", "vec_id").alias("id"), F.col("doc_id").isNotNull().alias("d"), F.col("vec_id").isNotNull().alias("v"))


@op("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_semi(spark, folder):
    return table(spark, folder, "customer").join(table(spark, folder, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@op("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_anti(spark, folder):
    return table(spark, folder, "customer").join(table(spark, folder, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@op("SELECT x.n_nationkey AS a, y.n_nationkey AS b FROM nation x JOIN nation y ON x.n_nationkey < y.n_nationkey AND x.n_regionkey IS NOT DISTINCT FROM y.n_regionkey")
def join_null_safe_theta(spark, folder):
    n = table(spark, folder, "nation")
    x, y = n.select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("r")), n.select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("s"))
    return x.join(y, F.col("r").eqNullSafe(F.col("s")) & (F.col("a") < F.col("b"))).select("a", "b")


@op("SELECT r_regionkey, n_nationkey FROM region, nation")
def join_cross(spark, folder):
    """Fixed tables of 5 and 25 rows."""
    return table(spark, folder, "region").select("r_regionkey").crossJoin(table(spark, folder, "nation").select("n_nationkey"))


@op("SELECT p_partkey, p_size // 10 AS band FROM part")
def join_range(spark, folder):
    """Sizes to bands of ten: the range join id -> block, as a lookup in a fixed table of bands."""
    bands = F.broadcast(spark.range(10).select(F.col("id").cast("int").alias("band"), (F.col("id") * 10).alias("lo"), (F.col("id") * 10 + 9).alias("hi")))
    return table(spark, folder, "part").join(bands, F.col("p_size").between(F.col("lo"), F.col("hi"))).select("p_partkey", "band")


@op("SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON y.ts > x.ts AND y.ts <= x.ts + INTERVAL 1 MINUTE AND x.user_id = y.user_id")
def join_interval(spark, folder):
    """Events of a user at most a minute apart: bucketed by minute, each event looks into its own and the next bucket."""
    e = table(spark, folder, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    minute = 60_000_000
    x = e.select(F.col("event_id").alias("a"), "user_id", F.col("us").alias("u"), F.explode(F.array(F.expr(f"us div {minute}"), F.expr(f"us div {minute} + 1"))).alias("bucket"))
    y = e.select(F.col("event_id").alias("b"), "user_id", F.col("us").alias("w"), F.expr(f"us div {minute}").alias("bucket"))
    return x.join(y, ["user_id", "bucket"]).where(f"w > u and w <= u + {minute}").select("a", "b")


@op("SELECT event_id, (SELECT max(p.event_id) FROM events p WHERE p.event_type = 'purchase' AND p.user_id = e.user_id AND p.event_id < e.event_id) AS earlier FROM events e")
def join_asof(spark, folder):
    """Each event with the user's last earlier purchase, in one window."""
    line = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, folder, "events").select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(line).alias("earlier"))


@op("SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DECIMAL(28,2)) AS q, min(l_shipdate)::VARCHAR AS first, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1, 2")
def agg_group(spark, folder):
    return table(spark, folder, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("decimal(18,2)")).cast("decimal(28,2)").alias("q"), F.date_format(F.min("l_shipdate").cast("timestamp"), "yyyy-MM-dd HH:mm:ss").alias("first"), F.count_distinct("l_suppkey").alias("suppliers"))


@op(None)
def agg_approx_distinct(spark, folder):
    return table(spark, folder, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"))


@op("SELECT c_nationkey, round(median(c_acctbal), 4) AS mid, round(stddev_samp(c_acctbal), 4) AS spread, bool_or(c_acctbal < 0) AS debt, max_by(c_custkey, c_acctbal) AS top FROM customer GROUP BY 1")
def agg_statistics(spark, folder):
    return table(spark, folder, "customer").groupBy("c_nationkey").agg(F.round(F.percentile("c_acctbal", 0.5), 4).alias("mid"), F.round(F.stddev_samp("c_acctbal"), 4).alias("spread"), F.bool_or(F.col("c_acctbal") < 0).alias("debt"), F.max_by("c_custkey", "c_acctbal").alias("top"))


@op("SELECT o_orderpriority, list_aggregate(list_sort(list(DISTINCT o_orderstatus)), 'string_agg', ',') AS kinds FROM orders GROUP BY 1")
def agg_collect(spark, folder):
    return table(spark, folder, "orders").groupBy("o_orderpriority").agg(F.array_join(F.sort_array(F.collect_set("o_orderstatus")), ",").alias("kinds"))


_GEO = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _geo(spark, folder):
    return table(spark, folder, "customer").join(F.broadcast(table(spark, folder, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(spark, folder, "region")), F.col("n_regionkey") == F.col("r_regionkey"))


@op(f"SELECT r_name, n_name, count(*) AS n {_GEO} GROUP BY ROLLUP (r_name, n_name)")
def rollup(spark, folder):
    return _geo(spark, folder).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@op(f"SELECT r_name, c_mktsegment, count(*) AS n {_GEO} GROUP BY CUBE (r_name, c_mktsegment)")
def cube(spark, folder):
    return _geo(spark, folder).cube("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@op("SELECT o_orderstatus, count(*) FILTER (WHERE o_orderpriority LIKE '1%') AS urgent, count(*) FILTER (WHERE o_orderpriority LIKE '5%') AS low FROM orders GROUP BY 1")
def pivot(spark, folder):
    first = table(spark, folder, "orders").withColumn("p", F.when(F.col("o_orderpriority").startswith("1"), "urgent").when(F.col("o_orderpriority").startswith("5"), "low"))
    return first.groupBy("o_orderstatus").pivot("p", ["urgent", "low"]).agg(F.count(F.lit(1))).select("o_orderstatus", F.coalesce("urgent", F.lit(0).cast("long")).alias("urgent"), F.coalesce("low", F.lit(0).cast("long")).alias("low"))


@op("SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")
def having(spark, folder):
    return table(spark, folder, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).where("n > 12")


@op("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER v, 6) AS pr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def window_rank(spark, folder):
    w, v = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return table(spark, folder, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(v), 6).alias("pr"))


@op("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS near FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def window_lag_rows(spark, folder):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return table(spark, folder, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.count(F.lit(1)).over(w.rowsBetween(-3, 0)).alias("near"))


@op("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS hour FROM events")
def window_range(spark, folder):
    e = table(spark, folder, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("hour"))


@op("SELECT p_partkey, p_size FROM part ORDER BY p_size DESC, p_partkey LIMIT 25 OFFSET 5")
def topk_offset(spark, folder):
    return table(spark, folder, "part").select("p_partkey", "p_size").orderBy(F.desc("p_size"), "p_partkey").offset(5).limit(25)


@op("SELECT c_nationkey, c_custkey FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn FROM customer) WHERE rn <= 3")
def topk_group(spark, folder):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return table(spark, folder, "customer").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("c_nationkey", "c_custkey")


for _name, _set in {"union_all": "UNION ALL", "union_distinct": "UNION", "intersect": "INTERSECT", "intersect_all": "INTERSECT ALL", "except": "EXCEPT", "except_all": "EXCEPT ALL"}.items():
    same(_name, f"SELECT l_suppkey AS k FROM lineitem WHERE l_quantity > 25 {_set} SELECT l_suppkey AS k FROM lineitem WHERE l_discount > 0.05", "lineitem")


@op("SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")
def distinct(spark, folder):
    return table(spark, folder, "lineitem").select("l_partkey", "l_suppkey").distinct()


@op("""WITH s AS (SELECT o_custkey AS c, list(DISTINCT l_partkey) AS p FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1)
  SELECT x.c, len(list_intersect(x.p, y.p)) AS both, len(list_distinct(x.p || y.p)) AS any_, list_has_any(x.p, y.p) AS hit FROM s x JOIN s y ON y.c = x.c + 1""")
def array_sets(spark, folder):
    s = table(spark, folder, "orders").join(table(spark, folder, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy(F.col("o_custkey").alias("c")).agg(F.collect_set("l_partkey").alias("p"))
    y = s.select((F.col("c") - 1).alias("c"), F.col("p").alias("q"))
    return s.join(y, "c").select("c", F.size(F.array_intersect("p", "q")).cast("long").alias("both"), F.size(F.array_union("p", "q")).cast("long").alias("any_"), F.arrays_overlap("p", "q").alias("hit"))


@op("""WITH s AS (SELECT l_orderkey AS o, list_sort(list(l_partkey)) AS p FROM lineitem GROUP BY 1)
  SELECT o, CAST(list_sum(list_transform(p, lambda x: x * 2)) AS BIGINT) AS doubled, len(list_filter(p, lambda x: x % 2 = 0)) AS even, list_contains(p, 1) AS has1, p[1] AS first, p[-1] AS last, array_to_string(p[1:3], ',') AS head FROM s""")
def array_lambdas(spark, folder):
    s = table(spark, folder, "lineitem").groupBy(F.col("l_orderkey").alias("o")).agg(F.sort_array(F.collect_list("l_partkey")).alias("p"))
    return s.select("o", F.aggregate(F.transform("p", lambda x: x * 2), F.lit(0).cast("long"), lambda a, x: a + x).alias("doubled"), F.size(F.filter("p", lambda x: x % 2 == 0)).cast("long").alias("even"), F.array_contains("p", 1).alias("has1"), F.element_at("p", 1).alias("first"), F.element_at("p", -1).alias("last"), F.array_join(F.slice("p", 1, 3), ",").alias("head"))


@op("SELECT doc_id, i - 1 AS pos, words[i] AS word FROM (SELECT doc_id, words, unnest(range(1, len(words) + 1)) AS i FROM (SELECT doc_id, string_split(text, ' ') AS words FROM documents WHERE lang = 'es'))")
def posexplode(spark, folder):
    return table(spark, folder, "documents").where("lang = 'es'").select("doc_id", F.posexplode(F.split("text", " ")).alias("pos", "word")).withColumn("pos", F.col("pos").cast("long"))


@op("SELECT event_type, CAST(sum(CAST(props->>'$.k' AS BIGINT)) AS BIGINT) AS k FROM events GROUP BY 1")
def json_props(spark, folder):
    return table(spark, folder, "events").select("event_type", F.from_json("props", "k long")["k"].alias("k")).groupBy("event_type").agg(F.sum("k").alias("k"))


@op("SELECT doc_id, len(regexp_extract_all(text, '[a-zA-Z]+')) AS words, lower(substr(text, 1, 5)) AS head, length(text) AS n FROM documents")
def regexp_tokens(spark, folder):
    return table(spark, folder, "documents").select("doc_id", F.size(F.regexp_extract_all("text", F.lit("[a-zA-Z]+"), F.lit(0))).cast("long").alias("words"), F.lower(F.substring("text", 1, 5)).alias("head"), F.length("text").cast("long").alias("n"))


@op("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages")
def parse_url(spark, folder):
    return table(spark, folder, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"))


@op("SELECT x.n_nationkey AS a, y.n_nationkey AS b, levenshtein(x.n_name, y.n_name) AS d FROM nation x JOIN nation y ON x.n_regionkey = y.n_regionkey AND x.n_nationkey < y.n_nationkey")
def levenshtein(spark, folder):
    n = table(spark, folder, "nation")
    x, y = n.select(F.col("n_nationkey").alias("a"), F.col("n_name").alias("s"), "n_regionkey"), n.select(F.col("n_nationkey").alias("b"), F.col("n_name").alias("t"), "n_regionkey")
    return x.join(y, "n_regionkey").where("a < b").select("a", "b", F.levenshtein("s", "t").cast("long").alias("d"))


@op("SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n, max(date_diff('day', TIMESTAMP '1992-01-01', o_orderdate)) AS days FROM orders GROUP BY 1")
def dates(spark, folder):
    day = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date"))
    return table(spark, folder, "orders").groupBy(F.date_format(F.col("o_orderdate").cast("timestamp"), "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.max(day).cast("long").alias("days"))


@op("SELECT p_partkey, p_size // 7 AS q, p_size % 7 AS r, xor(p_partkey, 85) AS x, p_partkey >> 2 AS h, greatest(p_size, 20) AS g, round(sqrt(p_size), 6) AS s, round(ln(p_size + 1), 6) AS l FROM part")
def arithmetic(spark, folder):
    return table(spark, folder, "part").select("p_partkey", F.expr("cast(p_size div 7 as int)").alias("q"), F.pmod("p_size", F.lit(7)).alias("r"), F.col("p_partkey").bitwiseXOR(F.lit(85).cast("long")).alias("x"), F.shiftright("p_partkey", 2).alias("h"), F.greatest("p_size", F.lit(20)).alias("g"), F.round(F.sqrt("p_size"), 6).alias("s"), F.round(F.log(F.col("p_size") + 1), 6).alias("l"))


same("subquery_scalar", "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer)", "customer")
same("subquery_exists", "SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_suppkey = s_suppkey AND l_quantity > 49)", "supplier lineitem")
same("cte_recursive", "WITH RECURSIVE r(q, i, x) AS (SELECT DISTINCT l_quantity, 0, CAST(floor(l_quantity) AS INT) FROM lineitem UNION ALL SELECT q, i + 1, CAST(floor(x * 3 / 4) AS INT) FROM r WHERE x > 1) SELECT q, i, x FROM r", "lineitem")


@op("SELECT doc_id FROM documents WHERE doc_id % 10 = 3")
def sample_hash(spark, folder):
    """The sampling operator with a deterministic rule."""
    return table(spark, folder, "documents").where(F.pmod("doc_id", F.lit(10)) == 3).select("doc_id")


@op(None)
def sample_random(spark, folder):
    """Bernoulli sample, ten per cent."""
    return table(spark, folder, "lineitem").sample(fraction=0.1, seed=42).select("l_orderkey", "l_linenumber")


@op(None)
def sample_by(spark, folder):
    """Stratified sample by language."""
    return table(spark, folder, "documents").sampleBy("lang", {"en": 0.1, "de": 0.5, "fr": 0.5, "es": 1.0}, seed=42).select("doc_id", "lang")


@op("SELECT map_keys(m)[1] AS k, len(map_keys(m)) AS n FROM (SELECT map_from_entries(list((d, c) ORDER BY d)) AS m FROM (SELECT n_regionkey AS d, count(*) AS c FROM nation GROUP BY 1))")
def map_entries(spark, folder):
    counts = table(spark, folder, "nation").groupBy(F.col("n_regionkey").alias("d")).agg(F.count(F.lit(1)).alias("c"))
    m = F.map_from_entries(F.sort_array(F.collect_list(F.struct("d", "c"))))
    return counts.agg(m.alias("m")).select(F.element_at(F.map_keys("m"), 1).alias("k"), F.size(F.map_keys("m")).cast("long").alias("n"))
