"""The registered queries of the counting methods with their SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import functions, plans, streaming
from . import oracles as o
from .experiments import EXPERIMENTS
from .operators import approx, blocks, cost, derived, dynamic, exact, exchange, generators, graph, mapreduce, measures, orient, overlap, tasks, workloads
from .operators.relational import OPS
from .session import cut as cut_lineage
from .session import shared_folder
from .sources import table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, f: Query, sql: str | None = None) -> None:
    QUERIES[name] = f
    if sql:
        ORACLES[name] = sql


def on(name: str, f: Callable[[DataFrame], DataFrame]) -> Query:
    """A query that runs ``f`` on the edges of a network, which ``relabel`` has stored and which are read as often as ``f`` asks."""
    return lambda spark, folder: f(workloads.GRAPHS[name](spark, folder))


def longs(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.col(n).cast("long") for n in names})


# Networks and summaries
for _g in workloads.GRAPHS:
    add(f"edges_{_g}", workloads.GRAPHS[_g], o.graph(_g) + " SELECT src, dst FROM edges")
    add(f"tri_intersect_{_g}", on(_g, exact.count_intersect), o.graph(_g) + o.arcs() + o.TRIANGLES + " SELECT count(*) AS triangles FROM tri")
add("edges_emb", lambda s, d: workloads.emb(s, d))
_PA = o.pa_graph_over("customer", "c_custkey", 10)


def attached_customers(spark: SparkSession, folder: str) -> DataFrame:
    """A network of preferential attachment whose nodes are the customers."""
    return generators.pa_over(table(spark, folder, "customer").select("c_custkey"), 10)


add("edges_pa", attached_customers, _PA + " SELECT src, dst FROM edges")
_T = " SELECT count(*) AS triangles FROM tri"
add("tri_intersect_pa", lambda s, d: exact.count_intersect(cut_lineage(attached_customers(s, d))), _PA + o.arcs() + o.TRIANGLES + _T)
_SUM = "SELECT count(*) AS n, CAST(sum(deg) // 2 AS BIGINT) AS m, round(sum(deg) / count(*), 4) AS avg_deg, round(quantile_cont(deg, 0.5), 4) AS p50, round(quantile_cont(deg, 0.99), 4) AS p99, max(deg) AS max_deg FROM deg"
for _g in ("part", "star", "token"):
    add(f"network_summary_{_g}", on(_g, measures.summary), o.graph(_g) + o.arcs() + " " + _SUM)
add("degree_histogram", on("token", measures.degree_histogram), o.graph("token") + o.arcs() + " SELECT deg, count(*) AS nodes FROM deg GROUP BY 1")
add("degrees_token", on("token", orient.node_table), o.graph("token") + o.arcs() + " SELECT id, deg, eff FROM eff")
for _order in ("degree", "id"):
    add(f"arcs_{_order}_token", on("token", lambda e, k=_order: orient.orient(e, k)), o.graph("token") + o.arcs(_order) + " SELECT src, dst FROM arcs")
add("adjacency_user", on("user", lambda e: orient.adjacency(e).select("id", "deg", "eff", F.array_join(F.col("nbrs").cast("array<string>"), " ").alias("nbrs"))), o.graph("user") + o.arcs() + " SELECT eff.id, deg, eff, coalesce(l, '') AS nbrs FROM eff LEFT JOIN (SELECT src AS id, string_agg(CAST(dst AS VARCHAR), ' ' ORDER BY dst) AS l FROM arcs GROUP BY 1) x ON x.id = eff.id")
add("relabel_hashed_user", on("user", lambda e: exact.count_intersect(graph.relabel(e, "hashed"))), o.graph("user") + o.arcs() + o.TRIANGLES + _T)
add("relabel_degree_user", on("user", lambda e: exact.count_intersect(graph.relabel(e, "degree"))), o.graph("user") + o.arcs() + o.TRIANGLES + _T)

# Kernels
_part, _user, _token = (o.graph(g) + o.arcs() + o.TRIANGLES for g in ("part", "user", "token"))
add("tri_all_triples_next", on("next", exact.count_all_triples), o.graph("next") + o.arcs() + o.TRIANGLES + _T)
add("tri_node_centred_part", on("part", exact.count_node_centred), _part + _T)
add("tri_node_centred_raw_user", on("user", lambda e: exact.count_node_centred(e, raw=True)), _user + " SELECT 6 * count(*) AS met FROM tri")
add("tri_id_order_part", on("part", exact.count_ordered), _part + _T)
add("tri_random_order_part", on("part", lambda e: exact.count_ordered(e, "random")), _part + _T)
add("tri_merge_part", on("part", lambda e: exact.count_intersect(e, kernel="merge")), _part + _T)
add("tri_gallop_token", on("token", lambda e: exact.count_intersect(e, kernel="gallop")), _token + _T)
add("tri_closure_token", on("token", exact.count_closure), _token + _T)
add("tri_list_user", on("user", exact.list_triangles), _user + " SELECT a, b, c FROM tri")
add("tri_per_node_part", on("part", derived.node_triangles), _part + o.PER_NODE + " SELECT id, triangles FROM pernode")
add("tri_per_node_def_user", on("user", derived.node_triangles_def), _user + o.PER_NODE + " SELECT id, triangles FROM pernode")
add("matrix_user", on("user", exact.count_matrix), _user + _T)
add("planned_part", on("part", lambda e: plans.choose(e).count(e)), _part + _T)

# Costs and blocks
for _k in cost.COSTS:
    add(f"cost_{_k}", on("token", lambda e, k=_k: cost.node_cost(e, k)), o.graph("token") + o.arcs() + o.cost(_k) + " SELECT id, CAST(f AS BIGINT) AS f FROM cost")
    if _k != "effective":
        add(
            f"blocks_{_k}_token_p16", on("token", lambda e, k=_k: longs(blocks.balanced_blocks(cost.node_cost(e, k), 16), "cost")),
            o.graph("token") + o.arcs() + o.cost(_k) + o.blocks(16) + " SELECT part, min(id) AS lo, max(id) AS hi, count(*) AS nodes, CAST(sum(f) AS BIGINT) AS cost FROM owner GROUP BY 1",
        )
add("cost_custom", on("token", lambda e: cost.node_cost(e, "custom", expr="deg * eff + 1")), o.graph("token") + o.arcs() + " SELECT id, deg * eff + 1 AS f FROM eff")
add(
    "cost_totals_agree", on("part", lambda e: longs(cost.node_cost(e, "owner").agg(F.sum("f").alias("owner")).join(F.broadcast(cost.node_cost(e, "surrogate").agg(F.sum("f").alias("surrogate")))), "owner", "surrogate")),
    o.graph("part") + o.arcs() + o.cost("owner") + o.cost("surrogate", "other") + " SELECT (SELECT CAST(sum(f) AS BIGINT) FROM cost) AS owner, (SELECT CAST(sum(f) AS BIGINT) FROM other) AS surrogate",
)
add("block_assign_part", on("part", lambda e: blocks.assign(cost.node_cost(e, "surrogate"), 16).select("id", "part")), o.graph("part") + o.arcs() + o.cost("surrogate") + o.blocks(16) + " SELECT id, part FROM owner")
add("half_point_part", on("part", lambda e: blocks.half_point(cost.node_cost(e, "degree"))), o.graph("part") + o.arcs() + o.cost("degree") + ", run AS (SELECT id, sum(f) OVER (ORDER BY id) AS upto, sum(f) OVER () AS total FROM cost) SELECT min(id) + 1 AS half FROM run WHERE 2 * upto >= total")


def cut(name: str, parts: int = 16, kind: str = "surrogate") -> str:
    return o.graph(name) + o.arcs() + o.cost(kind) + o.blocks(parts) + o.PLACED


# Method 1
for _g in ("part", "token"):
    add(
        f"nonoverlap_sizes_{_g}", on(_g, lambda e: exchange.sizes(exchange.build(e, 16))),
        cut(_g) + ", known AS (SELECT part, id FROM owner UNION SELECT x.part, a.dst AS id FROM arcs a JOIN owner x ON x.id = a.src), vs AS (SELECT part, count(*) AS v_count FROM known GROUP BY 1), es AS (SELECT x.part, CAST(sum(eff) AS BIGINT) AS e_count FROM owner x JOIN eff ON eff.id = x.id GROUP BY 1) SELECT vs.part, v_count, e_count FROM vs JOIN es ON es.part = vs.part",
    )
    for _s in exchange.SCHEMES:
        add(f"nonoverlap_count_{_s}_{_g}", on(_g, lambda e, s=_s: exchange.count(exchange.build(e, 16), s)), cut(_g) + o.TRIANGLES + " " + o.exchange(_s))
    add(f"traffic_{_g}_p16", on(_g, lambda e: exchange.traffic(exchange.build(e, 16))), cut(_g) + " " + o.traffic())
    add(f"redundancy_ratio_{_g}", on(_g, lambda e: measures.redundancy(exchange.build(e, 16))), cut(_g) + " SELECT count(*) AS direct, count(DISTINCT (v, pu)) AS surrogate, round(count(*) / count(DISTINCT (v, pu)), 4) AS ratio FROM placed WHERE pv <> pu")
for _d in ("last", "set", "none"):
    add(
        f"surrogate_guard_{_d}_part", on("part", lambda e, d=_d: exchange.messages(exchange.build(e, 16), d).groupBy("dest").agg(F.count(F.lit(1)).alias("messages"), F.sum(F.size("nbrs")).alias("elements"))),
        cut("part") + f" SELECT pu AS dest, count(*) AS messages, CAST(sum(ev) AS BIGINT) AS elements FROM (SELECT {'DISTINCT v, pu, ev' if _d != 'none' else 'v, pu, ev'} FROM placed WHERE pv <> pu) GROUP BY 1",
    )
add("surrogate_unguarded_count_part", on("part", lambda e: exchange.count(exchange.build(e, 16), "surrogate", "none")), cut("part") + o.TRIANGLES + " " + o.exchange("surrogate"))
add("surrogate_cogrouped_user", on("user", lambda e: functions.receive_cogrouped(exchange.build(e, 4)).where("triangles > 0")), cut("user", 4) + o.TRIANGLES + f" SELECT part, remote_triangles AS triangles FROM ({o.exchange('surrogate')}) WHERE remote_triangles > 0")
add("traffic_by_block", on("part", lambda e: exchange.traffic(exchange.build(e, 16), by_part=True)), cut("part") + " " + o.traffic(True))
add("exchange_choice", on("part", lambda e: exchange.choose(exchange.build(e, 16))), cut("part") + f", t AS (SELECT * FROM ({o.traffic()}) WHERE scheme <> 'scan') SELECT (SELECT scheme FROM t WHERE scheme <> 'cached' ORDER BY elements, messages LIMIT 1) AS bounded, (SELECT scheme FROM t ORDER BY elements, messages LIMIT 1) AS \"any\"")

# Method 2
for _k in ("static", "equal", "shrinking"):
    add(
        f"tasks_{_k}_part", on("part", lambda e, k=_k: longs(tasks.table(e.sparkSession, cost.node_cost(e, "degree"), 17, k), "size")),
        o.graph("part") + o.arcs() + o.cost("degree") + o.tasks(17, _k) + " SELECT CAST(seq AS INTEGER) AS seq, phase, v, t, CAST(size AS BIGINT) AS size FROM tasks",
    )
add("tasks_initial_part", on("part", lambda e: longs(tasks.table(e.sparkSession, cost.node_cost(e, "degree"), 17).where("phase = 'initial'"), "size")), o.graph("part") + o.arcs() + o.cost("degree") + o.tasks(17, "shrinking") + " SELECT CAST(seq AS INTEGER) AS seq, phase, v, t, CAST(size AS BIGINT) AS size FROM tasks WHERE phase = 'initial'")
for _g in ("part", "token"):
    _sql = o.graph(_g) + o.arcs() + o.TRIANGLES + o.cost("degree") + o.tasks(9, "shrinking") + " SELECT CAST(seq AS INTEGER) AS seq, v, t, coalesce(n, 0) AS triangles FROM tasks LEFT JOIN (SELECT seq AS s, count(*) AS n FROM tri JOIN tasks ON a BETWEEN v AND v + t - 1 GROUP BY 1) x ON s = seq"
    add(f"task_counts_{_g}", on(_g, lambda e: dynamic.count(e, 9)), _sql)
add("task_counts_shuffle_part", on("part", lambda e: dynamic.count(e, 9, mode="shuffle")), ORACLES["task_counts_part"])

# Baselines
for _m in ("full", "induced"):
    _held = "SELECT i.part, count(*) AS v_count, CAST(sum(e) AS BIGINT) AS e_count FROM (SELECT i.part, i.id, count(a.dst){0} AS e FROM inblock i LEFT JOIN arcs a ON a.src = i.id {1} GROUP BY 1, 2) i GROUP BY 1"
    _full = _held.format("", "")
    _ind = "SELECT part, count(*) AS v_count, CAST(sum(e) AS BIGINT) AS e_count FROM (SELECT i.part, i.id, count(j.id) AS e FROM inblock i LEFT JOIN arcs a ON a.src = i.id LEFT JOIN inblock j ON j.part = i.part AND j.id = a.dst GROUP BY 1, 2) GROUP BY 1"
    add(f"overlap_sizes_{_m}_part", on("part", lambda e, m=_m: overlap.sizes(overlap.build(exchange.build(e, 16, "owner"), m))), cut("part", 16, "owner") + o.OVERLAP + " " + (_full if _m == "full" else _ind))
add("overlap_count_part", on("part", lambda e: overlap.count(overlap.build(exchange.build(e, 16, "owner")))), cut("part", 16, "owner") + o.TRIANGLES + " SELECT p.part, coalesce(n, 0) AS triangles FROM (SELECT DISTINCT part FROM owner) p LEFT JOIN (SELECT part, count(*) AS n FROM tri JOIN owner ON id = a GROUP BY 1) t ON t.part = p.part")
for _g, _q in (("part", _part), ("user", _user)):
    add(f"two_paths_{_g}", on(_g, mapreduce.count_two_paths), _q + _T)
add("two_paths_oriented_part", on("part", lambda e: mapreduce.count_two_paths(e, oriented=True)), _part + _T)
add("bucket_triples_part", on("part", mapreduce.count_bucket_triples), _part + _T)
add("bucket_pairs_triples_part", on("part", mapreduce.count_bucket_pairs_triples), _part + _T)


def _edge_hash(seed: int = 42) -> str:
    return graph.mix_sql(f"(({graph.mix_sql('src', seed)} + dst) % 2147483648)", seed + 1)


def _sampled(where: str, estimate: str) -> str:
    """kept, triangles, estimate for the edges that ``where`` keeps."""
    return o.graph("part") + f", kept AS MATERIALIZED (SELECT src, dst FROM edges WHERE {where}), tri AS (SELECT x.src FROM kept x JOIN kept y ON x.dst = y.src JOIN kept z ON z.src = x.src AND z.dst = y.dst) SELECT (SELECT count(*) FROM kept) AS kept, count(*) AS triangles, round({estimate}, 6) AS estimate FROM tri"


add("sparsify_part", on("part", approx.sparsify), _sampled(f"{_edge_hash()} < {approx.RANGE // 2}", "count(*) / 0.125"))
_KEPT = "(SELECT src, dst FROM edges ORDER BY " + _edge_hash() + ", src, dst LIMIT 50000)"
add(
    "stream_sample_part", on("part", approx.stream_sample),
    o.graph("part") + f", kept AS MATERIALIZED {_KEPT}, size AS (SELECT (SELECT count(*) FROM edges) AS m, (SELECT count(*) FROM kept) AS k), tri AS (SELECT count(*) AS t FROM kept x JOIN kept y ON x.dst = y.src JOIN kept z ON z.src = x.src AND z.dst = y.dst)"
    + " SELECT k AS kept, t AS triangles, round(t * CASE WHEN k >= m THEN 1.0 ELSE (m * (m - 1.0::DOUBLE) * (m - 2.0::DOUBLE)) / greatest(1.0::DOUBLE, k * (k - 1.0::DOUBLE) * (k - 2.0::DOUBLE)) END, 6) AS estimate FROM size, tri",
)
_WEDGE = graph.mix_sql(f"(({graph.mix_sql(f'(({graph.mix_sql("v")} + u) % 2147483648)')} + w) % 2147483648)")
add(
    "wedge_sample_part", on("part", approx.wedge_sample),
    o.graph("part") + o.arcs() + f", wedge AS (SELECT x.src AS v, x.dst AS u, y.dst AS w FROM near x JOIN near y ON x.src = y.src AND x.dst < y.dst), picked AS MATERIALIZED (SELECT u, w FROM wedge WHERE {_WEDGE} < {int(0.05 * approx.RANGE)}),"
    + " s AS (SELECT (SELECT CAST(sum(deg * (deg - 1) // 2) AS BIGINT) FROM deg) AS wedges, (SELECT count(*) FROM picked) AS probed, (SELECT count(*) FROM picked p JOIN edges e ON e.src = p.u AND e.dst = p.w) AS closed)"
    + " SELECT wedges, probed, closed, round(closed / greatest(probed, 1) * wedges / 3, 6) AS estimate, round(wedges / 3 * sqrt(closed / greatest(probed, 1) * (1 - closed / greatest(probed, 1)) / greatest(probed, 1)), 6) AS stderr FROM s",
)
add(
    "approx_error_part", on("part", lambda e: approx.compared(approx.sparsify(e), e).select("exact", "estimate", "error")),
    _sampled(f"{_edge_hash()} < {approx.RANGE // 2}", "count(*) / 0.125").replace("SELECT (SELECT count(*) FROM kept) AS kept", ", few AS (SELECT (SELECT count(*) FROM kept) AS kept", 1)
    + "), whole AS (SELECT count(*) AS exact FROM edges x JOIN edges y ON x.dst = y.src JOIN edges z ON z.src = x.src AND z.dst = y.dst) SELECT exact, estimate, round(abs(estimate - exact) / greatest(exact, 1), 6) AS error FROM few, whole",
)

# Measures
add(
    "load_imbalance_token", on("token", lambda e: measures.modelled_speedup(e, [16]).select("cut", "parts", "imbalance")),
    o.graph("token") + o.arcs() + o.cost("surrogate", "work") + "".join(o.cost(k, f"c_{k}") + o.blocks(16, f"c_{k}", f"o_{k}") for k in ("unit", "degree", "owner", "surrogate"))
    + " " + " UNION ALL ".join(f"SELECT '{k}' AS cut, 16 AS parts, round(CAST(max(w) AS DOUBLE) * 16 / CAST(sum(w) AS DOUBLE), 4) AS imbalance FROM (SELECT part, sum(work.f) AS w FROM o_{k} x JOIN work ON work.id = x.id GROUP BY 1)" for k in ("unit", "degree", "owner", "surrogate")),
)

# Derived quantities
add("clustering_local_part", on("part", derived.local_clustering), _part + o.PER_NODE + " SELECT id, CASE WHEN deg > 1 THEN round(2 * triangles / (deg * (deg - 1)), 6) ELSE 0.0 END AS clustering FROM pernode")
add("clustering_avg", on("part", derived.average_clustering), _part + o.PER_NODE + " SELECT round(avg(CASE WHEN deg > 1 THEN 2 * triangles / (deg * (deg - 1)) ELSE 0.0 END), 6) AS clustering FROM pernode")
add("transitivity", on("part", derived.transitivity), _part + " SELECT (SELECT count(*) FROM tri) AS triangles, CAST(sum(deg * (deg - 1) // 2) AS BIGINT) AS paths, round(3 * (SELECT count(*) FROM tri) / sum(deg * (deg - 1) // 2), 6) AS transitivity FROM deg")
add("edge_support_user", on("user", derived.edge_support), _user + o.SUPPORT + " SELECT src, dst, support FROM support")


def _peeled(rounds: int) -> str:
    """e0, e1, ..: edges that keep two triangles or more, round by round; enough rounds reach the end."""
    steps = ["e0 AS MATERIALIZED (SELECT src, dst FROM edges)"]
    for k in range(rounds):
        side = f"FROM e{k} x JOIN e{k} y ON x.dst = y.src JOIN e{k} z ON z.src = x.src AND z.dst = y.dst"
        sides = " UNION ALL ".join(f"SELECT {a}.src, {a}.dst {side}" for a in "xyz")
        steps.append(f"e{k + 1} AS MATERIALIZED (SELECT src, dst FROM ({sides}) GROUP BY 1, 2 HAVING count(*) >= 2)")
    return ", ".join(steps)


add("truss_user", on("user", lambda e: derived.k_truss(e, 4)), o.graph("user") + f", {_peeled(12)} SELECT src, dst FROM e12")
add(
    "triangle_components_user", on("user", derived.triangle_components),
    o.graph("user") + """, t AS MATERIALIZED (SELECT row_number() OVER () AS i, x.src AS a, x.dst AS b, y.dst AS c FROM edges x JOIN edges y ON x.dst = y.src JOIN edges z ON z.src = x.src AND z.dst = y.dst),
      sides AS MATERIALIZED (SELECT i, a AS src, b AS dst FROM t UNION ALL SELECT i, b, c FROM t UNION ALL SELECT i, a, c FROM t),
      beside AS MATERIALIZED (SELECT DISTINCT x.i, y.i AS j FROM sides x JOIN sides y USING (src, dst)),
      reach(i, j) AS (SELECT i, j FROM beside UNION SELECT r.i, b.j FROM reach r JOIN beside b ON b.i = r.j),
      of AS (SELECT i, min(j) AS g FROM reach GROUP BY 1),
      first AS (SELECT g, min((src, dst)) AS e FROM of JOIN sides USING (i) GROUP BY 1),
      corner AS (SELECT g, a AS id FROM of JOIN t USING (i) UNION SELECT g, b FROM of JOIN t USING (i) UNION SELECT g, c FROM of JOIN t USING (i))
      SELECT CAST(first.e[1] AS BIGINT) AS src, CAST(first.e[2] AS BIGINT) AS dst, (SELECT count(*) FROM of WHERE of.g = first.g) AS triangles, (SELECT count(*) FROM corner WHERE corner.g = first.g) AS nodes FROM first""",
)
add("closure_candidates_user", on("user", derived.closure_candidates), o.graph("user") + o.arcs() + " SELECT x.dst AS u, y.dst AS w, count(*) AS paths FROM near x JOIN near y ON x.src = y.src AND x.dst < y.dst WHERE NOT EXISTS (SELECT 1 FROM edges e WHERE e.src = x.dst AND e.dst = y.dst) GROUP BY 1, 2")


def quality_signal(spark: SparkSession, folder: str) -> DataFrame:
    """Mean clustering of labelled documents by quality, in the network of shared shingles; keys of nodes are doc_ids in order."""
    e = workloads.doc(spark, folder)
    w = workloads.words(table(spark, folder, "documents")).where("size(w) >= 5")
    grams = w.select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.array_join(F.slice("w", i, F.lit(5)), " ")))).alias("g"))
    held = grams.groupBy("g").agg(F.count(F.lit(1)).alias("n")).where("n between 2 and 50").select("g")
    named = graph.number(grams.join(held, "g").select("doc_id").distinct(), ["doc_id"])
    marked = named.join(table(spark, folder, "labels").select("doc_id", "quality"), "doc_id").join(derived.local_clustering(e), "id")
    return marked.groupBy("quality").agg(F.count(F.lit(1)).alias("docs"), F.round(F.avg("clustering"), 4).alias("clustering"))


add("quality_signal_doc", quality_signal, o.graph("doc") + o.arcs() + o.TRIANGLES + o.PER_NODE + " SELECT quality, count(*) AS docs, round(avg(CASE WHEN deg > 1 THEN round(2 * triangles / (deg * (deg - 1)), 6) ELSE 0.0 END), 4) AS clustering FROM pernode JOIN named ON named.id = pernode.id JOIN labels ON labels.doc_id = named.k GROUP BY 1")

# Functions
_LISTS = o.graph("user") + o.arcs()
add("udf_common_user", on("user", lambda e: exact.paired_lists(e).select(F.coalesce(F.sum(functions.common("nv", "nu")), F.lit(0)).cast("long").alias("triangles"))), _user + _T)
add("udf_list_sizes_user", on("user", lambda e: orient.adjacency(e).select("id", functions.list_sizes("nbrs").alias("n"))), _LISTS + " SELECT id, eff AS n FROM eff")
add("udf_gini_part", on("part", lambda e: measures.load(e, 16, "unit").agg(F.round(functions.gini(F.col("work").cast("double")), 6).alias("gini"))), o.graph("part") + o.arcs() + o.cost("unit") + o.cost("surrogate", "work") + o.blocks(16) + ", loads AS (SELECT part, CAST(sum(work.f) AS DOUBLE) AS w FROM owner JOIN work USING (id) GROUP BY 1), r AS (SELECT w, row_number() OVER (ORDER BY w) AS i, count(*) OVER () AS n FROM loads) SELECT round(sum((2 * i - n - 1) * w) / (max(n) * sum(w)), 6) AS gini FROM r")


def udtf_triangles(spark: SparkSession, folder: str) -> DataFrame:
    """The triangles on top of each node, by the table function on the edges among its higher neighbours: rows are bounded by the lists, not by the network."""
    functions.register(spark)
    arcs = workloads.user(spark, folder)
    pair = arcs.select(F.col("src").alias("a"), F.col("dst").alias("src")).join(arcs, "src").join(arcs.select(F.col("src").alias("a"), "dst"), ["a", "dst"], "left_semi")
    own = pair.groupBy("a").agg(F.collect_list(F.struct("src", "dst")).alias("inner"))
    spokes = F.flatten(F.transform("inner", lambda e: F.array(F.struct(F.col("a").alias("src"), e["src"].alias("dst")), F.struct(F.col("a").alias("src"), e["dst"].alias("dst")), e)))
    own.select("a", spokes.alias("edges")).createOrReplaceTempView("edge_rows")
    return spark.sql("SELECT t.a, t.b, t.c FROM edge_rows r, LATERAL triangles_of(r.edges) t WHERE t.a = r.a")


add("op_udtf_triangles", udtf_triangles, o.graph("user") + " SELECT x.src AS a, x.dst AS b, y.dst AS c FROM edges x JOIN edges y ON x.dst = y.src JOIN edges z ON z.src = x.src AND z.dst = y.dst")

# Streams
_MINUTES = "SELECT CAST(epoch(date_trunc('minute', ts)) AS BIGINT) AS start, count(DISTINCT user_id) AS n FROM events GROUP BY 1"


def _streamed(f: Callable[[DataFrame], DataFrame], mode: str, batches: int = 3) -> Query:
    def run(spark: SparkSession, folder: str) -> DataFrame:
        path = streaming.staged(spark, table(spark, folder, "events"), batches)
        return streaming.drained(f(streaming.event_stream(spark, path)), mode)

    return run


add("stream_window_user", _streamed(streaming.window_counts, "complete"), f"SELECT start, n AS users, n * (n - 1) * (n - 2) // 6 AS triangles FROM ({_MINUTES})")
add("stream_session_user", _streamed(streaming.sessions, "complete"), "SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS events FROM (SELECT user_id, ts, sum(CASE WHEN p IS NULL OR ts >= p + INTERVAL 30 MINUTE THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events)) GROUP BY user_id, s")
add("stream_degrees_user", _streamed(streaming.user_activity, "complete"), "SELECT user_id, count(*) AS events FROM events GROUP BY 1")


def dedupe_late(spark: SparkSession, folder: str) -> DataFrame:
    """Every event is delivered twice; each comes out once."""
    events = table(spark, folder, "events")
    path = streaming.staged(spark, events.unionAll(events))
    return streaming.drained(streaming.without_repeats(streaming.event_stream(spark, path)), "append").select("event_id", "user_id")


add("stream_dedupe_late", dedupe_late, "SELECT event_id, user_id FROM events")


def coactive(spark: SparkSession, folder: str) -> DataFrame:
    """Pairs of events of different users at most a minute apart, by a join of two streams."""
    path = streaming.staged(spark, table(spark, folder, "events"))
    return streaming.drained(streaming.coactivity(streaming.event_stream(spark, path), streaming.event_stream(spark, path)), "append")


add("stream_coactivity_user", coactive, "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 1 MINUTE AND x.event_id <> y.event_id AND x.user_id < y.user_id")


def incremental(spark: SparkSession, folder: str) -> DataFrame:
    """The edges of g_user in batches; the sum of the increments is the count."""
    root = f"{shared_folder(spark)}/growing-{uuid.uuid4().hex}"
    edges = workloads.user(spark, folder)
    for k in range(3):
        edges.where(F.pmod(F.col("src") + F.col("dst"), F.lit(3)) == k).coalesce(1).write.mode("append").parquet(f"{root}/in")
    run = streaming.Incremental(spark, f"{root}/state")
    run.follow(spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(f"{root}/in"))
    return run.total()


add("stream_incremental_user", incremental, _user + _T)

for _name, (_f, _sql) in OPS.items():
    add(_name, _f, _sql)
for _name, (_f, _sql) in EXPERIMENTS.items():
    add(_name, _f, _sql)
