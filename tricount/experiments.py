"""The experiment workloads: modelled scaling, memory and idle time of both methods beside the overlapping one, with their SQL.

What a cluster of P processors would take is modelled from the work and the traffic of its blocks or tasks; the bench
measures what this machine takes.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles as o
from .operators import blocks, cost, dynamic, exchange, generators, graph, measures, tasks, workloads
from .session import cut

Query = Callable[[SparkSession, str], DataFrame]
EXPERIMENTS: dict[str, tuple[Query, str | None]] = {}

#: Numbers of blocks, of processors that work by tasks (one coordinates), nodes and degrees of the generated networks.
PARTS = [1, 2, 4, 8, 16, 50, 100, 200]
MEMORY = [4, 16, 50, 100, 200]
PROCESSORS = [5, 17, 65]
DEGREES = [10, 20, 50, 100]
SIZES = [1000, 5000, 10_000, 50_000]
WEAK = [4, 8, 16, 32, 64]
_PROCESSED = [("unit", "static"), ("unit", "shrinking"), ("degree", "static"), ("degree", "equal"), ("degree", "shrinking")]


def on(name: str, f: Callable[[DataFrame], DataFrame]) -> Query:
    return lambda spark, folder: f(workloads.GRAPHS[name](spark, folder))


def swept(values: list, row: Callable[[SparkSession, object], DataFrame]) -> Query:
    """The union of what ``row`` gives for each value of a parameter."""

    def run(spark: SparkSession, folder: str) -> DataFrame:
        out = None
        for x in values:
            one = row(spark, x)
            out = one if out is None else out.unionByName(one)
        return out

    return run


def united(queries: list[str]) -> str:
    """The union of queries that each bring their own tables."""
    return " UNION ALL ".join(f"SELECT * FROM ({q})" for q in queries)


# SQL ----------------------------------------------------------------------------------------------------------------


def _owners(parts: list[int], of: str, name: str) -> str:
    return f""", {name}_run AS (SELECT id, sum(f) OVER (ORDER BY id) - f AS before, sum(f) OVER (ORDER BY id) AS upto, sum(f) OVER () AS total, count(*) OVER () AS n FROM {of}),
      {name} AS MATERIALIZED (SELECT p.parts, id, CAST(least(p.parts - 1, CASE WHEN total > 0 THEN ((before + upto) * p.parts) // (2 * total) ELSE (id * p.parts) // n END) AS INTEGER) AS part FROM {name}_run, (SELECT unnest({parts}) AS parts) p)"""


def _both_cuts(parts: list[int]) -> str:
    return o.arcs() + o.cost("surrogate", "cs") + o.cost("owner", "co") + _owners(parts, "cs", "os") + _owners(parts, "co", "oo")


def speedup_sql(edges: str, parts: list[int], extra: str = "") -> str:
    placed = "SELECT x.parts, a.src AS v, a.dst AS u, x.part AS pv, y.part AS pu, ex.eff AS ev, ey.eff AS eu FROM arcs a JOIN eff ex ON ex.id = a.src JOIN eff ey ON ey.id = a.dst JOIN {0} x ON x.id = a.src JOIN {0} y ON y.id = a.dst AND y.parts = x.parts"
    return edges + _both_cuts(parts) + f""", pl AS MATERIALIZED ({placed.format("os")}), po AS ({placed.format("oo")}),
      once AS (SELECT DISTINCT parts, v, pv, pu, ev FROM pl WHERE pv <> pu),
      each AS (
        SELECT 'direct' AS scheme, parts, pv AS part, ev + eu AS t FROM pl UNION ALL SELECT 'direct', parts, pv, 2 + eu FROM pl WHERE pv <> pu UNION ALL SELECT 'direct', parts, pu, 2 + eu FROM pl WHERE pv <> pu
        UNION ALL SELECT 'surrogate', parts, pu, ev + eu FROM pl UNION ALL SELECT 'surrogate', parts, pv, 1 + ev FROM once UNION ALL SELECT 'surrogate', parts, pu, 1 + ev FROM once
        UNION ALL SELECT 'overlapping', parts, pv, ev + eu FROM po),
      sums AS (SELECT scheme, parts, part, sum(t) AS t FROM each GROUP BY 1, 2, 3), whole AS (SELECT sum(ev + eu) AS total FROM pl WHERE parts = {parts[0]}),
      found AS (SELECT scheme, parts, CAST(max(t) AS BIGINT) AS most, round(CAST(any_value(total) AS DOUBLE) / CAST(max(t) AS DOUBLE), 4) AS speedup FROM sums, whole GROUP BY 1, 2)
      SELECT {extra} scheme, parts, most, speedup FROM found"""


def memory_sql(edges: str, parts: list[int], columns: str = "parts, nonoverlap, overlapping, ratio") -> str:
    return edges + _both_cuts(parts) + f""",
      known AS (SELECT parts, part, id FROM os UNION SELECT os.parts, os.part, a.dst FROM os JOIN arcs a ON a.src = os.id),
      mine AS (SELECT parts, max(v + coalesce(e, 0)) * 8 AS nonoverlap FROM (SELECT parts, part, count(*) AS v FROM known GROUP BY 1, 2) k LEFT JOIN (SELECT os.parts, os.part, count(*) AS e FROM os JOIN arcs a ON a.src = os.id GROUP BY 1, 2) l USING (parts, part) GROUP BY 1),
      held AS (SELECT parts, part, id FROM oo UNION SELECT oo.parts, oo.part, a.dst FROM oo JOIN arcs a ON a.src = oo.id),
      theirs AS (SELECT parts, max(b) AS overlapping FROM (SELECT h.parts, h.part, (count(*) + sum(eff)) * 8 AS b FROM held h JOIN eff ON eff.id = h.id GROUP BY 1, 2) GROUP BY 1),
      found AS (SELECT parts, CAST(nonoverlap AS BIGINT) AS nonoverlap, CAST(overlapping AS BIGINT) AS overlapping, round(CAST(overlapping AS DOUBLE) / CAST(nonoverlap AS DOUBLE), 4) AS ratio FROM mine JOIN theirs USING (parts))
      SELECT {columns} FROM found"""


def replayed(processors: int, granularity: str) -> str:
    """sched(k, free, cnt) after cost, work: when each worker is free and how many tasks it had, after k tasks."""
    w = processors - 1
    return o.tasks(processors, granularity) + f""",
      tw AS MATERIALIZED (SELECT CAST(seq AS BIGINT) AS seq, phase, CAST((SELECT coalesce(sum(work.f), 0) FROM work WHERE work.id BETWEEN v AND v + t - 1) AS BIGINT) AS w FROM tasks),
      tm AS (SELECT count(*) FILTER (WHERE phase = 'initial') AS lead, count(*) AS n FROM tw),
      sched(k, free, cnt) AS (
        SELECT CAST(0 AS BIGINT), list_transform(range({w}), lambda x: CAST(0 AS BIGINT)), list_transform(range({w}), lambda x: CAST(0 AS BIGINT))
        UNION ALL
        SELECT k + 1, list_transform(free, lambda x, i: CASE WHEN i = pos THEN x + w ELSE x END), list_transform(cnt, lambda x, i: CASE WHEN i = pos THEN x + 1 ELSE x END)
        FROM (SELECT sched.k, free, cnt, tw.w, CASE WHEN sched.k < tm.lead THEN sched.k + 1 ELSE list_position(free, list_min(free)) END AS pos FROM sched JOIN tw ON tw.seq = sched.k, tm)),
      done AS (SELECT free, cnt FROM sched, tm WHERE sched.k = tm.n)"""


def replay_sql(edges: str, processors: int, kind: str, granularity: str, columns: str = "worker, tasks, busy, idle") -> str:
    return edges + o.arcs() + o.cost(kind) + o.cost("owner", "work") + replayed(processors, granularity) + f""",
      workers AS (SELECT unnest(range({processors - 1})) AS i, free, cnt FROM done),
      found AS (SELECT CAST(i AS INTEGER) AS worker, CAST(cnt[i + 1] AS INTEGER) AS tasks, free[i + 1] AS busy, list_max(free) - free[i + 1] AS idle FROM workers)
      SELECT {columns} FROM found"""


def sweep_sql(edges: str, processors: list[int], combos: list[tuple[str, str]], extra: str = "") -> str:
    base = edges + o.arcs() + o.cost("unit", "c_unit") + o.cost("degree", "c_degree") + o.cost("owner", "work")
    each = []
    for kind, granularity in combos:
        for p in processors:
            each.append(f"""WITH RECURSIVE cost AS (SELECT * FROM c_{kind}){replayed(p, granularity)}
              SELECT '{kind}' AS "cost", '{granularity}' AS granularity, {p} AS processors, CAST((SELECT n FROM tm) AS INTEGER) AS tasks, list_max(free) AS makespan, CAST({p - 1} * list_max(free) - list_sum(free) AS BIGINT) AS idle, round(CAST(list_sum(free) AS DOUBLE) / list_max(free), 4) AS speedup FROM done""")
    return base + f", found AS ({united(each)}) SELECT {extra} \"cost\", granularity, processors, tasks, makespan, idle, speedup FROM found"


# Strong scaling, memory and the tables of both methods beside the overlapping one ---------------------------------------


def _sweep(e: DataFrame, processors: list[int]) -> DataFrame:
    out = None
    for kind in ("unit", "degree"):
        one = dynamic.sweep(e, processors, (kind,), tuple(g for k, g in _PROCESSED if k == kind))
        out = one if out is None else out.unionByName(one)
    return out


def dynamic_beside_overlapping(e: DataFrame, processors: list[int]) -> DataFrame:
    """processors, dynamic, overlapping: modelled speedups; the dynamic method has one worker less."""
    mine = dynamic.sweep(e, processors, ("degree",), ("shrinking",)).select("processors", F.col("speedup").alias("dynamic"))
    theirs = measures.scheme_speedup(e, processors).where("scheme = 'overlapping'").select(F.col("parts").alias("processors"), F.col("speedup").alias("overlapping"))
    return mine.join(theirs, "processors")


for _g in ("part", "star", "token"):
    EXPERIMENTS[f"scheme_speedup_{_g}"] = on(_g, lambda e: measures.scheme_speedup(e, PARTS)), speedup_sql(o.graph(_g), PARTS)
    EXPERIMENTS[f"memory_by_parts_{_g}"] = on(_g, lambda e: measures.memory(e, MEMORY)), memory_sql(o.graph(_g), MEMORY)
    EXPERIMENTS[f"memory_by_parts_{_g}_hashed"] = on(_g, lambda e: measures.memory(graph.relabel(e, "hashed"), MEMORY)), None
    EXPERIMENTS[f"dynamic_speedup_{_g}"] = on(_g, lambda e: _sweep(e, PROCESSORS)), sweep_sql(o.graph(_g), PROCESSORS, _PROCESSED)
    EXPERIMENTS[f"dynamic_beside_overlapping_{_g}"] = (
        on(_g, lambda e: dynamic_beside_overlapping(e, PROCESSORS)),
        f"SELECT d.processors, d.speedup AS dynamic, x.speedup AS overlapping FROM ({sweep_sql(o.graph(_g), PROCESSORS, [('degree', 'shrinking')])}) d JOIN ({speedup_sql(o.graph(_g), PROCESSORS)}) x ON x.parts = d.processors AND x.scheme = 'overlapping'",
    )
for _k in ("static", "equal", "shrinking"):
    EXPERIMENTS[f"replay_{_k}_part"] = on("part", lambda e, k=_k: dynamic.replay(e, 17, "degree", k)), replay_sql(o.graph("part"), 17, "degree", _k)
EXPERIMENTS["idle_by_worker_part"] = on("part", lambda e: dynamic.replay(e, 17).select("worker", "idle")), replay_sql(o.graph("part"), 17, "degree", "shrinking", "worker, idle")
EXPERIMENTS["space_ratio_part"] = on("part", lambda e: measures.space_ratio(e, 16)), memory_sql(o.graph("part"), [16], "nonoverlap, overlapping, ratio")

# Generated networks ---------------------------------------------------------------------------------------------------


def _pa(spark: SparkSession, n: int, d: int) -> DataFrame:
    return cut(generators.pa(spark, n, d))


def _weak(spark: SparkSession, p: int) -> DataFrame:
    """Network and blocks grow together: the largest time tells how the time would grow."""
    return measures.scheme_speedup(_pa(spark, p * 250, 10), [p]).where("scheme = 'surrogate'").select("parts", "most", "speedup")


def _size(spark: SparkSession, n: int) -> DataFrame:
    return measures.scheme_speedup(_pa(spark, n, 10), [4, 16, 64]).select(F.lit(n).alias("nodes"), "scheme", "parts", "most", "speedup")


def _degree(how: str) -> Callable[[SparkSession, int], DataFrame]:
    def row(spark: SparkSession, d: int) -> DataFrame:
        e = _pa(spark, 4000, d)
        return measures.memory(e if how == "natural" else graph.relabel(e, how), [20]).select(F.lit(d).alias("degree"), "nonoverlap", "overlapping", "ratio")

    return row


def _dynamic_size(spark: SparkSession, n: int) -> DataFrame:
    return dynamic.sweep(_pa(spark, n, 10), [5, 17], ("degree",), ("shrinking",)).select(F.lit(n).alias("nodes"), "processors", "tasks", "makespan", "idle", "speedup")


def _dynamic_weak(spark: SparkSession, p: int) -> DataFrame:
    return dynamic.sweep(_pa(spark, p * 250, 10), [p + 1], ("degree",), ("shrinking",)).select("processors", "tasks", "makespan", "idle", "speedup")


EXPERIMENTS["weak_scaling_pa"] = swept(WEAK, _weak), united([f"SELECT parts, most, speedup FROM ({speedup_sql(o.pa_graph(p * 250, 10), [p])}) WHERE scheme = 'surrogate'" for p in WEAK])
EXPERIMENTS["size_scaling_pa"] = swept(SIZES, _size), united([speedup_sql(o.pa_graph(n, 10), [4, 16, 64], f"{n} AS nodes,") for n in SIZES])
EXPERIMENTS["memory_by_degree_pa"] = swept(DEGREES, _degree("natural")), united([memory_sql(o.pa_graph(4000, d), [20], f"{d} AS degree, nonoverlap, overlapping, ratio") for d in DEGREES])
EXPERIMENTS["memory_by_degree_pa_hashed"] = swept(DEGREES, _degree("hashed")), None
_SHORT = "processors, tasks, makespan, idle, speedup"
EXPERIMENTS["dynamic_size_scaling_pa"] = swept(SIZES[:3], _dynamic_size), united([f"SELECT {n} AS nodes, {_SHORT} FROM ({sweep_sql(o.pa_graph(n, 10), [5, 17], [('degree', 'shrinking')])})" for n in SIZES[:3]])
EXPERIMENTS["dynamic_weak_scaling_pa"] = swept(WEAK, _dynamic_weak), united([f"SELECT {_SHORT} FROM ({sweep_sql(o.pa_graph(p * 250, 10), [p + 1], [('degree', 'shrinking')])})" for p in WEAK])


def hub(spark: SparkSession, n: int) -> DataFrame:
    """A node that is linked to all of a ring: its degree is n - 1."""
    return spark.range(1, n).select(F.array(F.struct(F.lit(0).cast("long").alias("src"), F.col("id").alias("dst")), F.struct(F.least("id", F.col("id") % (n - 1) + 1).alias("src"), F.greatest("id", F.col("id") % (n - 1) + 1).alias("dst"))).alias("e")).select(F.explode("e").alias("e")).select("e.src", "e.dst")


_HUB = "WITH RECURSIVE edges AS MATERIALIZED (SELECT 0 AS src, i AS dst FROM range(1, 4000) r(i) UNION ALL SELECT least(i, i % 3999 + 1), greatest(i, i % 3999 + 1) FROM range(1, 4000) r(i))"
EXPERIMENTS["memory_hub"] = lambda spark, folder: measures.memory(cut(hub(spark, 4000)), [4, 16, 100]), memory_sql(_HUB, [4, 16, 100])

# Single measures ------------------------------------------------------------------------------------------------------

_CUT16 = o.graph("part") + o.arcs() + o.cost("surrogate") + o.blocks(16) + o.PLACED
EXPERIMENTS["completion_messages"] = (
    on("next", lambda e: exchange.completions(cut(blocks.assign(cost.node_cost(e, "degree"), 16).select("id", "part")))),
    o.graph("next") + o.arcs() + o.cost("degree") + o.blocks(16) + " SELECT part, (SELECT count(DISTINCT part) FROM owner) - 1 AS messages FROM (SELECT DISTINCT part FROM owner)",
)
EXPERIMENTS["task_size_part"] = on("part", lambda e: tasks.task_size(cost.node_cost(e, "degree"), 20, 50).select(F.col("size").cast("long").alias("size"))), o.graph("part") + o.arcs() + " SELECT CAST(coalesce(sum(deg), 0) AS BIGINT) AS size FROM deg WHERE id BETWEEN 20 AND 69"
EXPERIMENTS["complexity_terms_part"] = (
    on("part", lambda e: measures.complexity_terms(exchange.build(e, 16))),
    _CUT16 + """, known AS (SELECT part, id FROM owner UNION SELECT x.part, a.dst FROM arcs a JOIN owner x ON x.id = a.src),
      ve AS (SELECT k.part, count(*) + any_value(coalesce(e, 0)) AS b FROM known k LEFT JOIN (SELECT x.part, count(*) AS e FROM arcs a JOIN owner x ON x.id = a.src GROUP BY 1) l ON l.part = k.part GROUP BY 1),
      busy AS (SELECT pu AS part, ev + eu AS w FROM placed UNION ALL SELECT pv, ev FROM (SELECT DISTINCT v, pv, pu, ev FROM placed WHERE pv <> pu))
      SELECT (SELECT max(b) FROM ve) AS block, (SELECT max(deg) FROM deg) AS d_max, (SELECT max(eff) FROM eff) AS eff_max, (SELECT CAST(max(w) AS BIGINT) FROM (SELECT part, sum(w) AS w FROM busy GROUP BY 1)) AS work""",
)
_LOADS = [(k, p) for k in ("owner", "surrogate") for p in (4, 16)]
EXPERIMENTS["modelled_speedup_part"] = (
    on("part", lambda e: measures.modelled_speedup(e, [4, 16], ("owner", "surrogate"))),
    o.graph("part") + o.arcs() + o.cost("owner", "c_owner") + o.cost("surrogate", "c_surrogate") + "".join(o.blocks(p, f"c_{k}", f"o_{k}_{p}") for k, p in _LOADS) + " "
    + " UNION ALL ".join(f"SELECT '{k}' AS cut, {p} AS parts, round(CAST(max(w) AS DOUBLE) * {p} / CAST(sum(w) AS DOUBLE), 4) AS imbalance, round(CAST(sum(w) AS DOUBLE) / CAST(max(w) AS DOUBLE), 4) AS speedup FROM (SELECT part, sum(s.f) AS w FROM o_{k}_{p} x JOIN c_surrogate s ON s.id = x.id GROUP BY 1)" for k, p in _LOADS),
)
_BUCKETS = f"b AS (SELECT src, dst, {graph.mix_sql('src')} % 4 AS bs, {graph.mix_sql('dst')} % 4 AS bd FROM edges), t3 AS (SELECT i, j, k FROM range(4) x(i), range(4) y(j), range(4) z(k) WHERE i < j AND j < k), copies AS MATERIALIZED (SELECT b.*, i * 16 + j * 4 + k AS key FROM b JOIN t3 ON bs IN (i, j, k) AND bd IN (i, j, k))"
EXPERIMENTS["intermediate_rows"] = (
    on("part", measures.intermediate_rows),
    o.graph("part") + o.arcs() + f", {_BUCKETS} SELECT 'two_paths' AS method, CAST(sum(deg * (deg - 1) // 2) AS BIGINT) AS \"rows\" FROM deg UNION ALL SELECT 'two_paths_oriented', CAST(sum(eff * (eff - 1) // 2) AS BIGINT) FROM eff UNION ALL SELECT 'bucket_triples', count(*) FROM copies",
)


def _multiplicity(e: DataFrame) -> DataFrame:
    from .operators import mapreduce

    return mapreduce.bucket_triple_counts(e, 4).select("kinds", "found")


EXPERIMENTS["bucket_multiplicity_user"] = (
    on("user", _multiplicity),
    o.graph("user") + f", {_BUCKETS}, met AS (SELECT x.bs AS p, x.bd AS q, y.bd AS r FROM copies x JOIN copies y ON y.key = x.key AND y.src = x.dst JOIN copies z ON z.key = x.key AND z.src = x.src AND z.dst = y.dst) SELECT CAST(len(list_distinct([p, q, r])) AS INTEGER) AS kinds, count(*) AS found FROM met GROUP BY 1",
)
