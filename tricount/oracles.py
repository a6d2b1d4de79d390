"""SQL for DuckDB that gives what the queries give, built from common table expressions."""

from __future__ import annotations

from .operators.generators import STEPS
from .operators.graph import mix_sql
from .operators.workloads import PART, SUPPLIER

_LINES = "SELECT DISTINCT o_custkey AS c, l_partkey AS p, l_suppkey AS s FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
_WORDS = "SELECT doc_id, regexp_extract_all(text, '[a-zA-Z]+') AS w FROM documents WHERE lang = 'en'"


def _pairs(groups: str) -> str:
    return f"SELECT DISTINCT x.m AS a, y.m AS b FROM ({groups}) x JOIN ({groups}) y ON x.g = y.g AND x.m < y.m"


# Pairs a, b of keys before canonical form, by network.
RAW = {
    "part": _pairs("SELECT DISTINCT l_orderkey AS g, l_partkey AS m FROM lineitem"),
    "supp": _pairs("SELECT DISTINCT l_orderkey AS g, l_suppkey AS m FROM lineitem"),
    "cust": _pairs(f"SELECT DISTINCT p || '/' || s AS g, c AS m FROM ({_LINES})"),
    "star": f"SELECT c AS a, p + {PART} AS b FROM ({_LINES}) UNION SELECT c, s + {SUPPLIER} FROM ({_LINES}) UNION SELECT p + {PART}, s + {SUPPLIER} FROM ({_LINES})",
    "bip": f"SELECT DISTINCT c AS a, p + {PART} AS b FROM ({_LINES})",
    "token": f"SELECT w[i] AS a, w[i + 1] AS b FROM (SELECT w, unnest(range(1, len(w))) AS i FROM ({_WORDS}))",
    "user": _pairs("SELECT DISTINCT date_trunc('minute', ts) AS g, user_id AS m FROM events"),
    "next": "SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events",
    "link": "SELECT 'page:' || page_id AS a, 'href:' || unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS b FROM pages",
    "doc": "SELECT DISTINCT x.doc_id AS a, y.doc_id AS b FROM held x JOIN held y ON x.g = y.g AND x.doc_id < y.doc_id",
    "emb": "SELECT x.vec_id AS a, y.vec_id AS b FROM embeddings x JOIN embeddings y ON x.vec_id < y.vec_id WHERE list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) > 0.25",
}
_BEFORE = {
    "doc": f"""words AS ({_WORDS}),
      grams AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM words WHERE len(w) >= 5)),
      held AS (SELECT doc_id, g FROM grams WHERE g IN (SELECT g FROM grams GROUP BY g HAVING count(*) BETWEEN 2 AND 50)),""",
}


def graph(name: str, how: str = "natural") -> str:
    """``WITH`` .. edges(src, dst) of a network."""
    return f"""WITH RECURSIVE {_BEFORE.get(name, "")} raw AS ({RAW[name]}),
      canon AS (SELECT DISTINCT least(a, b) AS a, greatest(a, b) AS b FROM raw WHERE a <> b),
      keys AS (SELECT a AS k FROM canon UNION SELECT b FROM canon),
      named AS (SELECT k, row_number() OVER (ORDER BY k) - 1 AS id FROM keys),
      edges AS MATERIALIZED (SELECT least(x.id, y.id) AS src, greatest(x.id, y.id) AS dst FROM canon JOIN named x ON x.k = a JOIN named y ON y.k = b)"""


def pa_graph(n: int, d: int, seed: int = 42) -> str:
    return _pa_graph(f"range({n * (d // 2)}) r(j)", d, seed)


def pa_graph_over(table: str, key: str, d: int, seed: int = 42) -> str:
    k = d // 2
    return _pa_graph(f"(SELECT n * {k} + i AS j FROM (SELECT row_number() OVER (ORDER BY k) - 1 AS n FROM (SELECT DISTINCT {key} AS k FROM {table} WHERE {key} IS NOT NULL)), range({k}) r(i))", d, seed)


def _pa_graph(slots: str, d: int, seed: int) -> str:
    k = d // 2
    return f"""WITH RECURSIVE chase AS (
        SELECT j, 2 * j + 1 AS s, 0 AS step FROM {slots}
        UNION ALL SELECT j, {mix_sql("s", seed)} % s, step + 1 FROM chase WHERE s % 2 = 1 AND step < {STEPS}),
      canon AS (SELECT DISTINCT least(2 * j // {2 * k}, s // {2 * k}) AS src, greatest(2 * j // {2 * k}, s // {2 * k}) AS dst FROM chase WHERE s % 2 = 0),
      edges AS MATERIALIZED (SELECT src, dst FROM canon WHERE src <> dst)"""


def arcs(order: str = "degree") -> str:
    """near, deg, arcs, eff after edges."""
    low = "(dx.deg, src) < (dy.deg, dst)" if order == "degree" else "src < dst"
    return f""", near AS MATERIALIZED (SELECT src, dst FROM edges UNION ALL SELECT dst, src FROM edges),
      deg AS MATERIALIZED (SELECT src AS id, count(*) AS deg FROM near GROUP BY 1),
      arcs AS MATERIALIZED (SELECT CASE WHEN {low} THEN src ELSE dst END AS src, CASE WHEN {low} THEN dst ELSE src END AS dst FROM edges JOIN deg dx ON dx.id = src JOIN deg dy ON dy.id = dst),
      eff AS MATERIALIZED (SELECT deg.id, deg, coalesce(e, 0) AS eff FROM deg LEFT JOIN (SELECT src AS id, count(*) AS e FROM arcs GROUP BY 1) x ON x.id = deg.id)"""


TRIANGLES = """, tri AS MATERIALIZED (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM arcs x JOIN arcs y ON x.dst = y.src JOIN arcs z ON z.src = x.src AND z.dst = y.dst)"""
PER_NODE = """, corners AS (SELECT id, count(*) AS n FROM (SELECT a AS id FROM tri UNION ALL SELECT b FROM tri UNION ALL SELECT c FROM tri) GROUP BY 1),
      pernode AS (SELECT deg.id, deg, coalesce(n, 0) AS triangles FROM deg LEFT JOIN corners ON corners.id = deg.id)"""
SUPPORT = """, sides AS (SELECT least(a, b) AS src, greatest(a, b) AS dst FROM tri UNION ALL SELECT least(b, c), greatest(b, c) FROM tri UNION ALL SELECT least(a, c), greatest(a, c) FROM tri),
      support AS (SELECT e.src, e.dst, coalesce(n, 0) AS support FROM edges e LEFT JOIN (SELECT src, dst, count(*) AS n FROM sides GROUP BY 1, 2) s ON s.src = e.src AND s.dst = e.dst)"""


def cost(kind: str, name: str = "cost") -> str:
    """cost(id, f) after arcs."""
    if kind in ("owner", "surrogate"):
        end = "src" if kind == "owner" else "dst"
        return f""", {name} AS MATERIALIZED (SELECT eff.id, coalesce(w, 0) AS f FROM eff LEFT JOIN (SELECT {end} AS id, sum(x.eff + y.eff) AS w FROM arcs JOIN eff x ON x.id = src JOIN eff y ON y.id = dst GROUP BY 1) k ON k.id = eff.id)"""
    f = {"unit": "1", "degree": "deg", "effective": "eff"}[kind]
    return f", {name} AS MATERIALIZED (SELECT id, {f} AS f FROM eff)"


def blocks(parts: int, of: str = "cost", name: str = "owner") -> str:
    """owner(id, part, f, before, upto, total) after cost."""
    return f""", {name}_run AS (SELECT id, f, sum(f) OVER (ORDER BY id) - f AS before, sum(f) OVER (ORDER BY id) AS upto, sum(f) OVER () AS total, count(*) OVER () AS n FROM {of}),
      {name} AS MATERIALIZED (SELECT id, f, before, upto, total, CAST(least({parts - 1}, CASE WHEN total > 0 THEN ((before + upto) * {parts}) // (2 * total) ELSE (id * {parts}) // n END) AS INTEGER) AS part FROM {name}_run)"""


PLACED = """, placed AS MATERIALIZED (SELECT arcs.src AS v, arcs.dst AS u, x.part AS pv, y.part AS pu, ex.eff AS ev, ey.eff AS eu FROM arcs JOIN owner x ON x.id = arcs.src JOIN owner y ON y.id = arcs.dst JOIN eff ex ON ex.id = arcs.src JOIN eff ey ON ey.id = arcs.dst)"""
OVERLAP = """, core AS MATERIALIZED (SELECT part, id, id AS via FROM owner), named_in AS MATERIALIZED (SELECT DISTINCT x.part, arcs.dst AS id FROM arcs JOIN owner x ON x.id = arcs.src),
      inblock AS MATERIALIZED (SELECT part, id FROM core UNION SELECT part, id FROM named_in)"""


def exchange(scheme: str) -> str:
    """part, local_triangles, remote_triangles, triangles; crossing edges count for u's block with surrogate, else for v's."""
    at = "y.part" if scheme == "surrogate" else "x.part"
    return f"""SELECT p.part, coalesce(l, 0) AS local_triangles, coalesce(r, 0) AS remote_triangles, coalesce(l, 0) + coalesce(r, 0) AS triangles
      FROM (SELECT DISTINCT part FROM owner) p LEFT JOIN (
        SELECT {at} AS part, count(*) FILTER (WHERE x.part = y.part) AS l, count(*) FILTER (WHERE x.part <> y.part) AS r
        FROM tri JOIN owner x ON x.id = tri.a JOIN owner y ON y.id = tri.b GROUP BY 1) t ON t.part = p.part"""


def traffic(by_part: bool = False) -> str:
    key = "part, " if by_part else ""
    group = "GROUP BY part" if by_part else ""
    asked = "SELECT pv AS part, 1 AS m, 0 AS x FROM {0} UNION ALL SELECT pu, 1, eu FROM {0}"
    once = "(SELECT DISTINCT pv, u, pu, eu FROM placed WHERE pv <> pu)"
    rows = {
        "direct": asked.format("(SELECT * FROM placed WHERE pv <> pu)"), "cached": asked.format(once), "scan": asked.format(once),
        "surrogate": "SELECT pv AS part, 1 AS m, ev AS x FROM (SELECT DISTINCT v, pv, pu, ev FROM placed WHERE pv <> pu)",
    }
    return " UNION ALL ".join(f"SELECT '{s}' AS scheme, {key}coalesce(CAST(sum(m) AS BIGINT), 0) AS messages, coalesce(CAST(sum(x) AS BIGINT), 0) AS elements FROM ({q}) {group}" for s, q in rows.items())


def tasks(processors: int, granularity: str) -> str:
    """tasks(seq, phase, v, t, size) after cost: cuts by recursive steps over running sums."""
    w = processors - 1
    if granularity == "static":
        return blocks(w, name="dealt") + """, tasks AS (SELECT row_number() OVER (ORDER BY part) - 1 AS seq, 'initial' AS phase, min(id) AS v, count(*) AS t, sum(f) AS size FROM dealt GROUP BY part)"""
    queue = {
        "shrinking": f""", step(k, v, rest) AS (
          SELECT 0, (SELECT half FROM half), (SELECT max(total) FROM run) - (SELECT s FROM half)
          UNION ALL
          SELECT k + 1, CASE WHEN rest = 0 THEN (SELECT max(id) + 1 FROM run) ELSE (SELECT min(id) + 1 FROM run WHERE id >= step.v AND {w} * (upto - (SELECT max(total) FROM run) + step.rest) >= step.rest) END,
                 CASE WHEN rest = 0 THEN -1 ELSE (SELECT max(total) FROM run) - (SELECT min(upto) FROM run WHERE id >= step.v AND {w} * (upto - (SELECT max(total) FROM run) + step.rest) >= step.rest) END
          FROM step WHERE step.v <= (SELECT max(id) FROM run)),
        cuts AS (SELECT k, v, lead(v) OVER (ORDER BY k) AS e FROM step),
        queued AS (SELECT k, v, e - v AS t FROM cuts WHERE e IS NOT NULL AND e > v)""",
        "equal": f""", later AS (SELECT id, f, sum(f) OVER (ORDER BY id) - f AS before, sum(f) OVER (ORDER BY id) AS upto, sum(f) OVER () AS total FROM cost WHERE id >= (SELECT half FROM half)),
        queued AS (SELECT least({2 * w - 1}, ((before + upto) * {2 * w}) // (2 * total)) AS k, min(id) AS v, count(*) AS t FROM later GROUP BY 1)""",
    }[granularity]
    return f""", run AS MATERIALIZED (SELECT id, f, sum(f) OVER (ORDER BY id) AS upto, sum(f) OVER () AS total FROM cost),
      half AS (SELECT min(id) + 1 AS half, min(upto) AS s FROM run WHERE 2 * upto >= total),
      early AS (SELECT id, least({w - 1}, ((upto - f) * {w}) // (SELECT s FROM half)) AS k FROM run WHERE id < (SELECT half FROM half)){queue},
      spans AS (SELECT 0 AS ph, k, min(id) AS v, count(*) AS t FROM early GROUP BY k UNION ALL SELECT 1, k, v, t FROM queued),
      tasks AS (SELECT row_number() OVER (ORDER BY ph, k) - 1 AS seq, CASE WHEN ph = 0 THEN 'initial' ELSE 'queue' END AS phase, v, t, (SELECT sum(f) FROM cost WHERE id BETWEEN v AND v + t - 1) AS size FROM spans)"""
