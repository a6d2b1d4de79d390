"""Hand-worked network, closed forms, invariants, equivalence of methods."""

from collections import Counter

import numpy as np
import pytest

from tricount.operators import approx, blocks, cost, derived, dynamic, exact, exchange, generators, graph, mapreduce, measures, orient, overlap, tasks, workloads

F1 = [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3), (3, 4), (3, 5), (4, 5), (0, 6)]


def net(spark, pairs):
    return spark.createDataFrame(pairs, "src long, dst long").coalesce(1)


@pytest.fixture(scope="module")
def f1(spark):
    return net(spark, F1).cache()


def value(df):
    return df.collect()[0][0]


def by_id(df, column):
    return [getattr(r, column) for r in sorted(df.collect(), key=lambda r: r.id)]


def test_node_table(f1):
    t = orient.adjacency(f1)
    assert by_id(t, "deg") == [4, 3, 3, 5, 2, 2, 1]
    assert by_id(t, "eff") == [1, 3, 2, 0, 2, 1, 1]
    assert by_id(t, "nbrs") == [[3], [0, 2, 3], [0, 3], [], [3, 5], [3], [0]]


def test_costs(f1):
    assert by_id(cost.node_cost(f1, "owner"), "f") == [1, 12, 5, 0, 5, 1, 2]
    assert by_id(cost.node_cost(f1, "surrogate"), "f") == [9, 0, 5, 9, 0, 3, 0]
    assert by_id(cost.node_cost(f1, "custom", expr="deg + eff"), "f") == [5, 6, 5, 5, 4, 3, 2]
    with pytest.raises(ValueError):
        cost.node_cost(f1, "nothing")


def test_kernels_agree(f1):
    found = [exact.count_intersect(f1), exact.count_closure(f1), exact.count_node_centred(f1), exact.count_all_triples(f1), exact.count_matrix(f1), exact.count_ordered(f1), exact.count_intersect(f1, "random"), exact.count_intersect(f1, kernel="merge"), exact.count_intersect(f1, kernel="gallop")]
    assert [value(x) for x in found] == [5] * len(found)
    assert value(exact.count_node_centred(f1, raw=True)) == 30
    assert by_id(derived.node_triangles(f1), "triangles") == [3, 3, 3, 4, 1, 1, 0] == by_id(derived.node_triangles_def(f1), "triangles")


@pytest.mark.parametrize(
    ("kind", "parts", "owner", "messages", "found"),
    [
        ("surrogate", 2, "0001111", {"direct": (8, 1), "cached": (4, 1), "surrogate": (4, 7)}, [4, 1]),
        ("surrogate", 3, "0112222", {"direct": (12, 3), "cached": (8, 2), "surrogate": (6, 12)}, [2, 2, 1]),
        ("owner", 2, "0011111", {"direct": (10, 4), "cached": (6, 3), "surrogate": (4, 7)}, [2, 3]),
        ("unit", 3, "0011122", {"direct": (14, 5), "cached": (12, 5), "surrogate": (6, 10)}, [2, 2, 1]),
    ],
)
def test_exchange_schemes(f1, kind, parts, owner, messages, found):
    assert "".join(map(str, by_id(blocks.assign(cost.node_cost(f1, kind), parts), "part"))) == owner
    cut = exchange.build(f1, parts, kind)
    seen = {r.scheme: (r.messages, r.elements) for r in exchange.traffic(cut).collect()}
    assert {k: seen[k] for k in messages} == messages
    for scheme in exchange.SCHEMES:
        rows = sorted(exchange.count(cut, scheme).collect(), key=lambda r: r.part)
        assert sum(r.triangles for r in rows) == 5
        if scheme == "surrogate":
            assert [r.triangles for r in rows] == found
    assert value(overlap.count(overlap.build(cut)).agg({"triangles": "sum"})) == 5
    assert value(overlap.count(overlap.build(cut, "induced")).agg({"triangles": "sum"})) == 5
    assert value(exchange.sizes(cut).agg({"e_count": "sum"})) == len(F1)


def test_guards_send_the_same(f1):
    cut = exchange.build(f1, 3, "surrogate")
    rows = {d: sorted((r.dest, r.src) for r in exchange.messages(cut, d).collect()) for d in ("last", "set")}
    assert rows["last"] == rows["set"] and len(rows["set"]) == 6


def test_tasks_of_the_fixture(spark, f1):
    unit = [(r.v, r.t) for r in tasks.table(spark, cost.node_cost(f1, "unit"), 3).collect()]
    degree = [(r.v, r.t) for r in tasks.table(spark, cost.node_cost(f1, "degree"), 3).collect()]
    assert unit == [(0, 2), (2, 2), (4, 2), (6, 1)]
    assert degree == [(0, 2), (2, 1), (3, 1), (4, 2), (6, 1)]
    assert [r.triangles for r in sorted(dynamic.count(f1, 3).collect())] == [3, 1, 0, 1, 0]
    assert sorted(map(tuple, dynamic.count(f1, 3, mode="shuffle").collect())) == sorted(map(tuple, dynamic.count(f1, 3).collect()))
    with pytest.raises(ValueError):
        tasks.table(spark, cost.node_cost(f1, "unit"), 1)


def test_tasks_cover_and_replay():
    c = tasks.Costs([0, 5, 5, 9, 30, 31, 31, 40], 1, 7)
    for kind in ("static", "equal", "shrinking"):
        for p in (2, 3, 5, 9):
            spans = [x[1:] for x in tasks.plan(c, p, kind)]
            assert spans[0][0] == 0 and spans[-1][1] == 7 and all(a[1] == b[0] for a, b in zip(spans, spans[1:], strict=False))
    log, idle = tasks.replay([4, 2, 2, 1], 2, 2)
    assert log == [(0, 0, 0, 4), (1, 1, 0, 2), (2, 1, 2, 4), (3, 0, 4, 5)] and idle == [0, 1]
    assert tasks.idle_share([1, 1, 1, 1], 2, 2) == 0 and tasks.gini([1, 1, 1]) == 0


@pytest.mark.parametrize(
    ("pairs", "t"),
    [
        ([(i, j) for i in range(7) for j in range(i + 1, 7)], 35),
        ([(0, i) for i in range(1, 9)] + [(i, i % 8 + 1) for i in range(1, 9)], 8),  # a wheel; some pairs are reversed
        ([(0, 1), (1, 2), (2, 3), (3, 0)], 0),
        ([(0, 1), (1, 0), (1, 1), (1, 2), (2, 0), (0, 2)], 1),
        ([], 0),
    ],
)
def test_closed_forms(spark, pairs, t):
    e = graph.canonicalize(net(spark, pairs))
    assert value(exact.count_intersect(e)) == t
    assert value(mapreduce.count_two_paths(e)) == t == value(mapreduce.count_two_paths(e, oriented=True))


def test_baselines(f1):
    for rho in (3, 5):
        assert value(mapreduce.count_bucket_triples(f1, rho)) == 5 == value(mapreduce.count_bucket_pairs_triples(f1, rho))


def test_generator_and_labels(spark):
    e = generators.pa(spark, 1000, 10).cache()
    assert (e.count(), value(exact.count_intersect(e)), generators.pa_slots_left(spark, 1000, 10)) == (4878, 1087, 0)
    for how in ("hashed", "degree"):
        again = graph.relabel(e, how).cache()
        assert again.count() == 4878 and value(exact.count_intersect(again)) == 1087
        assert again.selectExpr("max(dst) + 1").collect()[0][0] == measures.summary(e).collect()[0].n


def test_derived(spark, f1):
    s = {(r.src, r.dst): r.support for r in derived.edge_support(f1).collect()}
    assert s[(0, 1)] == 2 and s[(0, 6)] == 0 and sum(s.values()) == 15
    assert sorted(map(tuple, derived.k_truss(f1, 4).collect())) == [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3)]
    assert sorted((r.triangles, r.nodes) for r in derived.triangle_components(f1).collect()) == [(1, 3), (4, 4)]
    assert by_id(derived.local_clustering(f1), "clustering")[:2] == [0.5, 1.0]
    assert {(r.u, r.w): r.paths for r in derived.closure_candidates(f1).collect()}[(0, 4)] == 1


def test_estimates(spark):
    e = generators.complete(spark, 30).cache()
    assert approx.sparsify(e, 1.0).collect()[0].estimate == 4060
    assert approx.stream_sample(e, 1000).collect()[0].estimate == 4060
    row = approx.compared(approx.wedge_sample(e, 0.5), e).collect()[0]
    assert row.error == 0 and row.exact == 4060


def test_trends(spark):
    """New cost cuts the surrogate's work no worse than the old one; an owned block is within the overlapping one under equal cuts."""
    e = graph.relabel(generators.pa(spark, 800, 10), "hashed").cache()
    ratio = {r.cut: r.imbalance for r in measures.modelled_speedup(e, [8], ("owner", "surrogate")).collect()}
    assert ratio["surrogate"] <= ratio["owner"]
    cut = exchange.build(e, 8)
    mine = {r.part: r.e_count for r in exchange.sizes(cut).collect()}
    theirs = {r.part: r.e_count for r in overlap.sizes(overlap.build(cut)).collect()}
    assert all(mine[p] <= theirs[p] for p in mine)
    sent = measures.redundancy(cut).collect()[0]
    assert sent.surrogate <= sent.direct


def test_plans_have_no_cartesian_product(f1):
    text = exact.count_intersect(f1)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text


def test_common_entries_equal_set_intersections(monkeypatch):
    """Lists sent against lists held, also where look-ups are cut into many chunks and where ids are too large for joint keys."""
    rng = np.random.default_rng(4)
    for spread in (1, 1 << 56):
        ids = np.sort(rng.choice(60, 25, replace=False)) * spread
        held = [np.sort(rng.choice(60, int(rng.integers(0, 9)), replace=False)) * spread for _ in ids]
        sent = [np.sort(rng.choice(60, int(rng.integers(0, 12)), replace=False)) * spread for _ in range(40)]
        own = dict(zip(ids.tolist(), map(set, (h.tolist() for h in held)), strict=True))
        want = sum(len(set(x.tolist()) & own.get(u, set())) for x in sent for u in x.tolist())
        flat = lambda xs: (np.concatenate([[0], np.cumsum([len(x) for x in xs])]), np.concatenate(xs))
        for chunk in (1, 7, 1 << 20):
            monkeypatch.setattr(exchange, "CHUNK", chunk)
            assert exchange.common_entries(ids, *flat(held), *flat(sent)) == want


def test_surrogate_moves_each_list_once(spark):
    """The plan of the surrogate's count has one exchange of lists; many small batches give the same counts."""
    e = graph.relabel(generators.pa(spark, 600, 10), "hashed")
    cut = exchange.build(e, 5)
    t = value(exact.count_intersect(e))
    assert sum(r.triangles for r in exchange.count(cut, "surrogate").collect()) == t
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        assert sum(r.triangles for r in exchange.count(cut, "surrogate").collect()) == t
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    plan = exchange.receive(cut, exchange.messages(cut))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "Join" not in plan


def test_lists_cross_once_for_each_block(spark, monkeypatch):
    """Counts over many blocks equal those over one; the one exchange of lists stands behind no join, and no pair of lists is a row."""
    e = graph.relabel(generators.pa(spark, 400, 10), "hashed").cache()
    want = value(exact.count_intersect(e, kernel="hash"))
    once = {(r.id, r.triangles) for r in derived.node_triangles(e).collect()}
    monkeypatch.setattr(exact, "ENTRIES", 150)
    monkeypatch.setattr(exact, "UNITS", 64)
    dealt = exact._sent(orient.orient(e))
    rows = dealt.where("kind = 1").select("dest", "src").collect()
    assert len({r.dest for r in rows}) > 8 and len(rows) == len(set(rows)) < e.count()
    assert want == value(exact.count_intersect(e)) == value(exact.count_closure(e)) == value(exact.count_node_centred(e))
    assert once == {(r.id, r.triangles) for r in derived.node_triangles(e).collect()} == {(r.id, r.triangles) for r in derived.node_triangles_def(e).collect()}
    plan = exact.count_intersect(e)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan


def test_tasks_of_tiny_networks(spark):
    one = spark.createDataFrame([(0, 3)], "id long, f long")
    assert tasks.collected(one).n == 1 and tasks.collected(one.limit(0)).n == 0
    assert value(tasks.task_size(one, 0, 5)) == 3 and value(tasks.task_size(one, 1, 5)) == 0


def test_sweeps_agree_with_single_measures(f1):
    cut = exchange.build(f1, 3)
    rows = {(r.scheme, r.parts): r for r in measures.scheme_speedup(f1, [1, 3]).collect()}
    assert rows[("surrogate", 1)].most == 26 and rows[("overlapping", 1)].speedup == 1.0
    own = measures.memory(f1, [3]).collect()[0]
    assert own.nonoverlap == max(r.bytes for r in measures.space(exchange.sizes(cut)).collect())
    whole = dynamic.sweep(f1, [3], ("degree",), ("shrinking",)).collect()[0]
    each = dynamic.replay(f1, 3).collect()
    assert whole.makespan == max(r.busy for r in each) and whole.idle == sum(r.idle for r in each) and whole.tasks == 5


def test_cuts_are_exact_beyond_the_units(spark):
    """Few units, each of many ids, give the tasks that single ids give; also where costs are zero."""
    rng = np.random.default_rng(3)
    for f in (rng.integers(0, 9, 90), np.where(np.arange(90) % 40 == 3, 500, 0), np.zeros(90, dtype=int)):
        costs = spark.createDataFrame([(i, int(x)) for i, x in enumerate(f)], "id long, f long").coalesce(1).cache()
        single, coarse = tasks.collected(costs), tasks.collected(costs, units=4)
        assert (single.step, coarse.step, len(coarse.upto)) == (1, 23, 5)
        for kind in ("static", "equal", "shrinking"):
            for p in (2, 5, 17):
                assert tasks.plan(coarse, p, kind) == tasks.plan(single, p, kind)
        assert [coarse.below(i) for i in range(91)] == [single.below(i) for i in range(91)]


def test_star_with_parts_among_the_suppliers_numbers(spark, tmp_path):
    """Part 1,000,005 has the number of supplier 5: links met in both directions stay one edge, and a loop goes."""
    spark.createDataFrame([(1, 1_000_005, 5), (1, 1_000_005, 7), (2, 1_000_007, 5)], "l_orderkey long, l_partkey long, l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(1, 3), (2, 4)], "o_orderkey long, o_custkey long").write.parquet(f"{tmp_path}/orders.parquet")
    rows = sorted(map(tuple, workloads.star(spark, str(tmp_path)).collect()))
    assert rows == [(0, 2), (0, 3), (1, 2), (1, 3), (2, 3)]


def test_overlapping_blocks_broadcast_no_list(f1):
    """Lists are joined by merging, and met where their block is: no list reaches the driver."""
    built = overlap.build(exchange.build(f1, 3, "owner"))
    plan = built._jdf.queryExecution().optimizedPlan().toString()
    assert "strategy=merge" in plan
    rows = overlap.count(built)
    text = rows._jdf.queryExecution().executedPlan().toString()
    assert sum(r.triangles for r in rows.collect()) == 5 and "array_intersect" not in text


def test_reducers_of_buckets_move_no_two_path(spark, monkeypatch):
    """The bucket methods meet lists in blocks: no two-path goes through a join or a shuffle, whatever the number of blocks."""
    e = graph.relabel(generators.pa(spark, 300, 10), "hashed").cache()
    for rho in (4,):
        each = {}
        for r in mapreduce.triple_copies(e, rho).collect():
            each.setdefault(tuple(r.key), {}).setdefault(r.src, {})[r.dst] = (r.bs, r.bd)
        want = [0] * 4
        for near in each.values():
            for a in near:
                for b, (x, y) in near[a].items():
                    for c in near[a].keys() & near.get(b, {}).keys():
                        want[len({x, y, near[a][c][1]})] += 1
        monkeypatch.setattr(exact, "ENTRIES", 150)
        monkeypatch.setattr(exact, "UNITS", 64)
        met = mapreduce.bucket_triple_counts(e, rho)
        assert {r.kinds: r.found for r in met.collect()} == {k: n for k, n in enumerate(want) if n}
        assert value(mapreduce.count_bucket_triples(e, rho)) == value(mapreduce.count_bucket_pairs_triples(e, rho)) == value(exact.count_intersect(e))
    assert "Join" not in met._jdf.queryExecution().executedPlan().toString()


def test_pairs_of_lists_are_formed_where_they_meet(spark, monkeypatch):
    """A row of two lists stands behind no join, and the pairs are those of the arcs, over many blocks too; tasks over a shuffle form none."""
    e = graph.relabel(generators.pa(spark, 300, 10), "hashed").cache()
    near = {}
    for r in orient.orient(e).collect():
        near.setdefault(r.src, []).append(r.dst)
    want = sorted((v, u, sorted(x), sorted(near[u])) for v, x in near.items() if len(x) > 1 for u in x if u in near)
    monkeypatch.setattr(exact, "ENTRIES", 150)
    monkeypatch.setattr(exact, "UNITS", 64)
    rows = exact.paired_lists(e)
    assert sorted((r.v, r.u, r.nv, r.nu) for r in rows.collect()) == want
    assert "Join" not in rows._jdf.queryExecution().executedPlan().toString()
    moved = dynamic.count(e, 3, mode="shuffle")
    assert "array_intersect" not in moved._jdf.queryExecution().executedPlan().toString()
    assert sum(r.triangles for r in moved.collect()) == value(exact.count_intersect(e))


def test_two_paths_are_closed_where_edges_are_held(spark, monkeypatch):
    """No two-path goes through a join, over many blocks too, and ids may be large."""
    e = graph.relabel(generators.pa(spark, 300, 10), "hashed").cache()
    far = e.selectExpr(f"src + {1 << 61} AS src", f"dst + {1 << 61} AS dst")
    paths = mapreduce.two_paths(e, True).join(e.toDF("u", "w"), ["u", "w"], "left_semi").count()
    assert value(mapreduce.count_two_paths(far, oriented=True)) == paths
    monkeypatch.setattr(exact, "ENTRIES", 150)
    monkeypatch.setattr(exact, "UNITS", 64)
    for oriented in (False, True):
        found = mapreduce.count_two_paths(e, oriented)
        assert value(found) == paths
    assert "u <" not in found._jdf.queryExecution().executedPlan().toString()
    assert value(mapreduce.count_two_paths(e.limit(0))) == 0


def test_speedup_makes_no_row_for_an_arc_and_a_number_of_blocks(spark, monkeypatch):
    """No table that is stored has more rows than the network, and the times are those of single arcs."""
    e = graph.relabel(generators.pa(spark, 120, 6), "hashed").cache()
    kept, store = [], measures.stored
    monkeypatch.setattr(measures, "stored", lambda df: kept.append(store(df)) or kept[-1])
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 7)
    try:
        got = {(r.scheme, r.parts): r.most for r in measures.scheme_speedup(e, [1, 3, 8]).collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert max(t.count() for t in kept) <= e.count()
    arcs = [tuple(r) for r in orient.orient(e).collect()]
    eff = Counter(v for v, _ in arcs)
    for p in (1, 3, 8):
        own, other = ({r.id: r.part for r in blocks.assign(cost.node_cost(e, k), p).collect()} for k in ("surrogate", "owner"))
        t = {s: Counter() for s in ("direct", "surrogate", "overlapping")}
        for v, u in arcs:
            a, b = own[v], own[u]
            t["direct"][a] += eff[v] + eff[u]
            t["surrogate"][b] += eff[v] + eff[u]
            t["overlapping"][other[v]] += eff[v] + eff[u]
            if a != b:
                t["direct"][a] += 2 + eff[u]
                t["direct"][b] += 2 + eff[u]
        for v, b in {(v, own[u]) for v, u in arcs if own[v] != own[u]}:
            t["surrogate"][own[v]] += 1 + eff[v]
            t["surrogate"][b] += 1 + eff[v]
        assert all(got[s, p] == max(x.values()) for s, x in t.items())


def test_replies_meet_the_block_without_pairs_of_lists(spark):
    """direct, cached and unguarded messages: counts of every block are those of scan and surrogate; no row holds two lists."""
    e = graph.relabel(generators.pa(spark, 200, 10), "hashed").cache()
    owned = exchange.build(e, 5)
    rows = {}
    for scheme, dedupe in (("direct", "last"), ("cached", "last"), ("scan", "last"), ("surrogate", "last"), ("surrogate", "none")):
        found = exchange.count(owned, scheme, dedupe)
        rows[scheme, dedupe] = sorted(map(tuple, found.collect()))
        assert scheme == "scan" or "array_intersect" not in found._jdf.queryExecution().executedPlan().toString()
    assert rows["direct", "last"] == rows["cached", "last"] == rows["scan", "last"]
    assert rows["surrogate", "last"] == rows["surrogate", "none"]
    assert sum(r[3] for r in rows["direct", "last"]) == sum(r[3] for r in rows["surrogate", "last"]) == value(exact.count_intersect(e))


def test_no_edge_moves_to_get_its_labels_or_degrees(spark, monkeypatch):
    """Few nodes are held by every task; with more, joins give the same. Stored tables that the labels replace are gone."""
    ids = net(spark, [(10 * a, 10 * b) for a, b in F1])
    names = spark.createDataFrame([(f"w{a}", f"w{b}") for a, b in F1] + [("Wide", "w é")], "src string, dst string").coalesce(1)
    assert "Join" not in orient.orient(ids)._jdf.queryExecution().optimizedPlan().toString()

    def found():
        return [sorted(map(tuple, df.collect())) for df in (orient.orient(ids), graph.relabel(ids), graph.relabel(ids, "degree"), graph.relabel(names), graph.relabel(net(spark, [])))]

    few = found()
    assert few[1] == sorted(F1) and (0, 1) in few[3] and not few[4]
    monkeypatch.setattr(graph, "TOGETHER", 3)
    assert found() == few
    monkeypatch.setattr(graph, "HELD", 2)
    assert "Join" in orient.orient(ids)._jdf.queryExecution().optimizedPlan().toString()
    assert found() == few
    gone = []
    monkeypatch.setattr(graph, "remove", lambda _, paths: gone.extend(paths))
    graph.relabel(ids)
    assert len(gone) == 2


def test_members_of_a_group_meet_after_one_move(spark):
    """Each row moves once to its group, and pairs once to be made distinct; nulls and repeats make no pair."""
    rows = spark.createDataFrame([(1, 5), (1, 3), (1, 3), (1, 9), (2, 3), (2, 5), (3, 7), (None, 3), (None, 4), (4, None), (4, 8)], "g long, m long")
    pairs = workloads._together(rows, ["g"], "m")
    assert sorted(map(tuple, pairs.collect())) == [(3, 5), (3, 9), (5, 9)]
    plan = pairs._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    assert "Join" not in plan
