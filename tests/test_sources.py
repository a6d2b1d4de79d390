from tricount import plans, sources, streaming
from tricount.operators import exact, generators


def test_readers_and_writers(spark, tmp_path):
    e = generators.complete(spark, 6)
    (tmp_path / "edges.txt").write_text("# comment\n0\t1\n1\t2\nbad\tline\n")
    assert sorted(map(tuple, sources.edge_list(spark, str(tmp_path / "edges.txt")).collect())) == [(0, 1), (1, 2)]
    (tmp_path / "adj.txt").write_text("# comment\n0 1 2\n1 2\n3\n")
    assert sorted(map(tuple, sources.adjacency_text(spark, str(tmp_path / "adj.txt")).collect())) == [(0, 1), (0, 2), (1, 2)]
    for kind in ("parquet", "orc", "json"):
        sources.write_edges(e, str(tmp_path / kind), kind)
        assert exact.count_intersect(sources.edges(spark, str(tmp_path / kind), kind)).collect()[0][0] == 20


def test_incremental_is_repeatable(spark, tmp_path):
    run = streaming.Incremental(spark, str(tmp_path))
    run.start()
    first, second = spark.createDataFrame([(0, 1), (1, 2)], "src long, dst long"), spark.createDataFrame([(0, 2), (2, 3), (1, 3)], "src long, dst long")
    run.add(first, 0)
    run.add(second, 1)
    run.add(second, 1)  # a batch that is delivered again
    assert run.total().collect()[0][0] == 2 == run.check().collect()[0][0]


def test_planner(spark):
    e = generators.complete(spark, 8)
    assert plans.choose(e).count(e).collect()[0][0] == 56
    assert plans.unordered_rows(e) == 8 * 7 * 6 and "order" in plans.explain(e)
