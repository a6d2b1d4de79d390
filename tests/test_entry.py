"""The registered queries against their SQL, at the smallest scale."""

import decimal

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: One of each kind; the others differ in network or parameter.
SOME = "edges_pa tri_intersect_pa completion_messages op_cte_recursive edges_user tri_intersect_user tri_per_node_part cost_surrogate nonoverlap_count_surrogate_part traffic_part_p16 tasks_shrinking_part task_counts_part overlap_count_part sparsify_part clustering_avg op_join_asof op_window_range op_array_sets op_udtf_triangles udf_common_user udf_list_sizes_user stream_window_user stream_session_user stream_dedupe_late stream_incremental_user stream_coactivity_user replay_shrinking_part memory_hub scheme_speedup_part truss_user wedge_sample_part nonoverlap_sizes_part".split()


def plain(v):
    return round(float(v), 6) if isinstance(v, float | decimal.Decimal) else v


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, sf, con, name):
    df = entry.queries()[name](spark, sf)
    names = sorted(df.columns)
    rows = sorted((tuple(plain(r[c]) for c in names) for r in df.collect()), key=repr)
    got = con.execute(entry.oracle_sql()[name])
    columns = [d[0] for d in got.description]
    assert sorted(columns) == names
    assert rows == sorted((tuple(plain(r[columns.index(c)]) for c in names) for r in got.fetchall()), key=repr)


def test_entry_and_catalogue(spark):
    assert len(entry.entry(spark).columns) == 2
    assert set(entry.oracle_sql()) <= set(entry.queries())
