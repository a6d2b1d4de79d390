"""Dense networks: edges in few bytes, and common neighbours without a list that moves."""

import datetime
from pathlib import Path

import numpy as np
import pytest

from tricount.operators import exact, graph, mapreduce, packed, workloads
from tricount.operators.derived import node_triangles_def
from tricount.session import shared_folder


def _events(spark, folder, minutes, users, present, seed=1):
    """Some users of each minute, with repeats, nulls and a minute of one user; the edges among them."""
    rng = np.random.default_rng(seed)
    start = datetime.datetime(2024, 1, 1)
    seen = [(start + datetime.timedelta(minutes=m), int(u) * 7 - 1000) for m in range(minutes) for u in rng.choice(users, present, replace=False)]
    odd = [seen[0], seen[0], (start, None), (None, 5), (start + datetime.timedelta(days=9), 99_999_999)]
    spark.createDataFrame(seen + odd, "ts timestamp_ntz, user_id long").write.parquet(f"{folder}/events.parquet")
    by: dict = {}
    for ts, u in seen:
        by.setdefault(ts, set()).add(u)
    met = {(a, b) for g in by.values() for a in g for b in g if a < b}
    ids = {u: i for i, u in enumerate(sorted({x for e in met for x in e}))}
    return {(ids[a], ids[b]) for a, b in met}


def _matrix(edges):
    n = max(b for _, b in edges) + 1
    m = np.zeros((n, n), dtype=np.int64)
    for a, b in edges:
        m[a, b] = m[b, a] = 1
    return m


def _bytes(spark):
    return sum(f.stat().st_size for f in Path(shared_folder(spark).removeprefix("file:")).rglob("*.parquet"))


def test_dense_network_takes_few_bytes(spark, tmp_path):
    want = _events(spark, tmp_path, 60, 2000, 70)
    before = _bytes(spark)
    got = workloads.user(spark, str(tmp_path))
    hashed = graph.relabel(got, "hashed")
    assert _bytes(spark) - before < 4 * len(want)  # two networks and their labels; one took as much before
    assert {tuple(r) for r in got.collect()} == want
    assert hashed.count() == len(want)


def test_counts_by_bits_in_rounds(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(packed, "BITS", 1 << 15)
    monkeypatch.setattr(packed, "PAIRS", 1 << 12)
    monkeypatch.setattr(packed, "RECORDS", 1)
    m = _matrix(_events(spark, tmp_path, 40, 300, 40))
    edges = workloads.user(spark, str(tmp_path))
    assert packed.of(edges) is not None
    six = int(np.trace(m @ m @ m))
    for net in (edges, graph.relabel(edges, "hashed"), graph.relabel(edges, "degree")):
        assert packed.of(net) is not None
        assert exact.count_intersect(net).collect()[0][0] * 6 == six
    ranked = graph.relabel(edges, "degree").collect()
    deg = np.bincount([x for r in ranked for x in r])
    assert (np.diff(deg) >= 0).all() and all(r.src < r.dst for r in ranked)
    for order in ("id", "random"):
        assert exact.count_intersect(edges, order).collect()[0][0] * 6 == six
    assert exact.count_node_centred(edges, raw=True).collect()[0].met == six
    assert exact.count_node_centred(edges).collect()[0][0] * 6 == six
    assert dict(node_triangles_def(edges).collect()) == dict(enumerate((np.diag(m @ m @ m) // 2).tolist()))
    plain = spark.createDataFrame(edges.collect(), "src long, dst long")
    assert packed.of(plain) is None
    assert {tuple(r) for r in mapreduce.bucket_triple_counts(edges, 4).collect()} == {tuple(r) for r in mapreduce.bucket_triple_counts(plain, 4).collect()}
    assert mapreduce.count_bucket_triples(edges, 5).collect()[0][0] * 6 == six


def test_sparse_network_is_formed_as_before(spark, tmp_path):
    want = _events(spark, tmp_path, 400, 4000, 2)
    edges = workloads.user(spark, str(tmp_path))
    assert packed.of(edges) is None
    assert {tuple(r) for r in edges.collect()} == want


@pytest.mark.parametrize("keys", [[], [0], [254, 255, 256, 511, 1 << 40], list(range(0, 10_000, 3))])
def test_packed_numbers(keys):
    assert packed.unpack(packed.pack(np.array(keys, dtype=np.int64))).tolist() == keys
