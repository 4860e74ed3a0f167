"""Queries that took too long at size: the same results in fewer passes."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecblock.baselines import graphs as G
from vecblock.functions import arrays as A
from vecblock.operators import cache, exact, search, temporal, tree, view
from vecblock.plans.vector_queries import PARAMS
from vecblock.sources import vectors as V

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def held(spark):
    v = V.vectors(spark, SF)
    return v, V.queries_of(v, 20), tree.build(v, PARAMS)


def rows(df) -> list:
    return sorted((r.query_id, r["rank"], r.vec_id, round(r.dist, 9)) for r in df.collect())


def test_many_probes_copy_no_vector(held, monkeypatch):
    """More probes than travel as a list: a byte for each query and leaf tells what is open, and no query is joined to its probes."""
    v, q, t = held
    n, m = q.count(), t.levels[-1]
    monkeypatch.setattr(search, "PROBE_BYTES", n * m)
    for far in (False, True):
        want = exact.knn(v, q, 10, "chebyshev", farthest=far)
        got = search.search_exact(tree.with_metric(t, "chebyshev"), q, 10, farthest=far)
        assert rows(got) == rows(want) and "FlatMapCoGroups" not in got._jdf.queryExecution().toString()
    p = search.SearchParams(beam=3)
    few = search.search(t, q, p)
    monkeypatch.setattr(search, "PROBE_BYTES", 32 << 20)
    assert rows(few) == rows(search.search(t, q, p)) != []


def test_one_tree_for_several_metrics(spark, held):
    _, _, t = held
    other = tree.build(V.vectors(spark, SF), tree.TreeParams(**{**PARAMS.__dict__, "metric": "l1"}))
    mine = tree.with_metric(t, "l1")
    assert mine.params == other.params and mine.nodes.exceptAll(other.nodes).isEmpty() and mine.rows.exceptAll(other.rows).isEmpty()
    with pytest.raises(ValueError):
        tree.with_metric(t, "cosine")


@pytest.mark.parametrize("metric", ["l1", "chebyshev", "minkowski", "hamming"])
def test_distances_by_coordinate(metric):
    rng = np.random.default_rng(3)
    q, x = np.round(rng.normal(size=(70, 9)), 1), np.round(rng.normal(size=(2100, 9)), 1)
    ids, ok = rng.permutation(len(x)), rng.random((70, 2100)) < 0.01
    assert np.allclose(A.rough(q, x, metric), [A.distance(one, x, metric) for one in q], rtol=1e-12, atol=1e-12)
    row, found, dist = A.block_topk(q, x, ids, 7, metric, allowed=ok)
    for i in range(len(q)):
        at = np.flatnonzero(ok[i])
        d = A.distance(q[i], x[at], metric)
        order = np.lexsort((ids[at], d))[:7]
        assert found[row == i].tolist() == ids[at][order].tolist() and dist[row == i].tolist() == d[order].tolist()


def test_a_search_of_all_leaves_lists_no_probes(held, monkeypatch):
    v, q, t = held
    monkeypatch.setattr(search, "descend", lambda *a, **b: pytest.fail("probes were listed"))
    assert rows(search.search(t, q, search.SearchParams(beam=search.ALL))) == rows(exact.knn(v, q, 10))


def test_the_cache_reads_ahead(held, monkeypatch):
    """One read of Spark for the leaves of a batch; what the cache holds, loads and answers is as with a read for each leaf."""
    _, q, t = held
    p = search.SearchParams(beam=2)
    ahead, single = (cache.LeafCache(t, 3 * PARAMS.leaf_capacity * (8 * t.dim + 8)) for _ in range(2))
    got = ahead.search(q, p)
    assert rows(ahead.rows(got)) == rows(search.search(t, q, p)) and not ahead.read
    monkeypatch.setattr(cache, "READ_LEAVES", 1)
    assert single.search(q, p) == got
    assert (ahead.log, ahead.bytes_read, ahead.peak) == (single.log, single.bytes_read, single.peak) and ahead.peak <= ahead.max_bytes
    assert ahead.reads < single.reads / 2


def test_sessions_with_views_of_several_sizes(spark, held):
    v, q, _ = held
    s = q.join(temporal.order_correlated(q), "query_id").select("query_id", "seq", "v")
    sizes = [0, 20, 50]
    sessions = s.crossJoin(spark.createDataFrame([(i, z) for i, z in enumerate(sizes)], "session_id long, view_size int"))
    both = view.replay(v, sessions, 10, max(sizes), with_links=True, beam=2)
    for i, z in enumerate(sizes):
        one = view.replay(v, s.withColumn("session_id", F.lit(i).cast("long")), 10, z, with_links=True, beam=2)
        same = lambda t: sorted((r.seq, r.query_id, r.view_no, r.served_from, r.recall, tuple(r.ids)) for r in t.collect())
        assert same(both.where(F.col("session_id") == i)) == same(one)


@pytest.mark.parametrize("kind", ["layered", "disk_graph", "tree_rng"])
def test_graphs_from_kept_distances(kind, monkeypatch):
    """The same links and walks as with distances computed one hop at a time."""
    rng = np.random.default_rng(2)
    x, ids = rng.normal(size=(300, 12)), np.arange(300) * 3
    x[5] = x[6]
    p = {"metric": "l2", "degree": 6, "ef_build": 20, "width": 20}
    g = G.BUILDERS[kind](ids, x, p)
    monkeypatch.setattr(G, "TABLE_BYTES", 0)
    other = G.BUILDERS[kind](ids, x, p)
    links = "layers" if kind == "layered" else "links"
    assert g[links] == other[links]
    for q in x[:12]:
        for ef in (20, 300):
            steps: list[int] = []
            got, plain = G.walk(g, q, 5, ef, "l2"), G.walk(g, q, 5, ef, "l2", trace=steps)
            assert got[0].tolist() == plain[0].tolist() and got[1].tolist() == plain[1].tolist() and got[2:] == plain[2:] and len(steps) == got[2]


def test_graphs_in_bounded_shards(spark, monkeypatch):
    v = V.hubs(spark, SF)
    q, n = V.queries_of(v, 20), v.count()
    monkeypatch.setattr(G, "SHARD_ROWS", n // 3)
    g = G.build(v, "disk_graph", degree=8, width=16)
    sizes = [r.n for r in g.collect()]
    assert len(sizes) >= 3 and sum(sizes) == n
    assert rows(G.merged(G.search(g, q, 10, n), 10)) == rows(exact.knn(v, q, 10))
    assert {r.shard for r in G.trace(g, q.limit(1), 10).collect()} == {r.shard for r in g.collect()}
