"""The disk index: exact answers from few pairs, passes over the rows, and searches of many queries."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pytest

from vecblock.functions import arrays as A
from vecblock.operators import exact, partition, search, tree
from vecblock.plans.vector_queries import PARAMS
from vecblock.sources import vectors as V

SF = "/root/testdata/sf0.001"


def _slow(qid, q, ids, x, k, metric, far, exclude_self):
    out = []
    for i, v in zip(qid.tolist(), q):
        d = A.distance(v, x, metric)
        best = [j for j in np.lexsort((ids, -d if far else d)).tolist() if not (exclude_self and ids[j] == i)][:k]
        out += [(i, int(ids[j]), float(d[j])) for j in best]
    return out


@pytest.mark.parametrize("metric", ["l2", "cosine", "l1"])
@pytest.mark.parametrize("far", [False, True])
@pytest.mark.parametrize("kind", ["plain", "ties", "copies", "far from zero", "zeros"])
def test_running_best_is_exact(metric, far, kind):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(3000, 6)) + 0.1
    if kind == "ties":
        x = np.round(x) + 0.5
    elif kind == "copies":
        x[:2000] = x[0]
    elif kind == "far from zero":
        x = x + 1000.0
    elif kind == "zeros" and metric != "cosine":
        x[::7] = 0
    ids = rng.permutation(3000)
    qid, q = ids[:90], x[:90]
    for exclude_self in (False, True):
        best = A.Best(qid, q, 5, metric, far, exclude_self)
        for a in range(0, 3000, 1100):
            best.add(ids[a : a + 1100], x[a : a + 1100])
        assert list(zip(*(c.tolist() for c in best.rows()))) == _slow(qid, q, ids, x, 5, metric, far, exclude_self)


def test_exact_answers_weigh_few_pairs_in_double_precision(monkeypatch):
    rng = np.random.default_rng(4)
    x, ids = rng.normal(size=(20000, 16)), np.arange(20000)
    pairs = []
    rough, distance = A.rough, A.distance
    monkeypatch.setattr(A, "rough", lambda q, x, metric: pairs.append(len(q) * len(x)) or rough(q, x, metric))
    monkeypatch.setattr(A, "distance", lambda q, x, metric: pairs.append(len(x)) or distance(q, x, metric))
    got = exact._best(10, "l2", False, True)(ids[:300], x[:300], ids, x)
    assert sum(pairs) < 300 * 20000 / 10
    assert list(zip(*(c.tolist() for c in got))) == _slow(ids[:300], x[:300], ids, x, 10, "l2", False, True)


def test_a_round_of_sums_reads_the_rows_once(spark):
    read = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            read.add(len(b))
            yield b

    df = V.hubs(spark, SF).selectExpr("vec_id", "'r' AS path", "v")
    n = df.count()
    got = partition._sums(df.mapInArrow(count, df.schema), {"r": np.zeros((1, 64))})
    assert read.value == n and [(p, c, k) for p, c, k, _ in got] == [("r", 0, n)]
    assert np.allclose(got[0][3], np.array([r.v for r in df.collect()]).sum(0))


def test_rows_of_many_leaves_get_the_statistics_of_each():
    rng = np.random.default_rng(5)
    at = rng.integers(0, 30, 500)
    t = pa.table({"leaf_path": [f"r.{a}" for a in at], "path": [f"r.{a}.0" for a in at], "vec_id": np.arange(500), "v": A.lists(rng.normal(size=(500, 7)))})
    got = tree._leaf_rows(t)
    assert sorted(r for r in got.column("vec_id").to_pylist() if r is not None) == list(range(500))
    for leaf in set(t.column("leaf_path").to_pylist()):
        want = tree._leaf_stats(t.filter(pa.compute.equal(t.column("leaf_path"), leaf))).to_pylist()[0]
        mine = got.filter(pa.compute.equal(got.column("leaf_path"), leaf)).to_pylist()
        (head,) = [r for r in mine if r["kind"] == 0]
        rows = [r for r in mine if r["kind"] == 1]
        assert head["n_rows"] == want["n_rows"] == len(rows)
        assert all(np.allclose(head[c], want[c]) for c in ("vec_sum", "centroid", "radius"))
        assert np.isclose(max(r["d_centroid"] for r in rows), want["radius"])


def test_a_beam_of_many_queries_opens_what_one_query_opens(spark, monkeypatch):
    v = V.hubs(spark, SF)
    lv = search.levels_of(tree.build(v, PARAMS))
    q = A.matrix(v.select("v").toArrow().column("v"))
    for p in (search.SearchParams(beam=1), search.SearchParams(beam=5), search.SearchParams(beam=3, farthest=True, node_score="bound")):
        want = sorted((i, s, *x) for i, o in enumerate(search.descend_local(lv, q, p, "l2")) for s, x in enumerate(o))
        for sparse in (0.0, 1e9):  # children alone, whole levels
            monkeypatch.setattr(search, "SPARSE", sparse)
            assert sorted(zip(*(c.tolist() for c in search.descend_beam(lv, q, p, "l2")))) == want


def test_queries_beyond_a_broadcast_meet_groups_of_leaves(spark, monkeypatch):
    """The same answers, and a task for each group of leaves instead of up to 16 for each leaf."""
    v = V.hubs(spark, SF)
    t, q = tree.build(v, PARAMS), V.queries_of(v, 2)
    p = search.SearchParams(beam=4)
    want = sorted(map(tuple, search.search(t, q, p).collect()))
    monkeypatch.setattr(exact, "QUERY_BLOCK", 0)
    assert sorted(map(tuple, search.search(t, q, p).collect())) == want
    for probes in (8192, 30):  # in one turn, in several
        monkeypatch.setattr(search, "MEET_PROBES", probes)
        found = search._scan_met(search.descend(t, q, p).where("is_leaf").selectExpr("query_id", "node_id AS leaf_id"), search.prepared(t, q), t.rows, p, "l2")
        assert sorted(map(tuple, exact.ranked(found, 10).collect())) == want
        assert found.groupBy("query_id").count().agg({"count": "max"}).first()[0] <= 10 * (1 + max(t.nodes.toArrow().column("node_id").to_pylist()) // search.MEET_LEAVES)
