"""Trees, searches, views, growth and streams on small collections."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecblock.baselines import graphs as G
from vecblock.functions import metrics as M
from vecblock.operators import exact, graph, ingest, measures, search, temporal, tree, view
from vecblock.operators.partition import PartitionParams
from vecblock.operators.search import ALL, SearchParams
from vecblock.sources import formats, vectors

PARAMS = tree.TreeParams(leaf_capacity=16, inner_capacity=4, partition=PartitionParams(max_cluster_rows=12, fanout=3, lloyd_iters=4))


def points(spark, n=200, dim=4, seed=0):
    x = np.random.default_rng(seed).normal(size=(n, dim))
    return spark.createDataFrame([(i, [float(z) for z in v]) for i, v in enumerate(x)], "vec_id long, v array<double>")


def answers(df):
    return {(r.query_id, r.rank): (r.vec_id, round(r.dist, 9)) for r in df.collect()}


@pytest.fixture(scope="module")
def data(spark):
    df = points(spark).cache()
    return df, vectors.queries_of(df), tree.build(df, PARAMS)


def test_full_beam_is_exact_both_ways(data):
    df, q, t = data
    for far in (False, True):
        want = answers(exact.knn(df, q, 5, farthest=far))
        assert answers(search.search(t, q, SearchParams(k=5, beam=ALL, farthest=far))) == want
        assert answers(search.search_exact(t, q, 5, farthest=far)) == want


def test_joined_levels_and_leaves_agree(data, monkeypatch):
    df, q, t = data
    want = answers(search.search(t, q, SearchParams(k=5, beam=3)))
    monkeypatch.setattr(search, "LEVEL_BYTES", 0)
    monkeypatch.setattr(search, "PROBE_BYTES", 0)
    assert answers(search.search(t, q, SearchParams(k=5, beam=3))) == want


def test_invariants_of_every_build(spark, data, monkeypatch):
    df, q, t = data
    monkeypatch.setattr(tree, "DRIVER_BYTES", 0)
    wide = tree.build(df, tree.TreeParams(**{**PARAMS.__dict__, "partition": PartitionParams(max_cluster_rows=12, fanout=3, lloyd_iters=4, local_rows=60, sample_rows=80)}))
    for one in (t, wide):
        assert all(r.violations == 0 for r in tree.invariants(one).collect())
    assert answers(search.search(wide, q, SearchParams(k=5, beam=ALL))) == answers(exact.knn(df, q, 5))


def test_order_of_input_does_not_matter(spark, data):
    df, q, t = data
    other = tree.build(df.orderBy(F.desc("vec_id")).repartition(3), PARAMS)
    assert sorted(map(tuple, other.rows.select("leaf_id", "vec_id").collect())) == sorted(map(tuple, t.rows.select("leaf_id", "vec_id").collect()))


def test_small_and_empty(spark):
    empty = spark.createDataFrame([], "vec_id long, v array<double>")
    q = spark.createDataFrame([(0, [1.0, 2.0])], "query_id long, v array<double>")
    t = tree.build(empty, PARAMS)
    assert t.n == 0 and search.search(t, q).count() == 0
    one = spark.createDataFrame([(7, [1.0, 2.0])], "vec_id long, v array<double>")
    t = tree.build(one, PARAMS)
    assert [r.vec_id for r in search.search(t, q, SearchParams(k=5)).collect()] == [7]
    assert search.search(t, q, SearchParams(k=0)).count() == 0
    assert exact.knn(one, q, 0).count() == 0


def test_duplicates_degenerate(spark):
    df = spark.createDataFrame([(i, [1.0, 1.0]) for i in range(50)], "vec_id long, v array<double>")
    t = tree.build(df, PARAMS)
    assert all(r.violations == 0 for r in tree.invariants(t).collect())
    q = vectors.queries_of(df)
    assert answers(search.search(t, q, SearchParams(k=3, beam=ALL))) == answers(exact.knn(df, q, 3))


def test_bad_vectors(spark):
    df = spark.createDataFrame([(0, [1.0, 2.0]), (1, None), (2, [float("nan"), 1.0]), (3, [1.0]), (4, [0.0, 0.0])], "vec_id long, v array<double>")
    ok = df.select("vec_id", M.checked(F.col("v"), 2, "cosine", "null_dist").alias("v")).where("v IS NOT NULL")
    assert [r.vec_id for r in ok.collect()] == [0]
    with pytest.raises(Exception, match="bad vector"):
        df.select(M.checked(F.col("v"), 2).alias("v")).collect()


def test_save_open_and_versions(spark, data, tmp_path):
    df, q, t = data
    want = answers(search.search(t, q, SearchParams(k=5, beam=3)))
    tree.save(t, f"file:{tmp_path}/index")
    grown = ingest.insert(t, points(spark, 40, seed=9).withColumn("vec_id", F.col("vec_id") + 1000))
    tree.save(grown, f"file:{tmp_path}/index")
    assert tree.versions(spark, f"file:{tmp_path}/index") == [0, 1]
    assert answers(search.search(tree.open_tree(spark, f"file:{tmp_path}/index", 0), q, SearchParams(k=5, beam=3))) == want
    assert tree.open_tree(spark, f"file:{tmp_path}/index").n == 240
    spark.dataSource.register(formats.leaf_source())
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    leaf = t.rows.first().leaf_id
    got = spark.read.format("blocktree").option("path", f"{tmp_path}/index/v000000").load().where(F.col("leaf_id") == leaf)
    assert got.count() == t.rows.where(F.col("leaf_id") == leaf).count()


def test_growth(spark, data):
    df, q, _ = data
    t = ingest.insert(tree.build(df.where("vec_id % 5 = 0"), PARAMS), df.where("vec_id % 5 <> 0"))
    assert all(r.violations == 0 for r in tree.invariants(t).collect())
    assert answers(search.search(t, q, SearchParams(k=5, beam=ALL))) == answers(exact.knn(df, q, 5))
    t = ingest.compact(ingest.delete(t, df.where("vec_id % 3 = 0")))
    assert all(r.violations == 0 for r in tree.invariants(t).collect())
    assert answers(search.search(t, q, SearchParams(k=5, beam=ALL))) == answers(exact.knn(df.where("vec_id % 3 <> 0"), q, 5))


def test_links_and_greedy(spark, data):
    df, q, t = data
    links = graph.build_links(t, 6, 3).cache()
    assert links.groupBy("src").count().where("count > 6").isEmpty() and links.where("src = dst").isEmpty()
    truth = exact.knn(df, q, 5)
    plain = search.search(t, q, SearchParams(k=5, beam=1))
    with_links = search.search(t, q, SearchParams(k=5, beam=1), links)
    r = lambda f: measures.recall(f, truth, 5).first().recall
    assert r(with_links) >= r(plain)
    qq = search.prepared(t, q)
    a = graph.greedy(plain, links, df, qq, 5)
    b = graph.greedy(plain, links, df, qq, 5, local=False)
    assert r(b) >= r(plain) and r(a) >= r(plain)


def test_views(spark, data):
    df, q, t = data
    v = view.create(t, q, 30)
    assert len(v.ids) == 30
    inside = view.as_rows(spark, v)
    for far in (False, True):
        assert answers(view.search_view(v, q, 4, far)) == answers(exact.knn(inside, q, 4, farthest=far))
    again = view.from_json(view.to_json(v))
    assert again.ids.tolist() == v.ids.tolist()


def test_lru_trace(spark):
    log = spark.createDataFrame([(i, 0, ord(c) - 97) for i, c in enumerate("abcadb")], "seq long, query_id long, node_id long")
    want = [False, False, False, True, False, False]
    assert [r.hit for r in measures.lru(log, 3).orderBy("seq").collect()] == want
    assert [r.hit for r in measures.lru_replay(log.withColumn("trace", F.lit(0).cast("long")), 3).orderBy("seq").collect()] == want


def test_orders_are_permutations(spark, data):
    _, q, _ = data
    for order in (temporal.order_correlated, temporal.order_random):
        assert sorted(r.seq for r in order(q).collect()) == list(range(20))


@pytest.mark.parametrize("kind", ["layered", "disk_graph", "tree_rng"])
def test_baselines_reach_full_recall(spark, data, kind):
    df, q, _ = data
    g = G.build(df, kind, degree=8, ef_build=32, width=32)
    truth = exact.knn(df, q, 5)
    assert measures.recall(G.merged(G.search(g, q, 5, 200), 5), truth, 5).first().recall > 0.97
    assert G.max_degree(g) <= 17


def test_dumps_round_trip(spark, tmp_path):
    x = np.arange(12, dtype=float).reshape(3, 4)
    for kind in ("fvecs", "ivecs", "bvecs"):
        (tmp_path / kind).write_bytes(formats.encode_dump(x, kind))
        got = formats.read_dump(spark, f"file:{tmp_path}/{kind}", kind).orderBy("pos").collect()
        assert [r.v for r in got] == x.tolist()
    df = spark.createDataFrame([("[1, 2.5]",), ("x,1",)], "t string")
    assert [r.v for r in formats.parse_text(df, "t").collect()] == [[1.0, 2.5], [None, 1.0]]
