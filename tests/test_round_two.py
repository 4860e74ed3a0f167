"""Growth, bounded cache, views that serve, other norms, streams: what the registered queries do not hold against SQL."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecblock.functions import arrays as A
from vecblock.operators import cache, exact, graph, ingest, search, tree, view
from vecblock.operators.partition import PartitionParams
from vecblock.operators.search import ALL, SearchParams
from vecblock.streaming import streams

PARAMS = tree.TreeParams(leaf_capacity=16, inner_capacity=4, partition=PartitionParams(max_cluster_rows=12, fanout=3, lloyd_iters=4))


@pytest.fixture(scope="module")
def vectors(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(240, 6)) + 4 * np.eye(6)[np.arange(240) % 6]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, v array<double>")
    return x, df, df.where("vec_id % 12 = 0").select(F.col("vec_id").alias("query_id"), "v")


@pytest.fixture(scope="module")
def index(vectors):
    return tree.build(vectors[1], PARAMS)


def rows_of(df):
    return sorted((r.query_id, r["rank"], r.vec_id, round(r.dist, 9)) for r in df.collect())


def test_empty_clusters_begin_anew():
    x = np.array([[0.0], [0.0], [0.0], [10.0], [11.0], [50.0]])
    ids = np.arange(6)
    at, centers = A.kmeans(x, ids, 4, 10, "random", 3, "drop")
    again, more = A.kmeans(x, ids, 4, 10, "random", 3, "farthest")
    assert len(more) >= len(centers) and len(more) == 4
    assert ((x - more[again]) ** 2).sum() <= ((x - centers[at]) ** 2).sum()


def test_insert_writes_only_touched_leaves(spark, vectors, index):
    x, df, _ = vectors
    near = spark.createDataFrame([(1000 + k, (x[0] + 0.01 * k).tolist()) for k in range(3)], "vec_id long, v array<double>")
    grown = ingest.insert(index, near)
    changed = {r.leaf_id for r in ingest.changed_leaves(index, grown).collect()}
    old = {r.vec_id: r.leaf_id for r in index.rows.collect()}
    new = {r.vec_id: r.leaf_id for r in grown.rows.collect()}
    assert 1 <= len(changed) <= 4 < index.levels[-1]
    assert len(new) == 243 and grown.n == 243
    assert {i for i in old if old[i] != new[i]} == {i for i in old if new[i] in changed}
    assert tree.invariants(grown).agg(F.sum("violations")).first()[0] == 0
    for _ in range(2):  # further versions on top, until nodes split
        more = spark.createDataFrame([(2000 + 40 * grown.version + k, (x[0] + 0.001 * k).tolist()) for k in range(40)], "vec_id long, v array<double>")
        grown = ingest.insert(grown, more)
        assert tree.invariants(grown).agg(F.sum("violations")).first()[0] == 0
    assert grown.n == 323 and sum(grown.levels) > sum(index.levels)


def test_insert_after_delete(spark, vectors, index):
    """An id that was deleted may come back."""
    x, df, q = vectors
    gone = ingest.delete(index, df.where("vec_id < 40"))
    back = ingest.insert(gone, df.where("vec_id < 20"))
    assert back.rows.count() == 220 and tree.invariants(back).agg(F.sum("violations")).first()[0] == 0


def test_cache_stays_within_its_bytes(vectors, index):
    _, _, q = vectors
    leaf = 16 * (8 * 6 + 8)
    p = SearchParams(k=5, beam=3)
    want = rows_of(search.search(index, q, p))
    for preload in (0.0, 1.0):
        held = cache.LeafCache(index, 4 * leaf, preload)
        got = held.rows(held.search(q, p))
        assert rows_of(got) == want and held.peak <= 4 * leaf
        log = held.accesses()
        assert log.agg(F.max("resident_bytes")).first()[0] <= 4 * leaf and log.count() == 3 * q.count()
    with pytest.raises(ValueError):
        cache.LeafCache(index, leaf // 100)


def test_other_norms(spark, vectors):
    _, df, q = vectors
    for metric in ("l1", "chebyshev", "minkowski"):
        t = tree.build(df, tree.TreeParams(**{**PARAMS.__dict__, "metric": metric}))
        for far in (False, True):
            assert rows_of(search.search_exact(t, q, 7, farthest=far)) == rows_of(exact.knn(df, q, 7, metric, farthest=far))
    signs = df.select("vec_id", F.transform("v", lambda x: (x > 0).cast("double")).alias("v"))
    t = tree.build(signs, tree.TreeParams(**{**PARAMS.__dict__, "metric": "hamming"}))
    with pytest.raises(ValueError):
        search.search_exact(t, q, 3)
    with pytest.raises(ValueError):
        search.within(t, q, 1.0)


def test_large_inner_levels(vectors, index, monkeypatch):
    _, df, q = vectors
    want = rows_of(search.search_exact(index, q, 5))
    monkeypatch.setattr(search, "LEVEL_BYTES", 0)
    assert rows_of(search.search_exact(index, q, 5)) == want
    with pytest.raises(ValueError):
        search.descend(index, q, SearchParams(frontier="best_first"))


def test_far_probes_meet_rows(vectors, index, monkeypatch):
    _, _, q = vectors
    want = rows_of(search.search(index, q, SearchParams(k=6, beam=3)))
    monkeypatch.setattr(search, "PROBE_BYTES", 32)
    assert rows_of(search.search(index, q, SearchParams(k=6, beam=3))) == want


def test_walks_in_rounds_and_alone(vectors, index):
    _, df, q = vectors
    links = graph.build_links(index, 5, 4)
    seeds = search.search(index, q, SearchParams(k=4, beam=1))
    one, many = (rows_of(graph.greedy(seeds, links, df, q, 4, local=local)) for local in (True, False))
    assert one == many
    with pytest.raises(RuntimeError):
        graph.greedy(graph.random_seeds(q, df), links, df, q, 4, local=False, max_rounds=1).count()


def test_views_serve_or_step_aside(spark, vectors, index):
    x, df, q = vectors
    seq = q.select(F.lit(1).cast("long").alias("session_id"), F.col("query_id").alias("seq"), "query_id", "v")
    none = view.replay(df, seq, 5, 0).collect()
    assert all(r.served_from == "base" and r.recall == 1.0 and r.view_no == 0 for r in none)
    for trigger in ("truth", "probe"):
        got = sorted(view.replay(df, seq, 5, 60, trigger=trigger, tree=index, with_links=True, beam=2).collect(), key=lambda r: r.seq)
        assert got[0].served_from == "new" and {r.served_from for r in got} == {"new", "view"}
        assert all(len(r.ids) == 5 for r in got)
    truth = {i: {r.vec_id for r in rows} for i, rows in _grouped(exact.knn(df, q, 5)).items()}
    assert all(abs(r.recall - len(truth[r.query_id] & set(r.ids)) / 5) < 1e-9 for r in got)


def _grouped(df):
    out = {}
    for r in df.collect():
        out.setdefault(r.query_id, []).append(r)
    return out


def test_live_views_answer(spark, vectors, tmp_path):
    x, df, _ = vectors
    turns = spark.createDataFrame([(k % 2, k, x[(k % 2) + 6 * (k // 4)].tolist()) for k in range(12)], "session_id long, seq long, v array<double>")
    turns.coalesce(1).write.parquet(str(tmp_path / "turns"))
    stream = streams.file_stream(spark, str(tmp_path / "turns"), turns.schema)
    out = streams.run_once(streams.view_sessions(stream, 9.0, rows=df, k=3, view_size=120), "live_views", str(tmp_path / "ck")).collect()
    asked = {(r.session_id, r.seq): np.array(r.v) for r in turns.collect()}
    assert len(out) == 12 and {r.served_from for r in out} == {"new", "view"}
    for r in out:
        true = np.argsort(((x - asked[r.session_id, r.seq]) ** 2).sum(1), kind="stable")[:3]
        if r.served_from == "new":
            assert r.ids == true.tolist()
        else:
            assert len(r.ids) == 3


def test_stream_modes(spark, tmp_path):
    """Duplicates within the watermark, a join with an index version, update mode, and the rate source."""
    rows = [(1, "2024-01-01 00:00:00", 5, "click", 1.0), (1, "2024-01-01 00:01:00", 5, "click", 1.0), (2, "2024-01-01 00:02:00", 6, "click", 2.0), (3, "2024-01-01 03:00:00", 6, "purchase", 2.0)]
    ev = spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double").withColumn("ts", F.col("ts").cast("timestamp"))
    ev.coalesce(1).write.parquet(str(tmp_path / "ev"))
    stream = lambda: streams.file_stream(spark, str(tmp_path / "ev"), ev.schema)
    once = streams.run_once(streams.once(stream()), "once_events", str(tmp_path / "c1"))
    assert sorted(r.event_id for r in once.collect()) == [1, 2, 3]
    found = spark.createDataFrame([(5, 1, 70, 0.5), (6, 1, 80, 0.5)], "query_id long, rank int, vec_id long, dist double")
    joined = streams.run_once(streams.queries_with_index(stream().select(F.col("user_id").alias("query_id"), "event_id"), found), "joined_events", str(tmp_path / "c2"))
    assert sorted((r.event_id, r.vec_id) for r in joined.collect()) == [(1, 70), (1, 70), (2, 80), (3, 80)]
    seen = []
    q = streams.tumbling(stream()).writeStream.outputMode("update").foreachBatch(lambda b, i: seen.extend(b.collect())).option("checkpointLocation", str(tmp_path / "c3")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert {(r.event_type, r.n) for r in seen} >= {("click", 3), ("purchase", 1)}
    rate = streams.rate_stream(spark, 5)
    assert rate.isStreaming and rate.columns == ["timestamp", "value"]


def test_fast_functions_and_nulls(spark):
    from vecblock.functions import sql as S

    S.register_fast(spark)
    df = spark.createDataFrame([([1.0, 2.0], [4.0, 6.0]), (None, [1.0, 1.0])], "a array<double>, b array<double>")
    got = [tuple(r) for r in df.selectExpr("vec_l2_fast(a, b)", "vec_dot_fast(a, b)").collect()]
    assert got == [(5.0, 16.0), (None, None)]


def test_half_precision_round_trip(spark, vectors):
    x, df, _ = vectors
    rows = df.select("vec_id", "v")
    back = {r.vec_id: r.v for r in tree.decode(tree.encode(rows, "float16"), "float16").collect()}
    assert np.allclose(np.array([back[i] for i in range(240)]), x.astype(np.float16).astype(float))


def test_build_refuses_to_grow_what_the_driver_cannot_hold(vectors, monkeypatch):
    monkeypatch.setattr(tree, "DRIVER_BYTES", 0)
    with pytest.raises(ValueError):
        tree.build(vectors[1], tree.TreeParams(**{**PARAMS.__dict__, "how": "grow"}))
    packed = tree.build(vectors[1], tree.TreeParams(**{**PARAMS.__dict__, "how": "pack"}))
    assert tree.invariants(packed).agg(F.sum("violations")).first()[0] == 0 and ALL > packed.n
