"""Streams over small files."""

from __future__ import annotations

import datetime as dt

import numpy as np
from pyspark.sql import functions as F

from vecblock.operators import search, tree
from vecblock.operators.partition import PartitionParams
from vecblock.streaming import streams

PARAMS = tree.TreeParams(leaf_capacity=16, inner_capacity=4, partition=PartitionParams(max_cluster_rows=12, fanout=3, lloyd_iters=4))


def test_stream_insert_equals_batch(spark, tmp_path):
    x = np.random.default_rng(1).normal(size=(90, 3))
    df = spark.createDataFrame([(i, [float(z) for z in v]) for i, v in enumerate(x)], "vec_id long, v array<double>")
    tree.save(tree.build(df.where("vec_id < 30"), PARAMS), f"{tmp_path}/index")
    for k in (1, 2):
        df.where(F.floor(F.col("vec_id") / 30) == k).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    for _ in range(2):  # the second run finds nothing new
        streams.insert_stream(streams.file_stream(spark, f"{tmp_path}/in", df.schema), f"{tmp_path}/index", f"{tmp_path}/ck").awaitTermination()
    t = tree.open_tree(spark, f"{tmp_path}/index")
    assert t.version == 2 and t.n == 90
    assert all(r.violations == 0 for r in tree.invariants(t).collect())
    q = df.where("vec_id % 10 = 0").select(F.col("vec_id").alias("query_id"), "v")
    from vecblock.operators import exact

    got = [tuple(r)[:3] for r in search.search(t, q, search.SearchParams(k=3, beam=search.ALL)).orderBy("query_id", "rank").collect()]
    assert got == [tuple(r)[:3] for r in exact.knn(df, q, 3).orderBy("query_id", "rank").collect()]


def test_late_events_are_dropped(spark, tmp_path):
    base = dt.datetime(2024, 1, 1)
    rows = lambda minutes: spark.createDataFrame([(i, base + dt.timedelta(minutes=m), 1, "click", 1.0) for i, m in enumerate(minutes)], "event_id long, ts timestamp, user_id long, event_type string, value double")
    for k, minutes in enumerate(([5, 65, 200], [210], [10, 400])):
        rows(minutes).coalesce(1).write.parquet(f"{tmp_path}/in/f{k}")
    src = spark.readStream.schema(rows([0]).schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/in")
    out = streams.run_once(streams.tumbling(src), "late_test", f"{tmp_path}/ck")
    got = {r.start.hour: r.n for r in out.collect()}
    assert got[0] == 1  # the event at minute 10 came after its window was closed and given out


def test_view_sessions(spark, tmp_path):
    rows = [(1, 0, [0.0, 0.0]), (1, 1, [0.1, 0.0]), (1, 2, [5.0, 5.0]), (2, 0, [1.0, 1.0]), (2, 1, [1.0, 1.2])]
    df = spark.createDataFrame(rows, "session_id long, seq long, v array<double>")
    df.coalesce(1).write.parquet(f"{tmp_path}/in")
    out = streams.run_once(streams.view_sessions(streams.file_stream(spark, f"{tmp_path}/in", df.schema), 0.5), "views_test", f"{tmp_path}/ck")
    assert sorted((r.session_id, r.seq, r.served_from, r.view_no) for r in out.collect()) == [(1, 0, "new", 1), (1, 1, "view", 1), (1, 2, "new", 2), (2, 0, "new", 1), (2, 1, "view", 1)]
