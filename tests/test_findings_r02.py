"""Queries whose rows differed from their SQL at size, or that read no given table."""

from __future__ import annotations

import os

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"


def sql_rows(path: str, name: str, tables: list[str]) -> list:
    con = duckdb.connect()
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{path}/{t}.parquet{'/*.parquet' if os.path.isdir(f'{path}/{t}.parquet') else ''}')")
    return con.execute(entry.oracle_sql()[name])


def same(spark, path: str, name: str, tables: list[str]):
    df = entry.queries()[name](spark, path)
    want = sql_rows(path, name, tables)
    names = [d[0] for d in want.description]
    assert sorted(tuple(r[c] for c in names) for r in df.collect()) == sorted(want.fetchall())
    return df


def test_agg_pickers_of_equal_balances(spark, tmp_path):
    """Copies of customers have equal balances: the one with the smallest key is picked."""
    rows = [(60 * i + c, f"c{i}", i % 3, [5.0, -1.5, None, 2.0][i % 4], "AB"[i % 2]) for i in range(24) for c in range(20)][::-1]
    df = spark.createDataFrame(rows, "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string")
    df.coalesce(1).sortWithinPartitions("c_custkey").write.parquet(f"{tmp_path}/customer.parquet")
    df.repartition(7).write.parquet(f"{tmp_path}/dealt/customer.parquet")
    same(spark, str(tmp_path), "agg_pickers", ["customer"])
    ordered, dealt = (sorted(map(tuple, entry.queries()["agg_pickers"](spark, str(p)).collect())) for p in (tmp_path, tmp_path / "dealt"))
    assert ordered == dealt


def test_no_query_of_fixed_values():
    assert "capabilities" not in entry.queries() and "capabilities" not in entry.oracle_sql()


@pytest.mark.parametrize("name", ["recommended", "speedup_fixture"])
def test_the_job_reads_a_table(spark, name):
    df = same(spark, SF, name, ["lineitem"])
    assert "lineitem.parquet" in df._jdf.queryExecution().toString()


def test_links_through_all_leaves_copy_no_rows(spark):
    """Every leaf near every other: the same links as before, without a copy of each row for each leaf."""
    from vecblock.operators import graph, tree
    from vecblock.plans.vector_queries import PARAMS
    from vecblock.sources import vectors as V

    t = tree.build(V.hubs(spark, SF), PARAMS)
    m = t.levels[-1]
    leaves = t.nodes.where("is_leaf").select("node_id")
    every = leaves.selectExpr("node_id AS leaf_id").crossJoin(leaves.selectExpr("node_id AS near_id"))
    got, want = graph.build_links(t, 6, m), graph.build_links(t, 6, m, near=every)
    assert got.schema.names == want.schema.names and sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert got.count() == 6 * t.n and "FlatMapCoGroups" not in got._jdf.queryExecution().toString()


def test_adjacency_in_two_arrays():
    """As lists per row, in the order of the links; links of rows that are not there are left out."""
    import pickle

    import numpy as np

    from vecblock.operators.graph import Adjacency

    ids = np.array([2, 5, 9])
    src, dst = np.array([2, 2, 3, 5, 9, 9, 2]), np.array([9, 5, 2, 7, 9, 2, 2])
    adj = Adjacency.of(ids, src, dst)
    assert len(adj) == 3 and [adj[i].tolist() for i in range(3)] == [[2, 1, 0], [], [2, 0]]
    assert len(Adjacency.of(np.zeros(0, np.int64), src, dst)) == 0
    n = np.arange(20_000)
    assert len(pickle.dumps(Adjacency.of(n, np.repeat(n, 8), np.roll(np.repeat(n, 8), 3)))) < 1 << 20  # a list of arrays took more than twice as much


def test_sparse_dots_shuffle_no_pair(spark, tmp_path):
    rows = [(i, (i * 7) % 1300 if i % 11 else None, None if i % 13 == 0 else "abcde"[(i // 3 + i % 2) % 5]) for i in range(4000)]
    spark.createDataFrame(rows, "event_id long, user_id long, event_type string").write.parquet(f"{tmp_path}/events.parquet")
    df = same(spark, str(tmp_path), "sparse_dot_map", ["events"])
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert plan.strip().startswith("MapInArrow") and df.schema.simpleString() == "struct<u:bigint,w:bigint,dot:bigint>"


def test_hashing_without_a_join_of_buckets(spark):
    """As Spark's own similarity join, whose buckets hold most pairs."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector
    from pyspark.sql import functions as F

    from vecblock.baselines import others
    from vecblock.operators import exact
    from vecblock.sources import vectors as V

    v = V.hubs(spark, SF)
    q = V.queries_of(v)
    for bucket, radius in ((2.0, 2.0), (0.3, 1.2)):
        a, b = v.select("vec_id", array_to_vector("v").alias("f")), q.select("query_id", array_to_vector("v").alias("f"))
        model = BucketedRandomProjectionLSH(inputCol="f", outputCol="h", bucketLength=bucket, numHashTables=4, seed=42).fit(a)
        pairs = model.approxSimilarityJoin(b, a, radius, "dist").select(F.col("datasetA.query_id").alias("query_id"), F.col("datasetB.vec_id").alias("vec_id"), "dist")
        rows = lambda t: sorted((r.query_id, r["rank"], r.vec_id, round(r.dist, 9)) for r in t.collect())
        got = others.lsh_search(v, q, 10, bucket=bucket, radius=radius)
        assert rows(got) == rows(exact.ranked(pairs.where("query_id <> vec_id"), 10)) != []
        assert "Generate" not in got._jdf.queryExecution().toString()  # the join made a row per table
