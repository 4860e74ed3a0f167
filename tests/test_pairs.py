"""Distances of all pairs, scored in packs, against the column expressions."""

from __future__ import annotations

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecblock.functions import arrays as A
from vecblock.functions import metrics as M
from vecblock.plans import vector_queries as VQ

ODD = [[0.0] * 3, [1e-200, 0.0, 0.0], None, [1.0, None, 2.0], [1.0, 2.0], [], [3e2, 3e2, 3e2 + 1e-4], [3e2, 3e2, 3e2], [float("nan"), 1.0, -1.0], [-0.5, 0.25, 1e3]]
LISTS = {"dist_l2": M.l2, "dist_l2_sq": M.l2_sq, "dist_cosine": M.cosine, "dist_dot": M.dot, "dist_manhattan": M.DISTANCES["l1"], "dist_chebyshev": M.DISTANCES["chebyshev"]}


def packed():
    return [k for k in LISTS if k in VQ._PACKED]


def plain(rows):
    return sorted(((r.query_id, r.vec_id, None if r.dist is None else "nan" if math.isnan(r.dist) else r.dist + 0.0) for r in rows), key=repr)


@pytest.fixture(scope="module")
def odd_dir(spark, tmp_path_factory):
    """Two hundred vectors, and each tenth an odd one that is a query as well."""
    rng = np.random.default_rng(3)
    rows = [(i, ODD[i // 10] if i % 10 == 0 and i // 10 < len(ODD) else rng.normal(size=3).tolist(), 0) for i in range(200)]
    path = str(tmp_path_factory.mktemp("odd"))
    spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").write.parquet(f"{path}/embeddings.parquet")
    return path


@pytest.mark.parametrize("name", packed())
def test_odd_vectors(spark, odd_dir, name):
    got = VQ.QUERIES[name](spark, odd_dir)
    want = VQ.r6(VQ._pairs(spark, odd_dir, LISTS[name]), "dist")
    assert got.schema == want.schema and plain(got.collect()) == plain(want.collect())


@pytest.mark.parametrize("name", ["dist_hamming", "dist_hamming_packed"])
def test_odd_signs(spark, odd_dir, name):
    sign = lambda v: F.transform(v, lambda x: (x > 0).cast("int"))
    pack = lambda v: M.sign_bits(F.slice(v, 1, 32))
    f = {"dist_hamming": lambda a, b: M.hamming(sign(a), sign(b)), "dist_hamming_packed": lambda a, b: F.bit_count(pack(a).bitwiseXOR(pack(b)))}[name]
    assert plain(VQ.QUERIES[name](spark, odd_dir).collect()) == plain(VQ._pairs(spark, odd_dir, f).collect())


def test_arrow_functions_in_packs(spark, tmp_path):
    rng = np.random.default_rng(4)
    x = [None if i == 30 else rng.normal(size=64).tolist() for i in range(90)]
    spark.createDataFrame([(i, v, 0) for i, v in enumerate(x)], "vec_id long, embedding array<double>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    df = VQ.QUERIES["arrow_functions"](spark, str(tmp_path))
    assert "MapInArrow" in df._jdf.queryExecution().toString()
    got = {(r.query_id, r.vec_id): (r.l2, r.dot) for r in df.collect()}
    assert len(got) == 9 * 89
    for (a, b), (l2, dot) in got.items():
        if x[a] is None or x[b] is None:
            assert l2 is None and dot is None
        else:
            assert l2 == pytest.approx(math.dist(x[a], x[b]), abs=1e-6) and dot == pytest.approx(float(np.dot(x[a], x[b])), abs=1e-6)


@pytest.mark.parametrize("name", [*packed(), "dist_hamming", "dist_hamming_packed"])
def test_no_vector_meets_a_vector_in_spark(spark, odd_dir, name):
    """Per pair, lambdas over arrays took some fifty microseconds; packs meet instead."""
    text = VQ.QUERIES[name](spark, odd_dir)._jdf.queryExecution().toString()
    assert "MapInArrow" in text


def test_rounding_is_that_of_spark(spark):
    x = np.concatenate([np.random.default_rng(1).normal(size=500) * 10.0 ** np.arange(500).clip(0, 8), [0.0, 1e-7, 5e-7, -5e-7, 1e300, float("inf")]])
    df = spark.createDataFrame([(float(v),) for v in x], "x double").selectExpr("round(x, 6) AS r")
    assert [r.r for r in df.collect()] == A.round_half_up(x, 6).tolist()


def test_blocks_of_every_shape():
    rng = np.random.default_rng(2)
    for m, n in ((1, 1), (3, 700), (65, 2)):
        q, x = rng.normal(size=(m, 5)), rng.normal(size=(n, 5))
        for metric in ("l2", "cosine", "l1", "chebyshev"):
            assert np.allclose(A.fold(q, x, metric), A.distance(q[:, None], x[None], metric))
