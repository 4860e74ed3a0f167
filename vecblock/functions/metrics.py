"""Distances and vector aggregates as Spark columns (the reference semantics of every kernel)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def doubles(v: str | Column) -> Column:
    return (F.col(v) if isinstance(v, str) else v).cast("array<double>")


def _fold(a: Column, b: Column, f) -> Column:
    return F.aggregate(F.zip_with(a, b, f), F.lit(0.0), lambda s, x: s + x)


def dot(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: x * y)


def l2_sq(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: (x - y) * (x - y))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2_sq(a, b))


def norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x))


def cosine(a: Column, b: Column) -> Column:
    """1 - cos; null if a vector is zero."""
    return F.lit(1.0) - F.try_divide(dot(a, b), norm(a) * norm(b))


def hamming(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x != y).cast("int")), F.lit(0), lambda s, x: s + x)


def sign_bits(v: Column) -> Column:
    """Signs of up to 63 coordinates in one BIGINT; its hamming distance is bit_count(a ^ b)."""
    return F.aggregate(F.transform(v, lambda x: (x > 0).cast("bigint")), F.lit(0).cast("bigint"), lambda s, b: s * 2 + b)


def minkowski(a: Column, b: Column, p: float) -> Column:
    if p == float("inf"):
        return F.array_max(F.zip_with(a, b, lambda x, y: F.abs(x - y)))
    if p == 1:
        return _fold(a, b, lambda x, y: F.abs(x - y))
    return F.pow(_fold(a, b, lambda x, y: F.pow(F.abs(x - y), F.lit(float(p)))), F.lit(1.0 / p))


def mahalanobis_diag(a: Column, b: Column, variance: Column) -> Column:
    """Mahalanobis distance under a diagonal covariance."""
    d = F.zip_with(a, b, lambda x, y: (x - y) * (x - y))
    return F.sqrt(F.aggregate(F.zip_with(d, variance, lambda x, v: x / v), F.lit(0.0), lambda s, x: s + x))


def whiten(v: Column, rows: list[list[float]]) -> Column:
    """Multiply by a small constant matrix; L2 of whitened vectors is the full Mahalanobis distance."""
    return F.array(*[dot(v, F.array(*[F.lit(float(x)) for x in r])) for r in rows])


def fit_whitener(df: DataFrame, vec: str = "v") -> list[list[float]]:
    """Rows of L^-1 for the covariance L L^T, from one pass of partial sums (n x n numbers reach the driver)."""
    import numpy as np
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.linalg import Vectors  # noqa: F401  (registers the vector type)
    from pyspark.ml.stat import Correlation, Summarizer

    vectors = df.select(array_to_vector(doubles(vec)).alias("f"))
    std = vectors.select(Summarizer.std(F.col("f"))).first()[0].toArray()
    corr = Correlation.corr(vectors, "f").first()[0].toArray()
    cov = corr * np.outer(std, std)
    return np.linalg.inv(np.linalg.cholesky(cov + 1e-12 * np.eye(len(cov)))).tolist()


DISTANCES = {
    "l2": l2,
    "l2_sq": l2_sq,
    "cosine": cosine,
    "dot": dot,
    "hamming": hamming,
    "l1": lambda a, b: minkowski(a, b, 1),
    "chebyshev": lambda a, b: minkowski(a, b, float("inf")),
    "minkowski": lambda a, b: minkowski(a, b, 3),
}


def checked(v: Column, dim: int, metric: str = "l2", on_bad: str = "error") -> Column:
    """The vector, or what ``on_bad`` says for nulls, NaN, wrong lengths and zero vectors under cosine."""
    bad = v.isNull() | (F.size(v) != dim) | F.exists(v, lambda x: x.isNull() | F.isnan(x))
    if metric == "cosine":
        bad = bad | (norm(v) == 0)
    if on_bad == "error":
        return F.when(F.coalesce(bad, F.lit(True)), F.raise_error(F.lit("bad vector")).cast("array<double>")).otherwise(v)
    return F.when(~F.coalesce(bad, F.lit(True)), v)


def normalized(v: Column) -> Column:
    n = norm(v)
    return F.transform(v, lambda x: x / n)


def _positions(df: DataFrame, by: list[str], vec: str, agg) -> DataFrame:
    """Aggregate coordinate by coordinate and put the coordinates together again."""
    flat = df.select(*by, F.posexplode(doubles(vec)).alias("_pos", "_x")).groupBy(*by, "_pos").agg(agg(F.col("_x")).alias("_x"))
    return flat.groupBy(*by).agg(F.transform(F.array_sort(F.collect_list(F.struct("_pos", "_x"))), lambda s: s["_x"]).alias(vec))


def centroid(df: DataFrame, by: list[str], vec: str = "v") -> DataFrame:
    return _positions(df, by, vec, F.avg)


def vector_sum(df: DataFrame, by: list[str], vec: str = "v") -> DataFrame:
    return _positions(df, by, vec, F.sum)


def vector_min(df: DataFrame, by: list[str], vec: str = "v") -> DataFrame:
    return _positions(df, by, vec, F.min)


def vector_max(df: DataFrame, by: list[str], vec: str = "v") -> DataFrame:
    return _positions(df, by, vec, F.max)
