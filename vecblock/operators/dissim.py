"""Unlikeness: outliers and commonality."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecblock.functions import metrics as M
from vecblock.operators import exact


def global_mean(df: DataFrame) -> list[float]:
    """Mean vector of a collection (n numbers)."""
    got = M.centroid(df.withColumn("one", F.lit(1)), ["one"]).first()
    return list(got.v) if got else []


def commonality(df: DataFrame) -> DataFrame:
    """(vec_id, commonality): cosine to the mean of all; low values stand apart."""
    mean = F.array(*[F.lit(float(x)) for x in global_mean(df)])
    return df.select("vec_id", (1 - M.cosine(F.col("v"), mean)).alias("commonality"))


def outliers_by_mean(df: DataFrame, k: int) -> DataFrame:
    """The k rows farthest from the mean vector."""
    mean = F.array(*[F.lit(float(x)) for x in global_mean(df)])
    return df.select("vec_id", M.l2(F.col("v"), mean).alias("dist")).orderBy(F.desc("dist"), "vec_id").limit(k)


def outliers_by_votes(df: DataFrame, q: DataFrame, k: int, top: int) -> DataFrame:
    """(vec_id, votes): how often a row is among the k farthest of the queries."""
    far = exact.kfn(df, q, k)
    return far.groupBy("vec_id").agg(F.count("*").alias("votes")).orderBy(F.desc("votes"), "vec_id").limit(top)
