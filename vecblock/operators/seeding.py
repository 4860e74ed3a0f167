"""Starting centers of clusterings, as passes over a DataFrame (vec_id, v)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecblock.functions import metrics as M


def _draw(seed: int, turn: int):
    """A number in (0, 1) from the id alone, equal in other engines (md5)."""
    text = F.concat_ws("|", F.col("vec_id").cast("string"), F.lit(str(seed)), F.lit(str(turn)))
    return (F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") + 1) / F.lit(4294967297.0)


def random(df: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """(pos, vec_id, v): the k rows with the smallest draws; plain K-Means starts here."""
    top = df.select("vec_id", "v", _draw(seed, 0).alias("u")).orderBy("u", "vec_id").limit(k)
    rows = top.collect()  # k rows
    return df.sparkSession.createDataFrame([(i, r.vec_id, list(r.v)) for i, r in enumerate(rows)], "pos int, vec_id long, v array<double>")


def _grow(df: DataFrame, k: int, first, score) -> DataFrame:
    """Add seeds one at a time; each pass keeps the distance to the nearest seed in one column."""
    spark = df.sparkSession
    chosen = [first]
    near = df.select("vec_id", "v", F.lit(float("inf")).alias("d"))
    for turn in range(1, k):
        last = F.array(*[F.lit(float(x)) for x in chosen[-1].v])
        near = near.withColumn("d", F.least("d", M.l2_sq(F.col("v"), last)))
        best = near.where("d > 0").agg(F.max_by(F.struct("vec_id", "v"), F.struct(score(turn), -F.col("vec_id"))).alias("b")).first().b
        if best is None:
            break
        chosen.append(best)
    return spark.createDataFrame([(i, r.vec_id, list(r.v)) for i, r in enumerate(chosen)], "pos int, vec_id long, v array<double>")


def farthest(df: DataFrame, k: int) -> DataFrame:
    """Start at the lowest id, then always the row farthest from all seeds."""
    first = df.agg(F.min_by(F.struct("vec_id", "v"), "vec_id").alias("b")).first().b
    return _grow(df, k, first, lambda turn: F.col("d"))


def d2(df: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """Rows drawn in proportion to their squared distance from the seeds (an exponential race on id hashes)."""
    first = df.agg(F.min_by(F.struct("vec_id", "v"), F.struct(_draw(seed, 0), "vec_id")).alias("b")).first().b
    return _grow(df, k, first, lambda turn: F.log(_draw(seed, turn)) / F.col("d"))


def parallel(df: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """Oversampled seeding in few passes, from MLlib."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    model = KMeans(k=k, seed=seed, maxIter=0, initMode="k-means||", featuresCol="f").fit(df.select(array_to_vector(M.doubles("v")).alias("f")))
    rows = [(i, None, [float(x) for x in c]) for i, c in enumerate(model.clusterCenters())]
    return df.sparkSession.createDataFrame(rows, "pos int, vec_id long, v array<double>")
