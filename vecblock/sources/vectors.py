"""Vector tables: the given one and deterministic inputs derived from the others."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.functions import metrics as M


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, v, label) of the given embeddings in double precision."""
    return table(spark, sf_dir, "embeddings").select("vec_id", M.doubles("embedding").alias("v"), "label")


def queries_of(df: DataFrame, every: int = 10) -> DataFrame:
    return df.where(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query_id"), "v")


def hubs(spark: SparkSession, sf_dir: str, strength: float = 1.0, unit: bool = False) -> DataFrame:
    """Clustered vectors: coordinate number ``label`` is raised."""
    df = vectors(spark, sf_dir)
    v = F.transform("v", lambda x, i: F.when(i == F.col("label"), x + strength).otherwise(x))
    df = df.withColumn("v", v)
    return df.withColumn("v", M.normalized(F.col("v"))) if unit else df


def rolled(df: DataFrame, times: int) -> DataFrame:
    """``times`` copies of the collection, copy s with coordinates rotated by s."""
    n = df.agg((F.max("vec_id") + 1).alias("n")).first().n or 0
    dim = F.size("v")
    s = F.col("s")
    v = F.concat(F.slice("v", s + 1, dim), F.slice("v", F.lit(1), s))
    return df.withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(times - 1)))).select((s * n + F.col("vec_id")).cast("long").alias("vec_id"), v.alias("v"), "label")


def _standard(df: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """z-scores over the whole table; population spread, 0 where a column is constant."""
    one = df.agg(*[F.avg(c).alias(f"m_{c}") for c in columns], *[F.stddev_pop(c).alias(f"s_{c}") for c in columns])
    m = one.first()  # one row of moments
    z = [F.when(F.lit((m[f"s_{c}"] or 0.0) > 0), (F.col(c) - F.lit(m[f"m_{c}"])) / F.lit(m[f"s_{c}"] or 1.0)).otherwise(0.0) for c in columns]
    return df.select(F.col(key).cast("long").alias("vec_id"), F.array(*z).alias("v"))


def part_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    per = table(spark, sf_dir, "lineitem").groupBy("l_partkey").agg(F.avg("l_quantity").alias("q"), F.avg("l_discount").alias("d"))
    part = table(spark, sf_dir, "part")
    joined = part.join(per, part.p_partkey == per.l_partkey).select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"), "q", "d")
    return _standard(joined, "p_partkey", ["size", "price", "q", "d"])


def customer_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    per = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").cast("double").alias("n"), F.sum("o_totalprice").alias("s"), F.avg("o_totalprice").alias("a"))
    cust = table(spark, sf_dir, "customer")
    joined = cust.join(per, cust.c_custkey == per.o_custkey, "left").select("c_custkey", F.col("c_acctbal").alias("bal"), *[F.coalesce(c, F.lit(0.0)).alias(c) for c in ("n", "s", "a")])
    return _standard(joined, "c_custkey", ["bal", "n", "s", "a"])


def lineitem_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many exact duplicates; ids number the rows in full row order (test data only)."""
    li = table(spark, sf_dir, "lineitem")
    w = Window.orderBy(*li.columns)
    v = F.array(F.col("l_quantity"), F.round(F.col("l_discount") * 100) + 0.0, F.round(F.col("l_tax") * 100) + 0.0)
    return li.select(F.row_number().over(w).cast("long").alias("vec_id"), v.alias("v"))


def user_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per user: count and mean value of each event type."""
    ev = table(spark, sf_dir, "events")
    kinds = [r[0] for r in ev.select("event_type").distinct().orderBy("event_type").collect()]  # five types
    wide = ev.groupBy("user_id").agg(*[F.count(F.when(F.col("event_type") == t, 1)).cast("double").alias(f"n_{i}") for i, t in enumerate(kinds)], *[F.coalesce(F.avg(F.when(F.col("event_type") == t, F.col("value"))), F.lit(0.0)).alias(f"m_{i}") for i, t in enumerate(kinds)])
    return wide.select(F.col("user_id").alias("vec_id"), F.array(*[f"n_{i}" for i in range(len(kinds))], *[f"m_{i}" for i in range(len(kinds))]).alias("v"))


def trigram_vectors(df: DataFrame, key: list[str], text: str, buckets: int = 64) -> DataFrame:
    """Hashed character trigrams of the lower-cased text, counts divided by their norm; empty texts give no row."""
    low = df.select(*key, F.lower(text).alias("t")).where(F.length("t") > 0)
    grams = low.select(*key, F.explode(F.transform(F.sequence(F.lit(1), F.greatest(F.length("t") - 2, F.lit(1))), lambda i: F.substring(F.col("t"), i, F.lit(3)))).alias("g"))
    bucket = (F.conv(F.substring(F.md5("g"), 1, 8), 16, 10).cast("long") % buckets).cast("int")
    counts = grams.groupBy(*key, bucket.alias("b")).agg(F.count("*").cast("double").alias("c"))
    m = counts.groupBy(*key).agg(F.map_from_entries(F.collect_list(F.struct("b", "c"))).alias("m"), F.sqrt(F.sum(F.col("c") * F.col("c"))).alias("n"))
    return m.select(*key, F.transform(F.sequence(F.lit(0), F.lit(buckets - 1)), lambda i: F.coalesce(F.element_at("m", i), F.lit(0.0)) / F.col("n")).alias("v"))


def document_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trigram_vectors(table(spark, sf_dir, "documents"), ["doc_id"], "text").withColumnRenamed("doc_id", "vec_id")


def turn_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").where("role = 'user'")
    return trigram_vectors(turns, ["conv_id", "turn"], "text")
