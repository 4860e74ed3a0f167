"""Accuracy and cost measures, over answers and access logs."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def recall_per_query(found: DataFrame, truth: DataFrame, k: int, k_prime: int | None = None) -> DataFrame:
    """(query_id, recall): share of the true k among the first k_prime found."""
    t = truth.where(F.col("rank") <= k).select("query_id", "vec_id")
    f = found.where(F.col("rank") <= (k_prime or k)).select("query_id", "vec_id", F.lit(1).alias("hit"))
    return t.join(f, ["query_id", "vec_id"], "left").groupBy("query_id").agg((F.count("hit") / F.count("*")).alias("recall"))


def recall(found: DataFrame, truth: DataFrame, k: int, k_prime: int | None = None) -> DataFrame:
    return recall_per_query(found, truth, k, k_prime).agg(F.avg("recall").alias("recall"))


def timed(df: DataFrame) -> float:
    """Seconds to run a plan to the end without keeping its rows."""
    start = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def qps(n_queries: int, seconds: float) -> float:
    return n_queries / seconds if seconds > 0 else math.inf


def latency_ms(n_queries: int, seconds: float) -> float:
    return 1000 * seconds / max(1, n_queries)


def rel_gain(new, old):
    return (F.lit(new) - F.lit(old)) / F.lit(old) if isinstance(new, (int, float)) else (new - old) / old


def speedup(curves: DataFrame, at: float, fast: str, slow: str) -> DataFrame:
    """(recall, speedup): qps of ``fast`` over ``slow`` at one recall, linear between points of (method, recall, qps)."""
    w = Window.partitionBy("method").orderBy("recall", "qps")
    seg = curves.withColumns({"r2": F.lead("recall").over(w), "q2": F.lead("qps").over(w)}).where((F.col("recall") <= at) & (F.col("r2") >= at) & (F.col("r2") > F.col("recall")))
    y = seg.select("method", (F.col("qps") + (F.lit(at) - F.col("recall")) * (F.col("q2") - F.col("qps")) / (F.col("r2") - F.col("recall"))).alias("y"))
    best = y.groupBy("method").agg(F.max("y").alias("y"))
    return best.agg(F.max(F.when(F.col("method") == fast, F.col("y"))).alias("f"), F.max(F.when(F.col("method") == slow, F.col("y"))).alias("s")).select(F.lit(at).alias("recall"), (F.col("f") / F.col("s")).alias("speedup"))


# --- access logs: (seq, query_id, node_id) -------------------------------------


def lru(log: DataFrame, capacity: int, trace: str | None = None) -> DataFrame:
    """(seq, query_id, node_id, hit): exact LRU hits by stack distance.

    An access hits if fewer than ``capacity`` distinct nodes were read since the
    node's last read, counted as reads in between whose own next read lies past this one.
    """
    by = [trace] if trace else []
    w = Window.partitionBy(*by, "node_id").orderBy("seq")
    one = log.withColumns({"prev": F.lag("seq").over(w), "next": F.lead("seq").over(w)})
    a = one.select(*[F.col(c).alias(f"a_{c}") for c in (*by, "seq", "prev")]).where("a_prev IS NOT NULL")
    b = one.select(*[F.col(c).alias(f"b_{c}") for c in (*by, "seq", "next")])
    between = (F.col("b_seq") > F.col("a_prev")) & (F.col("b_seq") < F.col("a_seq")) & (F.col("b_next").isNull() | (F.col("b_next") > F.col("a_seq")))
    # ranges meet in blocks of the sequence, as an equi-join
    width = 256
    a = a.withColumn("cell", F.explode(F.sequence(F.floor(F.col("a_prev") / width), F.floor(F.col("a_seq") / width))))
    b = b.withColumn("cell", F.floor(F.col("b_seq") / width))
    same = between
    for c in by:
        same = same & (F.col(f"a_{c}") == F.col(f"b_{c}"))
    depth = a.join(b, "cell").where(same).groupBy(*[f"a_{c}" for c in by], "a_seq").agg(F.count("*").alias("depth"))
    keys = [F.col(c) == F.col(f"a_{c}") for c in (*by, "seq")]
    return one.join(depth, keys, "left").select(*by, "seq", "query_id", "node_id", (F.col("prev").isNotNull() & (F.coalesce("depth", F.lit(0)) < capacity)).alias("hit"))


def lru_replay(log: DataFrame, capacity: int, start: list[int] | None = None, trace: str = "trace") -> DataFrame:
    """The same by replaying each trace in order (a cache may start filled); also the resident number of nodes."""
    from collections import OrderedDict

    import pyarrow as pa

    def run(t: pa.Table) -> pa.Table:
        cache: OrderedDict[int, None] = OrderedDict((n, None) for n in (start or [])[-capacity:])
        out = []
        for r in sorted(t.to_pylist(), key=lambda r: r["seq"]):
            hit = r["node_id"] in cache
            cache[r["node_id"]] = None
            cache.move_to_end(r["node_id"])
            if len(cache) > capacity:
                cache.popitem(last=False)
            out.append((r[trace], r["seq"], r["query_id"], r["node_id"], hit, len(cache)))
        cols = list(zip(*out)) or [[]] * 6
        return pa.table([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.int64()))], names=[trace, "seq", "query_id", "node_id", "hit", "resident"])

    return log.groupBy(trace).applyInArrow(run, f"{trace} long, seq long, query_id long, node_id long, hit boolean, resident long")


def page_log(log: DataFrame, pages: DataFrame) -> DataFrame:
    """Reads of pages instead of nodes, from (node_id, page): a cache that knows no nodes."""
    return log.join(pages, "node_id").select("seq", "query_id", F.col("page").alias("node_id"))


def io_curve(log: DataFrame, capacity: int | None = None) -> DataFrame:
    """(seq, reads, cum_reads) per query number: first touches, or misses of an LRU cache."""
    if capacity is None:
        w = Window.partitionBy("node_id").orderBy("seq")
        cold = log.withColumn("miss", (F.row_number().over(w) == 1).cast("long"))
    else:
        cold = lru(log, capacity).withColumn("miss", (~F.col("hit")).cast("long"))
    per = cold.groupBy("query_id").agg(F.min("seq").alias("seq"), F.sum("miss").alias("reads"))
    return per.select("query_id", "seq", "reads", F.sum("reads").over(Window.orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)).alias("cum_reads"))


def warmup_curve(hits: DataFrame, bucket: int) -> DataFrame:
    """(bucket, accesses, hit_rate) over stretches of the log."""
    return hits.groupBy(F.floor(F.col("seq") / bucket).cast("long").alias("bucket")).agg(F.count("*").alias("accesses"), F.avg(F.col("hit").cast("double")).alias("hit_rate"))


def hops(log: DataFrame) -> DataFrame:
    """(queries, mean_hops): nodes opened per query."""
    per = log.groupBy("query_id").agg(F.count("*").alias("hops"))
    return per.agg(F.count("*").alias("queries"), F.avg("hops").alias("mean_hops"))


def distance_count(log: DataFrame) -> DataFrame:
    return log.groupBy("query_id").agg(F.sum("n_scored").alias("n_scored"))


def touched_fraction(log: DataFrame, n_nodes: int) -> DataFrame:
    """(query_id, touched): share of all nodes that a query opened."""
    return log.groupBy("query_id").agg((F.count_distinct("node_id") / F.lit(n_nodes)).alias("touched"))


def seek_distance(log: DataFrame, place: str = "node_order") -> DataFrame:
    """(reads, mean_gap, sequential): distance on disk between consecutive reads."""
    w = Window.orderBy("seq")
    gap = log.withColumn("gap", F.abs(F.col(place) - F.lag(place).over(w))).where("gap IS NOT NULL")
    return gap.agg(F.count("*").alias("reads"), F.avg("gap").alias("mean_gap"), F.avg((F.col("gap") <= 1).cast("double")).alias("sequential"))


def label_agreement(found: DataFrame, labels: DataFrame) -> DataFrame:
    """(agreement): share of answers whose label is the query's."""
    a = labels.select(F.col("vec_id").alias("query_id"), F.col("label").alias("mine"))
    return found.join(a, "query_id").join(labels.select("vec_id", "label"), "vec_id").agg(F.avg((F.col("mine") == F.col("label")).cast("double")).alias("agreement"))


def pca2(df: DataFrame) -> DataFrame:
    """(vec_id, x, y): the two leading principal components."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector, vector_to_array

    v = df.select("vec_id", array_to_vector(F.col("v").cast("array<double>")).alias("f"))
    out = PCA(k=2, inputCol="f", outputCol="p").fit(v).transform(v).select("vec_id", vector_to_array("p").alias("p"))
    return out.select("vec_id", F.col("p")[0].alias("x"), F.col("p")[1].alias("y"))


# --- cost formulas ---------------------------------------------


def predicted_cost(spark: SparkSession, n: int, fanout: int, iters: int, capacity: int, link_leaves: int, beam: int, inner_capacity: int, n_queries: int) -> DataFrame:
    """(step, distances): distance computations that the formulas of each step predict."""
    leaves = math.ceil(n / capacity)
    height = max(1, math.ceil(math.log(max(leaves, 2), max(inner_capacity, 2))))
    rows = [
        ("clustering", float(fanout * n * iters * math.log(n, fanout))),
        ("near_leaves", float(leaves * leaves)),
        ("links", float(capacity * link_leaves * n)),
        ("brute_force", float(n_queries * n)),
        ("search", float(n_queries * (beam * height * inner_capacity + beam * capacity))),
    ]
    return spark.createDataFrame(rows, "step string, distances double")
