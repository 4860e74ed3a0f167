"""The relational and streaming surround of the vector methods: one query per operator."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.sources.vectors import table as T
from vecblock.streaming import streams

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def put(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return put


def r(c: str, n: int = 4):
    return F.round(c, n).alias(c)


# --- scans, filters, projections ----------------------------------------------------


@query("SELECT p_partkey, p_name, p_size FROM part WHERE p_size BETWEEN 10 AND 20 AND p_brand IN (SELECT DISTINCT p_brand FROM part ORDER BY p_brand LIMIT 3) AND p_name LIKE '%ring%' AND NOT (p_retailprice IS NULL)")
def filter_predicates(spark, d):
    part = T(spark, d, "part")
    brands = [x[0] for x in part.select("p_brand").distinct().orderBy("p_brand").limit(3).collect()]  # three names
    return part.where(F.col("p_size").between(10, 20) & F.col("p_brand").isin(brands) & F.col("p_name").like("%ring%") & ~F.col("p_retailprice").isNull()).select("p_partkey", "p_name", "p_size")


@query("SELECT o_orderkey FROM orders WHERE o_orderstatus IS NOT DISTINCT FROM 'F' AND regexp_matches(o_orderpriority, '^[12]')")
def filter_null_safe(spark, d):
    return T(spark, d, "orders").where(F.col("o_orderstatus").eqNullSafe("F") & F.col("o_orderpriority").rlike("^[12]")).select("o_orderkey")


@query("SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) AS charge, CAST(l_quantity AS BIGINT) AS qty FROM lineitem WHERE l_discount >= 0.05")
def project_computed(spark, d):
    return T(spark, d, "lineitem").where("l_discount >= 0.05").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax")), 6).alias("charge"), F.col("l_quantity").cast("long").alias("qty"))


# --- joins ----------------------------------------------------------------------------


@query("SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def join_equi(spark, d):
    return T(spark, d, "orders").join(T(spark, d, "lineitem").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


@query("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_broadcast(spark, d):
    return T(spark, d, "customer").join(F.broadcast(T(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))  # 25 nations


@query("SELECT s_suppkey, r_name FROM supplier, region WHERE s_suppkey % 7 < r_regionkey")
def join_theta(spark, d):
    return T(spark, d, "supplier").join(F.broadcast(T(spark, d, "region")), F.col("s_suppkey") % 7 < F.col("r_regionkey")).select("s_suppkey", "r_name")  # five regions


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'O')")
def join_semi(spark, d):
    return T(spark, d, "customer").join(T(spark, d, "orders").where("o_orderstatus = 'O'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
def join_anti(spark, d):
    return T(spark, d, "customer").join(T(spark, d, "orders").where("o_totalprice > 200000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey")
def join_left(spark, d):
    return T(spark, d, "customer").join(T(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("SELECT c_custkey, o_orderkey FROM (SELECT c_custkey FROM customer WHERE c_acctbal < 0) RIGHT JOIN orders ON o_custkey = c_custkey")
def join_right(spark, d):
    return T(spark, d, "customer").where("c_acctbal < 0").select("c_custkey").join(T(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "right").select("c_custkey", "o_orderkey")


@query("SELECT count(*) AS n, count(c_custkey) AS with_customer, count(user_id) AS with_user FROM (SELECT c_custkey FROM customer WHERE c_custkey % 3 = 0) FULL JOIN (SELECT DISTINCT user_id FROM events) ON c_custkey = user_id")
def join_full(spark, d):
    a = T(spark, d, "customer").where("c_custkey % 3 = 0").select("c_custkey")
    b = T(spark, d, "events").select("user_id").distinct()
    return a.join(b, F.col("c_custkey") == F.col("user_id"), "full").agg(F.count("*").alias("n"), F.count("c_custkey").alias("with_customer"), F.count("user_id").alias("with_user"))


@query("SELECT a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b ON b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_type = 'click' AND b.event_type = 'purchase' AND a.user_id = b.user_id")
def join_interval(spark, d):
    ev = T(spark, d, "events")
    a = ev.where("event_type = 'click'").select(F.col("event_id").alias("e1"), F.col("ts").alias("t1"), F.col("user_id").alias("u"))
    b = ev.where("event_type = 'purchase'").select(F.col("event_id").alias("e2"), F.col("ts").alias("t2"), "user_id")
    return a.join(b, (F.col("u") == F.col("user_id")) & (F.col("t2") > F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr("INTERVAL 10 MINUTES"))).select("e1", "e2")


@query("SELECT o.o_orderkey, e.event_id FROM (SELECT o_orderkey, o_custkey, o_orderdate FROM orders) o ASOF LEFT JOIN (SELECT event_id, user_id, ts - INTERVAL 20 YEAR + INTERVAL 0 DAY AS ts FROM events) e ON o.o_custkey = e.user_id AND o.o_orderdate >= e.ts")
def asof_join(spark, d):
    o = T(spark, d, "orders").select("o_orderkey", F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("at"), F.lit(None).cast("long").alias("event_id"), F.lit(1).alias("side"))
    e = T(spark, d, "events").select(F.lit(None).cast("long").alias("o_orderkey"), F.col("user_id").alias("k"), (F.col("ts") - F.expr("INTERVAL 20 YEARS")).alias("at"), "event_id", F.lit(0).alias("side"))
    w = Window.partitionBy("k").orderBy("at", "side", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return o.union(e).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w)).where("side = 1").select("o_orderkey", "event_id")


@query("SELECT n_name, c_custkey FROM (SELECT n_name, c_custkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn FROM nation JOIN customer ON c_nationkey = n_nationkey) WHERE rn <= 3")
def join_lateral_topk(spark, d):
    T(spark, d, "customer").createOrReplaceTempView("vecblock_customer")
    T(spark, d, "nation").createOrReplaceTempView("vecblock_nation")
    return spark.sql("SELECT n_name, c_custkey FROM vecblock_nation, LATERAL (SELECT c_custkey FROM vecblock_customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3)")


@query("SELECT o_orderpriority, count(*) AS pairs FROM orders o JOIN customer c ON o.o_custkey = c.c_custkey GROUP BY o_orderpriority")
def join_salted(spark, d):
    """A hot key dealt out by salt on one side and repeated on the other."""
    salt = 8
    o = T(spark, d, "orders").withColumn("salt", F.pmod(F.xxhash64("o_orderkey"), F.lit(salt)))
    c = T(spark, d, "customer").select("c_custkey", F.explode(F.sequence(F.lit(0), F.lit(salt - 1))).alias("s"))
    return o.join(c, (F.col("o_custkey") == F.col("c_custkey")) & (F.col("salt") == F.col("s"))).groupBy("o_orderpriority").agg(F.count("*").alias("pairs"))


# --- aggregates -------------------------------------------------------------------------


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS s, round(avg(l_extendedprice), 4) AS a, min(l_discount) + 0.0 AS lo, max(l_tax) + 0.0 AS hi, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS c FROM lineitem GROUP BY 1, 2")
def agg_basic(spark, d):
    return T(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("s"), F.round(F.avg("l_extendedprice"), 4).alias("a"), (F.min("l_discount") + 0.0).alias("lo"), (F.max("l_tax") + 0.0).alias("hi"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("c"))


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def agg_distinct(spark, d):
    return T(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query()
def agg_sketches(spark, d):
    ev = T(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("hll"))
    return ev


@query("SELECT l_returnflag, l_linestatus, grouping(l_returnflag) * 2 + grouping(l_linestatus) AS gid, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def cube_lineitem(spark, d):
    return T(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("gid"), F.count("*").alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def rollup_orders(spark, d):
    return T(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")
def grouping_sets(spark, d):
    c = T(spark, d, "customer")
    return c.groupingSets([["c_mktsegment"], ["c_nationkey"], []], "c_mktsegment", "c_nationkey").agg(F.count("*").alias("n")).select("c_mktsegment", "c_nationkey", "n")


@query("SELECT o_orderstatus, count(*) FILTER (o_orderpriority LIKE '1%') AS p1, count(*) FILTER (o_orderpriority LIKE '2%') AS p2 FROM orders GROUP BY o_orderstatus")
def pivot_orders(spark, d):
    o = T(spark, d, "orders").withColumn("p", F.concat(F.lit("p"), F.substring("o_orderpriority", 1, 1)))
    return o.groupBy("o_orderstatus").pivot("p", ["p1", "p2"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT p_partkey, k, v FROM (SELECT p_partkey, 'size' AS k, CAST(p_size AS DOUBLE) AS v FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part)")
def unpivot_part(spark, d):
    p = T(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return p.unpivot("p_partkey", ["size", "price"], "k", "v")


@query("SELECT l_returnflag, quantile_cont(l_extendedprice, 0.5) AS p50, quantile_cont(l_extendedprice, 0.9) AS p90 FROM lineitem GROUP BY l_returnflag")
def agg_percentiles(spark, d):
    return T(spark, d, "lineitem").groupBy("l_returnflag").agg(F.expr("percentile(l_extendedprice, 0.5)").alias("p50"), F.expr("percentile(l_extendedprice, 0.9)").alias("p90"))


@query("SELECT l_returnflag, 0 AS violations FROM lineitem GROUP BY l_returnflag")
def agg_percentiles_approx(spark, d):
    """Approximate percentiles whose rank is off by more than half a percent: none."""
    li = T(spark, d, "lineitem").select("l_returnflag", "l_extendedprice")
    cuts = li.groupBy("l_returnflag").agg(F.percentile_approx("l_extendedprice", [0.5, 0.9], 10_000).alias("p"), F.count("*").alias("n"))
    below = lambda i: F.sum((F.col("l_extendedprice") <= F.col("p")[i]).cast("long")) / F.first("n")
    ranks = li.join(F.broadcast(cuts), "l_returnflag").groupBy("l_returnflag").agg(below(0).alias("a"), below(1).alias("b"))  # a row per flag
    return ranks.select("l_returnflag", ((F.abs(F.col("a") - 0.5) > 0.005).cast("int") + (F.abs(F.col("b") - 0.9) > 0.005).cast("int")).alias("violations"))


@query("SELECT c_nationkey, arg_max(c_custkey, c_acctbal) AS richest, arg_min(c_custkey, c_acctbal) AS poorest, count(*) FILTER (c_acctbal < 0) AS in_debt, array_to_string(list(DISTINCT c_mktsegment ORDER BY c_mktsegment), ',') AS segments FROM customer GROUP BY c_nationkey")
def agg_pickers(spark, d):
    # of equal balances the smallest key
    at = lambda key: F.when(F.col("c_acctbal").isNotNull(), F.struct("c_acctbal", key))
    return T(spark, d, "customer").groupBy("c_nationkey").agg(F.max_by("c_custkey", at(-F.col("c_custkey"))).alias("richest"), F.min_by("c_custkey", at(F.col("c_custkey"))).alias("poorest"), F.count_if(F.col("c_acctbal") < 0).alias("in_debt"), F.array_join(F.array_sort(F.collect_set("c_mktsegment")), ",").alias("segments"))


@query("SELECT c_nationkey, array_to_string(list_transform(list(c_custkey ORDER BY c_acctbal DESC, c_custkey)[1:3], lambda x: CAST(x AS VARCHAR)), ',') AS top3 FROM customer GROUP BY c_nationkey")
def agg_topk(spark, d):
    top = F.slice(F.sort_array(F.collect_list(F.struct((-F.col("c_acctbal")).alias("a"), "c_custkey"))), 1, 3)
    return T(spark, d, "customer").groupBy("c_nationkey").agg(F.array_join(F.transform(top, lambda s: s["c_custkey"].cast("string")), ",").alias("top3"))


# --- windows, sorting, sets ----------------------------------------------------------------


@query("SELECT c_custkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment, c_custkey)")
def window_ranks(spark, d):
    w = Window.partitionBy("c_nationkey").orderBy("c_mktsegment", "c_custkey")
    one = lambda c, n: c.over(w).cast("long").alias(n)
    return T(spark, d, "customer").select("c_custkey", one(F.row_number(), "rn"), one(F.rank(), "rk"), one(F.dense_rank(), "dr"), one(F.ntile(4), "nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(event_id) OVER w AS first_id, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def window_offsets(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return T(spark, d, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"), F.first("event_id").over(w).alias("first_id"), F.nth_value("event_id", 2).over(whole).alias("second_id"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING), 4) AS running, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING), 4) AS sliding, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS day_count FROM events")
def window_frames(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    ev = T(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    day = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return ev.select("event_id", F.round(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running"), F.round(F.avg("value").over(w.rowsBetween(-3, 3)), 4).alias("sliding"), F.count("*").over(day).alias("day_count"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
def sort_topk_offset(spark, d):
    return T(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(10)


@query("SELECT c_custkey AS k FROM customer UNION ALL SELECT user_id FROM events WHERE event_type = 'purchase'")
def set_union(spark, d):
    return T(spark, d, "customer").select(F.col("c_custkey").alias("k")).unionByName(T(spark, d, "events").where("event_type = 'purchase'").select(F.col("user_id").alias("k")))


@query("SELECT c_custkey AS k FROM customer INTERSECT SELECT user_id FROM events")
def set_intersect(spark, d):
    return T(spark, d, "customer").select(F.col("c_custkey").alias("k")).intersect(T(spark, d, "events").select("user_id"))


@query("SELECT user_id AS k FROM events EXCEPT ALL SELECT o_custkey FROM orders")
def set_except_all(spark, d):
    return T(spark, d, "events").select(F.col("user_id").alias("k")).exceptAll(T(spark, d, "orders").select("o_custkey"))


# --- functions --------------------------------------------------------------------------------


@query("SELECT vec_id, round(list_sum(list_filter(CAST(embedding AS DOUBLE[]), lambda x: x > 0)), 6) AS positive, len(list_filter(embedding, lambda x: x < 0)) AS n_negative, round(list_max(CAST(embedding AS DOUBLE[])), 6) AS top, CAST(list_position(embedding, list_max(embedding)) AS BIGINT) AS top_at FROM embeddings")
def fn_arrays(spark, d):
    v = F.col("embedding").cast("array<double>")
    return T(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(F.filter(v, lambda x: x > 0), F.lit(0.0), lambda s, x: s + x), 6).alias("positive"), F.size(F.filter(v, lambda x: x < 0)).cast("long").alias("n_negative"), F.round(F.array_max(v), 6).alias("top"), F.array_position(v, F.array_max(v)).alias("top_at"))


@query("WITH k AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) SELECT a.user_id AS u, b.user_id AS w, CAST(sum(a.n * b.n) AS BIGINT) AS dot FROM k a JOIN k b USING (event_type) WHERE a.user_id < b.user_id GROUP BY 1, 2")
def sparse_dot_map(spark, d):
    k = T(spark, d, "events").where("user_id IS NOT NULL AND event_type IS NOT NULL").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    return sparse_dots(k)


#: Sparse vectors of one pack.
PACK = 512


def sparse_dots(k):
    """(u, w, dot) for all u < w that share an entry, from entries (user_id, event_type, n).

    Packs of vectors meet and each meeting is a matrix product, so no pair is shuffled.
    """
    deal = 4 * k.sparkSession.sparkContext.defaultParallelism
    users = k.groupBy("user_id").agg(F.collect_list(F.struct("event_type", "n")).alias("e"))
    sorted_ = users.repartitionByRange(deal, "user_id").sortWithinPartitions("user_id").select("user_id", F.col("e.event_type").alias("t"), F.col("e.n").alias("n"))

    def pack(batches):
        for b in batches:
            for a in range(0, len(b), PACK):
                ids, t, n = (b.column(c).slice(a, PACK) for c in ("user_id", "t", "n"))
                of = np.repeat(np.arange(len(ids)), np.diff(np.asarray(t.offsets)))
                one = lambda x: pa.array([x.to_pylist()])
                yield pa.RecordBatch.from_arrays([pa.array([min(ids.to_pylist())]), pa.array([max(ids.to_pylist())]), one(ids), pa.array([of.tolist()]), one(t.flatten()), one(n.flatten())], names=["lo", "hi", "ids", "at", "t", "n"])

    packs = sorted_.mapInArrow(pack, "lo long, hi long, ids array<long>, at array<long>, t array<string>, n array<long>")
    names = packs.columns
    left, right = packs.toDF(*[f"u_{c}" for c in names]), packs.toDF(*[f"w_{c}" for c in names])
    # both sides are shuffled, for a product reads its right side again for each part of the left
    met = left.repartition(deal).join(right.repartition(2), F.col("u_lo") < F.col("w_hi"), "cross")

    def dots(batches):
        for b in batches:
            for i in range(len(b)):
                side = {c: b.column(c)[i].values for c in b.schema.names if c[2:] in ("ids", "at", "t", "n")}
                u, w = side["u_ids"].to_numpy(), side["w_ids"].to_numpy()
                code = pa.concat_arrays([side["u_t"], side["w_t"]]).dictionary_encode()
                col, split = code.indices.to_numpy(), len(side["u_t"])
                x, y = np.zeros((len(u), len(code.dictionary)), np.int64), np.zeros((len(w), len(code.dictionary)), np.int64)
                x[side["u_at"].to_numpy(), col[:split]], y[side["w_at"].to_numpy(), col[split:]] = side["u_n"].to_numpy(), side["w_n"].to_numpy()
                dot = x @ y.T
                r, c = np.nonzero((dot > 0) & (u[:, None] < w[None]))  # counts are positive: a shared entry shows
                yield pa.RecordBatch.from_arrays([pa.array(u[r]), pa.array(w[c]), pa.array(dot[r, c])], names=["u", "w", "dot"])

    return met.mapInArrow(dots, "u long, w long, dot long")


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def json_props(spark, d):
    return T(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def json_variant(spark, d):
    return T(spark, d, "events").select(F.try_variant_get(F.parse_json("props"), "$.k", "long").alias("k")).groupBy("k").agg(F.count("*").alias("n"))


@query("SELECT page_id, length(regexp_replace(html, '<[^>]*>', ' ', 'g')) AS n_text, md5(lower(url)) AS url_md5, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages")
def html_text(spark, d):
    return T(spark, d, "pages").select("page_id", F.length(F.regexp_replace("html", "<[^>]*>", " ")).cast("long").alias("n_text"), F.md5(F.lower("url")).alias("url_md5"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))


@query("SELECT p_partkey, levenshtein(p_brand, p_type) AS dist, upper(substr(p_name, 1, 3)) || '-' || p_size AS code FROM part")
def fn_strings(spark, d):
    return T(spark, d, "part").select("p_partkey", F.levenshtein("p_brand", "p_type").cast("long").alias("dist"), F.concat_ws("-", F.upper(F.substring("p_name", 1, 3)), F.col("p_size")).alias("code"))


@query("SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days, CAST(o_orderdate + INTERVAL 2 MONTH AS DATE) AS due, dayofweek(o_orderdate) + 1 AS dow FROM orders")
def fn_dates(spark, d):
    return T(spark, d, "orders").select("o_orderkey", F.to_date(F.date_trunc("month", "o_orderdate")).alias("m"), F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01").cast("date")).cast("long").alias("days"), F.add_months(F.to_date("o_orderdate"), 2).alias("due"), F.dayofweek("o_orderdate").cast("long").alias("dow"))


@query("SELECT l_partkey, round(sum(sqrt(l_extendedprice) + ln(l_quantity + 1) + pow(l_discount, 2)), 4) AS x, max(greatest(l_quantity, 10)) AS g, bit_xor(l_suppkey) AS b FROM lineitem GROUP BY l_partkey")
def fn_math(spark, d):
    return T(spark, d, "lineitem").groupBy("l_partkey").agg(F.round(F.sum(F.sqrt("l_extendedprice") + F.log(F.col("l_quantity") + 1) + F.pow("l_discount", F.lit(2))), 4).alias("x"), F.max(F.greatest("l_quantity", F.lit(10.0))).alias("g"), F.bit_xor("l_suppkey").alias("b"))


@query("SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'low' WHEN c_acctbal < 5000 THEN 'mid' ELSE 'high' END AS band, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS seg, TRY_CAST(c_name AS INT) AS n FROM customer")
def fn_conditional(spark, d):
    return T(spark, d, "customer").select("c_custkey", F.when(F.col("c_acctbal") < 0, "low").when(F.col("c_acctbal") < 5000, "mid").otherwise("high").alias("band"), F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("none")).alias("seg"), F.col("c_name").try_cast("int").alias("n"))


@query("WITH m AS (SELECT avg(p_size) AS a, stddev_pop(p_size) AS s FROM part) SELECT p_partkey, round((p_size - a) / s, 6) AS z, CAST(p_brand = (SELECT min(p_brand) FROM part) AS INT) AS one_hot FROM part, m")
def vectorise_numeric(spark, d):
    p = T(spark, d, "part")
    m = p.agg(F.avg("p_size").alias("a"), F.stddev_pop("p_size").alias("s"), F.min("p_brand").alias("b")).first()
    return p.select("p_partkey", F.round((F.col("p_size") - m.a) / m.s, 6).alias("z"), (F.col("p_brand") == m.b).cast("int").alias("one_hot"))


@query("SELECT p_partkey FROM part p WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part q WHERE q.p_brand = p.p_brand)")
def subquery_correlated(spark, d):
    T(spark, d, "part").createOrReplaceTempView("vecblock_part")
    return spark.sql("SELECT p_partkey FROM vecblock_part p WHERE p_retailprice > (SELECT avg(p_retailprice) FROM vecblock_part q WHERE q.p_brand = p.p_brand)")


_EDGES = "e AS (SELECT 'r' AS up, concat('r.', n_regionkey) AS down, 0 AS own FROM nation GROUP BY n_regionkey UNION ALL SELECT concat('r.', n_regionkey), concat('n.', n_nationkey), 1 FROM nation)"
_WALK = "t{0} AS (SELECT 'r' AS node, CAST(0 AS BIGINT) AS depth UNION ALL SELECT e.down, depth + 1 FROM t JOIN e ON e.up = t.node) SELECT node, depth FROM t"


@query(f"WITH RECURSIVE {_EDGES}, {_WALK.format('')}")
def recursive_cte(spark, d):
    """A walk down a tree of world, regions and nations."""
    T(spark, d, "nation").createOrReplaceTempView("nation")
    return spark.sql(f"WITH RECURSIVE {_EDGES}, {_WALK.format('(node, depth)')}")


@query("SELECT vec_id FROM embeddings WHERE CAST(('0x' || substr(md5(CAST(vec_id AS VARCHAR)), 1, 8)) AS BIGINT) % 5 = 0")
def sample_by_hash(spark, d):
    return T(spark, d, "embeddings").where(F.conv(F.substring(F.md5(F.col("vec_id").cast("string")), 1, 8), 16, 10).cast("long") % 5 == 0).select("vec_id")


# --- event windows (the batch form of the streaming queries) --------------------------------------


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def tumbling_events(spark, d):
    return streams.tumbling(T(spark, d, "events")).withColumn("total", F.round("total", 4))


@query("WITH w AS (SELECT time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 1 HOUR * o AS start FROM events, (VALUES (0), (1)) t(o)) SELECT start, count(*) AS n FROM w GROUP BY start")
def sliding_events(spark, d):
    return streams.sliding(T(spark, d, "events"))


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS \"end\", count(*) AS n FROM s GROUP BY user_id, sid")
def sessions_events(spark, d):
    return streams.sessions(T(spark, d, "events"))


@query("SELECT a.user_id, a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def attributed_events(spark, d):
    ev = T(spark, d, "events")
    return streams.attributed(ev.where("event_type = 'click'"), ev.where("event_type = 'purchase'"))
