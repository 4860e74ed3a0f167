"""Registered queries over vectors, and the DuckDB SQL that must give the same rows."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.baselines import others
from vecblock.functions import arrays as A
from vecblock.functions import metrics as M
from vecblock.operators import dissim, exact, graph, ingest, measures, partition, search, seeding, temporal, tree, view
from vecblock.operators.partition import PartitionParams
from vecblock.operators.search import ALL, SearchParams
from vecblock.sources import vectors as V
from vecblock.sources.stored import fresh_path, stored

QUERIES: dict = {}
SQL: dict[str, str] = {}

PARAMS = tree.TreeParams(leaf_capacity=64, inner_capacity=8, partition=PartitionParams(max_cluster_rows=40, fanout=4, lloyd_iters=5, init="farthest"))


def query(sql: str | None = None, name: str | None = None):
    def put(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            SQL[key] = sql
        return f

    return put


def r6(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns})


def long_rank(df: DataFrame) -> DataFrame:
    return r6(df, "dist").withColumn("rank", F.col("rank").cast("long")).select("query_id", "rank", "vec_id", "dist")


# --- the index that several queries share -----------------------------------------


@lru_cache(maxsize=8)
def _tree(spark: SparkSession, sf_dir: str, kind: str = "raw") -> tree.BlockTree:
    source = {"raw": V.vectors, "hubs": V.hubs, "cosine": V.vectors}[kind]
    params = tree.TreeParams(**{**PARAMS.__dict__, "metric": "cosine" if kind == "cosine" else "l2"})
    return tree.build(source(spark, sf_dir), params)


# --- SQL pieces ------------------------------------------------------------------

BASE = "v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v, label FROM embeddings), q AS (SELECT vec_id AS query_id, v AS qv FROM v WHERE vec_id % 10 = 0)"
HUBS = "v AS (SELECT vec_id, list_transform(CAST(embedding AS DOUBLE[]), lambda x, i: CASE WHEN i = label + 1 THEN x + 1.0 ELSE x END) AS v, label FROM embeddings), q AS (SELECT vec_id AS query_id, v AS qv FROM v WHERE vec_id % 10 = 0)"


def pair_sql(expr: str) -> str:
    return f"WITH {BASE} SELECT query_id, vec_id, {expr} AS dist FROM q, v"


def knn_sql(k: int, expr: str = "list_distance(qv, v)", base: str = BASE, order: str = "d, vec_id", where: str = "query_id <> vec_id") -> str:
    return f"WITH {base}, d AS (SELECT query_id, vec_id, {expr} AS d FROM q, v WHERE {where}) SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY {order}) AS rank, vec_id, round(d, 6) AS dist FROM d QUALIFY rank <= {k}"


ZERO = "SELECT * FROM (VALUES {}) AS t(\"check\", violations)"


def zeros(*names: str) -> str:
    return "SELECT c AS \"check\", CAST(0 AS BIGINT) AS violations FROM (VALUES " + ", ".join(f"('{n}')" for n in names) + ") t(c)"


# --- distances ---------------------------------------------------------------------


def _pairs(spark, sf_dir, f):
    v = V.vectors(spark, sf_dir)
    q = V.queries_of(v).withColumnRenamed("v", "qv")
    return v.join(F.broadcast(q), how="cross").select("query_id", "vec_id", f(F.col("qv"), F.col("v")).alias("dist"))  # the stated query set against all rows


def _packed(spark, sf_dir, metric, f):
    """The same pairs rounded to six digits, scored in packs; ``f`` is the column form of the metric."""
    v = V.vectors(spark, sf_dir)
    q = V.queries_of(v).withColumnRenamed("v", "qv")

    return exact.pairs(v.select("vec_id", "v"), q, lambda a, b: [A.round_half_up(A.fold(a, b, metric), 6)], lambda a, b: [F.round(f(a, b), 6)], {"dist": "double"})


def _packed_long(spark, sf_dir, kernel, plain):
    v = V.vectors(spark, sf_dir)
    return exact.pairs(v.select("vec_id", "v"), V.queries_of(v).withColumnRenamed("v", "qv"), lambda a, b: [kernel(a, b)], lambda a, b: [plain(a, b)], {"dist": "long"})


_ZIP = "list_transform(list_zip(qv, v), lambda z: {})"
#: Metrics of queries that are scored in packs.
_PACKED = {"dist_chebyshev": "chebyshev", "dist_cosine": "cosine", "dist_dot": "dot", "dist_l2": "l2", "dist_l2_sq": "l2_sq", "dist_manhattan": "l1"}
for _name, _f, _sql in (
    ("dist_l2", M.l2, "list_distance(qv, v)"),
    ("dist_l2_sq", M.l2_sq, "list_distance(qv, v) * list_distance(qv, v)"),
    ("dist_cosine", M.cosine, "list_cosine_distance(qv, v)"),
    ("dist_dot", M.dot, "list_inner_product(qv, v)"),
    ("dist_manhattan", lambda a, b: M.minkowski(a, b, 1), "list_sum(" + _ZIP.format("abs(z[1] - z[2])") + ")"),
    ("dist_minkowski3", lambda a, b: M.minkowski(a, b, 3), "pow(list_sum(" + _ZIP.format("pow(abs(z[1] - z[2]), 3)") + "), 1.0 / 3.0)"),
    ("dist_chebyshev", lambda a, b: M.minkowski(a, b, float("inf")), "list_max(" + _ZIP.format("abs(z[1] - z[2])") + ")"),
):

    def _run(spark, sf_dir, f=_f, metric=_PACKED.get(_name)):
        return _packed(spark, sf_dir, metric, f) if metric else r6(_pairs(spark, sf_dir, f), "dist")

    query(pair_sql(f"round({_sql}, 6)"), _name)(_run)


@query(pair_sql("CAST(list_sum(" + _ZIP.format("CASE WHEN (z[1] > 0) <> (z[2] > 0) THEN 1 ELSE 0 END") + ") AS BIGINT)"))
def dist_hamming(spark, sf_dir):
    sign = lambda v: F.transform(v, lambda x: (x > 0).cast("int"))
    return _packed_long(spark, sf_dir, lambda a, b: A.fold(A.positive(a), A.positive(b), "hamming"), lambda a, b: M.hamming(sign(a), sign(b)))


@query(pair_sql("CAST(list_sum(list_transform(list_zip(qv[1:32], v[1:32]), lambda z: CASE WHEN (z[1] > 0) <> (z[2] > 0) THEN 1 ELSE 0 END)) AS BIGINT)"))
def dist_hamming_packed(spark, sf_dir):
    pack = lambda v: M.sign_bits(F.slice(v, 1, 32))
    return _packed_long(spark, sf_dir, lambda a, b: np.bitwise_count(A.sign_bits(a[:, :32])[:, None] ^ A.sign_bits(b[:, :32])[None]), lambda a, b: F.bit_count(pack(a).bitwiseXOR(pack(b))))


@query(f"""WITH {BASE}, e AS (SELECT vec_id, unnest(v) AS x, generate_subscripts(v, 1) AS p FROM v), s AS (SELECT p, var_samp(x) AS s FROM e GROUP BY p), w AS (SELECT list(s ORDER BY p) AS w FROM s)
SELECT query_id, vec_id, round(sqrt(list_sum(list_transform(list_zip(qv, v, w), lambda z: (z[1] - z[2]) * (z[1] - z[2]) / z[3]))), 6) AS dist FROM q, v, w""")
def dist_mahalanobis_diag(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    var = M._positions(v.withColumn("g", F.lit(1)), ["g"], "v", F.var_samp).first().v  # 64 numbers
    lit = F.array(*[F.lit(float(x)) for x in var])
    return r6(_pairs(spark, sf_dir, lambda a, b: M.mahalanobis_diag(a, b, lit)), "dist")


@query(f"WITH {BASE} SELECT vec_id, round(sqrt(list_inner_product(v, v)), 6) AS norm, round(list_sum(list_transform(v, lambda x: abs(x) / sqrt(list_inner_product(v, v)))), 6) AS l1_of_unit FROM v")
def norms(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    return r6(v.select("vec_id", M.norm(F.col("v")).alias("norm"), F.aggregate(M.normalized(F.col("v")), F.lit(0.0), lambda s, x: s + F.abs(x)).alias("l1_of_unit")), "norm", "l1_of_unit")


@query(f"WITH {BASE} SELECT query_id, vec_id, round(list_distance(qv, v), 6) AS l2, round(list_cosine_distance(qv, v), 6) AS cosine, round(list_cosine_similarity(qv, v), 6) AS similarity FROM q, v")
def sql_functions(spark, sf_dir):
    from vecblock.functions import sql as S

    S.register(spark)
    v = V.vectors(spark, sf_dir)
    v.createOrReplaceTempView("vecblock_v")
    V.queries_of(v).createOrReplaceTempView("vecblock_q")
    return spark.sql("SELECT query_id, vec_id, round(vec_l2(q.v, v.v), 6) AS l2, round(vec_cosine(q.v, v.v), 6) AS cosine, round(vec_similarity(q.v, v.v), 6) AS similarity FROM vecblock_q q CROSS JOIN vecblock_v v")


@query(f"WITH {BASE} SELECT query_id, vec_id, round(list_distance(qv, v), 6) AS l2, round(list_inner_product(qv, v), 6) AS dot FROM q, v WHERE query_id <> vec_id")
def arrow_functions(spark, sf_dir):
    from vecblock.functions import sql as S

    S.register_fast(spark)
    v = V.vectors(spark, sf_dir)
    names, q = ("l2", "dot"), V.queries_of(v).withColumnRenamed("v", "qv")
    pairs = exact.pairs(v.select("vec_id", "v"), q, lambda a, b: [A.round_half_up(S.over_packs(m, a, b), 6) for m in names], lambda a, b: [F.round(F.call_function(f"vec_{m}_fast", a, b), 6) for m in names], dict.fromkeys(names, "double"))
    return pairs.where("query_id <> vec_id")


@query(f"WITH {BASE} SELECT vec_id, CAST(generate_subscripts(v, 1) - 1 AS BIGINT) AS pos, round(unnest(v), 6) AS val FROM v")
def table_function_unpack(spark, sf_dir):
    from vecblock.functions import sql as S

    S.register_tables(spark)
    V.vectors(spark, sf_dir).createOrReplaceTempView("vecblock_v")
    return spark.sql("SELECT vec_id, CAST(u.pos AS BIGINT) AS pos, round(u.val, 6) AS val FROM vecblock_v, LATERAL vec_unpack(v) u")


# --- exact answers --------------------------------------------------------------------


def _exact(spark, sf_dir, **kw):
    v = V.vectors(spark, sf_dir)
    return long_rank(exact.knn(v, V.queries_of(v), **kw))


query(knn_sql(10), "knn_l2_10")(lambda s, d: _exact(s, d, k=10))
query(knn_sql(100), "knn_l2_100")(lambda s, d: _exact(s, d, k=100))
query(knn_sql(10, "list_cosine_distance(qv, v)"), "knn_cosine_10")(lambda s, d: _exact(s, d, k=10, metric="cosine"))
query(knn_sql(10, order="d DESC, vec_id"), "kfn_l2_10")(lambda s, d: _exact(s, d, k=10, farthest=True))
query(knn_sql(10, "list_sum(" + _ZIP.format("abs(z[1] - z[2])") + ")"), "knn_manhattan_10")(lambda s, d: _exact(s, d, k=10, metric="l1"))


@query(knn_sql(5, base=BASE.replace(" WHERE vec_id % 10 = 0", "")))
def knn_graph_5(spark, sf_dir):
    return long_rank(exact.knn_graph(V.vectors(spark, sf_dir), 5))


@query(f"WITH n AS ({knn_sql(10)}) SELECT query_id, array_to_string(list(vec_id ORDER BY vec_id), ',') AS ids FROM n GROUP BY query_id")
def knn_sets_10(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    return exact.knn_sets(v, V.queries_of(v), 10).select("query_id", F.array_join(F.transform("ids", lambda x: x.cast("string")), ",").alias("ids"))


@query(f"WITH {BASE} SELECT query_id, vec_id, round(list_distance(qv, v), 6) AS dist FROM q, v WHERE query_id <> vec_id AND list_distance(qv, v) <= 1.2")
def range_radius(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    return r6(exact.within(v, V.queries_of(v), 1.2), "dist")


def trigram_sql(name: str, table: str, keys: str, where: str = "TRUE") -> str:
    k = keys
    using = f"USING ({k})"
    return f"""{name}_g AS (SELECT {k}, substr(t, CAST(i AS BIGINT), 3) AS g FROM (SELECT {k}, lower(text) AS t, unnest(generate_series(1, greatest(length(text) - 2, 1))) AS i FROM {table} WHERE ({where}) AND length(text) > 0)),
{name}_c AS (SELECT {k}, CAST(('0x' || substr(md5(g), 1, 8)) AS BIGINT) % 64 AS b, CAST(count(*) AS DOUBLE) AS c FROM {name}_g GROUP BY ALL),
{name}_n AS (SELECT {k}, sqrt(sum(c * c)) AS n FROM {name}_c GROUP BY {k}),
{name}_f AS (SELECT {k}, n, unnest(generate_series(0, 63)) AS b FROM {name}_n),
{name} AS (SELECT {k}, list(coalesce(c, 0.0) / n ORDER BY b) AS v FROM {name}_f LEFT JOIN {name}_c USING ({k}, b) GROUP BY {k})"""


DOCV, TURNV = trigram_sql("dv", "documents", "doc_id"), trigram_sql("tv", "conversations", "conv_id, turn", "role = 'user'")


@query(f"WITH {DOCV} SELECT doc_id AS vec_id, CAST(p AS BIGINT) AS pos, round(x, 6) AS x FROM (SELECT doc_id, unnest(v) AS x, generate_subscripts(v, 1) - 1 AS p FROM dv) WHERE x <> 0")
def trigram_vectors(spark, sf_dir):
    return r6(V.document_vectors(spark, sf_dir).select("vec_id", F.posexplode("v").alias("pos", "x")).where("x <> 0").withColumn("pos", F.col("pos").cast("long")), "x")


@query(f"WITH {DOCV}, {TURNV}, d AS (SELECT conv_id, turn, doc_id, list_distance(tv.v, dv.v) AS d FROM tv, dv) SELECT conv_id, turn, row_number() OVER (PARTITION BY conv_id, turn ORDER BY round(d, 9), doc_id) AS rank, doc_id AS vec_id, round(d, 6) AS dist FROM d QUALIFY rank <= 3")
def similarity_join(spark, sf_dir):
    docs, turns = V.document_vectors(spark, sf_dir), V.turn_vectors(spark, sf_dir)
    q = stored(turns.withColumn("query_id", F.monotonically_increasing_id()), "turns")
    near = exact.knn(docs, q.select("query_id", "v"), 20, exclude_self=False)
    w = Window.partitionBy("query_id").orderBy(F.round("dist", 9), "vec_id")
    top = near.withColumn("rank", F.row_number().over(w).cast("long")).where("rank <= 3")
    return r6(top.join(q.select("query_id", "conv_id", "turn"), "query_id").select("conv_id", "turn", "rank", "vec_id", "dist"), "dist")


# --- centroids, seeds and clusters -----------------------------------------------------


def _by_label_sql(agg: str) -> str:
    return f"WITH {BASE}, e AS (SELECT label, unnest(v) AS x, generate_subscripts(v, 1) - 1 AS pos FROM v) SELECT CAST(label AS BIGINT) AS label, CAST(pos AS BIGINT) AS pos, round({agg}(x), 6) AS x FROM e GROUP BY ALL"


for _name, _f, _agg in (("centroid_by_label", M.centroid, "avg"), ("vector_sum_by_label", M.vector_sum, "sum"), ("vector_min_by_label", M.vector_min, "min"), ("vector_max_by_label", M.vector_max, "max")):

    def _run(spark, sf_dir, f=_f):
        df = f(V.vectors(spark, sf_dir), ["label"]).select(F.col("label").cast("long"), F.posexplode("v").alias("pos", "x"))
        return r6(df.withColumn("pos", F.col("pos").cast("long")), "x")

    query(_by_label_sql(_agg), _name)(_run)


@query(_by_label_sql("avg"))
def aggregate_function_mean(spark, sf_dir):
    from vecblock.functions import sql as S

    df = S.vec_mean(V.vectors(spark, sf_dir).withColumn("label", F.col("label").cast("long")), ["label"])
    return r6(df.select("label", F.posexplode("v").alias("pos", "x")).withColumn("pos", F.col("pos").cast("long")), "x")


def _round_sql(name: str, old: str) -> str:
    return f"""{name}_a AS (SELECT vec_id, v.v AS v, arg_min(pos, {{'d': list_distance(v.v, {old}.v), 'p': pos}}) AS pos FROM v, {old} GROUP BY vec_id, v.v),
{name}_e AS (SELECT pos, unnest(v) AS x, generate_subscripts(v, 1) AS p FROM {name}_a), {name}_m AS (SELECT pos, p, avg(x) AS x FROM {name}_e GROUP BY pos, p),
{name} AS (SELECT pos, list(x ORDER BY p) AS v FROM {name}_m GROUP BY pos)"""


_START = "c0 AS (SELECT vec_id AS pos, v FROM v WHERE vec_id < 6)"
_CENTERS = "SELECT CAST(pos AS BIGINT) AS pos, CAST((SELECT count(*) FROM {0}_a a WHERE a.pos = {0}.pos) AS BIGINT) AS n, round(list_sum(list_transform(v, lambda x, i: x * i)), 5) AS digest FROM {0}"


def _centers(df: DataFrame) -> DataFrame:
    digest = F.aggregate(F.transform("v", lambda x, i: x * (i + 1)), F.lit(0.0), lambda s, x: s + x)
    return df.select(F.col("pos").cast("long").alias("pos"), "n", F.round(digest, 5).alias("digest"))


@query(f"WITH {BASE}, {_START}, {_round_sql('c1', 'c0')} " + _CENTERS.format("c1"))
def kmeans_one_round(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    return _centers(partition.lloyd_round(v, v.where("vec_id < 6").select(F.col("vec_id").cast("int").alias("pos"), "v")))


@query(f"WITH {BASE}, {_START}, {_round_sql('c1', 'c0')}, {_round_sql('c2', 'c1')} " + _CENTERS.format("c2"))
def kmeans_two_rounds(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    return _centers(partition.kmeans(v, v.where("vec_id < 6").select(F.col("vec_id").cast("int").alias("pos"), "v"), 2))


@query(f"""WITH RECURSIVE {BASE}, s0 AS (SELECT vec_id, v FROM v ORDER BY vec_id LIMIT 1),
s1 AS (SELECT v.vec_id, v.v FROM v, s0 ORDER BY list_distance(v.v, s0.v) DESC, v.vec_id LIMIT 1),
s2 AS (SELECT v.vec_id, v.v FROM v, s0, s1 ORDER BY least(list_distance(v.v, s0.v), list_distance(v.v, s1.v)) DESC, v.vec_id LIMIT 1),
s3 AS (SELECT v.vec_id, v.v FROM v, s0, s1, s2 ORDER BY least(list_distance(v.v, s0.v), list_distance(v.v, s1.v), list_distance(v.v, s2.v)) DESC, v.vec_id LIMIT 1)
SELECT CAST(0 AS BIGINT) AS pos, vec_id FROM s0 UNION ALL SELECT 1, vec_id FROM s1 UNION ALL SELECT 2, vec_id FROM s2 UNION ALL SELECT 3, vec_id FROM s3""")
def seeds_farthest4(spark, sf_dir):
    return seeding.farthest(V.vectors(spark, sf_dir), 4).select(F.col("pos").cast("long").alias("pos"), "vec_id")


@query(f"WITH {BASE} SELECT row_number() OVER (ORDER BY CAST(('0x' || substr(md5(CAST(vec_id AS VARCHAR) || '|42|0'), 1, 8)) AS BIGINT), vec_id) - 1 AS pos, vec_id FROM v QUALIFY pos < 8")
def seeds_random8(spark, sf_dir):
    return seeding.random(V.vectors(spark, sf_dir), 8).select(F.col("pos").cast("long").alias("pos"), "vec_id")


@query()
def seeds_d2(spark, sf_dir):
    return seeding.d2(V.vectors(spark, sf_dir), 8).select("pos", "vec_id")


@query()
def seeds_parallel(spark, sf_dir):
    return seeding.parallel(V.vectors(spark, sf_dir), 8).select("pos")


def _hierarchy(spark, sf_dir, **kw):
    return partition.hierarchy(V.hubs(spark, sf_dir), PartitionParams(**{**PARAMS.partition.__dict__, **kw}))


@query(zeros("every_vector_once", "final_sizes", "parents_sum"))
def hierarchy_invariants(spark, sf_dir):
    h = _hierarchy(spark, sf_dir)
    n = V.vectors(spark, sf_dir).count()
    own = h.clusters.select("path", "n")
    counted = partition.subtree_counts(h.clusters).withColumnRenamed("n", "below")
    bad = {
        "every_vector_once": abs(h.members.count() - n) + abs(h.members.select("vec_id").distinct().count() - n),
        "final_sizes": h.clusters.where(f"is_final AND n > {PARAMS.partition.max_cluster_rows}").count(),
        "parents_sum": own.join(counted, "path").where("n <> below").count(),
    }
    return spark.createDataFrame([(k, int(v)) for k, v in bad.items()], "check string, violations long")


@query()
def hierarchy_sizes(spark, sf_dir):
    return _hierarchy(spark, sf_dir).clusters.select("path", "level", "n", "is_final")


@query()
def hierarchy_flat(spark, sf_dir):
    return _hierarchy(spark, sf_dir, max_depth=1, fanout=16).clusters.select("path", "level", "n")


@query()
def hierarchy_binary(spark, sf_dir):
    return partition.density_report(_hierarchy(spark, sf_dir, fanout=2).clusters)


# --- structures that DuckDB can build too ------------------------------------------------

_SEG = "seg AS (SELECT n_regionkey AS r, c_nationkey AS n, dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS s, count(*) AS k FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_regionkey, c_nationkey, c_mktsegment)"
_CLUSTERS = f"""{_SEG}, cl AS (SELECT 'r' AS path, NULL AS parent_path, 0 AS level, sum(k) AS n, FALSE AS is_final FROM seg UNION ALL SELECT 'r.' || r, 'r', 1, sum(k), FALSE FROM seg GROUP BY r
UNION ALL SELECT 'r.' || r || '.' || n, 'r.' || r, 2, sum(k), FALSE FROM seg GROUP BY r, n UNION ALL SELECT 'r.' || r || '.' || n || '.' || s, 'r.' || r || '.' || n, 3, k, TRUE FROM seg)"""


def fixture_clusters(spark, sf_dir) -> DataFrame:
    """World, region, nation, market segment as a hierarchy of customer counts."""
    c = V.table(spark, sf_dir, "customer").join(V.table(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    c = c.groupBy("n_regionkey", "c_nationkey", "c_mktsegment").agg(F.count("*").alias("k"))
    c = c.withColumn("s", F.dense_rank().over(Window.orderBy("c_mktsegment")) - 1)  # five segments per nation
    full = c.select(F.concat_ws(".", F.lit("r"), F.col("n_regionkey"), F.col("c_nationkey"), F.col("s")).alias("leaf"), "k")
    every = full.select(F.explode(partition.prefixes("leaf")).alias("path"), "k").groupBy("path").agg(F.sum("k").alias("n"))
    level = F.size(F.split("path", r"\.")) - 1
    return every.select("path", F.when(F.col("path") != "r", F.regexp_replace("path", r"\.[0-9]+$", "")).alias("parent_path"), level.alias("level"), "n", (level == 3).alias("is_final"), F.lit(False).alias("degenerate"))


@query(f"WITH {_CLUSTERS}, tops AS (SELECT c.path AS leaf_path FROM cl c LEFT JOIN cl p ON c.parent_path = p.path WHERE c.n <= 100 AND (p.n IS NULL OR p.n > 100)) SELECT f.path, t.leaf_path FROM cl f JOIN tops t ON f.path = t.leaf_path OR starts_with(f.path, t.leaf_path || '.') WHERE f.is_final")
def tree_cut_fixture(spark, sf_dir):
    return tree.cut(fixture_clusters(spark, sf_dir), 100)


@query(f"WITH {_CLUSTERS} SELECT path, path AS leaf_path FROM cl WHERE is_final")
def tree_cut_by_cluster(spark, sf_dir):
    return tree.cut(fixture_clusters(spark, sf_dir), 100, "cluster")


@query(f"WITH RECURSIVE {_CLUSTERS}, up AS (SELECT path, path AS ancestor, 0 AS distance FROM cl UNION ALL SELECT up.path, cl.parent_path, distance + 1 FROM up JOIN cl ON up.ancestor = cl.path WHERE cl.parent_path IS NOT NULL) SELECT path, ancestor, CAST(distance AS BIGINT) AS distance FROM up")
def tree_paths_recursive(spark, sf_dir):
    return partition.paths(fixture_clusters(spark, sf_dir)).withColumn("distance", F.col("distance").cast("long"))


@query(f"WITH {_CLUSTERS} SELECT path, CAST(n AS BIGINT) AS n FROM cl")
def tree_subtree_counts(spark, sf_dir):
    return partition.subtree_counts(fixture_clusters(spark, sf_dir))


def _fixture_nodes(spark, sf_dir):
    c = fixture_clusters(spark, sf_dir)
    number = F.xxhash64
    return c.select(number("path").alias("node_id"), number("parent_path").alias("parent_id"), "path", F.col("is_final").alias("is_leaf")).withColumn("parent_id", F.when(F.col("path") != "r", F.col("parent_id")))


@query(f"WITH {_CLUSTERS} SELECT path, CAST(level - 1 AS BIGINT) AS depth FROM cl WHERE path = 'r.1' OR starts_with(path, 'r.1.')")
def tree_subtree_fixture(spark, sf_dir):
    nodes = _fixture_nodes(spark, sf_dir)
    root = nodes.where("path = 'r.1'").first().node_id
    return tree.subtree(nodes, root).join(nodes.select("node_id", "path"), "node_id").select("path", F.col("depth").cast("long").alias("depth"))


@query(f"WITH {_CLUSTERS} SELECT path, lag(path) OVER (ORDER BY path) AS prev_path, lead(path) OVER (ORDER BY path) AS next_path FROM cl WHERE is_final")
def leaf_chain_fixture(spark, sf_dir):
    c = fixture_clusters(spark, sf_dir).where("is_final")
    got = tree.chain(c.select(F.col("path").alias("leaf_id"), F.col("path").alias("node_order")))
    return got.select(F.col("leaf_id").alias("path"), F.col("prev_leaf").alias("prev_path"), F.col("next_leaf").alias("next_path"))


# --- the tree --------------------------------------------------------------------------

CHECKS = ("one_root", "leaf_depths", "inner_capacity", "leaf_capacity", "child_rows", "leaf_rows", "each_vector_once", "rows_inside_radius")


@query(zeros(*CHECKS))
def tree_invariants(spark, sf_dir):
    return tree.invariants(_tree(spark, sf_dir))


@query(zeros(*CHECKS))
def tree_invariants_packed(spark, sf_dir):
    p = tree.TreeParams(**{**PARAMS.__dict__, "how": "pack"})
    return tree.invariants(tree.build(V.hubs(spark, sf_dir), p))


@query(f"WITH {BASE} SELECT count(*) AS n, count(DISTINCT vec_id) AS n_distinct FROM v")
def leaf_partition_of_rows(spark, sf_dir):
    return _tree(spark, sf_dir).rows.agg(F.count("*").alias("n"), F.count_distinct("vec_id").alias("n_distinct"))


@query()
def tree_balance(spark, sf_dir):
    return tree.balance(_tree(spark, sf_dir, "hubs").nodes)


def _search(spark, sf_dir, kind="raw", links=None, **kw):
    t = _tree(spark, sf_dir, kind)
    q = V.queries_of(V.hubs(spark, sf_dir) if kind == "hubs" else V.vectors(spark, sf_dir))
    return search.search(t, q, SearchParams(**kw), links)


query(knn_sql(10), "tree_search_full_beam")(lambda s, d: long_rank(_search(s, d, beam=ALL)))
query(knn_sql(10), "tree_search_batch_1")(lambda s, d: long_rank(_search(s, d, beam=ALL, batch_size=1)))
query(knn_sql(10), "tree_search_batch_64")(lambda s, d: long_rank(_search(s, d, beam=ALL, batch_size=64)))
query(knn_sql(10), "tree_search_drain_all")(lambda s, d: long_rank(_search(s, d, beam=ALL, frontier="drain")))
query(knn_sql(10), "tree_search_best_first_all")(lambda s, d: long_rank(_search(s, d, frontier="best_first", max_leaves=ALL)))
query(knn_sql(10, order="d DESC, vec_id"), "tree_search_farthest_full")(lambda s, d: long_rank(_search(s, d, beam=ALL, farthest=True)))
query(knn_sql(10, "list_cosine_distance(qv, v)"), "tree_search_cosine_full")(lambda s, d: long_rank(_search(s, d, "cosine", beam=ALL)))


@query(knn_sql(10))
def tree_search_exact_pruned(spark, sf_dir):
    return long_rank(search.search_exact(_tree(spark, sf_dir), V.queries_of(V.vectors(spark, sf_dir)), 10))


@query(knn_sql(10, base=HUBS))
def tree_search_exact_hubs(spark, sf_dir):
    return long_rank(search.search_exact(_tree(spark, sf_dir, "hubs"), V.queries_of(V.hubs(spark, sf_dir)), 10))


@query(knn_sql(10, order="d DESC, vec_id"))
def tree_farthest_exact_pruned(spark, sf_dir):
    return long_rank(search.search_exact(_tree(spark, sf_dir), V.queries_of(V.vectors(spark, sf_dir)), 10, farthest=True))


@query(f"WITH {BASE} SELECT query_id, vec_id, round(list_distance(qv, v), 6) AS dist FROM q, v WHERE query_id <> vec_id AND list_distance(qv, v) <= 1.2")
def tree_range(spark, sf_dir):
    return r6(search.within(_tree(spark, sf_dir), V.queries_of(V.vectors(spark, sf_dir)), 1.2), "dist")


@query(zeros("beam_opens_more_than_drain"))
def drain_superset(spark, sf_dir):
    t, q = _tree(spark, sf_dir), V.queries_of(V.vectors(spark, sf_dir))
    leaves = lambda f: search.descend(t, q, SearchParams(beam=2, frontier=f)).where("is_leaf").select("query_id", "node_id")
    return leaves("beam").exceptAll(leaves("drain")).agg(F.count("*").alias("violations")).select(F.lit("beam_opens_more_than_drain").alias("check"), "violations")


@query(knn_sql(10, where="query_id <> vec_id AND label < 5"))
def filter_pre_knn(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    return long_rank(search.search(_tree(spark, sf_dir), V.queries_of(v), SearchParams(beam=ALL), allowed=v.where("label < 5")))


@query(f"WITH n AS ({knn_sql(40)}), f AS (SELECT n.query_id, n.vec_id, n.rank, n.dist FROM n JOIN embeddings e USING (vec_id) WHERE e.label < 5) SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY rank) AS rank, vec_id, dist FROM f QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY f.rank) <= 10")
def filter_post_knn(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    return long_rank(search.post_filtered(_tree(spark, sf_dir), V.queries_of(v), v.where("label < 5"), 10, 4, beam=ALL))


query(knn_sql(10), "rerank_100_to_10")(lambda s, d: long_rank(search.rerank(_tree(s, d), V.queries_of(V.vectors(s, d)), 100, 10, beam=ALL)))


@query()
def beam_curve(spark, sf_dir):
    from vecblock.plans import workloads

    return workloads.beam_curve(spark, sf_dir)


# --- links --------------------------------------------------------------------------------

_ALL_Q = BASE.replace(" WHERE vec_id % 10 = 0", "")


@query(f"WITH n AS ({knn_sql(6, base=_ALL_Q)}) SELECT query_id AS src, vec_id AS dst, dist FROM n")
def links_full(spark, sf_dir):
    t = _tree(spark, sf_dir)
    return r6(graph.build_links(t, 6, t.levels[-1]).select("src", "dst", "dist"), "dist")


_LABEL_LEAVES = f"WITH {BASE}, e AS (SELECT label, unnest(v) AS x, generate_subscripts(v, 1) AS p FROM v), m AS (SELECT label, p, avg(x) AS x FROM e GROUP BY label, p), c AS (SELECT CAST(label AS BIGINT) AS leaf_id, list(x ORDER BY p) AS v FROM m GROUP BY label)"


@query(_LABEL_LEAVES + " SELECT a.leaf_id, b.leaf_id AS near_id, row_number() OVER (PARTITION BY a.leaf_id ORDER BY list_distance(a.v, b.v), b.leaf_id) AS rank FROM c a, c b QUALIFY rank <= 4")
def near_leaves_fixture(spark, sf_dir):
    leaves = M.centroid(V.vectors(spark, sf_dir), ["label"]).select(F.col("label").cast("long").alias("leaf_id"), F.col("v").alias("centroid"))
    return graph.near_leaves(leaves, 4).select("leaf_id", "near_id", F.col("rank").cast("long").alias("rank"))


@query(f"WITH n AS ({knn_sql(6, base=_ALL_Q)}) SELECT CASE WHEN a.label = b.label THEN 'within' ELSE 'across' END AS kind, count(*) AS n FROM n JOIN embeddings a ON a.vec_id = n.query_id JOIN embeddings b ON b.vec_id = n.vec_id GROUP BY 1")
def link_kinds(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    links = exact.knn_graph(v, 6).select(F.col("query_id").alias("src"), F.col("vec_id").alias("dst"), "dist")
    named = v.select("vec_id", F.col("label").cast("long").alias("leaf"))
    links = links.join(named.select(F.col("vec_id").alias("src"), F.col("leaf").alias("src_leaf")), "src").join(named.select(F.col("vec_id").alias("dst"), F.col("leaf").alias("dst_leaf")), "dst")
    return graph.with_kind(links).groupBy("kind").agg(F.count("*").alias("n"))


@query("SELECT CAST(0 AS BIGINT) AS violations")
def greedy_fixpoint(spark, sf_dir):
    v = V.hubs(spark, sf_dir)
    q, t = V.queries_of(v), _tree(spark, sf_dir, "hubs")
    links = graph.build_links(t, 8, 4)
    found = graph.greedy(search.search(t, q, SearchParams(beam=1, exclude_self=False)), links, v, q, 10, exclude_self=False)
    return graph.fixpoint_violations(found.select("query_id", "vec_id", "dist"), links, v, q, 10)


@query("SELECT CAST(0 AS BIGINT) AS violations")
def pruned_links_equal(spark, sf_dir):
    """Ordered leaves: bands give the same links as all pairs of a leaf."""
    t = _tree(spark, sf_dir, "hubs")
    got = graph.build_links_pruned(t.rows, 1.1).select("src", "dst")
    a, b = t.rows.select("leaf_id", F.col("vec_id").alias("src"), F.col("v").alias("x")), t.rows.select("leaf_id", F.col("vec_id").alias("dst"), F.col("v").alias("y"))
    want = a.join(b, "leaf_id").where("src <> dst").where(M.l2(F.col("x"), F.col("y")) <= 1.1).select("src", "dst")
    return got.exceptAll(want).union(want.exceptAll(got)).agg(F.count("*").alias("violations"))


def _edges_sql(far: bool) -> str:
    op = ">" if far else "<"
    return f"WITH {BASE}, d AS MATERIALIZED (SELECT a.vec_id AS a, b.vec_id AS b, list_distance(a.v, b.v) AS d FROM v a, v b WHERE a.vec_id <> b.vec_id) SELECT o.a, o.b, round(o.d, 6) AS dist FROM d o WHERE o.a < o.b AND NOT EXISTS (SELECT 1 FROM d x, d y WHERE x.a = o.a AND y.a = o.b AND x.b = y.b AND x.d {op} o.d AND y.d {op} o.d)"


query(_edges_sql(False), "rng_edges")(lambda s, d: r6(others.rng_edges(V.vectors(s, d)), "dist"))
query(_edges_sql(True), "dissim_rng_edges")(lambda s, d: r6(others.far_edges(V.vectors(s, d)), "dist"))


@query(f"WITH f AS ({knn_sql(16, base=_ALL_Q, order='d DESC, vec_id')}) SELECT x.query_id AS a, x.vec_id AS b FROM f x JOIN f y ON x.query_id = y.vec_id AND x.vec_id = y.query_id WHERE x.query_id < x.vec_id")
def mutual_far_edges(spark, sf_dir):
    return others.mutual_far_edges(V.vectors(spark, sf_dir), 16)


# --- views and sequences ---------------------------------------------------------------------


def _view(spark, sf_dir, size=50, **kw):
    t = _tree(spark, sf_dir)
    return view.create(t, V.queries_of(V.vectors(spark, sf_dir)).where("query_id = 0"), size, **kw)


_VIEW = f"{BASE}, w AS (SELECT v.vec_id, v.v FROM v, (SELECT qv FROM q WHERE query_id = 0) a ORDER BY list_distance(a.qv, v.v), vec_id LIMIT 50)"


@query(f"WITH {_VIEW} SELECT vec_id FROM w")
def view_rows(spark, sf_dir):
    return view.as_rows(spark, _view(spark, sf_dir)).select("vec_id")


def _view_sql(order: str, k: int) -> str:
    return f"WITH {_VIEW}, d AS (SELECT query_id, w.vec_id, list_distance(qv, w.v) AS d FROM q, w WHERE query_id <> w.vec_id) SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY {order}) AS rank, vec_id, round(d, 6) AS dist FROM d QUALIFY rank <= {k}"


@query(_view_sql("d, vec_id", 10))
def view_search(spark, sf_dir):
    return long_rank(view.search_view(_view(spark, sf_dir), V.queries_of(V.vectors(spark, sf_dir)), 10))


@query(_view_sql("d, vec_id", 10))
def view_search_induced(spark, sf_dir):
    return long_rank(view.search_view(_view(spark, sf_dir, build="induced"), V.queries_of(V.vectors(spark, sf_dir)), 10))


@query(_view_sql("d DESC, vec_id", 5))
def view_farthest(spark, sf_dir):
    return long_rank(view.search_view(_view(spark, sf_dir), V.queries_of(V.vectors(spark, sf_dir)), 5, farthest=True))


@query(f"WITH {BASE}, a AS (SELECT vec_id AS view_id, v AS av FROM v WHERE vec_id IN (1, 2, 3, 4)) SELECT query_id, CAST(arg_min(view_id, {{'d': list_distance(qv, av), 'i': view_id}}) AS BIGINT) AS view_id, round(min(list_distance(qv, av)), 6) AS dist FROM q, a GROUP BY query_id")
def view_routing(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    return r6(view.route(v.where("vec_id IN (1, 2, 3, 4)").select(F.col("vec_id").alias("view_id"), "v"), V.queries_of(v)), "dist")


@query(f"WITH {BASE}, g AS (SELECT c_custkey AS user_id, CAST(c_custkey % 10 AS BIGINT) AS view_id FROM customer), d AS (SELECT user_id, query_id, vec_id, list_distance(qv, v) AS d FROM g JOIN v ON v.label = g.view_id, q WHERE query_id <> vec_id) SELECT user_id, query_id, row_number() OVER (PARTITION BY user_id, query_id ORDER BY d, vec_id) AS rank, vec_id, round(d, 6) AS dist FROM d QUALIFY rank <= 3")
def view_access(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    grants = V.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), (F.col("c_custkey") % 10).alias("view_id"))
    asked = grants.select("user_id").distinct().join(F.broadcast(V.queries_of(v)), how="cross")  # each user asks the stated questions
    got = view.authorised_search(v.select(F.col("label").cast("long").alias("view_id"), "vec_id", "v"), grants, asked, 3)
    return r6(got.withColumn("rank", F.col("rank").cast("long")), "dist")


def _sessions(spark, sf_dir, source=V.hubs, order="correlated", every=10):
    v = source(spark, sf_dir)
    q = V.queries_of(v, every)
    seq = (temporal.order_correlated if order == "correlated" else temporal.order_random)(q)
    return v, q.join(seq, "query_id").select(F.lit(0).cast("long").alias("session_id"), "seq", "query_id", "v")


@query()
def survival_truth(spark, sf_dir):
    v, s = _sessions(spark, sf_dir)
    return view.survival(view.replay(v, s, 10, 50))


@query()
def survival_radius(spark, sf_dir):
    v, s = _sessions(spark, sf_dir)
    return view.survival(view.replay(v, s, 10, 50, trigger="radius"))


@query(f"""WITH RECURSIVE {BASE}, n AS (SELECT query_id, vec_id, row_number() OVER (PARTITION BY query_id ORDER BY list_distance(qv, v), vec_id) AS rank FROM q, v WHERE query_id <> vec_id),
vw AS (SELECT query_id AS anchor, vec_id FROM n WHERE rank <= 50),
hit AS (SELECT a.query_id AS anchor, b.query_id AS asked, (SELECT count(*) FROM (SELECT w.vec_id FROM vw w, v x, q y WHERE w.anchor = a.query_id AND x.vec_id = w.vec_id AND y.query_id = b.query_id AND w.vec_id <> b.query_id ORDER BY list_distance(y.qv, x.v), w.vec_id LIMIT 10) t WHERE t.vec_id IN (SELECT vec_id FROM n WHERE n.query_id = b.query_id AND rank <= 10)) AS h FROM q a, q b),
run AS (SELECT CAST(0 AS BIGINT) AS query_id, CAST(0 AS BIGINT) AS anchor, CAST(1 AS BIGINT) AS view_no UNION ALL
SELECT run.query_id + 10, CASE WHEN hit.h = 0 THEN run.query_id + 10 ELSE run.anchor END, run.view_no + CASE WHEN hit.h = 0 THEN 1 ELSE 0 END FROM run JOIN hit ON hit.anchor = run.anchor AND hit.asked = run.query_id + 10)
SELECT query_id, view_no FROM run""")
def survival_fixture(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    q = V.queries_of(v).select(F.lit(0).cast("long").alias("session_id"), F.col("query_id").alias("seq"), "query_id", "v")
    return view.replay(v, q, 10, 50).select("query_id", "view_no")


@query(f"""WITH RECURSIVE {BASE}, walk AS (SELECT CAST(0 AS BIGINT) AS seq, min(query_id) AS here, [min(query_id)] AS used FROM q UNION ALL
SELECT seq + 1, nxt, list_append(used, nxt) FROM (SELECT seq, used, (SELECT b.query_id FROM q b, q a WHERE a.query_id = walk.here AND NOT list_contains(walk.used, b.query_id) ORDER BY list_distance(a.qv, b.qv), b.query_id LIMIT 1) AS nxt FROM walk) t WHERE nxt IS NOT NULL)
SELECT here AS query_id, seq FROM walk""")
def query_order_correlated(spark, sf_dir):
    return temporal.order_correlated(V.queries_of(V.vectors(spark, sf_dir)))


@query(f"WITH {BASE} SELECT query_id, row_number() OVER (ORDER BY md5(CAST(query_id AS VARCHAR) || '|42'), query_id) - 1 AS seq FROM q")
def query_order_random(spark, sf_dir):
    return temporal.order_random(V.queries_of(V.vectors(spark, sf_dir)))


def _log(spark, sf_dir):
    """All events as an access log: users as nodes, in event order."""
    return V.table(spark, sf_dir, "events").select(F.col("event_id").alias("seq"), F.floor(F.col("event_id") / 4).cast("long").alias("query_id"), F.pmod("user_id", F.lit(97)).alias("node_id"))


LOG = "log AS (SELECT event_id AS seq, CAST(floor(event_id / 4) AS BIGINT) AS query_id, user_id % 97 AS node_id FROM events)"
LRU = f"{LOG}, p AS (SELECT seq, query_id, node_id, lag(seq) OVER (PARTITION BY node_id ORDER BY seq) AS prev FROM log), h AS (SELECT seq, query_id, node_id, coalesce(prev IS NOT NULL AND (SELECT count(DISTINCT b.node_id) FROM log b WHERE b.seq > p.prev AND b.seq < p.seq) < 20, FALSE) AS hit FROM p)"


@query(f"WITH {LRU} SELECT seq, node_id, hit FROM h")
def lru_stack_distance(spark, sf_dir, log=_log):
    return measures.lru(log(spark, sf_dir), 20).select("seq", "node_id", "hit")


@query(f"WITH {LRU} SELECT seq, node_id, hit FROM h")
def lru_replayed(spark, sf_dir, log=_log):
    return measures.lru_replay(log(spark, sf_dir).withColumn("trace", F.lit(0).cast("long")), 20).select("seq", "node_id", "hit")


@query(f"WITH {LRU} SELECT CAST(floor(seq / 500) AS BIGINT) AS bucket, count(*) AS accesses, round(avg(CASE WHEN hit THEN 1.0 ELSE 0.0 END), 6) AS hit_rate FROM h GROUP BY 1")
def warmup_curve(spark, sf_dir, log=_log):
    return r6(measures.warmup_curve(measures.lru(log(spark, sf_dir), 20), 500), "hit_rate")


@query(f"WITH {LRU}, c AS (SELECT query_id, min(seq) AS seq, CAST(sum(CASE WHEN hit THEN 0 ELSE 1 END) AS BIGINT) AS reads FROM h GROUP BY query_id) SELECT query_id, seq, reads, CAST(sum(reads) OVER (ORDER BY seq) AS BIGINT) AS cum_reads FROM c")
def io_lru(spark, sf_dir, log=_log):
    return measures.io_curve(log(spark, sf_dir), 20)


@query(f"WITH {LOG}, m AS (SELECT *, CASE WHEN row_number() OVER (PARTITION BY node_id ORDER BY seq) = 1 THEN 1 ELSE 0 END AS miss FROM log), c AS (SELECT query_id, min(seq) AS seq, CAST(sum(miss) AS BIGINT) AS reads FROM m GROUP BY query_id) SELECT query_id, seq, reads, CAST(sum(reads) OVER (ORDER BY seq) AS BIGINT) AS cum_reads FROM c")
def io_first_touch(spark, sf_dir, log=_log):
    return measures.io_curve(log(spark, sf_dir))


@query(f"WITH {LOG}, c AS (SELECT query_id, count(*) AS n FROM log GROUP BY query_id) SELECT count(*) AS queries, round(avg(n), 6) AS mean_hops FROM c")
def hops_mean(spark, sf_dir, log=_log):
    return r6(measures.hops(log(spark, sf_dir)), "mean_hops")


@query(f"WITH {LOG} SELECT query_id, CAST(sum(node_id) AS BIGINT) AS n_scored FROM log GROUP BY query_id")
def distance_count(spark, sf_dir, log=_log):
    return measures.distance_count(log(spark, sf_dir).withColumn("n_scored", F.col("node_id")))


@query(f"WITH {LOG} SELECT query_id, round(count(DISTINCT node_id) / 97.0, 6) AS touched FROM log GROUP BY query_id")
def touched_fraction(spark, sf_dir, log=_log):
    return r6(measures.touched_fraction(log(spark, sf_dir), 97), "touched")


@query(f"WITH {LOG}, g AS (SELECT abs(node_id - lag(node_id) OVER (ORDER BY seq)) AS gap FROM log) SELECT count(gap) AS reads, round(avg(gap), 6) AS mean_gap, round(avg(CASE WHEN gap <= 1 THEN 1.0 ELSE 0.0 END) FILTER (gap IS NOT NULL), 6) AS sequential FROM g")
def seek_distance(spark, sf_dir, log=_log):
    return r6(measures.seek_distance(log(spark, sf_dir), "node_id"), "mean_gap", "sequential")


@query(f"WITH {LOG}, pg AS (SELECT seq, query_id, node_id // 10 AS node_id FROM log), m AS (SELECT *, CASE WHEN row_number() OVER (PARTITION BY node_id ORDER BY seq) = 1 THEN 1 ELSE 0 END AS miss FROM pg) SELECT CAST(sum(miss) AS BIGINT) AS page_reads FROM m")
def io_pages(spark, sf_dir, log=_log):
    log = log(spark, sf_dir)
    pages = log.select("node_id", F.floor(F.col("node_id") / 10).cast("long").alias("page")).distinct()
    return measures.io_curve(measures.page_log(log, pages)).agg(F.sum("reads").alias("page_reads"))


def _overlap_sql(rule: str) -> str:
    return f"""WITH {DOCV}, {TURNV}, g AS (SELECT conv_id, turn, doc_id FROM tv, dv QUALIFY row_number() OVER (PARTITION BY conv_id, turn ORDER BY list_cosine_distance(tv.v, dv.v), doc_id) <= 10),
t AS (SELECT conv_id, turn, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS nth FROM (SELECT DISTINCT conv_id, turn FROM g)), h AS (SELECT conv_id, nth, doc_id FROM g JOIN t USING (conv_id, turn)),
s AS (SELECT a.conv_id, a.nth, count(*) AS k, count(*) FILTER (EXISTS (SELECT 1 FROM h b WHERE b.conv_id = a.conv_id AND b.doc_id = a.doc_id AND {rule})) AS again FROM h a WHERE nth > 1 GROUP BY a.conv_id, a.nth)
SELECT nth, count(*) AS n_turns, round(avg(again / k), 4) AS p_repeat FROM s GROUP BY nth"""


for _name, _rule in (("first", "b.nth = 1"), ("previous", "b.nth = a.nth - 1"), ("any", "b.nth < a.nth")):

    def _run(spark, sf_dir, against=_name):
        got = temporal.retrieved(V.turn_vectors(spark, sf_dir), V.document_vectors(spark, sf_dir), 10)
        return temporal.turn_overlap(got, against).select(F.col("nth").cast("long").alias("nth"), "n_turns", F.round("p_repeat", 4).alias("p_repeat"))

    query(_overlap_sql(_rule), f"dialog_overlap_{_name}")(_run)


# --- growth ------------------------------------------------------------------------------------


@lru_cache(maxsize=2)
def _grown(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    first = tree.build(v.where("vec_id % 20 < 3"), PARAMS)
    return first, ingest.insert(first, v.where("vec_id % 20 >= 3"))


query(zeros(*CHECKS), "insert_invariants")(lambda s, d: tree.invariants(_grown(s, d)[1]))
query(knn_sql(10), "insert_search_full")(lambda s, d: long_rank(search.search(_grown(s, d)[1], V.queries_of(V.vectors(s, d)), SearchParams(beam=ALL))))


@query(knn_sql(10, where="query_id <> vec_id AND vec_id % 7 <> 0"))
def delete_search(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    t = ingest.delete(_tree(spark, sf_dir), v.where("vec_id % 7 = 0"))
    return long_rank(search.search(t, V.queries_of(v), SearchParams(beam=ALL)))


@query(knn_sql(10, where="query_id <> vec_id AND vec_id % 7 <> 0"))
def compact_search(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    t = ingest.compact(ingest.delete(_tree(spark, sf_dir), v.where("vec_id % 7 = 0")))
    return long_rank(search.search(t, V.queries_of(v), SearchParams(beam=ALL)))


@query(knn_sql(10))
def insert_clusters_search(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    t = tree.build(v.where("label < 5"), PARAMS)
    t = ingest.insert_clusters(t, v.where("label >= 5").select(F.col("label").alias("cluster"), "vec_id", "v"))
    return long_rank(search.search(t, V.queries_of(v), SearchParams(beam=ALL)))


@query("SELECT CAST(label AS BIGINT) AS old_leaf, CAST(vec_id % 4 AS BIGINT) AS new_leaf, count(*) AS n FROM embeddings WHERE vec_id % 20 < 3 GROUP BY ALL UNION ALL SELECT NULL, vec_id % 4, count(*) FROM embeddings WHERE vec_id % 20 >= 3 GROUP BY ALL")
def lineage_crosstab(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    before = v.where("vec_id % 20 < 3").select("vec_id", F.col("label").cast("long").alias("leaf"))
    return ingest.lineage(before, v.select("vec_id", (F.col("vec_id") % 4).alias("leaf")))


# --- measures ------------------------------------------------------------------------------------

_HALF = knn_sql(10, where="query_id <> vec_id AND vec_id % 2 = 0")


@query(f"WITH f AS ({_HALF}), t AS ({knn_sql(10)}) SELECT t.query_id, round(count(f.vec_id) / count(*), 6) AS recall FROM t LEFT JOIN f USING (query_id, vec_id) GROUP BY t.query_id")
def recall_at_10(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    q = V.queries_of(v)
    return r6(measures.recall_per_query(exact.knn(v.where("vec_id % 2 = 0"), q, 10), exact.knn(v, q, 10), 10), "recall")


@query(f"WITH f AS ({knn_sql(100, where='query_id <> vec_id AND vec_id % 2 = 0')}), t AS ({knn_sql(10)}) SELECT round(avg(r), 6) AS recall FROM (SELECT t.query_id, count(f.vec_id) / count(*) AS r FROM t LEFT JOIN f USING (query_id, vec_id) GROUP BY t.query_id)")
def recall_10_at_100(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    q = V.queries_of(v)
    return r6(measures.recall(exact.knn(v.where("vec_id % 2 = 0"), q, 100), exact.knn(v, q, 10), 10, 100), "recall")


@query(f"WITH f AS ({knn_sql(100, where='query_id <> vec_id AND vec_id % 4 > 0')}), t AS ({knn_sql(100)}) SELECT round(avg(r), 6) AS recall FROM (SELECT t.query_id, count(f.vec_id) / count(*) AS r FROM t LEFT JOIN f USING (query_id, vec_id) GROUP BY t.query_id)")
def recall_100(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    q = V.queries_of(v)
    return r6(measures.recall(exact.knn(v.where("vec_id % 4 > 0"), q, 100), exact.knn(v, q, 100), 100), "recall")


@query("""WITH c AS (SELECT l_returnflag AS method, round(l_discount, 2) AS recall, avg(l_quantity) AS qps FROM lineitem GROUP BY 1, 2),
s AS (SELECT method, recall, qps, lead(recall) OVER w AS r2, lead(qps) OVER w AS q2 FROM c WINDOW w AS (PARTITION BY method ORDER BY recall, qps)),
y AS (SELECT method, max(qps + (0.055::DOUBLE - recall) * (q2 - qps) / (r2 - recall)) AS y FROM s WHERE recall <= 0.055::DOUBLE AND r2 >= 0.055::DOUBLE AND r2 > recall GROUP BY method)
SELECT 0.055::DOUBLE AS recall, round(max(y) FILTER (method = 'A') / max(y) FILTER (method = 'R'), 9) AS speedup FROM y""")
def speedup_fixture(spark, sf_dir):
    """Curves from lines: the return flag as method, the discount as recall, the mean quantity as throughput."""
    curve = V.table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("method"), F.round("l_discount", 2).alias("recall")).agg(F.avg("l_quantity").alias("qps"))
    return measures.speedup(curve, 0.055, "A", "R").withColumn("speedup", F.round("speedup", 9))


@query("SELECT round((sum(l_extendedprice) FILTER (l_returnflag = 'A') - sum(l_extendedprice) FILTER (l_returnflag = 'R')) / sum(l_extendedprice) FILTER (l_returnflag = 'R'), 6) AS gain FROM lineitem")
def rel_gain(spark, sf_dir):
    s = V.table(spark, sf_dir, "lineitem").agg(F.sum(F.when(F.col("l_returnflag") == "A", F.col("l_extendedprice"))).alias("a"), F.sum(F.when(F.col("l_returnflag") == "R", F.col("l_extendedprice"))).alias("r"))
    return r6(s.select(measures.rel_gain(F.col("a"), F.col("r")).alias("gain")), "gain")


@query(f"WITH n AS ({knn_sql(1, base=HUBS)}) SELECT round(avg(CASE WHEN a.label = b.label THEN 1.0 ELSE 0.0 END), 6) AS agreement FROM n JOIN embeddings a ON a.vec_id = n.query_id JOIN embeddings b ON b.vec_id = n.vec_id")
def label_agreement(spark, sf_dir):
    v = V.hubs(spark, sf_dir)
    return r6(measures.label_agreement(exact.knn(v, V.queries_of(v), 1), v), "agreement")


@query(f"WITH f AS ({knn_sql(10, order='d DESC, vec_id')}) SELECT vec_id, count(*) AS votes FROM f GROUP BY vec_id ORDER BY votes DESC, vec_id LIMIT 20")
def outliers_kfn_votes(spark, sf_dir):
    v = V.vectors(spark, sf_dir)
    return dissim.outliers_by_votes(v, V.queries_of(v), 10, 20)


_MEAN = f"WITH {HUBS}, e AS (SELECT unnest(v) AS x, generate_subscripts(v, 1) AS p FROM v), m AS (SELECT list(x ORDER BY p) AS m FROM (SELECT p, avg(x) AS x FROM e GROUP BY p))"


@query(_MEAN + " SELECT vec_id, round(list_cosine_similarity(v, m), 6) AS commonality FROM v, m")
def commonality(spark, sf_dir):
    return r6(dissim.commonality(V.hubs(spark, sf_dir)), "commonality")


@query(_MEAN + " SELECT vec_id, round(list_distance(v, m), 6) AS dist FROM v, m ORDER BY list_distance(v, m) DESC, vec_id LIMIT 20")
def outliers_mean(spark, sf_dir):
    return r6(dissim.outliers_by_mean(V.hubs(spark, sf_dir), 20), "dist")


@query("WITH c AS (SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey) SELECT l_suppkey, n, CASE WHEN n > 1 THEN CAST(ceil(sqrt(n / ln(n))) AS BIGINT) ELSE 1 END AS leaf_capacity, CASE WHEN n > 1 THEN CAST(ceil(sqrt(n * (ln(n) / ln(10)))) AS BIGINT) ELSE 1 END AS link_leaves FROM c")
def recommended(spark, sf_dir):
    """The sizes of an index for each supplier's lines."""
    sizes = V.table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n"))
    return sizes.select("l_suppkey", "n", F.udf(graph.recommended_leaf_capacity, "long")("n").alias("leaf_capacity"), F.udf(graph.recommended_link_leaves, "long")("n").alias("link_leaves"))


@query("WITH n AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM lineitem) SELECT 'clustering' AS step, round(8 * n * 5 * ln(n) / ln(8), 3) AS distances FROM n UNION ALL SELECT 'near_leaves', ceil(n / 64) * ceil(n / 64) FROM n UNION ALL SELECT 'links', 64 * 4 * n FROM n UNION ALL SELECT 'brute_force', 50 * n FROM n UNION ALL SELECT 'search', 50 * (4 * ceil(ln(ceil(n / 64)) / ln(8)) * 8 + 4 * 64) FROM n")
def predicted_cost(spark, sf_dir):
    n = V.table(spark, sf_dir, "lineitem").count()
    return measures.predicted_cost(spark, n, 8, 5, 64, 4, 4, 8, 50).withColumn("distances", F.round("distances", 3))


# --- storage, sources, sinks, functions and streams around the index -------------------------------


@query(knn_sql(10))
def storage_round_trip(spark, sf_dir):
    path = fresh_path(spark, "index")
    tree.save(_tree(spark, sf_dir), path)
    return long_rank(search.search(tree.open_tree(spark, path), V.queries_of(V.vectors(spark, sf_dir)), SearchParams(beam=ALL)))


@query(knn_sql(10))
def storage_half_pinned(spark, sf_dir):
    t = tree.pin(_tree(spark, sf_dir), 0.5)
    return long_rank(search.search(t, V.queries_of(V.vectors(spark, sf_dir)), SearchParams(beam=ALL)))


@query(f"WITH {BASE} SELECT vec_id, round(list_sum(v), 6) AS s FROM v")
def source_leaves(spark, sf_dir):
    """The tree's leaves through the 'blocktree' data source."""
    from vecblock.sources import formats

    path = fresh_path(spark, "index")
    base = tree.save(_tree(spark, sf_dir), path)
    spark.dataSource.register(formats.leaf_source())
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    df = spark.read.format("blocktree").option("path", base).load()
    return r6(df.select("vec_id", F.aggregate("v", F.lit(0.0), lambda s, x: s + x).alias("s")), "s")


def _imported(spark, sf_dir, kind: str):
    from vecblock.sources import formats

    path = fresh_path(spark, kind)
    v = V.vectors(spark, sf_dir).select("vec_id", "v")
    if kind == "csv":
        v.select("vec_id", F.concat(F.lit("["), F.array_join(F.transform("v", lambda x: x.cast("string")), ","), F.lit("]")).alias("t")).write.option("header", True).csv(path)
        got = formats.parse_text(spark.read.option("header", True).schema("vec_id long, t string").csv(path), "t")
    else:
        getattr(v.write, kind)(path)
        got = getattr(spark.read.schema("vec_id long, v array<double>"), kind)(path)
    return r6(got.select("vec_id", F.aggregate("v", F.lit(0.0), lambda s, x: s + x).alias("s")), "s")


for _kind in ("csv", "json", "orc"):
    query(f"WITH {BASE} SELECT vec_id, round(list_sum(v), 6) AS s FROM v", f"source_{_kind}")(lambda s, d, kind=_kind: _imported(s, d, kind))


@query(knn_sql(5))
def table_function_search(spark, sf_dir):
    """A lateral search in a saved index at full beam."""
    from vecblock.functions import sql as S

    path = fresh_path(spark, "index")
    tree.save(_tree(spark, sf_dir), path)
    spark.udtf.register("vec_search", S.search_table(spark, path))
    V.queries_of(V.vectors(spark, sf_dir)).createOrReplaceTempView("vecblock_q")
    return long_rank(spark.sql(f"SELECT s.* FROM vecblock_q q, LATERAL vec_search(q.query_id, q.v, 5, {ALL}) s"))


@query(f"WITH {BASE} SELECT row_number() OVER (ORDER BY list_distance((SELECT qv FROM q WHERE query_id = 0), v), vec_id) AS rank, vec_id, round(list_distance((SELECT qv FROM q WHERE query_id = 0), v), 6) AS dist FROM v QUALIFY rank <= 10")
def planner_rewrite_topk(spark, sf_dir):
    from vecblock.plans import planner

    v = V.vectors(spark, sf_dir)
    literal = v.where("vec_id = 0").first().v
    got = planner.rewrite_topk(v, list(literal), 10, _tree(spark, sf_dir), beam=ALL)
    return r6(got.withColumn("rank", F.col("rank").cast("long")), "dist")


@query(knn_sql(10))
def stream_insert_equal(spark, sf_dir):
    """Half the vectors in an index, the rest inserted by a stream of two files."""
    from vecblock.streaming import streams

    v = V.vectors(spark, sf_dir).select("vec_id", "v")
    index, source = fresh_path(spark, "index"), fresh_path(spark, "in")
    tree.save(tree.build(v.where("vec_id % 4 < 2"), PARAMS), index)
    for k in (2, 3):
        v.where(F.col("vec_id") % 4 == k).coalesce(1).write.mode("append").parquet(source)
    streams.insert_stream(streams.file_stream(spark, source, v.schema), index, fresh_path(spark, "ck")).awaitTermination()
    return long_rank(search.search(tree.open_tree(spark, index), V.queries_of(v), SearchParams(beam=ALL)))


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def stream_tumbling_complete(spark, sf_dir):
    """The same windows as a stream in complete mode."""
    from vecblock.streaming import streams

    ev = V.table(spark, sf_dir, "events")
    source = fresh_path(spark, "in")
    streams.timed_events(ev).select("event_id", "ts", "event_type", "value").coalesce(1).write.parquet(source)
    stream = streams.file_stream(spark, source, spark.read.parquet(source).schema)
    name = "vecblock_windows"
    out = streams.run_once(streams.tumbling(stream), name, fresh_path(spark, "ck"), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query()
def greedy_per_branch(spark, sf_dir):
    """Walks from every opened leaf apart, merged, beside the plain tree answer."""
    v, t = V.hubs(spark, sf_dir), _tree(spark, sf_dir, "hubs")
    q = V.queries_of(v)
    links = graph.build_links(t, 8, 4)
    found = search.search(t, q, SearchParams(beam=2))
    seeds = found.join(t.rows.select("vec_id", F.col("leaf_id").alias("branch")), "vec_id").select("query_id", "branch", "vec_id")
    return long_rank(graph.greedy_per_branch(seeds, links, v, q, 10))


@query()
def mllib_partitions(spark, sf_dir):
    """MLlib's own K-Means and bisecting K-Means as controls: cluster sizes."""
    from pyspark.ml.clustering import BisectingKMeans, KMeans
    from pyspark.ml.functions import array_to_vector

    f = V.hubs(spark, sf_dir).select(array_to_vector("v").alias("features"))
    out = None
    for name, model in (("kmeans", KMeans(k=10, seed=42)), ("bisecting", BisectingKMeans(k=10, seed=42))):
        part = model.fit(f).transform(f).groupBy("prediction").agg(F.count("*").alias("n")).select(F.lit(name).alias("method"), "prediction", "n")
        out = part if out is None else out.union(part)
    return out


@query(f"WITH {BASE}, a AS (SELECT label, count(*) AS n FROM v GROUP BY label) SELECT CAST(label AS BIGINT) AS label, n FROM a")
def sink_bucketed_table(spark, sf_dir):
    """A table bucketed by label: grouping it again needs no shuffle."""
    name = "vecblock_bucketed"
    spark.sql(f"DROP TABLE IF EXISTS {name}")
    V.vectors(spark, sf_dir).withColumn("label", F.col("label").cast("long")).write.bucketBy(4, "label").sortBy("vec_id").mode("overwrite").option("path", fresh_path(spark, "bucketed")).saveAsTable(name)
    return spark.table(name).groupBy("label").agg(F.count("*").alias("n"))
