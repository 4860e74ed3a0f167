"""Exact nearest, farthest and range answers.

A query set of at most QUERY_BLOCK bytes is broadcast: vectors stay, and every task keeps its own
top k per query, so a shuffle carries |Q| k rows per task and no vector.  Larger sets
meet the vectors on a grid of blocks, each pair of blocks one task; no query
passes the driver.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.functions import arrays as A
from vecblock.functions import metrics as M

#: Bytes of query vectors in one broadcast.
QUERY_BLOCK = 32 << 20
FOUND = "query_id long, vec_id long, dist double"
_FOUND = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("dist", pa.float64())])


def query_block(q: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
    """(ids, matrix) of (query_id, v), or None where they exceed QUERY_BLOCK bytes."""
    q = q.select("query_id", M.doubles("v").alias("v")).where("v IS NOT NULL")
    size = q.agg((F.count("*") * (8 * F.max(F.size("v")) + 8)).alias("b")).first().b or 0
    if size > QUERY_BLOCK:
        return None
    got = q.orderBy("query_id").toArrow()  # checked against QUERY_BLOCK
    return got.column("query_id").to_numpy(), A.matrix(got.column("v"))


def query_blocks(q: DataFrame):
    """(ids, matrix) blocks of at most QUERY_BLOCK bytes, streamed: for the comparison methods, whose query sets are small."""
    ids, rows, size = [], [], 0
    for r in q.select("query_id", M.doubles("v").alias("v")).where("v IS NOT NULL").orderBy("query_id").toLocalIterator():
        ids.append(r.query_id)
        rows.append(r.v)
        size += 8 * len(r.v)
        if size >= QUERY_BLOCK:
            yield np.array(ids, np.int64), np.array(rows)
            ids, rows, size = [], [], 0
    if ids:
        yield np.array(ids, np.int64), np.array(rows)


def _on_grid(rows: DataFrame, q: DataFrame, meet) -> DataFrame:
    """FOUND from meet(ids, queries, vec_ids, vectors) for every pair of a block of queries and a block of rows."""
    q = q.select("query_id", M.doubles("v").alias("v")).where("v IS NOT NULL")
    sides = []
    for df, key in ((q, "query_id"), (rows, "vec_id")):
        size = df.agg((F.count("*") * (8 * F.max(F.size("v")) + 8)).alias("b")).first().b or 0
        n = max(1, -(-int(size) // QUERY_BLOCK))
        sides.append((df.withColumn("own", F.pmod(F.xxhash64(key), F.lit(n)).cast("int")), n))
    (left, nq), (right, nr) = sides
    left = left.withColumn("i", F.col("own")).withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(nr - 1)))).drop("own")
    right = right.withColumn("j", F.col("own")).withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(nq - 1)))).drop("own")

    def run(key, a: pa.Table, b: pa.Table) -> pa.Table:
        if not len(a) or not len(b):
            return _FOUND.empty_table()
        who, found, dist = meet(a.column("query_id").to_numpy(), A.matrix(a.column("v")), b.column("vec_id").to_numpy(), A.matrix(b.column("v")))
        return pa.table([pa.array(who, pa.int64()), pa.array(found, pa.int64()), pa.array(dist, pa.float64())], schema=_FOUND)

    return left.groupBy("i", "j").cogroup(right.groupBy("i", "j")).applyInArrow(run, FOUND)


def _best(k: int, metric: str, farthest: bool, exclude_self: bool):
    """The best k rows of a block for each query."""

    def meet(qid, q, ids, x):
        best = A.Best(qid, q, k, metric, farthest, exclude_self)
        best.add(ids, x)
        return best.rows()

    return meet


def ranked(found: DataFrame, k: int, farthest: bool = False, by: str = "query_id") -> DataFrame:
    """The k best (dist, id) of each query with their ranks."""
    order = [F.desc("dist") if farthest else F.asc("dist"), F.asc("vec_id")]
    w = Window.partitionBy(by).orderBy(*order)
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select(by, "rank", "vec_id", "dist")


def _scan(block, meet, k: int, farthest: bool):
    def run(batches):
        qid, q = block.value
        best: pa.Table | None = None
        for batch in batches:
            who, found, dist = meet(qid, q, batch.column("vec_id").to_numpy(zero_copy_only=False), A.matrix(batch.column("v")))
            now = pa.table({"query_id": pa.array(who, pa.int64()), "vec_id": pa.array(found, pa.int64()), "dist": pa.array(dist, pa.float64())})
            best = _cut(now if best is None else pa.concat_tables([best, now]), k, farthest)
        if best is not None:
            yield from best.cast(_FOUND).to_batches()

    return run


def _scan_best(block, k: int, metric: str, farthest: bool, exclude_self: bool):
    """A task keeps its best k of each query from batch to batch."""

    def run(batches):
        best = A.Best(*block.value, k, metric, farthest, exclude_self)
        for batch in batches:
            best.add(batch.column("vec_id").to_numpy(zero_copy_only=False), A.matrix(batch.column("v")))
        yield from pa.table(list(best.rows()), schema=_FOUND).to_batches()

    return run


def _cut(t: pa.Table, k: int, farthest: bool) -> pa.Table:
    q, v, d = (t.column(c).to_numpy() for c in ("query_id", "vec_id", "dist"))
    order = np.lexsort((v, -d if farthest else d, q))
    q = q[order]
    first = np.flatnonzero(np.append(True, q[1:] != q[:-1])) if len(q) else np.zeros(0, np.int64)
    at = np.arange(len(q)) - np.repeat(first, np.diff(np.append(first, len(q))))
    return t.take(pa.array(order[at < k]))


def knn(df: DataFrame, q: DataFrame, k: int, metric: str = "l2", exclude_self: bool = True, farthest: bool = False) -> DataFrame:
    """(query_id, rank, vec_id, dist): exact k nearest of (vec_id, v) for each of (query_id, v)."""
    spark = df.sparkSession
    rows = df.select("vec_id", M.doubles("v").alias("v")).where("v IS NOT NULL")
    if k <= 0:
        return ranked(spark.createDataFrame([], FOUND), k, farthest)
    block = query_block(q)
    if block is None:
        return ranked(_on_grid(rows, q, _best(k, metric, farthest, exclude_self)), k, farthest)
    held = spark.sparkContext.broadcast(block)  # at most QUERY_BLOCK bytes
    return ranked(rows.mapInArrow(_scan_best(held, k, metric, farthest, exclude_self), FOUND), k, farthest)


def kfn(df: DataFrame, q: DataFrame, k: int, metric: str = "l2", exclude_self: bool = True) -> DataFrame:
    return knn(df, q, k, metric, exclude_self, farthest=True)


def knn_graph(df: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    return knn(df, df.select(F.col("vec_id").alias("query_id"), "v"), k, metric)


def knn_sets(df: DataFrame, q: DataFrame, k: int, metric: str = "l2", exclude_self: bool = True) -> DataFrame:
    """(query_id, ids, total): the set-valued form, ids ascending."""
    found = knn(df, q, k, metric, exclude_self)
    return found.groupBy("query_id").agg(F.array_sort(F.collect_set("vec_id")).alias("ids"), F.sum("dist").alias("total"))


def _near(radius: float, metric: str):
    def meet(qid, q, ids, x):
        if not len(x) or not len(q):
            z = np.zeros(0, np.int64)
            return z, z, np.zeros(0)
        i, j = np.nonzero(A.rough(q, x, metric) <= radius + 1e-6 * (1 + radius))
        d = A.distance(q[i], x[j], metric)
        ok = d <= radius
        return qid[i[ok]], ids[j[ok]], d[ok]

    return meet


def within(df: DataFrame, q: DataFrame, radius: float, metric: str = "l2", exclude_self: bool = True) -> DataFrame:
    """(query_id, vec_id, dist) of all vectors in a radius."""
    rows = df.select("vec_id", M.doubles("v").alias("v")).where("v IS NOT NULL")
    meet, block = _near(radius, metric), query_block(q)
    if block is None:
        out = _on_grid(rows, q, meet)
    else:
        held = df.sparkSession.sparkContext.broadcast(block)  # at most QUERY_BLOCK bytes

        def run(batches):
            for b in batches:
                who, found, dist = meet(*held.value, b.column("vec_id").to_numpy(zero_copy_only=False), A.matrix(b.column("v")))
                yield pa.RecordBatch.from_arrays([pa.array(who, pa.int64()), pa.array(found, pa.int64()), pa.array(dist, pa.float64())], schema=_FOUND)

        out = rows.mapInArrow(run, FOUND)
    return out.where("query_id <> vec_id") if exclude_self else out


#: Rows and queries of a pack; a batch of pairs() has their product.
PACK_ROWS, PACK_QUERIES = 512, 64
_PACK = "ids array<long>, flat array<double>"


def packs(df: DataFrame, key: str, vec: str, size: int, prefix: str) -> DataFrame:
    """(prefix_ids, prefix_flat): up to ``size`` vectors, all of one length, in a row, coordinates one after the other."""

    def run(batches):
        for b in batches:
            for a in range(0, len(b), size):
                some = b.slice(a, size)
                yield pa.RecordBatch.from_arrays([pa.array([some.column(key).to_numpy()], pa.list_(pa.int64())), A.lists(A.matrix(some.column(vec)).reshape(1, -1))], names=["ids", "flat"])

    return df.select(key, vec).mapInArrow(run, _PACK).toDF(f"{prefix}_ids", f"{prefix}_flat")


def regular(v, length: int):
    """A vector of that many numbers, none of them null."""
    return F.coalesce((F.size(v) == length) & (F.size(v) > 0) & ~F.exists(v, lambda x: x.isNull()), F.lit(False))


def split_regular(rows: DataFrame, q: DataFrame):
    """((rows, queries) of one length without nulls, the same of all others or None): (vec_id, v) and (query_id, qv)."""
    seen = rows.select(F.col("v").alias("x")).union(q.select(F.col("qv").alias("x")))
    length = seen.where("size(x) >= 0").agg(F.mode(F.size("x"), True).alias("n")).first().n or 0
    if seen.where(~regular(F.col("x"), length)).isEmpty():
        return (rows, q), None
    fine, other = regular(F.col("v"), length), regular(F.col("qv"), length)
    return (rows.where(fine), q.where(other)), (rows.where(~fine), rows.where(fine), q, q.where(~other))


def pairs(rows: DataFrame, q: DataFrame, kernel, plain, columns: dict[str, str]) -> DataFrame:
    """(query_id, vec_id, *columns) of every query (query_id, qv) with every row (vec_id, v).

    ``kernel`` scores a pack of queries against a pack of rows: one matrix for each of ``columns`` (name to type),
    masked where null.  Vectors with nulls or of another length are rare and go through the column expressions
    ``plain`` of (qv, v).  Nothing passes the driver.
    """
    deal = 4 * rows.sparkSession.sparkContext.defaultParallelism
    kinds = [{"double": pa.float64(), "long": pa.int64()}[k] for k in columns.values()]
    (fine, asked), odd = split_regular(rows, q)
    # both sides are shuffled, for a product reads its right side again for each part of the left
    met = packs(fine, "vec_id", "v", PACK_ROWS, "v").repartition(deal).crossJoin(packs(asked, "query_id", "qv", PACK_QUERIES, "q").repartition(2))

    def column(d, kind) -> pa.Array:
        return pa.array(np.ma.getdata(d).ravel(), kind, mask=np.ma.getmaskarray(d).ravel() if np.ma.isMaskedArray(d) else None)

    def run(batches):
        for b in batches:
            for i in range(len(b)):
                qid, vid, qf, vf = (b.column(c)[i].values.to_numpy() for c in ("q_ids", "v_ids", "q_flat", "v_flat"))
                found = kernel(qf.reshape(len(qid), -1), vf.reshape(len(vid), -1))
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(qid, len(vid))), pa.array(np.tile(vid, len(qid))), *map(column, found, kinds)], names=["query_id", "vec_id", *columns])

    out = met.mapInArrow(run, ", ".join(["query_id long, vec_id long", *[f"{c} {k}" for c, k in columns.items()]]))
    if odd is None:
        return out
    bad, good, every, strange = odd
    rest = bad.crossJoin(every).unionByName(good.crossJoin(strange))
    return out.union(rest.select("query_id", "vec_id", *[x.cast(k).alias(c) for x, (c, k) in zip(plain(F.col("qv"), F.col("v")), columns.items())]))
