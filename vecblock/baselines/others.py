"""Further comparison methods: quantised search, hashing, edge sets of relative-neighbour graphs."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecblock.functions import arrays as A
from vecblock.functions import metrics as M
from vecblock.operators import exact


def fit_codebooks(df: DataFrame, m: int = 8, centers: int = 32, sample: int = 20_000, iters: int = 8, seed: int = 42) -> np.ndarray:
    """(m, centers, n / m): k-means per subspace on the ``sample`` rows with the smallest id hashes."""
    rows = df.select("vec_id", M.doubles("v").alias("v")).orderBy(F.xxhash64("vec_id")).limit(sample).toArrow()
    x, ids = A.matrix(rows.column("v")), rows.column("vec_id").to_numpy()
    books = []
    for part in np.split(x, m, axis=1):
        _, c = A.kmeans(part, ids, centers, iters, "d2", seed)
        books.append(np.vstack([c, np.repeat(c[-1:], centers - len(c), 0)]))
    return np.stack(books)


def encode(df: DataFrame, books: np.ndarray) -> DataFrame:
    """(vec_id, code): one byte per subspace."""
    held = df.sparkSession.sparkContext.broadcast(books)

    def run(batches):
        for b in batches:
            x = A.matrix(b.column("v"))
            code = np.stack([A.nearest(p, c) for p, c in zip(np.split(x, len(held.value), axis=1), held.value)], 1).astype(np.uint8) if len(x) else np.zeros((0, 1), np.uint8)
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), pa.array([c.tobytes() for c in code], pa.binary())], names=["vec_id", "code"])

    return df.select("vec_id", M.doubles("v").alias("v")).mapInArrow(run, "vec_id long, code binary")


def quantised_search(df: DataFrame, q: DataFrame, k: int, m: int = 8, centers: int = 32, rescore: int = 50) -> DataFrame:
    """Score codes by table look-ups, take ``rescore`` candidates, score these exactly."""
    books = fit_codebooks(df, m, centers)
    codes = encode(df, books)
    spark = df.sparkSession
    out = None
    for block in exact.query_blocks(q):
        held = spark.sparkContext.broadcast((*block, books))

        def run(batches, held=held):
            qid, mat, bk = held.value
            tables = np.stack([((p[:, None, :] - c[None]) ** 2).sum(2) for p, c in zip(np.split(mat, len(bk), axis=1), bk)], 1)
            for b in batches:
                code = np.frombuffer(b"".join(b.column("code").to_pylist()), np.uint8).reshape(-1, len(bk))
                ids = b.column("vec_id").to_numpy()
                d = sum(tables[:, j, :][:, code[:, j]] for j in range(len(bk)))
                take = min(rescore + 1, len(ids))
                pick = np.argpartition(d, take - 1, axis=1)[:, :take] if take else np.zeros((len(qid), 0), int)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(qid, take)), pa.array(ids[pick].ravel(), pa.int64()), pa.array(np.sqrt(np.take_along_axis(d, pick, 1)).ravel())], names=["query_id", "vec_id", "dist"])

        part = codes.mapInArrow(run, exact.FOUND)
        out = part if out is None else out.union(part)
    short = exact.ranked(out.where("query_id <> vec_id"), rescore).select("query_id", "vec_id")
    again = short.join(df.select("vec_id", M.doubles("v").alias("x")), "vec_id").join(q.select("query_id", M.doubles("v").alias("v")), "query_id")
    return exact.ranked(again.select("query_id", "vec_id", M.l2(F.col("v"), F.col("x")).alias("dist")), k)


def lsh_search(df: DataFrame, q: DataFrame, k: int, bucket: float = 2.0, tables: int = 4, radius: float = 2.0, seed: int = 42) -> DataFrame:
    """Spark's own random-projection hashing as a control; pairs of one bucket are scored where the rows lie."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector, vector_to_array

    a = df.select("vec_id", array_to_vector(M.doubles("v")).alias("f"))
    b = q.select(F.col("query_id").alias("vec_id"), array_to_vector(M.doubles("v")).alias("f"))
    model = BucketedRandomProjectionLSH(inputCol="f", outputCol="h", bucketLength=bucket, numHashTables=tables, seed=seed).fit(a)
    # the vector and behind it its bucket in each table
    hashed = lambda t: model.transform(t).select("vec_id", F.concat(vector_to_array("f"), *[vector_to_array(F.col("h")[j]) for j in range(tables)]).alias("v"))
    meet = _sharing_a_bucket(k, tables, radius)
    rows, block = hashed(a), exact.query_block(asked := hashed(b).withColumnRenamed("vec_id", "query_id"))
    if block is None:
        return exact.ranked(exact._on_grid(rows, asked, meet), k)
    held = df.sparkSession.sparkContext.broadcast(block)  # at most exact.QUERY_BLOCK bytes
    return exact.ranked(rows.mapInArrow(exact._scan(held, meet, k, False), exact.FOUND), k)


def _sharing_a_bucket(k: int, tables: int, radius: float):
    """The best k rows of a block for each query among those in one of its buckets and within the radius; no pair leaves the block."""

    def meet(qid, q, ids, x):
        who, found, dist = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
        if len(q) and len(x):
            hq, hx, q, x = q[:, -tables:], np.ascontiguousarray(x[:, -tables:].T), q[:, :-tables], np.ascontiguousarray(x[:, :-tables])
            for i in range(len(q)):
                at = np.flatnonzero(np.logical_or.reduce([h == one for h, one in zip(hx, hq[i])]) & (ids != qid[i]))
                _, near, d = A.block_topk(q[i : i + 1], x if len(at) == len(x) else x[at], ids[at], k, "l2")
                near, d = near[d < radius], d[d < radius]
                who.append(np.full(len(near), qid[i]))
                found.append(near)
                dist.append(d)
        return np.concatenate(who), np.concatenate(found), np.concatenate(dist)

    return meet


#: Bytes of all distances between the rows of an exact edge set.
PAIR_BYTES = 512 << 20


def _edges(df: DataFrame, far: bool, candidates: int | None = None) -> DataFrame:
    """Edges that no third row blocks.  The rows visit each other in blocks of rows; they have to fit into a task.

    With ``candidates`` a row considers its nearest (farthest) so many rows as ends only; third rows are always all rows.
    """
    block = exact.query_block(df.select(F.col("vec_id").alias("query_id"), "v"))
    if block is None:
        raise ValueError("the rows exceed exact.QUERY_BLOCK")
    if 8 * len(block[0]) ** 2 > PAIR_BYTES:
        raise ValueError("all pairs exceed PAIR_BYTES: use the pruned graphs of baselines.graphs in shards")
    held = df.sparkSession.sparkContext.broadcast(block)
    sign = -1.0 if far else 1.0

    def run(batches):
        ids, x = held.value
        between = None
        for b in batches:
            if not len(b):
                continue
            if between is None:
                between = np.stack([sign * A.distance(one, x, "l2") for one in x])
            out: list[tuple] = []
            for a in np.searchsorted(ids, b.column("vec_id").to_numpy()).tolist():
                d = between[a]
                ends = np.arange(len(ids)) if candidates is None else np.lexsort((ids, np.where(ids == ids[a], np.inf, d)))[:candidates]
                ends = ends[ends != a]
                worst = np.maximum(d[None], between[ends])  # a third row is closer to both ends than they are to each other
                worst[:, a] = np.inf
                worst[np.arange(len(ends)), ends] = np.inf
                free = ends[~(worst < d[ends][:, None]).any(1)]
                out += [(int(ids[min(a, e)]), int(ids[max(a, e)]), float(sign * d[e])) for e in free.tolist()]
            cols = list(zip(*out)) or [[]] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.float64()))], names=["a", "b", "dist"])

    return df.select("vec_id").mapInArrow(run, "a long, b long, dist double").distinct()


def rng_edges(df: DataFrame, candidates: int | None = None) -> DataFrame:
    """(a, b, dist): no third row is closer to both ends."""
    return _edges(df, False, candidates)


def far_edges(df: DataFrame, candidates: int | None = None) -> DataFrame:
    """(a, b, dist): no third row is farther from both ends."""
    return _edges(df, True, candidates)


def mutual_far_edges(df: DataFrame, k: int) -> DataFrame:
    """(a, b): each among the other's k farthest."""
    far = exact.kfn(df, df.select(F.col("vec_id").alias("query_id"), "v"), k).select(F.col("query_id").alias("a"), F.col("vec_id").alias("b"))
    back = far.select(F.col("a").alias("b"), F.col("b").alias("a"))
    return far.where("a < b").join(back, ["a", "b"], "left_semi").select("a", "b")
