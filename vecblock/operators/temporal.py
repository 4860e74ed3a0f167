"""Sequences of queries: their order, and what dialogues retrieve again."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.functions import arrays as A
from vecblock.functions import metrics as M
from vecblock.operators import exact
from vecblock.sources.stored import stored

#: Queries up to which each step of a chain looks at all of them.
DIRECT = 2_000
#: Cells that a step opens at once.
OPEN = 8


class _Cells:
    """Unused rows in cells around sampled rows; a cell whose bound exceeds the best distance stays closed."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, metric: str):
        self.ids, self.x, self.metric = ids, x, metric
        k = int(np.sqrt(len(ids)))
        self.center = x[np.random.default_rng(0).choice(len(ids), k, replace=False)]
        near, far = np.zeros(len(ids), np.int64), np.full(len(ids), np.inf)
        for c in range(k):
            d = A.distance(self.center[c], x, metric)
            near[d < far] = c
            far = np.minimum(far, d)
        self.cell = near
        self.radius = np.zeros(k)
        np.maximum.at(self.radius, near, far)
        order = np.argsort(near, kind="stable")
        self.rows = np.split(order, np.cumsum(np.bincount(near, minlength=k))[:-1])
        self.open_ = np.array([len(r) > 0 for r in self.rows])

    def drop(self, at: int) -> None:
        c = self.cell[at]
        self.rows[c] = self.rows[c][self.rows[c] != at]
        self.open_[c] = len(self.rows[c]) > 0

    def nearest(self, at: int) -> int:
        """The nearest unused row, the lowest id among equals: exact by the triangle inequality."""
        d = A.distance(self.x[at], self.center, self.metric)
        bound = d - self.radius - 1e-9 * (d + self.radius)  # rounding
        todo = np.flatnonzero(self.open_)
        todo = todo[np.argsort(bound[todo])]
        best, row = np.inf, -1
        for k in range(0, len(todo), OPEN):
            if bound[todo[k]] > best:
                break
            rows = np.concatenate([self.rows[c] for c in todo[k : k + OPEN].tolist()])
            got = A.distance(self.x[at], self.x[rows], self.metric)
            one = np.lexsort((self.ids[rows], got))[0]
            if row < 0 or (got[one], self.ids[rows[one]]) < (best, self.ids[row]):
                best, row = got[one], int(rows[one])
        return row


def chain(ids: np.ndarray, x: np.ndarray, metric: str = "l2") -> np.ndarray:
    """Row numbers from the first row on, always the nearest unused one (the lowest id among equals)."""
    cells = _Cells(ids, x, metric) if metric == "l2" and len(ids) > DIRECT else None
    left = np.ones(len(ids), bool)
    seq = np.zeros(len(ids), np.int64)
    for k in range(1, len(ids)):
        at = int(seq[k - 1])
        if cells:
            cells.drop(at)
            seq[k] = cells.nearest(at)
            continue
        left[at] = False
        rest = np.flatnonzero(left)
        seq[k] = rest[np.lexsort((ids[rest], A.distance(x[at], x[rest], metric)))[0]]
    return seq


def order_correlated(q: DataFrame, metric: str = "l2") -> DataFrame:
    """(query_id, seq): start at the lowest id, then always the nearest unused query, at every size.

    A chain is sequential: one task holds all queries (8 bytes a coordinate).
    """

    def run(t: pa.Table) -> pa.Table:
        ids = t.column("query_id").to_numpy()
        order = np.argsort(ids, kind="stable")
        ids, x = ids[order], A.matrix(t.column("v"))[order]
        return pa.table([pa.array(ids[chain(ids, x, metric)], pa.int64()), pa.array(np.arange(len(ids)), pa.int64())], names=["query_id", "seq"])

    part = q.select("query_id", M.doubles("v").alias("v"), F.lit(0).cast("long").alias("cell"))
    return part.groupBy("cell").applyInArrow(run, "query_id long, seq long")


def order_random(q: DataFrame, seed: int = 42) -> DataFrame:
    """(query_id, seq) by md5 of the id."""
    key = F.md5(F.concat_ws("|", F.col("query_id").cast("string"), F.lit(str(seed))))
    return q.select("query_id", (F.row_number().over(Window.orderBy(key, "query_id")) - 1).cast("long").alias("seq"))


def retrieved(turns: DataFrame, docs: DataFrame, k: int, metric: str = "cosine") -> DataFrame:
    """(conv_id, turn, vec_id): the k nearest documents of each turn vector (conv_id, turn, v)."""
    q = stored(turns.withColumn("query_id", F.monotonically_increasing_id()), "turns")
    got = exact.knn(docs, q.select("query_id", "v"), k, metric, exclude_self=False)
    return got.join(q.select("query_id", "conv_id", "turn"), "query_id").select("conv_id", "turn", "vec_id")


def turn_overlap(got: DataFrame, against: str = "first") -> DataFrame:
    """(nth, n_turns, p_repeat): share of a turn's documents that the first, the previous or any earlier turn had retrieved.

    Turns are numbered within their dialogue; the first has nothing to repeat.
    """
    turns = got.select("conv_id", "turn").distinct().withColumn("nth", F.row_number().over(Window.partitionBy("conv_id").orderBy("turn")))
    hit = got.join(turns, ["conv_id", "turn"])
    old = hit.select("conv_id", "vec_id", F.col("nth").alias("before"))
    rule = {"first": F.col("before") == 1, "previous": F.col("before") == F.col("nth") - 1, "any": F.col("before") < F.col("nth")}[against]
    again = hit.where("nth > 1").join(old, ["conv_id", "vec_id"]).where(rule).select("conv_id", "nth", "vec_id").distinct().groupBy("conv_id", "nth").agg(F.count("*").alias("again"))
    size = hit.where("nth > 1").groupBy("conv_id", "nth").agg(F.count("*").alias("k"))
    share = size.join(again, ["conv_id", "nth"], "left").withColumn("share", F.coalesce("again", F.lit(0)) / F.col("k"))
    return share.groupBy("nth").agg(F.count("*").alias("n_turns"), F.avg("share").alias("p_repeat"))
