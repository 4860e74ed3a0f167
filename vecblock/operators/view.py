"""Views: a small in-memory index around a query that answers the questions after it."""

from __future__ import annotations

import json
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.functions import arrays as A
from vecblock.functions import metrics as M
from vecblock.operators import exact
from vecblock.operators.search import SearchParams, search
from vecblock.operators.tree import BlockTree

MAX_ROWS = 10_000


@dataclass
class View:
    """Rows of a view with their local leaves and links; pinned to one tree version."""

    ids: np.ndarray
    x: np.ndarray
    leaves: list[np.ndarray]
    centers: np.ndarray
    links: list[np.ndarray] | None
    anchor: np.ndarray
    radius: float
    metric: str
    version: int

    def answer(self, q: np.ndarray, k: int, beam: int | None = None, farthest: bool = False, skip: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(ids, distances) of the best k view rows for one query."""
        sign = -1.0 if farthest else 1.0
        if beam is None or beam >= len(self.leaves):
            at = np.arange(len(self.ids))
        else:
            d = sign * A.distance(q, self.centers, self.metric)
            at = np.concatenate([self.leaves[i] for i in np.argsort(d, kind="stable")[:beam]])
        d = A.distance(q, self.x[at], self.metric)
        if self.links is not None and beam is not None and beam < len(self.leaves):
            at, d, _, _ = A.refine(q, at[np.lexsort((self.ids[at], sign * d))[: k + 1]], self.links, self.x, k + 1, self.metric, farthest)
        if skip is not None:
            keep = self.ids[at] != skip
            at, d = at[keep], d[keep]
        order = np.lexsort((self.ids[at], sign * d))[:k]
        return self.ids[at[order]], d[order]


def local_view(ids: np.ndarray, x: np.ndarray, anchor: np.ndarray, metric: str = "l2", with_links: bool = True, degree: int = 8, leaf_rows: int = 32, version: int = 0) -> View:
    """Cluster and link a handful of rows with the same kernels as the large index."""
    order = np.argsort(ids, kind="stable")
    ids, x = ids[order], x[order]
    pieces, _ = A.split_all(x, ids, "r", leaf_rows, 4, 5, "d2", 42)
    leaves = [p[1] for p in pieces if len(p[1])]
    centers = np.array([x[p].mean(0) for p in leaves]) if leaves else np.zeros((0, len(anchor)))
    links = None
    if with_links and len(ids):
        row, found, _ = A.block_topk(x, x, np.arange(len(ids)), degree + 1, metric)
        links = [found[row == i] for i in range(len(ids))]
        links = [v[v != i] for i, v in enumerate(links)]
    radius = float(A.distance(anchor, x, metric).max()) if len(ids) else 0.0
    return View(ids, x, leaves, centers, links, anchor, radius, metric, version)


def create(tree: BlockTree, anchor: DataFrame, size: int, beam: int = 1 << 30, with_links: bool = True, build: str = "rebuild") -> View:
    """The view of the first query in ``anchor`` (query_id, v).

    'rebuild' clusters the rows anew, 'induced' keeps the leaves they have in the tree.
    """
    if size > MAX_ROWS:
        raise ValueError(f"a view holds at most {MAX_ROWS} rows")
    one = anchor.orderBy("query_id").limit(1)
    found = search(tree, one, SearchParams(k=size, beam=beam, exclude_self=False))
    rows = tree.live_rows().join(F.broadcast(found.select("vec_id")), "vec_id", "left_semi").select("vec_id", "leaf_id", "v").orderBy("vec_id").toArrow()  # at most ``size`` rows
    q = np.array(one.select(M.doubles("v").alias("v")).first().v)
    ids, x = rows.column("vec_id").to_numpy(), A.matrix(rows.column("v"))
    v = local_view(ids, x, q, tree.params.metric, with_links, version=tree.version)
    if build == "induced" and len(ids):
        leaf = rows.column("leaf_id").to_numpy()
        v.leaves = [np.flatnonzero(leaf == c) for c in np.unique(leaf)]
        v.centers = np.array([v.x[p].mean(0) for p in v.leaves])
    return v


def as_rows(spark, view: View) -> DataFrame:
    return spark.createDataFrame([(int(i), [float(z) for z in x]) for i, x in zip(view.ids, view.x)], "vec_id long, v array<double>")


def search_view(view: View, q: DataFrame, k: int, farthest: bool = False, beam: int | None = None, exclude_self: bool = True) -> DataFrame:
    """(query_id, rank, vec_id, dist) from the view alone, a narrow map over the queries."""
    held = q.sparkSession.sparkContext.broadcast(view)  # at most MAX_ROWS rows

    def run(batches):
        for b in batches:
            out: list[list] = [[], [], [], []]
            mat = A.matrix(b.column("v"))
            for i, qid in enumerate(b.column("query_id").to_pylist()):
                ids, d = held.value.answer(mat[i], k, beam, farthest, qid if exclude_self else None)
                for r, (v, e) in enumerate(zip(ids.tolist(), d.tolist()), 1):
                    for c, z in zip(out, (qid, r, v, e)):
                        c.append(z)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int32(), pa.int64(), pa.float64()))], names=["query_id", "rank", "vec_id", "dist"])

    return q.select("query_id", M.doubles("v").alias("v")).mapInArrow(run, "query_id long, rank int, vec_id long, dist double")


def replay(rows: DataFrame, q_seq: DataFrame, k: int, view_size: int, trigger: str = "truth", metric: str = "l2", tree: BlockTree | None = None, beam: int | None = None, with_links: bool = False) -> DataFrame:
    """(session_id, seq, query_id, view_no, served_from, recall, ids): each session's queries in order.

    ``q_seq``: (session_id, seq, query_id, v), and ``view_size`` where sessions differ in it (the argument is then
    the largest).  Each query's nearest ``view_size`` rows
    are found first for all queries at once; a session then runs by itself, with one copy of
    the vectors that its views can hold.  A view answers from ``beam`` of its leaves and, ``with_links``, by walking its links.
    'truth' renews a view whose answer holds none of the true k; 'radius' when the query is farther from the
    anchor than the view reaches; 'probe' when the best row of the one leaf that ``tree``
    leads to is not in the view.  The query that renews is answered by the new view.
    Without a view (``view_size`` 0) every query goes to the collection.
    """
    q = q_seq.select("query_id", "v").distinct()
    wide = exact.knn(rows, q, max(k, view_size), metric)
    lists = wide.groupBy("query_id").agg(F.array_sort(F.collect_list(F.struct("rank", "vec_id"))).alias("near"))
    probe = search(tree, q, SearchParams(k=1, beam=1)).select("query_id", F.col("vec_id").alias("probe")) if trigger == "probe" else q.select("query_id", F.lit(None).cast("long").alias("probe"))
    size = F.col("view_size") if "view_size" in q_seq.columns else F.lit(view_size)
    seq = q_seq.join(lists, "query_id").join(probe, "query_id", "left").select("session_id", "seq", "query_id", M.doubles("v").alias("v"), F.slice(F.transform("near", lambda x: x["vec_id"]), F.lit(1), F.greatest(F.lit(k), size)).alias("near"), "probe", size.cast("int").alias("size"))
    pool = seq.select("session_id", F.explode("near").alias("vec_id")).distinct().join(rows.select("vec_id", M.doubles("v").alias("x")), "vec_id").select(F.col("session_id").alias("of_session"), "vec_id", "x")

    def run(key, t: pa.Table, held: pa.Table) -> pa.Table:
        out: list[tuple] = []
        if len(t):
            ids = held.column("vec_id").to_numpy()
            order = np.argsort(ids)
            ids, x = ids[order], A.matrix(held.column("x"))[order]
            turn = np.argsort(t.column("seq").to_numpy(), kind="stable")
            asked = A.matrix(t.column("v"))
            view, number, view_size = None, 0, t.column("size")[0].as_py()
            for i in turn.tolist():
                qv, query = asked[i], t.column("query_id")[i].as_py()
                near = t.column("near")[i].values.to_numpy()
                truth = set(near[:k].tolist())
                got = np.zeros(0, np.int64)
                where = "base" if not view_size else "view"
                renew = view is None
                if view is not None:
                    got, _ = view.answer(qv, k, beam, skip=query)
                    renew = {"truth": not truth & set(got.tolist()), "radius": float(A.distance(qv, view.anchor, metric)) > view.radius, "probe": t.column("probe")[i].as_py() not in set(view.ids.tolist())}[trigger]
                if view_size and renew:
                    some = near[:view_size]
                    view = local_view(some, x[np.searchsorted(ids, some)], qv, metric, with_links)
                    got, _ = view.answer(qv, k, beam, skip=query)
                    number, where = number + 1, "new"
                if not view_size:
                    got = near[:k]
                out.append((key[0].as_py(), t.column("seq")[i].as_py(), query, number, where, len(truth & set(got.tolist())) / max(1, len(truth)), got.tolist()))
        cols = list(zip(*out)) or [[]] * 7
        return pa.table([pa.array(c, k2) for c, k2 in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.float64(), pa.list_(pa.int64())))], names=["session_id", "seq", "query_id", "view_no", "served_from", "recall", "ids"])

    return seq.groupBy("session_id").cogroup(pool.groupBy("of_session")).applyInArrow(run, "session_id long, seq long, query_id long, view_no long, served_from string, recall double, ids array<long>")


def survival(trace: DataFrame) -> DataFrame:
    """(session_id, view_no, served): queries that each view answered before its successor."""
    return trace.groupBy("session_id", "view_no").agg(F.count("*").alias("served"))


def route(anchors: DataFrame, q: DataFrame) -> DataFrame:
    """(query_id, view_id, dist): the view whose anchor is closest; ``anchors`` (view_id, v) are few."""
    a = anchors.select("view_id", F.col("v").alias("a"))
    d = q.join(F.broadcast(a), how="cross").select("query_id", "view_id", M.l2(F.col("v"), F.col("a")).alias("dist"))  # views are few
    best = d.groupBy("query_id").agg(F.min(F.struct("dist", "view_id")).alias("b"))
    return best.select("query_id", "b.view_id", "b.dist")


def authorised_search(view_rows: DataFrame, grants: DataFrame, asked: DataFrame, k: int) -> DataFrame:
    """(user_id, query_id, rank, vec_id, dist): each user's best k among the rows of the views granted to them.

    ``view_rows`` (view_id, vec_id, v), ``grants`` (user_id, view_id), ``asked`` (user_id, query_id, v).
    """
    # a user's best k are among the best k of each granted view: vectors meet queries once per view, not once per user
    q = asked.select("query_id", "v").distinct().withColumnRenamed("v", "qv")
    views = view_rows.select("view_id", "vec_id", F.col("v").alias("x")).join(grants.select("view_id").distinct(), "view_id", "left_semi")
    d = views.join(F.broadcast(q), F.col("query_id") != F.col("vec_id")).select("view_id", "query_id", "vec_id", M.l2(F.col("qv"), F.col("x")).alias("dist"))  # the stated questions
    w = Window.partitionBy("view_id", "query_id").orderBy("dist", "vec_id")
    near = d.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).drop("r")
    mine = asked.select("user_id", "query_id").join(grants, "user_id").join(near, ["view_id", "query_id"]).dropDuplicates(["user_id", "query_id", "vec_id"])
    w = Window.partitionBy("user_id", "query_id").orderBy("dist", "vec_id")
    return mine.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("user_id", "query_id", "rank", "vec_id", "dist")


def to_json(view: View) -> str:
    """For state stores: a view as text."""
    return json.dumps({"ids": view.ids.tolist(), "x": view.x.tolist(), "anchor": view.anchor.tolist(), "metric": view.metric, "version": view.version})


def from_json(text: str) -> View:
    d = json.loads(text)
    return local_view(np.array(d["ids"], np.int64), np.array(d["x"]), np.array(d["anchor"]), d["metric"], False, version=d["version"])
