"""Graphs over vectors: links between neighbours and greedy walks along them."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.functions import arrays as A
from vecblock.functions import metrics as M
from vecblock.operators import exact
from vecblock.operators.search import LEVEL_BYTES, SearchParams, descend
from vecblock.operators.tree import BlockTree
from vecblock.sources.stored import stored

LINKS = "src long, dst long, dist double, src_leaf long, dst_leaf long"
#: Bytes of vectors and links that a walk inside one task may hold (views and shards).
LOCAL_BYTES = 128 << 20


def recommended_leaf_capacity(n: int, base: float = math.e) -> int:
    """Root of n / log n; at it the leaf-to-leaf distances cost n log n."""
    return max(1, math.ceil(math.sqrt(n / math.log(n, base)))) if n > 1 else 1


def recommended_link_leaves(n: int, base: float = 10) -> int:
    """Largest useful number of near leaves: root of n log n."""
    return max(1, math.ceil(math.sqrt(n * math.log(n, base)))) if n > 1 else 1


def near_leaves(leaves: DataFrame, s: int, metric: str = "l2") -> DataFrame:
    """(leaf_id, near_id, rank, dist): the s nearest leaves of each by centroid, its own included.

    ``leaves``: (leaf_id, centroid).  Exact at any number of leaves and quadratic in it, on a
    grid of blocks; ``near_leaves_by_tree`` is the approximation that is not.
    """
    q = leaves.select(F.col("leaf_id").alias("query_id"), F.col("centroid").alias("v"))
    found = exact.knn(leaves.select(F.col("leaf_id").alias("vec_id"), F.col("centroid").alias("v")), q, s, metric, exclude_self=False)
    return found.select(F.col("query_id").alias("leaf_id"), F.col("vec_id").alias("near_id"), "rank", "dist")


def near_leaves_by_tree(tree: BlockTree, s: int, beam: int | None = None) -> DataFrame:
    """The same through the tree itself: every leaf's centroid descends with a beam of s."""
    leaf = tree.nodes.where("is_leaf").select(F.col("node_id").alias("query_id"), F.col("centroid").alias("v"))
    log = descend(tree, leaf, SearchParams(beam=beam or s)).where("is_leaf")
    other = tree.nodes.where("is_leaf").select(F.col("node_id").alias("near_id"), F.col("centroid").alias("c"))
    pairs = log.select(F.col("query_id").alias("leaf_id"), F.col("node_id").alias("near_id")).union(leaf.select("query_id", "query_id")).distinct()
    d = pairs.join(other, "near_id").join(leaf.select(F.col("query_id").alias("leaf_id"), "v"), "leaf_id").select("leaf_id", "near_id", M.l2(F.col("v"), F.col("c")).alias("dist"))
    w = Window.partitionBy("leaf_id").orderBy("dist", "near_id")
    return d.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= s)


def build_links(tree: BlockTree, link_degree: int = 8, link_leaves: int = 4, max_scan_fraction: float = 1.0, near: DataFrame | None = None, by_tree: bool = False) -> DataFrame:
    """LINKS and kind: each vector's nearest vectors among the rows of its leaf's near leaves.

    ``by_tree`` finds near leaves by a search in the tree instead of by all pairs of leaves.
    """
    m = tree.levels[-1] if tree.levels else 0
    s = max(1, min(link_leaves, math.ceil(m * max_scan_fraction), m or 1))
    if near is None and s >= m:
        return with_kind(_links_of_all(tree.live_rows(), link_degree, tree.params.metric))
    if near is None:
        leaves = tree.nodes.where("is_leaf").select(F.col("node_id").alias("leaf_id"), "centroid")
        near = near_leaves_by_tree(tree, s) if by_tree else near_leaves(leaves, s)
    rows = tree.live_rows().select("leaf_id", "vec_id", "v")
    asked = near.select(F.col("leaf_id").alias("home"), F.col("near_id").alias("at"))
    other = rows.select(F.col("leaf_id").alias("at"), F.col("vec_id").alias("other"), F.col("v").alias("w")).join(asked, "at").select("home", "at", "other", "w")
    metric = tree.params.metric

    def link(key, left: pa.Table, right: pa.Table) -> pa.Table:
        x, ids = A.matrix(left.column("v")), left.column("vec_id").to_numpy()
        y, oid, at = A.matrix(right.column("w")), right.column("other").to_numpy(), right.column("at").to_numpy()
        row, found, dist = A.block_topk(x, y, oid, link_degree + 1, metric)
        src = ids[row] if len(row) else row
        keep = src != found
        src, found, dist = src[keep], found[keep], dist[keep]
        first = np.flatnonzero(np.append(True, src[1:] != src[:-1])) if len(src) else np.zeros(0, np.int64)
        nth = np.arange(len(src)) - np.repeat(first, np.diff(np.append(first, len(src))))
        keep = nth < link_degree
        src, found, dist = src[keep], found[keep], dist[keep]
        order = np.argsort(oid)
        leaf = at[order][np.searchsorted(oid[order], found)] if len(found) else found
        home = left.column("leaf_id")[0].as_py() if len(left) else 0
        return pa.table([pa.array(src, pa.int64()), pa.array(found, pa.int64()), pa.array(dist, pa.float64()), pa.array(np.full(len(src), home, np.int64)), pa.array(leaf, pa.int64())], names=["src", "dst", "dist", "src_leaf", "dst_leaf"])

    made = rows.groupBy("leaf_id").cogroup(other.groupBy("home")).applyInArrow(link, LINKS)
    return with_kind(made)


def _links_of_all(rows: DataFrame, link_degree: int, metric: str) -> DataFrame:
    """LINKS where every leaf is near every other: the exact neighbours, met in blocks, so that no row is copied once per leaf."""
    found = exact.knn(rows, rows.select(F.col("vec_id").alias("query_id"), "v"), link_degree, metric)
    home, other = (rows.select(F.col("vec_id").alias(a), F.col("leaf_id").alias(b)) for a, b in (("src", "src_leaf"), ("dst", "dst_leaf")))
    return found.select(F.col("query_id").alias("src"), F.col("vec_id").alias("dst"), "dist").join(home, "src").join(other, "dst").select("src", "dst", "dist", "src_leaf", "dst_leaf")


def with_kind(links: DataFrame) -> DataFrame:
    return links.withColumn("kind", F.when(F.col("src_leaf") == F.col("dst_leaf"), "within").otherwise("across"))


def build_links_pruned(leaf_rows: DataFrame, bound: float, metric: str = "l2") -> DataFrame:
    """Links up to a length, inside leaves whose rows are sorted by distance to the centroid.

    |d(u,c) - d(v,c)| <= d(u,v), so only a band of the sorted rows is scored.
    Returns LINKS columns and n_scored, the distances computed for the source row.
    """

    def band(t: pa.Table) -> pa.Table:
        order = np.argsort(t.column("d_centroid").to_numpy(), kind="stable")
        d = t.column("d_centroid").to_numpy()[order]
        x, ids = A.matrix(t.column("v"))[order], t.column("vec_id").to_numpy()[order]
        lo, hi = np.searchsorted(d, d - bound - 1e-12), np.searchsorted(d, d + bound + 1e-12, "right")
        src, dst, dist, cost = [], [], [], []
        for i in range(len(ids)):
            at = np.arange(lo[i], hi[i])
            at = at[at != i]
            e = A.distance(x[i], x[at], metric)
            ok = e <= bound
            src.append(np.full(ok.sum(), ids[i]))
            dst.append(ids[at[ok]])
            dist.append(e[ok])
            cost.append(np.full(ok.sum(), len(at)))
        leaf = np.full(sum(map(len, src)), t.column("leaf_id")[0].as_py())
        return pa.table([pa.array(np.concatenate(src), pa.int64()), pa.array(np.concatenate(dst), pa.int64()), pa.array(np.concatenate(dist), pa.float64()), pa.array(leaf, pa.int64()), pa.array(leaf, pa.int64()), pa.array(np.concatenate(cost), pa.int64())], names=["src", "dst", "dist", "src_leaf", "dst_leaf", "n_scored"])

    return leaf_rows.select("leaf_id", "vec_id", "v", "d_centroid").groupBy("leaf_id").applyInArrow(band, LINKS + ", n_scored long")


class Adjacency:
    """Row numbers linked from each row, as two arrays: a list per row would hold some ten times the memory."""

    def __init__(self, first: np.ndarray, to: np.ndarray):
        self.first, self.to = first, to

    @classmethod
    def of(cls, ids: np.ndarray, src: np.ndarray, dst: np.ndarray) -> "Adjacency":
        """Links between sorted ids in the order given for each source; links of other ids are left out."""
        if not len(ids):
            return cls(np.zeros(1, np.int64), np.zeros(0, np.int64))
        a, b = (np.minimum(np.searchsorted(ids, e), len(ids) - 1) for e in (src, dst))
        known = (ids[a] == src) & (ids[b] == dst)
        a, b = a[known], b[known]
        order = np.argsort(a, kind="stable")
        return cls(np.searchsorted(a[order], np.arange(len(ids) + 1)), b[order].astype(np.int32 if len(ids) < 2**31 else np.int64))

    def __getitem__(self, row: int) -> np.ndarray:
        return self.to[self.first[row] : self.first[row + 1]]

    def __len__(self) -> int:
        return len(self.first) - 1


def local_graph(links: DataFrame, rows: DataFrame):
    """(ids, matrix, adjacency) of a small graph on the driver; None where vectors and links exceed LOCAL_BYTES."""
    size = rows.agg((F.count("*") * F.max(F.size("v")) * 8).alias("b")).first().b or 0
    if size > LOCAL_BYTES or size + 16 * links.count() > LOCAL_BYTES:
        return None
    got = rows.select("vec_id", "v").orderBy("vec_id").toArrow()  # checked against LOCAL_BYTES
    ids, x = got.column("vec_id").to_numpy(), A.matrix(got.column("v"))
    edges = links.select("src", "dst").orderBy("src", "dist", "dst").toArrow()
    src, dst = edges.column("src").to_numpy(), edges.column("dst").to_numpy()
    return ids, x, Adjacency.of(ids, src, dst)


def greedy(seeds: DataFrame, links: DataFrame, rows: DataFrame, q: DataFrame, k: int, metric: str = "l2", farthest: bool = False, ef: int | None = None, exclude_self: bool = True, max_rounds: int = 10_000, local: bool = True) -> DataFrame:
    """(query_id, rank, vec_id, dist, hops, n_seen) from seeds (query_id, vec_id).

    A graph that fits into a task is broadcast and each query walks alone; others
    advance all queries together, a join per round, until no answer changes.  Both end at the
    same fixed point; more than ``max_rounds`` raise.
    """
    width = max(k, ef or k)
    graph = local_graph(links, rows) if local else None
    if graph is None:
        return _greedy_rounds(seeds, links, rows, q, k, width, metric, farthest, exclude_self, max_rounds)
    held = rows.sparkSession.sparkContext.broadcast(graph)
    asked = seeds.groupBy("query_id").agg(F.sort_array(F.collect_set("vec_id")).alias("seeds")).join(q, "query_id")

    def run(batches):
        ids, x, adj = held.value
        where = {v: i for i, v in enumerate(ids.tolist())}
        for b in batches:
            out: list[list] = [[] for _ in range(6)]
            mat = A.matrix(b.column("v"))
            for i, (qid, start) in enumerate(zip(b.column("query_id").to_pylist(), b.column("seeds").to_pylist())):
                first = np.array([where[s] for s in start if s in where], np.int64)
                own = where.get(qid) if exclude_self else None
                keep = width + (own is not None)
                got, dist, hops, seen = A.refine(mat[i], first, adj, x, keep, metric, farthest) if len(first) else (first, np.zeros(0), 0, 0)
                if own is not None:
                    dist, got = dist[got != own], got[got != own]
                exact_d = A.distance(mat[i], x[got], metric) if len(got) else dist
                order = np.lexsort((ids[got], -exact_d if farthest else exact_d))[:k]
                for r, j in enumerate(order.tolist(), 1):
                    for c, v in zip(out, (qid, r, int(ids[got[j]]), float(exact_d[j]), hops, seen)):
                        c.append(v)
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.float64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, kinds)], names=["query_id", "rank", "vec_id", "dist", "hops", "n_seen"])

    return asked.select("query_id", "seeds", "v").mapInArrow(run, "query_id long, rank int, vec_id long, dist double, hops long, n_seen long")


def _greedy_rounds(seeds, links, rows, q, k, width, metric, farthest, exclude_self, max_rounds) -> DataFrame:
    """Frontier form: states seen (1) and expanded (2) in a stored table."""
    d = (M.cosine if metric == "cosine" else M.l2)(F.col("v"), F.col("x"))
    body = rows.select("vec_id", F.col("v").alias("x"))

    def scored(pairs: DataFrame) -> DataFrame:
        return pairs.join(body, "vec_id").join(q, "query_id").select("query_id", "vec_id", d.alias("dist"))

    best = F.desc("dist") if farthest else F.asc("dist")
    w = Window.partitionBy("query_id").orderBy(best, F.asc("vec_id"))
    pool = stored(scored(seeds.select("query_id", "vec_id").distinct()).withColumn("state", F.lit(1)), "pool")
    for _ in range(max_rounds):
        top = pool.withColumn("r", F.row_number().over(w)).withColumn("open", (F.col("r") <= width + int(exclude_self)) & (F.col("state") == 1))
        if top.where("open").isEmpty():
            break
        new = top.where("open").join(links.select(F.col("src").alias("vec_id"), "dst"), "vec_id").select("query_id", F.col("dst").alias("vec_id")).distinct()
        fresh = scored(new.join(pool.select("query_id", "vec_id"), ["query_id", "vec_id"], "left_anti")).withColumn("state", F.lit(1))
        marked = top.withColumn("state", F.when(F.col("open"), 2).otherwise(F.col("state"))).select("query_id", "vec_id", "dist", "state")
        pool = stored(marked.union(fresh), "pool")
    else:
        raise RuntimeError(f"the walk did not end in {max_rounds} rounds")
    seen = pool.groupBy("query_id").agg(F.count(F.when(F.col("state") == 2, 1)).alias("hops"), F.count("*").alias("n_seen"))
    hits = pool.where("query_id <> vec_id") if exclude_self else pool
    return exact.ranked(hits, k, farthest).join(seen, "query_id").select("query_id", "rank", "vec_id", "dist", "hops", "n_seen")


def random_seeds(q: DataFrame, rows: DataFrame, n: int = 1, seed: int = 42) -> DataFrame:
    """The same n random rows for every query: a start without a tree."""
    pick = rows.select("vec_id").orderBy(F.md5(F.concat_ws("|", "vec_id", F.lit(seed))), "vec_id").limit(n)
    return q.select("query_id").join(F.broadcast(pick), how="cross")  # n rows


def fixpoint_violations(found: DataFrame, links: DataFrame, rows: DataFrame, q: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """Answers that one more expansion would improve: none after a finished walk."""
    again = greedy(found, links, rows, q, k, metric)
    kth = lambda t: t.groupBy("query_id").agg(F.max("dist").alias("kth"))
    worse = kth(found).alias("a").join(kth(again).alias("b"), "query_id").where(F.col("b.kth") < F.col("a.kth") - 1e-12)
    return worse.agg(F.count("*").alias("violations"))


__all__ = ["LEVEL_BYTES", "build_links", "build_links_pruned", "fixpoint_violations", "greedy", "greedy_per_branch", "local_graph", "near_leaves", "near_leaves_by_tree", "random_seeds", "recommended_leaf_capacity", "recommended_link_leaves", "with_kind"]


def greedy_per_branch(seeds: DataFrame, links: DataFrame, rows: DataFrame, q: DataFrame, k: int, metric: str = "l2", farthest: bool = False, exclude_self: bool = True) -> DataFrame:
    """(query_id, rank, vec_id, dist): one walk for each branch's seeds (query_id, branch, vec_id), merged at the end."""
    walks = stored(seeds.select("query_id", "branch").distinct().withColumn("walk", F.monotonically_increasing_id()), "walks")
    apart = seeds.join(walks, ["query_id", "branch"])
    got = greedy(apart.select(F.col("walk").alias("query_id"), "vec_id"), links, rows, walks.join(q, "query_id").select(F.col("walk").alias("query_id"), "v"), k + int(exclude_self), metric, farthest, exclude_self=False)
    merged = got.select(F.col("query_id").alias("walk"), "vec_id", "dist").join(walks, "walk").select("query_id", "vec_id", "dist").distinct()
    return exact.ranked(merged.where("query_id <> vec_id") if exclude_self else merged, k, farthest)
