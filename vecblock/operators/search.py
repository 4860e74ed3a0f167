"""Search in a block tree: descend by centroids, scan the chosen leaves, keep the best k.

Inner levels whose centroids fit into LEVEL_BYTES are broadcast and descended
for a whole block of queries by matrix products, in one narrow stage; larger levels are joined
by parent.  Leaves are read where they lie: the few probes travel to them, many of them as
one byte for each query and leaf; beyond PROBE_BYTES both sides meet by leaf.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.functions import arrays as A
from vecblock.functions import metrics as M
from vecblock.operators import exact
from vecblock.operators.tree import BlockTree
from vecblock.sources.stored import stored

LEVEL_BYTES, PROBE_BYTES = 64 << 20, 32 << 20
ALL = 1 << 30


@dataclass(frozen=True)
class SearchParams:
    k: int = 10
    beam: int = 4
    frontier: str = "beam"  # or 'drain', 'best_first'
    farthest: bool = False
    node_score: str = "centroid"  # or 'bound'
    exclude_self: bool = True
    max_leaves: int | None = None
    batch_size: int = 256


@dataclass
class Levels:
    """Inner levels and leaves of a tree as arrays, root first."""

    ids: list[np.ndarray]
    centers: list[np.ndarray]
    radius: list[np.ndarray]
    children: list[list[np.ndarray]]


def levels_of(tree: BlockTree) -> Levels:
    rows = tree.nodes.select("node_id", "parent_id", "level", "centroid", "radius").orderBy("level", "node_id").toArrow()  # checked by fits()
    levels, node, radius = (rows.column(c).to_numpy() for c in ("level", "node_id", "radius"))
    ids, cents, rad, kids = [], [], [], []
    for level in range(len(tree.levels)):
        a, b = np.searchsorted(levels, [level, level + 1])
        ids.append(node[a:b].astype(np.int64))
        cents.append(A.matrix(rows.column("centroid").slice(a, b - a)))
        rad.append(radius[a:b])
        if level:
            at = np.searchsorted(ids[level - 1], rows.column("parent_id").slice(a, b - a).to_numpy())
            below = np.argsort(at, kind="stable")
            kids.append(np.split(below, np.searchsorted(at[below], np.arange(1, len(ids[level - 1])))))
    return Levels(ids, cents, rad, kids)


def fits(tree: BlockTree) -> bool:
    return sum(tree.levels) * tree.dim * 8 <= LEVEL_BYTES


def _score(q: np.ndarray, c: np.ndarray, r: np.ndarray, p: SearchParams, metric: str) -> np.ndarray:
    """Smaller is better."""
    return _signed(A.rough(q, c, metric), r[None], p)


def _exact_score(q: np.ndarray, c: np.ndarray, r: np.ndarray, p: SearchParams, metric: str) -> np.ndarray:
    """The same, row by row."""
    d = 1.0 - (A.unit(q) * A.unit(c)).sum(1) if metric == "cosine" else A.distance(q, c, metric)
    return _signed(d, r, p)


def _signed(d: np.ndarray, r: np.ndarray, p: SearchParams) -> np.ndarray:
    if p.node_score == "bound":
        d = d + r if p.farthest else np.maximum(d - r, 0.0)
    return -d if p.farthest else d


def descend_local(lv: Levels, q: np.ndarray, p: SearchParams, metric: str) -> list[list[tuple[int, int, int]]]:
    """Per query the opened nodes (level, index, children scored), leaves last."""
    depth = len(lv.ids) - 1
    opened: list[list[tuple[int, int, int]]] = [[] for _ in range(len(q))]
    if p.frontier == "best_first":
        import heapq

        budget = p.max_leaves or p.beam
        scores = [_score(q, c, r, p, metric) for c, r in zip(lv.centers, lv.radius)]
        for i in range(len(q)):
            heap, leaves = [(0.0, 0, 0)], 0
            while heap and leaves < budget:
                _, level, n = heapq.heappop(heap)
                if level == depth:
                    opened[i].append((level, n, 0))
                    leaves += 1
                    continue
                kids = lv.children[level][n]
                opened[i].append((level, n, len(kids)))
                for c in kids.tolist():
                    heapq.heappush(heap, (float(scores[level + 1][i, c]), level + 1, c))
        return opened
    now = [np.zeros(1, np.int64) for _ in range(len(q))]
    for level in range(depth):
        s = _score(q, lv.centers[level + 1], lv.radius[level + 1], p, metric)
        for i in range(len(q)):
            pools = [lv.children[level][n] for n in now[i].tolist()]
            opened[i] += [(level, n, len(k)) for n, k in zip(now[i].tolist(), pools)]
            if p.frontier == "drain":
                pools = [k[np.lexsort((k, s[i, k]))[: p.beam]] for k in pools]
                now[i] = np.concatenate(pools)
            else:
                k = np.concatenate(pools)
                now[i] = k[np.lexsort((k, s[i, k]))[: p.beam]]
    for i in range(len(q)):
        opened[i] += [(depth, n, 0) for n in now[i].tolist()]
    return opened


#: Rows of a level for each child of a beam from which on scoring the children alone is less work than a product with the level.
SPARSE = 16


def _children(kids: list[np.ndarray], node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(place in ``node``, child) of all children."""
    count = np.array([len(k) for k in kids], np.int64)
    flat, many = np.concatenate(kids), count[node]
    first = np.cumsum(count) - count
    at = np.repeat(first[node] - (np.cumsum(many) - many), many) + np.arange(int(many.sum()))
    return np.repeat(np.arange(len(node)), many), flat[at]


def _places(row: np.ndarray) -> np.ndarray:
    """Place inside its run of equal numbers."""
    first = np.flatnonzero(np.append(True, row[1:] != row[:-1])) if len(row) else np.zeros(0, np.int64)
    return np.arange(len(row)) - np.repeat(first, np.diff(np.append(first, len(row))))


def descend_beam(lv: Levels, q: np.ndarray, p: SearchParams, metric: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The beam of a block of queries at once: (row, step, level, index, children scored) of the opened nodes."""
    depth, out = len(lv.ids) - 1, []
    row, node, steps = np.arange(len(q)), np.zeros(len(q), np.int64), np.zeros(len(q), np.int64)
    for level in range(depth + 1):
        scored = np.array([len(k) for k in lv.children[level]], np.int64)[node] if level < depth else np.zeros(len(node), np.int64)
        out.append((row, steps[row] + _places(row), np.full(len(row), level), node, scored))
        if level == depth:
            break
        steps += np.bincount(row, minlength=len(q))
        at, child = _children(lv.children[level], node)
        row = row[at]
        c, r = lv.centers[level + 1], lv.radius[level + 1]
        if len(child) * SPARSE < len(q) * len(c):
            s = np.concatenate([_exact_score(q[row[a : a + 8192]], c[child[a : a + 8192]], r[child[a : a + 8192]], p, metric) for a in range(0, len(child), 8192)])
        else:
            s = _score(q, c, r, p, metric)[row, child]
        order = np.lexsort((child, s, row))
        order = order[_places(row[order]) < p.beam]
        row, node = row[order], child[order]
    return tuple(np.concatenate(c) for c in zip(*out))


LOG = "query_id long, step int, node_id long, level int, n_scored long, is_leaf boolean"


def _descend_broadcast(tree: BlockTree, q: DataFrame, p: SearchParams) -> DataFrame:
    held = tree.nodes.sparkSession.sparkContext.broadcast(levels_of(tree))
    depth, metric = tree.height, tree.params.metric

    def opened(lv, v):
        if p.frontier == "beam":
            return descend_beam(lv, v, p, metric)
        flat = [(i, s, *x) for i, o in enumerate(descend_local(lv, v, p, metric)) for s, x in enumerate(o)]
        return tuple(np.array(c, np.int64) for c in zip(*flat))

    def run(batches):
        lv = held.value
        ids, first = np.concatenate(lv.ids), np.cumsum([0, *map(len, lv.ids)])
        for b in batches:
            for at in range(0, len(b), p.batch_size):
                part = b.slice(at, p.batch_size)
                row, step, level, node, scored = opened(lv, A.matrix(part.column("v")))
                columns = [pa.array(part.column("query_id").to_numpy()[row], pa.int64()), pa.array(step, pa.int32()), pa.array(ids[first[level] + node], pa.int64()), pa.array(level, pa.int32()), pa.array(scored, pa.int64()), pa.array(level == depth, pa.bool_())]
                yield pa.RecordBatch.from_arrays(columns, names=["query_id", "step", "node_id", "level", "n_scored", "is_leaf"])

    return q.select("query_id", "v").mapInArrow(run, LOG)


def _descend_joined(tree: BlockTree, q: DataFrame, p: SearchParams) -> DataFrame:
    """The same, one join by parent for each level; node rows never leave their partitions' size."""
    nodes = tree.nodes.select("node_id", F.col("parent_id").alias("up"), "level", "centroid", "radius")
    root = nodes.where("up IS NULL").select(F.col("node_id").alias("at"))
    now = q.select("query_id", "v").join(F.broadcast(root), how="cross")  # the one root
    log = None
    for level in range(tree.height):
        kids = nodes.where(F.col("level") == level + 1).drop("level")
        d = M.cosine(F.col("v"), F.col("centroid")) if tree.params.metric == "cosine" else M.l2(F.col("v"), F.col("centroid"))
        if p.node_score == "bound":
            d = d + F.col("radius") if p.farthest else F.greatest(d - F.col("radius"), F.lit(0.0))
        scored = now.join(kids, F.col("at") == F.col("up")).select("query_id", "v", "at", "node_id", (-d if p.farthest else d).alias("s"))
        part = scored.groupBy("query_id", "at").agg(F.count("*").alias("n")).select("query_id", F.lit(level).alias("step"), F.col("at").alias("node_id"), F.lit(level).alias("level"), F.col("n").alias("n_scored"), F.lit(False).alias("is_leaf"))
        by = ["query_id", "at"] if p.frontier == "drain" else ["query_id"]
        best = scored.withColumn("r", F.row_number().over(Window.partitionBy(*by).orderBy("s", "node_id"))).where(F.col("r") <= p.beam)
        now = stored(best.select("query_id", "v", F.col("node_id").alias("at")), "frontier")
        log = part if log is None else log.union(part)
    leaf = now.select("query_id", F.lit(tree.height).alias("step"), F.col("at").alias("node_id"), F.lit(tree.height).alias("level"), F.lit(0).cast("long").alias("n_scored"), F.lit(True).alias("is_leaf"))
    return leaf if log is None else log.union(leaf)


def descend(tree: BlockTree, q: DataFrame, p: SearchParams = SearchParams()) -> DataFrame:
    """Access log (query_id, step, node_id, level, n_scored, is_leaf); leaf rows are the probes."""
    if not tree.levels:
        return q.sparkSession.createDataFrame([], LOG)
    q = prepared(tree, q)
    if fits(tree):
        return _descend_broadcast(tree, q, p)
    if p.frontier == "best_first":
        raise ValueError("best_first needs all inner levels at once: they exceed LEVEL_BYTES, use the beam")
    if tree.params.metric not in ("l2", "cosine"):
        raise ValueError(f"inner levels beyond LEVEL_BYTES are joined by l2 or cosine, not by {tree.params.metric}")
    return _descend_joined(tree, q, p)


def prepared(tree: BlockTree, q: DataFrame) -> DataFrame:
    v = M.doubles("v")
    return q.select("query_id", (M.normalized(v) if tree.params.metric == "cosine" else v).alias("v"))


def scan_leaves(tree: BlockTree, probes: DataFrame, q: DataFrame, p: SearchParams, allowed: DataFrame | None = None) -> DataFrame:
    """Best k per query among the rows of its probed leaves; ``allowed`` (vec_id) is a filter before the distances."""
    spark = q.sparkSession
    metric, k = tree.params.metric, p.k
    rows = tree.live_rows().select("shard", "leaf_id", "vec_id", "v")
    if allowed is not None:
        rows = rows.join(allowed.select("vec_id"), "vec_id", "left_semi")
    probes = probes.select("query_id", F.col("node_id").alias("leaf_id"))
    few = PROBE_BYTES // 16
    block = exact.query_block(prepared(tree, q))
    asked = probes.limit(few + 1).toArrow() if block is not None else None  # at most PROBE_BYTES: one row more tells that there are too many
    kinds = exact._FOUND
    if block is not None and len(asked) <= few:
        ids, mat = block
        order = np.lexsort((asked.column("query_id").to_numpy(), asked.column("leaf_id").to_numpy()))
        leaf, who = asked.column("leaf_id").to_numpy()[order], np.searchsorted(ids, asked.column("query_id").to_numpy()[order])
        edge = np.flatnonzero(np.append(True, leaf[1:] != leaf[:-1])) if len(leaf) else np.zeros(0, np.int64)
        want = {int(leaf[a]): np.unique(who[a:b]) for a, b in zip(edge.tolist(), [*edge[1:].tolist(), len(leaf)])}
        held = spark.sparkContext.broadcast((ids, mat, want))
        if 0 < len(want) <= 500:  # reaches the scan: files and row groups of other leaves are skipped
            rows = rows.where(F.col("leaf_id").isin(sorted(want)))

        def run(batches):
            qid, q_all, wanted = held.value
            best = None
            for b in batches:
                leaf = b.column("leaf_id").to_numpy()
                vec = b.column("vec_id").to_numpy()
                parts = []
                for one in np.unique(leaf).tolist():
                    qs = wanted.get(one)
                    if qs is None:
                        continue
                    at = np.flatnonzero(leaf == one)
                    x = A.matrix(b.column("v").take(pa.array(at)))
                    row, found, dist = A.block_topk(q_all[qs], x, vec[at], k + p.exclude_self, metric, p.farthest)
                    who = qid[qs[row]]
                    keep = who != found if p.exclude_self else np.ones(len(who), bool)
                    parts.append(pa.table({"query_id": pa.array(who[keep], pa.int64()), "vec_id": pa.array(found[keep], pa.int64()), "dist": pa.array(dist[keep], pa.float64())}))
                if parts:
                    best = exact._cut(pa.concat_tables(parts if best is None else [best, *parts]), k, p.farthest)
            if best is not None:
                yield from best.cast(kinds).to_batches()

        return exact.ranked(rows.select("leaf_id", "vec_id", "v").mapInArrow(run, exact.FOUND), k, p.farthest)

    if block is not None and len(block[0]) * tree.levels[-1] <= PROBE_BYTES:
        return exact.ranked(_scan_dense(tree, probes, block, p, rows), k, p.farthest)
    return exact.ranked(_scan_met(probes, prepared(tree, q), rows, p, metric), k, p.farthest)


#: Leaves of neighbouring ids that meet their queries in one task, and probes that do.
MEET_LEAVES, MEET_PROBES = 64, 8192


def _scan_met(probes: DataFrame, q: DataFrame, rows: DataFrame, p: SearchParams, metric: str) -> DataFrame:
    """FOUND where rows and queries meet by groups of leaves; groups of many probes are dealt out, each turn with the rows of its leaves."""
    group = F.floor(F.col("leaf_id") / MEET_LEAVES).alias("group")
    probes = stored(probes.select("query_id", "leaf_id", group), "probes")
    turns = probes.groupBy("group").agg(F.ceil(F.count("*") / MEET_PROBES).cast("int").alias("turns"))
    turn = F.pmod(F.xxhash64("query_id"), F.col("turns")).cast("int").alias("turn")
    left = probes.join(turns, "group").select("query_id", "leaf_id", "group", turn).groupBy("group", "turn", "query_id").agg(F.collect_list("leaf_id").alias("leaves")).join(q, "query_id")
    right = rows.select("leaf_id", "vec_id", "v", group).join(turns, "group").withColumn("turn", F.explode(F.sequence(F.lit(0), F.col("turns") - 1))).drop("turns")

    def meet(key, a: pa.Table, b: pa.Table) -> pa.Table:
        if not len(a) or not len(b):
            return exact._FOUND.empty_table()
        qid, q_all, x, vec = a.column("query_id").to_numpy(), A.matrix(a.column("v")), A.matrix(b.column("v")), b.column("vec_id").to_numpy()
        wanted = a.column("leaves").combine_chunks()
        asked, who = wanted.flatten().to_numpy(), np.repeat(np.arange(len(a)), np.diff(wanted.offsets.to_numpy()))
        leaf = b.column("leaf_id").to_numpy()
        by_query, by_row = np.argsort(asked, kind="stable"), np.argsort(leaf, kind="stable")
        parts = [exact._FOUND.empty_table()]
        for one in np.unique(asked).tolist():
            qs, at = (order[slice(*np.searchsorted(keys[order], [one, one + 1]))] for keys, order in ((asked, by_query), (leaf, by_row)))
            qs = who[qs]
            row, found, dist = A.block_topk(q_all[qs], x[at], vec[at], p.k + p.exclude_self, metric, p.farthest)
            mine = qid[qs[row]]
            keep = mine != found if p.exclude_self else np.ones(len(mine), bool)
            parts.append(pa.table([pa.array(mine[keep], pa.int64()), pa.array(found[keep], pa.int64()), pa.array(dist[keep], pa.float64())], schema=exact._FOUND))
        return exact._cut(pa.concat_tables(parts), p.k, p.farthest)

    return left.groupBy("group", "turn").cogroup(right.groupBy("group", "turn")).applyInArrow(meet, exact.FOUND)


def _scan_dense(tree: BlockTree, probes: DataFrame, block, p: SearchParams, rows: DataFrame) -> DataFrame:
    """FOUND where queries open a large share of all leaves: whole batches of rows are scored, what a query did not open is left out."""
    context, metric = rows.sparkSession.sparkContext, tree.params.metric
    leaves = np.array([r.node_id for r in tree.nodes.where("is_leaf").select("node_id").orderBy("node_id").collect()], np.int64)  # a byte for each and query is within PROBE_BYTES
    keys = context.broadcast((block[0], leaves))

    def mark(batches):
        ids, leaf = keys.value
        opened = np.zeros((len(ids), len(leaf)), bool)
        for b in batches:
            opened[np.searchsorted(ids, b.column("query_id").to_numpy()), np.searchsorted(leaf, b.column("leaf_id").to_numpy())] = True
        yield pa.RecordBatch.from_arrays([pa.array([np.packbits(opened).tobytes()], pa.binary())], names=["bits"])

    bits = np.zeros(-(-len(block[0]) * len(leaves) // 8), np.uint8)
    for r in probes.coalesce(16).mapInArrow(mark, "bits binary").collect():  # at most 16 times PROBE_BYTES / 8
        bits |= np.frombuffer(r.bits, np.uint8)
    held = context.broadcast((*block, leaves, bits))

    def run(batches):
        ids, mat, leaf, packed = held.value
        opened = np.unpackbits(packed, count=len(ids) * len(leaf)).reshape(len(ids), len(leaf)).astype(bool)
        best = None
        for b in batches:
            at, vec, x = np.searchsorted(leaf, b.column("leaf_id").to_numpy()), b.column("vec_id").to_numpy(), A.matrix(b.column("v"))
            some = np.flatnonzero(opened[:, np.unique(at)].any(1))
            for a in range(0, len(some), 256):
                who = some[a : a + 256]
                row, found, dist = A.block_topk(mat[who], x, vec, p.k + p.exclude_self, metric, p.farthest, opened[who][:, at])
                who = ids[who[row]]
                keep = who != found if p.exclude_self else np.ones(len(who), bool)
                now = pa.table({"query_id": pa.array(who[keep], pa.int64()), "vec_id": pa.array(found[keep], pa.int64()), "dist": pa.array(dist[keep], pa.float64())})
                best = now if best is None else pa.concat_tables([best, now])
            if best is not None:
                best = exact._cut(best, p.k, p.farthest)
        if best is not None:
            yield from best.cast(exact._FOUND).to_batches()

    return rows.select("leaf_id", "vec_id", "v").mapInArrow(run, exact.FOUND)


def opens_all(tree: BlockTree, p: SearchParams) -> bool:
    return (p.max_leaves or p.beam if p.frontier == "best_first" else p.beam) >= tree.levels[-1]


def search(tree: BlockTree, q: DataFrame, params: SearchParams = SearchParams(), links: DataFrame | None = None, allowed: DataFrame | None = None) -> DataFrame:
    """(query_id, rank, vec_id, dist); ``links`` adds greedy refinement from the tree's answer."""
    p = params
    if p.k <= 0 or not tree.levels:
        return q.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, dist double")
    if opens_all(tree, p):  # no probes to list: every leaf is scanned for every query
        rows = tree.live_rows().select("vec_id", "v")
        found = exact.knn(rows if allowed is None else rows.join(allowed.select("vec_id"), "vec_id", "left_semi"), prepared(tree, q), p.k, tree.params.metric, p.exclude_self, p.farthest)
    else:
        found = scan_leaves(tree, descend(tree, q, p).where("is_leaf"), q, p, allowed)
    if links is None:
        return found
    from vecblock.operators import graph

    return graph.greedy(found, links, tree.live_rows().select("vec_id", "v"), prepared(tree, q), p.k, tree.params.metric, p.farthest, exclude_self=p.exclude_self).select("query_id", "rank", "vec_id", "dist")


#: A metric m and c such that m(a, b) <= c * l2(a, b), and C such that C * m(a, b) >= l2(a, b), for vectors of n numbers.
_BELOW_L2 = {"l2": lambda n: 1.0, "l1": lambda n: math.sqrt(n), "chebyshev": lambda n: 1.0, "minkowski": lambda n: 1.0}
_ABOVE_L2 = {"l2": lambda n: 1.0, "l1": lambda n: 1.0, "chebyshev": lambda n: math.sqrt(n), "minkowski": lambda n: n ** (1 / 2 - 1 / 3)}


def l2_bound(metric: str, bound: np.ndarray, dim: int, farthest: bool) -> np.ndarray:
    """An L2 distance such that no answer lies beyond it (or, of the farthest, below it), from a bound in the tree's metric."""
    if metric == "cosine":  # on unit vectors 1 - cos = d^2 / 2
        return np.sqrt(np.maximum(2 * bound, 0.0))
    if metric not in _BELOW_L2:
        raise ValueError(f"no distance bound is known for {metric}")
    # nearest: m <= bound gives l2 <= C m; farthest: m >= bound gives l2 >= m / c
    return bound / _BELOW_L2[metric](dim) if farthest else bound * _ABOVE_L2[metric](dim)


def _open_local(lv: Levels, q: np.ndarray, bound: np.ndarray, farthest: bool) -> tuple[np.ndarray, np.ndarray]:
    """(query row, leaf) pairs that the triangle inequality leaves open, by matrix products level by level."""
    row, node = np.arange(len(q)), np.zeros(len(q), np.int64)
    for level in range(len(lv.ids) - 1):
        at, node = _children(lv.children[level], node)
        row = row[at]
        d = A.rough(q, lv.centers[level + 1], "l2")[row, node]
        r, b = lv.radius[level + 1][node], bound[row]
        slack = 1e-6 * (1 + np.minimum(b, 1e12) + d)  # rounding of the products
        ok = d + r >= b - slack if farthest else d - r <= b + slack
        row, node = row[ok], node[ok]
    return row, lv.ids[-1][node]


def _open_within(tree: BlockTree, q: DataFrame, farthest: bool) -> DataFrame:
    """(query_id, node_id): leaves that may hold an answer, from (query_id, v, bound) with L2 bounds."""
    if fits(tree):
        held = tree.nodes.sparkSession.sparkContext.broadcast(levels_of(tree))

        def run(batches):
            for b in batches:
                ids = b.column("query_id").to_numpy()
                for at in range(0, len(b), 256):
                    part = b.slice(at, 256)
                    row, leaf = _open_local(held.value, A.matrix(part.column("v")), part.column("bound").to_numpy(), farthest)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[at : at + 256][row]), pa.array(leaf)], names=["query_id", "node_id"])

        return q.select("query_id", "v", "bound").mapInArrow(run, "query_id long, node_id long")
    nodes = tree.nodes.select("node_id", F.col("parent_id").alias("up"), "level", "centroid", "radius")
    root = nodes.where("up IS NULL").select(F.col("node_id").alias("at"))
    now = q.join(F.broadcast(root), how="cross")  # the one root
    for level in range(tree.height):
        kids = nodes.where(F.col("level") == level + 1).drop("level")
        d = M.l2(F.col("v"), F.col("centroid"))
        slack = 1e-9 * (1 + F.col("bound"))
        ok = d + F.col("radius") >= F.col("bound") - slack if farthest else d - F.col("radius") <= F.col("bound") + slack
        now = now.join(kids, F.col("at") == F.col("up")).where(ok).select("query_id", "v", "bound", F.col("node_id").alias("at"))
    return now.select("query_id", F.col("at").alias("node_id"))


def search_exact(tree: BlockTree, q: DataFrame, k: int = 10, farthest: bool = False, exclude_self: bool = True, beam: int = 2) -> DataFrame:
    """Exact answers: a beam search bounds the k-th distance, then the other leaves that the triangle inequality allows are read.

    Bounds are L2; other metrics (l1, chebyshev, minkowski of order 3, cosine on unit vectors) are
    brought to L2 by their norms' ratios, which depend on the dimension; for further metrics this raises.
    """
    metric = tree.params.metric
    l2_bound(metric, np.zeros(1), max(tree.dim, 1), farthest)
    if not tree.levels or k <= 0:
        return q.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, dist double")
    p = SearchParams(k=k, beam=beam, farthest=farthest, exclude_self=exclude_self, node_score="bound" if farthest and metric == "l2" else "centroid")
    seen = stored(descend(tree, q, p).where("is_leaf").select("query_id", "node_id"), "seen")
    first = stored(scan_leaves(tree, seen, q, p), "first")
    kth = first.groupBy("query_id").agg(F.max("rank").alias("n"), (F.min("dist") if farthest else F.max("dist")).alias("b"))
    factor = float(l2_bound(metric, np.ones(1), tree.dim, farthest)[0])
    to_l2 = F.sqrt(F.greatest(2 * F.col("b"), F.lit(0.0))) if metric == "cosine" else F.col("b") * factor
    bound = F.when(F.col("n") >= k, to_l2).otherwise(-1.0 if farthest else 1e300)
    asked = prepared(tree, q).join(kth, "query_id", "left").select("query_id", "v", bound.alias("bound"))
    more = stored(_open_within(tree, asked, farthest).join(seen, ["query_id", "node_id"], "left_anti"), "open")
    rest = scan_leaves(tree, more, q, SearchParams(k=k, farthest=farthest, exclude_self=exclude_self))
    return exact.ranked(first.drop("rank").unionByName(rest.drop("rank")), k, farthest)


def within(tree: BlockTree, q: DataFrame, radius: float, exclude_self: bool = True) -> DataFrame:
    """(query_id, vec_id, dist) of all rows in a radius of the tree's metric (l2 or cosine), reading only leaves that can hold one."""
    metric = tree.params.metric
    if metric not in ("l2", "cosine"):
        raise ValueError(f"a radius search needs an l2 or cosine tree, not {metric}")
    q2 = prepared(tree, q)
    reach = float(l2_bound(metric, np.array([radius]), tree.dim, False)[0])
    probes = _open_within(tree, q2.withColumn("bound", F.lit(reach)), False)
    rows = tree.live_rows().select("leaf_id", "vec_id", F.col("v").alias("x"))
    hit = probes.withColumnRenamed("node_id", "leaf_id").join(q2, "query_id").join(rows, "leaf_id")
    d = M.cosine(F.col("v"), F.col("x")) if metric == "cosine" else M.l2(F.col("v"), F.col("x"))
    out = hit.select("query_id", "vec_id", d.alias("dist")).where(F.col("dist") <= radius)
    return out.where("query_id <> vec_id") if exclude_self else out


def post_filtered(tree: BlockTree, q: DataFrame, allowed: DataFrame, k: int, factor: int = 4, **options) -> DataFrame:
    """Search for k * factor, filter afterwards, keep k; may return fewer."""
    got = search(tree, q, SearchParams(k=k * factor, **options))
    return exact.ranked(got.join(allowed.select("vec_id"), "vec_id", "left_semi").drop("rank"), k, options.get("farthest", False))


def rerank(tree: BlockTree, q: DataFrame, broad: int = 100, k: int = 10, **options) -> DataFrame:
    """Broad retrieval, exact scores once more, best k."""
    got = search(tree, q, SearchParams(k=broad, **options))
    rows = tree.live_rows().select("vec_id", F.col("v").alias("x"))
    again = got.join(rows, "vec_id").join(prepared(tree, q), "query_id")
    d = M.cosine(F.col("v"), F.col("x")) if tree.params.metric == "cosine" else M.l2(F.col("v"), F.col("x"))
    return exact.ranked(again.select("query_id", "vec_id", d.alias("dist")), k)
