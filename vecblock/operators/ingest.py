"""Growth: inserts with splits, clusters at once, tombstones and compaction; every change is a new version."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.functions import arrays as A
from vecblock.functions import metrics as M
from vecblock.operators.search import SearchParams, descend
from vecblock.operators.tree import DRIVER_BYTES, NODES, BlockTree, _assemble_wide, _laid_out, _leaf_stats, _locate, _packable, _two, assemble, build
from vecblock.sources.stored import stored

_PLACED = "leaf_path string, path string, vec_id long, v array<double>"


def split_rows(x: np.ndarray, ids: np.ndarray, capacity: int, seed: int = 42) -> list[np.ndarray]:
    """Two-means again and again until every part fits."""
    pieces, _ = A.split_all(x, ids, "r", capacity, 2, 8, "d2", seed)
    return [p[1] for p in pieces]


def _split(capacity: int, split_at: float):
    limit = max(1, int(capacity * split_at))

    def run(t: pa.Table) -> pa.Table:
        leaf = t.column("leaf_id")[0].as_py()
        x, ids = A.matrix(t.column("v")), t.column("vec_id").to_numpy()
        parts = [np.arange(len(ids))] if len(ids) <= limit else split_rows(x, ids, limit)
        # leaves keep their place in the order: numbers below the old leaf
        names, rows = [], []
        for k, p in enumerate(parts):
            names += [f"r.{leaf}" if len(parts) == 1 else f"r.{leaf}.{k}"] * len(p)
            rows.append(p)
        at = np.concatenate(rows)
        return pa.table([pa.array(names), pa.array(names), pa.array(ids[at], pa.int64()), A.lists(x[at])], names=["leaf_path", "path", "vec_id", "v"])

    return run


def _stats(placed: DataFrame) -> DataFrame:
    return stored(placed.groupBy("leaf_path").applyInArrow(_leaf_stats, "leaf_path string, n_rows long, vec_sum array<double>, centroid array<double>, radius double"), "leaves")


def _rebuilt(tree: BlockTree, placed: DataFrame, n: int) -> BlockTree:
    """Inner nodes and layout for placed rows (_PLACED); sums give the new centroids."""
    spark = tree.nodes.sparkSession
    stats = _stats(placed)
    p = tree.params
    m = stats.count()
    if m * tree.dim * 16 > DRIVER_BYTES:
        nodes, names = _assemble_wide(_packable(stats, p), p)
    else:
        rows, number = assemble(stats.collect(), p)  # checked against DRIVER_BYTES
        nodes = spark.createDataFrame([(*r, int(r[-1] // p.leaves_per_shard)) for r in rows], tree.nodes.schema)
        names = spark.createDataFrame(list(number.items()), "leaf_path string, leaf_id long")
    nodes = stored(nodes, "nodes")
    return _laid_out(nodes, _locate(nodes, placed, names), p, tree.dim, n, tree.version + 1)


class _Nodes:
    """The nodes of a tree on the driver, for changes along a few paths from leaf to root."""

    def __init__(self, tree: BlockTree):
        self.p = tree.params
        self.of: dict[int, dict] = {}
        for r in tree.nodes.orderBy("node_order").collect():  # checked against DRIVER_BYTES
            self.of[r.node_id] = {"up": r.parent_id, "leaf": r.is_leaf, "kids": [], "n": r.n_rows, "sum": np.array(r.vec_sum), "c": np.array(r.centroid), "r": r.radius, "shard": r.shard}
        for me, x in self.of.items():
            if x["up"] is not None:
                self.of[x["up"]]["kids"].append(me)
        self.next = max(self.of) + 1
        self.touched: set[int] = set()

    def new(self, up, leaf: bool, kids: list[int], shard: int) -> int:
        me, self.next = self.next, self.next + 1
        self.of[me] = {"up": up, "leaf": leaf, "kids": kids, "n": 0, "sum": None, "c": None, "r": 0.0, "shard": shard}
        for k in kids:
            self.of[k]["up"] = me
        return me

    def replace_leaf(self, old: int, parts: list) -> list[int]:
        """New leaves from statistics in the old one's place; the numbers given to them."""
        gone = self.of.pop(old)
        made = []
        for r in parts:
            me = self.new(gone["up"], True, [], gone["shard"])
            self.of[me].update(n=r.n_rows, sum=np.array(r.vec_sum), c=np.array(r.centroid), r=r.radius)
            made.append(me)
        if gone["up"] is None:  # the root was a leaf
            self.new(None, False, made, gone["shard"])
            gone["up"] = self.of[made[0]]["up"]
        else:
            kids = self.of[gone["up"]]["kids"]
            at = kids.index(old)
            kids[at : at + 1] = made
        self.touched.add(gone["up"])
        return made

    def settle(self) -> None:
        """Split overfull nodes upwards, then refresh sums, centroids and radii on all paths that changed."""
        limit = max(2, int(self.p.inner_capacity * self.p.split_at))
        full = list(self.touched)
        while full:
            me = full.pop()
            x = self.of[me]
            if len(x["kids"]) <= limit:
                continue
            for k in x["kids"]:
                if self.of[k]["c"] is None:
                    self._refresh(k)
            side = _two(np.stack([self.of[k]["c"] for k in x["kids"]]))
            other = [k for k, s in zip(x["kids"], side.tolist()) if s]
            x["kids"] = [k for k, s in zip(x["kids"], side.tolist()) if not s]
            if x["up"] is None:
                x["up"] = self.new(None, False, [me], x["shard"])
            twin = self.new(x["up"], False, other, x["shard"])
            up = self.of[x["up"]]["kids"]
            up.insert(up.index(me) + 1, twin)
            self.touched |= {me, twin, x["up"]}
            full += [me, twin, x["up"]]
        todo = set(self.touched)
        for me in self.touched:
            while (me := self.of[me]["up"]) is not None:
                todo.add(me)
        depth = self.depths()
        for me in sorted(todo, key=lambda k: -depth[k]):
            self._refresh(me)

    def _refresh(self, me: int) -> None:
        x = self.of[me]
        kids = [self.of[k] for k in x["kids"]]
        if x["leaf"] or not kids:
            return
        x["n"], x["sum"] = sum(k["n"] for k in kids), sum(k["sum"] for k in kids)
        x["c"] = np.mean([k["c"] for k in kids], axis=0) if self.p.inner_centroid == "children_mean" else x["sum"] / x["n"]
        x["r"] = max(float(np.sqrt(((k["c"] - x["c"]) ** 2).sum())) + k["r"] for k in kids)

    def depths(self) -> dict[int, int]:
        root = next(k for k, x in self.of.items() if x["up"] is None)
        out, todo = {root: 0}, [root]
        while todo:
            me = todo.pop()
            for k in self.of[me]["kids"]:
                out[k] = out[me] + 1
                todo.append(k)
        return out

    def rows(self) -> list[tuple]:
        """NODES in depth-first order; leaves keep their shard."""
        root = next(k for k, x in self.of.items() if x["up"] is None)
        out, todo = [], [(root, 0)]
        while todo:
            me, level = todo.pop()
            x = self.of[me]
            out.append((me, x["up"], level, x["leaf"], len(x["kids"]), int(x["n"]), x["sum"].tolist(), x["c"].tolist(), float(x["r"]), len(out), int(x["shard"])))
            todo += [(k, level + 1) for k in reversed(x["kids"])]
        return out


def _grafted(tree: BlockTree, placed: DataFrame, touched: DataFrame) -> BlockTree:
    """A new version in which the ``touched`` leaves (leaf_id) give way to those of ``placed``; all other rows stay where they are."""
    spark = tree.nodes.sparkSession
    parts: dict[int, list] = {}
    for r in sorted(_stats(placed).collect(), key=lambda r: r.leaf_path):  # leaves that received rows
        parts.setdefault(int(r.leaf_path.split(".")[1]), []).append(r)
    nodes, names = _Nodes(tree), []
    for old, own in parts.items():
        names += [(r.leaf_path, me) for r, me in zip(own, nodes.replace_leaf(old, own))]
    nodes.settle()
    table = nodes.rows()
    new = stored(spark.createDataFrame(table, NODES), "nodes")
    number = spark.createDataFrame(names, "leaf_path string, leaf_id long")
    order = ["shard", "leaf_id", "d_centroid", "vec_id"]
    fresh = stored(_locate(new, placed, number).repartitionByRange("leaf_id").sortWithinPartitions(*order), "rows")
    rows = tree.live_rows().join(F.broadcast(touched), "leaf_id", "left_anti").select(*fresh.columns).union(fresh)  # ids of touched leaves: fewer than nodes on the driver
    levels: dict[int, int] = {}
    for r in table:
        levels[r[2]] = levels.get(r[2], 0) + 1
    return replace(tree, nodes=new, rows=rows, levels=[levels[k] for k in sorted(levels)], n=next(r[5] for r in table if r[1] is None), version=tree.version + 1, deleted=None)


def changed_leaves(before: BlockTree, after: BlockTree) -> DataFrame:
    """(leaf_id): leaves of ``after`` that were written anew."""
    leaf = lambda t: t.nodes.where("is_leaf").select(F.col("node_id").alias("leaf_id"))
    return leaf(after).join(leaf(before), "leaf_id", "left_anti")


def insert(tree: BlockTree, df: DataFrame, split_at: float = 1.0) -> BlockTree:
    """A new version with the rows of (vec_id, v): each goes to the leaf a beam of one leads to.

    Leaves above ``split_at`` times their capacity split by 2-means; parents follow where
    they overflow.  Only leaves that receive rows are read and written, and only nodes above them
    change.  Where the nodes exceed DRIVER_BYTES, or rows were deleted, all leaves are written and all
    inner nodes made anew.
    """
    rows = df.select("vec_id", M.doubles("v").alias("v"))
    if tree.params.metric == "cosine":
        rows = rows.withColumn("v", M.normalized(F.col("v")))
    if not tree.levels:
        return replace(build(rows, tree.params), version=tree.version + 1)
    q = rows.select(F.col("vec_id").alias("query_id"), "v")
    goal = descend(tree, q, SearchParams(beam=1)).where("is_leaf").select(F.col("query_id").alias("vec_id"), F.col("node_id").alias("leaf_id"))
    arrived = stored(rows.join(goal, "vec_id").select("leaf_id", "vec_id", "v"), "inserted")
    touched = stored(arrived.select("leaf_id").distinct(), "touched")
    local = tree.deleted is None and sum(tree.levels) * tree.dim * 16 <= DRIVER_BYTES
    old = tree.live_rows().select("leaf_id", "vec_id", "v")
    every = (old.join(touched, "leaf_id", "left_semi") if local else old).unionByName(arrived)
    placed = stored(every.groupBy("leaf_id").applyInArrow(_split(tree.params.leaf_capacity, split_at), _PLACED), "placed")
    if not local:
        return _rebuilt(tree, placed, placed.count())
    return tree if touched.isEmpty() else _grafted(tree, placed, touched)


def insert_clusters(tree: BlockTree, clusters: DataFrame) -> BlockTree:
    """A new version with whole clusters (cluster, vec_id, v) as leaves of their own; larger ones are split."""
    offset = tree.nodes.agg((F.max("node_id") + 1).alias("m")).first().m or 0
    names = clusters.select("cluster").distinct().repartitionByRange("cluster").sortWithinPartitions("cluster")
    names = stored(names.select("cluster", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("i")), "names")
    ahead = names.groupBy("part").agg(F.count("*").alias("k"), F.min("i").alias("first"))
    ahead = ahead.select("part", (F.sum("k").over(Window.orderBy("part")) - F.col("k") - F.col("first")).alias("shift"))  # a row per task
    number = names.join(F.broadcast(ahead), "part").select("cluster", (F.col("i") + F.col("shift") + offset).alias("leaf_id"))
    own = clusters.join(number, "cluster").select("leaf_id", "vec_id", M.doubles("v").alias("v"))
    every = tree.live_rows().select("leaf_id", "vec_id", "v").unionByName(own)
    placed = stored(every.groupBy("leaf_id").applyInArrow(_split(tree.params.leaf_capacity, 1.0), _PLACED), "placed")
    return _rebuilt(tree, placed, placed.count())


def delete(tree: BlockTree, ids: DataFrame) -> BlockTree:
    """A new version whose reads leave out ``ids`` (vec_id): tombstones, no rewrite."""
    gone = ids.select("vec_id").distinct()
    gone = stored(gone if tree.deleted is None else gone.union(tree.deleted).distinct(), "deleted")
    return replace(tree, deleted=gone, version=tree.version + 1)


def compact(tree: BlockTree) -> BlockTree:
    """A new version without tombstones; leaves keep their rows."""
    placed = stored(tree.live_rows().groupBy("leaf_id").applyInArrow(_split(tree.params.leaf_capacity, 1.0), _PLACED), "placed")
    return _rebuilt(tree, placed, placed.count())


def lineage(before: DataFrame, after: DataFrame) -> DataFrame:
    """(old_leaf, new_leaf, n) from (vec_id, leaf) tables; null marks rows that were not there."""
    b = before.select("vec_id", F.col("leaf").alias("old_leaf"))
    a = after.select("vec_id", F.col("leaf").alias("new_leaf"))
    return b.join(a, "vec_id", "full").groupBy("old_leaf", "new_leaf").agg(F.count("*").alias("n"))
