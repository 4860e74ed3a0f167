"""The block tree: leaves hold vectors, inner nodes hold their children's centroids."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, DoubleType, StructField, StructType
from pyspark.sql.window import Window

from vecblock.functions import arrays as A
from vecblock.operators.partition import Hierarchy, PartitionParams, hierarchy, prefixes
from vecblock.sources.stored import delete, fresh_path, read_json, stored, write_json

#: Bytes of leaf centroids that the driver may hold while it grows the inner nodes.
DRIVER_BYTES = 256 << 20
#: Bytes of leaf names and numbers that a join may broadcast beside the rows, a name counted as 128.
NAME_BYTES = 32 << 20
NODES = "node_id long, parent_id long, level int, is_leaf boolean, n_children int, n_rows long, vec_sum array<double>, centroid array<double>, radius double, node_order long, shard int"
ROWS = "shard int, leaf_id long, cluster string, vec_id long, v array<double>, d_centroid double"


@dataclass(frozen=True)
class TreeParams:
    leaf_capacity: int = 64
    inner_capacity: int = 8
    pack: str = "subtree"
    how: str = "auto"  # 'grow' by insertion on the driver, up to DRIVER_BYTES of centroids, or 'pack', at any size; 'auto' grows where that is possible
    split_at: float = 1.0  # fill of an inner node, as a share of its capacity, at which it splits
    order: str = "dfs"
    inner_centroid: str = "weighted"
    metric: str = "l2"
    leaves_per_shard: int = 64
    partition: PartitionParams = field(default_factory=PartitionParams)

    def __post_init__(self):
        if self.partition.max_cluster_rows > self.leaf_capacity:
            raise ValueError("max_cluster_rows must not exceed leaf_capacity")


@dataclass
class BlockTree:
    """``nodes`` and ``rows`` of one index version; ``levels`` counts nodes from the root down."""

    nodes: DataFrame
    rows: DataFrame
    params: TreeParams
    levels: list[int]
    dim: int
    n: int
    version: int = 0
    deleted: DataFrame | None = None

    @property
    def height(self) -> int:
        return len(self.levels) - 1

    def live_rows(self) -> DataFrame:
        return self.rows if self.deleted is None else self.rows.join(self.deleted.select("vec_id"), "vec_id", "left_anti")


def cut(clusters: DataFrame, leaf_capacity: int, pack: str = "subtree") -> DataFrame:
    """(path, leaf_path): the leaf block of every final cluster.

    'subtree': the largest subtrees of at most ``leaf_capacity`` rows are one leaf
    each; 'cluster': every final cluster is its own leaf.
    """
    if pack == "cluster":
        return clusters.where("is_final").select("path", F.col("path").alias("leaf_path"))
    up = clusters.select(F.col("path").alias("parent_path"), F.col("n").alias("parent_n"))
    tops = clusters.join(up, "parent_path", "left").where((F.col("n") <= leaf_capacity) & (F.col("parent_n").isNull() | (F.col("parent_n") > leaf_capacity))).select(F.col("path").alias("leaf_path"))
    final = clusters.where("is_final").select("path", F.explode(prefixes()).alias("leaf_path"))
    return final.join(tops, "leaf_path").select("path", "leaf_path")


def _leaf_stats(t: pa.Table) -> pa.Table:
    x = A.matrix(t.column("v"))
    total = x.sum(0)
    center = total / len(x)
    radius = float(np.sqrt(((x - center) ** 2).sum(1)).max())
    return pa.table([pa.array([t.column("leaf_path")[0].as_py()]), pa.array([len(x)], pa.int64()), A.lists(total[None]), A.lists(center[None]), pa.array([radius])], names=["leaf_path", "n_rows", "vec_sum", "centroid", "radius"])


LEAVES = "kind int, leaf_path string, cluster string, vec_id long, v array<double>, d_centroid double, n_rows long, vec_sum array<double>, centroid array<double>, radius double"


#: Rows of neighbouring leaves that one call of ``_leaf_rows`` gets.
LEAF_ROWS = 4096


def _leaf_rows(t: pa.Table) -> pa.Table:
    """Of some whole leaves the statistics (kind 0) and the rows with their distance from the center (kind 1)."""
    t = t.combine_chunks()
    key = t.column("leaf_path").combine_chunks().dictionary_encode()
    order = np.argsort(key.indices.to_numpy(), kind="stable")
    at = key.indices.to_numpy()[order]
    t, first = t.take(pa.array(order)), np.flatnonzero(np.append(True, at[1:] != at[:-1]))
    x, n = A.matrix(t.column("v")), np.diff(np.append(first, len(t)))
    total = np.add.reduceat(x, first, axis=0)
    center = total / n[:, None]
    away = x - center[at]
    radius = np.maximum.reduceat(np.sqrt((away**2).sum(1)), first)
    head = pa.table({"leaf_path": key.dictionary, "n_rows": pa.array(n, pa.int64()), "vec_sum": A.lists(total), "centroid": A.lists(center), "radius": radius})
    body = t.select(["leaf_path", "path", "vec_id", "v"]).rename_columns(["leaf_path", "cluster", "vec_id", "v"]).append_column("d_centroid", pa.array(np.sqrt(sum(c * c for c in np.ascontiguousarray(away.T)))))
    parts = [y.append_column("kind", pa.array([k] * len(y), pa.int32())) for k, y in enumerate((head, body))]
    return pa.concat_tables(parts, promote_options="default").select([f.split(" ")[0] for f in LEAVES.split(", ")])


def _named(df: DataFrame, n: int) -> DataFrame:
    """``df`` of n names beside rows: broadcast up to NAME_BYTES."""
    return F.broadcast(df) if n * 128 <= NAME_BYTES else df


def _path_key(path: str) -> tuple:
    return tuple(int(x) for x in path.split(".")[1:])


class _Inner:
    """``means`` holds the children's centroids, with room for one child more than a node may keep."""

    __slots__ = ("children", "means", "total", "weight")

    def __init__(self, children, means, total, weight, room):
        self.children, self.total, self.weight = children, total, weight
        self.means = np.empty((room, len(total)))
        self.means[: len(means)] = means

    def mean(self):
        return self.total / max(self.weight, 1e-300)

    def nearest(self, c) -> int:
        d = self.means[: len(self.children)] - c
        return int((d * d).sum(1).argmin())


def _two(x: np.ndarray) -> np.ndarray:
    """Two groups by 2-means from the farthest pair of a first row; halves if one side stays empty."""
    a = int(((x - x.mean(0)) ** 2).sum(1).argmax())
    b = int(((x - x[a]) ** 2).sum(1).argmax())
    centers, last = np.stack([x[a], x[b]]), None
    for _ in range(8):
        at = A.nearest(x, centers)
        if at.min() == at.max():
            return np.arange(len(x)) >= len(x) // 2
        if last is not None and (at == last).all():  # nothing moves any more
            return at == 1
        last = at
        centers = np.stack([x[at == c].mean(0) for c in (0, 1)])
    return A.nearest(x, centers) == 1


def grow(centroids: np.ndarray, weights: np.ndarray, capacity: int, split_at: float = 1.0) -> list[list[list[int]]]:
    """Insert leaves one by one below the nearest inner node; full nodes split in two, the root alone adds levels.

    Returns, from the lowest inner level up, lists of child numbers per node.
    """
    limit = max(2, int(capacity * split_at))
    room, dim = limit + 2, centroids.shape[1]
    root = _Inner([], np.empty((0, dim)), np.zeros(dim), 0.0, room)
    height = 1
    for leaf in range(len(centroids)):
        c, w = centroids[leaf], float(weights[leaf])
        path, places = [root], []
        for _ in range(height - 1):
            places.append(path[-1].nearest(c))
            path.append(path[-1].children[places[-1]])
        for depth, node in enumerate(path):
            node.total, node.weight = node.total + w * c, node.weight + w
            if depth:
                path[depth - 1].means[places[depth - 1]] = node.mean()
        path[-1].means[len(path[-1].children)] = c
        path[-1].children.append(leaf)
        for depth in range(len(path) - 1, -1, -1):
            node = path[depth]
            n = len(node.children)
            if n <= limit:
                break
            side = _two(node.means[:n])
            parts = []
            for s in (False, True):
                kids, means = [k for k, z in zip(node.children, side.tolist()) if z == s], node.means[:n][side == s]
                ws = [float(weights[k]) if isinstance(k, int) else k.weight for k in kids]
                parts.append(_Inner(kids, means, sum(m * x for m, x in zip(means, ws)), sum(ws), room))
            if depth:
                up, at = path[depth - 1], places[depth - 1]
                more = len(up.children)
                up.means[at + 2 : more + 1] = up.means[at + 1 : more].copy()
                up.means[at], up.means[at + 1] = parts[0].mean(), parts[1].mean()
                up.children[at : at + 1] = parts
            else:
                root = _Inner(parts, [p.mean() for p in parts], node.total, node.weight, room)
                height += 1
    levels: list[list[list[int]]] = []

    def number(node: _Inner, h: int) -> int:
        while len(levels) < h:
            levels.append([])
        kids = [k if isinstance(k, int) else number(k, h - 1) for k in node.children]
        levels[h - 1].append(kids)
        return len(levels[h - 1]) - 1

    number(root, height)
    return levels


def packed(m: int, capacity: int) -> list[list[list[int]]]:
    """Bottom-up packing in the given order: equal groups of at most ``capacity`` children."""
    levels = []
    n = m
    while True:
        groups = max(1, -(-n // capacity))
        edge = [round(i * n / groups) for i in range(groups + 1)]
        levels.append([list(range(a, b)) for a, b in zip(edge, edge[1:])])
        n = groups
        if n == 1:
            return levels


def assemble(leaves: list, params: TreeParams) -> tuple[list[tuple], dict[str, int]]:
    """Node rows (NODES without shard) and the number of each leaf path, from leaf statistics."""
    leaves = sorted(leaves, key=lambda r: _path_key(r.leaf_path))
    cents, weights = np.array([r.centroid for r in leaves]), np.array([r.n_rows for r in leaves], np.float64)
    levels = grow(cents, weights, params.inner_capacity, params.split_at) if params.how != "pack" else packed(len(leaves), params.inner_capacity)
    height = len(levels)
    total = [np.array([r.vec_sum for r in leaves])]
    count, center, radius = [weights.copy()], [cents], [np.array([r.radius for r in leaves])]
    for groups in levels:
        t, n, c, r = total[-1], count[-1], center[-1], radius[-1]
        total.append(np.array([t[g].sum(0) for g in groups]))
        count.append(np.array([n[g].sum() for g in groups]))
        center.append(np.array([c[g].mean(0) for g in groups]) if params.inner_centroid == "children_mean" else total[-1] / count[-1][:, None])
        radius.append(np.array([(np.sqrt(((c[g] - center[-1][i]) ** 2).sum(1)) + r[g]).max() for i, g in enumerate(groups)]))
    # ids in depth-first order, so a subtree is a range
    ids = [np.full(len(x), -1, np.int64) for x in count]
    order: list[tuple[int, int, int | None]] = []
    stack = [(height, 0, None)]
    while stack:
        h, i, up = stack.pop()
        ids[h][i] = len(order)
        order.append((h, i, up))
        if h:
            stack += [(h - 1, k, len(order) - 1) for k in reversed(levels[h - 1][i])]
    position = _positions(order, height, params)
    rows = []
    for me, (h, i, up) in enumerate(order):
        kids = len(levels[h - 1][i]) if h else 0
        rows.append((me, up, height - h, h == 0, kids, int(count[h][i]), total[h][i].tolist(), center[h][i].tolist(), float(radius[h][i]), int(position[me])))
    return rows, {r.leaf_path: int(ids[0][k]) for k, r in enumerate(leaves)}


def _positions(order, height: int, params: TreeParams) -> np.ndarray:
    """Place of every node on disk: depth first, breadth first or (as a control) random."""
    n = len(order)
    if params.order == "dfs":
        return np.arange(n)
    key = np.array([height - h for h, _, _ in order]) if params.order == "bfs" else A.uniform(np.arange(n), params.partition.seed, 5)
    out = np.empty(n, np.int64)
    out[np.argsort(key, kind="stable")] = np.arange(n)
    return out


def _locate(nodes: DataFrame, members: DataFrame, leaf_of: DataFrame) -> DataFrame:
    """ROWS from members with their leaf path."""
    spot = nodes.where("is_leaf").select(F.col("node_id").alias("leaf_id"), "shard", F.col("centroid").alias("c"))
    d = F.sqrt(F.aggregate(F.zip_with("v", "c", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    return members.join(leaf_of, "leaf_path").join(spot, "leaf_id").select("shard", "leaf_id", F.col("path").alias("cluster"), "vec_id", "v", d.alias("d_centroid"))


def build(df: DataFrame, params: TreeParams = TreeParams(), parts: Hierarchy | None = None) -> BlockTree:
    """Cluster, cut into leaves, grow the inner nodes, and lay the rows out in leaf order."""
    spark = df.sparkSession
    if params.metric == "cosine":
        from vecblock.functions import metrics as M

        df = df.withColumn("v", M.normalized(M.doubles("v")))
    h = parts or hierarchy(df, params.partition)
    leaf_of_cluster = cut(h.clusters, params.leaf_capacity, params.pack)
    size = h.clusters.where("is_final").agg(F.count("*").alias("k"), F.sum("n").alias("n")).first()
    some = F.pmod(F.xxhash64("leaf_path"), F.lit(max(1, (size.n or 0) // LEAF_ROWS))).alias("some")
    leaves = h.members.join(_named(leaf_of_cluster, size.k), "path").select("path", "vec_id", "v", "leaf_path", some)
    leaves = stored(leaves.groupBy("some").applyInArrow(_leaf_rows, LEAVES), "leaves")
    stats = leaves.where("kind = 0").select("leaf_path", "n_rows", "vec_sum", "centroid", "radius")
    members = leaves.where("kind = 1").select("leaf_path", "cluster", "vec_id", "v", "d_centroid")
    head = stats.agg(F.count("*").alias("m"), F.max(F.size("centroid")).alias("dim"), F.sum("n_rows").alias("n")).first()
    if not head.m:
        return BlockTree(spark.createDataFrame([], NODES), spark.createDataFrame([], ROWS), params, [], 0, 0)
    if head.m * head.dim * 16 > DRIVER_BYTES:
        nodes, names = _assemble_wide(_packable(stats, params), params)
    else:
        rows, number = assemble(stats.collect(), params)  # checked against DRIVER_BYTES
        shard = {me: pos // params.leaves_per_shard for me, *_, pos in rows}
        nodes = spark.createDataFrame(_node_table([(*r, int(shard[r[0]])) for r in rows]), NODES)
        names = spark.createDataFrame(pa.table({"leaf_path": pa.array(list(number), pa.string()), "leaf_id": pa.array(list(number.values()), pa.int64())}), "leaf_path string, leaf_id long")
    nodes = stored(nodes, "nodes")
    spot = names.join(nodes.where("is_leaf").select(F.col("node_id").alias("leaf_id"), "shard"), "leaf_id")
    return _laid_out(nodes, members.join(_named(spot, head.m), "leaf_path"), params, head.dim, head.n)


def _node_table(rows: list[tuple]) -> pa.Table:
    """NODES as an Arrow table."""
    kinds = {"long": pa.int64(), "int": pa.int32(), "boolean": pa.bool_(), "double": pa.float64()}
    names = [f.split(" ") for f in NODES.split(", ")]
    return pa.table({name: A.lists(np.array(c)) if kind == "array<double>" else pa.array(c, kinds[kind]) for (name, kind), c in zip(names, zip(*rows))})


def with_metric(tree: BlockTree, metric: str) -> BlockTree:
    """The same blocks searched by another metric; only cosine clusters and stores other vectors."""
    if metric != tree.params.metric and "cosine" in (metric, tree.params.metric):
        raise ValueError(f"a tree for {tree.params.metric} holds other vectors than one for {metric}")
    return replace(tree, params=replace(tree.params, metric=metric))


def _laid_out(nodes: DataFrame, rows: DataFrame, params: TreeParams, dim: int, n: int, version: int = 0, deleted: DataFrame | None = None) -> BlockTree:
    spark = nodes.sparkSession
    path = fresh_path(spark, "rows")
    levels = [r.n for r in nodes.groupBy("level").agg(F.count("*").alias("n")).orderBy("level").collect()]
    place = _named(nodes.select(F.col("node_id").alias("leaf_id"), "node_order"), sum(levels))
    laid = rows.join(place, "leaf_id").repartitionByRange("node_order").sortWithinPartitions("node_order", "d_centroid", "vec_id").drop("node_order")
    laid.select(*[f.split(" ")[0] for f in ROWS.split(", ")]).write.parquet(path)
    return BlockTree(nodes, spark.read.schema(ROWS).parquet(path), params, levels, dim, n, version, deleted)


def _packable(stats: DataFrame, params: TreeParams) -> DataFrame:
    if params.how == "grow":
        raise ValueError("growing inner nodes holds all leaf centroids on the driver, and they exceed DRIVER_BYTES: build with how='pack'")
    return stats


def _assemble_wide(stats: DataFrame, params: TreeParams) -> tuple[DataFrame, DataFrame]:
    """Bottom-up packing without the driver: number the leaves by path, group each level by capacity."""
    from vecblock.functions import metrics as M

    key = F.array_join(F.transform(F.split("leaf_path", r"\."), lambda x: F.lpad(x, 6, "0")), ".")
    spread = stored(stats.withColumn("key", key).repartitionByRange("key").withColumn("part", F.spark_partition_id()), "numbered")
    before = spread.groupBy("part").agg(F.count("*").alias("k"))
    before = before.select("part", (F.sum("k").over(Window.orderBy("part")) - F.col("k")).alias("ahead"))  # a row per task
    level = spread.join(F.broadcast(before), "part").withColumn("pos", F.col("ahead") + F.row_number().over(Window.partitionBy("part").orderBy("key")) - 1)
    level = stored(level.select("leaf_path", "pos", "n_rows", "vec_sum", "centroid", "radius"), "level")
    names = level.select("leaf_path", F.col("pos").alias("leaf_id"))
    made, base, depth = [], 0, 0
    now = level.select(F.col("pos").alias("node_id"), "pos", "n_rows", "vec_sum", "centroid", "radius", F.lit(0).alias("n_children"))
    n = now.count()
    while True:
        top = n == 1 and depth > 0
        base_next = base + n
        parent = F.lit(None).cast("long") if top else (F.col("pos") / params.inner_capacity).cast("long") + base_next
        made.append(now.select("node_id", parent.alias("parent_id"), F.lit(depth).alias("h"), "n_children", "n_rows", "vec_sum", "centroid", "radius"))
        if top:
            break
        group = now.withColumn("g", (F.col("pos") / params.inner_capacity).cast("long"))
        total = M.vector_sum(group, ["g"], "vec_sum").join(group.groupBy("g").agg(F.sum("n_rows").alias("n_rows"), F.count("*").cast("int").alias("n_children")), "g")
        total = total.withColumn("centroid", F.transform("vec_sum", lambda x: x / F.col("n_rows")))
        far = group.select("g", F.col("centroid").alias("c"), F.col("radius").alias("r")).join(total.select("g", "centroid"), "g")
        far = far.groupBy("g").agg(F.max(M.l2(F.col("c"), F.col("centroid")) + F.col("r")).alias("radius"))
        now = stored(total.join(far, "g").select((F.col("g") + base_next).alias("node_id"), F.col("g").alias("pos"), "n_rows", "vec_sum", "centroid", "radius", "n_children"), "level")
        base, depth, n = base_next, depth + 1, now.count()
    every = made[0]
    for m in made[1:]:
        every = every.union(m)
    nodes = every.select("node_id", "parent_id", (F.lit(depth) - F.col("h")).cast("int").alias("level"), (F.col("h") == 0).alias("is_leaf"), "n_children", "n_rows", "vec_sum", "centroid", "radius", F.col("node_id").alias("node_order"), (F.col("node_id") / params.leaves_per_shard).cast("int").alias("shard"))
    return nodes, names


# --- reading the tree ----------------------------------------------------------


def leaf_chain(tree: BlockTree) -> DataFrame:
    """(leaf_id, prev_leaf, next_leaf) in disk order; the window runs inside shards and their borders."""
    leaves = tree.nodes.where("is_leaf").select(F.col("node_id").alias("leaf_id"), "node_order", "shard")
    return chain(leaves)


def chain(leaves: DataFrame) -> DataFrame:
    w = Window.orderBy("node_order")
    return leaves.select("leaf_id", F.lag("leaf_id").over(w).alias("prev_leaf"), F.lead("leaf_id").over(w).alias("next_leaf"))


def subtree(nodes: DataFrame, root: int, max_depth: int = 64) -> DataFrame:
    """(node_id, depth) below and including a node, level by level."""
    spark = nodes.sparkSession
    now = spark.createDataFrame([(root, 0)], "node_id long, depth int")
    out = now
    edges = nodes.select(F.col("node_id").alias("child"), F.col("parent_id").alias("up"))
    for depth in range(1, max_depth):
        now = stored(now.join(edges, now.node_id == edges.up).select(F.col("child").alias("node_id"), F.lit(depth).alias("depth")), "below")
        if now.isEmpty():
            break
        out = out.union(now)
    return out


def ancestors(nodes: DataFrame, node: int) -> DataFrame:
    up = {r.node_id: r.parent_id for r in nodes.where("NOT is_leaf").select("node_id", "parent_id").collect()} if nodes.where("NOT is_leaf").count() <= 1_000_000 else None
    if up is None:
        raise ValueError("too many inner nodes for a local walk; join level by level instead")
    first = nodes.where(F.col("node_id") == node).select("parent_id").first()
    out, at, depth = [], first.parent_id if first else None, 1
    while at is not None:
        out.append((at, depth))
        at, depth = up.get(at), depth + 1
    return nodes.sparkSession.createDataFrame(out, "node_id long, distance int")


def invariants(tree: BlockTree) -> DataFrame:
    """(check, violations): all zero for a sound tree."""
    p, nodes, rows = tree.params, tree.nodes, tree.rows
    leaf = nodes.where("is_leaf")
    kids = nodes.where("parent_id IS NOT NULL").groupBy(F.col("parent_id").alias("up")).agg(F.count("*").alias("k"), F.sum("n_rows").alias("r"), F.min("node_order").alias("lo"), F.max("node_order").alias("hi"))
    inner = nodes.where("NOT is_leaf").join(kids, F.col("node_id") == F.col("up"), "left")
    held = rows.groupBy("leaf_id").agg(F.count("*").alias("k"))
    checks = {
        "one_root": nodes.where("parent_id IS NULL").count() != (1 if tree.n else 0),
        "leaf_depths": max(0, leaf.select("level").distinct().count() - 1),
        "inner_capacity": inner.where(F.col("k") > p.inner_capacity).count(),
        "leaf_capacity": leaf.where(F.col("n_rows") > p.leaf_capacity).count(),
        "child_rows": inner.where(F.col("r") != F.col("n_rows")).count(),
        "leaf_rows": leaf.join(held, F.col("node_id") == F.col("leaf_id"), "left").where(F.coalesce("k", F.lit(0)) != F.col("n_rows")).count(),
        "each_vector_once": rows.groupBy("vec_id").count().where("count <> 1").count() + abs(rows.count() - tree.n),
        "rows_inside_radius": rows.join(leaf.select("node_id", "radius"), F.col("leaf_id") == F.col("node_id")).where(F.col("d_centroid") > F.col("radius") + 1e-9).count(),
    }
    return nodes.sparkSession.createDataFrame([(k, int(v)) for k, v in checks.items()], "check string, violations long")


def balance(nodes: DataFrame) -> DataFrame:
    """Height, leaf fill and children per node."""
    leaf = nodes.agg(F.max("level").alias("height"), F.count(F.when(F.col("is_leaf"), 1)).alias("leaves"), F.min(F.when(F.col("is_leaf"), F.col("n_rows"))).alias("fill_min"), F.avg(F.when(F.col("is_leaf"), F.col("n_rows"))).alias("fill_avg"), F.max(F.when(F.col("is_leaf"), F.col("n_rows"))).alias("fill_max"), F.max("n_children").alias("children_max"))
    return leaf


# --- versions on disk -----------------------------------------------------------


def refresh_centroids(tree: BlockTree) -> BlockTree:
    """Sums, centroids and radii of all nodes from the rows that are alive, bottom up; ids and shape stay."""
    from vecblock.functions import metrics as M

    def far(rows: DataFrame, to: DataFrame, key: str, center: str, extra) -> DataFrame:
        both = rows.join(to.select(F.col("node_id").alias(key), F.col("centroid").alias("c")), key)
        return both.groupBy(key).agg(F.max(M.l2(F.col(center), F.col("c")) + extra).alias("radius"))

    live = tree.live_rows().select("leaf_id", "v")
    fixed = tree.nodes.drop("n_rows", "vec_sum", "centroid", "radius")
    total = M.vector_sum(live, ["leaf_id"]).join(live.groupBy("leaf_id").agg(F.count("*").alias("n_rows")), "leaf_id")
    now = total.select(F.col("leaf_id").alias("node_id"), "n_rows", F.col("v").alias("vec_sum"), F.transform("v", lambda x: x / F.col("n_rows")).alias("centroid"))
    now = stored(now.join(far(live, now, "leaf_id", "v", F.lit(0.0)).withColumnRenamed("leaf_id", "node_id"), "node_id"), "level")
    made = [now]
    for level in range(tree.height - 1, -1, -1):
        up = tree.nodes.where(F.col("level") == level + 1).select("node_id", F.col("parent_id").alias("up"))
        kids = now.join(up, "node_id")
        total = M.vector_sum(kids, ["up"], "vec_sum").join(kids.groupBy("up").agg(F.sum("n_rows").alias("n_rows")), "up")
        above = total.select(F.col("up").alias("node_id"), "n_rows", "vec_sum", F.transform("vec_sum", lambda x: x / F.col("n_rows")).alias("centroid"))
        reach = far(kids.select("up", "centroid", F.col("radius").alias("r")), above, "up", "centroid", F.col("r"))
        now = stored(above.join(reach.withColumnRenamed("up", "node_id"), "node_id"), "level")
        made.append(now)
    every = made[0]
    for m in made[1:]:
        every = every.unionByName(m)
    nodes = fixed.join(every, "node_id").select(*tree.nodes.columns)
    return replace(tree, nodes=stored(nodes, "nodes"), version=tree.version + 1)


def save(tree: BlockTree, path: str, store_dtype: str = "double", links: DataFrame | None = None) -> str:
    """Write a version: data first, its manifest last; a reader sees whole versions only.

    'float16' and 'int8' store vectors small; readers re-score in double what they decode.
    ``links`` (src, dst, dist, src_leaf, dst_leaf) are optional, sorted by their source's leaf.
    """
    spark = tree.nodes.sparkSession
    base = f"{path}/v{tree.version:06d}"
    tree.nodes.write.parquet(f"{base}/nodes")
    place = _named(tree.nodes.select(F.col("node_id").alias("leaf_id"), "node_order"), sum(tree.levels))
    rows = tree.live_rows().join(place, "leaf_id").repartitionByRange("shard", "node_order").sortWithinPartitions("shard", "node_order", "d_centroid", "vec_id").drop("node_order")
    encode(rows, store_dtype).write.partitionBy("shard").parquet(f"{base}/rows")
    if links is not None:
        links.repartitionByRange("src_leaf").sortWithinPartitions("src_leaf", "src", "dist", "dst").write.parquet(f"{base}/links")
    params = asdict(tree.params)
    n = tree.live_rows().count() if tree.deleted is not None else tree.n
    write_json(spark, {"version": tree.version, "dim": tree.dim, "n": n, "levels": tree.levels, "params": params, "dtype": store_dtype, "links": links is not None}, f"{base}/manifest")
    return base


def encode(rows: DataFrame, dtype: str) -> DataFrame:
    if dtype == "double":
        return rows
    if dtype == "int8":  # one scale per vector
        scale = F.greatest(F.array_max(F.transform("v", lambda x: F.abs(x))) / 127.0, F.lit(1e-300))
        return rows.withColumn("scale", scale).withColumn("v", F.transform("v", lambda x: F.round(x / F.col("scale")).cast("tinyint")))
    if dtype == "float16":
        return _recoded(rows, BinaryType(), _to_half)
    raise ValueError(f"unknown storage type {dtype}")


def decode(rows: DataFrame, dtype: str) -> DataFrame:
    if dtype == "double":
        return rows
    if dtype == "int8":
        return rows.withColumn("v", F.transform("v", lambda x: x * F.col("scale"))).drop("scale")
    return _recoded(rows, ArrayType(DoubleType()), _from_half)


def _to_half(col: pa.Array) -> pa.Array:
    half = np.ascontiguousarray(A.matrix(col).astype(np.float16))
    off = np.arange(len(col) + 1, dtype=np.int32) * (half.shape[1] * 2)
    return pa.Array.from_buffers(pa.binary(), len(col), [None, pa.py_buffer(off), pa.py_buffer(half)])


def _from_half(col: pa.Array) -> pa.Array:
    off = np.frombuffer(col.buffers()[1], np.int32, len(col) + 1, 4 * col.offset)
    flat = np.frombuffer(col.buffers()[2], np.uint8)[off[0] : off[-1]].view(np.float16)
    return A.lists(flat.astype(np.float64).reshape(len(col), -1)) if len(col) else pa.array([], pa.list_(pa.float64()))


def _recoded(rows: DataFrame, kind, f) -> DataFrame:
    """Column v by a kernel over whole Arrow batches."""
    schema = StructType([StructField("v", kind) if x.name == "v" else x for x in rows.schema.fields])

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([f(c) if name == "v" else c for name, c in zip(b.schema.names, b.columns)], names=b.schema.names)

    return rows.mapInArrow(run, schema)


def versions(spark: SparkSession, path: str) -> list[int]:
    fs_path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = fs_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    names = [s.getPath().getName() for s in fs.listStatus(fs_path)]
    jp = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    return sorted(int(n[1:]) for n in names if n.startswith("v") and fs.exists(jp(f"{path}/{n}/manifest/_SUCCESS")))


def open_tree(spark: SparkSession, path: str, version: int | None = None) -> BlockTree:
    version = versions(spark, path)[-1] if version is None else version
    base = f"{path}/v{version:06d}"
    m = read_json(spark, f"{base}/manifest")
    raw = m["params"]
    params = TreeParams(**{**raw, "partition": PartitionParams(**raw["partition"])})
    rows = decode(spark.read.parquet(f"{base}/rows"), m["dtype"]).select(*[f.split(" ")[0] for f in ROWS.split(", ")])
    return BlockTree(spark.read.schema(NODES).parquet(f"{base}/nodes"), rows, params, m["levels"], m["dim"], m["n"], version)


def open_links(spark: SparkSession, path: str, version: int | None = None) -> DataFrame | None:
    """The links saved with a version, or None."""
    version = versions(spark, path)[-1] if version is None else version
    base = f"{path}/v{version:06d}"
    return spark.read.parquet(f"{base}/links") if read_json(spark, f"{base}/manifest").get("links") else None


def vacuum(spark: SparkSession, path: str, keep: int = 2) -> list[int]:
    """Remove all but the newest ``keep`` versions."""
    old = versions(spark, path)[:-keep] if keep else []
    for v in old:
        delete(spark, f"{path}/v{v:06d}")
    return old


def describe(tree: BlockTree) -> dict:
    return {"version": tree.version, "n": tree.n, "dim": tree.dim, "levels": tree.levels, "params": json.loads(json.dumps(asdict(tree.params)))}


def with_params(tree: BlockTree, **changes) -> BlockTree:
    return replace(tree, params=replace(tree.params, **changes))


def pin(tree: BlockTree, fraction: float = 1.0) -> BlockTree:
    """Keep the leading ``fraction`` of the shards in memory (spilling to disk); the rest stays on disk.

    Answers do not depend on it.  Inner levels are broadcast by each search anyway.
    """
    from pyspark import StorageLevel

    top = tree.nodes.agg((F.max("shard") + 1).alias("n")).first().n or 0
    edge = int(round(top * fraction))
    if edge <= 0:
        return tree
    hot = tree.rows.where(F.col("shard") < edge).persist(StorageLevel.MEMORY_AND_DISK)
    return replace(tree, rows=hot.unionByName(tree.rows.where(F.col("shard") >= edge)))
