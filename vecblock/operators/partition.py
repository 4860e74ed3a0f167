"""Recursive partition of a collection by K-Means.

Parts larger than ``local_rows`` are clustered by passes over the whole
collection: centers start from a bounded sample of each part and are refined on
all rows, with only sums crossing the network.  Smaller parts finish inside one
task.  Every part is named by its path of child numbers, "r.3.0", and the whole
hierarchy is kept.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecblock.functions import arrays as A
from vecblock.functions import metrics as M
from vecblock.sources.stored import stored

ROOT = "r"


@dataclass(frozen=True)
class PartitionParams:
    max_cluster_rows: int = 64
    fanout: int = 8
    lloyd_iters: int = 10
    init: str = "d2"
    seed: int = 42
    max_depth: int | None = None
    local_rows: int = 200_000
    sample_rows: int = 50_000
    on_empty: str = "drop"  # or 'farthest': an empty cluster begins anew at the row farthest from its center


@dataclass
class Hierarchy:
    """``clusters``: path, parent_path, level, n, is_final, degenerate; ``members``: vec_id, path, v."""

    clusters: DataFrame
    members: DataFrame


_MEMBER = "vec_id long, path string, v array<double>"
_PART = "kind int, path string, vec_id long, v array<double>, n long, is_final boolean, degenerate boolean"


def assign(df: DataFrame, centers: np.ndarray) -> DataFrame:
    """(vec_id, v, cluster): nearest center of each row; ``centers`` are few and broadcast."""
    held = df.sparkSession.sparkContext.broadcast(centers)

    def run(batches):
        for b in batches:
            x = A.matrix(b.column("v"))
            at = A.nearest(x, held.value) if len(x) else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), b.column("v"), pa.array(at)], names=["vec_id", "v", "cluster"])

    return df.select("vec_id", M.doubles("v").alias("v")).mapInArrow(run, "vec_id long, v array<double>, cluster long")


def lloyd_round(df: DataFrame, centers: DataFrame) -> DataFrame:
    """One round as a plain DataFrame plan: (pos, n, v) new centers from (pos, v); ties go to the lower pos."""
    c = centers.select(F.col("pos").cast("int").alias("pos"), F.col("v").alias("c"))
    pairs = df.select("vec_id", "v").join(F.broadcast(c), how="cross")  # the few centers beside every row
    near = pairs.groupBy("vec_id").agg(F.min_by(F.struct("pos", "v"), F.struct(M.l2_sq(F.col("v"), F.col("c")), F.col("pos"))).alias("b")).select("b.pos", "b.v")
    return near.groupBy("pos").agg(F.count("*").alias("n")).join(M.centroid(near, ["pos"]).withColumnRenamed("pos", "at"), F.col("pos") == F.col("at")).drop("at")


def kmeans(df: DataFrame, centers: DataFrame, iters: int) -> DataFrame:
    """Lloyd refinement with summed partial results; (pos, n, v)."""
    now = np.array([r.v for r in centers.orderBy("pos").collect()])  # k centers
    n = np.zeros(len(now), np.int64)
    for _ in range(iters):
        got = _sums(df.withColumn("path", F.lit(ROOT)), {ROOT: now})
        n, old = np.zeros(len(now), np.int64), now
        now = old.copy()
        for _, c, count, total in got:
            n[c], now[c] = count, np.array(total) / count
        if np.array_equal(now, old):
            break
    rows = [(i, int(n[i]), now[i].tolist()) for i in range(len(now))]
    return df.sparkSession.createDataFrame(rows, "pos int, n long, v array<double>")


def inertia(df: DataFrame, centers: DataFrame) -> float:
    """Sum of squared distances to the nearest center."""
    c = np.array([r.v for r in centers.orderBy("pos").collect()])
    at = assign(df, c)
    mine = F.element_at(F.array(*[F.array(*[F.lit(float(x)) for x in row]) for row in c]), (F.col("cluster") + 1).cast("int"))
    return float(at.agg(F.sum(M.l2_sq(F.col("v"), mine))).first()[0] or 0.0)


def _sums(df: DataFrame, centers: dict[str, np.ndarray]) -> list[tuple[str, int, int, list[float]]]:
    """(path, cluster, n, vector sum) over all parts in ``centers``."""
    held = df.sparkSession.sparkContext.broadcast(centers)

    def run(batches):
        total: dict[tuple[str, int], list] = {}
        for b in batches:
            x = A.matrix(b.column("v"))
            paths = np.array(b.column("path").to_pylist(), dtype=object)
            for p in set(paths.tolist()):
                rows = x[paths == p]
                at = A.nearest(rows, held.value[p])
                for c in np.unique(at).tolist():
                    part = rows[at == c]
                    got = total.setdefault((p, c), [0, 0.0])
                    got[0] += len(part)
                    got[1] = got[1] + part.sum(0)
        keys, task = list(total), TaskContext.get().partitionId()
        yield pa.RecordBatch.from_arrays(
            [pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.int32()), pa.array([task] * len(keys), pa.int32()), pa.array([total[k][0] for k in keys], pa.int64()), pa.array([total[k][1].tolist() for k in keys], pa.list_(pa.float64()))],
            names=["path", "cluster", "task", "n", "v"],
        )

    def add(t: pa.Table) -> pa.Table:
        t = t.sort_by("task")
        return pa.table({"path": t.column("path")[:1], "cluster": t.column("cluster")[:1], "n": pa.array([t.column("n").to_numpy().sum()], pa.int64()), "v": A.lists(A.matrix(t.column("v")).sum(0)[None])})

    part = df.select("path", M.doubles("v").alias("v")).mapInArrow(run, "path string, cluster int, task int, n long, v array<double>")
    done = part.groupBy("path", "cluster").applyInArrow(add, "path string, cluster int, n long, v array<double>")  # one pass over the rows
    return [(r.path, r.cluster, r.n, r.v) for r in done.collect()]  # parts x fanout rows


def _open_level(rows: DataFrame, big: dict[str, int], p: PartitionParams) -> DataFrame:
    """Split every part in ``big`` once, over the whole cluster."""
    spark = rows.sparkSession
    share = {k: min(1.0, p.sample_rows / n) for k, n in big.items()}
    held_share = spark.sparkContext.broadcast(share)

    def sample(batches):
        for b in batches:
            rate = np.array([held_share.value.get(x, 0.0) for x in b.column("path").to_pylist()])
            keep = A.uniform(b.column("vec_id").to_numpy(), p.seed, 99) < rate
            yield b.filter(pa.array(keep))

    def start(t: pa.Table) -> pa.Table:
        x, ids = A.matrix(t.column("v")), t.column("vec_id").to_numpy()
        _, centers = A.kmeans(x, ids, p.fanout, p.lloyd_iters, p.init, p.seed, p.on_empty)
        return pa.table({"path": pa.array([t.column("path")[0].as_py()] * len(centers)), "v": A.lists(centers)})

    sampled = rows.mapInArrow(sample, _MEMBER).groupBy("path").applyInArrow(start, "path string, v array<double>")
    centers: dict[str, list] = {}
    for r in sampled.collect():  # parts x fanout centers
        centers.setdefault(r.path, []).append(r.v)
    now = {k: np.array(sorted(v)) for k, v in centers.items()}
    target = rows.where(F.col("path").isin(list(big))) if len(big) < 1000 else rows.join(F.broadcast(spark.createDataFrame([(k,) for k in big], "path string")), "path", "left_semi")
    for _ in range(p.lloyd_iters):
        new = {k: v.copy() for k, v in now.items()}
        for path, c, n, total in _sums(target, now):
            new[path][c] = np.array(total) / n
        same = all(np.array_equal(new[k], now[k]) for k in now)
        now = new
        if same:
            break
    held = spark.sparkContext.broadcast(now)

    def name(batches):
        for b in batches:
            paths = b.column("path").to_pylist()
            x = A.matrix(b.column("v"))
            arr = np.array(paths, dtype=object)
            for q in set(paths) & held.value.keys():
                at = np.flatnonzero(arr == q)
                for i, c in zip(at.tolist(), A.nearest(x[at], held.value[q]).tolist()):
                    paths[i] = f"{q}.{c}"
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), pa.array(paths, pa.string()), b.column("v")], names=["vec_id", "path", "v"])

    return rows.mapInArrow(name, _MEMBER)


def _finish(p: PartitionParams):
    def run(t: pa.Table) -> pa.Table:
        path = t.column("path")[0].as_py()
        x, ids = A.matrix(t.column("v")), t.column("vec_id").to_numpy()
        depth = None if p.max_depth is None else max(0, p.max_depth - path.count("."))
        pieces, parts = A.split_all(x, ids, path, p.max_cluster_rows, p.fanout, p.lloyd_iters, p.init, p.seed, depth, p.on_empty)
        n = len(parts)
        none = pa.nulls(n, pa.list_(pa.float64()))
        head = pa.table([pa.array([0] * n, pa.int32()), pa.array([q[0] for q in parts], pa.string()), pa.nulls(n, pa.int64()), none, pa.array([q[1] for q in parts], pa.int64()), pa.array([q[2] for q in parts], pa.bool_()), pa.array([q[3] for q in parts], pa.bool_())], names=["kind", "path", "vec_id", "v", "n", "is_final", "degenerate"])
        order = np.concatenate([r for _, r, _ in pieces])
        names = [q for q, r, _ in pieces for _ in range(len(r))]
        m = len(order)
        body = pa.table([pa.array([1] * m, pa.int32()), pa.array(names, pa.string()), pa.array(ids[order], pa.int64()), A.lists(x[order]), pa.nulls(m, pa.int64()), pa.nulls(m, pa.bool_()), pa.nulls(m, pa.bool_())], names=head.column_names)
        return pa.concat_tables([head, body])

    return run


def hierarchy(df: DataFrame, params: PartitionParams = PartitionParams()) -> Hierarchy:
    p = params
    rows = df.select("vec_id", F.lit(ROOT).alias("path"), M.doubles("v").alias("v"))
    upper: list[tuple[str, int]] = []
    seen: set[str] = set()
    while True:
        sizes = {r.path: r.n for r in rows.groupBy("path").agg(F.count("*").alias("n")).where(F.col("n") > p.local_rows).collect()}
        # a part that would not split any further is left to one task, which chops it
        big = {k: n for k, n in sizes.items() if k not in seen and (p.max_depth is None or k.count(".") < p.max_depth)}
        if not big:
            break
        seen |= set(big)
        upper += big.items()
        rows = stored(_open_level(rows, big, p), "level")
    both = stored(rows.groupBy("path").applyInArrow(_finish(p), _PART), "parts")
    spark = df.sparkSession
    parts = both.where("kind = 0").select("path", "n", "is_final", "degenerate")
    if upper:
        parts = parts.union(spark.createDataFrame([(k, int(n), False, False) for k, n in upper], "path string, n long, is_final boolean, degenerate boolean"))
    level = F.size(F.split("path", r"\.")) - 1
    parent = F.when(F.col("path") != ROOT, F.regexp_replace("path", r"\.[0-9]+$", ""))
    clusters = parts.select("path", parent.alias("parent_path"), level.alias("level"), "n", "is_final", "degenerate")
    return Hierarchy(clusters, both.where("kind = 1").select("vec_id", "path", "v"))


def prefixes(path: str = "path"):
    """All ancestor-or-self paths of a path column, as an array."""
    parts = F.split(path, r"\.")
    return F.transform(F.sequence(F.lit(1), F.size(parts)), lambda i: F.array_join(F.slice(parts, 1, i), "."))


def paths(clusters: DataFrame) -> DataFrame:
    """(path, ancestor, distance): every cluster with each of its ancestors and itself."""
    flat = clusters.select("path", F.posexplode(prefixes()).alias("depth", "ancestor"))
    return flat.select("path", "ancestor", (F.size(F.split("path", r"\.")) - 1 - F.col("depth")).alias("distance"))


def subtree_counts(clusters: DataFrame) -> DataFrame:
    """(path, n): rows of the final clusters below each part."""
    final = clusters.where("is_final").select("path", "n")
    return final.select(F.explode(prefixes()).alias("path"), "n").groupBy("path").agg(F.sum("n").alias("n"))


def density_report(clusters: DataFrame) -> DataFrame:
    return clusters.where("is_final").groupBy("level").agg(F.count("*").alias("clusters"), F.min("n").alias("least"), F.percentile_approx("n", 0.5).alias("median"), F.max("n").alias("most"))
