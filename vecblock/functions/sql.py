"""The distances as SQL functions: inlined SQL UDFs, Arrow versions, an aggregate and table functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructField, StructType

from vecblock.functions import arrays as A

_SUM = "aggregate({0}, 0D, (s, x) -> s + x)"
DOT = _SUM.format("zip_with(a, b, (x, y) -> x * y)")
NORM = "sqrt(" + _SUM.format("transform({0}, x -> x * x)") + ")"

SQL_FUNCTIONS = {
    "vec_dot": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", DOT),
    "vec_norm": ("a ARRAY<DOUBLE>", NORM.format("a")),
    "vec_l2": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "sqrt(" + _SUM.format("zip_with(a, b, (x, y) -> (x - y) * (x - y))") + ")"),
    "vec_cosine": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", f"1D - try_divide({DOT}, {NORM.format('a')} * {NORM.format('b')})"),
    "vec_similarity": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", f"try_divide({DOT}, {NORM.format('a')} * {NORM.format('b')})"),
    "vec_commonality": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", f"try_divide({DOT}, {NORM.format('a')} * {NORM.format('b')})"),
}


def register(spark: SparkSession) -> None:
    """Temporary SQL functions; the analyzer inlines their bodies."""
    for name, (args, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")


def _arrow(f):
    """A scalar Arrow function of two list columns, as one kernel over whole batches; null where a side is null."""

    def run(a: pa.Array, b: pa.Array) -> pa.Array:
        there = pc.and_(pc.is_valid(a), pc.is_valid(b))
        x, y = A.matrix(a.filter(there)), A.matrix(b.filter(there))
        out = np.full(len(a), np.nan)
        out[there.to_numpy(zero_copy_only=False)] = f(x, y) if len(x) else np.zeros(0)
        return pa.array(out, mask=~there.to_numpy(zero_copy_only=False))

    return F.arrow_udf(run, "double")


#: Kernels over vectors in the last axis.
FAST = {
    "l2": lambda x, y: np.sqrt(((x - y) ** 2).sum(-1)),
    "dot": lambda x, y: (x * y).sum(-1),
    "cosine": lambda x, y: 1 - (x * y).sum(-1) / np.sqrt((x * x).sum(-1) * (y * y).sum(-1)),
}


def register_fast(spark: SparkSession) -> None:
    """The same names with suffix _fast, over Arrow batches; the rows of a batch have one dimension."""
    for name, f in FAST.items():
        spark.udf.register(f"vec_{name}_fast", _arrow(f))


def over_packs(name: str, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The same kernel for each row of x with each of y, where neither has been copied into pairs."""
    return np.stack([FAST[name](one[None], y) for one in x])


def vec_mean(df: DataFrame, keys: list[str], v: str = "v") -> DataFrame:
    """(keys, v): the mean vector of each group; tasks send partial sums, so no group meets as a whole."""
    schema = StructType([*[df.schema[k] for k in keys], StructField("n", LongType()), StructField("v", ArrayType(DoubleType()))])

    def part(batches):
        for b in batches:
            x = A.matrix(b.column(v))
            groups: dict[tuple, list[int]] = {}
            for i, key in enumerate(zip(*[b.column(k).to_pylist() for k in keys])):
                groups.setdefault(key, []).append(i)
            cols = list(zip(*groups)) or [[] for _ in keys]
            sums = np.array([x[at].sum(0) for at in groups.values()]).reshape(len(groups), -1)
            yield pa.RecordBatch.from_arrays([*[pa.array(list(c), b.schema.field(k).type) for c, k in zip(cols, keys)], pa.array([len(at) for at in groups.values()], pa.int64()), A.lists(sums) if len(groups) else pa.array([], pa.list_(pa.float64()))], names=[*keys, "n", "v"])

    sums = df.select(*keys, v).mapInArrow(part, schema)
    flat = sums.select(*keys, "n", F.posexplode("v").alias("pos", "x")).groupBy(*keys, "pos").agg((F.sum("x") / F.sum("n")).alias("x"))
    return flat.groupBy(*keys).agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "x"))), lambda e: e["x"]).alias("v"))


def register_tables(spark: SparkSession) -> None:
    """vec_unpack(array) -> (pos, val)."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="pos: int, val: double")
    class Unpack:
        def eval(self, v):
            for i, x in enumerate(v or []):
                yield i, float(x)

    spark.udtf.register("vec_unpack", Unpack)


def search_table(spark: SparkSession, index_path: str, metric: str = "l2", max_bytes: int = 64 << 20):
    """A table function vec_search(query_id, v, k, beam) over a saved index of at most ``max_bytes``, descended like any tree."""
    from pyspark.sql.functions import udtf

    from vecblock.operators import search as S, tree as T

    index = T.open_tree(spark, index_path)
    if index.n * (8 * index.dim + 16) > max_bytes:
        raise ValueError("the index exceeds max_bytes: use search() on it")
    levels = S.levels_of(index)
    got = index.live_rows().select("leaf_id", "vec_id", "v").orderBy("leaf_id", "vec_id").toArrow()  # at most ``max_bytes``
    held = spark.sparkContext.broadcast((levels, got.column("leaf_id").to_numpy(), got.column("vec_id").to_numpy(), A.matrix(got.column("v"))))

    @udtf(returnType="query_id: bigint, rank: int, vec_id: bigint, dist: double")
    class Search:
        def eval(self, query_id, v, k, beam):
            lv, leaf, ids, x = held.value
            q = np.asarray([v], float)
            opened = S.descend_local(lv, q, S.SearchParams(k=int(k), beam=int(beam)), metric)[0]
            at = np.concatenate([np.arange(*np.searchsorted(leaf, [lv.ids[level][n], lv.ids[level][n] + 1])) for level, n, _ in opened if level == len(lv.ids) - 1])
            _, found, dist = A.block_topk(q, x[at], ids[at], int(k) + 1, metric)
            rank = 0
            for i, d in zip(found.tolist(), dist.tolist()):
                if i != query_id and rank < k:
                    rank += 1
                    yield query_id, rank, i, d

    return Search
