"""Other formats: raw vector dumps, delimited text, and leaves as a data source."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_ITEM = {"fvecs": "<f4", "ivecs": "<i4", "bvecs": "u1"}


def decode_dump(raw: bytes, kind: str) -> np.ndarray:
    """Rows of a dump: each a 32-bit length and then that many values."""
    item = np.dtype(_ITEM[kind])
    if not raw:
        return np.zeros((0, 0))
    dim = int(np.frombuffer(raw, "<i4", 1)[0])
    row = 4 + dim * item.itemsize
    if len(raw) % row:
        raise ValueError("rows of different lengths")
    body = np.frombuffer(raw, np.uint8).reshape(-1, row)[:, 4:]
    return np.ascontiguousarray(body).view(item).reshape(-1, dim).astype(np.float64)


def encode_dump(x: np.ndarray, kind: str) -> bytes:
    head = np.full((len(x), 1), x.shape[1], "<i4").view(np.uint8)
    body = np.ascontiguousarray(x, _ITEM[kind]).view(np.uint8).reshape(len(x), -1)
    return np.hstack([head, body]).tobytes()


def read_dump(spark: SparkSession, path: str, kind: str) -> DataFrame:
    """(path, pos, v) of raw dump files."""

    def run(batches):
        for b in batches:
            for name, raw in zip(b.column("path").to_pylist(), b.column("content").to_pylist()):
                x = decode_dump(raw, kind)
                off = pa.array(np.arange(len(x) + 1, dtype=np.int32) * (x.shape[1] if x.size else 0))
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(x)), pa.array(np.arange(len(x))), pa.ListArray.from_arrays(off, pa.array(x.ravel()))], names=["path", "pos", "v"])

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, "path string, pos long, v array<double>")


def parse_text(df: DataFrame, column: str, sep: str = ",") -> DataFrame:
    """Text vectors such as "[1,2,3]" or "1,2,3" as arrays in ``v``; unreadable values become null."""
    body = F.regexp_replace(column, r"[\[\]\s]", "")
    return df.withColumn("v", F.transform(F.split(body, sep), lambda x: x.try_cast("double")))


def leaf_source():
    """The data source class 'blocktree' over one saved version (option path); pushed filters on leaf_id and shard choose files.

    Python sources open files themselves, so this one needs a file system that
    every machine mounts; ``tree.open_tree`` reads any store.  Needs
    spark.sql.python.filterPushdown.enabled.
    """
    from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition

    class Shard(InputPartition):
        def __init__(self, shard: int, leaves):
            self.shard, self.leaves = shard, leaves

    class Reader(DataSourceReader):
        def __init__(self, rows: dict):
            self.rows, self.leaves, self.shards = rows, None, None

        def pushFilters(self, filters):
            for f in filters:
                if isinstance(f, (EqualTo, In)) and f.attribute in (("leaf_id",), ("shard",)):
                    values = {f.value} if isinstance(f, EqualTo) else set(f.value)
                    if f.attribute == ("leaf_id",):
                        self.leaves = values if self.leaves is None else self.leaves & values
                    else:
                        self.shards = values if self.shards is None else self.shards & values
                yield f  # Spark applies every predicate again

        def partitions(self):
            return [Shard(s, self.leaves) for s in self.rows if self.shards is None or s in self.shards]

        def read(self, part):
            import pyarrow.parquet as pq

            for file in self.rows[part.shard]:
                t = pq.read_table(file, columns=["leaf_id", "vec_id", "v"], partitioning=None, filters=[("leaf_id", "in", sorted(part.leaves))] if part.leaves else None)
                t = t.append_column("shard", pa.array(np.full(len(t), part.shard, np.int32)))
                yield from t.to_batches()

    class BlockTreeSource(DataSource):
        @classmethod
        def name(cls):
            return "blocktree"

        def schema(self):
            return "leaf_id bigint, vec_id bigint, v array<double>, shard int"

        def reader(self, schema):
            import glob
            import os
            import re

            base = self.options["path"].removeprefix("file:")
            rows: dict[int, list[str]] = {}
            for file in sorted(glob.glob(os.path.join(base, "rows", "shard=*", "*.parquet"))):
                rows.setdefault(int(re.search(r"shard=(\d+)", file)[1]), []).append(file)
            return Reader(rows)

    return BlockTreeSource
