"""Intermediate tables in the folder that the whole cluster shares."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; where it is unset, a temporary folder in local mode (tests) and an error on a cluster."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the whole cluster shares")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="vecblock-"))
        root = spark.sparkContext.getCheckpointDir()
    return root.rstrip("/")


def delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def _at_exit(spark: SparkSession, path: str) -> None:
    try:
        delete(spark, path)
    except Exception:  # the session has ended already
        return


def drop_at_exit(spark: SparkSession, path: str) -> None:
    atexit.register(_at_exit, spark, path)


class Stored:
    """A written table: ``df`` reads it, ``drop()`` removes its files."""

    def __init__(self, spark: SparkSession, df: DataFrame, tag: str, **options: str):
        self.spark, self.path = spark, f"{shared_root(spark)}/{tag}-{uuid.uuid4().hex}"
        writer = df.write
        for k, v in options.items():
            writer = writer.option(k, v)
        writer.parquet(self.path)
        self.schema = df.schema
        drop_at_exit(spark, self.path)

    @property
    def df(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        delete(self.spark, self.path)


def input_bytes(df: DataFrame) -> int:
    """Catalyst's estimate of what a plan reads; used to choose bucket counts."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def bucket_count(df: DataFrame, bytes_each: int = 4 << 20, least: int = 64, most: int = 1 << 20) -> int:
    """A power of two such that one bucket holds about ``bytes_each`` of the input; 256 where Catalyst has no estimate."""
    size = input_bytes(df)
    want = max(least, min(most, size // bytes_each)) if size < 1 << 60 else max(least, 256)
    return 1 << (int(want) - 1).bit_length()


def free_name(df: DataFrame, name: str) -> str:
    """A column name like ``name`` that ``df`` has not."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name
