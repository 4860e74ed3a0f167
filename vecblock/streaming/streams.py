"""Streams: ingest into versions, windows over events, and a live view per session."""

from __future__ import annotations

import json
import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecblock.operators import ingest, tree as T

#: Bytes of vectors that live views are made from.
SERVED_BYTES = 16 << 20
ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def file_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def insert_stream(stream: DataFrame, index_path: str, checkpoint: str):
    """Insert every micro-batch into the index at ``index_path`` as a new version.

    A version remembers its batch: one that is replayed after a failure is skipped, so
    each row arrives exactly once.  Readers keep the version they opened.
    """

    def write(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        last = T.versions(spark, index_path)
        marks = [v for v in last if v >= 1]
        if marks and max(marks) > batch_id:
            return
        now = T.open_tree(spark, index_path)
        new = ingest.insert(now, batch.select("vec_id", "v"))
        new.version = batch_id + 1
        T.save(new, index_path)

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def timed_events(events: DataFrame) -> DataFrame:
    """Event time as TIMESTAMP, which watermarks need."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, size: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    w = events.withWatermark("ts", late) if events.isStreaming else events
    out = w.groupBy(F.window("ts", size), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return out.select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, size: str = "2 hours", step: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    w = events.withWatermark("ts", late) if events.isStreaming else events
    return w.groupBy(F.window("ts", size, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    w = events.withWatermark("ts", late) if events.isStreaming else events
    out = w.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def once(events: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    """Each key once within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def attributed(left: DataFrame, right: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Interval join of two event streams on the user: right events up to ``within`` after a left one."""
    a, b = left, right
    if left.isStreaming:
        a, b = a.withWatermark("ts", late), b.withWatermark("ts", late)
    a = a.select(F.col("user_id").alias("u"), F.col("ts").alias("t1"), F.col("event_id").alias("e1"))
    b = b.select("user_id", F.col("ts").alias("t2"), F.col("event_id").alias("e2"))
    on = (F.col("u") == F.col("user_id")) & (F.col("t2") >= F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).select("user_id", "e1", "e2")


def run_once(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run a stream over what there is and give its memory table back."""
    spark = stream.sparkSession
    stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def view_sessions(turns: DataFrame, radius: float, ttl_ms: int | None = None, rows: DataFrame | None = None, k: int = 5, view_size: int = 100) -> DataFrame:
    """(session_id, seq, served_from, view_no, ids): a live view per session, kept in state.

    ``turns``: (session_id, seq, v).  A query within ``radius`` of the session's
    anchor is answered by its view, others renew it from ``rows`` (vec_id, v), a collection of at most SERVED_BYTES;
    without ``rows`` only the anchor is kept and ids are null.  ``ttl_ms`` forgets idle
    sessions by processing time, which keeps a query running (no availableNow).
    Needs the RocksDB state store.
    """
    import numpy as np
    import pandas as pd
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    from vecblock.functions import arrays as A
    from vecblock.operators import view as W

    held = None
    if rows is not None:
        size = rows.agg((F.count("*") * F.max(F.size("v")) * 8).alias("b")).first().b or 0
        if size > SERVED_BYTES:
            raise ValueError("the rows exceed SERVED_BYTES: serve views from replay()")
        got = rows.select("vec_id", F.col("v").cast("array<double>").alias("v")).orderBy("vec_id").toArrow()  # at most SERVED_BYTES
        held = got.column("vec_id").to_numpy(), A.matrix(got.column("v"))  # part of the processor: it cannot see broadcasts

    class Live(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.state = handle.getValueState("view", "anchor string, no long, view string", ttlDurationMs=ttl_ms)

        def handleInputRows(self, key, rows, timerValues):
            got = pd.concat(list(rows)).sort_values("seq")
            had = self.state.get() if self.state.exists() else None
            anchor, no = (json.loads(had[0]), had[1]) if had else (None, 0)
            view = W.from_json(had[2]) if had and had[2] else None
            out = []
            for seq, v in zip(got["seq"], got["v"]):
                v = [float(x) for x in v]
                near = anchor is not None and math.dist(anchor, v) <= radius
                if not near:
                    anchor, no = v, no + 1
                    if held is not None:
                        ids, x = held
                        _, found, _ = A.block_topk(np.array([v]), x, ids, view_size, "l2")
                        view = W.local_view(found, x[np.searchsorted(ids, found)], np.array(v), with_links=True)
                answer = view.answer(np.array(v), k)[0].tolist() if view is not None else None
                out.append((int(key[0]), int(seq), "view" if near else "new", int(no), answer))
            self.state.update((json.dumps(anchor), no, W.to_json(view) if view is not None else None))
            yield pd.DataFrame(out, columns=["session_id", "seq", "served_from", "view_no", "ids"])

        def close(self) -> None:
            return

    return turns.groupBy("session_id").transformWithStateInPandas(Live(), "session_id long, seq long, served_from string, view_no long, ids array<long>", "append", "none" if ttl_ms is None else "processingTime")


def queries_with_index(stream: DataFrame, found: DataFrame) -> DataFrame:
    """Stream-static join: arriving (query_id, ...) beside the answers (query_id, rank, vec_id, dist) of an index version."""
    return stream.join(found, "query_id")


def rate_stream(spark: SparkSession, rows_per_second: int = 10) -> DataFrame:
    """(timestamp, value) from Spark's own clock source, for soak tests."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
