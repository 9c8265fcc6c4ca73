"""Streams: windows over events, late rows, assembly of series, and insertion into an index.

Sources are folders of Parquet files (any streaming source with the same columns does).
Batch forms of the windows give the same rows and are what SQL checks.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..functions.summaries import paa_rows, sax_rows
from ..plans import update
from ..plans.build import checked
from ..plans.build import _normal as normal_rows
from ..plans.index import SeriesIndex
from ..plans.storage import fresh_path, shared_dir
from ..plans.tree import WordTree

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
DELAY = "1 hour"


def event_stream(spark: SparkSession, folder: str, files_per_batch: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(EVENTS)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.parquet(folder)


def _timed(events: DataFrame) -> DataFrame:
    return events.withColumn("at", F.col("ts").cast("timestamp"))


def _sums() -> list:
    return [F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total")]


def tumbling(events: DataFrame, size: str = "1 day", delay: str = DELAY) -> DataFrame:
    return _timed(events).withWatermark("at", delay).groupBy(F.window("at", size).alias("w")).agg(*_sums()).select(F.col("w.start").cast("timestamp_ntz").alias("began"), "n", "total")


def sliding(events: DataFrame, size: str = "1 day", slide: str = "6 hours", delay: str = DELAY) -> DataFrame:
    return _timed(events).withWatermark("at", delay).groupBy(F.window("at", size, slide).alias("w")).agg(*_sums()).select(F.col("w.start").cast("timestamp_ntz").alias("began"), "n", "total")


def sessions(events: DataFrame, gap: str = "6 hours", delay: str = DELAY) -> DataFrame:
    return _timed(events).withWatermark("at", delay).groupBy("user_id", F.session_window("at", gap).alias("w")).agg(*_sums()).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("began"), "n", "total")


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there now into Parquet (append) or a memory table (complete)."""
    spark = stream.sparkSession
    checkpoint = fresh_path(spark, "stream-checkpoint")
    if mode == "append":
        path = fresh_path(spark, "stream-out")
        stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    name = f"stream_{uuid.uuid4().hex}"
    stream.writeStream.format("memory").queryName(name).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def late_rows(events: DataFrame, delay_seconds: int = 3600, block: int = 1_000_000) -> DataFrame:
    """Side list: rows older than the newest row before them (by id) less the delay.

    A running maximum over all rows would be one task; blocks of ids are summarised first
    (one row for each million rows) and a row looks at the blocks before its own and at its
    own block alone.
    """
    us = F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01', ts)")
    rows = events.select("event_id", us.alias("t")).withColumn("block", F.floor(F.col("event_id") / block))
    blocks = rows.groupBy("block").agg(F.max("t").alias("top"))
    before = blocks.withColumn("before", F.max("top").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1))).select("block", "before")
    inside = F.max("t").over(Window.partitionBy("block").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0))
    seen = rows.withColumn("own", inside).join(before, "block").withColumn("newest", F.greatest("own", F.coalesce("before", F.col("own"))))
    return seen.where(F.col("t") < F.col("newest") - delay_seconds * 1_000_000).select("event_id")


class Assembler(StatefulProcessor):
    """Keeps each user's last values and gives a series whenever a window is full."""

    def __init__(self, n: int = 32, stride: int = 4):
        self.n, self.stride = n, stride

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.kept = handle.getValueState("kept", "count long, vals array<double>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        state = self.kept.get() if self.kept.exists() else None
        count, kept = (state[0], list(state[1])) if state else (0, [])
        new = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        out = []
        for v in new["value"]:
            kept = (kept + [float(v)])[-self.n :]
            count += 1
            if count >= self.n and (count - self.n) % self.stride == 0:
                x = np.array(kept)
                out.append((int(key[0]) * 1000003 + (count - self.n) // self.stride, np.cumsum(x - x.mean()).tolist()))
        self.kept.update((count, kept))
        yield pd.DataFrame({"series_id": [o[0] for o in out], "values": [o[1] for o in out]})

    def close(self) -> None:
        pass


def assembled_stream(events: DataFrame, n: int = 32, stride: int = 4) -> DataFrame:
    """Series of a stream of events that arrive in order; state is the last ``n`` values of a user."""
    return events.select("user_id", "ts", "event_id", "value").groupBy("user_id").transformWithStateInPandas(Assembler(n, stride), "series_id long, values array<double>", "Append", "None")


def stream_into(ix: SeriesIndex, stream: DataFrame, reorganize: bool = False, name: str | None = None) -> SeriesIndex:
    """Inserts every micro-batch of (series_id, values); a batch that comes again is not taken again.

    ``name`` says which stream it is: its checkpoint and its batch ids belong to that name
    and to this index, so a later call goes on where the last one ended.  Without a name
    every call is a stream of its own.
    """
    name = name or f"once-{uuid.uuid4().hex}"

    def take(batch: DataFrame, batch_id: int) -> None:
        update.insert(ix, batch, batch_id, name)
        if reorganize:
            update.reorganize(ix)

    checkpoint = f"{shared_dir(ix.spark)}/stream-insert-{ix.uid}-{name}"
    stream.writeStream.foreachBatch(take).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return ix


def routed(ix: SeriesIndex, series: DataFrame) -> DataFrame:
    """(series_id, leaf_id) of arriving series, a stream or a table, by the index as it is now.

    leaf_id is null where the cell has no leaf yet; bad rows (see ``checked``) are left out.
    """
    if not isinstance(ix.tree, WordTree):
        raise ValueError("routed: only indexes whose splits are decided by words")
    p, n = ix.params, ix.n
    shared = ix.spark.sparkContext.broadcast((ix.tree, np.array([i if ix.tree.is_leaf(node) else -1 for node, i in enumerate(ix.tree.leaf_id)], np.int64)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree, ids = shared.value
        for b in batches:
            at = ids[tree.route(sax_rows(paa_rows(normal_rows(b.column(1), n, p), p.w), p.bits))]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(at, mask=at < 0)], names=["series_id", "leaf_id"])

    return checked(series, n)[0].mapInArrow(run, "series_id long, leaf_id long")


def use_rocksdb(spark: SparkSession) -> Callable[[], None]:
    """Keyed state needs the RocksDB store; returns what puts the session's setting back."""
    key, new = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
    old = spark.conf.get(key, None)
    spark.conf.set(key, new)
    return lambda: spark.conf.set(key, old) if old else spark.conf.unset(key)


def _folder(spark: SparkSession, sf_dir: str) -> str:
    """The events table as a folder that a stream can watch."""
    path = fresh_path(spark, "events")
    spark.read.parquet(f"{sf_dir}/events.parquet").repartitionByRange("ts", "event_id").sortWithinPartitions("ts", "event_id").write.parquet(path)
    return path


def _q_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run_to_table(tumbling(event_stream(spark, _folder(spark, sf_dir))), "complete")


def _q_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run_to_table(sliding(event_stream(spark, _folder(spark, sf_dir))), "complete")


def _q_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run_to_table(sessions(event_stream(spark, _folder(spark, sf_dir))), "complete")


def _q_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    return late_rows(spark.read.parquet(f"{sf_dir}/events.parquet"))


#: A step and a prime above the number of events, so that ids are dealt anew without repeats.
_STEP, _PRIME = 61_803_399, 100_000_007


def _q_late_arrivals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Late rows where events arrive far out of the order of their times."""
    arrival = F.pmod(F.col("event_id") * _STEP, F.lit(_PRIME))
    return late_rows(spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("event_id", arrival), 86_400, 1_000_000)


def _q_assembled(spark: SparkSession, sf_dir: str) -> DataFrame:
    back = use_rocksdb(spark)
    try:
        out = run_to_table(assembled_stream(event_stream(spark, _folder(spark, sf_dir))))
    finally:
        back()
    v = F.col("values")
    return out.select("series_id", F.size(v).cast("long").alias("n"), (F.round(F.get(v, F.lit(0)), 8) + 0.0).alias("head"), (F.round(F.array_max(v), 8) + 0.0).alias("top"))


def _assembled_sql() -> str:
    from ..oracle_sql import SERIES

    return f"WITH {SERIES['pulses']} SELECT series_id, CAST(len(vals) AS BIGINT) AS n, round(vals[1], 8) + 0.0 AS head, round(list_max(vals), 8) + 0.0 AS top FROM series"


_GAP = 6 * 3_600_000_000
QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "stream_tumbling": (_q_tumbling, "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS began, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1"),
    "stream_sliding": (_q_sliding, "SELECT CAST(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - k.k * INTERVAL 6 HOUR AS TIMESTAMP) AS began, count(*) AS n, round(sum(value), 4) AS total FROM events CROSS JOIN (VALUES (0), (1), (2), (3)) k(k) GROUP BY 1"),
    "stream_session": (_q_sessions, f"""SELECT user_id, min(ts) AS began, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT user_id, ts, value, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (
SELECT user_id, ts, event_id, value, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) < {_GAP} THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s"""),
    "late_counts": (_q_late, "SELECT event_id FROM (SELECT event_id, ts, max(ts) OVER (ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS newest FROM events) WHERE ts < newest - INTERVAL 1 HOUR"),
    "late_arrivals": (_q_late_arrivals, f"SELECT event_id FROM (SELECT event_id, ts, max(ts) OVER (ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS newest FROM (SELECT (event_id * {_STEP}) % {_PRIME} AS event_id, ts FROM events)) WHERE ts < newest - INTERVAL 1 DAY"),
    "assembled_series": (_q_assembled, _assembled_sql()),
}
