"""The miner on streaming DataFrames.  (M20, M20a, M26, W8)

Spark does not order the rows of a group within a micro-batch: they are sorted by (ts, point_id)
before they are read.  Rows later than the watermark are dropped by Spark; a late row inside an open
chunk is taken in arrival order.  The last, incomplete chunk of a stream closes by the idle timer or
at the end (``flush``).
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import StringType, StructField, StructType

from ..operators.engine import Settings, StreamMiner
from ..operators.miner import assign

VERDICTS = "stream_key string, median_id long, first_phase int, settled_phase int, age int, score int, weight double, verdict string"
_COLUMNS = [c.split()[0] for c in VERDICTS.split(", ")]


def event_time(df: DataFrame, ts: str = "ts") -> DataFrame:
    """A timestamp without zone cannot carry a watermark: it becomes one of the session's zone."""
    return df.withColumn(ts, F.col(ts).cast("timestamp"))


def _take(stream: StreamMiner, rows: list) -> list[dict]:
    """Gives (ts, point_id, vec, weight) rows in their order; returns new verdicts."""
    before = len(stream.miner.log.verdicts)
    if rows:
        rows = sorted(rows)
        stream.add(np.array([r[1] for r in rows], np.int64), np.array([r[2] for r in rows], float).reshape(len(rows), stream.d), np.array([r[3] for r in rows], float))
    return stream.miner.log.verdicts[before:]


def _chunked(settings: Settings) -> Settings:
    if settings.mode != "chunked":
        raise ValueError("a stream is mined in chunks: the state between batches holds no open phase")
    return settings


def _frame(key: str, verdicts: list[dict]) -> pd.DataFrame:
    return pd.DataFrame([{"stream_key": key} | v for v in verdicts], columns=_COLUMNS)


class _Processor(StatefulProcessor):
    def __init__(self, settings: Settings, d: int, idle_ms: int | None):
        self.settings, self.d, self.idle_ms = _chunked(settings), d, idle_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.held = handle.getValueState("miner", StructType([StructField("json", StringType())]))

    def _stream(self) -> StreamMiner:
        return StreamMiner(self.settings, self.d, self.held.get()[0] if self.held.exists() else None)

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        stream = self._stream()
        batch = pd.concat(list(rows), ignore_index=True)
        taken = [(str(t), int(i), [float(c) for c in v], float(w)) for t, i, v, w in zip(batch["ts"], batch["point_id"], batch["vec"], batch["weight"], strict=True)]
        out = _take(stream, taken)
        self.held.update((stream.state(),))
        if self.idle_ms is not None:
            for timer in list(self.handle.listTimers()):
                self.handle.deleteTimer(timer)
            self.handle.registerTimer(timerValues.getCurrentProcessingTimeInMs() + self.idle_ms)
        yield _frame(key[0], out)

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        stream = self._stream()
        before = len(stream.miner.log.verdicts)
        stream.flush()
        out = stream.miner.log.verdicts[before:]
        self.held.update((stream.state(),))
        yield _frame(key[0], out)

    def close(self) -> None:
        pass


def mine_outliers_stream(points: DataFrame, settings: Settings, d: int, *, idle_ms: int | None = None) -> DataFrame:
    """Verdicts of many keyed streams: ``points`` is (stream_key, ts, point_id, vec, weight), streaming.
    State lies in the RocksDB store; one exchange by key a micro-batch.  (M20)"""
    mode = "processingTime" if idle_ms is not None else "none"
    return points.groupBy("stream_key").transformWithStateInPandas(_Processor(settings, d, idle_ms), VERDICTS, "append", mode)


def batch_miner(path: str, settings: Settings, d: int):
    """A ``foreachBatch`` sink for one unkeyed stream: the state of batch b is the file folder
    ``path``/state=b, its verdicts ``path``/verdicts/batch=b.  A batch that comes again overwrites the
    same folders from the state before it, so restarts change nothing.  (M20a)"""

    def run(df: DataFrame, batch: int) -> None:
        spark = df.sparkSession
        state = None
        if batch > 0:
            state = spark.read.schema("json string").json(f"{path}/state={batch - 1}").head()[0]
        stream = StreamMiner(_chunked(settings), d, state)
        out = []
        rows = df.select("ts", "point_id", "vec", "weight").orderBy("ts", "point_id").toLocalIterator()  # one partition at a time
        while some := [(str(r.ts), r.point_id, list(r.vec), r.weight) for r in islice(rows, 10_000)]:
            out += _take(stream, some)
        frame = _frame("all", out).astype({"median_id": "int64"} if out else {})
        spark.createDataFrame(frame, VERDICTS).write.mode("overwrite").parquet(f"{path}/verdicts/batch={batch}")
        spark.createDataFrame([(stream.state(),)], "json string").write.mode("overwrite").json(f"{path}/state={batch}")

    return run


def live_points(events: DataFrame, *, watermark: str = "1 hour", key: str | None = "user_id") -> DataFrame:
    """Streaming ``events`` as points, each event once within the watermark."""
    e = event_time(events).withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])
    k = F.lit("all") if key is None else F.col(key).cast("string")
    return e.select(k.alias("stream_key"), "ts", F.col("event_id").alias("point_id"), F.array("value").alias("vec"), F.lit(1.0).alias("weight"))


def score_stream(points: DataFrame, medians: DataFrame, d: int, far: float) -> DataFrame:
    """Distance of each streaming point to the nearest of some static medians: a stream-static join of
    one row (all medians in one array, behind the check in ``assign``).  (M26)"""
    held = medians.agg(F.collect_list(F.struct("median_id", "vec")).alias("ms"))
    gap = lambda m: F.sqrt(sum(((F.col("vec")[i] - m["vec"][i]) * (F.col("vec")[i] - m["vec"][i]) for i in range(d)), F.lit(0.0)))
    best = F.array_min(F.transform("ms", lambda m: F.struct(gap(m).alias("dist"), m["median_id"].alias("median_id"))))
    out = points.join(F.broadcast(held), F.lit(True)).withColumn("b", best)
    return out.select("stream_key", "ts", "point_id", "b.median_id", "b.dist", (F.col("b.dist") > far).alias("is_far"))


def late_rows(query) -> int:
    """Rows that came below the watermark and were dropped, over the progress that the query still holds.
    Spark holds rows against the watermark of the batch before; rows that were pre-aggregated count once."""
    progress = [p if isinstance(p, dict) else json.loads(p.json) for p in query.recentProgress]
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in progress for op in p.get("stateOperators", []))


def windowed_counts(events: DataFrame, width: str, watermark: str) -> DataFrame:
    """Counts by event-time window, closed by the watermark."""
    return event_time(events).withWatermark("ts", watermark).groupBy(F.window("ts", width)).agg(F.count("*").alias("points"), F.avg("value").alias("mean"))


def with_verdicts(points: DataFrame, verdicts: DataFrame, within: str) -> DataFrame:
    """Stream-stream join of points with verdicts on them, bounded in time by ``within``."""
    v = verdicts.select(F.col("stream_key").alias("v_key"), F.col("median_id"), F.col("ts").alias("v_ts"), "verdict")
    bound = (F.col("v_ts") >= F.col("ts")) & (F.col("v_ts") <= F.col("ts") + F.expr(f"interval {within}"))
    return points.join(v, (F.col("stream_key") == F.col("v_key")) & (F.col("point_id") == F.col("median_id")) & bound)


__all__ = ["StreamMiner", "assign", "batch_miner", "event_time", "late_rows", "live_points", "mine_outliers_stream", "score_stream", "windowed_counts", "with_verdicts"]
