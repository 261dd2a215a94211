"""Novelty online: the best-so-far fold as a stateful stream."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..session import ship

OUTPUT = "series string, row_id bigint, ts timestamp, value double, s int, nu bigint"
STATE = "best double, nu bigint, late bigint, held array<struct<ts:timestamp,row_id:bigint,value:double>>"


def stream_advances(stream: DataFrame, series: str, row_id: str, ts: str, value: str, delay: str = "1 day", direction: int = 1) -> DataFrame:
    """Verdict and nu of every row once the watermark has passed it, in order of (ts, row id).

    Rows wait in state until the watermark; one that is older than the watermark when it arrives is dropped
    and counted in the state.  State per series is the best value, the count and the rows still waiting.
    NTZ timestamps are cast, since watermarks need timestamps.
    """
    ship(stream.sparkSession)
    rows = stream.select(F.col(series).cast("string").alias("series"), F.col(row_id).cast("bigint").alias("row_id"), F.col(ts).cast("timestamp").alias("ts"), F.col(value).cast("double").alias("value")).withWatermark("ts", delay)

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        best, nu, late, held = state.get if state.exists else (None, 0, 0, [])
        mark = pd.Timestamp(state.getCurrentWatermarkMs(), unit="ms", tz="UTC")
        waiting = [(pd.Timestamp(h["ts"] if not isinstance(h, tuple) else h[0]), h["row_id"] if not isinstance(h, tuple) else h[1], h["value"] if not isinstance(h, tuple) else h[2]) for h in held or []]
        waiting = [(t.tz_localize("UTC") if t.tzinfo is None else t, i, v) for t, i, v in waiting]
        for batch in batches:
            for t, i, v in zip(batch["ts"], batch["row_id"], batch["value"]):
                t = pd.Timestamp(t)
                t = t.tz_localize("UTC") if t.tzinfo is None else t
                if t < mark:
                    late += 1
                else:
                    waiting.append((t, int(i), None if pd.isna(v) else float(v)))
        waiting.sort(key=lambda x: x[:2])
        ready, out = [x for x in waiting if x[0] < mark], []
        for t, i, v in ready:
            s = None
            if v is not None:
                lead = None if best is None else (v - best) * direction
                s = 1 if lead is None or lead > 0 else 0 if lead == 0 else -1
                if s == 1:
                    best, nu = v, nu + 1
            out.append((key[0], i, t, v, s, nu))
        rest = waiting[len(ready) :]
        state.update((best, nu, late, [(t.to_pydatetime(), i, v) for t, i, v in rest]))
        if rest:
            state.setTimeoutTimestamp(max(int(rest[0][0].timestamp() * 1000), state.getCurrentWatermarkMs()) + 1)
        if out:
            made = pd.DataFrame(out, columns=["series", "row_id", "ts", "value", "s", "nu"])
            made["s"] = made["s"].astype("Int32")
            yield made

    return rows.groupBy("series").applyInPandasWithState(step, OUTPUT, STATE, "append", GroupStateTimeout.EventTimeTimeout)


def windowed_counts(stream: DataFrame, ts: str, by: str, window: str = "1 day", slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """Rows per tumbling or sliding window."""
    rows = stream.withColumn("ts_", F.col(ts).cast("timestamp")).withWatermark("ts_", delay)
    return rows.groupBy(F.window("ts_", window, slide) if slide else F.window("ts_", window), by).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), by, "n")


def session_counts(stream: DataFrame, ts: str, by: str, gap: str = "1 hour", delay: str = "1 day") -> DataFrame:
    """Rows per burst of activity."""
    rows = stream.withColumn("ts_", F.col(ts).cast("timestamp")).withWatermark("ts_", delay)
    return rows.groupBy(F.session_window("ts_", gap), by).agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), by, "n")


def distinct_rows(stream: DataFrame, ts: str, keys: list[str], delay: str = "1 day") -> DataFrame:
    """Each key once within the watermark."""
    return stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay).dropDuplicatesWithinWatermark(keys)


def run_to_end(stream: DataFrame, folder: str, checkpoint: str, mode: str = "append") -> None:
    """Process everything that is there, writing Parquet."""
    query = stream.writeStream.format("parquet").option("path", folder).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    if query.exception() is not None:
        raise RuntimeError(str(query.exception()))
