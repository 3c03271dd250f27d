"""The chain over a stream: each series keeps its window and what is not yet safe to use.

Readings wait until the watermark has passed them and are then used in time order, so a
stream gives the batch's anomalies whatever the order within the watermark's delay. A
series' state is its last ``w`` values and its waiting rows, packed into bytes. Rows
behind the watermark are dropped by Spark and counted in its progress metrics.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.kernel import RULES, Options, scan
from ..plans.chain import divided
from ..ship import ship
from ..sources.feeds import SERIES
from ..sources.params import attach

OUT = "machine_id long, sensor_id string, rn long, ts timestamp, p double, rule string"
STATE = "ring array<long>, rn long, k int, waiting binary"


def _advance(ring: list[int], rn: int, ready: np.ndarray, k: int, o: Options) -> tuple[list[int], int, dict[str, np.ndarray]]:
    """Uses ready rows (time, tick, value) in order: the new ring, its last row number, and the scored windows' columns."""
    v = np.append(np.array(ring, np.int64), ready[2])
    out = {}
    if len(v) >= o.w and ready.size:
        got = scan(v, k, max(0, len(ring) - o.w + 1), o)
        at = got["at"] + o.w - 1 - len(ring)
        out = {"rn": rn + at + 1, "ts": ready[0, at].astype("datetime64[us]"), "p": divided(got["num"], got["den"]), "rule": np.array(RULES, object)[got["rule"]]}
    return v[-o.w :].tolist(), rn + ready.shape[1], out


def detect(readings: DataFrame, params: DataFrame, w: int = 10, n: int = 5, delay: str = "1 hour") -> DataFrame:
    """Every scored window of a streaming feed; filter on ``p`` for anomalies."""
    ship(readings.sparkSession)
    o = Options(w=w, n=n)
    rows = attach(readings, params).withWatermark("ts", delay).select(*SERIES, "ts", "tick", "v", "k")

    def follow(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ring, rn, k, held = state.get if state.exists else ([], 0, 1, b"")
        parts = [np.frombuffer(held, np.int64).reshape(3, -1)]
        for b in batches:
            if not len(b):  # a timeout brings no rows
                continue
            parts.append(np.stack([b["ts"].astype("datetime64[us]").astype("int64"), b["tick"].to_numpy(np.int64), b["v"].to_numpy(np.int64)]))
            k = int(b["k"].iloc[0])
        waiting = np.concatenate(parts, axis=1)
        waiting = waiting[:, np.lexsort(waiting[::-1])]
        cut = int(np.searchsorted(waiting[0], state.getCurrentWatermarkMs() * 1000, "right"))
        ready, rest = waiting[:, :cut], waiting[:, cut:]
        ring, rn, out = _advance(list(ring), rn, ready, int(k), o)
        state.update((ring, rn, int(k), rest.tobytes()))
        if rest.size:
            # Comes back when the watermark passes the next row, with or without new readings.
            state.setTimeoutTimestamp(max(int(rest[0, 0]) // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        if out:
            yield pd.DataFrame({"machine_id": key[0], "sensor_id": key[1]} | out)

    return rows.groupBy(*SERIES).applyInPandasWithState(follow, OUT, STATE, "append", GroupStateTimeout.EventTimeTimeout)


def with_lateness(df: DataFrame, delay: str = "1 hour") -> DataFrame:
    return df.withWatermark("ts", delay)


def dedup(df: DataFrame, keys: list[str], delay: str = "1 hour") -> DataFrame:
    """Repeated readings within the watermark's delay come through once."""
    return df.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys)


def tumbling(df: DataFrame, size: str = "1 day", delay: str = "1 hour") -> DataFrame:
    return _counted(df.withWatermark("ts", delay), F.window("ts", size))


def sliding(df: DataFrame, size: str = "2 days", slide: str = "1 day", delay: str = "1 hour") -> DataFrame:
    return _counted(df.withWatermark("ts", delay), F.window("ts", size, slide))


def session(df: DataFrame, gap: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    return _counted(df.withWatermark("ts", delay), F.session_window("ts", gap))


def _counted(df: DataFrame, span) -> DataFrame:
    out = df.groupBy("sensor_id", span.alias("span")).agg(F.count(F.lit(1)).alias("n"))
    return out.select("sensor_id", F.col("span.start").alias("start"), F.col("span.end").alias("end"), "n")


def correlate(anomalies: DataFrame, errors: DataFrame, delay: str = "2 hours") -> DataFrame:
    """Errors within an hour of an anomaly, stream against stream.

    They meet by machine and hour of the clock: an anomaly stands in three hours, an error in one.
    """

    def hour(ts: str):
        return F.floor(F.unix_seconds(ts) / 3600)

    near = F.explode(F.sequence(hour("ts") - 1, hour("ts") + 1)).alias("_near")
    a = anomalies.withWatermark("ts", delay).select("*", near).alias("a")
    e = errors.select(F.col("machine_id").alias("m"), F.col("ts").alias("error_ts")).withWatermark("error_ts", delay).withColumn("_hour", hour("error_ts"))
    return a.join(e, F.expr("a.machine_id = m AND _near = _hour AND error_ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR")).drop("_near", "_hour")
