"""The incremental test for rotation: counts of the seeds' prefix, kept from slide to slide."""

from __future__ import annotations

from collections import deque

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ship import ship
from ..sources.feeds import SERIES
from ..sources.params import attach
from . import windows


class PrefixTracker:
    """Tells after each slide whether window and seeds are what they were.

    ``conservative`` looks for one replacement of a seed that has left, so it may miss
    rotations after windows with fewer than k values; ``complete`` looks until the
    prefix holds k values or the window ends.
    """

    def __init__(self, k: int, w: int, mode: str = "complete"):
        self.k, self.w, self.mode = k, w, mode
        self.ring: deque[int] = deque()
        self.prefix_counts: dict[int, int] = {}
        self.prefix_end = 0  # places of the window that the counts cover
        self.full = False

    def _grow(self, most: int) -> list[int]:
        """Extends the prefix up to ``most`` new seeds; stops at the one that makes k."""
        added = []
        while self.prefix_end < self.w:
            value = self.ring[self.prefix_end]
            if value not in self.prefix_counts:
                if len(self.prefix_counts) >= self.k or len(added) >= most:
                    break
                added.append(value)
            elif len(self.prefix_counts) >= self.k and self.mode == "complete":
                break
            self.prefix_counts[value] = self.prefix_counts.get(value, 0) + 1
            self.prefix_end += 1
            if len(added) >= most:
                break
        return added

    def slide(self, arrived: int) -> bool | None:
        """Null until the window is full, false at the first full one."""
        self.ring.append(arrived)
        if len(self.ring) < self.w:
            return None
        if not self.full:
            self.full = True
            self._grow(self.k)
            return False
        departed = self.ring.popleft()
        self.prefix_end -= 1
        self.prefix_counts[departed] -= 1
        dropped, added = [], []
        if not self.prefix_counts[departed]:
            del self.prefix_counts[departed]
            dropped = [departed]
            added = self._grow(1 if self.mode == "conservative" else self.k)
        elif self.mode == "complete" and len(self.prefix_counts) < self.k:
            added = self._grow(self.k)
        return arrived == departed and dropped == added


def tracked(readings: DataFrame, params: DataFrame, w: int) -> DataFrame:
    """Both forms for every full window. A series is one sequence here, in one task: use ``chain.score`` for scale."""
    ship(readings.sparkSession)
    rows = attach(windows.numbered(readings), params).select(*SERIES, "rn", "v", "k")

    def follow(table: pa.Table) -> pa.Table:
        table = table.sort_by("rn")
        k = table.column("k")[0].as_py()
        both = [PrefixTracker(k, w, m) for m in ("complete", "conservative")]
        flags = [[t.slide(v) for t in both] for v in table.column("v").to_pylist()]
        out = table.select(["machine_id", "sensor_id", "rn"]).append_column("complete", pa.array([f[0] for f in flags], pa.bool_())).append_column("conservative", pa.array([f[1] for f in flags], pa.bool_()))
        return out.slice(min(w - 1, len(flags)))

    return rows.groupBy(*SERIES).applyInArrow(follow, "machine_id long, sensor_id string, rn long, complete boolean, conservative boolean").where(F.col("complete").isNotNull())
