"""Sliding windows over series, with no task that must hold a whole series."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.feeds import SERIES
from ..store import stored


def by_order():
    return Window.partitionBy(*SERIES).orderBy("ts", "tick")


def ranged(readings: DataFrame, parts: int) -> DataFrame:
    """``rn`` from 1 in each series, however long: ranges of the total order, of even sizes by a sample, are numbered one by one."""
    held = stored(readings.repartitionByRange(parts, *SERIES, "ts", "tick").withColumn("_bucket", F.spark_partition_id()), "ranges")
    return _numbered(held).select(*readings.columns, "rn")


def numbered(readings: DataFrame, bucket: str = "month") -> DataFrame:
    """``rn`` from 1 in each series. Rows are ordered within time buckets only, and start where the buckets before end."""
    return _numbered(readings.withColumn("_bucket", F.date_trunc(bucket, "ts").cast("timestamp_ntz"))).select(*readings.columns, "rn")


def _numbered(rows: DataFrame) -> DataFrame:
    """Rows with ``_bucket`` in, which ascends with their order."""
    counts = rows.groupBy(*SERIES, "_bucket").agg(F.count(F.lit(1)).alias("_n"))
    before = F.sum("_n").over(Window.partitionBy(*SERIES).orderBy("_bucket")) - F.col("_n")
    offsets = counts.withColumn("_before", before).drop("_n")
    within = F.row_number().over(Window.partitionBy(*SERIES, "_bucket").orderBy("ts", "tick"))
    keys = [*SERIES, "_bucket"]
    return rows.withColumn("_in", within).join(offsets, keys).withColumn("rn", (F.col("_before") + F.col("_in")).cast("long"))


def count_windows(readings: DataFrame, w: int, full_only: bool = True) -> DataFrame:
    """The last ``w`` values as an array, what arrived and what departed. The readable form: w-fold memory."""
    order = by_order()
    out = readings.withColumns(
        {
            "rn": F.row_number().over(order).cast("long"),
            "w": F.collect_list("v").over(order.rowsBetween(1 - w, 0)),
            "departed": F.lag("v", w).over(order),
            "arrived": F.col("v"),
        }
    )
    return out.where(F.col("rn") >= w) if full_only else out


def time_windows(readings: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """Values of each series by time span; tumbling without ``slide``."""
    return readings.groupBy(*SERIES, F.window("ts", size, slide)).agg(F.count(F.lit(1)).alias("n"), F.sum("v").alias("total"), F.min("v").alias("low"), F.max("v").alias("high"))


def chunked(rows: DataFrame, w: int, size: int) -> DataFrame:
    """``chunk`` of each numbered row; the last ``w`` rows of a chunk are also in the next."""
    if size < w:
        raise ValueError("a chunk must hold a window")
    at = (F.col("rn") - 1).cast("long")
    own = F.floor(at / size)
    return rows.withColumn("chunk", F.explode(F.when(at % size >= size - w, F.array(own, own + 1)).otherwise(F.array(own))))


def with_halo(readings: DataFrame, low, high, w: int) -> DataFrame:
    """Rows of a time slice and the ``w`` rows of each series before it."""
    rows = numbered(readings)
    bounds = rows.where((F.col("ts") >= low) & (F.col("ts") < high)).groupBy(*SERIES).agg(F.min("rn").alias("_a"), F.max("rn").alias("_b"))
    return rows.join(bounds, list(SERIES)).where((F.col("rn") >= F.col("_a") - w) & (F.col("rn") <= F.col("_b"))).drop("_a", "_b")


def pairs_by_join(readings: DataFrame) -> DataFrame:
    """Each reading with its predecessor, by an equality join on the row number."""
    rows = numbered(readings)
    before = rows.select(*SERIES, (F.col("rn") + 1).alias("rn"), F.col("v").alias("previous"))
    return rows.join(before, [*SERIES, "rn"], "left").select(*SERIES, "rn", "v", "previous")
