"""Memo of windows: what share would be found again, by exact content or by what clusters depend on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .native import labelled


def keyed(win: DataFrame, canonical: bool = False) -> DataFrame:
    """``key`` of (w, k): the window itself, or its seed set and sorted values."""
    seeds = F.array_sort(F.slice(F.array_distinct("w"), F.lit(1), F.col("k")))
    return win.withColumn("key", F.struct("k", seeds.alias("seeds"), F.array_sort("w").alias("w")) if canonical else F.struct("k", F.col("w").alias("w")))


def hit_rate(win: DataFrame, canonical: bool = False) -> DataFrame:
    """Windows, distinct keys and the share of windows found in the memo, by sensor."""
    # The 64-bit hash spreads the shuffle; the key itself decides.
    once = keyed(win, canonical).groupBy("sensor_id", F.xxhash64("key").alias("h"), "key").agg(F.count(F.lit(1)).alias("n"))
    return once.groupBy("sensor_id").agg(F.sum("n").alias("windows"), F.count(F.lit(1)).alias("distinct_keys")).withColumn("hit_rate", 1 - F.col("distinct_keys") / F.col("windows"))


def clustered(win: DataFrame, canonical: bool = False, max_iter: int = 50) -> DataFrame:
    """``labels`` of windows (w, k): each distinct key is clustered once and joined back.

    Behind the canonical key stands the sorted window, whose labels go back to the places
    their values came from.
    """
    rows = keyed(win, canonical).withColumn("h", F.xxhash64("key"))
    once = rows.select("h", "key").distinct().select("h", "key", F.col("key.k").alias("k"), F.col("key.w").alias("w"))
    done = labelled(once, max_iter, F.col("key.seeds") if canonical else None).select("h", "key", F.col("labels").alias("of_key"))
    # The hash deals both sides; the key itself decides.
    back = rows.join(done, ["h", "key"])
    own = F.transform("w", lambda x: F.get("of_key", F.array_position(F.col("key.w"), x).cast("int") - 1)) if canonical else F.col("of_key")
    return back.withColumn("labels", own).drop("h", "key", "of_key")
