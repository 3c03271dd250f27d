"""Cost measures: counters that do not depend on the machine they are taken on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.feeds import SERIES


def message_bytes(msgs: DataFrame) -> DataFrame:
    return msgs.agg(F.count(F.lit(1)).alias("messages"), F.sum(F.octet_length("msg")).alias("bytes"))


def window_total(readings: DataFrame, w: int) -> DataFrame:
    """Full windows in closed form."""
    return readings.groupBy(*SERIES).agg(F.count(F.lit(1)).alias("n")).agg(F.sum(F.greatest(F.col("n") - (w - 1), F.lit(0))).alias("windows"))


def shortcut_share(scored: DataFrame) -> DataFrame:
    cut = F.count_if(F.col("rule") != "iterate")
    return scored.agg(F.count(F.lit(1)).alias("windows"), cut.alias("shortcut"), (cut / F.count(F.lit(1))).alias("share"))


def cluster_ops(scored: DataFrame, w: int) -> DataFrame:
    """Distance tests: all windows iterated naively, by the sweep, and with shortcuts. ``scored`` must come without them."""
    k = F.least("k", "n_distinct")
    naive, swept = F.col("iterations") * k * w, F.col("iterations") * (k + w)
    short = F.when((F.col("rule") == "iterate"), naive).when(F.col("k") == 1, 0).otherwise(w)
    return scored.agg(*[F.sum(x.cast("long")).alias(n) for x, n in ((naive, "naive"), (swept, "sweep"), (short, "shortcuts"))])


def markov_ops(scored: DataFrame, w: int) -> DataFrame:
    """Counts and divisions: full model, lazy, and with counts kept under rotation."""
    full = F.lit(w - 1) + F.col("k") * F.col("k")
    kept = F.when(F.col("rule") == "rotation", 2).otherwise(w - 1)
    return scored.agg(F.sum(full.cast("long")).alias("full_model"), F.sum(F.lit(w - 1).cast("long")).alias("lazy"), F.sum(kept.cast("long")).alias("with_rotation"), F.sum((F.col("k") * F.col("k")).cast("long")).alias("all_ratios"), F.sum("divisions").alias("tail_ratios"))


def mean_k(scored: DataFrame) -> DataFrame:
    return scored.agg(F.avg("k").alias("by_window"), F.count(F.lit(1)).alias("windows"))


def state_bytes(readings: DataFrame, w: int) -> DataFrame:
    """Bytes of the values in all windows, eight each."""
    return readings.groupBy(*SERIES).agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)).alias("series"), F.sum(F.least("n", F.lit(w)) * 8).alias("bytes"))


def iteration_histogram(scored: DataFrame) -> DataFrame:
    return scored.groupBy("iterations").agg(F.count(F.lit(1)).alias("windows"))
