"""Aggregates, rankings and reports over scored windows and readings."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def shares(scored: DataFrame, *by: str) -> DataFrame:
    """Windows per exclusive rule."""
    return scored.groupBy(*by).agg(F.count(F.lit(1)).alias("windows"), *[F.count_if(F.col("rule") == r).alias(r) for r in ("rotation", "single", "few", "iterate")])


def share_rollup(scored: DataFrame) -> DataFrame:
    return scored.rollup("sensor_id", "rule").agg(F.count(F.lit(1)).alias("windows"))


def share_cube(scored: DataFrame) -> DataFrame:
    return scored.cube("sensor_id", "rule").agg(F.count(F.lit(1)).alias("windows"))


def share_sets(scored: DataFrame) -> DataFrame:
    return scored.groupingSets([["sensor_id"], ["machine_id"], ["rule"]], "sensor_id", "machine_id", "rule").agg(F.count(F.lit(1)).alias("windows"))


def dispersion(readings: DataFrame, exact: bool = True) -> DataFrame:
    """Distinct values per sensor: what a memo can hope for."""
    count = F.count_distinct if exact else F.approx_count_distinct
    return readings.groupBy("sensor_id").agg(F.count(F.lit(1)).alias("readings"), count("v").alias("distinct_values"))


def quantiles(scored: DataFrame, exact: bool = True) -> DataFrame:
    p = [F.lit(x) for x in (0.01, 0.1, 0.5)]
    of = (lambda q: F.percentile("p", q)) if exact else (lambda q: F.percentile_approx("p", q))
    return scored.groupBy("sensor_id").agg(*[of(q).alias(n) for q, n in zip(p, ("p01", "p10", "p50"))])


def worst_window(scored: DataFrame) -> DataFrame:
    """The least likely window of each series, the earliest of equals."""
    return scored.groupBy("machine_id", "sensor_id").agg(F.min(F.struct("p", "rn")).alias("x"), F.count_if(F.col("p") < F.col("threshold")).alias("anomalies")).select("machine_id", "sensor_id", F.col("x.p").alias("p"), F.col("x.rn").alias("rn"), "anomalies")


def rank_series(scored: DataFrame) -> DataFrame:
    """Sensors of each machine by their number of unlikely windows."""
    counts = scored.groupBy("machine_id", "sensor_id").agg(F.count_if(F.col("p") < 0.05).alias("unlikely"))
    order = Window.partitionBy("machine_id").orderBy(F.desc("unlikely"))
    total = Window.partitionBy("machine_id").orderBy(F.desc("unlikely"), "sensor_id")
    return counts.select("machine_id", "sensor_id", "unlikely", F.rank().over(order).alias("rank"), F.dense_rank().over(order).alias("dense"), F.row_number().over(total).alias("place"), F.ntile(2).over(total).alias("half"))


def topk(scored: DataFrame, k: int) -> DataFrame:
    return scored.orderBy("p", "machine_id", "sensor_id", "rn").limit(k)


def topk_per_machine(scored: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("machine_id").orderBy("p", "sensor_id", "rn")
    return scored.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k)


def pair_maps(scored: DataFrame) -> DataFrame:
    """``counts``: a map from each transition of a window, written ``a>b``, to how often it occurs. Needs ``labels``."""
    steps = F.zip_with(F.slice("labels", F.lit(1), F.size("labels") - 1), F.slice("labels", F.lit(2), F.size("labels") - 1), lambda a, b: F.concat_ws(">", a.cast("string"), b.cast("string")))
    own = F.transform(F.array_distinct("_steps"), lambda x: F.struct(x.alias("pair"), F.size(F.filter("_steps", lambda y: y == x)).alias("n")))
    return scored.withColumn("_steps", steps).withColumn("counts", F.map_from_entries(own)).drop("_steps")
