"""Relational helpers around readings and anomalies."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SERIES = ["machine_id", "sensor_id"]


def only_sensors(df: DataFrame, names: list[str]) -> DataFrame:
    return df.where(F.col("sensor_id").isin(names))


def pivot_tick(readings: DataFrame, sensors: list[str]) -> DataFrame:
    """One row per machine and instant, a column per sensor."""
    return readings.groupBy("machine_id", "ts", "tick").pivot("sensor_id", sensors).agg(F.first("v"))


def name_machine(anomalies: DataFrame, supplier: DataFrame, nation: DataFrame, region: DataFrame, hint: str | None = None) -> DataFrame:
    """Supplier, nation and region of a machine. ``hint``: a join strategy; else the planner's choice."""
    s = supplier.select(F.col("s_suppkey").alias("machine_id"), "s_name", F.col("s_nationkey").alias("n_nationkey"))
    n = nation.select("n_nationkey", "n_name", F.col("n_regionkey").alias("r_regionkey"))
    r = region.select("r_regionkey", "r_name")
    if hint:
        s = s.hint(hint)
    return anomalies.join(s, "machine_id").join(n, "n_nationkey").join(r, "r_regionkey")


def coverage(machines: DataFrame, anomalies: DataFrame) -> DataFrame:
    """Every machine with its number of anomalies, zero included."""
    return machines.join(anomalies.groupBy("machine_id").agg(F.count(F.lit(1)).alias("n")), "machine_id", "left").select(*machines.columns, F.coalesce("n", F.lit(0)).alias("anomalies"))


def active_series(series: DataFrame, anomalies: DataFrame) -> DataFrame:
    return series.join(anomalies.select(*SERIES).distinct(), SERIES, "left_semi")


def silent_machines(machines: DataFrame, readings: DataFrame, low, high) -> DataFrame:
    """Machines without a reading in a span."""
    return machines.join(readings.where((F.col("ts") >= low) & (F.col("ts") < high)).select("machine_id"), "machine_id", "left_anti")


def diff_runs(a: DataFrame, b: DataFrame) -> DataFrame:
    """Windows whose probability differs between two runs, or that only one of them has."""
    keys = [*SERIES, "rn"]
    both = a.select(*keys, F.col("p").alias("p_a")).join(b.select(*keys, F.col("p").alias("p_b")), keys, "full")
    return both.where(~F.col("p_a").eqNullSafe(F.col("p_b")))


def asof(left: DataFrame, right: DataFrame, on: str, ts: str, value: str) -> DataFrame:
    """``value`` of the latest row of ``right`` not after each row of ``left``, by key: one union and one sort."""
    rows = left.select(*left.columns, F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"))
    other = right.select(F.col(on), F.col(ts), F.col(value).alias("_v"), F.lit(0).alias("_side"))
    order = Window.partitionBy(on).orderBy(ts, "_side", "_v").rowsBetween(Window.unboundedPreceding, 0)
    both = rows.unionByName(other, allowMissingColumns=True)
    return both.withColumn(value, F.last("_v", ignorenulls=True).over(order)).where("_side = 1").drop("_v", "_side")


def within(left: DataFrame, right: DataFrame, on: str, hours: int) -> DataFrame:
    """Pairs of a key at most ``hours`` apart: an equality join on time buckets, then the exact test."""
    span = F.expr(f"INTERVAL {hours} HOURS")
    width = hours * 3600
    number = lambda c: F.floor(F.unix_seconds(c.cast("timestamp")) / width)
    r = right.withColumn("_b", F.explode(F.array(*[number(F.col("right_ts")) + k for k in (-1, 0, 1)])))
    near = left.withColumn("_b", number(F.col("ts"))).join(r, [on, "_b"])
    return near.where(F.col("right_ts").between(F.col("ts") - span, F.col("ts") + span)).drop("_b")


def setops(a: DataFrame, b: DataFrame, kind: str) -> DataFrame:
    return {"union": a.unionByName(b), "intersect": a.intersect(b), "intersect_all": a.intersectAll(b), "except": a.subtract(b), "except_all": a.exceptAll(b)}[kind]


def time_parts(df: DataFrame, ts: str = "ts") -> DataFrame:
    t = F.col(ts)
    return df.withColumns({"day": F.date_trunc("day", t), "hour": F.hour(t), "micros": F.unix_micros(t.cast("timestamp"))})
