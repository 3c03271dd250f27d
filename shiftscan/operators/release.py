"""Ordered release: an anomaly leaves once no worker can still produce an earlier one."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..store import stored

FAR = "9999-12-31 00:00:00"


def progress(readings: DataFrame, workers: int, epoch: int = 1000, idle_epochs: int | None = None) -> DataFrame:
    """(epoch, worker, progress_ts): the latest time each worker has processed by the end of each epoch of arrivals.

    A worker without a row in the last ``idle_epochs`` epochs signals the far future.
    """
    at = F.floor(F.col("tick") / epoch)
    seen = stored(readings.select(at.alias("epoch"), F.pmod("machine_id", F.lit(workers)).cast("int").alias("worker"), "ts").groupBy("epoch", "worker").agg(F.max("ts").alias("ts")), "seen")
    grid = seen.select("epoch").distinct().select("epoch", F.explode(F.sequence(F.lit(0), F.lit(workers - 1))).alias("worker"))
    upto = Window.partitionBy("worker").orderBy("epoch").rowsBetween(Window.unboundedPreceding, 0)
    rows = grid.join(seen, ["epoch", "worker"], "left").select("epoch", "worker", F.max("ts").over(upto).alias("progress_ts"), F.max(F.when(F.col("ts").isNotNull(), F.col("epoch"))).over(upto).alias("last"))
    if idle_epochs is not None:
        idle = F.col("last").isNull() | (F.col("epoch") - F.col("last") > idle_epochs)
        rows = rows.withColumn("progress_ts", F.when(idle, F.lit(FAR).cast("timestamp_ntz")).otherwise(F.col("progress_ts")))
    return rows.drop("last")


def frontier(progress_: DataFrame) -> DataFrame:
    """(epoch, frontier): the least progress; an epoch in which some worker has none holds everything back."""
    held = F.count_if(F.col("progress_ts").isNull()) > 0
    return progress_.groupBy("epoch").agg(F.when(~held, F.min("progress_ts")).alias("frontier")).where("frontier is not null")


def gate(anomalies: DataFrame, progress_: DataFrame) -> DataFrame:
    """``released_at``: the first epoch whose frontier lies beyond an anomaly; null if none does.

    Anomalies and the frontier's steps are sorted together, backwards and day by day; what
    the days after a day have to offer is one row for each, so one per day of the calendar.
    Both inputs are written first, since each is used twice and stands for the whole chain.
    """
    steps = stored(frontier(progress_).groupBy(F.col("frontier").alias("_at")).agg(F.min("epoch").alias("_epoch")).withColumn("_day", F.date_trunc("day", "_at")), "steps")
    rows = stored(anomalies.withColumns({"_at": F.col("ts"), "_day": F.date_trunc("day", "ts")}), "anomalies")
    days = steps.select("_day", "_epoch").unionByName(rows.select("_day"), allowMissingColumns=True).groupBy("_day").agg(F.min("_epoch").alias("_epoch"))
    after = F.min("_epoch").over(Window.orderBy(F.desc("_day")).rowsBetween(Window.unboundedPreceding, -1))
    # At equal times the anomaly comes first: a frontier must lie beyond it.
    upto = Window.partitionBy("_day").orderBy(F.desc("_at"), F.col("_epoch").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    both = rows.unionByName(steps, allowMissingColumns=True).withColumns({"_near": F.min("_epoch").over(upto)}).where("_epoch is null")
    placed = both.join(F.broadcast(days.select("_day", after.alias("_later"))), "_day", "left")
    return placed.withColumn("released_at", F.least("_near", "_later")).drop("_at", "_day", "_epoch", "_near", "_later")


def delays(released: DataFrame, epoch: int = 1000) -> DataFrame:
    """(delay, outputs): epochs between an anomaly's arrival and its release; null for those not released."""
    return released.groupBy((F.col("released_at") - F.floor(F.col("tick") / epoch)).cast("long").alias("delay")).agg(F.count(F.lit(1)).alias("outputs"))


def overhead(released: DataFrame, epoch: int = 1000) -> DataFrame:
    """What the gate costs: outputs, those held over an epoch's end, their epochs of waiting, and the longest wait."""
    wait = F.col("released_at") - F.floor(F.col("tick") / epoch)
    return released.agg(F.count(F.lit(1)).alias("outputs"), F.count("released_at").alias("released"), F.count_if(wait > 0).alias("held"), F.sum(wait).cast("long").alias("epochs_waited"), F.max(wait).cast("long").alias("longest"))


def unsynced(anomalies: DataFrame, workers: int) -> DataFrame:
    """Output order without the gate: arrival plus a fixed lag of the worker."""
    worker = F.pmod("machine_id", F.lit(workers))
    return anomalies.withColumn("finished", F.col("tick") + F.pmod(worker * 7, F.lit(13)) * 100)


def inversions(out: DataFrame, place: str, span: str) -> DataFrame:
    """(outputs, inversions) per ``span``: consecutive outputs whose times run backwards."""
    order = Window.partitionBy(span).orderBy(place, "ts", "machine_id", "sensor_id", "rn")
    marked = out.withColumn("before", F.lag("ts").over(order))
    return marked.groupBy(span).agg(F.count(F.lit(1)).alias("outputs"), F.count_if(F.col("before") > F.col("ts")).alias("inversions"))


def ordered(anomalies: DataFrame) -> DataFrame:
    """A total order: a series' anomalies at the same time leave as they were found."""
    return anomalies.orderBy("ts", "machine_id", "sensor_id", "rn")
