"""Routing of readings to workers, its invariant and its balance."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def modulo(df: DataFrame, workers: int) -> DataFrame:
    return df.withColumn("worker", F.pmod("machine_id", F.lit(workers)).cast("int"))


def placed(df: DataFrame, workers: int) -> DataFrame:
    """Rows of a worker in one partition."""
    return modulo(df, workers).repartition(workers, "worker")


def by_series(df: DataFrame, parts: int | None = None) -> DataFrame:
    keys = ["machine_id", "sensor_id"]
    return df.repartition(parts, *keys) if parts else df.repartition(*keys)


def check_affinity(df: DataFrame) -> DataFrame:
    """Workers of each machine; one is expected."""
    return df.groupBy("machine_id").agg(F.count_distinct("worker").alias("workers"), F.count(F.lit(1)).alias("readings"))


def check_order(df: DataFrame) -> DataFrame:
    """Per series: rows whose time lies before that of the row which arrived before them; none are expected."""
    keys = ["machine_id", "sensor_id"]
    marked = df.withColumn("before", F.lag("ts").over(Window.partitionBy(*keys).orderBy("tick")))
    return marked.groupBy(*keys).agg(F.count(F.lit(1)).alias("readings"), F.count_if(F.col("before") > F.col("ts")).alias("backwards"))


def load_profile(df: DataFrame, workers: int, bucket: str = "1 day") -> DataFrame:
    """Readings of each worker by time, and the most loaded worker against the mean."""
    load = modulo(df, workers).groupBy(F.window("ts", bucket).start.alias("bucket"), "worker").agg(F.count(F.lit(1)).alias("readings"))
    all_ = Window.partitionBy("bucket")
    return load.select("bucket", "worker", "readings", (F.max("readings").over(all_) * F.lit(workers) / F.sum("readings").over(all_)).alias("skew"))


def balanced(spark, load: DataFrame, workers: int, most: int = 100_000) -> DataFrame:
    """(machine_id, worker) by longest load first; ``load``: (machine_id, readings).

    The ``most`` largest machines are placed one by one on the driver. All others are
    smaller than any of those: a hash spreads them over the workers in proportion to the
    room that each has left, so that what is placed stays within one of them of even.
    """
    rows = load.orderBy(F.desc("readings"), "machine_id").limit(most).collect()
    heap = [(0, k) for k in range(workers)]
    out = []
    for r in rows:
        total, k = heapq.heappop(heap)
        heapq.heappush(heap, (total + r.readings, k))
        out.append((r.machine_id, k))
    placed = spark.createDataFrame(out, "machine_id long, worker int")
    if len(rows) < most:
        return placed
    rest = load.join(F.broadcast(placed), "machine_id", "left_anti")
    sums = dict((k, t) for t, k in heap)
    goal = (sum(sums.values()) + (rest.agg(F.sum("readings")).first()[0] or 0)) / workers
    room = [max(goal - sums[k], 0.0) for k in range(workers)]
    upto, worker = 0.0, F.lit(workers - 1)
    for k in reversed(range(workers - 1)):
        upto = sum(room[: k + 1]) / (sum(room) or 1.0)
        worker = F.when(F.pmod(F.xxhash64("machine_id"), F.lit(1 << 30)) < F.lit(int(upto * (1 << 30))), F.lit(k)).otherwise(worker)
    return placed.unionByName(rest.select("machine_id", worker.cast("int").alias("worker")))
