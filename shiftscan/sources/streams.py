"""Streaming sources and sinks."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..store import new_path

# State outside the heap; counting its rows would cost a read for every write.
STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.trackTotalNumberOfRows": "false",
}


def files(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream. Watermarks need a zoned timestamp, so ``ts`` is cast."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def rate(spark: SparkSession, rows_per_second: int) -> DataFrame:
    """A load generator with the shape of readings."""
    raw = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return raw.select((F.col("value") % 10).alias("machine_id"), (F.col("value") % 5).cast("string").alias("sensor_id"), F.col("timestamp").alias("ts"), F.col("value").alias("tick"), F.pmod(F.xxhash64("value"), F.lit(25)).alias("v"))


def to_batches(df: DataFrame, handle: Callable[[DataFrame, int], None], checkpoint: str, available_now: bool = True):
    """Runs a stream into ``handle(batch, id)``; with ``available_now`` until what is there is used up."""
    writer = df.writeStream.foreachBatch(handle).option("checkpointLocation", checkpoint).outputMode("append")
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def drained(df: DataFrame, table: str, mode: str = "append") -> DataFrame:
    """A stream run to its end into a table in memory, for tests and small results."""
    query = df.writeStream.format("memory").queryName(table).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return df.sparkSession.table(table)


def landed(df: DataFrame, name: str) -> DataFrame:
    """A stream run to its end into files of the shared folder, of any size: no row passes the driver, and state lies outside the heap."""
    spark = df.sparkSession
    path, before = new_path(spark, name), {c: spark.conf.get(c, None) for c in STATE}
    try:
        for c, x in STATE.items():
            spark.conf.set(c, x)  # a query keeps the settings it starts with
        query = df.writeStream.format("parquet").option("path", path).option("checkpointLocation", new_path(spark, f"{name}-checkpoint")).trigger(availableNow=True).start()
    finally:
        for c, x in before.items():
            spark.conf.unset(c) if x is None else spark.conf.set(c, x)
    query.awaitTermination()
    return spark.read.schema(df.schema).parquet(path)
