"""Named feeds of readings: (machine_id, sensor_id, ts, tick, v), in total order (ts, tick) per series."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

READING = T.StructType(
    [
        T.StructField("machine_id", T.LongType()),
        T.StructField("sensor_id", T.StringType()),
        T.StructField("ts", T.TimestampNTZType()),
        T.StructField("tick", T.LongType()),
        T.StructField("v", T.LongType()),
    ]
)
SERIES = ("machine_id", "sensor_id")
TEXT_TIME = "yyyy-MM-dd'T'HH:mm:ss[.SSSSSS]"  # to the microsecond; what text writers use unless told loses three digits


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _shaped(df: DataFrame, machine, sensor, ts, tick, v) -> DataFrame:
    return df.select(
        machine.cast("long").alias("machine_id"), sensor.cast("string").alias("sensor_id"), ts.cast("timestamp_ntz").alias("ts"), tick.cast("long").alias("tick"), v.cast("long").alias("v")
    )


def _events(machine, v):
    def make(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _shaped(table(spark, sf_dir, "events"), machine(), F.col("event_type"), F.col("ts"), F.col("event_id"), v())

    return make


def _grid():
    return F.floor(F.col("value") / 20)


def _line(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four sensors of one machine in each row; the whole row breaks ties of the date."""
    rows = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    order = Window.partitionBy("l_suppkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    rows = rows.withColumn("tick", F.row_number().over(order))
    values = [("quantity", F.round("l_quantity")), ("price", F.round(F.col("l_extendedprice") * 100)), ("discount", F.round(F.col("l_discount") * 100)), ("tax", F.round(F.col("l_tax") * 100))]
    wide = rows.select("l_suppkey", "l_shipdate", "tick", *[v.cast("long").alias(n) for n, v in values])
    long = wide.unpivot(["l_suppkey", "l_shipdate", "tick"], [n for n, _ in values], "sensor_id", "v")
    return _shaped(long, F.col("l_suppkey"), F.col("sensor_id"), F.col("l_shipdate"), F.col("tick"), F.col("v"))


def _orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shaped(table(spark, sf_dir, "orders"), F.col("o_custkey") % 10, F.lit("prio"), F.col("o_orderdate"), F.col("o_orderkey"), F.substring("o_orderpriority", 1, 1))


def _props(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shaped(table(spark, sf_dir, "events"), F.col("user_id") % 10, F.lit("k"), F.col("ts"), F.col("event_id"), F.get_json_object("props", "$.k"))


def _flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "labels").join(table(spark, sf_dir, "documents").select("doc_id", "source"), "doc_id")
    return _shaped(rows, F.regexp_extract("source", "([0-9]+)$", 1), F.lit("toxic"), F.lit("2020-01-01 00:00:00"), F.col("doc_id"), F.col("toxic"))


def _turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shaped(table(spark, sf_dir, "conversations"), F.col("conv_id"), F.col("role"), F.lit("2020-01-01 00:00:00"), F.col("turn"), F.floor(F.length("text") / 200))


def _embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("place", "x"))
    return _shaped(rows, F.col("vec_id"), F.col("label").cast("string"), F.lit("2020-01-01 00:00:00"), F.col("place"), F.floor(F.col("x").cast("double") * 20))


FEEDS = {
    "ev_single": _events(lambda: F.lit(0), _grid),
    "ev_ten": _events(lambda: F.col("user_id") % 10, _grid),
    "ev_many": _events(lambda: F.col("user_id"), _grid),
    "ev_alarm": _events(lambda: F.lit(0), lambda: F.when(F.col("value") > 150, 1).otherwise(0)),
    "li_sensors": _line,
    "ord_priority": _orders,
    "props_k": _props,
    "doc_flags": _flags,
    "turn_len": _turns,
    "emb_windows": _embeddings,
}


def feed(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return FEEDS[name](spark, sf_dir)


def fleet(readings: DataFrame, times: int) -> DataFrame:
    """Each machine ``times`` over, under machine ids of their own: the same readings as a longer feed."""
    copies = F.explode(F.sequence(F.lit(0), F.lit(times - 1))).alias("copy")
    return readings.select("*", copies).withColumn("machine_id", F.col("machine_id") * times + F.col("copy")).drop("copy")


def readings(spark: SparkSession, path: str, fmt: str = "csv", schema: T.StructType = READING) -> DataFrame:
    """CSV, JSON or Parquet readings; the schema is never inferred. Text holds times as in ``TEXT_TIME``."""
    return spark.read.schema(schema).option("timestampNTZFormat", TEXT_TIME).format(fmt).load(path)


def messages(spark: SparkSession, path: str) -> DataFrame:
    """Raw text messages, one a line, in column ``msg``."""
    return spark.read.text(path).withColumnRenamed("value", "msg")


def validate(raw: DataFrame, w: int, value: str = "raw", scale: int = 1) -> tuple[DataFrame, DataFrame]:
    """Readings fit for exact arithmetic, and those rejected with a reason.

    Values scale to integers; beyond the bound of ``fits`` sums of a window could overflow.
    """
    x = F.col(value).cast("double")
    most = (1 << 61) // (w * w)
    reason = F.when(x.isNull(), "null").when(F.isnan(x), "nan").when(F.abs(x * scale) >= most, "overflow")
    marked = raw.withColumn("reason", reason)
    ok = marked.where("reason is null").drop("reason").withColumn("v", F.round(x * scale).cast("long"))
    return ok, marked.where("reason is not null")
