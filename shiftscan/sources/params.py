"""Metadata per sensor: number of clusters and threshold. Broadcast behind a check of its size; joined by a shuffle beyond it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Clusters per sensor.
K_MAPS = {
    "A": {"click": 3, "error": 5, "purchase": 1, "signup": 2, "view": 11},
    "A53": {"click": 53, "error": 53, "purchase": 53, "signup": 53, "view": 53},
    "B": {"quantity": 11, "price": 4, "discount": 3, "tax": 5},
    "prio": {"prio": 6},
    "k": {"k": 5},
    "toxic": {"toxic": 2},
    "turns": {"system": 3, "user": 3, "assistant": 3},
    "alarm": {"click": 2, "error": 2, "purchase": 2, "signup": 2, "view": 2},
    "emb": {str(label): 3 for label in range(10)},
    "three": {"click": 3, "error": 3, "purchase": 3, "signup": 3, "view": 3},
}
MOST_SENSORS = 100_000


def load(spark: SparkSession, source: str | dict[str, int], threshold: float = 0.005) -> DataFrame:
    """(sensor_id, k, threshold) of a K-map by name, a mapping, or a Parquet path; validated."""
    if isinstance(source, str) and source not in K_MAPS:
        out = spark.read.parquet(source).select("sensor_id", F.col("k").cast("int").alias("k"), F.col("threshold").cast("double").alias("threshold"))
    else:
        out = spark.createDataFrame([(s, k, threshold) for s, k in (K_MAPS[source] if isinstance(source, str) else source).items()], "sensor_id string, k int, threshold double")
    bad, count = out.agg(F.count_if(~((F.col("k") >= 1) & F.col("threshold").between(0, 1)) | F.col("k").isNull()), F.count(F.lit(1))).first()
    if bad:
        raise ValueError("metadata needs k >= 1 and a threshold between 0 and 1")
    return F.broadcast(out) if count <= MOST_SENSORS else out


def attach(readings: DataFrame, params: DataFrame) -> DataFrame:
    return readings.join(params, "sensor_id")
