"""Where results go."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write(df: DataFrame, path: str, by: tuple[str, ...] = ("sensor_id",), mode: str = "overwrite") -> None:
    df.write.mode(mode).partitionBy(*by).parquet(path)


def drain(df: DataFrame) -> None:
    """Runs a plan into nothing, for measurement."""
    df.write.format("noop").mode("overwrite").save()
