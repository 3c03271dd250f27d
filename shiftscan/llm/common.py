"""What several operators share: stored intermediate tables and column checks."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import time

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..ship import ship
from ..store import stored  # noqa: F401


def need(df: DataFrame, *names: str) -> None:
    if missing := [x for x in names if x not in df.columns]:
        raise ValueError(f"missing columns: {', '.join(missing)}")


def text_of(column: str = "text"):
    """A null text counts as empty."""
    return F.coalesce(F.col(column).cast("string"), F.lit(""))


def prepare(spark: SparkSession, rows: int = 1000) -> None:
    """Before Python work on texts: the package goes to the executors, and Arrow batches have few rows.

    Batches are bounded by rows only, texts are long, and the plan is run by the caller;
    so the limit stays set for the session, unless it is lower already.
    """
    ship(spark)
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = int(spark.conf.get(key))
    if not 0 < before <= rows:
        spark.conf.set(key, str(rows))


def trim() -> None:
    """Gives memory that a Python worker no longer uses back to the system; the worker lives on for other tasks."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def forget(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of plans that nothing refers to any more.

    Its cleaner works behind the driver's garbage collector, which else may not run for hours.
    """
    for _ in range(2):
        gc.collect()
        spark._jvm.System.gc()
        time.sleep(1)
