"""The chain as separate relational stages: readable, in built-in expressions, for moderate data.

Only windows that do not rotate are clustered; the others take their anchor's labels,
turned by the distance, through a join on (series, anchor).
"""

from __future__ import annotations

from math import log2

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import codec
from ..operators import windows
from ..operators.native import labelled
from ..sources.feeds import SERIES
from ..sources.params import attach


def anchored(win: DataFrame) -> DataFrame:
    """``seeds``, ``rotated`` and ``anchor`` of windows with columns ``w`` and ``k``."""
    order = Window.partitionBy(*SERIES).orderBy("rn")
    rows = win.withColumn("seeds", F.array_sort(F.slice(F.array_distinct("w"), F.lit(1), F.col("k"))))
    same = (F.col("arrived") == F.col("departed")) & (F.col("seeds") == F.lag("seeds").over(order))
    rows = rows.withColumn("rotated", F.coalesce(same, F.lit(False)))
    return rows.withColumn("anchor", F.last(F.when(~F.col("rotated"), F.col("rn")), ignorenulls=True).over(order))


def probability(labels: Column, w: int, n: int) -> Column:
    """Product of the last ``n`` transition ratios: two integer products and one division."""
    n = min(n, w - 1)
    if n * log2(max(w, 2)) > 62:
        raise ValueError("too many transitions for exact products of this window size")

    def product(count) -> Column:
        return F.aggregate(F.transform(F.sequence(F.lit(w - n), F.lit(w - 1)), count), F.lit(1).cast("bigint"), lambda a, x: a * x)

    at = lambda i: F.get(labels, i - 1)
    every = F.sequence(F.lit(1), F.lit(w - 1))
    joint = product(lambda t: F.size(F.filter(every, lambda u: (at(u) == at(t)) & (at(u + 1) == at(t + 1)))))
    leave = product(lambda t: F.size(F.filter(every, lambda u: at(u) == at(t))))
    return joint / leave


def score(readings: DataFrame, params: DataFrame, w: int = 10, n: int = 5, max_iter: int = 50) -> DataFrame:
    rows = anchored(attach(windows.count_windows(readings, w), params))
    base = labelled(rows.where("not rotated"), max_iter).select(*SERIES, F.col("rn").alias("anchor"), F.col("labels").alias("base"))
    turn = ((F.col("rn") - F.col("anchor")) % w).cast("int")
    joined = rows.drop("seeds", "w").join(base, [*SERIES, "anchor"])
    labels = F.concat(F.slice("base", turn + 1, F.lit(w)), F.slice("base", F.lit(1), turn))
    return joined.withColumn("labels", labels).withColumn("p", probability(F.col("labels"), w, n)).select(*SERIES, "rn", "ts", "rotated", "anchor", "labels", "p", "threshold")


def ingest(msgs: DataFrame, lazy: bool = False, parts: int | None = None) -> DataFrame:
    """Readings from messages, each machine's in one partition.

    Eager parses before the exchange and moves readings; lazy looks up the machine only,
    moves the text, and parses behind the exchange.
    """
    spread = [parts] if parts else []
    if lazy:
        return codec.parse_by_offset(codec.peek_machine(msgs).repartition(*spread, "machine_id").select("msg"))
    return codec.parse_by_offset(msgs).repartition(*spread, "machine_id")
