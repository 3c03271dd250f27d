"""k-means of a window in built-in expressions alone: no Python on the executors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CENTRES = "array<struct<s: bigint, n: bigint>>"


def _label(x: Column, c: Column) -> Column:
    """How many borders between neighbouring centres a value has reached."""
    pairs = F.zip_with(F.slice(c, F.lit(1), F.size(c) - 1), F.slice(c, F.lit(2), F.size(c) - 1), lambda a, b: F.when(2 * x * a.n * b.n >= a.s * b.n + b.s * a.n, 1).otherwise(0))
    return F.aggregate(pairs, F.lit(0), lambda t, y: t + y)


def _round(w: Column, c: Column) -> Column:
    labels = F.transform(w, lambda x: _label(x, c))
    marked = F.arrays_zip(w.alias("x"), labels.alias("l"))

    def moved(centre: Column, i: Column) -> Column:
        own = F.filter(marked, lambda m: m.l == i)
        return F.when(F.size(own) == 0, centre).otherwise(F.struct(F.aggregate(own, F.lit(0).cast("bigint"), lambda t, m: t + m.x).alias("s"), F.size(own).cast("bigint").alias("n")))

    return F.transform(c, moved).cast(CENTRES)


def labelled(win: DataFrame, max_iter: int = 50, seeds: Column | None = None) -> DataFrame:
    """``labels`` of windows with columns ``w`` and ``k``; ``seeds`` where they cannot be told from ``w``."""
    seeds = F.array_sort(F.slice(F.array_distinct("w"), F.lit(1), F.col("k"))) if seeds is None else seeds
    start = F.struct(F.transform(seeds, lambda x: F.struct(x.cast("bigint").alias("s"), F.lit(1).cast("bigint").alias("n"))).cast(CENTRES).alias("c"), F.lit(False).alias("done"))

    def step(a: Column, _: Column) -> Column:
        def settle(new: Column) -> Column:
            same = F.forall(F.arrays_zip(new.alias("a"), a.c.alias("b")), lambda z: z.a.s * z.b.n == z.b.s * z.a.n)
            return F.struct(new.alias("c"), same.alias("done"))

        return F.when(a.done, a).otherwise(F.transform(F.array(_round(F.col("w"), a.c)), settle)[0])

    # The centres stay behind a column of their own, so that they are worked out once.
    centres = win.withColumn("_c", F.aggregate(F.sequence(F.lit(1), F.lit(max_iter)), start, step).c)
    return centres.withColumn("labels", F.transform("w", lambda x: _label(x, F.col("_c")))).drop("_c")
