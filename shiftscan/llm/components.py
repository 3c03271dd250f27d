"""Connected components of a table of links, by alternating star contraction.

Every step is a grouped minimum (combined before its shuffle) and a join that
adaptive execution can split, so a vertex with very many links is no bottleneck.
Links and labels stay distributed; only a two-number fingerprint of the round's
edge table reaches the driver, to see whether another round is needed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored


def _fingerprint(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def components(links: DataFrame, a: str = "a", b: str = "b", rounds: int = 60) -> DataFrame:
    """(id, component): every vertex that has a link, with the smallest id it reaches.

    Links may be repeated, reversed or from a vertex to itself; those with a null
    end are ignored. A vertex whose only link leads to itself is its own component.
    """
    pairs = links.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where("u is not null and v is not null")
    edges = stored(pairs.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "links")
    seen = _fingerprint(edges)
    for _ in range(rounds):
        # Large star: neighbours above a vertex move to the smallest neighbour.
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        big = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        lone = edges.where("u = v")
        big = big.union(lone)
        # Small star: neighbours below a vertex, and the vertex, move to the smallest of them.
        low = big.groupBy("u").agg(F.min("v").alias("m"))
        small = big.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        edges = stored(small.distinct(), "links")
        now = _fingerprint(edges)
        if now == seen:
            return edges.groupBy("u").agg(F.min("v").alias("component")).select(F.col("u").alias("id"), "component")
        seen = now
    raise RuntimeError(f"components did not settle within {rounds} rounds")
