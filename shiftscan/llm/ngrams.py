"""Katz backoff of any order, over stored tables.

For each order n there are two tables, written in folders by a hash of the context: the
n-grams with their discounted counts, and the contexts with their totals and backoff
weights. A token's probability is worked out recursively: that of its n-gram where
training has seen it, else the context's weight times the probability one order down.
Counts up to ``katz.CUT`` have Good-Turing discounts, larger ones lose ``1 / (c + 1)``;
every context's probabilities over the known words and the unknown one sum to one.

``katz.score`` gives the same for order 2 with each occurrence crossing the cluster
once. This form moves every token once for each join, about three an order, and is for
models whose tables are wanted or whose order is higher.

Words and contexts are 64-bit hashes. Defined results: a null text is empty; an empty
text is one end token; repeated rows are scored each; without training rows every token
is unknown with probability one; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import log10

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..store import new_path, stored
from .common import need, text_of
from .katz import CUT, discounts

START, END = "\x02", "\x03"  # blanks part words, so no word is one of these alone but by intent
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

TABLES = {"grams": "context long, w long, shorter long, c long, kept double, log_p double", "contexts": "context long, total long, log_weight double"}


@dataclass(frozen=True)
class Model:
    """Where a model's tables are: ``grams-n`` (context, w, shorter, c, kept, log_p) and ``contexts-n`` (context, total, log_weight)."""

    path: str
    order: int
    total: int
    log_unknown: float

    def table(self, spark: SparkSession, kind: str, n: int) -> DataFrame:
        return spark.read.schema(f"{TABLES[kind]}, part int").parquet(f"{self.path}/{kind}-{n}").drop("part")


def tokens(docs: DataFrame, order: int, *keep: str) -> DataFrame:
    """Every token with ``w`` and ``h1`` .. ``h{order}``: the hash of the n - 1 tokens before it."""
    words = F.regexp_extract_all(F.translate(text_of(), UPPER, LOWER), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))
    padded = docs.select(*keep, F.concat(F.array_repeat(F.lit(START), order - 1), words, F.array(F.lit(END))).alias("_all"))
    before = F.transform(F.sequence(F.lit(order), F.size("_all")), lambda i: F.struct(F.get("_all", i - 1).alias("w"), *[F.xxhash64(F.slice("_all", i - n + 1, F.lit(n - 1)), F.lit(n)).alias(f"h{n}") for n in range(1, order + 1)]))
    return padded.select(*keep, F.explode(before).alias("t")).select(*keep, F.xxhash64("t.w", F.lit(0)).alias("w"), *[F.col(f"t.h{n}").alias(f"h{n}") for n in range(1, order + 1)])


def _kept(low: list[float]) -> Column:
    return F.when(F.col("c") > CUT, F.col("c") - 1 / (F.col("c") + 1)).otherwise(F.get(F.array(*map(F.lit, low)), F.col("c").cast("int")))


def train(docs: DataFrame, order: int = 3, path: str | None = None, parts: int = 16) -> Model:
    """Counts, discounts and backoff weights of all texts of ``docs``, written below ``path``."""
    need(docs, "text")
    spark = docs.sparkSession
    path = path or new_path(spark, "model")
    model = Model(path, order, 0, 0.0)

    def write(df: DataFrame, kind: str, n: int) -> DataFrame:
        df.withColumn("part", F.pmod("context", F.lit(parts)).cast("int")).write.partitionBy("part").parquet(f"{path}/{kind}-{n}")
        return model.table(spark, kind, n)

    seen = tokens(docs, order)
    below: DataFrame | None = None
    total, unknown = 0, 1.0
    for n in range(1, order + 1):
        shorter = F.col(f"h{n - 1}") if n > 1 else F.lit(0).cast("long")
        counts = stored(seen.groupBy(F.col(f"h{n}").alias("context"), "w").agg(F.first(shorter).alias("shorter"), F.count(F.lit(1)).alias("c")), "counts")
        often = {r.c: r.n for r in counts.where(F.col("c") <= CUT + 1).groupBy("c").agg(F.count(F.lit(1)).alias("n")).collect()}
        kept = counts.withColumn("kept", _kept(discounts(often)))
        totals = kept.groupBy("context").agg(F.sum("c").alias("total"), F.sum("kept").alias("mass"))
        grams = write(kept.join(totals.select("context", "total"), "context").select("context", "w", "shorter", "c", "kept", F.log10(F.col("kept") / F.col("total")).alias("log_p")), "grams", n)
        if n == 1:
            got = totals.first()
            total, unknown = (int(got.total), 1 - got.mass / got.total) if got else (0, 1.0)
            write(totals.select("context", "total", F.lit(0.0).alias("log_weight")), "contexts", n)
        else:
            # What the shorter context gives to the words seen here; they have been seen there too.
            down = below.select(F.col("context").alias("shorter"), "w", F.pow(F.lit(10.0), "log_p").alias("p"))
            given = grams.join(down, ["shorter", "w"]).groupBy("context").agg(F.sum("p").alias("given"))
            left = (1 - F.col("mass") / F.col("total")) / F.greatest(1 - F.col("given"), F.lit(1e-15))
            write(totals.join(given, "context").select("context", "total", F.log10(left).alias("log_weight")), "contexts", n)
        below = grams
    return Model(path, order, total, log10(unknown))


def score(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, n_tokens, score) of every row of ``docs`` (doc_id, text)."""
    need(docs, "doc_id", "text")
    spark = docs.sparkSession
    rows = stored(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text"), F.monotonically_increasing_id().alias("row")), "rows")
    out = tokens(rows, model.order, "row")
    p = F.lit(model.log_unknown)
    for n in range(1, model.order + 1):
        grams = model.table(spark, "grams", n).select(F.col("context").alias(f"h{n}"), "w", F.col("log_p").alias(f"p{n}"))
        out = out.join(grams, [f"h{n}", "w"], "left")
        if n > 1:
            out = out.join(model.table(spark, "contexts", n).select(F.col("context").alias(f"h{n}"), F.col("log_weight").alias(f"a{n}")), f"h{n}", "left")
            p = F.coalesce(f"p{n}", F.coalesce(f"a{n}", F.lit(0.0)) + p)
        else:
            p = F.coalesce(f"p{n}", p)
    sums = out.groupBy("row").agg(F.count(F.lit(1)).alias("n_tokens"), F.sum(p).alias("score"))
    return rows.drop("text").join(sums, "row").select("doc_id", "n_tokens", "score")
