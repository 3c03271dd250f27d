"""Mixing sources to target weights over a tree of levels.

A token budget flows from the root: siblings share in proportion to their weights; a
node that cannot use its share (``epochs`` times the tokens below it) hands the rest to
its siblings, and only what a whole group cannot use reaches its ancestor's siblings.
A leaf that gets more than it has repeats whole epochs; the last, partial epoch is the
longest prefix, in that epoch's seeded order, whose tokens fit.

Prefixes are found without ordering any leaf as a whole: the order is a 64-bit hash,
its top 12 bits a bucket. Bucket sums (4096 a leaf at most) tell where a leaf's budget
ends; only that bucket's rows are sorted. Budgets are worked out on the driver from one
row per leaf as long as there are at most ``MAX_LEAVES``, and level by level on the
executors beyond, with equal results: the children of one node then meet in one task, and
leaves are joined by a shuffle instead of being broadcast.

Defined results: null levels are leaves named '' of their own; a row without words
has no tokens and goes with any selected prefix that reaches it; rows without a
doc_id are ordered by their text; equal rows tie and go in any order; other columns stay, whatever their names; an empty table
gives an empty result. Columns ``n_copies`` and ``n_tokens`` are replaced.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import need, stored, text_of

MAX_LEAVES = 100_000
BUCKET_BITS = 12


def share(budget: int, weights: dict[str, Fraction], caps: dict[str, int]) -> dict[str, int]:
    """Split among siblings by weight, none beyond its cap; whole tokens, remainders by name."""
    got = {k: 0 for k in caps}
    left = min(budget, sum(caps.values()))
    ratio = lambda k: (Fraction(caps[k]) / weights[k] if weights[k] else Fraction(1 << 200), k)
    open_ = sorted((k for k in caps if caps[k] > 0), key=ratio)
    total = sum(weights[k] for k in open_)
    while open_ and left > 0:
        k = open_[0]
        part = left * weights[k] / total if total else Fraction(left, len(open_))
        if part < caps[k]:
            break  # nobody else is short either
        got[k], left, total = caps[k], left - caps[k], total - weights[k]
        open_.pop(0)
    spare = left
    for k in open_:
        got[k] = min(caps[k], int(left * weights[k] / total) if total else left // len(open_))
        spare -= got[k]
    for k in sorted(open_):
        more = min(spare, caps[k] - got[k])
        got[k], spare = got[k] + more, spare - more
    return got


def budgets(tokens: dict[tuple, int], weights: dict[tuple, float], budget: int, epochs: int) -> dict[tuple, int]:
    """Budget of every leaf. ``weights``: of a path from the root; siblings not named weigh 1."""
    out: dict[tuple, int] = {}

    def below(prefix: tuple, mine: int, leaves: list[tuple]) -> None:
        if len(prefix) == len(leaves[0]):
            out[prefix] = mine
            return
        groups: dict[tuple, list[tuple]] = {}
        for leaf in leaves:
            groups.setdefault(leaf[: len(prefix) + 1], []).append(leaf)
        caps = {k: epochs * sum(tokens[x] for x in v) for k, v in groups.items()}
        part = share(mine, {k: Fraction(str(weights.get(k, 1))) for k in groups}, caps)
        for k, v in groups.items():
            below(k, part[k], v)

    if tokens:
        below((), budget, sorted(tokens))
    return out


def _splitter(own: list[str], weights: dict[tuple, float]):
    """Splits the budget of one node among its children, named by ``own``."""

    def split(children):
        keys = [tuple(k) for k in children[own].itertuples(index=False, name=None)]
        part = share(int(children["budget"].iloc[0]), {k: Fraction(str(weights.get(k, 1))) for k in keys}, dict(zip(keys, map(int, children["cap"]))))
        return children[own].assign(budget=[part[k] for k in keys])

    return split


def _spread(totals: DataFrame, names: list[str], weights: dict[tuple, float], goal: int, epochs: int) -> DataFrame:
    """``budgets`` level by level: the names of every leaf, its tokens and ``budget``."""
    above = totals.sparkSession.createDataFrame([(goal,)], "budget long")
    for depth in range(1, len(names) + 1):
        own, parent = names[:depth], names[: depth - 1]
        caps = totals.groupBy(*own).agg((F.sum("tokens") * epochs).alias("cap"))
        nodes = caps.join(above, parent) if parent else caps.join(F.broadcast(above))
        schema = ", ".join(f"{n} string" for n in own) + ", budget long"
        above = stored(nodes.groupBy(*parent).applyInPandas(_splitter(own, weights), schema), "budgets")
    return totals.join(above, names)


def words_of(text: Column) -> Column:
    return F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")).cast("long")


def mix(docs: DataFrame, levels: list[Column], weights: dict[tuple, float], fraction: float | None = None, budget: int | None = None, epochs: int = 4, seed: int = 13) -> DataFrame:
    """Selected rows of ``docs`` with ``n_copies`` (epochs it goes into) and ``n_tokens``.

    ``budget`` in tokens, or ``fraction`` of all tokens.
    """
    need(docs, "doc_id", "text")
    docs = docs.drop("n_copies", "n_tokens")
    names = [f"_l{k}" for k in range(len(levels))]
    # A row's own columns travel in one struct, so that no name of theirs can clash.
    leveled = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), *[F.coalesce(c.cast("string"), F.lit("")).alias(n) for n, c in zip(names, levels)],
        words_of(text_of()).alias("_n"), F.col("doc_id").alias("_id"), F.when(F.col("doc_id").isNull(), F.xxhash64(text_of())).alias("_k"),
    )
    slim = stored(leveled.drop("_row"), "tokens")
    totals = stored(slim.groupBy(*names).agg(F.sum("_n").alias("tokens")), "totals")
    n_leaves, n_tokens = totals.agg(F.count(F.lit(1)), F.coalesce(F.sum("tokens"), F.lit(0))).first()
    goal = budget if budget is not None else int(Fraction(str(fraction if fraction is not None else 1)) * int(n_tokens))
    few = n_leaves <= MAX_LEAVES
    small = F.broadcast if few else lambda df: df
    of_leaf = ", ".join(f"{n} string" for n in names)
    if few:
        tokens = {tuple(r[n] for n in names): int(r.tokens) for r in totals.collect()}
        plan = budgets(tokens, weights, goal, epochs)
        rows = [(*leaf, b // tokens[leaf] if tokens[leaf] else 0, b % tokens[leaf] if tokens[leaf] else 0) for leaf, b in plan.items()]
        leaves = docs.sparkSession.createDataFrame(rows, of_leaf + ", _epochs long, _rest long")
    else:
        whole = F.when(F.col("tokens") > 0, F.expr("budget div tokens")).otherwise(0).cast("long")
        rest = F.when(F.col("tokens") > 0, F.expr("budget % tokens")).otherwise(0).cast("long")
        leaves = stored(_spread(totals, names, weights, goal, epochs).select(*names, whole.alias("_epochs"), rest.alias("_rest")), "leaves")

    def ordered(df: DataFrame) -> DataFrame:
        return df.withColumn("_h", F.xxhash64(F.lit(seed), "_epochs", F.coalesce("_id", "_k"))).withColumn("_bucket", F.shiftrightunsigned("_h", 64 - BUCKET_BITS))

    sums = ordered(slim.join(small(leaves), names)).groupBy(*names, "_rest", "_bucket").agg(F.sum("_n").alias("t"))
    upto = F.sum("t").over(Window.partitionBy(*names).orderBy("_bucket"))
    crossed = sums.withColumn("_upto", upto).where("_upto > _rest").groupBy(*names).agg(F.min("_bucket").alias("_last"), F.min(F.col("_upto") - F.col("t")).alias("_before"))
    if few:
        cuts = docs.sparkSession.createDataFrame([tuple(r) for r in crossed.collect()], of_leaf + ", _last long, _before long")  # one row a leaf
    else:
        cuts = stored(crossed, "cuts")
    known = leaves.join(cuts, names, "left")
    placed = ordered(leveled.join(small(known), names))
    # A leaf whose rest was not crossed has no rest, or only rows without tokens.
    early = placed.where("_last is null or _bucket <> _last").withColumn("_more", ((F.col("_rest") > 0) & (F.col("_last").isNull() | (F.col("_bucket") < F.col("_last")))).cast("long"))
    running = F.sum("_n").over(Window.partitionBy(*names).orderBy(F.shiftrightunsigned("_h", 1), "_h", "_id").rowsBetween(Window.unboundedPreceding, 0))
    late = placed.where("_bucket = _last").withColumn("_more", (F.col("_before") + running <= F.col("_rest")).cast("long"))
    out = early.unionByName(late).select("_row.*", F.col("_n").alias("n_tokens"), (F.col("_epochs") + F.col("_more")).alias("n_copies"))
    return out.where("n_copies > 0")
