"""Near-duplicate documents by MinHash with tensored banding.

A table key is a pair ``(u_i, v_j)``: ``u`` and ``v`` are two small collections of
short minhash tuples, so ``collections**2`` tables cost only ``2 * collections``
tuples. At Jaccard similarity s a pair meets in some table with probability
``(1 - (1 - s**rows)**collections)**2``: 0.9985 at 0.8 and 0.9999 at 0.85 with the
defaults, and 60 minhashes stand in for the 600 that 100 separate bands would need.

Documents with the same shingle set form a class first; one of them goes on. In
each bucket all members meet the smallest one. The members of buckets that then still
lie in several components go on to an exact join on their rarest shingles, so that no
candidate pair that could join two components stays untested. Every link is confirmed on the
full shingle sets. Defined results: a null, empty or blank text has an empty set and
no links; repeated rows of one doc_id are one vertex; a row without a doc_id takes
its class's component, else null, and is kept only in the latter case; other columns
are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import tokens
from .common import need, prepare, stored, text_of, trim
from .components import components

_STEP = np.uint64(0x9E3779B97F4A7C15)


def shingle_sets(column, size: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, rows, row of each shingle, shingle): sorted and distinct within each row."""
    with np.errstate(over="ignore"):
        for w in tokens.words(column):
            n = len(w.hash)
            count = np.diff(w.first)
            if n >= size:
                h = w.hash[: n - size + 1].copy()
                for k in range(1, size):
                    h = h * _STEP + w.hash[k : n - size + 1 + k]
                doc = w.doc[: n - size + 1]
                whole = doc == w.doc[size - 1 :]
                h, doc = tokens.mix(h[whole]), doc[whole]
            else:
                h, doc = np.zeros(0, np.uint64), np.zeros(0, np.int64)
            short = np.flatnonzero((count > 0) & (count < size))
            if len(short):
                extra = np.zeros(len(short), np.uint64)
                for k in range(size - 1):
                    there = count[short] > k
                    extra[there] = extra[there] * _STEP + w.hash[w.first[short[there]] + k]
                h, doc = np.append(h, tokens.mix(extra ^ count[short].astype(np.uint64))), np.append(doc, short)
            order = np.lexsort((h, doc))
            h, doc = h[order], doc[order]
            fresh = np.ones(len(h), bool)
            fresh[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
            yield w.base, w.rows, doc[fresh], h[fresh]


def _signer(size: int, collections: int, rows: int, seed: int):
    rng = np.random.default_rng(seed)
    times = rng.integers(0, 1 << 63, 2 * collections * rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    plus = rng.integers(0, 1 << 63, 2 * collections * rows, dtype=np.uint64)
    each = pa.list_(pa.int64())
    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("set_a", pa.int64()), ("set_b", pa.int64()), ("u", each), ("v", each)])

    def sign(batches):
        for batch in batches:
            for base, n, doc, h in shingle_sets(batch.column(1), size):
                with np.errstate(over="ignore"):
                    count = np.bincount(doc, minlength=n)
                    full = np.flatnonzero(count)
                    start = (np.cumsum(count) - count)[full]
                    set_a, set_b = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
                    small = np.zeros((n, 2 * collections), np.uint64)
                    if len(full):
                        set_a[full] = np.add.reduceat(tokens.mix(h), start)
                        set_b[full] = np.add.reduceat(tokens.mix(h * _STEP + np.uint64(1)), start)
                        for k in range(2 * collections):
                            code = np.zeros(len(full), np.uint64)
                            for r in range(k * rows, (k + 1) * rows):
                                code = code * _STEP + np.minimum.reduceat(h * times[r] + plus[r], start)
                            small[full, k] = tokens.mix(code)
                small = small.view(np.int64)
                sides = [pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * collections), pa.array(np.ascontiguousarray(x).ravel())) for x in (small[:, :collections], small[:, collections:])]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(base, n), pa.array(count.astype(np.int64)), pa.array(set_a.view(np.int64)), pa.array(set_b.view(np.int64)), *sides], schema=schema)
        trim()

    return sign


def _verifier(size: int, percent: int):
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def check(batches):
        for batch in batches:
            row = 0
            while row < batch.num_rows:
                # Runs of whole pairs, by the bytes of their texts.
                to, held = row, 0
                while to < batch.num_rows and (held < (1 << 20) or to == row):
                    held += len(batch.column(2)[to].as_buffer() or b"") + len(batch.column(3)[to].as_buffer() or b"")
                    to += 1
                part = batch.slice(row, to - row)
                sides = []
                for c in (2, 3):
                    got = list(shingle_sets(part.column(c), size))
                    sides.append((np.concatenate([d + base for base, _, d, _ in got]), np.concatenate([h for *_, h in got])))
                doc, h = np.concatenate([sides[0][0], sides[1][0]]), np.concatenate([sides[0][1], sides[1][1]])
                order = np.lexsort((h, doc))
                doc, h = doc[order], h[order]
                twice = (doc[1:] == doc[:-1]) & (h[1:] == h[:-1])
                both = np.bincount(doc[1:][twice], minlength=part.num_rows)
                union = np.bincount(doc, minlength=part.num_rows) - both
                good = pa.array((union > 0) & (100 * both >= percent * union))
                yield pa.RecordBatch.from_arrays([part.column(0).filter(good), part.column(1).filter(good)], schema=schema)
                row = to
        trim()

    return check


def _shingles_of(size: int):
    schema = pa.schema([("id", pa.int64()), ("n", pa.int64()), ("c", pa.int64()), ("h", pa.int64())])

    def rows(batches):
        for batch in batches:
            for base, _, doc, h in shingle_sets(batch.column(3), size):
                take = pa.array(doc + base)
                yield pa.RecordBatch.from_arrays([*(batch.column(k).take(take) for k in range(3)), pa.array(h.view(np.int64))], schema=schema)

    return rows


def _rare_pairs(docs: DataFrame, size: int, percent: int) -> DataFrame:
    """(a, b, n_a, n_b): pairs of different components that share one of their rarest shingles.

    In any common order of shingles, sets of similarity t share one of the first
    ``n - ceil(t * n) + 1`` of either. Rarest first, what many texts have in common
    comes last and brings nothing together. ``docs``: (id, n, c, text).
    """
    rows = stored(docs.select("id", "n", "c", "text").mapInArrow(_shingles_of(size), "id long, n long, c long, h long"), "shingles")
    often = stored(rows.groupBy("h").agg(F.count(F.lit(1)).alias("df")).where("df > 1"), "often")
    ranked = rows.join(often, "h", "left").select("id", "n", "c", F.struct(F.coalesce("df", F.lit(1)).alias("df"), "h").alias("s"))
    need_first = F.col("n") - F.ceil(F.col("n") * percent / 100) + 1
    ordered = ranked.groupBy("id", "n", "c").agg(F.array_sort(F.collect_list("s")).alias("s"))
    first = ordered.select("id", "n", "c", F.posexplode(F.slice("s", F.lit(1), need_first.cast("int"))).alias("i", "s"))
    first = stored(first.where("s.df > 1").select(F.col("s.h").alias("h"), "id", "n", "c", (F.col("i") + 1).alias("i")), "rare")
    # The largest component of a shingle never meets itself: what is compared is what crosses to the others.
    sizes = first.groupBy("h", "c").agg(F.count(F.lit(1)).alias("k")).groupBy("h").agg(F.max(F.struct("k", "c")).alias("top"), F.count(F.lit(1)).alias("parts"))
    across = sizes.where("parts > 1").select("h", F.col("top.c").alias("main"))
    marked = stored(first.join(across, "h").select("h", "id", "n", "c", "i", (F.col("c") != F.col("main")).alias("minor")), "marked")
    # The smaller of two sets shares one of even fewer; and from the first shared shingle on, enough must be left.
    fewer = F.col("i") <= F.col("n") - F.ceil(F.col("n") * 2 * percent / (100 + percent)) + 1
    left = 1 + F.least(F.col("n_a") - F.col("i_a"), F.col("n_b") - F.col("i_b"))
    enough = left * (100 + percent) >= (F.col("n_a") + F.col("n_b")) * percent

    def crossing(larger: DataFrame, smaller: DataFrame) -> DataFrame:
        x, y = larger.drop("minor").toDF("h", "a", "n_a", "c_a", "i_a"), smaller.where(fewer).drop("minor").toDF("h", "b", "n_b", "c_b", "i_b")
        return x.join(y, (x.h == y.h) & (F.col("n_b") <= F.col("n_a")) & (F.col("c_a") != F.col("c_b")) & enough).drop("h")

    pairs = crossing(marked.where("minor"), marked).unionByName(crossing(marked.where("not minor"), marked.where("minor")))
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), F.when(F.col("a") < F.col("b"), F.col("n_a")).otherwise(F.col("n_b")).alias("n_a"), F.when(F.col("a") < F.col("b"), F.col("n_b")).otherwise(F.col("n_a")).alias("n_b"))


def near_duplicates(docs: DataFrame, size: int = 5, percent: int = 80, collections: int = 10, rows: int = 3, seed: int = 7) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of every row of ``docs`` (doc_id, text).

    ``percent``: least Jaccard similarity of the shingle sets, in hundredths.
    """
    need(docs, "doc_id", "text")
    spark = docs.sparkSession
    prepare(spark)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text"))
    signed = stored(texts.mapInArrow(_signer(size, collections, rows, seed), "doc_id long, n_shingles long, set_a long, set_b long, u array<long>, v array<long>"), "signed")
    # One vertex for each distinct shingle set; equal sets have equal collections.
    classes = signed.where("n_shingles > 0 and doc_id is not null").groupBy("n_shingles", "set_a", "set_b").agg(F.min("doc_id").alias("id"), F.first("u").alias("u"), F.first("v").alias("v"))
    # As many parts as a shuffle has: each row is about to become a hundred.
    classes = stored(classes.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "id"), "classes")
    keys = classes.select("id", "n_shingles", F.posexplode("u").alias("i", "p"), "v").select("id", "n_shingles", "i", "p", F.posexplode("v").alias("j", "q")).select(F.xxhash64("i", "p", "j", "q").alias("key"), "id", F.col("n_shingles").alias("n"))
    # Written, so that the join that follows deals both sides anew and adaptive execution can split a hot key.
    leads = stored(keys.groupBy("key").agg(F.min("id").alias("lead"), F.max("id").alias("last"), F.min_by("n", "id").alias("lead_n")).where("lead < last").drop("last"), "leads")
    members = stored(keys.join(leads, "key").where("id <> lead"), "buckets")

    def alike(n, m):
        return F.least(n, m) * 100 >= F.greatest(n, m) * percent

    def confirmed(pairs: DataFrame) -> DataFrame:
        full = pairs.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")), "a").select("b", "a", "text_a")
        full = full.join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b")), "b").select("a", "b", "text_a", "text_b")
        return stored(full.mapInArrow(_verifier(size, percent), "a long, b long"), "confirmed")

    links = confirmed(members.where(alike(F.col("n"), F.col("lead_n"))).select(F.col("lead").alias("a"), F.col("id").alias("b")).distinct())
    found = components(links)
    # What the first members could not settle: buckets whose other members lie in several components.
    label = F.coalesce("component", "id").alias("c")
    placed = members.join(found, "id", "left").select("key", "id", "n", label)
    open_keys = placed.groupBy("key").agg(F.min("c").alias("low"), F.max("c").alias("high")).where("low < high").select("key")
    rest = stored(placed.join(open_keys, "key").select("id", "n", "c").distinct(), "rest")
    if not rest.isEmpty():
        more = confirmed(_rare_pairs(rest.join(texts.withColumnRenamed("doc_id", "id"), "id"), size, percent).where(alike(F.col("n_a"), F.col("n_b"))).select("a", "b").distinct())
        if not more.isEmpty():
            found = components(links.union(more))
    of_class = classes.select("n_shingles", "set_a", "set_b", "id").join(found, "id", "left").select("n_shingles", "set_a", "set_b", F.coalesce("component", "id").alias("component"))
    out = signed.select("doc_id", "n_shingles", "set_a", "set_b").join(of_class, ["n_shingles", "set_a", "set_b"], "left")
    component = F.coalesce("component", "doc_id")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, component.isNull()).alias("kept"))
