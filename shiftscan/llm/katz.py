"""Katz backoff scoring of texts with word bigrams.

Counts come from the training rows of the same table. Counts of 1 to 5 are discounted
by Good-Turing, larger ones by a sliver, ``1 / (c + 1)`` of a token, so that every
context keeps something for words it has not seen. What a context keeps is spread over
the words unseen after it in proportion to the unigram model, whose own leftover is the
probability of an unknown word: both levels sum to one exactly. A text's tokens are its
words and one end; the first token's context is a start mark.

Every occurrence crosses the cluster once, packed by (word, context) in list columns,
into the bucket of its word; there a word's own count and all its pair counts meet.
Very frequent words are known by then (at most four per bucket) and spread by context.
A bucket leaves per-text sums, the pairs of held-out texts that still need their
context, each context's share of the normaliser, and its counts of counts. Those are
stored; the backoff table is partitioned by context and joined to the held-out pairs.

Words are 64-bit hashes. Defined results: a null text is empty; an empty text is one
end token; repeated rows are scored each, whatever their doc_id; without training rows
every token is unknown and the model gives it probability one (score 0); an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import tokens
from .common import forget, need, prepare, stored, text_of, trim

START, END = np.uint64(0x5851F42D4C957F2D), np.uint64(0x14057B7EF767814F)
CUT = 5  # counts up to this have Good-Turing discounts
MOST_TOKENS, MOST_TEXTS = 2_000_000, 30_000  # of a packed chunk
OUT = "kind int, id long, doc_id long, held boolean, v long, x double, y double, n long, m1 long, m2 long, m3 long, m4 long, m5 long"


def _texts(column) -> tuple:
    """(word, context, row) of every token of a batch, ends included."""
    word, context, row = [], [], []
    for w in tokens.words(column):
        count = np.diff(w.first)
        at = np.arange(w.rows + 1) + w.first  # each text's place once every text has an end
        n = len(w.hash) + w.rows
        ends = at[1:] - 1
        out = np.empty(n, np.uint64)
        inner = np.ones(n, bool)
        inner[ends] = False
        out[inner], out[ends] = w.hash, END
        before = np.empty(n, np.uint64)
        before[1:], before[at[:-1]] = out[:-1], START
        word.append(out), context.append(before), row.append(np.repeat(np.arange(w.rows) + w.base, count + 1))
    return tuple(np.concatenate(x) if x else np.zeros(0, np.uint64) for x in (word, context, row))


def _count_words(batches):
    def counted(parts):
        u, c = np.unique(np.concatenate(parts), return_counts=True)
        return pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(c.astype(np.int64))], names=["w", "c"])

    parts, held = [], 0
    for batch in batches:
        word, _, row = _texts(batch.column(1))
        train = ~np.array(batch.column(2).to_pylist(), bool)
        parts.append(word[train[row.astype(np.int64)]] if len(row) else word)
        held += len(parts[-1])
        if held > MOST_TOKENS:
            yield counted(parts)
            parts, held = [], 0
    if held:
        yield counted(parts)
    trim()


def _packer(buckets: int, hot: list[int]):
    frequent = np.sort(np.array(hot, np.int64).view(np.uint64))
    schema = pa.schema([("bucket", pa.int32()), ("chunk", pa.int64()), ("w", pa.list_(pa.int64())), ("pairs", pa.list_(pa.int32())), ("v", pa.list_(pa.int64())), ("times", pa.list_(pa.int32())), ("place", pa.list_(pa.int16())), ("ids", pa.list_(pa.int64())), ("held", pa.list_(pa.bool_()))])

    def flush(parts, chunk):
        word, context, place = (np.concatenate([p[k] for p in parts]) for k in range(3))
        ids, held = pa.concat_arrays([p[3] for p in parts]), np.concatenate([p[4] for p in parts])
        with np.errstate(over="ignore"):
            spread = np.isin(word, frequent)
            bucket = (tokens.mix(word ^ np.where(spread, tokens.mix(context), np.uint64(0))) % np.uint64(buckets)).astype(np.int32)
        order = np.lexsort((context, word, bucket))
        word, context, place, bucket = word[order], context[order], place[order], bucket[order]
        cut = np.flatnonzero(np.diff(bucket)) + 1
        for a, b in zip(np.concatenate([[0], cut]), np.concatenate([cut, [len(bucket)]])):
            w, v, p = word[a:b], context[a:b], place[a:b]
            fresh_w = np.concatenate([[True], w[1:] != w[:-1]])
            fresh = fresh_w | np.concatenate([[True], v[1:] != v[:-1]])
            first = np.flatnonzero(fresh)
            times = np.diff(np.append(first, len(w))).astype(np.int32)
            first_w = np.flatnonzero(fresh_w[first])
            pairs = np.diff(np.append(first_w, len(first))).astype(np.int32)
            # Only the texts that occur here, numbered anew.
            texts, local = np.unique(p, return_inverse=True)
            columns = [np.array([bucket[a]]), np.array([chunk])]
            lists = [w[first][first_w].view(np.int64), pairs, v[first].view(np.int64), times, local.astype(np.int16)]
            row = [pa.array(c, t.type) for c, t in zip(columns, schema)]
            row += [pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), pa.array(x)) for x in lists]
            own = ids.take(pa.array(texts))
            row += [pa.ListArray.from_arrays(pa.array([0, len(texts)], pa.int32()), own), pa.ListArray.from_arrays(pa.array([0, len(texts)], pa.int32()), pa.array(held[texts]))]
            key = pa.ListArray.from_arrays(pa.array([0, len(texts)], pa.int32()), pa.array(texts.astype(np.int32)))
            yield pa.RecordBatch.from_arrays([*row, key], names=[*schema.names, "nth"])

    def pack(batches):
        part = TaskContext.get().partitionId()
        parts, size, texts, chunk = [], 0, 0, 0
        for batch in batches:
            word, context, row = _texts(batch.column(1))
            parts.append((word, context, row.astype(np.int64) + texts, batch.column(0), np.array(batch.column(2).to_pylist(), bool)))
            size, texts = size + len(word), texts + batch.num_rows
            if size >= MOST_TOKENS or texts + 1000 >= MOST_TEXTS:
                yield from flush(parts, (part << 20) + chunk)
                parts, size, texts, chunk = [], 0, 0, chunk + 1
        if texts:
            yield from flush(parts, (part << 20) + chunk)
        trim()

    return pack


def discounts(n: dict[int, int]) -> list[float]:
    """Discounted counts of 0 to CUT, from counts of counts; half a token less where Good-Turing has no sound value."""
    out = [0.0]
    lost = (CUT + 1) * n.get(CUT + 1, 0) / n[1] if n.get(1) else 1.0
    for r in range(1, CUT + 1):
        d = ((r + 1) * n.get(r + 1, 0) / (r * n[r]) - lost) / (1 - lost) if n.get(r) and lost < 1 else 0.0
        out.append(r * d if 0 < d < 1 else r - 0.5)
    return out


def _kept(c: np.ndarray) -> np.ndarray:
    """Large counts less their sliver."""
    return c - 1 / (c + 1)


def _reducer(total: int, uni: list[float], unknown: float, hot: dict[int, int]):
    names = [x.split()[0] for x in OUT.split(", ")]
    kinds = [pa.int32(), pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.float64(), pa.float64(), *[pa.int64()] * 6]
    low = np.array(uni)

    def rows(size: int, /, **columns) -> pa.Table:
        return pa.Table.from_arrays([columns[c] if isinstance(columns.get(c), pa.Array) else pa.array(columns[c], t) if c in columns else pa.nulls(size, t) for c, t in zip(names, kinds)], names=names)

    def model(c: np.ndarray) -> np.ndarray:
        """Unigram probability by training count."""
        d = np.where(c > CUT, _kept(c.astype(float)), low[np.minimum(c, CUT)])
        return np.where(c > 0, d / max(total, 1), unknown)

    def reduce(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        flat = {c: table.column(c).combine_chunks().flatten().to_numpy(zero_copy_only=False) for c in ("w", "pairs", "v", "times", "place", "held", "nth")}
        ids = table.column("ids").combine_chunks().flatten()
        sizes = {c: np.diff(table.column(c).combine_chunks().offsets.to_numpy()) for c in ("place", "ids")}
        chunk = np.repeat(table.column("chunk").to_numpy(), sizes["ids"])
        text = flat["place"].astype(np.int32) + np.repeat((np.cumsum(sizes["ids"]) - sizes["ids"]).astype(np.int32), sizes["place"])
        held = flat["held"].astype(bool)
        w, v = np.repeat(flat["w"], flat["pairs"]), flat["v"]
        order = np.lexsort((v, w))
        sw, sv = w[order], v[order]
        fresh = np.ones(len(order), bool)
        fresh[1:] = (sw[1:] != sw[:-1]) | (sv[1:] != sv[:-1])
        group = np.empty(len(order), np.int32)
        group[order] = np.cumsum(fresh) - 1
        gw, gv = sw[fresh], sv[fresh]
        del w, v, sw, sv, order, fresh
        each = np.repeat(group, flat["times"])  # of every occurrence, its pair
        del group
        for name in ("w", "pairs", "v", "times", "place"):
            del flat[name]
        train = ~held[text]
        c = np.bincount(each[train], minlength=len(gw))
        words, of = np.unique(gw, return_inverse=True)
        cw = np.bincount(of, c, len(words)).astype(np.int64)
        for k in np.flatnonzero(np.isin(words, np.array(list(hot), np.int64))):
            cw[k] = hot[int(words[k])]
        cw = cw[of]
        # Per occurrence: logs of its pair's and its word's counts.
        ends = gw == END.view(np.int64)
        joint = np.where(c > CUT, np.log10(np.maximum(_kept(c.astype(float)), 1e-9)), 0.0)
        unseen = np.log10(model(cw))
        own = np.where((cw > 0) & ~ends, np.log10(np.maximum(cw, 1)), 0.0)
        ask = np.flatnonzero(~train)
        x = (joint - own)[each]
        x[ask] = np.where(c > 0, joint, unseen)[each[ask]]
        n_text = len(held)
        level = np.minimum(c, CUT + 1).astype(np.uint8)[each]
        counts = {f"m{r}": np.bincount(text[level == r], minlength=n_text) for r in range(1, CUT + 1)}
        known = np.bincount(text[(cw > 0)[each]], minlength=n_text)
        sums = np.bincount(text, x, n_text)
        del x, level
        base = np.bincount(text, np.log10(cw + 1.0)[each], n_text)
        key = chunk * (1 << 15) + flat["nth"]
        a = rows(n_text, kind=np.zeros(n_text, np.int32), id=key, doc_id=ids, held=pa.array(held), x=sums, y=base, n=np.bincount(text, minlength=n_text), v=known, **counts)
        pair = text[ask].astype(np.int64) * len(gw) + each[ask]
        pair, times = np.unique(pair, return_counts=True)
        who, what = pair // len(gw), pair % len(gw)
        seen = c[what] > 0
        b = rows(len(pair), kind=np.ones(len(pair), np.int32), id=key[who], v=gv[what], n=np.where(seen, times, 0), m1=np.where(seen, 0, times))
        have = c > 0
        contexts, at = np.unique(gv[have], return_inverse=True)
        hc, m = c[have], len(contexts)
        sums = {f"m{r}": np.bincount(at[hc == r], minlength=m) for r in range(1, CUT + 1)}
        big = hc > CUT
        ctx = rows(m, kind=np.full(m, 2, np.int32), v=contexts, x=np.bincount(at, model(cw[have]), m), y=np.bincount(at[big], _kept(hc[big].astype(float)), m), n=np.bincount(at, hc, m).astype(np.int64), **sums)
        r, often = np.unique(np.minimum(hc, CUT + 2), return_counts=True)
        d = rows(len(r), kind=np.full(len(r), 3, np.int32), v=r, n=often)
        del each, text
        trim()
        # Small batches, so that neither side holds a bucket's whole result twice.
        return pa.Table.from_batches([x for t in (a, b, ctx, d) for x in t.to_batches(max_chunksize=20_000)])

    return reduce


def score(docs: DataFrame, train: Column, bucket_tokens: int = 2_200_000) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every row of ``docs`` (doc_id, text).

    ``train``: which rows are learned from. ``base_score`` is add-one smoothing of the same
    tokens. ``bucket_tokens`` sets how many occurrences meet in one task.
    """
    need(docs, "doc_id", "text")
    spark = docs.sparkSession
    prepare(spark)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text"), (~F.coalesce(train, F.lit(False))).alias("held"))
    unigrams = stored(rows.mapInArrow(_count_words, "w long, c long").groupBy("w").agg(F.sum("c").alias("c")), "unigrams")
    total, distinct = (int(x or 0) for x in unigrams.agg(F.sum("c"), F.count(F.lit(1))).first())
    often = {r.c: r.n for r in unigrams.where(F.col("c") <= CUT + 1).groupBy("c").agg(F.count(F.lit(1)).alias("n")).collect()}
    ends = unigrams.where(F.col("w") == int(END.view(np.int64))).first()
    texts = int(ends.c) if ends else 0
    uni = discounts(often)
    mass = unigrams.agg(F.sum(F.when(F.col("c") > CUT, F.col("c") - 1 / (F.col("c") + 1)).otherwise(F.get(F.array(*map(F.lit, uni)), F.col("c").cast("int"))))).first()[0] or 0.0
    unknown = 1 - mass / total if total else 1.0
    cores = spark.sparkContext.defaultParallelism
    buckets = max(-(-total // bucket_tokens), min(2 * cores, -(-total // 250_000)), 1)
    hot = {r.w: r.c for r in unigrams.where(F.col("c") > max(1000, total // (4 * buckets))).collect()}  # at most 4 a bucket
    packed = rows.mapInArrow(_packer(buckets, list(hot)), "bucket int, chunk long, w array<long>, pairs array<int>, v array<long>, times array<int>, place array<short>, ids array<long>, held array<boolean>, nth array<int>")
    parts = packed.repartition(buckets, "bucket").groupBy("bucket").applyInArrow(_reducer(total, uni, unknown, hot), OUT)
    parts = stored(parts, "parts")
    del packed
    forget(spark)
    n = {r.v: int(r.n) for r in parts.where("kind = 3").groupBy("v").agg(F.sum("n").alias("n")).collect()}
    pairs = discounts(n)
    small = sum((F.col(f"m{r}") * pairs[r] for r in range(2, CUT + 1)), F.col("m1") * pairs[1])
    sums = [F.sum(f"m{r}").alias(f"m{r}") for r in range(1, CUT + 1)]
    contexts = parts.where("kind = 2").groupBy("v").agg(F.sum("x").alias("x"), F.sum("y").alias("y"), F.sum("n").alias("total"), *sums)
    left = 1 - (F.col("y") + small) / F.col("total")
    backoff = contexts.select("v", F.log10("total").alias("log_total"), F.log10(left / F.greatest(1 - F.col("x"), F.lit(1e-15))).alias("weight"))
    asked = parts.where("kind = 1").select("id", "v", F.col("n").alias("seen"), F.col("m1").alias("unseen")).join(backoff, "v", "left")
    settled = asked.groupBy("id").agg(F.sum(F.coalesce(F.col("unseen") * F.col("weight"), F.lit(0.0)) - F.coalesce(F.col("seen") * F.col("log_total"), F.lit(0.0))).alias("held_part"))
    by_text = parts.where("kind = 0").groupBy("id", "doc_id", "held").agg(F.sum("x").alias("x"), F.sum("y").alias("y"), F.sum("n").alias("n_tokens"), F.sum("v").alias("n_known"), *sums)
    logs = sum((F.col(f"m{r}") * float(np.log10(pairs[r])) for r in range(2, CUT + 1)), F.col("m1") * float(np.log10(pairs[1])))
    whole = F.col("x") + logs + F.when(F.col("held"), F.coalesce("held_part", F.lit(0.0))).otherwise(-float(np.log10(max(texts, 1))))
    base = F.col("y") - F.col("n_tokens") * float(np.log10(total + distinct + 1))
    return by_text.join(settled, "id", "left").select("doc_id", F.col("held").alias("held_out"), "n_tokens", "n_known", F.lit(total).cast("long").alias("train_tokens"), base.alias("base_score"), whole.alias("score"))
