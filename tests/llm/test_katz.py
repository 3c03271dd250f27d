"""Katz backoff against a dictionary version, and that its distributions sum to one."""

import math
import zlib
from collections import Counter, defaultdict

import pytest

from shiftscan.llm import katz, ngrams, queries


def model(texts):
    uni, bi = Counter(), Counter()
    for t in texts:
        seq = [*t, None]
        for v, w in zip(["<s>", *t], seq):
            uni[w] += 1
            bi[v, w] += 1

    def kept(counts):
        low = katz.discounts(Counter(counts.values()))
        return {k: low[c] if c <= 5 else c - 1 / (c + 1) for k, c in counts.items()}

    total = sum(uni.values())
    p1 = {w: d / total for w, d in kept(uni).items()}
    unknown = 1 - sum(p1.values())
    by, d2 = defaultdict(dict), kept(bi)
    for (v, w), c in bi.items():
        by[v][w] = d2[v, w]
    sums = {v: sum(bi[v, w] for w in ws) for v, ws in by.items()}

    def p(v, w):
        if w in by.get(v, ()):
            return by[v][w] / sums[v]
        low = p1.get(w, unknown)
        if v not in by:
            return low
        left = 1 - sum(by[v].values()) / sums[v]
        return left * low / (1 - sum(p1[x] for x in by[v]))

    return uni, total, p


def test_query(spark, tmp_path):
    import random

    rng = random.Random(3)
    vocab = [f"w{i}" for i in range(60)]
    rows = [(i, " ".join(rng.choice(vocab[: rng.choice([5, 20, 60])]) for _ in range(rng.randrange(30)))) for i in range(300)]
    rows += [(300, None), (301, ""), (302, "never seen words"), (5, "W1 w2\tW3"), (303, "w1 w2 " * 2000)]
    spark.createDataFrame(rows, "doc_id long, text string").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    got = queries.op8_katz_backoff(spark, str(tmp_path)).collect()
    cut = [(d, (t or "").lower().split()) for d, t in rows]
    held = {d: zlib.crc32(str(d).encode()) % 7 == 2 for d, _ in cut}
    uni, total, p = model([t for d, t in cut if not held[d]])
    want = []
    for d, t in cut:
        seq = [*t, None]
        base = sum(math.log10((uni[w] + 1) / (total + len(uni) + 1)) for w in seq)
        full = sum(math.log10(p(v, w)) for v, w in zip(["<s>", *t], seq))
        want.append((d, held[d], len(seq), sum(uni[w] > 0 for w in seq), total, base, full))
    assert len(got) == len(want)
    for g, x in zip(sorted(got, key=lambda r: (r.doc_id, r.n_tokens)), sorted(want, key=lambda r: (r[0], r[2]))):
        assert tuple(g)[:5] == x[:5]
        assert g.base_score == pytest.approx(x[5]) and g.score == pytest.approx(x[6])
    for v in ("<s>", "w1", "w59", "nowhere"):
        assert sum(p(v, w) for w in uni) + p(v, "unknown word") == pytest.approx(1)


def test_empty(spark):
    from pyspark.sql import functions as F

    none = spark.createDataFrame([], "doc_id long, text string, held boolean")
    assert katz.score(none, F.lit(True)).count() == 0
    untrained = katz.score(spark.createDataFrame([(1, "a b")], "doc_id long, text string"), F.lit(False)).first()
    assert untrained.train_tokens == 0 and untrained.score == 0


def recursive(texts, order):
    """p(context, word) of any order by the definition."""
    counts = [Counter() for _ in range(order + 1)]
    for t in texts:
        seq = ["<s>"] * (order - 1) + [*t, None]
        for i in range(order - 1, len(seq)):
            for n in range(1, order + 1):
                counts[n][tuple(seq[i - n + 1 : i]), seq[i]] += 1
    kept = [{}]
    for n in range(1, order + 1):
        low = katz.discounts(Counter(counts[n].values()))
        kept.append({k: low[c] if c <= 5 else c - 1 / (c + 1) for k, c in counts[n].items()})
    by = defaultdict(dict)
    for n in range(1, order + 1):
        for (context, w), c in counts[n].items():
            by[n, context][w] = c
    unknown = 1 - sum(kept[1].values()) / max(1, sum(counts[1].values()))

    def p(context, w):
        n = len(context) + 1
        seen = by.get((n, context), {})
        if w in seen:
            return kept[n][context, w] / sum(seen.values())
        if n == 1:
            return unknown
        if not seen:
            return p(context[1:], w)
        left = 1 - sum(kept[n][context, x] for x in seen) / sum(seen.values())
        return left / (1 - sum(p(context[1:], x) for x in seen)) * p(context[1:], w)

    return {w for _, w in counts[1]}, p


def test_any_order(spark):
    """Order 3 against the definition, over stored tables; order 2 against the packed form."""
    import random

    from pyspark.sql import functions as F

    rng = random.Random(4)
    rows = [(i, " ".join(rng.choice("abcdefgh"[: rng.choice([3, 8])]) for _ in range(rng.randrange(14)))) for i in range(150)] + [(150, None), (151, "A new word"), (7, "a b c"), (None, "b c")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumns({"context": F.lit("x"), "row": F.lit(1), "w": F.lit(2)})
    learn = docs.where("doc_id % 3 <> 0")
    texts = [(t or "").lower().split() for d, t in rows if d is not None and d % 3]
    for order in (1, 2, 3):
        words, p = recursive(texts, order)
        model = ngrams.train(learn, order)
        want = []
        for d, t in rows:
            seq = ["<s>"] * (order - 1) + [*(t or "").lower().split(), None]
            want.append((-1 if d is None else d, len(seq) - order + 1, sum(math.log10(p(tuple(seq[i - order + 1 : i]), seq[i])) for i in range(order - 1, len(seq)))))
        got = sorted((-1 if r.doc_id is None else r.doc_id, r.n_tokens, r.score) for r in ngrams.score(docs, model).collect())
        for g, x in zip(got, sorted(want)):
            assert g[:2] == x[:2] and g[2] == pytest.approx(x[2])
        for context in {("a", "b"), ("b", "nowhere"), ("<s>", "<s>"), ("h", "a")} if order == 3 else ():
            assert sum(p(context, w) for w in words) + p(context, "unknown word") == pytest.approx(1)
        if order == 2:
            packed = {(r.doc_id, r.n_tokens): r.score for r in katz.score(docs.where("doc_id is not null"), F.col("doc_id") % 3 != 0).collect()}
            assert all(packed[d, n] == pytest.approx(s) for d, n, s in got if d >= 0)
        assert spark.read.parquet(f"{model.path}/grams-{order}").where("part = 0").count() >= 0
    assert ngrams.score(docs.limit(0), model).count() == 0
    assert ngrams.score(docs.limit(5), ngrams.train(docs.limit(0), 3)).agg(F.sum("score")).first()[0] == 0
