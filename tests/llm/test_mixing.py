from fractions import Fraction

from pyspark.sql import functions as F

from shiftscan.llm import mixing


def test_shortages_go_to_siblings_first():
    tokens = {("a", "x"): 10, ("a", "y"): 1000, ("b", "z"): 1000}
    got = mixing.budgets(tokens, {("a",): 1, ("b",): 1}, 200, 1)
    assert got == {("a", "x"): 10, ("a", "y"): 90, ("b", "z"): 100}
    got = mixing.budgets({("a", "x"): 10, ("a", "y"): 20, ("b", "z"): 1000}, {}, 200, 1)
    assert got == {("a", "x"): 10, ("a", "y"): 20, ("b", "z"): 170}
    assert mixing.budgets({("a", "x"): 10}, {}, 1000, 3) == {("a", "x"): 30}
    assert sum(mixing.share(100, {k: Fraction(1) for k in "abc"}, dict.fromkeys("abc", 99)).values()) == 100


def test_prefixes(spark):
    rows = [(i, "w " * (i % 9 + 1), ["en", None][i % 5 == 0], f"s{i % 3}") for i in range(900)] + [(None, "lost words", "en", "s1"), (1000, None, "en", "s1"), (1001, "", "en", "s2")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").withColumn("n_tokens", F.lit("clash"))
    levels = [F.col("lang"), F.col("source")]
    for budget in (0, 1, 500, 3000, 9000, 40_000):
        got = mixing.mix(docs, levels, {("en",): 3}, budget=budget, epochs=4).collect()
        tokens = {}
        for d, t, lang, s in rows:
            leaf = (lang or "", s)
            tokens[leaf] = tokens.get(leaf, 0) + len((t or "").split())
        plan = mixing.budgets(tokens, {("en",): 3}, budget, 4)
        used = {}
        for r in got:
            leaf = (r.lang or "", r.source)
            used[leaf] = used.get(leaf, 0) + r.n_copies * r.n_tokens
        for leaf, b in plan.items():
            # A prefix stops short of its budget by less than one document.
            assert b - 9 < used.get(leaf, 0) <= b
        again = mixing.mix(docs.repartition(7), levels, {("en",): 3}, budget=budget, epochs=4).collect()
        assert sorted((r.doc_id or -1, r.n_copies) for r in got) == sorted((r.doc_id or -1, r.n_copies) for r in again)
    assert mixing.mix(docs.limit(0), levels, {}, budget=10).count() == 0


def test_clashing_columns(spark):
    docs = spark.createDataFrame([(i, "a b c", "en") for i in range(50)], "doc_id long, text string, lang string")
    names = ["_l0", "_k", "_h", "_n", "_id", "_row", "_bucket", "_epochs", "_rest", "_last", "_before", "_more", "t", "tokens"]
    plain = mixing.mix(docs, [F.col("lang")], {}, budget=60).select("doc_id", "n_copies").collect()
    got = mixing.mix(docs.withColumns({n: F.lit(n) for n in names}), [F.col("lang")], {}, budget=60)
    assert got.columns == [*docs.columns, *names, "n_tokens", "n_copies"]
    rows = got.collect()
    assert sorted((r.doc_id, r.n_copies) for r in rows) == sorted(map(tuple, plain)) and len(rows) == 20
    assert all([r[n] for n in names] == names for r in rows)


def test_many_leaves(spark, monkeypatch):
    """Beyond MAX_LEAVES the budgets are spread on the executors, with the same rows."""
    rows = [(i, "w " * (i * 7 % 11 + 1), ["en", "de", None][i % 3], f"s{i % 40 if i % 2 else 0}") for i in range(1200)] + [(2000, None, "fr", "empty"), (None, "lost words", "en", "s1")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    levels = [F.substring("source", 1, 2), F.col("lang"), F.col("source")]
    weights = {("s1",): 5, ("s1", "en"): 2.5, ("s2", "de"): 0}

    def selected(budget):
        return sorted((r.doc_id or -1, r.n_copies, r.n_tokens) for r in mixing.mix(docs, levels, weights, budget=budget, epochs=3).collect())

    want = {b: selected(b) for b in (1, 2500, 30_000)}
    monkeypatch.setattr(mixing, "MAX_LEAVES", 3)
    assert {b: selected(b) for b in want} == want and len(want[2500]) > 100
    assert mixing.mix(docs, levels, weights, fraction=0.5).count() > 0


def brute(tokens, weights, budget, epochs):
    """Water rises over the tree in small steps: whoever still has room gets its share by weight."""
    used = dict.fromkeys(tokens, 0.0)
    room = lambda prefix: sum(epochs * n - used[x] for x, n in tokens.items() if x[: len(prefix)] == prefix)

    def pour(prefix, amount):
        below = sorted({x[: len(prefix) + 1] for x in tokens if x[: len(prefix)] == prefix})
        if prefix in tokens:
            used[prefix] += amount
            return
        left = amount
        while left > 1e-9:
            open_ = [k for k in below if room(k) > 1e-9]
            total = sum(weights.get(k, 1) for k in open_)
            step = min([left, *(room(k) * total / weights.get(k, 1) for k in open_)])
            for k in open_:
                pour(k, step * weights.get(k, 1) / total)
            left -= step

    pour((), min(budget, epochs * sum(tokens.values())))
    return used


def test_budgets_by_brute_force():
    import random

    rng = random.Random(6)
    for _ in range(60):
        tokens = {(a, b): rng.randrange(1, 400) for a in "abc" for b in "xyz"[: rng.randrange(1, 4)]}
        weights = {k: rng.randrange(1, 6) for k in [("a",), ("b",), ("a", "x"), ("c", "y")]}
        budget, epochs = rng.randrange(1, 4000), rng.randrange(1, 4)
        got, want = mixing.budgets(tokens, weights, budget, epochs), brute(tokens, weights, budget, epochs)
        assert sum(got.values()) == min(budget, epochs * sum(tokens.values()))
        assert all(abs(got[k] - want[k]) <= 4 for k in tokens)
