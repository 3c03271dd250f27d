"""Near duplicates against brute force over all pairs."""

from itertools import combinations

from pyspark.sql import functions as F

from shiftscan.llm import minhash

SMALL = "/root/testdata/sf0.001"


def shingles(text):
    words = (text or "").encode().lower().split()
    return {tuple(words[i : i + 4]) for i in range(len(words) - 3)} or ({tuple(words)} if words else set())


def brute(rows):
    sets = {d: shingles(t) for d, t in rows}
    top = {d: d for d in sets}

    def find(x):
        while top[x] != x:
            x = top[x]
        return x

    for a, b in combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both and 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
            x, y = find(a), find(b)
            top[max(x, y)] = min(x, y)
    return {(d, len(sets[d]), find(d), find(d) == d) for d in sets}


def test_table(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    assert {tuple(r) for r in minhash.near_duplicates(docs, size=4).collect()} == brute(rows)


def test_edges(spark):
    long = " ".join(f"w{i % 977}" for i in range(30_000))
    rows = [(1, None), (2, ""), (3, " \n\t"), (4, "One two"), (5, "one  TWO"), (6, "one two three"), (7, long), (8, long + " end"), (9, "a b c d e f"), (10, "A b c d e f"), (11, "É b c d"), (12, "é b c d")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("component_id", F.lit("clash")).withColumn("n", F.lit(1))
    got = {tuple(r) for r in minhash.near_duplicates(docs, size=4).collect()}
    assert got == brute(rows)
    twice = minhash.near_duplicates(docs.union(docs), size=4).collect()
    assert {tuple(r) for r in twice} == got and len(twice) == 2 * len(rows)
    assert minhash.near_duplicates(docs.limit(0), size=4).count() == 0
    lost = spark.createDataFrame([(None, "a b c d"), (3, "a b c d"), (None, "x y")], "doc_id long, text string")
    assert {tuple(r) for r in minhash.near_duplicates(lost, size=4).collect()} == {(None, 1, 3, False), (3, 1, 3, True), (None, 1, None, True)}


def test_all_candidates_meet(spark):
    """A chain whose smallest member is far from most of the others."""
    base = [f"v{i}" for i in range(60)]
    rows = []
    for k in range(12):
        words = base.copy()
        words[60 - k * 2 :] = [f"x{i}" for i in range(k * 2)]
        rows.append((100 - k if k != 5 else 1, " ".join(words)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert {tuple(r) for r in minhash.near_duplicates(docs, size=4).collect()} == brute(rows)


def test_many_copies_and_a_straggler(spark):
    """A large group of near copies beside texts that share most of its shingles, but not enough, and one that is near a few."""
    rng = __import__("random").Random(2)
    base = [f"b{i}" for i in range(80)]
    rows = []
    for k in range(300):
        words = base.copy()
        words[rng.randrange(80)] = f"u{k}"
        rows.append((1000 + k, " ".join(words)))
    rows += [(k, " ".join(base[: 66 + k] + [f"s{k}_{i}" for i in range(14 - k)])) for k in range(9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert {tuple(r) for r in minhash.near_duplicates(docs, size=4).collect()} == brute(rows)
    placed = docs.select(F.col("doc_id").alias("id"), F.lit(77).cast("long").alias("n"), F.when(F.col("doc_id") < 1000, F.col("doc_id")).otherwise(1000).alias("c"), "text")
    pairs = minhash._rare_pairs(placed, 4, 80).select("a", "b").distinct()
    assert pairs.where("a >= 1000").count() == 0 and pairs.count() <= 9 * 300 + 36
