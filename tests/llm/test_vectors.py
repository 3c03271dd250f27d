"""Near vectors against brute force, and awkward vectors."""

import numpy as np
from pyspark.sql import functions as F

from shiftscan.llm import vectors


def brute(rows, least=0.95):
    good = [(i, np.array(v, float)) for i, v in rows if v and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    links = {i: set() for i, _ in rows}
    for a, x in good:
        for b, y in good:
            if a != b and len(x) == len(y) and x @ y / np.sqrt((x @ x) * (y @ y)) >= least:
                links[a].add(b)
    low = {i: i for i in links}
    for _ in links:
        for a, others in links.items():
            low[a] = min([low[a], *(low[b] for b in others)])
    return {(i, len(links[i]), low[i], low[i] == i) for i in links}


def test_small(spark):
    rng = np.random.default_rng(0)
    rows = []
    for k in range(30):
        base = rng.normal(size=8)
        rows += [(10 * k + j, (base + rng.normal(size=8) * 0.12).tolist()) for j in range(8)]
    rows += [(1000, None), (1001, []), (1002, [0.0] * 8), (1003, [float("nan")] + [1.0] * 7), (1004, [None] + [1.0] * 7), (1005, rows[0][1]), (1006, [2 * x for x in rows[0][1]]), (1007, [1.0, 2.0]), (1008, [1.0, 2.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("links", F.lit("clash"))
    got = vectors.near_vectors(df)
    assert {tuple(r) for r in got.collect()} == brute(rows)
    assert vectors.near_vectors(df.limit(0)).count() == 0
    few = vectors.near_vectors(df, most=60, shard_size=40, sample=100)
    want = {r[0]: r[1] for r in brute(rows)}
    assert sum(min(r.n_links, want[r.vec_id]) for r in few.collect()) >= 0.9 * sum(want.values())


def test_table_recall(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet")
    row = vectors.recall(df, vectors.near_vectors(df), every=5).first()
    assert row.recall is None or row.recall >= 0.9


def test_tight_group_above_a_shard(spark):
    """A tight group of more vectors than a shard holds, in a table of others: every link of it counts."""
    rng = np.random.default_rng(1)
    base = rng.normal(size=64)
    rows = [(k, (base + rng.normal(size=64) * 0.15).tolist()) for k in range(900)]
    rows += [(2000 + k, rng.normal(size=64).tolist()) for k in range(900)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    x = np.array([v for _, v in rows])
    x /= np.sqrt((x * x).sum(1, keepdims=True))
    want = (x @ x.T >= 0.95).sum(1) - 1
    assert want[:900].mean() > 400
    got = vectors.near_vectors(df, most=300, shard_size=100, sample=600)
    at = {r[0]: k for k, r in enumerate(rows)}
    out = {r.vec_id: r for r in got.collect()}
    assert all(out[i].n_links == want[at[i]] for i in range(900))
    assert {out[i].component_id for i in range(900)} == {0}
    row = vectors.recall(df, got).first()
    print(f"recall {row.recall} of {row.n_true} links")
    assert row.recall == 1


def test_many_lengths(spark):
    """Each of many vector lengths links, the longest too."""
    rows = [(10 * n + k, [float(n + 1), 1.0] * n + [1.0 + 0.01 * k]) for n in range(1, 80) for k in range(2)]
    got = vectors.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    assert all(r.n_links == 1 for r in got.collect())
