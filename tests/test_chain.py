"""The chain against goldens, hand cases, and itself with every shortcut off."""

import itertools

import numpy as np
import pytest

from shiftscan.operators import kernel
from shiftscan.operators.kernel import Options, scan
from shiftscan.operators.tracker import PrefixTracker
from shiftscan.plans import chain
from shiftscan.sources import feeds, params

SMALL = "/root/testdata/sf0.001"
RULES = kernel.RULES


def labels_of(got):
    return kernel.turned(got["labels"], got["anchor"], got["shift"])


def series(rng, n):
    return rng.integers(0, rng.choice([2, 4, 9, 40]), n)


def test_shortcuts_never_change_results():
    rng = np.random.default_rng(1)
    for _ in range(40):
        w, k = int(rng.integers(3, 14)), int(rng.integers(1, 9))
        v = series(rng, 150)
        base = scan(v, k, 0, Options(w=w, **chain.BASELINE))
        for flags in itertools.product([True, False], repeat=6):
            o = Options(w=w, **dict(zip(("rotation", "single", "few", "few_inclusive", "memo", "sorted_sweep"), flags)))
            got = scan(v, k, 0, o)
            assert (got["num"] == base["num"]).all() and (got["den"] == base["den"]).all() and (labels_of(got) == labels_of(base)).all()
        for flags in itertools.product([True, False], repeat=3):
            got = scan(v, k, 0, Options(w=w, **dict(zip(("ring", "lazy", "kept"), flags))))
            assert (got["num"] == base["num"]).all() and (got["den"] == base["den"]).all() and (labels_of(got) == labels_of(base)).all()


def test_marks_follow_their_definition():
    """Distinct values, seeds and rotations, window by window."""
    rng = np.random.default_rng(4)
    for _ in range(30):
        w, k = int(rng.integers(2, 9)), int(rng.integers(1, 6))
        v = series(rng, 80)
        block = kernel.Block(v, w)
        got, before = block.marks(k), None
        for t in range(len(v) - w + 1):
            win = v[t : t + w].tolist()
            seeds = set(list(dict.fromkeys(win))[:k])
            assert got.distinct[t] == len(set(win)) and set(block.seeds(np.array([t]), len(seeds))[0].tolist()) == seeds
            assert got.rotated[t] == (before is not None and v[t - 1] == win[-1] and seeds == before)
            before = seeds


def test_full_model_against_counting():
    """Numerators and denominators against plain counting of transitions."""
    v = np.random.default_rng(5).integers(0, 9, 60)
    for options in ({}, chain.BASELINE):
        got = scan(v, 3, 0, Options(w=12, **options))
        for i, labels in enumerate(labels_of(got).tolist()):
            pairs = list(zip(labels, labels[1:]))
            num, den = 1, 1
            for a, b in pairs[-5:]:
                num, den = num * pairs.count((a, b)), den * sum(x == a for x, _ in pairs)
            assert (got["num"][i], got["den"][i], got["divisions"][i]) == (num, den, len(set(pairs[-5:])))


@pytest.mark.parametrize(
    ("values", "k", "w", "rule"),
    [
        ([5, 5, 5, 5], 3, 4, "single"),
        ([1, 2, 1, 2], 3, 4, "few"),
        ([9, 1, 7, 3], 1, 4, "single"),
        ([2, 2, 3, 4, 2], 2, 4, "rotation"),
        ([2, 3, 2, 4, 2], 2, 4, "rotation"),
        ([2, 3, 4, 3, 2], 2, 4, "iterate"),
        ([3, 2, 3, 0, 3], 2, 4, "rotation"),
    ],
)
def test_hand_cases(values, k, w, rule):
    assert RULES[scan(np.array(values), k, 0, Options(w=w))["rule"][-1]] == rule


def test_small_windows():
    got = scan(np.array([1, 2, 1, 2]), 3, 0, Options(w=4))
    assert labels_of(got).tolist() == [[0, 1, 0, 1]] and got["num"][0] == got["den"][0]
    assert labels_of(scan(np.array([0, 2, 1]), 2, 0, Options(w=3))).tolist() == [[0, 1, 1]]  # on the border: the higher centre
    many = scan(np.arange(20) % 7, 3, 0, Options(w=10, n=20))
    assert (many["num"] <= many["den"]).all()
    wide = scan(np.random.default_rng(0).integers(0, 5, 400), 4, 0, Options(w=200, n=12))
    assert all(0 < a <= b for a, b in zip(wide["num"], wide["den"]))


def test_tracker_forms():
    rng = np.random.default_rng(2)
    for _ in range(60):
        w, k = int(rng.integers(3, 9)), int(rng.integers(1, 6))
        v = series(rng, 120)
        true = kernel.Block(v, w).marks(k).rotated.tolist()
        complete, printed = PrefixTracker(k, w), PrefixTracker(k, w, "conservative")
        got = [complete.slide(int(x)) for x in v][w - 1 :]
        low = [printed.slide(int(x)) for x in v][w - 1 :]
        assert got == true
        assert all(t or not p for p, t in zip(low, true))


@pytest.mark.parametrize(("feed", "kmap", "w", "rules", "anomalies"), [("ev_single", "A", 10, (119, 188, 191, 457), 4), ("ev_single", "A", 100, (63, 101, 26, 315), 220), ("ev_ten", "A", 10, (72, 105, 114, 260), 1), ("ev_many", "A", 10, (37, 66, 66, 165), 2), ("ord_priority", "prio", 10, (292, 0, 1118, 0), None)])
def test_goldens(spark, feed, kmap, w, rules, anomalies):
    rows = chain.score(feeds.feed(spark, SMALL, feed), params.load(spark, kmap), w=w).select("rule", "p", "threshold").collect()
    assert tuple(sum(r.rule == x for r in rows) for x in RULES) == rules
    if anomalies is not None:
        assert sum(r.p < r.threshold for r in rows) == anomalies


def test_chunks_and_order_do_not_matter(spark):
    readings, meta = feeds.feed(spark, SMALL, "ev_ten"), params.load(spark, "A")
    columns = ["machine_id", "sensor_id", "rn", "ts", "first_ts", "rule", "num", "den"]
    rows = [set(map(tuple, chain.score(readings.repartition(n), meta, chunk=c, most=m).select(*columns).collect())) for n, c, m in ((1, 10, 15), (7, 20, 30), (3, 100_000, 1 << 22))]
    assert rows[0] == rows[1] == rows[2]


def test_a_series_goes_on_from_batch_to_batch(spark, monkeypatch):
    """A kernel that holds few rows at a time gives what one that holds all gives."""
    readings, meta = feeds.feed(spark, SMALL, "ev_ten"), params.load(spark, "A")
    table = readings.join(meta, "sensor_id").orderBy("machine_id", "sensor_id", "ts", "tick").select("machine_id", "sensor_id", "ts", "tick", "v", "k", "threshold").toArrow()
    o = Options(w=10)

    def rows(held, batch):
        monkeypatch.setattr(chain, "HELD_ROWS", held)
        return [r for x in chain._kernel(o, 100, False, False)(table.to_batches(max_chunksize=batch)) for r in x.to_pylist()]

    every = rows(100_000, 1000)
    few = rows(40, 7)
    key = lambda r: (r["machine_id"], r["sensor_id"], r["rn"])
    same = ("rn", "ts", "first_ts", "rule", "num", "den", "p")
    assert [[r[c] for c in same] for r in sorted(every, key=key)] == [[r[c] for c in same] for r in sorted(few, key=key)]


def test_one_exchange_and_one_scan(spark):
    plan = chain.score(feeds.feed(spark, SMALL, "ev_ten"), params.load(spark, "A"))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and plan.count("FileScan") == 1


def test_detect_flags_what_score_flags(spark):
    readings, meta = feeds.feed(spark, SMALL, "ev_single"), params.load(spark, "A")
    columns = ["machine_id", "sensor_id", "rn", "ts", "tick", "first_ts", "p", "rule"]
    want = chain.flag(chain.score(readings, meta, w=100)).select(*columns).collect()
    assert want and sorted(chain.detect(readings, meta, w=100).select(*columns).collect()) == sorted(want)


def test_guards(spark):
    big = spark.createDataFrame([(0, "a", i, 1 << 60) for i in range(12)], "machine_id long, sensor_id string, tick long, v long").selectExpr("machine_id", "sensor_id", "timestamp_ntz'2024-01-01' AS ts", "tick", "v")
    with pytest.raises(Exception, match="too large"):
        chain.score(big, params.load(spark, {"a": 2})).count()
    short = big.where("tick < 5").withColumn("v", big.tick)
    assert chain.score(short, params.load(spark, {"a": 2})).count() == 0
    with pytest.raises(ValueError, match="k >= 1"):
        params.load(spark, {"a": 0})
    raw = spark.createDataFrame([(1.0,), (None,), (float("nan"),), (1e19,)], "raw double")
    ok, bad = feeds.validate(raw, 10)
    assert ok.count() == 1 and sorted(r.reason for r in bad.collect()) == ["nan", "null", "overflow"]
