"""Streams run to their end: where rows go, what state holds, and edges of the joins in time."""

import duckdb
import numpy as np

from shiftscan import catalogue
from shiftscan.operators.kernel import RULES, Options, scan
from shiftscan.sources import streams
from shiftscan.streaming import chain as stream

SMALL = "/root/testdata/sf0.001"


def test_a_deduplicated_stream_lands_in_files(spark):
    """No row goes to the driver, and the session's settings are as before."""
    before = {c: spark.conf.get(c, None) for c in streams.STATE}
    got = catalogue.RUNS["stream_dedup"](spark, SMALL)
    assert got.inputFiles() and all(x.startswith("file:") for x in got.inputFiles())
    want = duckdb.sql(f"SELECT event_type, count(*) FROM '{SMALL}/events.parquet' GROUP BY 1").fetchall()
    assert sorted(map(tuple, got.collect())) == sorted(want)
    assert {c: spark.conf.get(c, None) for c in streams.STATE} == before


def test_an_empty_stream_lands(spark, tmp_path):
    rows = spark.range(3)
    rows.write.parquet(f"{tmp_path}/in")
    none = spark.readStream.schema(rows.schema).parquet(f"{tmp_path}/in").where("id > 5")
    assert streams.landed(none, "none").collect() == []


def test_detected_windows_land_and_rows_wait_as_bytes(spark):
    """Only anomalies reach the sink, and a series' waiting rows are one value of its state."""
    got = catalogue.RUNS["stream_anomalies"](spark, "/root/testdata/sf0.01")
    assert got.inputFiles() and spark.read.parquet(*got.inputFiles()).count() == got.count() == 53
    assert "waiting binary" in stream.STATE


def test_windows_in_steps_are_those_of_the_batch():
    """A series used in pieces of any size gives the columns of all at once."""
    rng = np.random.default_rng(7)
    o, v = Options(w=6), rng.integers(0, 6, 200)
    rows = np.stack([np.arange(200) * 10, np.arange(200), v])
    want = scan(v, 3, 0, o)
    for step in (1, 3, 7, 200):
        ring, rn, parts = [], 0, []
        for low in range(0, 200, step):
            ring, rn, out = stream._advance(ring, rn, rows[:, low : low + step], 3, o)
            if out:
                parts.append(out)
        both = {c: np.concatenate([x[c] for x in parts]) for c in parts[0]}
        assert rn == 200 and both["rn"].tolist() == list(range(6, 201)) and both["ts"].astype(int).tolist() == rows[0, 5:].tolist()
        assert both["p"].tolist() == [int(a) / int(b) for a, b in zip(want["num"], want["den"])] and both["rule"].tolist() == [RULES[x] for x in want["rule"]]


def test_errors_meet_anomalies_by_the_hour(spark, tmp_path):
    """Every error within an hour comes once, the ends included; the join has the hour among its keys."""
    t = 1_704_067_200_000_000  # a full hour, in microseconds
    times = [t + x for x in (-3_600_000_001, -3_600_000_000, -1, 0, 1, 1_800_000_000, 3_599_999_999, 3_600_000_000, 3_600_000_001, 7_200_000_000)]
    rows = spark.createDataFrame([(m, i, x) for m in (1, 2) for i, x in enumerate(times)], "machine_id long, rn long, at long").selectExpr("machine_id", "rn", "timestamp_micros(at) AS ts")
    rows.write.parquet(f"{tmp_path}/in")
    one = spark.readStream.schema(rows.schema).parquet(f"{tmp_path}/in")
    both = stream.correlate(one, one.select("machine_id", "ts"))
    assert "_near" in both._jdf.queryExecution().analyzed().toString()
    got = streams.landed(both.selectExpr("machine_id", "rn", "unix_micros(error_ts) AS at"), "pairs").collect()
    want = [(m, i, y) for m in (1, 2) for i, x in enumerate(times) for y in times if abs(x - y) <= 3_600_000_000]
    assert sorted(map(tuple, got)) == sorted(want)


def test_correlated_rows_land_in_files(spark):
    got = catalogue.RUNS["stream_correlate"](spark, SMALL)
    assert got.inputFiles()
