"""The ordered release is a total order."""

import random

from shiftscan.operators import release


def test_ties_leave_in_the_order_of_their_series(spark):
    """Anomalies of one series at one time, dealt in any order and over any partitions."""
    rows = [(m, "prio", rn, f"2024-01-0{day}") for m in (1, 2) for day in (1, 2) for rn in range(day * 50, day * 50 + 40)]
    random.Random(2).shuffle(rows)
    df = spark.createDataFrame(rows, "machine_id long, sensor_id string, rn long, at string").selectExpr("machine_id", "sensor_id", "rn", "CAST(at AS timestamp_ntz) AS ts")
    for parts in (1, 7):
        got = [(str(r.ts)[:10], r.machine_id, r.rn) for r in release.ordered(df.repartition(parts)).collect()]
        assert got == sorted((day, m, rn) for m, _, rn, day in rows)
