"""The whole chain: readings to scored windows to anomalies.

The readings cross the cluster once, by series, and are scanned in order by one Arrow
kernel that keeps the last ``w`` rows between batches: a task's memory does not follow
the length of its series. A series of more than ``most`` rows would be a task of its
own for too long. Where the input is large enough to hold one, series are counted
first, and the long ones are cut into chunks that carry the last ``w`` rows of the one
before; only the reuse of labels restarts at a chunk's head, never a result.
"""

from __future__ import annotations

from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import windows
from ..operators.kernel import RULES, Options, scan, turned
from ..ship import ship
from ..sources.feeds import SERIES
from ..sources.params import attach

SCORED = "machine_id long, sensor_id string, rn long, ts timestamp_ntz, tick long, first_ts timestamp_ntz, k int, threshold double, rule string, rotated boolean, single boolean, few boolean, n_distinct int, iterations int, num decimal(38,0), den decimal(38,0), p double, divisions int, labels array<int>"
FOUND = "machine_id long, sensor_id string, rn long, ts timestamp_ntz, tick long, first_ts timestamp_ntz, p double, threshold double, rule string"
HELD_ROWS = 100_000  # rows that a task gathers before it scans them
_EXACT = 1 << 53


def divided(num: np.ndarray, den: np.ndarray) -> np.ndarray:
    """Correctly rounded quotients."""
    if num.dtype != object and (not len(den) or int(den.max()) < _EXACT):
        return num / den
    return np.array([int(a) / int(b) for a, b in zip(num, den)], float)


def _scanned(table: pa.Table, rn: np.ndarray, old: np.ndarray, owner: np.ndarray, o: Options, with_labels: bool, below: bool) -> list[pa.RecordBatch]:
    """Scored windows that end in rows that are not ``old``; series with as many clusters are scanned together."""
    k_of, v_of = table.column("k").to_numpy(), table.column("v").to_numpy()
    out = []
    for k in np.unique(k_of):
        rows = np.flatnonzero(k_of == k)
        v, m = v_of[rows], len(rows) - o.w + 1
        if m < 1:
            continue
        if int(np.abs(v).max()) >= (1 << 61) // (o.w * o.w):
            raise OverflowError("a value is too large for exact sums over a window")
        got = scan(v, int(k), old[rows[o.w - 1 :]], o, owner[rows])
        p = divided(got["num"], got["den"])
        last = rows[got["at"] + o.w - 1]
        if below:
            low = np.flatnonzero(p < table.column("threshold").to_numpy()[last])
            got, p, last = {c: x[low] if c != "labels" else x for c, x in got.items()}, p[low], last[low]
        count = len(last)
        if not count:
            continue
        own = table.take(pa.array(last))
        tail = table.column("ts").take(pa.array(last - min(o.n, o.w - 1)))
        columns = {c: own.column(c) for c in ("machine_id", "sensor_id", "ts", "tick", "threshold")} | {"rn": pa.array(rn[last]), "first_ts": tail, "p": pa.array(p), "rule": pa.array(RULES).take(pa.array(got["rule"]))}
        if not below:
            whole = pa.decimal128(38, 0)
            for name in ("num", "den"):
                x = got[name]
                columns[name] = pa.array(x, pa.int64()).cast(whole) if x.dtype != object else pa.array([Decimal(int(y)) for y in x], whole)
            columns |= {c: pa.array(got[c].astype(bool)) for c in ("rotated", "single", "few")}
            columns |= {n: pa.array(got[c].astype(np.int32)) for n, c in (("n_distinct", "distinct"), ("iterations", "iterations"), ("divisions", "divisions"))}
            columns["k"] = own.column("k").cast(pa.int32())
            columns["labels"] = pa.nulls(count, pa.list_(pa.int32()))
            if with_labels:
                flat = turned(got["labels"], got["anchor"], got["shift"]).ravel()
                columns["labels"] = pa.ListArray.from_arrays(pa.array(np.arange(count + 1, dtype=np.int32) * o.w), pa.array(flat))
        names = [x.split()[0] for x in (FOUND if below else SCORED).split(", ")]
        out += pa.Table.from_arrays([columns[n] for n in names], names=names).combine_chunks().to_batches()
    return out


def _owner(table: pa.Table) -> np.ndarray:
    """Numbers the series, or pieces of them, in a sorted table."""
    sensor = table.column("sensor_id").combine_chunks().dictionary_encode().indices.to_numpy()
    new = np.zeros(len(sensor), bool)
    for x in (table.column("machine_id").to_numpy(), sensor, *([table.column("chunk").to_numpy()] if "chunk" in table.column_names else [])):
        new[1:] |= x[1:] != x[:-1]
    return np.cumsum(new)


def _kernel(o: Options, size: int, with_labels: bool, below: bool):
    """Sorted batches to windows. With column ``chunk`` the rows are numbered already, and a chunk's first ones may be the last of the one before."""
    most = max(4 * o.w, min(HELD_ROWS, 32_000_000 // o.w))

    def run(batches):
        held: list[pa.RecordBatch] = []
        kept, first = 0, 1  # rows at the head that are known from before, and the first one's number

        def scanned():
            nonlocal held, kept, first
            table = pa.Table.from_batches(held)
            owner = _owner(table)
            if "chunk" in table.column_names:
                rn = table.column("rn").to_numpy()
                old = rn <= table.column("chunk").to_numpy() * size
            else:
                begins = np.flatnonzero(np.append(True, owner[1:] != owner[:-1]))
                rn = np.arange(len(owner)) - begins[owner] + np.where(owner == 0, first, 1)
                old = np.zeros(len(rn), bool)
            old[:kept] = True
            yield from _scanned(table, rn, old, owner, o, with_labels, below)
            kept = min(o.w, len(owner) - int(np.searchsorted(owner, owner[-1])))
            first = int(rn[len(rn) - kept])
            held = table.slice(len(owner) - kept).to_batches()

        size_ = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(batch)
            size_ += batch.num_rows
            if size_ >= most:
                yield from scanned()
                size_ = 0
        if size_:
            yield from scanned()

    return run


def _bytes(df: DataFrame) -> int:
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def _run(readings: DataFrame, params: DataFrame, o: Options, chunk: int, most: int, labels: bool, below: bool) -> DataFrame:
    ship(readings.sparkSession)
    size, schema = max(chunk, o.w), FOUND if below else SCORED
    columns = [*SERIES, "ts", "tick", "v"]
    # What single clusters can never flag does not cross the cluster.
    meta = params.where("k > 1") if below and o.single else params

    def scan_all(rows: DataFrame, *more: str) -> DataFrame:
        dealt = attach(rows, meta).select(*columns, "k", "threshold", *more).repartition(*SERIES, *more[:1])
        return dealt.sortWithinPartitions(*SERIES, *more[:1], "ts", "tick").mapInArrow(_kernel(o, size, labels, below), schema)

    rows = readings.select(*columns)
    if _bytes(rows) < most:  # fewer bytes than a long series has rows
        return scan_all(rows)
    long = rows.groupBy(*SERIES).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > most).persist()
    total = long.agg(F.sum("n")).first()[0]
    if not total:
        return scan_all(rows)
    pieces = windows.chunked(windows.ranged(rows.join(long, list(SERIES), "left_semi"), -(-2 * total // most)), o.w, size)
    return scan_all(rows.join(long, list(SERIES), "left_anti")).unionByName(scan_all(pieces, "chunk", "rn"))


def score(readings: DataFrame, params: DataFrame, w: int = 10, n: int = 5, max_iter: int = 50, chunk: int = 1 << 20, most: int = 1 << 22, labels: bool = False, **switches: bool) -> DataFrame:
    """Every full window with its rule, probability and cost counters. Switches: see ``Options``."""
    return _run(readings, params, Options(w=w, n=n, max_iter=max_iter, **switches), chunk, most, labels, below=False)


def flag(scored: DataFrame) -> DataFrame:
    """Anomalies: windows less likely than their sensor's threshold."""
    return scored.where(F.col("p") < F.col("threshold"))


def detect(readings: DataFrame, params: DataFrame, w: int = 10, n: int = 5, max_iter: int = 50, chunk: int = 1 << 20, most: int = 1 << 22, **switches: bool) -> DataFrame:
    """Anomalies alone: the kernel flags them, and sensors with one cluster never leave the scan."""
    return _run(readings, params, Options(w=w, n=n, max_iter=max_iter, **switches), chunk, most, False, below=True)


BASELINE = {"rotation": False, "single": False, "few": False, "lazy": False, "ring": False, "sorted_sweep": False}


def explain_window(readings: DataFrame, params: DataFrame, machine_id: int, sensor_id: str, rn: int, **options) -> DataFrame:
    """One window's row with its labels."""
    one = readings.where((F.col("machine_id") == machine_id) & (F.col("sensor_id") == sensor_id))
    return score(one, params, labels=True, **options).where(F.col("rn") == rn)


def warm_up(readings: DataFrame, params: DataFrame, groups: int = 5000, rounds: int = 3) -> None:
    """The chain over a few groups, into nothing, before a measurement."""
    few = readings.limit(groups)
    for _ in range(rounds):
        score(few, params).write.format("noop").mode("overwrite").save()
