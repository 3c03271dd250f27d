"""SQL functions over single windows and over scores."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..operators.kernel import Block, Options, clusters, probabilities
from ..plans.chain import divided
from ..ship import ship


def _alike(w: pa.Array, k: pa.Array, *more: pa.Array) -> Iterator[tuple[np.ndarray, int, np.ndarray]]:
    """(rows, length, labels) of the windows of each length; rows without values or clusters are left out."""
    size = pc.fill_null(pc.list_value_length(w), 0).to_numpy(zero_copy_only=False)
    good = (size > 0) & (pc.fill_null(k, 0).to_numpy(zero_copy_only=False) != 0)
    for x in more:
        good &= x.is_valid().to_numpy(zero_copy_only=False)
    for n in np.unique(size[good]):
        rows = np.flatnonzero(good & (size == n))
        flat = w.take(pa.array(rows)).flatten()
        if flat.null_count:
            raise TypeError("a window holds null")
        v = (flat if pa.types.is_integer(flat.type) else pc.trunc(flat)).cast(pa.int64()).to_numpy()
        at = np.arange(len(rows)) * int(n)
        block = Block(v, int(n), np.repeat(np.arange(len(rows), dtype=np.int32), n))
        distinct = (block.last.reshape(len(rows), n) < 0).sum(1)
        yield rows, int(n), clusters(block, at, np.minimum(k.take(pa.array(rows)).to_numpy(), distinct), Options(w=int(n)))[0]


def _cluster_labels(w: pa.Array, k: pa.Array) -> pa.Array:
    """The windows of a batch that are as long are clustered together."""
    parts, place, start = [pa.array([], pa.list_(pa.int32()))], np.full(len(w), -1), 0
    for rows, n, labels in _alike(w, k):
        parts.append(pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1, dtype=np.int32) * n), pa.array(labels.astype(np.int32).ravel())))
        place[rows] = start + np.arange(len(rows))
        start += len(rows)
    return pa.concat_arrays(parts).take(pa.array(place, mask=place < 0))


def _window_p(w: pa.Array, k: pa.Array, n: pa.Array) -> pa.Array:
    p = np.full(len(w), np.nan)
    for rows, size, labels in _alike(w, k, n):
        if size < 2:
            continue
        last = n.take(pa.array(rows)).to_numpy()
        for t in np.unique(last):
            some = np.flatnonzero(last == t)
            num, den, _ = probabilities(labels, some, np.zeros(len(some), np.int64), Options(w=size, n=int(t)))
            p[rows[some]] = divided(num, den)
    return pa.array(p, mask=np.isnan(p))


def _least_likely(p: pd.Series) -> float:
    """The smallest probability of a group."""
    return float(p.min()) if len(p) else float("nan")


def _dispersion(v: pd.Series) -> int:
    """Distinct values of a group."""
    return int(v.nunique())


class _WindowTrace:
    """The centres of one window's clusters after each iteration."""

    def eval(self, values: list, k: int):
        centres = [(x, 1) for x in sorted(list(dict.fromkeys(values))[:k])]
        for i in range(51):
            for label, (s, n) in enumerate(centres):
                yield i, label, s, n
            own: list[list[int]] = [[] for _ in centres]
            for x in values:
                own[sum(2 * x * a[1] * b[1] >= a[0] * b[1] + b[0] * a[1] for a, b in zip(centres, centres[1:]))].append(x)
            new = [(sum(o), len(o)) if o else c for o, c in zip(own, centres)]
            if all(a[0] * b[1] == b[0] * a[1] for a, b in zip(new, centres)):
                return
            centres = new


def functions() -> dict:
    """SQL name -> function; made on the driver only, executors import the plain ones above."""
    return {
        "cluster_labels": F.arrow_udf(_cluster_labels, "array<int>"),
        "window_p": F.arrow_udf(_window_p, "double"),
        "least_likely": F.pandas_udf(_least_likely, "double"),
        "dispersion": F.pandas_udf(_dispersion, "long"),
    }


def register(spark: SparkSession) -> None:
    ship(spark)
    for name, f in functions().items():
        spark.udf.register(name, f)
    spark.udtf.register("window_trace", F.udtf(_WindowTrace, returnType="iteration int, label int, total long, members long"))
