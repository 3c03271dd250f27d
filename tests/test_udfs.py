"""SQL functions over windows: batches at once, rows as one by one."""

import random

import numpy as np
import pyarrow as pa

from shiftscan.functions import udfs
from shiftscan.operators.kernel import Block, Options, clusters, probabilities


def alone(v, k, n):
    """Labels and probability of one window."""
    block = Block(np.array(v), len(v))
    labels, _ = clusters(block, np.zeros(1, np.int64), np.array([min(k, len(block.values))]), Options(w=len(v)))
    if len(v) < 2:
        return labels[0].tolist(), None
    num, den, _ = probabilities(labels, np.zeros(1, np.int64), np.zeros(1, np.int64), Options(w=len(v), n=n))
    return labels[0].tolist(), int(num[0]) / int(den[0])


def test_a_batch_is_clustered_at_once(monkeypatch):
    """One call for each length, whatever the number of windows; windows, k and n that are null or empty give null."""
    rng = random.Random(3)
    w = [[rng.randint(-20, 20) for _ in range(rng.choice([1, 4, 10]))] for _ in range(300)] + [None, [], [1, 2], [1, 2]]
    k = [rng.choice([1, 2, 3, 11]) for _ in range(300)] + [2, 2, None, 0]
    n = [rng.choice([1, 5, 40]) for _ in w]
    want = [alone(v, c, t) for v, c, t in zip(w[:300], k, n)] + [(None, None)] * 4
    calls = []

    def counted(*args):
        calls.append(args)
        return clusters(*args)

    monkeypatch.setattr(udfs, "clusters", counted)
    args = pa.array(w, pa.list_(pa.int64())), pa.array(k, pa.int32()), pa.array(n, pa.int32())
    assert udfs._cluster_labels(*args[:2]).to_pylist() == [x for x, _ in want] and len(calls) == 3
    assert udfs._window_p(*args).to_pylist() == [p for _, p in want] and len(calls) == 6
