"""Correlated order: the nearest unused query at every size."""

from __future__ import annotations

import numpy as np
import pytest

from vecblock.operators import temporal


def brute(x):
    left, seq = set(range(1, len(x))), [0]
    while left:
        rest = np.array(sorted(left))
        seq.append(int(rest[np.argmin(((x[rest] - x[seq[-1]]) ** 2).sum(1))]))
        left.remove(seq[-1])
    return seq


@pytest.mark.parametrize("kind", ["spread", "lattice"])
def test_order_is_exact_when_cells_are_used(spark, monkeypatch, kind):
    monkeypatch.setattr(temporal, "DIRECT", 20, raising=False)
    monkeypatch.setattr(temporal, "MAX_CHAIN", 100, raising=False)  # the former bound
    rng = np.random.default_rng(2)
    x = rng.normal(size=(600, 4)) if kind == "spread" else rng.integers(0, 5, (600, 4)).astype(float)
    q = spark.createDataFrame([(i, v) for i, v in enumerate(x.tolist())], "query_id long, v array<double>")
    got = [r.query_id for r in temporal.order_correlated(q).orderBy("seq").collect()]
    assert got == brute(x)
