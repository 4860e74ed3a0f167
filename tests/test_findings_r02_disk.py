"""The disk index and the graphs whose builds are timed."""

from __future__ import annotations

import numpy as np
import pytest

from vecblock.baselines import graphs as G
from vecblock.plans import workloads as W
from vecblock.sources import vectors as V

SF = "/root/testdata/sf0.001"


def test_the_disk_index_is_asked_by_every_twentieth_row(spark, monkeypatch):
    """Each size asks with the rows whose id is divisible by 20, against all rows."""

    class Asked(Exception):
        pass

    def asked(v, every=10):
        raise Asked(v.count(), every)

    for name in ("build", "save", "open_tree"):
        monkeypatch.setattr(W.tree, name, lambda *a, **b: None)
    monkeypatch.setattr(V, "queries_of", asked)
    with pytest.raises(Asked) as e:
        W.QUERIES["w_disk"].__wrapped__(spark, SF)
    assert e.value.args == (4 * V.hubs(spark, SF).count(), 20)


@pytest.mark.parametrize("alpha", [1.0, 1.2])
def test_pruning_reads_kept_distances_without_arrays(alpha, monkeypatch):
    rng = np.random.default_rng(6)
    x = np.round(rng.normal(size=(80, 3)), 1)
    table = G._table(x, "l2")
    cand = [rng.permutation(80)[:30].tolist() for _ in range(80)]
    want = [G._prune(x, i, np.array(c), 6, alpha, "l2") for i, c in enumerate(cand)]
    monkeypatch.setattr(G, "np", None)
    assert [G._prune(x, i, c, 6, alpha, "l2", table) for i, c in enumerate(cand)] == want
