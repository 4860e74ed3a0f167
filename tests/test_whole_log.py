"""The measures over the whole access log, replayed event by event."""

from __future__ import annotations

import os
from collections import OrderedDict

import pytest

from vecblock.plans.vector_queries import QUERIES

SF = "/root/testdata/sf0.01"


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
def test_whole_log(spark):
    rows = sorted((r.event_id, r.user_id % 97) for r in spark.read.parquet(f"{SF}/events.parquet").select("event_id", "user_id").collect())
    assert len(rows) > 4000
    cache, want = OrderedDict(), []
    for seq, node in rows:
        want.append((seq, node, node in cache))
        cache.pop(node, None)
        cache[node] = True
        if len(cache) > 20:
            cache.popitem(last=False)
    for name in ("lru_stack_distance", "lru_replayed"):
        assert sorted(map(tuple, QUERIES[name](spark, SF).select("seq", "node_id", "hit").collect())) == want
    assert sum(r.reads for r in QUERIES["io_lru"](spark, SF).collect()) == sum(not h for _, _, h in want)
    assert sum(r.accesses for r in QUERIES["warmup_curve"](spark, SF).collect()) == len(rows)
    assert sum(r.reads for r in QUERIES["io_first_touch"](spark, SF).collect()) == len({n for _, n in rows})
    for name in ("hops_mean", "distance_count", "touched_fraction", "seek_distance", "io_pages"):
        assert QUERIES[name](spark, SF).count() > 0
