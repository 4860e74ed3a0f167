"""The registry: names match, and SQL keys give the oracle's rows on the smallest tables."""

from __future__ import annotations

import os

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
KEYS = ["knn_l2_10", "tree_search_exact_pruned", "tree_invariants", "links_full", "view_farthest", "lru_stack_distance", "delete_search", "cube_lineitem", "sessions_events", "kmeans_one_round"]


def plain(v):
    return round(float(v), 6) + 0.0 if type(v).__name__ in ("float", "Decimal") else str(v) if not isinstance(v, (int, bool, type(None))) else v


def test_registry():
    q, s = entry.queries(), entry.oracle_sql()
    assert set(s) <= set(q) and len(q) > 150


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
@pytest.mark.parametrize("key", KEYS)
def test_oracle(spark, key):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = entry.queries()[key](spark, SF)
    cols = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=repr)
    rel = con.execute(entry.oracle_sql()[key])
    names = [d[0] for d in rel.description]
    want = sorted((tuple(plain(r[names.index(c)]) for c in cols) for r in rel.fetchall()), key=repr)
    assert sorted(names) == cols and got == want


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
def test_entry(spark):
    assert entry.entry(spark).count() == 500
