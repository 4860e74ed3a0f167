"""Different texts under one doc_id keep the links of each."""

from __future__ import annotations

import pytest

from vecblock.llm import minhash_dedup


@pytest.mark.parametrize("swap", [False, True])
def test_both_texts_of_an_id_are_linked(spark, swap):
    a, b = ([f"{x}{k}" for k in range(60)] for x in "ab")
    rows = [(5, a), (5, b), (7, [*a, "end"]), (9, [*b, "end"]), (11, [f"c{k}" for k in range(60)])]
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in (rows[::-1] if swap else rows)], "doc_id long, text string").coalesce(1)
    got = sorted((r.doc_id, r.component_id) for r in minhash_dedup.near_duplicates(docs).collect())
    assert got == [(5, 5), (5, 5), (7, 5), (9, 5), (11, 11)]
