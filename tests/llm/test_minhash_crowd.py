"""Crowds of near copies lose no link of a member to a text that is no candidate of their head."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from vecblock.llm import minhash_dedup

CROWDS, COPIES = 10, 120


def chains():
    """doc_id -> text: in each crowd near copies of 100 shingles, one member of 106 and one text of 132 that contains it."""
    texts = {}
    for c in range(CROWDS):
        head = [f"h{c}x{k}" for k in range(104)]
        tail = [f"t{c}x{k}" for k in range(32)]
        texts.update({1000 * c + k: head[:-1] + [f"c{c}x{k}"] for k in range(COPIES)})
        texts[1000 * c + 998] = head + tail[:6]
        texts[1000 * c + 999] = head + tail
    return {k: " ".join(w) for k, w in texts.items()}


def test_head_answers_for_its_members():
    texts = chains()
    ids = np.array(list(texts))
    sets = [next(minhash_dedup.shingle_sets(np.frombuffer(t.encode(), np.uint8), np.array([0, len(t)]), 5)) for t in texts.values()]
    size = np.array([len(s) for s in sets])
    assert sorted(set(size.tolist())) == [100, 106, 132]
    sides = minhash_dedup.tuple_hashes(np.concatenate(sets), np.cumsum(size) - size, 10, 2)
    batch = pa.RecordBatch.from_arrays([pa.array(ids), pa.array(size), *(pa.array(x.view(np.int64).tolist()) for x in sides)], names=["rep", "n", "left", "right"])
    dealt = pa.Table.from_batches(list(minhash_dedup._deal(1)([batch])))
    assert sum(x.as_py()[:1] == b"D" for x in dealt.column("block")) == 1  # the crowd is thinned
    pairs = minhash_dedup._forests(10, 80)(dealt)
    up = {i: i for i in ids.tolist()}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for u, v in zip(pairs.column("u").to_pylist(), pairs.column("v").to_pylist()):
        up[find(u)] = find(v)
    assert [c for c in range(CROWDS) if find(1000 * c + 998) != find(1000 * c + 999)] == []


def test_chain_beyond_a_crowd(spark):
    docs = spark.createDataFrame(list(chains().items()), "doc_id long, text string").coalesce(1)
    got = {r.doc_id: r.component_id for r in minhash_dedup.near_duplicates(docs).collect()}
    assert len(got) == CROWDS * (COPIES + 2)
    assert [(k, c) for k, c in got.items() if c != k // 1000 * 1000] == []


GROUPS = 12


def lone_members():
    """In each group one text of 103 words, 150 variants of its last word, one member with 3 more words, and one text with 25 more."""
    texts = {}
    for c in range(GROUPS):
        base = [f"g{c}x{k}" for k in range(103)]
        member = base + [f"m{c}x{k}" for k in range(3)]
        rows = [base, *(base[:-1] + [f"v{c}x{k}" for k in range(150)][k : k + 1] for k in range(150)), member, member + [f"z{c}x{k}" for k in range(25)]]
        texts.update({1000 * c + k: " ".join(w) for k, w in enumerate(rows)})
    return texts


def test_a_lone_member_keeps_its_link(spark):
    docs = spark.createDataFrame(list(lone_members().items()), "doc_id long, text string").coalesce(2)
    got = {r.doc_id: r.component_id for r in minhash_dedup.near_duplicates(docs, 4).collect()}
    assert sum(got[1000 * c + 152] == 1000 * c for c in range(GROUPS)) == GROUPS
    assert [(k, c) for k, c in got.items() if c != k // 1000 * 1000] == []


def test_candidate_recall():
    """Pairs of sets at a Jaccard similarity of 0.80 to 0.85: at most two in a thousand are no candidates."""
    rng = np.random.default_rng(11)
    sets, true = [], 0
    for _ in range(4000):
        n = int(rng.integers(40, 400))
        goal = rng.uniform(0.80, 0.85)
        common = int(np.ceil(2 * n * goal / (1 + goal)))
        items = rng.integers(0, 2**63, 2 * n - common).astype(np.uint64)
        sets += [np.unique(items[:n]), np.unique(np.concatenate([items[:common], items[n:]]))]
        true += 100 * len(np.intersect1d(*sets[-2:])) >= 80 * len(np.union1d(*sets[-2:]))
    assert true > 3900
    size = np.array([len(s) for s in sets])
    left, right = minhash_dedup.tuple_hashes(np.concatenate(sets), np.cumsum(size) - size, 10, 2)
    sketch = np.hstack([left, right])
    same = sketch[::2] == sketch[1::2]
    found = same[:, :10].any(1) & same[:, 10:].any(1) & (same.sum(1) >= minhash_dedup.AGREE)
    assert found.mean() > 0.998, found.mean()


def test_hot_nodes_of_a_star(spark, monkeypatch):
    """A hot centre, a chain and a clique: components do not depend on how hot keys are joined."""
    pairs = [(5, k) for k in range(100, 400)] + [(399, 1)] + [(k, k + 1) for k in range(500, 540)] + [(900 + a, 900 + b) for a in range(12) for b in range(a)]
    df = spark.createDataFrame(pairs, "u long, v long").repartition(4)
    want = {r.v: r.c for r in minhash_dedup.components(df, spark).df.collect()}
    assert want == {5: 1, **dict.fromkeys(range(100, 400), 1), **dict.fromkeys(range(501, 541), 500), **dict.fromkeys(range(901, 912), 900)}
    monkeypatch.setattr(minhash_dedup, "HOT", 3)
    assert {r.v: r.c for r in minhash_dedup.components(df, spark).df.collect()} == want
