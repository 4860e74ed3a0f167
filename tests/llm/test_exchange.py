"""Rows that share a doc_id or have none, hashes that used to collide, buckets in two steps, and the stored line index."""

from __future__ import annotations

import collections
import random

import numpy as np
import pytest
from tokenizers import Tokenizer

from vecblock.llm import exchange, kernels, line_dedup, substring_dedup, token_files
from vecblock.llm.entries import vocabulary

SCHEMA = "doc_id long, text string"
TOP = 2**63 - 1


def texts(n=90, seed=3):
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(60)]
    passage = " ".join(rng.choice(words) for _ in range(64))
    line = "a line that several documents hold"
    rows = []
    for k in range(n):
        body = " ".join(rng.choice(words) for _ in range(rng.randint(0, 120)))
        if k % 3 == 0:
            body = passage + "\n" + body
        if k % 4 == 0:
            body += "\n" + line
        rows.append((rng.choice([None, 1, 2, 3, 7, 7, TOP]), body if k % 11 else None))
    return rows


def brute_substrings(rows, width=50):
    key = lambda i: (i is None, i or 0)
    low = {}
    for i, t in rows:
        w = (t or "").split()
        for j in range(len(w) - width + 1):
            g = tuple(w[j : j + width])
            low[g] = min(low.get(g, (True, TOP)), key(i))
    out = []
    for i, t in rows:
        w = (t or "").split()
        gone = {k for j in range(len(w) - width + 1) if key(i) > low[tuple(w[j : j + width])] for k in range(j, j + width)}
        out.append((i, len(w), " ".join(x for k, x in enumerate(w) if k not in gone)))
    return collections.Counter(out)


def brute_lines(rows):
    key = lambda i: (i is None, i or 0)
    of = lambda x: x.strip(" \t\n\x0b\x0c\r").lower()
    held = collections.defaultdict(set)
    for i, t in rows:
        for x in (t or "").split("\n"):
            held[of(x)].add(key(i))
    out = []
    for i, t in rows:
        kept = [x for x in (t or "").split("\n") if not (len(of(x)) >= 20 and len(held[of(x)]) >= 3 and max(held[of(x)]) != key(i))]
        out.append((i, len((t or "").split("\n")), "\n".join(kept)))
    return collections.Counter(out)


@pytest.fixture(scope="module")
def rows():
    return texts()


@pytest.mark.parametrize("fan", [exchange.FAN, 8])
def test_substrings_of_shared_and_missing_ids(spark, rows, fan, monkeypatch):
    """With a small fan the entries go in two steps."""
    monkeypatch.setattr(exchange, "FAN", fan)
    monkeypatch.setattr(exchange, "CHUNK_BYTES", 4000)
    monkeypatch.setattr(exchange, "GATHER", 500)
    df = spark.createDataFrame(rows, SCHEMA).repartition(3)
    got = collections.Counter((r.doc_id, r.n_words, r.kept) for r in substring_dedup.remove_repeats(df, buckets=64).collect())
    assert got == brute_substrings(rows)


def test_lines_of_shared_and_missing_ids(spark, rows, monkeypatch):
    monkeypatch.setattr(exchange, "CHUNK_BYTES", 3000)
    df = spark.createDataFrame(rows, SCHEMA).repartition(3)
    got = collections.Counter((r.doc_id, r.n_lines, r.kept) for r in line_dedup.drop_lines(df).collect())
    assert got == brute_lines(rows) and sum(v for (_, _, kept), v in got.items()) == len(rows)


def test_rows_that_used_to_share_a_checksum(spark):
    """Two texts under one id whose CRC-32 agree in their low 16 bits."""
    w, u = " ".join(f"w{k}" for k in range(60)), " ".join(f"u{k}" for k in range(60))
    rows = [(1, w), (7, w + " tailA"), (7, u + " x76444"), (None, w), (None, u)]
    got = substring_dedup.remove_repeats(spark.createDataFrame(rows, SCHEMA)).collect()
    assert collections.Counter((r.doc_id, r.n_words, r.kept) for r in got) == brute_substrings(rows)


def test_token_file_of_shared_and_missing_ids(spark, rows):
    from vecblock.llm.shared import shared_root

    path = vocabulary("byte_bpe_50k.json")
    tok = Tokenizer.from_file(path)
    out = f"{shared_root(spark)}/tokens-shared"
    token_files.write_token_file(spark.createDataFrame(rows, SCHEMA), path, out, parts=6)
    back = token_files.read_token_file(spark, out, with_ids=True).orderBy("start").collect()
    order = [(r.doc_id is None, r.doc_id or 0) for r in back]
    assert order == sorted(order)
    assert [r.start for r in back] == np.cumsum([0, *(r.n_tokens for r in back)])[:-1].tolist()
    ids = lambda t: tuple(tok.encode(t or "", add_special_tokens=False).ids + [0])
    assert collections.Counter((r.doc_id, tuple(np.frombuffer(r.ids, np.uint32).tolist())) for r in back) == collections.Counter((i, ids(t)) for i, t in rows)


def _thue_morse(n):
    return np.array([bin(k).count("1") & 1 for k in range(n)], bool)


def test_no_structured_collisions():
    """Polynomials modulo a power of two give these strings one hash, whatever their base is."""
    t = _thue_morse(1024)
    for size in (256, 512, 1024):
        a = bytes(np.where(t[:size], ord("a"), ord("b")).astype(np.uint8))
        b = bytes(np.where(t[:size], ord("b"), ord("a")).astype(np.uint8))
        raw = np.frombuffer(a + b, np.uint8)
        for salt in (0, 1):
            h = kernels.span_hashes(raw, np.array([0, size]), np.array([size, 2 * size]), salt=salt)
            assert h[0] != h[1]
    two = kernels.span_hashes(np.frombuffer(b"xy", np.uint8), np.array([0, 1]), np.array([1, 2]))
    a, b = np.where(_thue_morse(2048), *two), np.where(_thue_morse(2048), *two[::-1])
    assert kernels.window_checks(a, 2048)[0] != kernels.window_checks(b, 2048)[0]


def test_hashes_by_content():
    rng = random.Random(1)
    text = " ".join("".join(rng.choice("abCÉ中") for _ in range(rng.choice([1, 3, 8, 9, 17, 300, 600]))) for _ in range(300)).encode()
    words = text.split()
    raw = np.frombuffer(text, np.uint8)
    for lower in (False, True):
        w = kernels.words(raw, np.array([0, len(raw)]), lower=lower, twice=True)
        seen = {}
        for x, pair in zip(words, zip(w.hash.tolist(), w.check.tolist())):
            assert seen.setdefault(x.lower() if lower else x, pair) == pair
        assert len(set(seen.values())) == len(seen)
        other = kernels.words(np.frombuffer(b"pad " + text, np.uint8), np.array([0, 4, len(raw) + 4]), lower=lower)
        assert other.hash[1:].tolist() == w.hash.tolist()


def test_colliding_pieces_are_told_apart():
    table = token_files.PieceTable(np.uint16, 1 << 6)
    h, check = np.array([5, 5, 9], np.uint64), np.array([1, 2, 1], np.uint32)
    table.add(h, check, [np.array(x, np.uint16).tobytes() for x in ([1], [2, 3], [4])])
    slot = table.find(h, check)
    ids, size = table(slot)
    assert ids.tolist() == [1, 2, 3, 4] and size.tolist() == [1, 2, 1]
    assert table.find(np.array([5], np.uint64), np.array([7], np.uint32)).tolist() == [-1]


def test_probes_use_the_stored_arrays():
    rng = np.random.default_rng(4)
    h = np.sort(np.unique(rng.integers(0, 2**63, 4000).astype(np.uint64)))
    h[11] = h[10]  # one hash, two fingerprints
    g = rng.integers(0, 2**63, len(h)).astype(np.uint64)
    docs, keeper, null = rng.integers(3, 900, len(h)), rng.integers(-5, 5, len(h)), rng.random(len(h)) < 0.1
    index = line_dedup.ShardIndex.unpack(line_dedup.ShardIndex.build(h, g, docs, keeper, null).pack())
    at, k, n = index.probe(h, g, 3)
    assert at.tolist() == list(range(len(h))) and k.tolist() == keeper.tolist() and n.tolist() == null.tolist()
    assert len(index.probe(h, g + np.uint64(1), 3)[0]) == len(index.probe(h + np.uint64(1), g + np.uint64(1), 3)[0]) == 0
    index.keeper[:] = 77  # answers come from the arrays alone
    assert (index.probe(h, g, 3)[1] == 77).sum() == len(h) - 1
    assert len(index.fingerprint) == len(h) - 1 and index.ph.bits_per_key < 8


def test_line_index_is_stored_once(spark, rows):
    from vecblock.llm.shared import Stored

    df = spark.createDataFrame(rows, SCHEMA)
    chunks = Stored(spark, df.mapInArrow(line_dedup._store(20), exchange.CHUNK + ", keys binary, lines binary"), "chunks").df
    index = line_dedup.line_index(chunks, 3, 4).df.collect()
    held = collections.defaultdict(set)
    for i, t in rows:
        for x in (t or "").split("\n"):
            if len(x.strip()) >= 20:
                held[x.strip().lower()].add(i)
    assert sum(r.n_keys for r in index) == sum(len(v) >= 3 for v in held.values()) > 0
    found = [line_dedup.ShardIndex.unpack(r["index"]) for r in index]
    most = sorted(len(v) for v in held.values() if len(v) >= 3)
    assert all(3 <= c <= m for c, m in zip(sorted(c for x in found for c in x.count.tolist()), most))
