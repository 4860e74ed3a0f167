"""Decontamination, quality classifier, toxicity, mixing and the pipeline against slow, independent versions."""

from __future__ import annotations

import collections
import math
import random
import re
import time

import numpy as np
import pyarrow as pa
import pytest

from vecblock.llm import decontaminate, mixing, quality_classifier, toxicity

TOKEN = re.compile(r"[0-9a-z\x80-\U0010ffff]+")


# --- greedy string tiling --------------------------------------------------------


def slow_tiling(doc, item, seed):
    """Longest unmarked common run again and again; the first in the item, then in the document, among equals."""
    used_d, used_i, covered = set(), set(), 0
    while True:
        best = None
        for i in range(len(item)):
            for d in range(len(doc)):
                k = 0
                while i + k < len(item) and d + k < len(doc) and item[i + k] == doc[d + k] and i + k not in used_i and d + k not in used_d:
                    k += 1
                if k >= seed and (best is None or (-k, i, d) < best):
                    best = (-k, i, d)
        if best is None:
            return covered
        n, i, d = -best[0], best[1], best[2]
        used_i.update(range(i, i + n))
        used_d.update(range(d, d + n))
        covered += n


@pytest.fixture(scope="module")
def tiling_case():
    rng = random.Random(6)
    vocab = [f"t{k}" for k in range(12)]
    items = [(k, " ".join(rng.choice(vocab) for _ in range(rng.choice([3, 4, 5, 9, 20, 30])))) for k in range(8)]
    docs = []
    for k in range(40):
        words = [rng.choice(vocab[:4] if k % 5 == 0 else vocab) for _ in range(rng.randint(0, 40))]
        for _ in range(k % 3):
            own = rng.choice(items)[1].split()
            a = rng.randrange(len(own))
            cut = rng.choice([own, own[a:] + own[:a], own[: len(own) // 2]])
            at = rng.randrange(len(words) + 1)
            words[at:at] = cut
        docs.append((k, rng.choice([" ", ", ", "\n"]).join(words).upper()))
    return items, docs


def slow_judge(items, text, seed=5):
    doc, best, cover, touched = TOKEN.findall(text.lower()), None, 0.0, 0
    for i, t in items:
        item = TOKEN.findall(t.lower())
        if len(item) < decontaminate.LEAST:
            continue
        got = slow_tiling(doc, item, min(seed, len(item))) / len(item)
        touched += got > 0
        if got > cover:
            best, cover = i, got
    return best, cover, touched


def test_tiling_equals_brute_force(tiling_case, monkeypatch):
    items, docs = tiling_case
    indexes = decontaminate.Index.build([i for i, _ in items], [t for _, t in items], 5)
    want = [slow_judge(items, t) for _, t in docs]
    for pairs in (1 << 20, 7):
        monkeypatch.setattr(decontaminate, "PAIRS", pairs)
        words, _ = decontaminate.tokens(pa.array([t for _, t in docs]))
        best, cover, touched = decontaminate.judge(indexes, words)
        assert [(None if b < 0 else b, c, t) for b, c, t in zip(best.tolist(), cover.tolist(), touched.tolist())] == want
    assert sum(c >= 0.7 for _, c, _ in want) > 5 and sum(0 < c < 0.7 for _, c, _ in want) > 5


def test_blocks_of_a_benchmark(spark, tiling_case):
    """Whatever the blocks, one at a time: the same verdicts; clashing columns, repeated rows, nulls and a one-token item do no harm."""
    items, docs = tiling_case
    rows = [*docs, docs[3], (None, docs[3][1]), (90, None)]
    df = spark.createDataFrame([(*r, 1, "x") for r in rows], "doc_id long, text string, b_item int, covered string")
    bench = spark.createDataFrame([*items, (50, "t1"), (51, None)], "item_id long, text string")
    want = collections.Counter((i, *slow_judge(items, t or "")) for i, t in rows)
    for chars in (1 << 20, 60):
        got = decontaminate.judged(df, bench, block_chars=chars).collect()
        assert collections.Counter((r.doc_id, r.best_item, r.covered, r.n_items) for r in got) == want
        assert all(r.contaminated == (r.covered >= 0.7) for r in got)


def test_equal_words_take_bounded_time():
    index = decontaminate.Index.build([1, 2], ["word " * 100, "word " * 400], 5)
    start = time.perf_counter()
    words, _ = decontaminate.tokens(pa.array(["word " * 60_000]))
    best, cover, _ = decontaminate.judge(index, words)
    assert best[0] == 1 and cover[0] == 1.0 and time.perf_counter() - start < 60


# --- site posteriors ---------------------------------------------------------------


def slow_rates(rows):
    """Method-of-moments shrinkage, group by group."""
    leaf = collections.defaultdict(list)
    for h, p, x in rows:
        leaf[h, p].append(x)
    host = collections.defaultdict(list)
    for (h, _), xs in leaf.items():
        host[h] += xs
    n = len(rows)
    rate = (sum(x for *_, x in rows) + 0.5) / (n + 1)
    means = {h: sum(xs) / len(xs) for h, xs in host.items()}
    spread = sum(len(host[h]) * (m - rate) ** 2 for h, m in means.items()) / n
    chance = sum(m * (1 - m) for m in means.values()) / n
    k = max(rate * (1 - rate) / max(spread - chance, 1e-6) - 1, 1.0)
    hosts = {h: (sum(xs) + k * rate) / (len(xs) + k) for h, xs in host.items()}
    out = {}
    for h, parent in hosts.items():
        own = {p: xs for (g, p), xs in leaf.items() if g == h}
        total = sum(map(len, own.values()))
        m = {p: sum(xs) / len(xs) for p, xs in own.items()}
        between = max(sum(len(own[p]) * (m[p] - parent) ** 2 for p in own) / total - sum(m[p] * (1 - m[p]) for p in own) / total, 1e-6)
        k2 = max(parent * (1 - parent) / between - 1, 1.0)
        out.update({(h, p): (parent, (sum(xs) + k2 * parent) / (len(xs) + k2), rate) for p, xs in own.items()})
    return out


def test_posteriors_equal_brute_force(spark):
    rng = random.Random(2)
    texts = [" ".join(rng.choice(["alpha", "beta", "gamma"]) for _ in range(rng.randint(0, 50))) + "#" * (40 * (k % 4 == 0)) for k in range(120)]
    rows = [(k if k % 13 else None, t if k % 17 else None, rng.choice(["a", "a", "b", "c", None]), rng.choice(["x", "y", None]), "mine", 0.5) for k, t in enumerate(texts)]
    rows += [rows[4], (7, "beta " * 30_000, "z", "only", "mine", 0.5)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, lang string, host_rate string, logit_of_text double")
    labels = spark.createDataFrame([(k, int(k % 4 != 0)) for k in range(120) if k % 13], "doc_id long, quality int")
    got = quality_classifier.score(df, labels).collect()
    assert len(got) == len(rows) and got[0].logit_of_text == 0.5
    want = slow_rates([(r.source, r.lang, r.doc_score) for r in got])
    for r in got:
        host, path, rate = want[r.source, r.lang]
        assert math.isclose(r.host_rate, host, rel_tol=1e-9) and math.isclose(r.path_rate, path, rel_tol=1e-9)
        z = math.log(r.doc_score / (1 - r.doc_score)) + math.log(path / (1 - path)) - math.log(rate / (1 - rate))
        assert math.isclose(r.posterior, 1 / (1 + math.exp(-z)), rel_tol=1e-7) and r.good == (r.posterior >= 0.5)
    thin = quality_classifier.score(df, labels, columns=["doc_id"]).collect()
    assert sorted(map(repr, ((r.doc_id, r.posterior) for r in thin))) == sorted(map(repr, ((r.doc_id, r.posterior) for r in got)))


def test_features_by_hand():
    text = "Ab ab ab ab! 12 |x|\n"
    raw = np.frombuffer(text.encode(), np.uint8)
    row = quality_classifier.features(raw, np.array([0, len(raw), len(raw)]))
    words = [w.lower() for w in text.split()]
    tri = list(zip(words, words[1:], words[2:]))
    share = [sum(text.encode().count(c) for c in kind) / len(raw) for kind in quality_classifier._CLASSES]
    extra = [sum(map(len, words)) / len(words), math.log1p(len(words)), len(set(words)) / len(words), 1 - len(set(tri)) / len(tri), math.log1p(len(raw))]
    assert np.allclose(row[0], share + extra) and not row[1].any()


# --- lexicon -------------------------------------------------------------------------


def slow_matches(lexicon, words):
    body = " " + " ".join(words) + " "
    spared = [(s, s + len(t) - 1) for t in lexicon.exceptions for s in range(len(body)) if body.startswith(t, s)]
    out = []
    for s in range(len(body)):
        here = [(w, t) for t, w in lexicon.weights.items() if body.startswith(t, s)]
        if here:
            w, t = max(here, key=lambda x: x[0])
            if not any(a <= s and s + len(t) - 1 <= b for a, b in spared):
                out.append((s, w, t))
    return out


def test_matches_equal_brute_force():
    rng = random.Random(9)
    words = ["".join(rng.choice("ab") for _ in range(rng.randint(1, 5))) for _ in range(30)]
    terms = {f" {w} " for w in words[:8]} | {f" {w[:k]}" for w in words[8:16] for k in (1, 2, 4)}
    weights = {t: 0.5 + k / 7 for k, t in enumerate(sorted(terms))}
    phrases = {f" {a} {b} " for a in words[:8] for b in words[16:22]}
    lexicon = toxicity.Lexicon(weights, {p for p in phrases if p not in weights})
    for _ in range(60):
        text = [rng.choice(words) for _ in range(rng.randint(0, 40))]
        assert lexicon.matches(text) == slow_matches(lexicon, text)


def test_matching_is_linear():
    lexicon = toxicity.Lexicon({" bad ": 2.0, " ba": 1.0}, {" bad luck ", " luck bad "})
    spent = []
    for n in (20_000, 160_000):
        text = ["bad", "luck"] * (n // 2) + ["bad", "bad"]
        start = time.perf_counter()
        assert len(lexicon.matches(text)) == 1
        spent.append(time.perf_counter() - start)
    assert spent[1] < 40 * spent[0] + 1


def test_long_repeated_and_missing_rows(spark):
    rows = [(k, "sun moon " * 20 + ("gronk" if k % 5 == 0 else "")) for k in range(60)] + [(5, "sun gronk"), (None, "gronk"), (70, None), (71, "sun moon " * 200_000 + "gronk"), (71, "")]
    labels = spark.createDataFrame([(k, int(k % 5 == 0)) for k in range(60)], "doc_id long, toxic int")
    df = spark.createDataFrame([(*r, "clash") for r in rows], "doc_id long, text string, score string")
    got = toxicity.score(df, labels).collect()
    assert collections.Counter(r.doc_id for r in got) == collections.Counter(i for i, _ in rows)
    assert all(r.predicted == 1 for r in got if r.doc_id is None or (r.doc_id < 60 and r.doc_id % 5 == 0))


# --- mixing ----------------------------------------------------------------------------


def test_taken_equals_brute_force(spark):
    """Budgets bought in key order, recomputed row by row; ties of the key, repeated rows, nulls and clashing names."""
    import hashlib

    rng = random.Random(12)
    rows = [(rng.choice([None, 1, 2, 3, 4, 5, 6, 7]), " ".join("w" * 3 for _ in range(rng.randint(0, 30))) if rng.random() > 0.1 else None, rng.choice(["a", "b", "b", "b", "c", None]), 0) for _ in range(150)]
    rows += [(9, "w " * 4000, "a", 0)] * 2
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, cut_epochs int")
    size = lambda t: len((t or "").split())
    total = collections.Counter()
    for _, t, s, _ in rows:
        total[s] += size(t)
    got = mixing.mix(df).collect()
    target = {r.source: r.target for r in got}
    want = collections.Counter()
    for s in total:
        key = lambda r: (int(hashlib.md5("|".join(["17", *([str(r[0])] if r[0] is not None else []), str(size(r[1]))]).encode()).hexdigest()[:15], 16), r[0] is not None, r[0] or 0, size(r[1]))
        budget = math.floor(target[s] + 0.5)
        epochs = min(budget // max(total[s], 1), 3)
        left = budget - epochs * max(total[s], 1) if epochs < 3 else 0
        for r in sorted((r for r in rows if r[2] == s), key=key):
            part = max(0, min(size(r[1]), left))
            left -= part
            want[r[0], s, size(r[1]), epochs * size(r[1]) + part] += 1
    assert collections.Counter((r.doc_id, r.source, r.size, r.taken) for r in got) == want
    assert mixing.mixed_documents(df).columns == df.columns
