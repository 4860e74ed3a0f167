"""The training-data operators against brute force, with awkward rows."""

from __future__ import annotations

import collections
import hashlib
import itertools
import os
import random
import re
import struct
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecblock.llm import decontaminate, exchange, kernels, line_dedup, minhash_dedup, mixing, quality_classifier, quality_rules, substring_dedup, token_counts, token_files, toxicity
from vecblock.llm.entries import vocabulary

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, kept string, n_words int, rep string, score string"


def corpus(seed=0, n=120):
    """Copies, near copies, shared passages and lines, nulls, blanks, odd spaces, one long text."""
    rng = random.Random(seed)
    vocab = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 7))) for _ in range(300)] + ["É", "ß", "中文", "I'm", "x-y"]
    line = lambda k: " ".join(rng.choice(vocab) for _ in range(k))
    passage, common = line(70), line(9)
    texts = []
    for i in range(n):
        t = "\n".join(line(rng.randint(3, 40)) for _ in range(rng.randint(1, 6)))
        if i % 7 == 0:
            t += "\n" + passage + "\n" + line(5)
        if i % 5 == 0:
            t = t + "\n  " + common.upper() + " \t\n" + line(4)
        texts.append(t)
    texts += [texts[3], texts[3], texts[4].upper(), texts[5] + " tail", texts[10] + "\n"]
    texts += [None, "", "   \n\t ", "one", "two words", "a b c d", "A B C D", "a b a b a b a b", " x y\x1cz ", line(6000), "\n\n\n"]
    return texts


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", ["s0", "s1", None][i % 3] if i % 2 else "s0", len(t or ""), "clash", 1, "r", "s") for i, t in enumerate(corpus())]
    return spark.createDataFrame(rows, SCHEMA).repartition(5).cache()


def rows_of(docs):
    return sorted(((r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()), key=lambda r: r[0])


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def brute_components(sets, percent):
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        x, y = sets[a], sets[b]
        if x and y and 100 * len(x & y) >= percent * len(x | y):
            p, q = find(a), find(b)
            up[max(p, q)] = min(p, q)
    return {i: find(i) for i in sets}


@pytest.mark.parametrize("width", [4, 5])
def test_near_duplicates(spark, docs, width):
    sets = {}
    for i, t in rows_of(docs):
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w[j : j + width]) for j in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())
    want = brute_components(sets, 80)
    got = {r.doc_id: r for r in minhash_dedup.near_duplicates(docs, width).collect()}
    assert {i: (r.n_shingles, r.component_id, r.kept) for i, r in got.items()} == {i: (len(sets[i]), want[i], want[i] == i) for i in sets}
    kept = minhash_dedup.keep_one(docs, width)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect()) == sorted(i for i in want if want[i] == i)


def test_near_duplicate_groups_without_a_common_head(spark):
    """A chain of ever further copies, and a group whose members are only close to its centre."""
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(6))
    chain = [[word() for _ in range(120)]]
    for _ in range(14):
        nxt = list(chain[-1])
        nxt[rng.randrange(120)] = word()
        chain.append(nxt)
    centre = [word() for _ in range(150)]
    star = [centre]
    for _ in range(40):
        c = list(centre)
        for at in rng.sample(range(5, 145), 3):
            c[at] = word()
        star.append(c)
    texts = [" ".join(w) for w in chain + star]
    rng.shuffle(texts)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    sets = {i: {tuple(t.split()[j : j + 4]) for j in range(len(t.split()) - 3)} for i, t in enumerate(texts)}
    want = brute_components(sets, 80)
    assert {r.doc_id: r.component_id for r in minhash_dedup.near_duplicates(df, 4).collect()} == want


def test_linked_is_exact():
    rng = np.random.default_rng(1)
    base = np.unique(rng.integers(0, 2**60, 80).astype(np.uint64))
    sets = []
    for _ in range(60):
        keep = rng.random(len(base)) > rng.choice([0.02, 0.1, 0.3])
        sets.append(np.unique(np.concatenate([base[keep], rng.integers(0, 2**60, 4).astype(np.uint64)])))
    plain = {i: set(s.tolist()) for i, s in enumerate(sets)}
    want = brute_components(plain, 80)
    up = {i: i for i in plain}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in minhash_dedup.linked(sets, 80):
        assert 100 * len(plain[a] & plain[b]) >= 80 * len(plain[a] | plain[b])
        p, q = find(a), find(b)
        up[max(p, q)] = min(p, q)
    assert {i: find(i) for i in plain} == want


def test_blocks_of_a_large_cluster(spark, docs, monkeypatch):
    want = sorted(map(tuple, minhash_dedup.near_duplicates(docs, 4).collect()))
    monkeypatch.setattr(minhash_dedup, "BLOCK", 150)
    monkeypatch.setattr(minhash_dedup, "BLOCK_SETS", 1)
    monkeypatch.setattr(minhash_dedup, "PARTY", 2)
    for heads in (16, 1):
        monkeypatch.setattr(minhash_dedup, "HEADS", heads)
        assert sorted(map(tuple, minhash_dedup.near_duplicates(docs, 4).collect())) == want


def test_substrings(spark, docs):
    width, low = 50, {}
    rows = rows_of(docs)
    for i, t in rows:
        w = (t or "").encode().split()
        for j in range(len(w) - width + 1):
            low.setdefault(tuple(w[j : j + width]), i)
    want = {}
    for i, t in rows:
        w = (t or "").encode().split()
        gone = {k for j in range(len(w) - width + 1) if low[tuple(w[j : j + width])] < i for k in range(j, j + width)}
        want[i] = (len(w), len(gone), b" ".join(x for j, x in enumerate(w) if j not in gone).decode())
    got = substring_dedup.remove_repeats(docs).collect()
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept) for r in got} == want
    assert all(sum(b - a for a, b in zip(r.intervals[::2], r.intervals[1::2])) == r.n_removed for r in got)


def test_lines(spark, docs):
    blank = b" \t\n\x0b\x0c\r"
    key = lambda x: x.encode().strip(blank).lower()
    rows, holders = rows_of(docs), collections.defaultdict(set)
    for i, t in rows:
        for x in (t or "").split("\n"):
            holders[key(x)].add(i)
    want = {}
    for i, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if not (len(key(x).decode()) >= 20 and len(holders[key(x)]) >= 3 and max(holders[key(x)]) != i)]
        want[i] = (len(lines), len(lines) - len(kept), "\n".join(kept))
    assert {r.doc_id: (r.n_lines, r.n_dropped, r.kept) for r in line_dedup.drop_lines(docs).collect()} == want
    assert sum(v[1] for v in want.values()) > 20


def test_repeated_ids_and_nulls_in_exchange_operators(spark):
    text = " ".join(f"w{i}" for i in range(60))
    rows = [(1, text), (1, text), (1, "other words here"), (None, text), (2, text + " x"), (3, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r.doc_id is None, r.doc_id, r.n_words, r.n_removed) for r in substring_dedup.remove_repeats(df).collect()), key=repr)
    assert got == sorted([(False, 1, 60, 0), (False, 1, 60, 0), (False, 1, 3, 0), (True, None, 60, 60), (False, 2, 61, 60), (False, 3, 0, 0)], key=repr)
    same = spark.createDataFrame([(i, "a line that is long enough\nown " + str(i)) for i in (1, 2, 2, 3)] + [(None, "A LINE THAT IS LONG ENOUGH  ")], "doc_id long, text string")
    assert sorted((r.doc_id is not None, r.n_dropped) for r in line_dedup.drop_lines(same).collect()) == [(False, 0), (True, 1), (True, 1), (True, 1), (True, 1)]


def test_perfect_hash():
    keys = np.unique(np.random.default_rng(2).integers(0, 2**63, 5000).astype(np.uint64))
    h = line_dedup.PerfectHash(keys)
    assert sorted(h(keys).tolist()) == list(range(len(keys))) and h.bits_per_key < 8
    assert line_dedup.PerfectHash(keys[:0]).n == 0


def test_rules(spark, docs):
    got = {r.doc_id: r for r in quality_rules.apply_policy(quality_rules.ledger(docs)).collect()}
    for i, t in rows_of(docs):
        t = t or ""
        w = WORD.findall(t)
        tri = collections.Counter(zip(w, w[1:], w[2:]))
        cover = {j + o for j in range(len(w) - 2) if tri[tuple(w[j : j + 3])] > 1 for o in range(3)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_lines, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), sum(t.count(c) for c in quality_rules.SYMBOLS), len(lines), len(lines) - len(set(lines)), len(cover))
    book = quality_rules.ledger(docs)
    ab = {r.rule: (r.n_failed, r.n_only) for r in quality_rules.ablation(book).collect()}
    fails = [r.failed for r in book.collect()]
    assert ab["min_words"] == (sum(f & 1 for f in fails), sum(f == 1 for f in fails))
    assert quality_rules.apply_policy(book, 1).where("NOT kept").count() <= quality_rules.apply_policy(book, 2).where("NOT kept").count()


def fill(sizes, weights, cap=3):
    """Water filling as the contract tells it: cut what is above, share the rest again."""
    total, target, open_ = sum(sizes.values()), {}, dict(weights)
    left = float(total)
    while open_:
        share = {s: left * w / sum(open_.values()) for s, w in open_.items()}
        over = [s for s in open_ if share[s] > cap * sizes[s]]
        if not over:
            return target | share
        for s in over:
            target[s] = float(cap * sizes[s])
            left -= target[s]
            del open_[s]
    return target


def test_mixing(spark, docs):
    size = {i: len(WORD.findall(t or "")) for i, t in rows_of(docs)}
    source = {r.doc_id: r.source for r in docs.collect()}
    names = sorted({s for s in source.values() if s is not None}) + [None]
    sizes = {s: sum(size[i] for i in size if source[i] == s) for s in names}
    want = fill(sizes, {s: (5, 2, 1)[k % 3] for k, s in enumerate(names)})
    got = mixing.mix(docs).collect()
    taken = collections.Counter()
    for r in got:
        taken[r.source] += r.taken
        assert r.size == size[r.doc_id] and r.source_size == sizes[r.source] and abs(r.target - want[r.source]) < 1e-6 and 0 <= r.taken <= 3 * r.size
    assert all(abs(taken[s] - want[s]) <= 1 for s in names)
    assert sorted(map(repr, got)) == sorted(map(repr, mixing.mix(docs.repartition(3)).collect()))
    drawn = collections.Counter(r.doc_id for r in mixing.mixed_documents(docs).collect())
    for r in got:
        assert drawn[r.doc_id] in (-(-r.taken // max(1, r.size)), r.taken // max(1, r.size), drawn[r.doc_id] if not r.size else -1)


def test_mixing_caps(spark):
    rows = [(i, "w " * (5 if i % 50 else 1), "big" if i % 50 else "a") for i in range(200)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    sizes = {"a": sum(len(t.split()) for _, t, s in rows if s == "a"), "big": sum(len(t.split()) for _, t, s in rows if s == "big")}
    want = fill(sizes, {"a": 5, "big": 2})
    assert {r.source: round(r.target, 6) for r in mixing.mix(df).collect()} == {s: round(v, 6) for s, v in want.items()}


def test_token_counts_and_files(spark, docs):
    from tokenizers import Tokenizer

    odd = ["It's ΣΑΣ x\x1cy <|endoftext|> we'll ÁB  ' ll 12３ 😀😀", "<|startoftext|>a", "aaaaaaaaaaaaaaaa ooooo", "x\u0085y  z ÷×é '", "tail  \n\n"]
    more = spark.createDataFrame([(1000 + i, t, None, None, 0, "", 0, "", "") for i, t in enumerate(odd)] + [(None, "null id", None, None, 0, "", 0, "", ""), (1, "again", None, None, 0, "", 0, "", "")], SCHEMA)
    every = docs.union(more)
    t9, t7 = Tokenizer.from_file(vocabulary("word_bpe_49k.json")), Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    rows = sorted(((r.doc_id is None, r.doc_id or 0, r.text or "") for r in every.collect()))
    got = sorted((r.doc_id is None, r.doc_id or 0, r.n_bytes, r.n_tokens, r.over_limit) for r in token_counts.count_tokens(every, vocabulary("word_bpe_49k.json")).collect())
    assert got == sorted((a, i, len(t.encode()), n := len(t9.encode(t, add_special_tokens=False).ids), n > 2048) for a, i, t in rows)

    from vecblock.llm.shared import shared_root

    path = f"{shared_root(spark)}/tokens-test"
    token_files.write_token_file(every, vocabulary("byte_bpe_50k.json"), path, parts=4)
    back = token_files.read_token_file(spark, path, with_ids=True).orderBy("start").collect()
    at = 0
    for r in back:
        assert r.start == at and zlib.crc32(r.ids) == r.ids_crc32 and len(r.ids) == 4 * r.n_tokens
        at += r.n_tokens
    assert [r.doc_id is None for r in back] == sorted(r.doc_id is None for r in back)
    assert [r.doc_id for r in back if r.doc_id is not None] == sorted(r.doc_id for r in back if r.doc_id is not None)
    ids = lambda t: t7.encode(t, add_special_tokens=False).ids + [0]
    want = collections.Counter((a, i, struct.pack(f"<{len(x)}I", *x)) for a, i, t in rows for x in [ids(t)])
    assert collections.Counter((r.doc_id is None, r.doc_id or 0, bytes(r.ids)) for r in back) == want


def test_pieces_at_random():
    from tokenizers import Tokenizer

    path = vocabulary("byte_bpe_50k.json")
    tok, enc = Tokenizer.from_file(path), token_files.Encoder(path)
    parts = ["a", "The", "é", "ñ", "×", "÷", " ", "  ", "\n", "\t", "'s", "'", "'ll", "12", "$", "##", "½", "中", " ", " ", "😀", "ß", "Ω", "\x85", "\x1c", "_", "²", "<|endoftext|>", "<|"]
    rng = random.Random(5)
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 14))) for _ in range(1500)]
    got = enc.encode([t.encode() for t in texts])
    assert [np.frombuffer(g, enc.type).tolist() for g in got] == [tok.encode(t, add_special_tokens=False).ids for t in texts]


def test_code_lengths_are_optimal_and_limited():
    counts = np.array([0, 1, 1, 2, 3, 5, 8, 13, 21, 34])
    got = token_files.code_lengths(counts)
    assert got[0] == 0 and sum(2.0 ** -int(x) for x in got[1:]) <= 1
    import heapq

    heap = [(int(c), [i]) for i, c in enumerate(counts) if c]
    heapq.heapify(heap)
    cost = 0
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        cost += a[0] + b[0]
        heapq.heappush(heap, (a[0] + b[0], a[1] + b[1]))
    assert int((counts * got).sum()) == cost
    steep = np.array([2**k for k in range(30)])
    assert token_files.code_lengths(steep).max() == token_files.LIMIT
    book = token_files.Codebook(token_files.code_lengths(steep))
    ids = np.random.default_rng(0).integers(0, 30, 5000)
    bits, marks = book.encode(ids)
    assert (book.decode(bits, marks, len(ids)) == ids).all()


def test_decontamination(spark, docs):
    item = "the quick brown fox jumps over the lazy dog while seven wizards watch from a crooked tower"
    w = item.split()
    shuffled = " ".join(w[9:] + ["filler"] + w[:9]).upper() + "!"
    third = " ".join(w[:6])
    rows = [(500, "start, " + item + ". end"), (501, shuffled), (502, third + " and else"), (503, None), (504, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string").union(docs.select("doc_id", "text"))
    bench = spark.createDataFrame([(1, item), (2, "tiny pair"), (3, None), (4, "")], "item_id long, text string")
    got = {r.doc_id: r for r in decontaminate.judged(df, bench).collect()}
    assert [i for i in got if got[i].contaminated] and {i for i, r in got.items() if r.contaminated} == {500, 501}
    assert got[500].best_item == 1 and got[500].covered == 1.0 and 0 < got[502].covered < 0.7
    blocks = {r.doc_id: r for r in decontaminate.judged(df, bench, block_chars=20).collect()}
    assert {i for i, r in blocks.items() if r.contaminated} == {500, 501}
    clean = decontaminate.clean_documents(docs.withColumn("covered", F.lit(1)), bench)
    assert clean.columns == [*docs.columns, "covered"] and clean.count() == docs.count()
    assert decontaminate.judged(df, bench.limit(0)).where("contaminated").count() == 0


def test_tiles_do_not_overlap():
    # the item's tokens 0-9; the document holds 3-9, then 0-5: tiles 7 + 3 tokens cannot reach beyond the item
    doc, item = np.array([0, 1, 2, 7, 8]), np.array([3, 4, 5, 0, 1])
    assert decontaminate.tile(doc, item, 5) == 7


def test_quality_classifier(spark, docs):
    rng = random.Random(3)
    rows, labels = [], []
    for i in range(200):
        good = i % 4 != 0
        t = " ".join(rng.choice(["alpha", "beta", "gamma", "delta"]) for _ in range(60))
        rows.append((i, t if good else t.replace(" ", "### "), f"host{i % 5}" if i % 9 else None, "p", 1.0))
        if i % 2 == 0:
            labels.append((i, int(good)))
    df = spark.createDataFrame([*rows, (900, None, "host1", None, 0.0), (901, "", None, None, 0.0)], "doc_id long, text string, source string, lang string, posterior double")
    lab = spark.createDataFrame(labels, "doc_id long, quality int")
    scored = quality_classifier.score(df.drop("posterior"), lab).collect()
    assert len(scored) == 202
    assert all(r.good == (r.doc_id % 4 != 0) for r in scored if r.doc_id < 200)
    kept = quality_classifier.keep_good(df, lab)
    assert kept.columns == df.columns and {r.doc_id for r in kept.collect()} >= {i for i in range(200) if i % 4}
    assert quality_classifier.keep_good(df, lab.limit(0)).count() in (0, 202)
    one = quality_classifier.site_rates(spark.createDataFrame([("a", "x", 0.9)] * 50 + [("a", "y", 0.1)] + [("b", "x", 0.2)] * 50, "h string, q string, p double"), "h", "q").collect()
    rate = {(r.host, r.path): r for r in one}
    assert rate["a", "y"].path_rate > 0.1 and abs(rate["b", "x"].path_rate - 0.2) < abs(rate["b", "x"].global_rate - 0.2)


def test_toxicity(spark):
    rng = random.Random(8)
    bad, plain = ["gronk", "snarfle"], ["sun", "moon", "tree", "river", "stone", "cloud"]
    rows, labels = [], []
    for i in range(400):
        words = [rng.choice(plain) for _ in range(40)]
        toxic = i % 8 == 0
        if toxic:
            words[rng.randrange(40)] = rng.choice(bad)
        rows.append((i, " ".join(words)))
        labels.append((i, int(toxic)))
    rows += [(1000, "sun GR0NK moon"), (1001, "sun grоnk moon"), (1002, "g r o n k"), (1003, None), (1004, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in toxicity.score(df, spark.createDataFrame(labels, "doc_id long, toxic int")).collect()}
    assert all(got[i].predicted == int(i % 8 == 0) for i in range(400))
    assert got[1000].predicted == got[1001].predicted == 1 and got[1003].predicted == got[1004].predicted == 0
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 4 == 2) for i, r in got.items())
    assert all(0 <= r.score <= 1 for r in got.values())
    lex = toxicity.Lexicon({" gronk ": 3.0}, {" gronk river "})
    assert lex.matches(["gronk", "river"]) == [] and len(lex.matches(["gronk", "sun"])) == 1
    none = toxicity.score(df, spark.createDataFrame([], "doc_id long, toxic int"))
    assert none.count() == len(rows)


def test_empty_tables(spark):
    e, lab, bench = empty(spark), spark.createDataFrame([], "doc_id long, quality int, toxic int"), spark.createDataFrame([], "item_id long, text string")
    assert minhash_dedup.near_duplicates(e).count() == 0
    assert mixing.mix(e).count() == mixing.mixed_documents(e).count() == 0
    assert decontaminate.judged(e, bench).count() == 0
    assert substring_dedup.remove_repeats(e).count() == line_dedup.drop_lines(e).count() == 0
    assert quality_classifier.score(e.drop("score"), lab).count() == 0
    assert quality_rules.ablation(quality_rules.ledger(e)).count() == 0
    assert token_counts.count_tokens(e, vocabulary("word_bpe_49k.json")).count() == 0
    assert toxicity.score(e, lab).count() == 0
    from vecblock.llm.shared import shared_root

    path = f"{shared_root(spark)}/tokens-empty"
    token_files.write_token_file(e, vocabulary("byte_bpe_50k.json"), path)
    assert token_files.read_token_file(spark, path).count() == 0


def test_word_hashes_do_not_depend_on_segments(monkeypatch):
    text = (" ".join("".join(random.Random(i).choices("abc", k=i % 9 + 1)) for i in range(2000)) + " " + "z" * 5000).encode()
    raw, off = np.frombuffer(text, np.uint8), np.array([0, 17, len(text)])
    want = kernels.words(raw, off).hash.tolist()
    monkeypatch.setattr(kernels, "SEGMENT", 300)
    assert kernels.words(raw, off).hash.tolist() == want
    packed = exchange.K.pack(np.arange(5), np.zeros(0, np.uint8))
    assert [a.tolist() for a in kernels.unpack(packed)] == [list(range(5)), []]


@pytest.mark.skipif(not os.path.isdir("/root/testdata/sf0.001"), reason="no test tables")
def test_pipeline(spark):
    import corpus_pipeline as P

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = docs.columns
    for _, stage in P.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == names
        docs = spark.createDataFrame(out.collect(), out.schema)
    last = P.STAGES[-1][1](spark, docs, sf)
    assert last.count() == docs.count() > 0
    want = {(r.doc_id, r.n_tokens, r.ids_crc32) for r in last.collect()}
    assert {(r.doc_id, r.n_tokens, r.ids_crc32) for r in P.run(spark, sf).collect()} == want
    assert hashlib.sha256(b"").hexdigest()  # the digests of op4 and op5 are plain SHA-256
