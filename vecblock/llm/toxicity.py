"""Toxicity by a weighted lexicon, matched with an Aho-Corasick automaton.

Texts are folded first: compatibility forms, lower case, look-alike letters of
other scripts, digits and signs that stand for letters inside a word.  The
lexicon holds words and word beginnings with log-odds weights learned from
labelled training rows, and exception phrases (a term with a neighbour that
clean rows show) whose match cancels the term's.  The sum of matched weights, its
share of the text's length and the largest weight enter a logistic calibration.

One part of the training rows yields the lexicon, the rest the
calibration; at most ``sample`` training rows are used, and the lexicon keeps the ``terms``
best terms and as many exceptions (8,000 each).  Texts are matched whole, in time linear in
their length.  Labels, language, source and
doc_id are never inputs of a score.

Defined results: a null or empty text has no match and gets the score of no
match; null doc_ids count as held out from learning; rows that share a doc_id
are scored each; without labels of both classes every score is the prior; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
import unicodedata
from bisect import bisect_right
from collections import Counter
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecblock.llm import kernels as K
from vecblock.llm.logistic import Logistic, sigmoid
from vecblock.llm.quality_classifier import labelled

SAMPLE, TERMS, MIN_DOCS, MIN_Z = 16_000, 8_000, 4, 2.5
MIN_ODDS, FEATURES = 1.5, 6
STEMS = range(4, 9)
LEXICON_SHARE = 0.7

# Letters of other scripts drawn like Latin ones.
LOOKALIKES = {
    "а": "a", "в": "b", "с": "c", "ԁ": "d", "е": "e", "һ": "h", "і": "i", "ј": "j", "к": "k", "м": "m", "н": "h", "о": "o", "р": "p", "ѕ": "s", "т": "t", "у": "y", "х": "x",
    "α": "a", "β": "b", "ε": "e", "ι": "i", "κ": "k", "ν": "v", "ο": "o", "ρ": "p", "τ": "t", "υ": "u", "χ": "x", "ı": "i", "ɡ": "g", "ʏ": "y",
}
# Digits and signs written for letters.
SIGNS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "@": "a", "$": "s", "!": "i"}
_LOOK, _SIGN = str.maketrans(LOOKALIKES), str.maketrans(SIGNS)
_FOREIGN = re.compile("[" + "".join(LOOKALIKES) + "]")
_MIXED = re.compile(r"[0134578@$!]+(?=[^\W\d_])|(?<=[^\W\d_])[013457@]+")
_WORD = re.compile(r"[^\W\d_]+")
_INVISIBLE = dict.fromkeys(map(ord, "­​‌‍⁠﻿"))


def fold(text: str) -> list[str]:
    """Words of the folded text."""
    if not text.isascii():
        text = unicodedata.normalize("NFKC", text).translate(_INVISIBLE)
    text = text.lower()
    if not text.isascii() and _FOREIGN.search(text):
        text = text.translate(_LOOK)
    text = _MIXED.sub(lambda m: m[0].translate(_SIGN), text)
    return _WORD.findall(text)


def _terms(words: list[str]) -> set[str]:
    """Features of a training text: ' word ' and ' begin'."""
    out = set(words)
    return {f" {w} " for w in out} | {f" {w[:k]}" for w in out for k in STEMS if len(w) > k}


def training(doc_id: str = "doc_id") -> Column:
    """Rows that labels may be learned from."""
    return F.pmod(F.crc32(F.col(doc_id).cast("string")), F.lit(4)) != 2


def _for_lexicon() -> Column:
    return F.pmod(F.xxhash64(F.lit(3), "doc_id"), F.lit(100)) < int(100 * LEXICON_SHARE)


def _flush(table: Counter, kinds: Counter):
    keys = list(table)
    return pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array([table[k] for k in keys], pa.int64()), pa.array([kinds[k] for k in keys], pa.int64())], names=["term", "pos", "neg"])


def _count(features):
    """Partial document counts by label; a table is sent whenever it has grown large."""

    def run(batches):
        pos, neg = Counter(), Counter()
        for batch in batches:
            for y, text in zip(batch.column("y").to_pylist(), batch.column("text")):
                (pos if y else neg).update(features(fold(text.as_py() or "")))
            if len(pos) + len(neg) > 300_000:
                for t in neg.keys() - pos.keys():
                    pos[t] = 0
                yield _flush(pos, neg)
                pos, neg = Counter(), Counter()
        for t in neg.keys() - pos.keys():
            pos[t] = 0
        yield _flush(pos, neg)

    return run


class Lexicon:
    """Weights of terms and the exception phrases; the automaton is built where it is used."""

    def __init__(self, weights: dict[str, float], exceptions: set[str]):
        self.weights, self.exceptions, self._auto = weights, exceptions, None

    def __getstate__(self):
        return {"weights": self.weights, "exceptions": self.exceptions, "_auto": None}

    def _automaton(self):
        if self._auto is None:
            import ahocorasick

            auto = ahocorasick.Automaton()
            for t, w in self.weights.items():
                auto.add_word(t, (len(t), w, t))
            for t in self.exceptions:
                auto.add_word(t, (len(t), 0.0, t))
            if len(auto):
                auto.make_automaton()
            self._auto = auto
        return self._auto

    def matches(self, words: list[str]) -> list[tuple[int, float, str]]:
        """(start, weight, term) of the best term at each place, exceptions applied."""
        auto = self._automaton()
        if not len(auto):
            return []
        body = " " + " ".join(words) + " "
        best: dict[int, tuple[float, str]] = {}
        spared: list[tuple[int, int]] = []
        for end, (length, weight, term) in auto.iter(body):
            start = end - length + 1
            if not weight:
                spared.append((start, end))
            elif start not in best or weight > best[start][0]:
                best[start] = (weight, term)
        if spared:
            spared.sort()
            begins, reach = [a for a, _ in spared], list(accumulate((b for _, b in spared), max))
            best = {s: v for s, v in best.items() if not (i := bisect_right(begins, s)) or reach[i - 1] < s + len(v[1]) - 1}
        return [(s, *v) for s, v in sorted(best.items())]

    def features(self, words: list[str], found: list[tuple[int, float, str]] | None = None) -> list[float]:
        found = self.matches(words) if found is None else found
        if not found:
            return [0.0] * FEATURES
        total = sum(w for _, w, _ in found)
        share = 1000 / (len(words) + 20)
        kinds = len({t for _, _, t in found})
        return [np.log1p(total), np.log1p(share * total), max(w for _, w, _ in found), np.log1p(kinds), np.log1p(len(found)), np.log1p(share * len(found))]


def learn_lexicon(rows: DataFrame, terms: int = TERMS) -> Lexicon:
    """From (y, text): words and beginnings that mark the positive class, and phrases that excuse them."""
    n = {r.y: r.n for r in rows.groupBy("y").agg(F.count("*").alias("n")).collect()}  # two classes
    n1, n0 = n.get(1, 0), n.get(0, 0)
    if not n1 or not n0:
        return Lexicon({}, set())
    odds = F.log((F.col("pos") + 0.5) / (n1 + 1.0)) - F.log((F.col("neg") + 0.5) / (n0 + 1.0))
    z = odds / F.sqrt(1 / (F.col("pos") + 0.5) + 1 / (F.col("neg") + 0.5))
    counts = rows.select("y", "text").mapInArrow(_count(_terms), "term string, pos long, neg long").groupBy("term").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    top = counts.where(F.col("pos") >= MIN_DOCS).withColumns({"w": odds, "z": z}).where((F.col("z") >= MIN_Z) & (F.col("w") >= MIN_ODDS)).orderBy(F.desc("z"), "term").limit(terms)
    got = top.select("term", "w", "pos").collect()  # at most ``terms``
    # a beginning that one word accounts for says no more than that word
    whole = {r.term: r.pos for r in got if r.term.endswith(" ")}
    covered = Counter()
    for word, pos in whole.items():
        for k in range(2, len(word)):
            covered[word[:k]] = max(covered[word[:k]], pos)
    weights = {r.term: float(r.w) for r in got if r.term in whole or covered[r.term] < 0.9 * r.pos}
    plain = Lexicon(weights, set())

    def phrases(folded: list[str]) -> set[str]:
        found = plain.matches(folded)
        if not found:
            return set()
        at, place = {}, 0
        for i, w in enumerate(folded):
            at[place] = i
            place += len(w) + 1
        out = set()
        for start, _, _ in found:
            i = at[start]
            if i:
                out.add(f" {folded[i - 1]} {folded[i]} ")
            if i + 1 < len(folded):
                out.add(f" {folded[i]} {folded[i + 1]} ")
        return out

    excuse = rows.select("y", "text").mapInArrow(_count(phrases), "term string, pos long, neg long").groupBy("term").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    excuse = excuse.where((F.col("neg") >= 3) & (F.col("pos") == 0)).orderBy(F.desc("neg"), "term").limit(terms)
    return Lexicon(weights, {r.term for r in excuse.select("term").collect()})  # at most ``terms``


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", sample: int = SAMPLE) -> tuple[Lexicon, Logistic]:
    lexicon = learn_lexicon(labelled(docs, labels, label, int(sample * LEXICON_SHARE), training() & _for_lexicon()))

    def run(batches):
        for batch in batches:
            x = [lexicon.features(fold(t.as_py() or "")) for t in batch.column("text")]
            yield pa.RecordBatch.from_arrays([batch.column("y").cast(pa.int32()), pa.array(x, pa.list_(pa.float64()))], names=["y", "x"])

    got = labelled(docs, labels, label, sample - int(sample * LEXICON_SHARE), training() & ~_for_lexicon()).select("y", "text").mapInArrow(run, "y int, x array<double>").toArrow()  # ``sample`` rows of FEATURES numbers
    x = np.array(got.column("x").to_pylist(), np.float64).reshape(-1, FEATURES)
    y = got.column("y").to_numpy().astype(np.float64)
    order = np.lexsort((*x.T, y))
    return lexicon, Logistic(x[order], y[order])


_OUT = pa.schema([("doc_id", pa.int64()), ("n_matches", pa.int64()), ("weight", pa.float64()), ("score", pa.float64())])


def score(docs: DataFrame, labels: DataFrame, label: str = "toxic", threshold: float = 0.3, sample: int = SAMPLE, model: tuple[Lexicon, Logistic] | None = None) -> DataFrame:
    """(doc_id, held_out, score, predicted, n_matches, weight) for every row."""
    lexicon, calibration = model or fit(docs, labels, label, sample)

    def run(batches):
        for batch in batches:
            raw, off = K.string_buffers(batch.column("text"))
            ids = batch.column("doc_id").cast(pa.int64())
            for i, j in K.slices(off, K.SEGMENT):
                view = memoryview(np.ascontiguousarray(raw[off[i] : off[j]]))
                cut = (off[i : j + 1] - off[i]).tolist()
                folded = [fold(str(view[a:b], "utf-8")) for a, b in zip(cut, cut[1:])]
                found = [lexicon.matches(w) for w in folded]
                x = np.array([lexicon.features(w, f) for w, f in zip(folded, found)], np.float64).reshape(-1, FEATURES)
                p = sigmoid(calibration.logit(x))
                yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), pa.array([len(f) for f in found], pa.int64()), pa.array([sum(w for _, w, _ in f) for f in found], pa.float64()), pa.array(p, pa.float64())], schema=_OUT)

    out = docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_matches long, weight double, score double")
    held = F.coalesce(~training(), F.lit(True))
    return out.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "n_matches", "weight")
