"""Token counts of texts by rank-synchronous merging of batched pre-tokens.

The vocabulary is a public byte-level BPE file of the ``tokenizers`` format with
word-end suffix (NFC, white space runs, lower case, then letters / one digit /
other).  Distinct pre-tokens of a batch lie in one flat array of symbols with
sequence numbers; each round looks up the rank of every adjacent pair, applies
each sequence's lowest-ranked pair everywhere at once, and closes the gaps.  The
symbols that survive are the tokens; only their number is kept.

Nothing crosses white space, so counts are remembered for blank-free pieces.
The memory is a cache of fixed size and never changes a result.

Defined results: a null or empty text has 0 bytes and 0 tokens; the file's own
special strings inside a text count one token each and split the text, as the
library does by default; null ids and repeated rows pass through; other columns
are ignored.
"""

from __future__ import annotations

import json
import unicodedata
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from vecblock.llm import kernels as K

CACHE = 200_000
NO_RANK = np.iinfo(np.int32).max


def byte_symbols() -> list[str]:
    """The printable stand-in character of each byte in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    other = [b for b in range(256) if b not in set(plain)]
    names = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(other)}
    return [names[b] for b in range(256)]


class MergeTable:
    """Vocabulary and merges of one file as sorted numpy arrays."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        vocab, suffix = model["vocab"], model.get("end_of_word_suffix") or ""
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        left = np.array([vocab[a] for a, _ in merges], np.int64)
        right = np.array([vocab[b] for _, b in merges], np.int64)
        made = np.array([vocab[a + b] for a, b in merges], np.int64)
        self.width = max(vocab.values()) + 1
        key = left * self.width + right
        order = np.argsort(key, kind="stable")
        keep = np.append(True, np.diff(key[order]) > 0)
        self.key, self.rank, self.made = key[order][keep], order[keep].astype(np.int32), made[order][keep]
        names = byte_symbols()
        self.inner = np.array([vocab[c] for c in names], np.int64)
        self.last = np.array([vocab[c + suffix] for c in names], np.int64)
        specials = [t["content"] for t in spec["added_tokens"]]
        self.special = regex.compile("|".join(regex.escape(s) for s in sorted(specials, key=len, reverse=True))) if specials else None
        steps = spec["pre_tokenizer"]["pretokenizers"]
        self.pieces = regex.compile(next(s["pattern"]["Regex"] for s in steps if s["type"] == "Split"))

    def survivors(self, tokens: list[bytes]) -> np.ndarray:
        """How many symbols are left of each pre-token after all merges."""
        n = len(tokens)
        size = np.fromiter(map(len, tokens), np.int64, n)
        raw = np.frombuffer(b"".join(tokens), np.uint8)
        seq = np.repeat(np.arange(n), size)
        sym = self.inner[raw]
        ends = np.cumsum(size) - 1
        sym[ends[size > 0]] = self.last[raw[ends[size > 0]]]
        left = size.copy()
        while len(sym) > 1:
            pair = sym[:-1] * self.width + sym[1:]
            at = np.minimum(np.searchsorted(self.key, pair), len(self.key) - 1)
            ok = (self.key[at] == pair) & (seq[:-1] == seq[1:])
            if not ok.any():
                break
            rank = np.where(ok, self.rank[at], NO_RANK)
            best = np.full(n, NO_RANK, np.int32)
            first = np.flatnonzero(np.diff(seq[:-1], prepend=-1))
            best[seq[first]] = np.minimum.reduceat(rank, first)
            hit = ok & (rank == best[seq[:-1]])
            # in a run of hits (equal symbols) every second one counts, from the left
            run = np.flatnonzero(hit & ~np.append(False, hit[:-1]))
            where = np.flatnonzero(hit)
            start = run[np.searchsorted(run, where, "right") - 1]
            where = where[(where - start) % 2 == 0]
            sym[where] = self.made[at[where]]
            np.subtract.at(left, seq[where], 1)
            # sequences without a hit are finished: drop them with the gaps
            live = np.zeros(n, bool)
            live[seq[where]] = True
            keep = live[seq]
            keep[where + 1] = False
            sym, seq = sym[keep], seq[keep]
        return left


@lru_cache(maxsize=4)
def table(path: str) -> MergeTable:
    return MergeTable(path)


class Counter:
    def __init__(self, path: str, cache: int = CACHE):
        self.merges, self.limit, self.known = table(path), cache, {}

    def _chunks(self, text: str) -> list[str]:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
        text = text.replace("Σ", "σ").lower()  # lower case by single characters: no final sigma
        if any(c in text for c in "\x1c\x1d\x1e\x1f"):  # blanks for str.split alone
            return regex.findall(r"[^\p{White_Space}]+", text)
        return text.split()

    def _learn(self, chunks: set[str]) -> None:
        names = list(chunks)
        split = [self.merges.pieces.findall(c) for c in names]
        distinct: dict[bytes, int] = {}
        index = [distinct.setdefault(p.encode(), len(distinct)) for ps in split for p in ps]
        counts = self.merges.survivors(list(distinct))[np.array(index, np.int64)] if index else np.zeros(0, np.int64)
        edge = np.cumsum([0, *map(len, split)])
        total = np.concatenate([[0], np.cumsum(counts)])
        self.known.update(zip(names, (total[edge[1:]] - total[edge[:-1]]).tolist()))

    def count(self, texts: list[str]) -> list[int]:
        parts, special = [], []
        for t in texts:
            hits = len(self.merges.special.findall(t)) if self.merges.special and "<|" in t else 0
            special.append(hits)
            parts.append([c for s in self.merges.special.split(t) for c in self._chunks(s)] if hits else self._chunks(t))
        fresh = set().union(*parts).difference(self.known)
        if fresh:
            if len(self.known) + len(fresh) > self.limit:
                self.known.clear()
                fresh = set().union(*parts)
            self._learn(fresh)
        get = self.known.__getitem__
        return [sum(map(get, p)) + s for p, s in zip(parts, special)]


@lru_cache(maxsize=2)
def shared_counter(path: str) -> Counter:
    """One counter for all tasks of a worker."""
    return Counter(path)


_OUT = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_tokens", pa.int64()), ("over_limit", pa.bool_())])


def count_tokens(docs: DataFrame, path: str, limit: int = 2048) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) for every row; ``path`` is the vocabulary file on every machine."""

    def run(batches):
        counter = shared_counter(path)
        for batch in batches:
            raw, off = K.string_buffers(batch.column("text"))
            ids = batch.column("doc_id").cast(pa.int64())
            for i, j in K.slices(off, K.SEGMENT):
                view = memoryview(np.ascontiguousarray(raw[off[i] : off[j]]))
                cut = (off[i : j + 1] - off[i]).tolist()
                n = np.array(counter.count([str(view[a:b], "utf-8") for a, b in zip(cut, cut[1:])]), np.int64)
                yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), pa.array(np.diff(off[i : j + 1])), pa.array(n), pa.array(n > limit)], schema=_OUT)

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
