"""Line dedup with sharded minimal perfect hashes.

Keys are lines stripped of ASCII blanks at both ends with A-Z lower-cased; those
of at least ``min_chars`` code points found in at least ``min_docs`` documents
lose all their lines except in the largest doc_id that holds them.

Documents are written once in chunks, each with the distinct hashes of its keys and
a map from lines to them.  Shards of the hash space count the documents of every key and
store an index of the repeated ones: a minimal perfect hash (levels of bit
arrays with rank counts) into compact arrays, a 64-bit fingerprint, a document count (a lower
bound from ``min_docs`` on) and the keeper's doc_id.  Chunks probe the shards' arrays with their distinct hashes and get
the keepers back.  A key that every document holds costs one hash per chunk;
no line text is joined or moved.

Defined results: a null or empty text is one empty line; a document that repeats
a key counts once, and the keeper keeps each of its copies; rows that share a
doc_id count as one document; a null doc_id is larger than all others; an empty
table gives no rows; other columns are ignored.  Keys are counted by 128 bits of
hash and probed by their slot and the 64 bits of the fingerprint.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecblock.llm import exchange as X
from vecblock.llm import kernels as K
from vecblock.llm.shared import Stored, bucket_count

MIN_CHARS, MIN_DOCS = 20, 3
_U = np.uint64


class PerfectHash:
    """Minimal perfect hash over distinct 64-bit keys; a foreign key gets some slot or -1."""

    def __init__(self, keys: np.ndarray, gamma: float = 2.0):
        self.levels: list[tuple[np.ndarray, np.ndarray, int]] = []
        base, left = 0, np.asarray(keys, np.uint64)
        while len(left):
            size = max(64, int(gamma * len(left)) | 1)
            slot = self._slot(left, len(self.levels), size)
            count = np.bincount(slot, minlength=size)
            taken = count == 1
            bits = np.packbits(taken, bitorder="little")
            rank = np.concatenate([[0], np.cumsum(np.bitwise_count(bits))]).astype(np.int64) + base
            self.levels.append((bits, rank, size))
            base += int(taken.sum())
            left = left[~taken[slot]]
        self.n = base

    @staticmethod
    def _slot(keys: np.ndarray, level: int, size: int) -> np.ndarray:
        h = K.mix(keys ^ _U((0xA0761D6478BD642F * (level + 1)) & (2**64 - 1)))
        return (h % _U(size)).astype(np.int64)

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        out = np.full(len(keys), -1, np.int64)
        open_ = np.arange(len(keys))
        for level, (bits, rank, size) in enumerate(self.levels):
            if not len(open_):
                break
            slot = self._slot(keys[open_], level, size)
            byte, bit = slot >> 3, (slot & 7).astype(np.uint8)
            here = (bits[byte] >> bit) & 1 == 1
            below = np.bitwise_count(bits[byte] & ((1 << bit.astype(np.uint16)) - 1).astype(np.uint8))
            out[open_[here]] = (rank[byte] + below)[here]
            open_ = open_[~here]
        return out

    def arrays(self) -> list[np.ndarray]:
        """What ``restored`` needs: level sizes and bits."""
        return [np.array([size for _, _, size in self.levels], np.int64), np.concatenate([b for b, _, _ in self.levels] or [np.zeros(0, np.uint8)])]

    @classmethod
    def restored(cls, sizes: np.ndarray, bits: np.ndarray) -> PerfectHash:
        out, at = cls(np.zeros(0, np.uint64)), 0
        for size in sizes.tolist():
            own = bits[at : at + (size + 7) // 8]
            rank = np.concatenate([[0], np.cumsum(np.bitwise_count(own))]).astype(np.int64) + out.n
            out.levels.append((own, rank, size))
            out.n, at = int(rank[-1]), at + len(own)
        return out

    @property
    def bits_per_key(self) -> float:
        return sum(8 * len(b) for b, _, _ in self.levels) / max(1, self.n)


class ShardIndex:
    """The repeated keys of a shard: a perfect hash into fingerprints, counts and keepers."""

    def __init__(self, ph: PerfectHash, fingerprint, count, keeper, null, extra):
        self.ph, self.fingerprint, self.count, self.keeper, self.null = ph, fingerprint, count, keeper, null
        self.extra = extra  # (hash, fingerprint, count, keeper, null) of keys that share their hash with an indexed one

    @classmethod
    def build(cls, h, g, docs, keeper, null) -> ShardIndex:
        """From distinct keys (h, g) in order, their document counts and keepers."""
        one = np.append(True, h[1:] != h[:-1])[: len(h)]
        ph = PerfectHash(h[one])
        at = ph(h[one])
        out = [np.empty(len(at), t) for t in (np.uint64, np.uint8, np.int64, bool)]
        for to, of in zip(out, (g, np.minimum(docs, 255), keeper, null)):
            to[at] = of[one]
        return cls(ph, *out, [x[~one] for x in (h, g, np.minimum(docs, 255).astype(np.uint8), keeper, null)])

    def pack(self) -> bytes:
        return K.pack(*self.ph.arrays(), self.fingerprint, self.count, self.keeper, self.null.astype(np.uint8), *self.extra[:4], self.extra[4].astype(np.uint8))

    @classmethod
    def unpack(cls, data) -> ShardIndex:
        sizes, bits, fingerprint, count, keeper, null, *extra = K.unpack(data)
        return cls(PerfectHash.restored(sizes, bits), fingerprint, count, keeper, null > 0, [*extra[:4], extra[4] > 0])

    def probe(self, h: np.ndarray, g: np.ndarray, min_docs: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(places of the keys that are repeated, their keepers, which of these are null)."""
        found, keeper, null = np.zeros(len(h), bool), np.zeros(len(h), np.int64), np.zeros(len(h), bool)
        slot = self.ph(h) if self.ph.n else np.full(len(h), -1)
        at = np.flatnonzero(slot >= 0)
        at = at[(self.fingerprint[slot[at]] == g[at]) & (self.count[slot[at]] >= min(min_docs, 255))]
        found[at], keeper[at], null[at] = True, self.keeper[slot[at]], self.null[slot[at]]
        for eh, eg, _, ek, en in zip(*self.extra):
            hit = (h == eh) & (g == eg)
            found[hit], keeper[hit], null[hit] = True, ek, en
        at = np.flatnonzero(found)
        return at, keeper[at], null[at]


def line_spans(raw: np.ndarray, off: np.ndarray, min_chars: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, line number, begin, end) of the stripped lines of at least ``min_chars`` code points."""
    feed = np.flatnonzero(raw == 10)
    n = len(off) - 1
    begin = np.concatenate([off[:-1], feed + 1])
    row = np.concatenate([np.arange(n), np.searchsorted(off[1:], feed, "right")])
    order = np.lexsort((begin, row))
    begin, row = begin[order], row[order]
    ends = np.append(begin[1:], 0) - 1
    last = np.append(row[1:] != row[:-1], True)[: len(row)]
    ends[last] = off[row[last] + 1]
    first = np.searchsorted(row, np.arange(n))
    line = np.arange(len(row)) - first[row]
    ink = np.flatnonzero(~K._SPACE[raw])
    a, b = np.searchsorted(ink, begin), np.searchsorted(ink, ends)
    ok = b > a
    row, line, a, b = row[ok], line[ok], a[ok], b[ok]
    if not len(row):
        z = np.zeros(0, np.int64)
        return z, z, z, z
    s, e = ink[a], ink[b - 1] + 1
    heads = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])
    ok = heads[e] - heads[s] >= min_chars
    return row[ok], line[ok], s[ok], e[ok]


_STORED = pa.schema([*X._CHUNK, ("keys", pa.binary()), ("lines", pa.binary())])


def _store(min_chars: int):
    """Chunks with their distinct key hashes (ascending) and, per line, its row, number and key."""

    def run(batches):
        for columns, c in X.cut_chunks(batches):
            row, line, s, e = line_spans(c.raw, c.off, min_chars)
            h, g = K.span_hashes(c.raw, s, e, True), K.span_hashes(c.raw, s, e, True, salt=1)
            order = np.lexsort((g, h))
            hs, gs = h[order], g[order]
            new = np.append(True, (hs[1:] != hs[:-1]) | (gs[1:] != gs[:-1]))[: len(h)]
            key = np.empty(len(h), np.uint32)
            key[order] = np.cumsum(new) - 1
            lines = K.pack(K.deltas(row).astype(np.uint32), line.astype(np.uint32), key)
            columns += [hs[new].tobytes() + gs[new].tobytes(), lines]
            yield pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(columns, _STORED)], schema=_STORED)

    return run


def _keys(data) -> tuple[np.ndarray, np.ndarray]:
    flat = np.frombuffer(data, np.uint64)
    return flat[: len(flat) // 2], flat[len(flat) // 2 :]


def _by_shard(h: np.ndarray, bits: int) -> Iterator[tuple[int, int, int]]:
    """(shard, begin, end) of ascending hashes."""
    to = (h >> _U(64 - bits)).astype(np.int64)
    first = np.flatnonzero(np.diff(to, prepend=-1))
    yield from zip(to[first].tolist(), first.tolist(), [*first[1:].tolist(), len(h)])


_COUNTS = pa.schema([("shard", pa.int32()), ("block", pa.binary())])


def _documents(min_docs: int, bits: int):
    """Per shard the documents of a chunk's keys: each of them, or from ``min_docs`` on the largest, marked as full."""

    def run(batches):
        for batch in batches:
            for k in range(len(batch)):
                c = X.Chunk.open(batch, k, with_text=False)
                h, g = _keys(batch.column("keys")[k].as_buffer())
                row, _, key = K.unpack(batch.column("lines")[k].as_buffer())
                row, key = np.cumsum(row.astype(np.int64)), key.astype(np.int64)
                rank = X.ranks(c.ids, c.null)
                pair = np.unique(key * (len(c.ids) + 1) + rank[row]) if len(key) else key
                key, rank_of = pair // (len(c.ids) + 1), pair % (len(c.ids) + 1)
                size = np.bincount(key, minlength=len(h))
                top = np.append(key[1:] != key[:-1], True)[: len(key)]
                full = size[key] >= min_docs
                keep = top | ~full
                key, full = key[keep], full[keep]
                by_rank = np.argsort(rank, kind="stable")
                doc = by_rank[np.searchsorted(rank[by_rank], rank_of[keep])]
                ids, null = c.ids[doc], c.null[doc]
                out_s, out_b = [], []
                for shard, a, b in _by_shard(h[key], bits):
                    out_s.append(shard)
                    out_b.append(K.pack(h[key[a:b]], g[key[a:b]], ids[a:b], null[a:b].astype(np.uint8), full[a:b].astype(np.uint8)))
                if out_s:
                    yield pa.RecordBatch.from_arrays([pa.array(out_s, pa.int32()), pa.array(out_b, pa.binary())], schema=_COUNTS)

    return run


_INDEX = pa.schema([("shard", pa.int32()), ("n_keys", pa.int64()), ("index", pa.binary())])


def _build(min_docs: int):
    """A shard's index from the documents of its keys."""

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [K.unpack(block.as_buffer()) for batch in batches for block in batch.column("block")]
        h, g, ids, null, full = (np.concatenate(x) for x in zip(*parts))
        null = null > 0
        rank = X.ranks(ids, null)
        order = np.lexsort((rank, g, h))
        h, g, ids, null, full, rank = h[order], g[order], ids[order], null[order], full[order], rank[order]
        new = np.append(True, (h[1:] != h[:-1]) | (g[1:] != g[:-1]))
        fresh = new | np.append(True, rank[1:] != rank[:-1])
        first = np.flatnonzero(new)
        last = np.append(first[1:], len(h)) - 1
        docs = np.add.reduceat(fresh.astype(np.int64), first)
        docs = np.where(np.maximum.reduceat(full, first) > 0, np.maximum(docs, min_docs), docs)
        pick = docs >= min_docs
        if pick.any():
            index = ShardIndex.build(h[first][pick], g[first][pick], docs[pick], ids[last][pick], null[last][pick])
            yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([int(pick.sum())], pa.int64()), pa.array([index.pack()], pa.binary())], schema=_INDEX)

    return run


_PROBE = pa.schema([("at_shard", pa.int32()), ("chunk", pa.binary()), ("first", pa.int64()), ("hashes", pa.binary())])
_ANSWER = pa.schema([("chunk", pa.binary()), ("at", pa.binary())])


def _ask(bits: int):
    """A chunk's distinct hashes, cut by shard."""

    def run(batches):
        for batch in batches:
            for k in range(len(batch)):
                h, g = _keys(batch.column("keys")[k].as_buffer())
                name = batch.column("chunk")[k].as_py()
                rows = [(shard, name, a, h[a:b].tobytes() + g[a:b].tobytes()) for shard, a, b in _by_shard(h, bits)]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*rows), _PROBE)], schema=_PROBE)

    return run


def _answer(min_docs: int):
    """Probe one shard's arrays with the hashes of all chunks."""

    def run(asked: pa.Table, stored: pa.Table) -> pa.Table:
        names, answers = [], []
        if len(stored):
            index = ShardIndex.unpack(stored.column("index")[0].as_buffer())
            for name, first, hashes in zip(asked.column("chunk"), asked.column("first").to_pylist(), asked.column("hashes")):
                at, keeper, null = index.probe(*_keys(hashes.as_buffer()), min_docs)
                if len(at):
                    names.append(name.as_py())
                    answers.append(K.pack((at + first).astype(np.uint32), keeper, null.astype(np.uint8)))
        return pa.Table.from_arrays([pa.array(names, pa.binary()), pa.array(answers, pa.binary())], schema=_ANSWER)

    return run


def _dropped(batch: pa.RecordBatch, k: int, c: X.Chunk) -> tuple[np.ndarray, np.ndarray]:
    """(row, line number) of the lines that go: those of a repeated key whose document comes before the keeper."""
    z = np.zeros(0, np.int64)
    answers = batch.column("at")[k].as_py()
    if not answers:
        return z, z
    at, keeper, null = (np.concatenate(x) for x in zip(*map(K.unpack, answers)))
    row, line, key = K.unpack(batch.column("lines")[k].as_buffer())
    row = np.cumsum(row.astype(np.int64))
    order = np.argsort(at)
    at, keeper, null = at[order], keeper[order], null[order] > 0
    spot = np.minimum(np.searchsorted(at, key), len(at) - 1)
    before = ~c.null[row] & (null[spot] | (c.ids[row] < keeper[spot]))
    hit = (at[spot] == key) & before
    return row[hit], line[hit].astype(np.int64)


_OUT = pa.schema([("doc_id", pa.int64()), ("n_lines", pa.int64()), ("n_dropped", pa.int64()), ("kept", pa.string())])


def _cut(batches):
    for batch in batches:
        for k in range(len(batch)):
            c = X.Chunk.open(batch, k)
            rows, drops = _dropped(batch, k, c)
            edge = np.searchsorted(rows, np.arange(len(c.ids) + 1)).tolist()
            counts, gone, kept = [], [], []
            for i, text in enumerate(c.texts()):
                drop = set(drops[edge[i] : edge[i + 1]].tolist())
                counts.append(text.count(b"\n") + 1)
                if drop:
                    text = b"\n".join([x for j, x in enumerate(text.split(b"\n")) if j not in drop])
                gone.append(len(drop))
                kept.append(text.decode())
            yield pa.RecordBatch.from_arrays([c.doc_ids(), pa.array(counts, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.string())], schema=_OUT)


def line_index(chunks: DataFrame, min_docs: int, bits: int) -> Stored:
    """(shard, n_keys, index): the stored index of the repeated keys, a row per shard that has some."""
    counted = chunks.select("n_raw", "head", "keys", "lines").mapInArrow(_documents(min_docs, bits), "shard int, block binary")
    return Stored(chunks.sparkSession, counted.groupBy("shard").applyInArrow(_build(min_docs), "shard int, n_keys long, index binary"), "line-index")


def drop_lines(docs: DataFrame, min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS, shards: int | None = None) -> DataFrame:
    """(doc_id, n_lines, n_dropped, kept) for every row."""
    docs = docs.select("doc_id", "text")
    bits = max(1, ((shards or bucket_count(docs, 16 << 20, least=16, most=1 << 17)) - 1).bit_length())
    chunks = Stored(docs.sparkSession, docs.mapInArrow(_store(min_chars), X.CHUNK + ", keys binary, lines binary"), "chunks", compression="none").df
    index = line_index(chunks, min_docs, bits).df
    asked = chunks.select("chunk", "keys").mapInArrow(_ask(bits), "at_shard int, chunk binary, first long, hashes binary")
    answers = asked.groupBy("at_shard").cogroup(index.groupBy("shard")).applyInArrow(_answer(min_docs), "chunk binary, at binary")
    answers = answers.groupBy("chunk").agg(F.collect_list("at").alias("at"))
    return chunks.join(answers, "chunk", "left").select("n_raw", "head", "body", "lines", "at").mapInArrow(_cut, "doc_id long, n_lines long, n_dropped long, kept string")
