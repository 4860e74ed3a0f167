"""Token ids in compact files: canonical length-limited Huffman codes.

Code lengths come from the counts of ids over the whole corpus (package-merge,
at most ``LIMIT`` bits), codes are canonical, so the code book is the lengths
alone.  A file holds independent blocks of consecutive documents in ascending
doc_id order; a block has its documents' ids and token counts, its bits, and the
bit offset of every ``STRIDE``-th token.  The decoder looks ``LIMIT`` bits up in one
table and advances all stretches of a block at once.

Layout under ``path``: ``blocks`` (part, first, n_tokens, head, marks, bits) and
``codebook`` (id, length), both Parquet so that any store serves.  Parts are ranges
of doc_id; part p's ids all precede part p+1's.  A doc_id that more rows share than a part
should hold, and the rows without one, are dealt over several parts by their texts.

Defined results: a null text counts as empty; every document ends with
``end_id``; rows that share a doc_id follow each other in a fixed order; rows
with a null doc_id come last; an empty table gives an empty file.
"""

from __future__ import annotations

import re
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.llm import exchange as X
from vecblock.llm import kernels as K
from vecblock.llm.shared import Stored, bucket_count

LIMIT, STRIDE, BLOCK = 16, 128, 1 << 19
#: Slots of a worker's piece table (14 bytes each); it is emptied when half full, and larger only for a slice that needs it.
SLOTS = 1 << 21
#: Bytes of the longest span that enters the piece table.
LONG = 1 << 10
#: White space beyond ASCII, and the mark of special strings: such texts go to the library whole.
_ODD = re.compile(rb"\xc2[\x85\xa0]|\xe1\x9a\x80|\xe2\x80[\x80-\x8a\xa8\xa9\xaf]|\xe2\x81\x9f|\xe3\x80\x80|<\|")


def piece_spans(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte spans that pre-tokenisation always separates: a word with one blank before it, and the rest of the white space.

    A run of white space before a word gives its last blank to the word; without
    a blank in last place that character stands alone.  What comes before it, and
    a run at the end of a text, is one span.
    """
    w = K.words(raw, off)
    s, e = w.start, w.end
    row = np.searchsorted(off, s, "right") - 1
    first = np.append(True, row[1:] != row[:-1])[: len(s)]
    before = np.where(first, off[row], np.append(0, e[:-1])[: len(s)])
    gap = s - before
    blank = (gap > 0) & (raw[np.maximum(s - 1, 0)] == 0x20)
    long = np.flatnonzero(gap > 1)
    alone = np.flatnonzero((gap > 0) & ~blank)
    last = off[:-1].copy()  # end of each text's last word
    last[row] = e  # ascending: the last one stays
    tail = np.flatnonzero(off[1:] > last)
    more_s = np.concatenate([before[long], s[alone] - 1, last[tail]])
    more_e = np.concatenate([s[long] - 1, s[alone], off[1:][tail]])
    order = np.argsort(more_s, kind="stable")
    more_s, more_e = more_s[order], more_e[order]
    at = np.searchsorted(s, more_s)
    return np.insert(s - blank, at, more_s), np.insert(e, at, more_e)


# Classes of bytes: white space, letter, digit, other ASCII, and what only the library's own pattern settles.
_CLASS = np.full(256, 4, np.uint8)
_CLASS[:128] = 3
_CLASS[[0x20, *range(0x09, 0x0E)]] = 0
_CLASS[[*range(65, 91), *range(97, 123)]] = 1
_CLASS[48:58] = 2
_CLASS[39] = 4  # an apostrophe may begin a contraction


def split_classes(raw: np.ndarray, s: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cut spans where letters, digits and other signs meet; (start, end, unsettled).

    Letters are ASCII and the accented ones of two bytes led by 0xC3.  A span with any other
    non-ASCII byte or an apostrophe stays whole and is unsettled.
    """
    kind = _CLASS[raw]
    lead = np.flatnonzero(raw[:-1] == 0xC3)
    sign = raw[lead + 1]
    lead = lead[(sign != 0x97) & (sign != 0xB7)]
    kind[lead], kind[lead + 1] = 1, 1
    odd = np.concatenate([[0], np.cumsum(kind == 4)])
    unsettled = odd[e] > odd[s]
    cut = np.flatnonzero((kind[1:] != kind[:-1]) & (kind[1:] > 0) & (kind[:-1] > 0)) + 1
    if len(cut) and len(s):
        at = np.searchsorted(s, cut, "right") - 1
        ok = (at >= 0) & (cut < e[at]) & (cut > s[at]) & ~unsettled[at]
        cut, at = cut[ok], at[ok]
        s, e, unsettled = np.insert(s, at + 1, cut), np.insert(e, at, cut), np.insert(unsettled, at + 1, False)
    return s, e, unsettled


class PieceTable:
    """Hash table from piece hashes to runs of ids, probed for whole arrays.

    Pieces are told apart by a hash of 64 bits, which is exact for eight bytes and less of one length, and a check of 32 bits.
    """

    def __init__(self, kind, slots: int = SLOTS):
        self.kind, self.least = kind, slots
        self.clear()

    def clear(self, n: int = 0) -> None:
        """Empty, with room for ``n`` pieces at least."""
        self.slots = max(self.least, 1 << (2 * n).bit_length())
        self.key = np.zeros(self.slots, np.uint64)
        self.check = np.zeros(self.slots, np.uint32)
        self.at = np.zeros(self.slots, np.int32)
        self.size = np.zeros(self.slots, np.uint16)
        self.ids = np.zeros(1 << 20, self.kind)
        self.used = self.n = 0

    def find(self, h: np.ndarray, check: np.ndarray) -> np.ndarray:
        """Slot of each piece, or -1."""
        out = np.full(len(h), -1, np.int64)
        open_ = np.arange(len(h))
        slot = (h & np.uint64(self.slots - 1)).astype(np.int64)
        while len(open_):
            key = self.key[slot]
            hit = (key == h[open_]) & (self.check[slot] == check[open_])
            out[open_[hit]] = slot[hit]
            go = ~hit & (key != 0)
            open_, slot = open_[go], (slot[go] + 1) & (self.slots - 1)
        return out

    def add(self, h: np.ndarray, check: np.ndarray, runs: list[bytes]) -> None:
        """New distinct pieces with their ids."""
        w = np.dtype(self.kind).itemsize
        size = np.fromiter(map(len, runs), np.int64, len(runs)) // w
        if size.max(initial=0) > 0xFFFF:
            raise ValueError("a piece has too many ids")
        flat = np.frombuffer(b"".join(runs), self.kind)
        if self.used + len(flat) > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros(max(len(self.ids), len(flat)), self.kind)])
        self.ids[self.used : self.used + len(flat)] = flat
        at = self.used + np.cumsum(size) - size
        self.used += len(flat)
        self.n += len(h)
        slot = (h & np.uint64(self.slots - 1)).astype(np.int64)
        todo = np.arange(len(h))
        while len(todo):
            free = self.key[slot[todo]] == 0
            _, one = np.unique(slot[todo[free]], return_index=True)
            put = todo[free][one]
            self.key[slot[put]], self.check[slot[put]], self.at[slot[put]], self.size[slot[put]] = h[put], check[put], at[put], size[put]
            done = np.zeros(len(h), bool)
            done[put] = True
            todo = todo[~done[todo]]
            slot[todo] = (slot[todo] + 1) & (self.slots - 1)

    def __call__(self, slot: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        size = self.size[slot].astype(np.int64)
        return self.ids[K.ragged(self.at[slot].astype(np.int64), size)], size


def _distinct(h: np.ndarray, check: np.ndarray, some: np.ndarray) -> np.ndarray:
    """One of ``some`` for each distinct pair."""
    order = some[np.lexsort((check[some], h[some]))]
    return order[np.append(True, (h[order][1:] != h[order][:-1]) | (check[order][1:] != check[order][:-1]))]


class Encoder:
    """Ids of whole texts by the library, which sees a distinct blank-separated piece once.

    The table of pieces never changes a result.
    """

    def __init__(self, path: str):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
        import public_tokenizers
        import regex
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.type = np.uint16 if self.tok.get_vocab_size() <= 1 << 16 else np.uint32
        self.special = [t.content for t in self.tok.get_added_tokens_decoder().values()]
        self.split = regex.compile(public_tokenizers.PATTERN).findall
        self.table = PieceTable(self.type)

    def _ids(self, text: str) -> bytes:
        return np.array(self.tok.encode(text, add_special_tokens=False).ids, self.type).tobytes()

    def _runs(self, pieces: list[str]) -> list[bytes]:
        """Ids of distinct pieces.  Those that start with a blank are sent as one text: the library parts them again there."""
        out: dict[str, bytes] = {}
        lead = [p for p in pieces if p[0] == " " and len(p) > 1 and not p[1].isspace()]
        for at in range(0, len(lead), 2048):
            some = lead[at : at + 2048]
            got = self.tok.encode("".join(some), add_special_tokens=False)
            word, ids = np.array(got.word_ids, np.int64), np.array(got.ids, self.type)
            edge = np.searchsorted(word, np.arange(len(some) + 1)).tolist()
            if word[-1] != len(some) - 1:
                raise RuntimeError("the library parted the pieces otherwise")
            raw, w = ids.tobytes(), ids.itemsize
            out.update((p, raw[w * a : w * b]) for p, a, b in zip(some, edge, edge[1:]))
        rest = [p for p in pieces if p not in out]
        got = self.tok.encode_batch_fast(rest, add_special_tokens=False)
        out.update((p, np.array(e.ids, self.type).tobytes()) for p, e in zip(rest, got))
        return [out[p] for p in pieces]

    def _learn(self, spans: list[str], unsettled: np.ndarray) -> list[bytes]:
        """Ids of distinct spans; unsettled ones are parted by the library's pattern first."""
        parts = [self.split(c) if u else (c,) for c, u in zip(spans, unsettled.tolist())]
        names = list(set().union(*parts))
        get = dict(zip(names, self._runs(names))).__getitem__
        return [get(p[0]) if len(p) == 1 else b"".join(map(get, p)) for p in parts]

    def _looked_up(self, raw: np.ndarray, s: np.ndarray, e: np.ndarray, unsettled: np.ndarray, words) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all spans, ids of each) by the table, which learns what it lacks."""
        h = np.maximum(K.span_hashes(raw, s, e), np.uint64(1))
        check = (K.span_hashes(raw, s, e, salt=1) >> np.uint64(32)).astype(np.uint32)
        slot = self.table.find(h, check)
        miss = np.flatnonzero(slot < 0)
        if len(miss):
            new = _distinct(h, check, miss)
            if self.table.n + len(new) > self.table.slots // 2:
                miss = np.arange(len(h))
                new = _distinct(h, check, miss)
                self.table.clear(len(new))
            self.table.add(h[new], check[new], self._learn(words(s[new], e[new]), unsettled[new]))
            slot[miss] = self.table.find(h[miss], check[miss])
        out = self.table(slot)
        if self.table.slots > self.table.least:
            self.table.clear()
        return out

    def encode(self, texts: list[bytes]) -> list[bytes]:
        """Ids of UTF-8 texts, packed."""
        odd = {k for k, t in enumerate(texts) if _ODD.search(t)}
        plain = [b"" if k in odd else t for k, t in enumerate(texts)]
        raw = np.frombuffer(b"".join(plain), np.uint8)
        off = np.concatenate([[0], np.cumsum(np.fromiter(map(len, plain), np.int64, len(plain)))])
        s, e, unsettled = split_classes(raw, *piece_spans(raw, off))
        view = raw.tobytes()
        words = lambda a, b: [str(view[i:j], "utf-8") for i, j in zip(a.tolist(), b.tolist())]
        long = e - s > LONG
        flat, size = self._looked_up(raw, s[~long], e[~long], unsettled[~long], words)
        if long.any():
            past = [np.array(x.ids, self.type) for x in self.tok.encode_batch_fast(words(s[long], e[long]), add_special_tokens=False)]
            at = np.flatnonzero(long) - np.arange(len(past))  # short spans before each
            runs = np.split(flat, np.concatenate([[0], np.cumsum(size)])[at])
            flat = np.concatenate([x for pair in zip(runs, past) for x in pair] + runs[-1:])
            size = np.insert(size, at, [len(x) for x in past])
        edge = np.concatenate([[0], np.cumsum(size)])[np.searchsorted(s, off)].tolist()
        body, w = flat.tobytes(), flat.itemsize
        return [self._ids(str(t, "utf-8")) if k in odd else body[w * a : w * b] for k, (t, a, b) in enumerate(zip(texts, edge, edge[1:]))]


@lru_cache(maxsize=2)
def encoder(path: str) -> Encoder:
    """One encoder for all tasks of a worker."""
    return Encoder(path)


def code_lengths(counts: np.ndarray, limit: int = LIMIT) -> np.ndarray:
    """Optimal code lengths of at most ``limit`` bits (package-merge); 0 where the count is 0."""
    out = np.zeros(len(counts), np.int64)
    used = np.flatnonzero(counts)
    n = len(used)
    if n <= 1:
        out[used] = 1
        return out
    if n > 1 << limit:
        raise ValueError(f"{n} ids do not fit into codes of {limit} bits")
    order = used[np.argsort(counts[used], kind="stable")]
    leaf = counts[order].astype(np.float64)
    levels, now = [], leaf
    flags = np.ones(n, bool)
    for _ in range(limit):
        levels.append(flags)
        pairs = now[: len(now) // 2 * 2].reshape(-1, 2).sum(1)
        both = np.concatenate([leaf, pairs])
        by = np.argsort(both, kind="stable")
        now, flags = both[by], by < n
    take = 2 * n - 2
    for flags in reversed(levels):
        singles = int(flags[:take].sum())
        out[order[:singles]] += 1
        take = 2 * (take - singles)
    return out


class Codebook:
    """Canonical codes from lengths; ``symbol`` and ``step`` decode LIMIT bits at once."""

    def __init__(self, lengths: np.ndarray):
        self.length = lengths.astype(np.int64)
        used = np.flatnonzero(lengths)
        order = used[np.lexsort((used, lengths[used]))]
        span = 1 << (LIMIT - lengths[order].astype(np.int64))
        base = np.cumsum(span) - span
        self.code = np.zeros(len(lengths), np.uint64)
        self.code[order] = (base >> (LIMIT - lengths[order].astype(np.int64))).astype(np.uint64)
        self.symbol = np.zeros(1 << LIMIT, np.uint32)
        self.step = np.ones(1 << LIMIT, np.int64)
        total = int(span.sum()) if len(span) else 0
        self.symbol[:total] = np.repeat(order, span)
        self.step[:total] = np.repeat(self.length[order], span)

    def encode(self, ids: np.ndarray) -> tuple[bytes, np.ndarray]:
        """(bits, bit offset of every STRIDE-th id)."""
        length = self.length[ids]
        end = np.cumsum(length)
        at = end - length
        word = at >> 5
        wide = self.code[ids] << (64 - (at & 31) - length).astype(np.uint64)
        n = int(end[-1] >> 5) + 2 if len(ids) else 0
        if not n:
            return b"", np.zeros(0, np.int64)
        high = np.bincount(word, (wide >> np.uint64(32)).astype(np.float64), n)
        low = np.bincount(word + 1, (wide & np.uint64(0xFFFFFFFF)).astype(np.float64), n)
        bits = (high + low).astype(np.uint32).astype(">u4").tobytes()
        return bits[: (int(end[-1]) + 7) // 8], at[::STRIDE]

    def decode(self, bits: bytes, marks: np.ndarray, n: int) -> np.ndarray:
        raw = np.frombuffer(bits + b"\0\0\0\0", np.uint8).astype(np.uint32)
        view = (raw[:-3] << 24) | (raw[1:-2] << 16) | (raw[2:-1] << 8) | raw[3:]
        at = marks.copy()
        out = np.zeros((STRIDE, len(marks)), np.uint32)
        last = len(view) - 1
        for k in range(STRIDE):
            look = (view[np.minimum(at >> 3, last)] >> (32 - LIMIT - (at & 7)).astype(np.uint32)) & ((1 << LIMIT) - 1)
            out[k] = self.symbol[look]
            at += self.step[look]
        return out.T.ravel()[:n]


_DEALT = pa.schema([("part", pa.int32()), ("doc_id", pa.int64()), ("tie", pa.int64()), ("n_raw", pa.int64()), ("packed", pa.binary())])
_IDS = pa.schema([("part", pa.int32()), ("seq", pa.int64()), ("doc_id", pa.int64()), ("ids", pa.binary())])
_BLOCKS = pa.schema([("part", pa.int32()), ("first", pa.int64()), ("n_tokens", pa.int64()), ("head", pa.binary()), ("marks", pa.binary()), ("bits", pa.binary())])
_BLOCKS_DDL = "part int, first long, n_tokens long, head binary, marks binary, bits binary"


def _deal(bounds: np.ndarray, null_parts: int):
    """Compressed texts with the part they belong to; a doc_id that is a bound may lie on both its sides."""

    def run(batches):
        for batch in batches:
            raw, off = K.string_buffers(batch.column("text"))
            ids, null = X.doc_ids(batch)
            cut = list(zip(off[:-1].tolist(), off[1:].tolist()))
            view = memoryview(np.ascontiguousarray(raw))
            tie = np.fromiter((zlib.crc32(view[a:b]) for a, b in cut), np.int64, len(cut))
            low, high = np.searchsorted(bounds, ids, "left"), np.searchsorted(bounds, ids, "right")
            part = np.where(null, len(bounds) + 1 + tie % null_parts, low + tie % (high - low + 1)).astype(np.int32)
            packed = [pa.compress(view[a:b], codec="zstd", asbytes=True) if b > a else b"" for a, b in cut]
            yield pa.RecordBatch.from_arrays([pa.array(part), batch.column("doc_id").cast(pa.int64()), pa.array(tie), pa.array(np.diff(off), pa.int64()), pa.array(packed, pa.binary())], schema=_DEALT)

    return run


def _tokenise(path: str, end_id: int):
    def run(batches):
        enc = encoder(path)
        end = np.array([end_id], enc.type).tobytes()
        seq = 0  # rows come by part and doc_id; the numbers only have to ascend
        for batch in batches:
            sizes = batch.column("n_raw").to_numpy()
            packed = batch.column("packed")
            off = np.concatenate([[0], np.cumsum(sizes)])
            for i, j in K.slices(off, 4 * K.SEGMENT):
                texts = [X.unpack_text(packed[k].as_py(), int(sizes[k])) for k in range(i, j)]
                ids = [x + end for x in enc.encode(texts)]
                yield pa.RecordBatch.from_arrays([batch.column("part").slice(i, j - i), pa.array(np.arange(seq, seq + j - i)), batch.column("doc_id").slice(i, j - i), pa.array(ids, pa.binary())], schema=_IDS)
                seq += j - i

    return run


def _flat(batch: pa.RecordBatch, kind) -> tuple[np.ndarray, np.ndarray]:
    """(all ids of a batch, bounds by document)."""
    col = batch.column("ids").cast(pa.large_binary())
    off = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + len(col) + 1]
    if not len(col):
        return np.zeros(0, kind), np.zeros(1, np.int64)
    width = np.dtype(kind).itemsize
    return np.frombuffer(col.buffers()[2], kind, int(off[-1] - off[0]) // width, int(off[0])), (off - off[0]) // width


def _histogram(kind):
    def run(batches):
        total = np.zeros(0, np.int64)
        for batch in batches:
            got = np.bincount(_flat(batch, kind)[0])
            if len(got) > len(total):
                total = np.concatenate([total, np.zeros(len(got) - len(total), np.int64)])
            total[: len(got)] += got
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(used, pa.int64()), pa.array(total[used], pa.int64())], names=["id", "n"])

    return run


def _blocks(lengths: np.ndarray, kind):
    def run(batches):
        book = Codebook(lengths)
        for batch in batches:
            ids, bound = _flat(batch, kind)
            part, seq = batch.column("part").to_numpy(), batch.column("seq").to_numpy()
            docs, null = X.doc_ids(batch)
            i = 0
            while i < len(part):
                j = i + 1
                while j < len(part) and part[j] == part[i] and bound[j + 1] - bound[i] <= BLOCK:
                    j += 1
                own = ids[bound[i] : bound[j]].astype(np.int64)
                bits, marks = book.encode(own)
                head = K.pack(K.deltas(docs[i:j]), null[i:j].astype(np.uint8), np.diff(bound[i : j + 1]).astype(np.uint32))
                cols = [[int(part[i])], [int(seq[i])], [len(own)], [head], [K.pack(K.deltas(marks).astype(np.uint32))], [bits]]
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, _BLOCKS)], schema=_BLOCKS)
                i = j

    return run


def write_token_file(docs: DataFrame, vocabulary: str, path: str, end_id: int = 0, parts: int | None = None) -> None:
    """Tokenise ``docs`` (doc_id, text) and write them under ``path`` in ascending doc_id order."""
    spark = docs.sparkSession
    docs = docs.select("doc_id", "text")
    parts = parts or bucket_count(docs, 4 << 20, least=16, most=1 << 15)
    cuts = docs.select(F.col("doc_id").cast("double").alias("d")).where("d IS NOT NULL").approxQuantile("d", [k / parts for k in range(1, parts)], 0.2 / parts) if parts > 1 else []
    bounds = np.sort(np.array([max(-(2**63), min(2**63 - 1, int(c))) for c in cuts], np.int64))
    n = docs.agg(F.count("*").alias("all"), F.count("doc_id").alias("named")).first()
    null_parts = max(1, -(-parts * (n.all - n.named) // max(1, n.all)))
    kind = Encoder(vocabulary).type
    dealt = docs.mapInArrow(_deal(bounds, null_parts), "part int, doc_id long, tie long, n_raw long, packed binary")
    sorted_ = dealt.repartition("part").sortWithinPartitions("part", F.asc_nulls_last("doc_id"), "tie", "n_raw", "packed")
    ids = Stored(spark, sorted_.mapInArrow(_tokenise(vocabulary, end_id), "part int, seq long, doc_id long, ids binary"), "ids", compression="zstd")
    counted = ids.df.select("ids").mapInArrow(_histogram(kind), "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).collect()  # at most the vocabulary
    counts = np.zeros(1 + max((r.id for r in counted), default=end_id), np.int64)
    for r in counted:
        counts[r.id] = r.n
    lengths = code_lengths(counts)
    book = [(int(k), int(lengths[k])) for k in np.flatnonzero(lengths)]
    spark.createDataFrame(book, "id long, length int").coalesce(1).write.parquet(f"{path}/codebook")
    ids.df.mapInArrow(_blocks(lengths, kind), _BLOCKS_DDL).write.option("compression", "none").parquet(f"{path}/blocks")
    ids.drop()


def load_codebook(spark: SparkSession, path: str) -> Codebook:
    rows = spark.read.schema("id long, length int").parquet(f"{path}/codebook").collect()  # at most the vocabulary
    lengths = np.zeros(1 + max((r.id for r in rows), default=0), np.int64)
    for r in rows:
        lengths[r.id] = r.length
    return Codebook(lengths)


def _per_doc(book: Codebook, with_ids: bool):
    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                key, null, count = K.unpack(row["head"])
                key, count = np.cumsum(key), count.astype(np.int64)
                marks = np.cumsum(K.unpack(row["marks"])[0].astype(np.int64))
                ids = np.ascontiguousarray(book.decode(row["bits"], marks, row["n_tokens"]).astype("<u4"))
                end = np.cumsum(count)
                m = len(key)
                view = memoryview(ids).cast("B") if len(ids) else memoryview(b"")
                edge = list(zip((4 * (end - count)).tolist(), (4 * end).tolist()))
                crc = [zlib.crc32(view[a:b]) for a, b in edge]
                cols = [
                    pa.array(np.full(m, row["part"], np.int32)), pa.array(np.full(m, row["first"])), pa.array(key, pa.int64(), mask=null > 0),
                    pa.array(end - count), pa.array(count), pa.array(crc, pa.int64()),
                ]
                names = ["part", "first", "doc_id", "before", "n_tokens", "ids_crc32"]
                if with_ids:
                    cols.append(pa.array([bytes(view[a:b]) for a, b in edge], pa.binary()))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(cols, names=names)

    return run


def read_token_file(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32[, ids]) decoded from the file; ids as little-endian unsigned 32-bit."""
    book = load_codebook(spark, path)
    blocks = spark.read.schema(_BLOCKS_DDL).parquet(f"{path}/blocks")
    name = ["part", "first"]
    docs = blocks.mapInArrow(_per_doc(book, with_ids), "part int, first long, doc_id long, before long, n_tokens long, ids_crc32 long" + (", ids binary" if with_ids else ""))
    size = blocks.select(*name, F.col("n_tokens").alias("k"))
    inside = size.select(*name, (F.sum("k").over(Window.partitionBy("part").orderBy("first")) - F.col("k")).alias("inside"))
    of_part = size.groupBy("part").agg(F.sum("k").alias("k"))
    before = of_part.select("part", (F.sum("k").over(Window.orderBy("part")) - F.col("k")).alias("ahead"))  # a row per part
    start = inside.join(before, "part")
    return docs.join(start, name).select("doc_id", (F.col("ahead") + F.col("inside") + F.col("before")).alias("start"), "n_tokens", "ids_crc32", *(["ids"] if with_ids else []))
