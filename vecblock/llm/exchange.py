"""A compact keyed exchange: hashed entries of documents meet in buckets, verdicts return per row.

A row is known by the file it is read from and its place there (64 bits each), so rows
that share a doc_id, or have none, are never mixed up; rows that do not come
straight from files are written to the shared folder first.

Tasks emit entries (hash, check, position).  Entries for one hash bucket travel
as one packed block, so that a shuffled row stands for thousands of entries; in
Spark's row format a row per entry would alone shuffle several times the
input.  What a slice of texts can settle itself is settled before the shuffle, hence a
hash that every document holds reaches its bucket once per slice and not once per
document.  With more than FAN buckets, entries go in two steps: coarse buckets
gather the blocks of many slices, settle them once more and cut them finer.  Buckets
answer with the positions concerned, packed per row.

Documents are compared by doc_id; a null doc_id comes after all others.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, LongType, StructField, StructType

from vecblock.llm import kernels as K
from vecblock.llm.shared import Stored

#: Texts that are hashed together.
CHUNK_BYTES = 2 << 20
#: Most buckets of one step.
FAN = 4096
#: Entries that the first of two steps gathers before it cuts them finer.
GATHER = 4 << 20
#: A bucket is judged in so many turns, to bound the memory of sorting it.
TURNS = 4
#: Bytes of an entry's check that travel.
CHECK = 3
CHUNK = "chunk binary, n_raw long, head binary, body binary"
BLOCK = "bucket int, block binary"
VERDICT = "src long, nth long, at binary"
_CHUNK = pa.schema([("chunk", pa.binary()), ("n_raw", pa.int64()), ("head", pa.binary()), ("body", pa.binary())])
_BLOCK = pa.schema([("bucket", pa.int32()), ("block", pa.binary())])
_VERDICT = pa.schema([("src", pa.int64()), ("nth", pa.int64()), ("at", pa.binary())])

#: entries(raw, off) -> parts of (row, position, hash, check)
Entries = Callable[[np.ndarray, np.ndarray], Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]]
#: settle(hash, check, document rank) -> (keep mask, hit mask): what some entries decide among themselves;
#: the kept ones must lead all others to the same decision as if all were there
Settle = Callable[[np.ndarray, np.ndarray, np.ndarray], tuple[np.ndarray, np.ndarray]]
#: decide(hash, check, document rank) -> hit mask
Decide = Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray]


def ranks(ids: np.ndarray, null: np.ndarray) -> np.ndarray:
    """Small numbers in the order of the ids, nulls last."""
    known = np.unique(ids[~null])
    return np.where(null, len(known), np.searchsorted(known, ids)).astype(np.int64)


def named_rows(docs: DataFrame) -> DataFrame:
    """(doc_id, text, src, nth): rows of files by the file's hash and their place in it; other rows are written to files first."""
    plan, kinds = docs._jdf.queryExecution().analyzed(), set()
    while True:
        kinds.add(plan.nodeName())
        if plan.children().size() != 1:
            break
        plan = plan.children().head()
    try:
        if not kinds <= {"Project", "Filter", "SubqueryAlias", "LogicalRelation"}:
            raise AnalysisException("rows of files only")
        file = docs.metadataColumn("_metadata")
        return docs.select("doc_id", "text", F.xxhash64(file["file_path"]).alias("src"), file["row_index"].alias("nth"))
    except AnalysisException:  # no file, or a format that does not number its rows
        file = (df := Stored(docs.sparkSession, docs.select("doc_id", "text"), "rows").df).metadataColumn("_metadata")
        return df.select("doc_id", "text", F.xxhash64(file["file_path"]).alias("src"), file["row_index"].alias("nth"))


# --- chunks ----------------------------------------------------------------------


class Chunk:
    """Rows of a chunk: ``raw[off[i]:off[i+1]]`` is text i; ``there`` is false where it is null."""

    __slots__ = ("ids", "null", "off", "raw", "there")

    def __init__(self, ids, null, there, off, raw):
        self.ids, self.null, self.there, self.off, self.raw = ids, null, there, off, raw

    @classmethod
    def open(cls, batch: pa.RecordBatch, k: int, with_text: bool = True) -> Chunk:
        ids, flags, size = K.unpack(batch.column("head")[k].as_buffer())
        raw = np.zeros(0, np.uint8)
        if with_text and batch.column("n_raw")[k].as_py():
            raw = np.frombuffer(pa.decompress(batch.column("body")[k].as_buffer(), batch.column("n_raw")[k].as_py(), codec="zstd"), np.uint8)
        return cls(np.cumsum(ids), (flags & 1) > 0, (flags & 2) > 0, np.concatenate([[0], np.cumsum(size.astype(np.int64))]), raw)

    def texts(self) -> Iterator[bytes]:
        for a, b in zip(self.off[:-1].tolist(), self.off[1:].tolist()):
            yield self.raw[a:b].tobytes()

    def doc_ids(self) -> pa.Array:
        return pa.array(self.ids, pa.int64(), mask=self.null)


def doc_ids(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """(ids, which are null) of a batch with a doc_id."""
    col = batch.column("doc_id").cast(pa.int64())
    return col.fill_null(0).to_numpy(zero_copy_only=False), col.is_null().to_numpy(zero_copy_only=False)


def cut_chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list, Chunk]]:
    """(the columns of CHUNK, the open chunk) for runs of rows of about CHUNK_BYTES."""
    for batch in batches:
        raw, off = K.string_buffers(batch.column("text"))
        ids, null = doc_ids(batch)
        there = batch.column("text").is_valid().to_numpy(zero_copy_only=False)
        for i, j in K.slices(off, CHUNK_BYTES):
            c = Chunk(ids[i:j], null[i:j], there[i:j], off[i : j + 1] - off[i], raw[off[i] : off[j]])
            head = K.pack(K.deltas(c.ids), c.null + 2 * c.there.astype(np.uint8), np.diff(c.off).astype(np.uint32))
            body = pa.compress(c.raw.tobytes(), codec="zstd", asbytes=True) if len(c.raw) else b""
            yield [uuid.uuid4().bytes, len(c.raw), head, body], c


# --- blocks -----------------------------------------------------------------------


class Gather:
    """Entries of many blocks: a table of rows, and the entries."""

    def __init__(self):
        self.parts: list[tuple] = []
        self.rows = self.n = 0

    def add(self, src: np.ndarray, nth: np.ndarray, ids: np.ndarray, null: np.ndarray, row: np.ndarray, pos: np.ndarray, h: np.ndarray, g: np.ndarray) -> None:
        self.parts.append((src, nth, ids, null, row + self.rows, pos, h, g))
        self.rows += len(src)
        self.n += len(h)

    def read(self, block: pa.Buffer) -> None:
        data = memoryview(block)
        start = 9 + int.from_bytes(data[1:9], "little")
        src, nth, ids, null, count, step = K.unpack(data[9:start])
        n = len(step)
        g = np.zeros((n, 4), np.uint8)
        g[:, :CHECK] = np.frombuffer(data, np.uint8, CHECK * n, start + 8 * n).reshape(n, CHECK)
        self.add(np.cumsum(src), np.cumsum(nth), np.cumsum(ids), null > 0, *_places(count, step), np.frombuffer(data, np.uint64, n, start), g.view("<u4").ravel())

    def close(self) -> None:
        """One array of each kind; ``rank`` orders the rows' documents."""
        self.src, self.nth, self.ids, self.null, self.row, self.pos, self.h, self.g = (np.concatenate(x) for x in zip(*self.parts))
        self.parts = []
        self.rank = ranks(self.ids, self.null).astype(np.int32)

    def block(self, pick: np.ndarray) -> bytes:
        """Some entries, ascending, as a block."""
        who, count, step = _steps(self.row[pick], self.pos[pick])
        body = K.pack(K.deltas(self.src[who]), K.deltas(self.nth[who]), K.deltas(self.ids[who]), self.null[who].astype(np.uint8), count, step)
        return b"E" + len(body).to_bytes(8, "little") + body + self.h[pick].tobytes() + self.g[pick].astype("<u4").view(np.uint8).reshape(-1, 4)[:, :CHECK].tobytes()

    def answers(self, pick: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(src, nth, count, step) of the rows that some entries, ascending, belong to."""
        who, count, step = _steps(self.row[pick], self.pos[pick])
        return self.src[who], self.nth[who], count, step


def _steps(row: np.ndarray, pos: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rows, entries of each, steps from position to position, anew in each row)."""
    first = np.flatnonzero(np.diff(row, prepend=-1))
    step = pos.copy()
    step[1:] -= np.where(np.diff(row) == 0, pos[:-1], np.uint32(0))
    return row[first], np.diff(np.append(first, len(row))).astype(np.uint32), step


def _places(count: np.ndarray, step: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row number, position) of entries from ``_steps``."""
    row = np.repeat(np.arange(len(count), dtype=np.int32), count)
    total = np.cumsum(step, dtype=np.uint32)
    first = np.cumsum(count.astype(np.int64)) - count
    base = np.where(first > 0, total[np.maximum(first - 1, 0)], np.uint32(0)) if len(total) else total
    return row, total - base[row]


def _parted(g: Gather, keep: np.ndarray, hit: np.ndarray, shift: int, bits: int, base: int) -> pa.RecordBatch | None:
    """Blocks of the kept entries by the hash bits below ``shift``, and what is settled already."""
    out_b, out_p = [], []
    if hit.any():  # passes through any bucket
        src, nth, count, step = g.answers(np.flatnonzero(hit))
        out_b.append(base + int(nth[0]) % (1 << bits))
        out_p.append(b"D" + K.pack(K.deltas(src), K.deltas(nth), count, step))
    pick = np.flatnonzero(keep)
    if len(pick):
        to = ((g.h[pick] >> np.uint64(shift)) & np.uint64((1 << bits) - 1)).astype(np.uint16)
        order = np.argsort(to, kind="stable")
        to, pick = to[order], pick[order]
        edge = np.flatnonzero(np.diff(to.astype(np.int64), prepend=-1))
        for a, b in zip(edge.tolist(), [*edge[1:].tolist(), len(to)]):
            out_b.append(base + int(to[a]))
            out_p.append(g.block(pick[a:b]))
    return pa.RecordBatch.from_arrays([pa.array(out_b, pa.int32()), pa.array(out_p, pa.binary())], schema=_BLOCK) if out_b else None


def _emit(entries: Entries, settle: Settle, bits: int):
    def run(batches):
        for batch in batches:
            raw, off = K.string_buffers(batch.column("text"))
            ids, null = doc_ids(batch)
            src, nth = batch.column("src").to_numpy(), batch.column("nth").to_numpy()
            for i, j in K.slices(off, CHUNK_BYTES):
                for row, pos, h, check in entries(raw[off[i] : off[j]], off[i : j + 1] - off[i]):
                    if not len(h):
                        continue
                    g = Gather()
                    g.add(src[i:j], nth[i:j], ids[i:j], null[i:j], row.astype(np.int32), pos.astype(np.uint32), h, check.astype(np.uint32) & np.uint32((1 << 8 * CHECK) - 1))
                    g.close()
                    out = _parted(g, *settle(g.h, g.g, g.rank[g.row]), 64 - bits, bits, 0)
                    if out is not None:
                        yield out

    return run


def _finer(settle: Settle, shift: int, bits: int):
    """Coarse buckets: the blocks of many slices, settled together and cut by the next bits of their hashes."""

    def cut(g: Gather, base: int) -> pa.RecordBatch | None:
        g.close()
        return _parted(g, *settle(g.h, g.g, g.rank[g.row]), shift, bits, base << bits)

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, g = key[0].as_py(), Gather()
        for batch in batches:
            for block in batch.column("block"):
                data = block.as_buffer()
                if data[:1].to_pybytes() == b"D":
                    yield pa.RecordBatch.from_arrays([pa.array([base << bits], pa.int32()), pa.array([data.to_pybytes()], pa.binary())], schema=_BLOCK)
                    continue
                g.read(data)
                if g.n >= GATHER:
                    out = cut(g, base)
                    g = Gather()
                    if out is not None:
                        yield out
        if g.n:
            out = cut(g, base)
            if out is not None:
                yield out

    return run


def _answered(src: np.ndarray, nth: np.ndarray, count: np.ndarray, step: np.ndarray) -> pa.RecordBatch:
    """One packed verdict for each row."""
    end = np.cumsum(count.astype(np.int64))
    at = [K.pack(step[a:b]) for a, b in zip((end - count).tolist(), end.tolist())]
    return pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(nth, pa.int64()), pa.array(at, pa.binary())], schema=_VERDICT)


def _judge(decide: Decide):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = Gather()
        for batch in batches:
            for block in batch.column("block"):
                data = block.as_buffer()
                if data[:1].to_pybytes() == b"D":
                    src, nth, count, step = K.unpack(data[1:])
                    yield _answered(np.cumsum(src), np.cumsum(nth), count, step)
                else:
                    g.read(data)
        if not g.n:
            return
        g.close()
        # equal hashes fall into the same turn, so the turns can be judged one by one
        hit = np.zeros(g.n, bool)
        turn = ((g.h >> np.uint64(8)) % np.uint64(TURNS)).astype(np.uint8)
        for k in range(TURNS):
            mine = np.flatnonzero(turn == k)
            if len(mine):
                hit[mine] = decide(g.h[mine], g.g[mine], g.rank[g.row[mine]])
        if hit.any():
            yield _answered(*g.answers(np.flatnonzero(hit)))

    return run


def exchange(rows: DataFrame, entries: Entries, settle: Settle, decide: Decide, buckets: int) -> DataFrame:
    """(src, nth, at): for each row (``named_rows``) the packed positions of the entries that ``decide`` or ``settle`` hit."""
    bits = max(1, (buckets - 1).bit_length())
    step = bits if 1 << bits <= FAN else (bits + 1) // 2
    sent = rows.mapInArrow(_emit(entries, settle, step), BLOCK)
    if step < bits:
        sent = sent.groupBy("bucket").applyInArrow(_finer(settle, 64 - bits, bits - step), BLOCK)
    heard = sent.groupBy("bucket").applyInArrow(_judge(decide), VERDICT)
    return heard.groupBy("src", "nth").agg(F.collect_list("at").alias("at"))


def positions(at: list[bytes] | None) -> np.ndarray:
    """All positions of one row, ascending."""
    if not at:
        return np.zeros(0, np.int64)
    return np.sort(np.concatenate([np.cumsum(K.unpack(x)[0].astype(np.int64)) for x in at]))


# --- texts on their own way ----------------------------------------------------------


def pack_texts(docs: DataFrame) -> DataFrame:
    """``docs`` with packed and n_raw for text: texts compressed before they are shuffled; null packed for a null text."""
    others = [f for f in docs.schema.fields if f.name != "text"]
    schema = StructType([*others, StructField("packed", BinaryType()), StructField("n_raw", LongType())])

    def run(batches):
        for batch in batches:
            col = batch.column("text")
            raw, off = K.string_buffers(col)
            there = col.is_valid().to_numpy(zero_copy_only=False)
            size = np.diff(off)
            packed = [pa.compress(raw[a:b].tobytes(), codec="zstd", asbytes=True) if ok and b > a else (b"" if ok else None) for a, b, ok in zip(off[:-1].tolist(), off[1:].tolist(), there.tolist())]
            yield pa.RecordBatch.from_arrays([*[batch.column(f.name) for f in others], pa.array(packed, pa.binary()), pa.array(size, pa.int64())], names=schema.names)

    return docs.mapInArrow(run, schema)


def small_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches of compressed texts (n_raw bytes each) in parts of about a megabyte of text."""
    for batch in batches:
        off = np.concatenate([[0], np.cumsum(batch.column("n_raw").to_numpy())])
        for i, j in K.slices(off):
            yield batch.slice(i, j - i)


def unpack_text(packed: bytes | None, n_raw: int) -> bytes:
    return pa.decompress(packed, n_raw, codec="zstd", asbytes=True) if packed else b""


def sha256_hex(data: bytes) -> str:
    return hashlib.sha256(data).hexdigest()


__all__ = ["Chunk", "Gather", "cut_chunks", "doc_ids", "exchange", "named_rows", "pack_texts", "positions", "ranks", "sha256_hex", "small_batches", "unpack_text"]
