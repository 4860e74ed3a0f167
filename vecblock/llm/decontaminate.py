"""Benchmark decontamination by greedy string tiling.

Documents and benchmark items are token sequences (runs of letters, digits and
other non-ASCII characters, lower-cased).  Shared seeds of ``seed`` tokens are
found by Karp-Rabin hashes; seeds on one diagonal join to maximal matches; the longest match that
is still free is marked as a tile, again and again, so that passages cut up and
reordered still add up.  A document is contaminated if tiles cover at least
``coverage`` of some item.

The benchmark is indexed in blocks of a bounded size, each broadcast to a pass
over the documents; one block serves any usual benchmark.  With more blocks the passes
follow each other, each written to the shared folder, and one index is held at a time.

Defined results: null or empty texts contain nothing; items of fewer than
``least_tokens`` tokens are ignored, as any document would hold them; an item with fewer
tokens than a seed matches as a whole; rows that share a doc_id are judged each; equal coverages report the smaller item; an empty
benchmark contaminates nothing; other columns are kept by ``clean_documents``.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, DoubleType, LongType, StructField, StructType

from vecblock.llm import kernels as K
from vecblock.llm.shared import Stored, free_name

SEED, COVERAGE, BLOCK_CHARS, LEAST = 5, 0.7, 16 << 20, 3
#: Pairs of equal seeds that are looked at together.
PAIRS = 1 << 20
_GAP = np.ones(256, bool)
_GAP[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False


def tokens(col: pa.Array) -> tuple[K.Words, np.ndarray]:
    raw, off = K.string_buffers(pc.utf8_lower(col))
    return _tokens(raw, off), off


def _tokens(raw: np.ndarray, off: np.ndarray) -> K.Words:
    return K.words(raw, off, space=_GAP)


@dataclass
class Index:
    """Seeds of a benchmark block, sorted by hash."""

    seed: int
    hash: np.ndarray
    item: np.ndarray  # row of the item
    place: np.ndarray
    ids: np.ndarray
    size: np.ndarray

    @classmethod
    def build(cls, ids: list[int], texts: list[str], seed: int, least: int = LEAST) -> list[Index]:
        """One index per seed length: ``seed``, and each shorter length that short items have."""
        w, _ = tokens(pa.array(texts, pa.string()))
        size = np.diff(w.bound)
        out = []
        for width in range(min(least, seed), seed + 1):
            rows = np.flatnonzero(size >= max(seed, least) if width == seed else size == width)
            if not len(rows):
                continue
            h = K.window_hashes(w.hash, width)
            count = size[rows] - width + 1
            at = K.ragged(w.bound[rows], count)
            place = at - np.repeat(w.bound[rows], count)
            item = np.repeat(np.arange(len(rows)), count)
            order = np.argsort(h[at], kind="stable")
            out.append(cls(width, h[at][order], item[order], place[order], np.array(ids, np.int64)[rows], size[rows]))
        return out


def tile_matches(in_doc: np.ndarray, in_item: np.ndarray, length: np.ndarray, size: int, seed: int) -> int:
    """Tokens of an item of ``size`` that greedy tiles cover, from its maximal matches with a document."""
    heap = sorted(zip((-length).tolist(), in_item.tolist(), in_doc.tolist()))
    used_d: set[int] = set()
    used_i: set[int] = set()
    total = 0
    while heap and size - total >= seed:
        neg, a, b = heapq.heappop(heap)
        free, start = [], None
        for k in range(-neg):
            ok = a + k not in used_i and b + k not in used_d
            if ok and start is None:
                start = k
            if start is not None and (not ok or k == -neg - 1):
                free.append((start, k if not ok else k + 1))
                start = None
        if free == [(0, -neg)]:
            used_i.update(range(a, a - neg))
            used_d.update(range(b, b - neg))
            total -= neg
        else:  # what is still free of it waits for its turn
            for s, e in free:
                if e - s >= seed:
                    heapq.heappush(heap, (s - e, a + s, b + s))
    return total


def _runs(row: np.ndarray, item: np.ndarray, diagonal: np.ndarray, place: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, ...]:
    """Matches that continue each other on a diagonal as one, ordered by row, item, diagonal and place."""
    order = np.lexsort((place, diagonal, item, row))
    row, item, diagonal, place, length = (x[order] for x in (row, item, diagonal, place, length))
    new = np.ones(len(row), bool)
    new[1:] = (np.diff(row) != 0) | (np.diff(item) != 0) | (np.diff(diagonal) != 0) | (place[1:] != place[:-1] + length[:-1])
    first = np.flatnonzero(new)
    return row[first], item[first], diagonal[first], place[first], np.add.reduceat(length, first) if len(first) else length


def tile(in_doc: np.ndarray, in_item: np.ndarray, seed: int) -> int:
    """The same from the places of single seeds."""
    z = np.zeros(len(in_doc), np.int64)
    _, _, diagonal, place, length = _runs(z, z, in_doc - in_item, in_item, z + 1)
    return tile_matches(place + diagonal, place, length + seed - 1, int(in_item.max(initial=-1)) + seed, seed)


def judge(indexes: list[Index], w: K.Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(best item or -1, its coverage, items touched) for each text."""
    n = len(w.bound) - 1
    best, cover, touched = np.full(n, -1, np.int64), np.zeros(n), np.zeros(n, np.int64)
    for index in indexes:
        h = K.window_hashes(w.hash, index.seed)
        if not len(h):
            continue
        lo = np.searchsorted(index.hash, h)
        hit = index.hash[np.minimum(lo, len(index.hash) - 1)] == h
        at = np.flatnonzero(hit)
        row = np.searchsorted(w.bound, at, "right") - 1
        inside = at + index.seed <= w.bound[row + 1]
        at, row = at[inside], row[inside]
        if not len(at):
            continue
        lo = lo[at]
        count = np.searchsorted(index.hash, h[at], "right") - lo
        edge = np.concatenate([[0], np.cumsum(count)])
        parts, i = [], 0
        while i < len(at):  # a repeated token pairs with each of its places in an item: a bounded number of pairs at once
            j = max(i + 1, int(np.searchsorted(edge, edge[i] + PAIRS, "right")) - 1)
            seeds = K.ragged(lo[i:j], count[i:j])
            r, d = np.repeat(row[i:j], count[i:j]), np.repeat(at[i:j] - w.bound[row[i:j]], count[i:j])
            parts.append(_runs(r, index.item[seeds], d - index.place[seeds], index.place[seeds], np.ones(len(seeds), np.int64)))
            i = j
        row, item, diagonal, place, length = _runs(*(np.concatenate(x) for x in zip(*parts)))
        length = length + index.seed - 1
        first = np.flatnonzero(np.append(True, (np.diff(row) != 0) | (np.diff(item) != 0)))
        for a, b in zip(first.tolist(), [*first[1:].tolist(), len(row)]):
            r, k = int(row[a]), int(item[a])
            share = tile_matches(place[a:b] + diagonal[a:b], place[a:b], length[a:b], int(index.size[k]), index.seed) / index.size[k]
            touched[r] += 1
            name = int(index.ids[k])
            if share > cover[r] or (share == cover[r] and (best[r] < 0 or name < best[r])):
                best[r], cover[r] = name, share
    return best, cover, touched


def _pass(indexes, names: list[str], text: str):
    def run(batches):
        built = indexes.value
        for batch in batches:
            lowered = pc.utf8_lower(batch.column(text))
            raw, off = K.string_buffers(lowered)
            got = [judge(built, _tokens(raw[off[i] : off[j]], off[i : j + 1] - off[i])) for i, j in K.slices(off, K.SEGMENT)]
            best, cover, touched = (np.concatenate([g[k] for g in got]) if got else np.zeros(0) for k in range(3))
            mine = [pa.array(best.astype(np.int64), mask=best < 0), pa.array(cover.astype(np.float64)), pa.array(touched.astype(np.int64))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *mine], names=[*batch.schema.names, *names])

    return run


def _blocks(benchmark: DataFrame, limit: int):
    """Lists of (item_id, text) of at most ``limit`` characters together, streamed to the driver one by one."""
    now, chars = [], 0
    for r in benchmark.select("item_id", "text").where("text IS NOT NULL AND item_id IS NOT NULL").orderBy("item_id", "text").toLocalIterator():
        if now and chars + len(r.text) > limit:
            yield now
            now, chars = [], 0
        now.append((r.item_id, r.text))
        chars += len(r.text)
    if now:
        yield now


def judged(docs: DataFrame, benchmark: DataFrame, seed: int = SEED, coverage: float = COVERAGE, block_chars: int = BLOCK_CHARS, least_tokens: int = LEAST) -> DataFrame:
    """``docs`` with best_item, covered, n_items and contaminated, which replace columns of these names."""
    spark = docs.sparkSession
    out = docs.withColumns({"best_item": F.lit(None).cast("long"), "covered": F.lit(0.0), "n_items": F.lit(0).cast("long")})
    names = [free_name(out, x) for x in ("b_item", "b_covered", "b_items")]
    held: list = []
    for items in _blocks(benchmark, block_chars):
        if held:  # one block at a time: what the last one found is written before the next is sent
            step = Stored(spark, out, "judged")
            held[0].destroy()
            if held[1] is not None:
                held[1].drop()
            out, held = step.df, [None, step]
        index = spark.sparkContext.broadcast(Index.build([i for i, _ in items], [t for _, t in items], seed, least_tokens))  # at most ``block_chars``
        held = [index, held[1] if held else None]
        schema = StructType([*out.schema.fields, StructField(names[0], LongType()), StructField(names[1], DoubleType()), StructField(names[2], LongType())])
        out = out.mapInArrow(_pass(index, names, "text"), schema)
        better = (F.col(names[1]) > F.col("covered")) | ((F.col(names[1]) == F.col("covered")) & F.col("best_item").isNull())
        out = out.withColumns({"best_item": F.when(better, F.col(names[0])).otherwise(F.col("best_item")), "covered": F.greatest("covered", names[1]), "n_items": F.col("n_items") + F.col(names[2])}).drop(*names)
    return out.withColumn("contaminated", (F.col("covered") >= coverage).cast(BooleanType()))


def clean_documents(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The documents that are not contaminated, in their own columns."""
    own = ("best_item", "covered", "n_items", "contaminated")
    clash = {c: f"_own_{c}" for c in docs.columns if c in own}
    out = judged(docs.withColumnsRenamed(clash), benchmark, **options).where("NOT contaminated").drop(*own)
    return out.withColumnsRenamed({v: k for k, v in clash.items()})
