"""Near-duplicate documents by MinHash with tensored banding.

A document's set holds the distinct shingles of ``width`` words (A-Z
lower-cased).  Two collections of ``groups`` short tuples of ``rows`` minhashes
each are computed; the key of table (i, j) combines tuple i of the first with
tuple j of the second.  groups**2 tables thus cost 2 * groups * rows minhashes
instead of groups**2 * 2 * rows.  At similarity s a pair meets in some table with
probability (1 - (1 - s**rows)**groups)**2: 0.9999 at s = 0.8 with the defaults, and
more above.

Copies (equal sets) collapse to one representative first.  Representatives meet
by the tuples of the first collection, in packed blocks; the tables (i, j) are
formed inside such a meeting, so a representative travels groups times and not groups**2
times.  A pair is a candidate if it shares a table and AGREE tuples in all.
Each meeting gives a spanning forest of its candidate pairs,
linear in its members; the connected parts of all forests are clusters.  Crowds
are thinned before the shuffle: members that agree with a local head almost
everywhere send their link to it and let it stand for them in that meeting.  The head
carries their least and largest size and the number of tuples in which one of them
differs from it, and takes every candidate that any of them could have.  Links are
confirmed on full shingle sets.  A small cluster is one block: sets outside the largest
component found so far are counted against all others by an inverted index.  A large
cluster is many blocks: its HEADS best connected sets visit each of them, and then the sets
that these left outside the cluster's largest component do.  No link between
components is missed and no pair is ever written out.  Components come from
alternating star contraction; neither links nor components visit the driver, and
the rows of a hot node or cluster are not gathered in one task.

Defined results: a text with fewer words than a shingle is its whole sequence as
one shingle; a null or blank text has the empty set and is linked with nothing;
rows that share a doc_id are separate texts under that id; a null doc_id is
kept and linked with nothing; an empty table gives no rows; other columns are ignored.
Shingles are compared by 64-bit hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vecblock.llm import exchange as X
from vecblock.llm import kernels as K
from vecblock.llm.shared import Stored, bucket_count, free_name

GROUPS, ROWS = 10, 2
#: Tuples (of 2 * GROUPS) that a candidate pair shares at least; at s = 0.8 fewer have a chance of 1e-4.
AGREE = 5
#: Members of a meeting that are compared pair by pair; larger ones are parted first.
DIRECT = 2048
#: Heads tried first in a meeting or block: they join most members at once.
HEADS = 16
#: Members of a meeting within one batch from which the crowd is thinned before the shuffle.
CROWD = 64
#: Tuples (of 2 * GROUPS) shared with a head by a member that the head can stand for (similarity of about 0.92 and more).
TIGHT = 17
#: Shingles and sets of one block of a cluster; the larger block counts.
BLOCK, BLOCK_SETS = 1 << 14, 128
#: Sets that visit the blocks of a cluster together.
PARTY = 128
#: Keys of more rows than HOT and a HOT_KEYS-th of all rows are joined by broadcast: HOT_KEYS keys at most.
HOT, HOT_KEYS = 200, 100_000
_U = np.uint64
_A = pa.list_(pa.int64())
_SKETCH = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("s1", pa.int64()), ("s2", pa.int64()), ("left", _A), ("right", _A)])


def shingle_sets(raw: np.ndarray, off: np.ndarray, width: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    w = K.words(raw, off, lower=True)
    wide = K.window_hashes(w.hash, width)
    for a, b in zip(w.bound[:-1].tolist(), w.bound[1:].tolist()):
        if b - a >= width:
            yield np.unique(wide[a : b - width + 1])
        elif b > a:
            yield np.array([K.sequence_hash(w.hash[a:b])], np.uint64)
        else:
            yield np.zeros(0, np.uint64)


def _identity(items: np.ndarray) -> tuple[int, int]:
    """128 bits for a whole set."""
    a = int(K.mix(items).sum(dtype=np.uint64))
    b = int(K.mix(items ^ _U(0xC2B2AE3D27D4EB4F)).sum(dtype=np.uint64)) ^ len(items)
    return a - 2**63, b - 2**63


def tuple_hashes(flat: np.ndarray, first: np.ndarray, groups: int, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """Both collections for many sets: sets x groups hashes of minhash tuples."""
    n = 2 * groups * rows
    odd = np.random.default_rng(977).integers(1, 2**63, (n, 2), dtype=np.uint64) * _U(2) + _U(1)
    out = np.empty((2 * groups, len(first)), np.uint64)
    for g in range(2 * groups):
        acc = np.full(len(first), g + 1, np.uint64)
        for r in range(rows):
            m, c = odd[g * rows + r]
            low = np.minimum.reduceat(flat * m + c, first) if len(first) else np.zeros(0, np.uint64)
            acc = K.mix(acc * _U(0x9FB21C651E98DF25) + low)
        out[g] = acc
    return out[:groups].T, out[groups:].T


def _sketch(width: int, groups: int, rows: int):
    def run(batches):
        for batch in batches:
            raw, off = K.string_buffers(batch.column("text"))
            ids = batch.column("doc_id").cast(pa.int64())
            for i, j in K.slices(off, 2 * K.SEGMENT):
                sets = list(shingle_sets(raw[off[i] : off[j]], off[i : j + 1] - off[i], width))
                size = np.array([len(s) for s in sets], np.int64)
                some = np.flatnonzero(size)
                left = np.zeros((j - i, groups), np.int64)
                right = left.copy()
                if len(some):
                    flat = np.concatenate([sets[k] for k in some.tolist()])
                    a, b = tuple_hashes(flat, np.cumsum(size[some]) - size[some], groups, rows)
                    left[some], right[some] = a.view(np.int64), b.view(np.int64)
                who = [_identity(s) for s in sets]
                edge = pa.array(np.arange(j - i + 1, dtype=np.int32) * groups)
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(i, j - i), pa.array(size), pa.array([w[0] for w in who], pa.int64()), pa.array([w[1] for w in who], pa.int64()), pa.ListArray.from_arrays(edge, pa.array(left.ravel())), pa.ListArray.from_arrays(edge, pa.array(right.ravel()))],
                    schema=_SKETCH,
                )

    return run


def spread_join(left: DataFrame, right: DataFrame, key: str) -> DataFrame:
    """Left join with the one row per key of ``right``; the left rows of a hot key stay where they are."""
    n = left.count()
    hot = left.groupBy(key).agg(F.count("*").alias("_n")).where((F.col("_n") > HOT) & (F.col("_n") > n // HOT_KEYS))
    hot = hot.select(key, F.lit(True).alias("_hot")).join(right, key, "left")
    marked = left.join(F.broadcast(hot), key, "left")  # at most HOT_KEYS rows
    cold = marked.where("_hot IS NULL").select(*left.columns).join(right, key, "left")
    return marked.where("_hot").drop("_hot").unionByName(cold)


def components(edges: DataFrame, spark: SparkSession, rounds: int = 60) -> Stored:
    """(v, c): every node of the undirected ``edges`` (u, v) and the least node it reaches.

    Alternating star contraction over links (v, u) with u < v; each round is written to the shared folder.
    """
    now = Stored(spark, edges.select(F.greatest("u", "v").alias("v"), F.least("u", "v").alias("u")).where("u <> v").distinct(), "links")
    seen = None
    for _ in range(rounds):
        # larger neighbours of u go to u's least neighbour; only nodes with a smaller neighbour have another than themselves
        least = now.df.groupBy(F.col("v").alias("u")).agg(F.min("u").alias("m"))
        large = Stored(spark, spread_join(now.df, least, "u").select("v", F.coalesce("m", "u").alias("u")).distinct(), "links")
        # now every node hangs on smaller ones: bring them under the least of these
        least = large.df.groupBy("v").agg(F.min("u").alias("m"))
        small = spread_join(large.df, least, "v").select(F.when(F.col("u") == F.col("m"), F.col("v")).otherwise(F.col("u")).alias("v"), F.col("m").alias("u")).where("u <> v").distinct()
        nxt = Stored(spark, small, "links")
        state = nxt.df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        now.drop()
        large.drop()
        now = nxt
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError(f"star contraction did not settle in {rounds} rounds")
    stars = now.df.groupBy("v").agg(F.min("u").alias("c"))
    out = Stored(spark, stars, "components")
    now.drop()
    return out


_PAIR = "u long, v long"
_NO_PAIRS = pa.table({"u": pa.array([], pa.int64()), "v": pa.array([], pa.int64())})


def _deal(buckets: int, percent: int = 80):
    """Send each representative's sketch to the bucket of each of its first-collection tuples."""

    def run(batches):
        for batch in batches:
            m = len(batch)
            if not m:
                continue
            rep, n = (batch.column(c).to_numpy() for c in ("rep", "n"))
            sides = [np.asarray(batch.column(c).values.to_numpy())[batch.column(c).offsets[0].as_py() : batch.column(c).offsets[-1].as_py()].reshape(m, -1) for c in ("left", "right")]
            to = (sides[0].view(np.uint64) % _U(buckets)).astype(np.int64)
            small = np.hstack(sides).view(np.uint64).astype(np.uint32)
            apart, least, most, loose, pairs = _thin(rep, n.astype(np.int64), small, percent)
            outs, blocks = [], []
            if len(pairs):
                outs.append(int(len(pairs) % buckets))
                blocks.append(b"D" + K.pack(*pairs.T))
            for b in np.unique(to[apart]).tolist():
                row, group = np.nonzero((to == b) & apart)
                outs.append(b)
                blocks.append(b"E" + K.pack(rep[row], least[row, group].astype(np.uint32), most[row, group].astype(np.uint32), loose[row, group], group.astype(np.uint8), *small[row].T))
            yield pa.RecordBatch.from_arrays([pa.array(outs, pa.int32()), pa.array(blocks, pa.binary())], names=["bucket", "block"])

    return run


def _thin(rep: np.ndarray, n: np.ndarray, sketch: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Crowds of one batch leave their heads and the loosely tied.

    By row and meeting: whether it still goes there, the least and the largest size it stands for,
    and the most tuples in which such a member differs from it; then the links made.
    """
    groups = sketch.shape[1] // 2
    apart = np.ones((len(rep), groups), bool)
    least, most = (np.repeat(n[:, None], groups, 1) for _ in range(2))
    loose = np.zeros((len(rep), groups), np.uint8)
    pairs = []
    for i in range(groups):
        order = np.lexsort((rep, sketch[:, i]))
        own = sketch[order, i]
        first = np.flatnonzero(np.append(True, own[1:] != own[:-1]))
        size = np.diff(np.append(first, len(order)))
        for a, m in zip(first[size > CROWD].tolist(), size[size > CROWD].tolist()):
            open_ = _by_center(order[a : a + m], rep, sketch, groups)
            for _ in range(HEADS):
                if len(open_) < 2:
                    break
                head, rest = open_[0], open_[1:]
                same = (sketch[rest] == sketch[head]).sum(1)
                near = (same >= TIGHT) & _fit_sizes(n[rest], n[head], percent)
                apart[rest[near], i] = False
                least[head, i] = n[rest[near]].min(initial=n[head])
                most[head, i] = n[rest[near]].max(initial=n[head])
                loose[head, i] = 2 * groups - same[near].min(initial=2 * groups)
                pairs.append(np.stack([np.full(int(near.sum()), rep[head]), rep[rest[near]]], 1))
                open_ = rest[~near]
    made = np.unique(np.concatenate(pairs), axis=0) if pairs else np.zeros((0, 2), np.int64)
    return apart, least, most, loose, made


def _by_center(rows: np.ndarray, rep: np.ndarray, sketch: np.ndarray, groups: int, all_rows: bool = False) -> np.ndarray:
    """Rows of a meeting that share a table with another (or ``all_rows``), most central first."""
    central = np.zeros(len(rows), np.int64)
    for j in range(groups):
        _, at, count = np.unique(sketch[rows, groups + j], return_inverse=True, return_counts=True)
        central += count[at]
    order = np.lexsort((rep[rows], -central))
    return rows[order if all_rows else order[central[order] > groups]]


def _meetings(table: pa.Table, groups: int):
    """Runs of rows that share a first-collection tuple: (rep, (least, most, loose), sketch matrix) of two or more."""
    parts = [K.unpack(x[1:]) for x in table.column("block").to_pylist() if x[:1] == b"E"]
    if not parts:
        return
    rep, least, most, loose, group = (np.concatenate([p[k] for p in parts]) for k in range(5))
    sketch = np.stack([np.concatenate([p[5 + k] for p in parts]) for k in range(2 * groups)], 1)
    own = sketch[np.arange(len(rep)), group]
    order = np.lexsort((rep, own, group))
    g, o = group[order], own[order]
    first = np.flatnonzero(np.append(True, (g[1:] != g[:-1]) | (o[1:] != o[:-1])))
    for a, b in zip(first.tolist(), [*first[1:].tolist(), len(order)]):
        if b - a > 1:
            at = order[a:b]
            yield rep[at], (least[at].astype(np.int64), most[at].astype(np.int64), loose[at].astype(np.int64)), sketch[at]


def _fit_sizes(n1: np.ndarray, n2: np.ndarray, percent: int) -> np.ndarray:
    """Sizes that allow 100 * intersection >= percent * union."""
    return 100 * np.minimum(n1, n2) >= percent * np.maximum(n1, n2)


def _out(us: list, vs: list) -> pa.Table:
    if not us:
        return _NO_PAIRS
    u, v = np.concatenate(us), np.concatenate(vs)
    pair = np.unique(np.stack([np.minimum(u, v), np.maximum(u, v)], 1), axis=0)
    pair = pair[pair[:, 0] != pair[:, 1]]
    return pa.table({"u": pa.array(pair[:, 0]), "v": pa.array(pair[:, 1])})


class _Forest:
    """Union-find over row numbers that remembers the unions made."""

    def __init__(self, m: int):
        self.up = np.arange(m)
        self.edges: list[tuple[int, int]] = []

    def find(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = int(self.up[x])
        return x

    def labels(self) -> np.ndarray:
        while True:
            top = self.up[self.up]
            if (top == self.up).all():
                return top
            self.up = top

    def join(self, x: int, others: np.ndarray) -> None:
        a = self.find(x)
        for y in others.tolist():
            b = self.find(y)
            if a != b:
                self.up[max(a, b)] = min(a, b)
                a = min(a, b)
                self.edges.append((x, y))


def _forests(groups: int, percent: int):
    """Spanning forests of the candidate pairs of each meeting."""

    def run(table: pa.Table) -> pa.Table:
        us, vs = [], []
        for block in table.column("block").to_pylist():
            if block[:1] == b"D":
                u, v = K.unpack(block[1:])
                us.append(u)
                vs.append(v)
        for rep, n, sketch in _meetings(table, groups):
            forest = _Forest(len(rep))
            wide = np.flatnonzero(n[2])
            open_ = _by_center(np.arange(len(rep)), rep, sketch, groups, len(wide) > 0)
            rows = np.sort(open_)
            for _ in range(HEADS):
                if len(open_) < 2:
                    break
                head, rest = open_[0], open_[1:]
                hit = _candidates(head, rest, n, sketch, groups, percent)
                forest.join(int(head), rest[hit])
                open_ = rest[~hit]
            for x in wide.tolist():  # what they accept may share no further tuple
                top = forest.labels()
                rest = np.flatnonzero(top != top[x])
                if len(rest):
                    forest.join(x, rest[_candidates(x, rest, n, sketch, groups, percent)])
            _agreeing(rows, n, forest, sketch, groups, percent, ())
            if forest.edges:
                e = np.array(forest.edges)
                us.append(rep[e[:, 0]])
                vs.append(rep[e[:, 1]])
        return _out(us, vs)

    return run


def _candidates(x: int, rest: np.ndarray, n: tuple[np.ndarray, np.ndarray, np.ndarray], sketch: np.ndarray, groups: int, percent: int) -> np.ndarray:
    """Which of ``rest``, all of one meeting, share a table with x, agree in AGREE tuples, and have a size that allows a link.

    A row answers for the members it stands for: one that differs from it in ``loose`` tuples may have so many
    more in common with the other side, and its table with it.
    """
    least, most, loose = n
    same = sketch[rest] == sketch[x]
    apart = loose[rest] + loose[x]
    table = same[:, :groups].any(1) & same[:, groups:].any(1)
    size = (100 * most[x] >= percent * least[rest]) & (100 * most[rest] >= percent * least[x])
    return (same.sum(1) >= AGREE - apart) & (table | (apart > 0)) & size


def _agreeing(rows: np.ndarray, n: tuple[np.ndarray, np.ndarray, np.ndarray], forest: _Forest, sketch: np.ndarray, groups: int, percent: int, used: tuple[int, ...]) -> None:
    """Join what the heads left apart: candidates of different trees among ``rows``."""
    label = forest.labels()[rows]
    if len(rows) < 2 or (label == label[0]).all():
        return
    if len(rows) > DIRECT and len(used) < 3:
        # one more tuple: a pair at 0.8 shares each of the others with chance 0.64
        for c in range(sketch.shape[1]):
            if c in used:
                continue
            order = rows[np.argsort(sketch[rows, c], kind="stable")]
            value = sketch[order, c]
            first = np.flatnonzero(np.append(True, value[1:] != value[:-1]))
            for a, b in zip(first.tolist(), [*first[1:].tolist(), len(order)]):
                if b - a > 1:
                    _agreeing(order[a:b], n, forest, sketch, groups, percent, (*used, c))
        return
    names, at, size = np.unique(label, return_inverse=True, return_counts=True)
    minor = rows[at != size.argmax()]  # pairs inside the largest tree are joined already
    for x in minor.tolist():
        top = forest.labels()
        rest = rows[top[rows] != top[x]]
        if len(rest):
            forest.join(x, rest[_candidates(x, rest, n, sketch, groups, percent)])


def linked(sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """A spanning forest of the links among full sets (sorted distinct hashes), exactly."""
    m = len(sets)
    size = np.fromiter(map(len, sets), np.int64, m)
    flat = np.concatenate(sets) if m else np.zeros(0, np.uint64)
    order = np.argsort(flat, kind="stable")
    owner = np.repeat(np.arange(m), size)[order]
    flat = flat[order]
    forest = _Forest(m)

    def count(x: int) -> None:
        lo, hi = np.searchsorted(flat, sets[x]), np.searchsorted(flat, sets[x], "right")
        shared = np.bincount(owner[K.ragged(lo, hi - lo)], minlength=m)
        hit = np.flatnonzero(100 * shared >= percent * (size + size[x] - shared))
        forest.join(x, hit[hit != x])

    # a head is found by its neighbours: start with the sets whose shingles most others hold
    lo, hi = np.searchsorted(flat, flat), np.searchsorted(flat, flat, "right")
    common = np.bincount(owner, hi - lo, m) / np.maximum(size, 1)
    done = np.zeros(m, bool)
    for x in np.argsort(-common, kind="stable")[:HEADS].tolist():
        count(x)
        done[x] = True
    label = forest.labels()
    largest = np.bincount(label, minlength=m).argmax()
    for x in np.flatnonzero((label != largest) & ~done).tolist():
        count(x)
    return forest.edges


_PLACED_DDL = "cluster long, block int, rep long, head boolean, items binary"
_PLACED = pa.schema([("cluster", pa.int64()), ("block", pa.int32()), ("rep", pa.int64()), ("head", pa.bool_()), ("items", pa.binary())])


def _place(width: int):
    """A compressed text becomes its set, in the block of its cluster that its id falls into."""

    def run(batches):
        for batch in X.small_batches(batches):
            out: list[list] = [[] for _ in range(5)]
            cols = [batch.column(c).to_pylist() for c in ("rep", "s1", "s2", "cluster", "blocks", "head", "n_raw")]
            for k, (rep, s1, s2, cluster, blocks, head, size) in enumerate(zip(*cols)):
                raw = np.frombuffer(X.unpack_text(batch.column("packed")[k].as_py(), size), np.uint8)
                one = next(shingle_sets(raw, np.array([0, len(raw)]), width))
                if _identity(one) != (s1, s2):
                    continue
                block = int(K.mix(np.array([rep], np.int64).view(np.uint64))[0] % _U(blocks)) if blocks > 1 else -1
                for c, v in zip(out, (cluster, block, rep, head, one.tobytes())):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out, _PLACED)], schema=_PLACED)

    return run


def _sets(table: pa.Table) -> tuple[np.ndarray, list[np.ndarray]]:
    """Distinct (rep, set) of some rows; an id may stand for several sets."""
    order = np.argsort(table.column("rep").to_numpy(), kind="stable").tolist()
    ids, items = table.column("rep"), table.column("items")
    own = dict.fromkeys((ids[i].as_py(), items[i].as_py()) for i in order)
    return np.array([k for k, _ in own], np.int64), [np.frombuffer(x, np.uint64) for _, x in own]


def _settle_cluster(percent: int):
    """Links inside a cluster of one block."""

    def run(table: pa.Table) -> pa.Table:
        rep, sets = _sets(table)
        edges = linked(sets, percent)
        if not edges:
            return _NO_PAIRS
        e = np.array(edges)
        return _out([rep[e[:, 0]]], [rep[e[:, 1]]])

    return run


def _settle_guests(percent: int):
    """Links between the sets of a block and guests that visit every block of their cluster (``head``)."""

    def run(table: pa.Table) -> pa.Table:
        guest = table.column("head").to_numpy(zero_copy_only=False)
        rep, sets = _sets(table.filter(pa.array(~guest)))
        guests, their = _sets(table.filter(pa.array(guest)))
        m = len(sets)
        size = np.fromiter(map(len, sets), np.int64, m)
        flat = np.concatenate(sets) if m else np.zeros(0, np.uint64)
        order = np.argsort(flat, kind="stable")
        owner = np.repeat(np.arange(m), size)[order]
        flat = flat[order]
        us, vs = [], []
        for who, one in zip(guests.tolist(), their):
            lo, hi = np.searchsorted(flat, one), np.searchsorted(flat, one, "right")
            shared = np.bincount(owner[K.ragged(lo, hi - lo)], minlength=m)
            hit = np.flatnonzero(100 * shared >= percent * (size + len(one) - shared))
            us.append(np.full(len(hit), who))
            vs.append(rep[hit])
        return _out(us, vs)

    return run


def _visit(sets: DataFrame, guests: DataFrame, percent: int, few: bool) -> DataFrame:
    """Links of ``guests`` (cluster, blocks, rep, items) with all sets (_PLACED) of their clusters.

    Unless they are ``few``, guests come in parties of about PARTY.
    """
    party = F.lit(0)
    sets = sets.select("cluster", "block", "rep", F.lit(False).alias("head"), "items")
    if few:
        sets = sets.withColumn("party", party)
    else:
        parties = guests.groupBy("cluster").agg(F.ceil(F.count("*") / PARTY).alias("parties"))
        sets = spread_join(sets, parties, "cluster").where("parties > 0").withColumn("party", F.explode(F.sequence(F.lit(0), (F.col("parties") - 1).cast("int")))).drop("parties")
        guests = spread_join(guests, parties, "cluster")
        party = F.pmod(F.xxhash64("rep"), F.col("parties")).cast("int")
    block = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    everywhere = guests.withColumn("party", party).select("cluster", block.alias("block"), "rep", F.lit(True).alias("head"), "items", "party")
    return sets.unionByName(everywhere).groupBy("cluster", "block", "party").applyInArrow(_settle_guests(percent), _PAIR)


def _heads(members: DataFrame, forests: DataFrame) -> DataFrame:
    """(rep): the HEADS members (cluster, rep) of each cluster with most candidate links."""
    degree = forests.select(F.col("u").alias("rep")).union(forests.select("v")).groupBy("rep").agg(F.count("*").alias("k"))
    some = members.join(degree, "rep").withColumn("salt", F.pmod(F.xxhash64("rep"), F.lit(16)))
    for by in (["cluster", "salt"], ["cluster"]):  # the few best of each part, then of all
        w = Window.partitionBy(*by).orderBy(F.desc("k"), "rep")
        some = some.withColumn("r", F.row_number().over(w)).where(F.col("r") <= HEADS)
    return some.select("rep", F.lit(True).alias("head"))


def _confirmed(docs: DataFrame, reps: DataFrame, forests: DataFrame, width: int, percent: int, keep: list[Stored]) -> DataFrame:
    """Links (u, v) that connect all components of each candidate cluster, confirmed on full sets."""
    spark = docs.sparkSession

    def hold(df: DataFrame, tag: str) -> DataFrame:
        keep.append(Stored(spark, df, tag))
        return keep[-1].df

    found = components(forests, spark)
    keep.append(found)
    named = found.df.select(F.col("v").alias("rep"), F.col("c").alias("cluster")).union(found.df.select("c", "c").distinct())
    named = hold(named.join(reps.select("rep", "n", "s1", "s2"), "rep"), "named")
    size = F.least(F.ceil(F.sum("n") / BLOCK), F.ceil(F.count("*") / BLOCK_SETS))
    blocks = named.groupBy("cluster").agg(F.greatest(size, F.lit(1)).cast("int").alias("blocks"))
    wanted = hold(spread_join(named, blocks, "cluster").select("rep", "s1", "s2", "cluster", "blocks"), "wanted")
    large = wanted.where("blocks > 1").select("cluster", "blocks", "rep").distinct()
    asked = wanted.join(_heads(large, forests), "rep", "left").withColumn("head", F.coalesce("head", F.lit(False)))
    # one plan at every size: a broadcast of few ids now would hide the shuffle of many later
    texts = X.pack_texts(docs).where("packed IS NOT NULL")
    asked = texts.join(asked.hint("merge"), F.col("doc_id") == F.col("rep")).select("rep", "s1", "s2", "cluster", "blocks", "head", "packed", "n_raw")
    placed = hold(asked.mapInArrow(_place(width), _PLACED_DDL), "sets")
    single = placed.where("block < 0").groupBy("cluster").applyInArrow(_settle_cluster(percent), _PAIR)
    large = hold(large, "large")
    if large.isEmpty():
        return single
    many = placed.where("block >= 0")
    by_id = large.select("rep", "blocks")
    first = hold(_visit(many, many.where("head").join(by_id, "rep"), percent, True), "links")
    # what the heads left outside the largest component of its cluster visits all blocks
    comp = components(first, spark)
    keep.append(comp)
    label = large.join(comp.df.withColumnRenamed("v", "rep"), "rep", "left").select("cluster", "blocks", "rep", F.coalesce("c", "rep").alias("c"))
    label = hold(label, "label")
    count = label.groupBy("cluster", "c").agg(F.count("*").alias("k"))
    top = count.groupBy("cluster").agg(F.max(F.struct("k", "c")).alias("t")).select("cluster", F.col("t.c").alias("top"))
    open_ = hold(spread_join(label, top, "cluster").where("c <> top").select("rep", "blocks").distinct(), "open")
    guests = hold(many.join(open_, "rep"), "guests")
    return single.union(first).union(_visit(many, guests, percent, False))


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, groups: int = GROUPS, rows: int = ROWS) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row."""
    spark = docs.sparkSession
    docs = docs.select("doc_id", "text")
    sketch = Stored(spark, docs.mapInArrow(_sketch(width, groups, rows), "doc_id long, n_shingles long, s1 long, s2 long, left array<long>, right array<long>"), "sketch")
    whole = sketch.df.where("n_shingles > 0 AND doc_id IS NOT NULL")
    reps = Stored(spark, whole.groupBy("s1", "s2").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n"), F.first("left").alias("left"), F.first("right").alias("right")), "reps")
    buckets = bucket_count(docs, 4 << 20, least=16)
    dealt = reps.df.select("rep", "n", "left", "right").mapInArrow(_deal(buckets, percent), "bucket int, block binary")
    forests = Stored(spark, dealt.groupBy("bucket").applyInArrow(_forests(groups, percent), _PAIR), "forests")
    keep = [sketch, reps, forests]
    comp = components(_confirmed(docs, reps.df, forests.df, width, percent, keep), spark)
    keep.append(comp)
    label = reps.df.select("s1", "s2", "rep").join(comp.df.withColumnRenamed("v", "rep"), "rep", "left").select("s1", "s2", F.coalesce("c", "rep").alias("component_id"))
    out = sketch.df.select("doc_id", "n_shingles", "s1", "s2").join(label, ["s1", "s2"], "left")
    cid = F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("component_id")).otherwise(F.col("doc_id"))
    out = Stored(spark, out.select("doc_id", "n_shingles", cid.alias("component_id"), F.coalesce(F.col("doc_id") == cid, F.lit(True)).alias("kept")), "components")
    for table in keep:
        table.drop()
    return out.df


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` without the near-copies: the document that names its group stays, in its own columns.

    Rows that repeat a doc_id all stay or all go.
    """
    name = free_name(docs, "gone")
    gone = near_duplicates(docs, width, percent).where("NOT kept").select(F.col("doc_id").alias(name)).distinct()
    gone = Stored(docs.sparkSession, gone, "gone").df  # with a known size, Spark decides on a broadcast
    return docs.join(gone, F.col("doc_id") == F.col(name), "left_anti")
