"""Numpy kernels shared by tasks: distances, block top-k, local clustering and local graph walks.

All comparisons that reach a result are made in double precision and break ties
by id.  A matrix product only makes a shortlist, which is then scored again.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

SPARE = 8


def matrix(col: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """A list column as an (m, n) double matrix; rows must have one length."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if not len(col):
        return np.zeros((0, 0))
    off = np.asarray(col.offsets)
    flat = np.asarray(col.values, dtype=np.float64)[off[0] : off[-1]] if not col.values.null_count else col.values.to_numpy(zero_copy_only=False).astype(np.float64)[off[0] : off[-1]]
    return flat.reshape(len(col), -1)


def lists(x: np.ndarray) -> pa.ListArray:
    m, n = x.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(m + 1, dtype=np.int32) * n), pa.array(np.ascontiguousarray(x, np.float64).ravel()))


def unit(x: np.ndarray) -> np.ndarray:
    norm = np.sqrt((x * x).sum(-1, keepdims=True))
    return x / np.where(norm > 0, norm, 1.0)


def distance(q: np.ndarray, x: np.ndarray, metric: str, p: float = 3.0) -> np.ndarray:
    """Exact row-wise distances of broadcastable vectors."""
    if metric == "l2":
        return np.sqrt(((q - x) ** 2).sum(-1))
    if metric == "cosine":
        top = (q * x).sum(-1)
        return 1.0 - top / np.sqrt((q * q).sum(-1) * (x * x).sum(-1))
    if metric == "l1":
        return np.abs(q - x).sum(-1)
    if metric == "chebyshev":
        return np.abs(q - x).max(-1)
    if metric == "minkowski":
        return (np.abs(q - x) ** p).sum(-1) ** (1 / p)
    if metric == "hamming":
        return (q != x).sum(-1).astype(np.float64)
    raise ValueError(f"unknown metric {metric}")


def rough(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    """All pairs; by one matrix product where the metric allows it."""
    if metric == "l2":
        d = (q * q).sum(1)[:, None] + (x * x).sum(1)[None, :] - 2.0 * (q @ x.T)
        return np.sqrt(np.maximum(d, 0.0))
    if metric == "cosine":
        return 1.0 - unit(q) @ unit(x).T
    out = np.empty((len(q), len(x)))
    for a in range(0, len(q), TILE[0]):
        for b in range(0, len(x), TILE[1]):
            out[a : a + TILE[0], b : b + TILE[1]] = _by_coordinate(q[a : a + TILE[0]], x[b : b + TILE[1]], metric)
    return out


#: Queries and rows whose distances stay in a core's cache while the coordinates are added up.
TILE = 32, 1024


def _by_coordinate(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    out = np.zeros((len(q), len(x)))
    t = np.empty_like(out)
    for a, b in zip(np.ascontiguousarray(q.T), np.ascontiguousarray(x.T)):
        if metric == "hamming":
            out += np.not_equal(a[:, None], b[None], out=t)
            continue
        np.abs(np.subtract(a[:, None], b[None], out=t), out=t)
        if metric == "chebyshev":
            np.maximum(out, t, out=out)
        elif metric == "l1":
            out += t
        elif metric == "minkowski":  # of order 3, as ``distance`` has it unless told otherwise
            out += t * t * t
        else:
            raise ValueError(f"unknown metric {metric}")
    return np.cbrt(out) if metric == "minkowski" else out


#: Of one coordinate of all pairs; ``fold`` adds these coordinate by coordinate, as the columns of ``metrics`` do, so both give the same bits.
TERMS = {
    "l2": lambda x, y: np.square(x - y),
    "l2_sq": lambda x, y: np.square(x - y),
    "dot": lambda x, y: x * y,
    "cosine": lambda x, y: x * y,
    "l1": lambda x, y: np.abs(x - y),
    "chebyshev": lambda x, y: np.abs(x - y),
    "hamming": lambda x, y: x != y,
}


def fold(q: np.ndarray, x: np.ndarray, metric: str) -> np.ndarray:
    """(len(q), len(x)) exact values of all pairs, every sum from the first coordinate to the last; masked beside a zero vector under cosine."""
    term, out = TERMS[metric], np.zeros((len(q), len(x)))
    with np.errstate(all="ignore"):
        for a, b in zip(np.ascontiguousarray(q.T), np.ascontiguousarray(x.T)):
            t = term(a[:, None], b[None])
            (np.maximum if metric == "chebyshev" else np.add)(out, t, out=out)
        if metric == "l2":
            return np.sqrt(out)
        if metric != "cosine":
            return out
        norms = [np.sqrt(np.cumsum(m * m, 1)[:, -1]) for m in (q, x)]
        both = norms[0][:, None] * norms[1][None]
        return np.ma.masked_array(1.0 - out / both, both == 0)


def positive(x: np.ndarray) -> np.ndarray:
    """Where a coordinate is above zero; NaN is above everything, as in SQL."""
    return (x > 0) | np.isnan(x)


def sign_bits(x: np.ndarray) -> np.ndarray:
    """Signs of up to 63 coordinates in one number for each row."""
    return positive(x).astype(np.int64) @ (1 << np.arange(x.shape[1], dtype=np.int64)[::-1])


def round_half_up(x: np.ndarray, digits: int) -> np.ndarray:
    """Rounded away from zero at a half, by a product and a quotient as DuckDB does; what is too large to have such digits stays."""
    mask, x = np.ma.getmask(x), np.ma.getdata(x)
    with np.errstate(all="ignore"):
        y = np.copysign(np.floor(np.abs(x) * 10.0**digits + 0.5) / 10.0**digits, x)
    y = np.where(np.abs(x) < 2.0**52 / 10.0**digits, y, x)
    return y if mask is np.ma.nomask else np.ma.masked_array(y, mask)


def block_topk(q: np.ndarray, x: np.ndarray, ids: np.ndarray, k: int, metric: str, farthest: bool = False, allowed: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, id, distance): at most k best rows of x for each q, by (distance, id) or (-distance, id).

    ``allowed`` (rows of q, rows of x) leaves the other pairs out.
    """
    m = len(x)
    if not len(q) or not m or k <= 0:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(0)
    rows, found, dist = [], [], []
    sign = -1.0 if farthest else 1.0
    for a in range(0, len(q), 256):
        part = q[a : a + 256]
        d = sign * rough(part, x, metric)
        ok = None if allowed is None else allowed[a : a + 256]
        if ok is not None:
            d[~ok] = np.inf
        take = min(m, k + SPARE)
        if take < m:
            short = np.argpartition(d, take - 1, axis=1)[:, :take]
            # rows level with the cut within rounding join the shortlist
            edge = np.take_along_axis(d, short, 1).max(1)
            close = d <= (edge + 1e-9 * (1 + np.abs(edge)))[:, None]
            np.put_along_axis(close, short, True, 1)
        else:
            close = np.ones((len(part), m), bool)
        row, pick = np.nonzero(close if ok is None else close & ok)
        exact = np.concatenate([np.zeros(0), *[distance(part[row[c : c + 8192]], x[pick[c : c + 8192]], metric) for c in range(0, len(row), 8192)]])
        order = np.lexsort((ids[pick], sign * exact, row))
        row, pick, exact = row[order], pick[order], exact[order]
        first = np.flatnonzero(np.append(True, row[1:] != row[:-1])) if len(row) else np.zeros(0, np.int64)
        keep = np.arange(len(row)) - np.repeat(first, np.diff(np.append(first, len(row)))) < k
        rows.append(a + row[keep])
        found.append(ids[pick[keep]])
        dist.append(exact[keep])
    return np.concatenate(rows), np.concatenate(found), np.concatenate(dist)


#: Queries and rows of one product in ``Best``, and rows that give its first bounds.
STRIP = 512, 2048
FIRST = 512


class Best:
    """The best k rows of each query, by (distance, id) or (-distance, id), as blocks of rows come by.

    Once a query has k rows, others must reach its k-th: a product in single precision, with its rounding
    allowed for, leaves few of them open, and these are scored in double precision.
    """

    def __init__(self, qid: np.ndarray, q: np.ndarray, k: int, metric: str, farthest: bool = False, exclude_self: bool = False):
        self.qid, self.q, self.k, self.metric, self.exclude_self = qid, q, k, metric, exclude_self
        self.sign = -1.0 if farthest else 1.0
        self.d = np.full((len(q), k), np.nan)
        self.ids = np.full((len(q), k), np.iinfo(np.int64).max)
        self.fast = metric in ("l2", "cosine") and bool(len(q)) and k > 0
        if self.fast:
            self.middle = q.mean(0) if metric == "l2" else 0.0
            self.norm, self.side = self._side(q)
            self.side[:, -1] = 1.0
            self.side *= self.sign
            self.single = self.side.astype(np.float32)
            self.fast = self._plain(self.norm)

    def _side(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Norms, and vectors with one number more: products of two sides are (|q|^2 - d^2) / 2 or 1 - d."""
        x = x - self.middle if self.metric == "l2" else unit(x)
        square = (x * x).sum(1)
        return np.sqrt(square), np.concatenate([x, (-0.5 * square if self.metric == "l2" else np.zeros(len(x)))[:, None]], 1)

    def _plain(self, norm: np.ndarray) -> bool:
        """Nothing that single precision or a threshold cannot hold."""
        return bool((norm < 1e15).all()) and (self.metric == "l2" or bool((norm > 0.5).all()))

    def add(self, ids: np.ndarray, x: np.ndarray) -> None:
        if not len(x) or not len(self.q) or self.k <= 0:
            return
        fast, at = self.fast, 0
        if fast:
            norm, side = self._side(x)
            fast = self._plain(norm)
        with np.errstate(invalid="ignore"):
            if fast and not np.isfinite(self.d[:, -1]).all():
                at = min(FIRST, len(x))
                self._score_all(slice(0, len(self.q)), ids[:at], x[:at])
        single = side.astype(np.float32) if fast else None
        for a in range(0, len(self.q), STRIP[0]):
            part = slice(a, min(a + STRIP[0], len(self.q)))
            b = at
            while b < len(x):
                if not fast or not np.isfinite(self.d[part, -1]).all():
                    self._score_all(part, ids[b:], x[b:])
                    break
                end = min(len(x), b + min(STRIP[1], max(FIRST, b)))
                row, pick = self._within(part, single[b:end], side[b:end], float(norm[b:end].max()))
                self._score(a + row, ids, x, b + pick)
                b = end

    def _within(self, part: slice, single: np.ndarray, side: np.ndarray, top: float) -> tuple[np.ndarray, np.ndarray]:
        """(query, row) pairs that may reach the k-th distance of their query."""
        kth, norm, n = self.d[part, -1], self.norm[part], side.shape[1]
        if self.metric == "l2":
            square = kth * kth
            level, size = 0.5 * self.sign * (norm * norm - square), norm * top + 0.5 * top * top
            loose = 1e-12 * (norm * norm + square + size)
        else:  # 1 - d is the product; of the farthest, d - 1
            level, size = self.sign - kth, np.ones(len(kth))
            loose = 1e-12 * (2 + np.abs(kth))
        for q, x in ((self.single[part], single), (self.side[part], side)):
            eps = float(np.finfo(x.dtype).eps)
            least = (level - loose - eps * ((n + 8) * size + np.abs(level)) - 1e-30).astype(x.dtype)
            open_ = (q @ x.T) >= least[:, None]
            if np.count_nonzero(open_) * 8 < open_.size:
                break
        return np.divmod(np.flatnonzero(open_.ravel()), len(x))

    def _score(self, row: np.ndarray, ids: np.ndarray, x: np.ndarray, pick: np.ndarray) -> None:
        d = self.sign * np.concatenate([np.zeros(0), *[distance(self.q[row[c : c + 8192]], x[pick[c : c + 8192]], self.metric) for c in range(0, len(row), 8192)]])
        found, last = ids[pick], self.d[row, -1]
        keep = (d < last) | ((d == last) & (found < self.ids[row, -1]))
        self._merge(row[keep], found[keep], d[keep])

    def _score_all(self, part: slice, ids: np.ndarray, x: np.ndarray) -> None:
        row, found, d = block_topk(self.q[part], x, ids, self.k + self.exclude_self, self.metric, self.sign < 0)
        self._merge(part.start + row, found, self.sign * d)

    def _merge(self, row: np.ndarray, found: np.ndarray, d: np.ndarray) -> None:
        if self.exclude_self:
            keep = self.qid[row] != found
            row, found, d = row[keep], found[keep], d[keep]
        if not len(row):
            return
        some, at = np.unique(row, return_inverse=True)
        at = np.concatenate([np.repeat(np.arange(len(some)), self.k), at])
        found, d = np.concatenate([self.ids[some].ravel(), found]), np.concatenate([self.d[some].ravel(), d])
        order = np.lexsort((found, d, at))
        first = np.searchsorted(at[order], np.arange(len(some)))
        take = order[first[:, None] + np.arange(self.k)]
        self.ids[some], self.d[some] = found[take], d[take]

    def rows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query id, id, distance)."""
        row, place = np.nonzero(~np.isnan(self.d) | (self.ids != np.iinfo(np.int64).max))
        return self.qid[row], self.ids[row, place], self.sign * self.d[row, place]


# --- local clustering -------------------------------------------------------


def uniform(ids: np.ndarray, seed: int, turn: int) -> np.ndarray:
    """Numbers in (0, 1) that depend on the id alone, not on order or partition."""
    h = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64((seed * 1_000_003 + turn * 7919) & (2**63 - 1))
    h ^= h >> np.uint64(30)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return (h >> np.uint64(11)).astype(np.float64) / 2.0**53 + 1e-17


def seed_rows(x: np.ndarray, ids: np.ndarray, k: int, init: str, seed: int) -> np.ndarray:
    """Rows of x that start the clusters."""
    if init == "random":
        return np.lexsort((ids, uniform(ids, seed, 0)))[:k]
    first = int(np.argmin(ids)) if init == "farthest" else int(np.lexsort((ids, uniform(ids, seed, 0)))[0])
    chosen = [first]
    d = ((x - x[first]) ** 2).sum(1)
    for turn in range(1, min(k, len(x))):
        if d.max() <= 0:
            break
        if init == "farthest":
            pick = int(np.lexsort((ids, -d))[0])
        else:  # an exponential race: the winner is drawn in proportion to d
            with np.errstate(divide="ignore"):
                race = np.where(d > 0, -np.log(uniform(ids, seed, turn)) / d, np.inf)
            pick = int(np.lexsort((ids, race))[0])
        chosen.append(pick)
        d = np.minimum(d, ((x - x[pick]) ** 2).sum(1))
    return np.array(chosen)


def nearest(x: np.ndarray, centers: np.ndarray) -> np.ndarray:
    """Index of the nearest center by exact squared distance, lowest index on ties."""
    out = np.empty(len(x), np.int64)
    for a in range(0, len(x), 4096):
        part = x[a : a + 4096]
        d = (part * part).sum(1)[:, None] + (centers * centers).sum(1)[None] - 2 * part @ centers.T
        out[a : a + 4096] = d.argmin(1)
    return out


def kmeans(x: np.ndarray, ids: np.ndarray, k: int, iters: int, init: str = "d2", seed: int = 42, on_empty: str = "drop") -> tuple[np.ndarray, np.ndarray]:
    """(assignment, centers) after Lloyd rounds; empty clusters disappear, or begin anew at the ``farthest`` row."""
    centers = x[seed_rows(x, ids, k, init, seed)].copy()
    at = nearest(x, centers)
    columns = np.ascontiguousarray(x.T)
    for _ in range(iters):
        n = np.bincount(at, minlength=len(centers))
        sums = np.stack([np.bincount(at, weights=c, minlength=len(centers)) for c in columns], 1)  # row after row, as one loop would add
        keep = n > 0
        new = sums[keep] / n[keep][:, None]
        if on_empty == "farthest":
            for _ in range(len(centers) - len(new)):
                far = np.sqrt(((x - new[nearest(x, new)]) ** 2).sum(1))
                if far.max(initial=0.0) <= 0:
                    break
                new = np.concatenate([new, x[np.lexsort((ids, -far))[:1]]])
        centers = new
        new = nearest(x, centers)
        if len(keep) == len(centers) and (new == at).all():
            break
        at = new
    used, at = np.unique(at, return_inverse=True)
    return at, centers[used]


def split_all(x: np.ndarray, ids: np.ndarray, path: str, stop: int, fanout: int, iters: int, init: str, seed: int, depth: int | None = None, on_empty: str = "drop") -> tuple[list[tuple[str, np.ndarray, bool]], list[tuple[str, int, bool, bool]]]:
    """Split a part until every piece has at most ``stop`` rows.

    Returns the final pieces (path, rows, degenerate) and every part below and
    including ``path`` as (path, rows, final, degenerate).
    """
    pieces: list[tuple[str, np.ndarray, bool]] = []
    parts: list[tuple[str, int, bool, bool]] = []
    todo = [(path, np.arange(len(ids)), 0)]
    while todo:
        name, rows, level = todo.pop()
        if len(rows) <= stop or (depth is not None and level >= depth):
            pieces.append((name, rows, False))
            parts.append((name, len(rows), True, False))
            continue
        parts.append((name, len(rows), False, False))
        at, centers = kmeans(x[rows], ids[rows], min(fanout, len(rows)), iters, init, seed, on_empty)
        if len(centers) < 2:  # nothing tells these rows apart: chop them by id
            order = rows[np.argsort(ids[rows], kind="stable")]
            for c, a in enumerate(range(0, len(order), stop)):
                piece = order[a : a + stop]
                pieces.append((f"{name}.{c}", piece, True))
                parts.append((f"{name}.{c}", len(piece), True, True))
            continue
        todo += [(f"{name}.{c}", rows[at == c], level + 1) for c in range(len(centers))]
    return pieces, parts


# --- local graphs -------------------------------------------------------------


def refine(q: np.ndarray, seeds: np.ndarray, links: list[np.ndarray], x: np.ndarray, k: int, metric: str, farthest: bool = False) -> tuple[np.ndarray, np.ndarray, int, int]:
    """(rows, distances, hops, vectors seen): walk links from ``seeds`` until the best k stay the same.

    A row is unseen, seen, or expanded; only seen members of the current best k are expanded.
    """
    sign = -1.0 if farthest else 1.0
    state = np.zeros(len(x), np.int8)
    pool = np.unique(seeds)
    state[pool] = 1
    d = sign * distance(q, x[pool], metric)
    hops = 0
    while True:
        order = np.lexsort((pool, d))[:k]
        pool, d = pool[order], d[order]
        open_ = pool[state[pool] == 1]
        if not len(open_):
            return pool, sign * d, hops, int((state > 0).sum())
        hops += len(open_)
        state[open_] = 2
        new = np.unique(np.concatenate([links[v] for v in open_.tolist()])) if len(open_) else open_
        new = new[state[new] == 0]
        state[new] = 1
        pool = np.concatenate([pool, new])
        d = np.concatenate([d, sign * distance(q, x[new], metric)])


def best_first(q: np.ndarray, entry: list[int], links, x: np.ndarray, ef: int, metric: str, farthest: bool = False, trace: list[int] | None = None, known: list[float] | None = None) -> tuple[np.ndarray, np.ndarray, int, int]:
    """Candidate-list walk of width ``ef``: (rows, distances, hops, vectors seen); ``trace`` gets the rows whose links were read.

    ``known`` has the distances from q to all rows, where they were computed at once.
    """
    import heapq

    sign = -1.0 if farthest else 1.0
    seen = bytearray(len(x))
    start = list(zip(known_at(known, entry) if known is not None else distance(q, x[list(entry)], metric).tolist(), entry))
    for u in entry:
        seen[u] = 1
    todo = [(sign * d, e) for d, e in start]
    best = [(-d, -e) for d, e in todo]
    heapq.heapify(todo)
    heapq.heapify(best)
    hops = 0
    while todo:
        d, v = heapq.heappop(todo)
        if len(best) >= ef and d > -best[0][0]:
            break
        hops += 1
        if trace is not None:
            trace.append(v)
        fresh = [u for u in links[v] if not seen[u]]
        if not fresh:
            continue
        for u, du in zip(fresh, known_at(known, fresh) if known is not None else distance(q, x[fresh], metric).tolist()):
            seen[u] = 1
            du *= sign
            if len(best) < ef:
                heapq.heappush(todo, (du, u))
                heapq.heappush(best, (-du, -u))
            elif du < -best[0][0]:
                heapq.heappush(todo, (du, u))
                heapq.heapreplace(best, (-du, -u))
    out = sorted((-d, -u) for d, u in best)
    return np.array([u for _, u in out], np.int64), sign * np.array([d for d, _ in out]), hops, sum(seen)


def known_at(known, rows) -> list[float]:
    return [known[u] for u in rows]
