"""Numpy kernels over the raw UTF-8 buffers of Arrow string batches.

Words are maximal runs of bytes outside 0x20 and 0x09-0x0D.  A span's hash chains
its bytes, eight at a time, through a bijective finaliser, so a batch costs a
handful of vector operations and no Python object per word, and spans of at most
eight bytes and one length never collide.  Windows of words are Rabin-Karp polynomials
over word hashes, modulo 2**64 and, as a second opinion, modulo a prime.  Work proceeds in
segments: memory does not depend on the batch or on the length of one text.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SEGMENT = 1 << 18
_U = np.uint64
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
#: Bytes of the longest span that is hashed in place; longer ones are few per byte and go to hashlib one by one.
IN_PLACE = 512
_MASK = np.array([(1 << (8 * k)) - 1 for k in range(9)], np.uint64)
_WORD_BASE = 0xD1342543DE82EF9B
_PRIME, _PRIME_BASE = 2**31 - 1, 1_220_703_125
_tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n (base odd)."""
    have = _tables.get(base)
    if have is None or len(have[0]) < n:
        size = max(n, 1 << 16)
        both = []
        for b in (base, pow(base, -1, 1 << 64)):
            p = np.full(size, b, np.uint64)
            p[0] = 1
            both.append(np.multiply.accumulate(p))
        have = _tables[base] = (both[0], both[1])
    return have[0][:n], have[1][:n]


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective finaliser for 64-bit hashes."""
    h = h ^ (h >> _U(31))
    h = h * _U(0x7FB5D329728EA185)
    h ^= h >> _U(27)
    h *= _U(0x81DADEF4BC2DD44D)
    return h ^ (h >> _U(33))


def string_buffers(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; a null counts as an empty text."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if col.null_count:
        col = col.fill_null("")
    if not pa.types.is_large_string(col.type):
        col = col.cast(pa.large_string())
    n = len(col)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    off = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + n + 1]
    data = col.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


class Words:
    """Word hashes of a run of texts: ``hash[bound[i]:bound[i+1]]`` are text i's; ``check`` has second ones where asked for."""

    __slots__ = ("bound", "check", "end", "hash", "start")

    def __init__(self, hashes, start, end, bound, check=None):
        self.hash, self.start, self.end, self.bound, self.check = hashes, start, end, bound, check


def words(raw: np.ndarray, off: np.ndarray, lower: bool = False, space: np.ndarray = _SPACE, twice: bool = False) -> Words:
    """Hash every word; ``start``/``end`` are byte positions in ``raw``."""
    n = len(raw)
    edge = np.zeros(n + 1, bool)
    edge[off[(off >= 0) & (off <= n)]] = True
    space = space[raw]
    ink = ~space
    after = np.empty(n, bool)  # the byte before is a blank or another text's
    before = np.empty(n, bool)
    if n:
        after[0], after[1:] = True, space[:-1]
        before[-1], before[:-1] = True, space[1:]
        after |= edge[:-1]
        before |= edge[1:]
    start = np.flatnonzero(ink & after)
    end = np.flatnonzero(ink & before) + 1
    out = span_hashes(raw, start, end, lower)
    return Words(out, start, end, np.searchsorted(start, off), span_hashes(raw, start, end, lower, 1) if twice else None)


def _lower8(w: np.ndarray) -> np.ndarray:
    """A-Z lower-cased in each of the eight bytes."""
    low = w & _U(0x7F7F7F7F7F7F7F7F)
    upper = ((low + _U(0x3F3F3F3F3F3F3F3F)) ^ (low + _U(0x2525252525252525))) & ~w & _U(0x8080808080808080)
    return w | (upper >> _U(2))


def span_hashes(raw: np.ndarray, start: np.ndarray, end: np.ndarray, lower: bool = False, salt: int = 0) -> np.ndarray:
    """Hashes of byte spans; other salts give independent hashes."""
    out = np.empty(len(start), np.uint64)
    if not len(start):
        return out
    seed = _U(((salt + 1) * 0x9E3779B97F4A7C15) & (2**64 - 1))
    raw = np.ascontiguousarray(raw) if len(raw) >= 8 else np.concatenate([raw, np.zeros(8 - len(raw), np.uint8)])
    eight = np.ndarray((len(raw) - 7,), "<u8", raw, 0, (1,))  # the eight bytes from every place on
    top = len(raw) - 8
    for a in range(0, len(start), SEGMENT // 4):
        s, e = start[a : a + SEGMENT // 4], end[a : a + SEGMENT // 4]
        size = e - s
        h = mix(size.astype(np.uint64) * _U(0xD6E8FEB86659FD93) + seed)
        open_ = None  # all
        for k in range(0, min(int(size.max()), IN_PLACE), 8):
            if k:
                open_ = np.flatnonzero((size > k) & (size <= IN_PLACE))
                if not len(open_):
                    break
            at = (s if open_ is None else s[open_]) + k
            left = np.minimum((size if open_ is None else size[open_]) - k, 8)
            here = np.minimum(at, top)
            w = (eight[here] >> ((at - here) * 8).astype(np.uint64)) & _MASK[left]
            if lower:
                w = _lower8(w)
            if open_ is None:
                h = mix(h ^ w)
            else:
                h[open_] = mix(h[open_] ^ w)
        for k in np.flatnonzero(size > IN_PLACE).tolist():
            body = raw[s[k] : e[k]].tobytes()
            body = body.lower() if lower else body  # of bytes: A-Z alone
            h[k] = int.from_bytes(hashlib.blake2b(body, digest_size=8, salt=salt.to_bytes(8, "little")).digest(), "little")
        out[a : a + SEGMENT // 4] = h
    return out


def window_hashes(h: np.ndarray, width: int) -> np.ndarray:
    """Rabin-Karp hashes of all ``width`` consecutive words (text edges are the caller's)."""
    n = len(h) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.empty(n, np.uint64)
    step = SEGMENT
    for a in range(0, n, step):
        b = min(n, a + step)
        part = h[a : b + width - 1]
        up, down = powers(_WORD_BASE, len(part) + 1)
        total = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(part * up[:-1], out=total[1:])
        out[a:b] = mix((total[width:] - total[:-width]) * down[: b - a] + _U(width))
    return out


def window_checks(h: np.ndarray, width: int) -> np.ndarray:
    """Second Rabin-Karp hashes of the same windows, modulo a prime of 31 bits, from other word hashes."""
    n = len(h) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint32)
    out = np.empty(n, np.uint32)
    prime = _U(_PRIME)
    for a in range(0, n, SEGMENT):
        b = min(n, a + SEGMENT)
        part = (h[a : b + width - 1] >> _U(33)) % prime
        up, down = prime_powers(len(part) + 1)
        total = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(part * up[:-1] % prime, out=total[1:])
        out[a:b] = (total[width:] - total[:-width]) % prime * down[: b - a] % prime
    return out


def prime_powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the prime field's base and of its inverse."""
    have = _tables.get(_PRIME)
    if have is None or len(have[0]) < n:
        both = []
        for base in (_PRIME_BASE, pow(_PRIME_BASE, -1, _PRIME)):
            p = np.ones(1, np.uint64)
            while len(p) < n:  # doubling: the next half is the first, times base ** len
                p = np.concatenate([p, p * _U(pow(base, len(p), _PRIME)) % _U(_PRIME)])
            both.append(p)
        have = _tables[_PRIME] = (both[0], both[1])
    return have[0][:n], have[1][:n]


def sequence_hash(h: np.ndarray) -> int:
    """One hash for a whole word sequence of any length."""
    up, _ = powers(_WORD_BASE, len(h) + 1)
    return int(mix(np.array([(h * up[:-1]).sum(dtype=np.uint64) + _U(len(h))]))[0])


def slices(off: np.ndarray, most: int = 4 * SEGMENT) -> Iterator[tuple[int, int]]:
    """Runs [i, j) of texts of about ``most`` bytes together (one text at least)."""
    i, n = 0, len(off) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + most, "right")) - 1)
        yield i, min(j, n)
        i = j


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Indices of many slices one after another."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    shift = np.repeat(starts - (np.cumsum(lengths) - lengths), lengths)
    return np.arange(total, dtype=np.int64) + shift


# Integer arrays in few bytes: differences, packed small, behind a general codec.


def pack(*arrays: np.ndarray) -> bytes:
    """Arrays of integers as one compressed block (see ``unpack``)."""
    head, body = [len(arrays)], []
    for a in arrays:
        a = np.ascontiguousarray(a)
        head += [ord(a.dtype.char), len(a)]
        body.append(a.view(np.uint8).reshape(len(a), a.itemsize).T.tobytes() if len(a) else b"")
    flat = b"".join(body)
    lead = np.array([*head, len(flat)], np.int64).tobytes()
    return lead + (pa.compress(flat, codec="zstd", asbytes=True) if flat else b"")


def unpack(block: bytes | memoryview | pa.Buffer) -> list[np.ndarray]:
    block = memoryview(block)
    n = int(np.frombuffer(block, np.int64, 1)[0])
    head = np.frombuffer(block, np.int64, 2 * n + 2)
    size = int(head[-1])
    flat = pa.decompress(pa.py_buffer(block[8 * len(head) :]), size, codec="zstd") if size else b""
    out, at = [], 0
    for k in range(n):
        kind, length = np.dtype(chr(int(head[1 + 2 * k]))), int(head[2 + 2 * k])
        part = np.frombuffer(flat, np.uint8, kind.itemsize * length, at)
        out.append(np.ascontiguousarray(part.reshape(kind.itemsize, length).T).view(kind).reshape(length))
        at += kind.itemsize * length
    return out


def deltas(a: np.ndarray) -> np.ndarray:
    """First value, then differences, as int64."""
    return np.diff(a.astype(np.int64), prepend=np.int64(0))
