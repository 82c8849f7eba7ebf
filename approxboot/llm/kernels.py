"""Array kernels over batches of text: word hashes, shingles, gram hashes and sliding minima."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
#: Odd base of the polynomial hash and its inverse mod 2**64.
BASE = 0x9E3779B97F4A7C15 | 1
INVERSE = pow(BASE, -1, 1 << 64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


@lru_cache(maxsize=4)
def _powers(n: int, base: int) -> np.ndarray:
    out = np.full(n, base, U)
    out[0] = 1
    return np.multiply.accumulate(out)


def powers(n: int, base: int) -> np.ndarray:
    """base**0 ... base**(n-1) mod 2**64; grown in large steps and kept."""
    size = 1 << max(16, (n - 1).bit_length())
    return _powers(size, base)[:n]


@lru_cache(maxsize=2)
def _byte_values(fold: bool) -> np.ndarray:
    table = np.random.Generator(np.random.PCG64(20240101)).integers(0, 1 << 64, 256, dtype=U)
    if fold:
        table[65:91] = table[97:123]
    return table


def prefix_of(values: np.ndarray) -> np.ndarray:
    """P with P[j] - P[i] = sum of values[k] * BASE**k over i <= k < j."""
    out = np.zeros(len(values) + 1, U)
    np.cumsum(values * powers(len(values), BASE) if len(values) else out[:0], out=out[1:])
    return out


def prefix_hash(data: np.ndarray, fold: bool = False) -> np.ndarray:
    """prefix_of the values that stand for bytes; fold makes A-Z those of a-z."""
    return prefix_of(_byte_values(fold)[data])


def span_hash(prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of what stands in each span, wherever it lies."""
    return mix((prefix[ends] - prefix[starts]) * powers(len(prefix), INVERSE)[starts] + (ends - starts).astype(U) * U(0xD6E8FEB86659FD93))


def utf8(column: pa.Array, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of rows lo to hi of a string column, one after another, and where each begins (and the end); null is empty."""
    part = column.slice(lo, hi - lo).cast(pa.large_binary())
    if part.null_count:
        part = part.fill_null(b"")
    _, offsets, data = part.buffers()
    at = np.frombuffer(offsets, np.int64, len(part) + 1, part.offset * 8)
    if data is None:
        return np.zeros(0, np.uint8), np.zeros(len(part) + 1, np.int64)
    return np.frombuffer(data, np.uint8)[at[0] : at[-1]], at - at[0]


def byte_slices(column: pa.Array, limit: int = 500_000):
    """Ranges of rows whose bytes stay under limit, one row at least."""
    sizes = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)
    lo = size = 0
    for i, n in enumerate(sizes.tolist()):
        if size and size + n > limit:
            yield lo, i
            lo, size = i, 0
        size += n
    if lo < len(sizes):
        yield lo, len(sizes)


def _separators() -> np.ndarray:
    out = np.zeros(256, bool)
    out[[9, 10, 11, 12, 13, 32]] = True
    return out


SEPARATOR = _separators()


def words(data: np.ndarray, at: np.ndarray, fold: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, hashes, first word of each row and the number of all words) of blank-separated words, A-Z folded or not."""
    if not len(data):
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(0, U), np.zeros(len(at), np.int64)
    gap = SEPARATOR[data]
    edge = np.zeros(len(data) + 1, bool)
    edge[at] = True
    before = np.concatenate([[True], gap[:-1]]) | edge[:-1]
    after = np.concatenate([gap[1:], [True]]) | edge[1:]
    starts = np.flatnonzero(before & ~gap)
    ends = np.flatnonzero(after & ~gap) + 1
    hashes = span_hash(prefix_hash(data, fold), starts, ends)
    return starts, ends, hashes, np.searchsorted(starts, at)


def units(column: pa.Array, lo: int, hi: int, unit: str) -> tuple[np.ndarray, np.ndarray]:
    """Values that stand for the bytes, or the blank-separated words, of rows lo to hi, and where each row begins (and the end)."""
    data, at = utf8(column, lo, hi)
    if unit == "bytes":
        return _byte_values(False)[data], at
    _, _, hashes, first = words(data, at, False)
    return hashes, first


def gram_hashes(hashes: np.ndarray, n: int) -> np.ndarray:
    """Hash of the n words from each on; callers leave out those that cross a row's end."""
    if len(hashes) < n:
        return hashes[:0]
    m = len(hashes) - n + 1
    out = np.zeros(m, U)
    for i in range(n):
        out += hashes[i : i + m] * U(powers(64, BASE)[2 * i + 1])
    return mix(out)


def shingle_sets(data: np.ndarray, at: np.ndarray, n: int = 5) -> list[np.ndarray]:
    """Distinct shingle hashes of each row, ascending: of n words, or of all words where there are fewer, none without words."""
    _, _, hashes, first = words(data, at)
    grams = gram_hashes(hashes, n)
    out = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
        if b - a >= n:
            out.append(np.unique(grams[a : b - n + 1]))
        elif b > a:
            out.append(gram_hashes(hashes[a:b], b - a) ^ U(b - a))
        else:
            out.append(hashes[:0])
    return out


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of x[i : i + w] for each i, by minima from both ends of blocks of w."""
    n = len(x) - w + 1
    if n <= 0:
        return x[:0]
    top = np.iinfo(x.dtype).max
    padded = np.concatenate([x, np.full(-len(x) % w, top, x.dtype)]).reshape(-1, w)
    ahead = np.minimum.accumulate(padded, axis=1).ravel()
    behind = np.minimum.accumulate(padded[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[:n], ahead[w - 1 : w - 1 + n])
