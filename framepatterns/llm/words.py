"""Vectorised word hashing over Arrow string buffers.

Words are maximal runs of characters other than space and U+0009..U+000D.  A whole batch is hashed with numpy
(no Python object per word): bytes are mapped to random 64-bit values, summed with the powers of an odd
multiplier, and the sum of a word is a difference of prefix sums brought back to position zero.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_BLOCK = 1 << 18
_P = np.uint64(0x9E3779B97F4A7C15)
_P_INV = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_BYTE = np.random.default_rng(20240607).integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_STEP = np.random.default_rng(7).integers(1, 1 << 63, 64, dtype=np.uint64) | np.uint64(1)
#: A-Z to a-z.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_powers: list[np.ndarray] = [np.ones(1, dtype=np.uint64), np.ones(1, dtype=np.uint64)]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if _powers[0].size <= n:
        size = max(n + 1, _BLOCK + 1)
        for k, base in enumerate((_P, _P_INV)):
            t = np.full(size, base, dtype=np.uint64)
            t[0] = 1
            _powers[k] = np.multiply.accumulate(t)
    return _powers[0], _powers[1]


def _hash_bytes(b: np.ndarray, cuts: np.ndarray, fold: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of ``b`` and, for each cut position, the number of words before it."""
    n = b.size
    if fold is not None:
        b = fold[b]
    inside = ~((b == 32) | ((b >= 9) & (b <= 13)))
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    edge = cuts[(cuts > 0) & (cuts < n)]
    first[edge] = inside[edge]
    last[edge - 1] = inside[edge - 1]
    s, e = np.flatnonzero(first), np.flatnonzero(last) + 1
    up, down = _tables(n)
    total = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum(_BYTE[b] * up[:n], out=total[1:])
    h = mix((total[e] - total[s]) * down[s] + (e - s).astype(np.uint64))
    return h, np.searchsorted(s, cuts)


def string_buffers(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of an Arrow string column; null rows are empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if len(col) == 0 or col.type == pa.null():
        return np.zeros(0, np.uint8), np.zeros(len(col) + 1, np.int64)
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    raw = col.buffers()
    offs = np.frombuffer(raw[1], np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    data = np.frombuffer(raw[2], np.uint8) if raw[2] is not None else np.zeros(0, np.uint8)
    if col.null_count:  # a null slot may cover stray bytes
        keep = np.diff(offs) * np.asarray(col.is_valid())
        if keep.sum() != offs[-1] - offs[0]:
            return string_buffers(pa.array(["" if v is None else v for v in col.to_pylist()], pa.large_string()))
    return data, offs


def hashed_rows(col: pa.Array, lower: bool = False, block: int = _BLOCK, fold: np.ndarray | None = None) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Yield (first row, end row, word hashes, word offsets per row) for runs of rows of bounded size.

    ``lower`` folds A-Z; ``fold`` maps each byte value before words are cut (bytes below 128 only, for UTF-8).
    A row larger than ``block`` comes alone and is hashed piece by piece, cut at white space, so that working
    memory stays near 8 bytes a word however long the text is.
    """
    data, offs = string_buffers(col)
    fold = LOWER if fold is None and lower else fold
    row, rows = 0, len(offs) - 1
    while row < rows:
        end = int(np.searchsorted(offs, offs[row] + block, side="right")) - 1
        end = min(max(end, row + 1), rows)
        if offs[end] - offs[row] <= block:
            cuts = offs[row : end + 1] - offs[row]
            h, w = _hash_bytes(data[offs[row] : offs[end]], cuts, fold) if cuts[-1] else (np.zeros(0, np.uint64), np.zeros(end - row + 1, np.int64))
        else:
            parts, at, stop = [], int(offs[row]), int(offs[end])
            while at < stop:
                to = min(at + block, stop)
                while to < stop:
                    piece = data[to : min(to + 4096, stop)]
                    gap = np.flatnonzero((piece == 32) | ((piece >= 9) & (piece <= 13)))
                    if gap.size:
                        to += int(gap[0])
                        break
                    to = min(to + 4096, stop)
                parts.append(_hash_bytes(data[at:to], np.array([0, to - at]), fold)[0])
                at = to
            h = np.concatenate(parts)
            w = np.array([0, h.size])
        yield row, end, h, w
        row = end


def grams(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of the k consecutive words from each position; the last k - 1 positions have none."""
    n = h.size - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    if k > _STEP.size:  # long windows from their halves
        half = k // 2
        return mix(grams(h, half)[:n] * _STEP[0] + grams(h, k - half)[half : half + n] * _STEP[1])
    out = h[:n] * _STEP[0]
    for i in range(1, k):
        out += h[i : i + n] * _STEP[i]
    return mix(out)


def shingle_set(h: np.ndarray, k: int) -> np.ndarray:
    """Sorted distinct k-word shingles of one text; a shorter text is one shingle, an empty one has none."""
    if h.size >= k:
        g = np.sort(grams(h, k))
        return g[np.concatenate(([True], g[1:] != g[:-1]))]
    if h.size == 0:
        return np.zeros(0, np.uint64)
    return mix(grams(h, h.size) + np.uint64(h.size))


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum over each run of w neighbours, by doubling."""
    have = 1
    while have * 2 <= w:
        x = np.minimum(x[:-have], x[have:])
        have *= 2
    if have < w:
        x = np.minimum(x[: x.size - (w - have)], x[w - have :])
    return x
