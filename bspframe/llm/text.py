"""Vectorised text kernels shared by the Arrow-side operators of this subpackage.

A batch of texts is seen as one byte buffer. Words are runs of bytes outside
``[\\x20\\x09-\\x0D]`` with A-Z lower-cased; each gets a 64-bit hash from prefix sums of a
polynomial over the ring of 64-bit integers, so that no word becomes a Python object.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

U = np.uint64
#: Odd, so it has an inverse modulo 2**64.
BASE = 0x5851F42D4C957F2D
BASE_INV = pow(BASE, -1, 1 << 64)
#: Bytes hashed at once; bounds the working memory whatever a text's length.
WINDOW = 1 << 20
_powers: list[np.ndarray] = []


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**i and BASE**-i for i < n at least, modulo 2**64."""
    if not _powers or len(_powers[0]) < n:
        out = []
        for b in (BASE, BASE_INV):
            t = np.full(max(n, WINDOW + 1), b, dtype=U)
            t[0] = 1
            out.append(np.multiply.accumulate(t))
        _powers[:] = out
    return _powers[0], _powers[1]


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser, in place."""
    h ^= h >> U(30)
    h *= U(0xBF58476D1CE4E5B9)
    h ^= h >> U(27)
    h *= U(0x94D049BB133111EB)
    h ^= h >> U(31)
    return h


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, bounds) of a string column; a null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null(b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, off, data = column.buffers()
    bounds = np.frombuffer(off, dtype=kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8)[bounds[0] : bounds[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, bounds - bounds[0]


def words(raw: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every word, and for each text the index of its first word (one entry more at the end)."""
    hashes, starts_all, at, n = [], [], 0, len(raw)
    while at < n:
        end = min(at + WINDOW, n)
        if end < n:
            end = _cut(raw, bounds, at, end)
        low = raw[at:end]
        low = low + (((low >= 65) & (low <= 90)).view(np.uint8) << 5)
        inside = ~((low == 32) | ((low >= 9) & (low <= 13)))
        fresh = np.zeros(len(low) + 1, dtype=bool)
        fresh[0] = fresh[-1] = True
        a, b = np.searchsorted(bounds, (at, end), side="left")
        cuts = bounds[a:b] - at
        fresh[cuts] = True
        first = inside & fresh[:-1]
        first[1:] |= inside[1:] & ~inside[:-1]
        last = inside & fresh[1:]
        last[:-1] |= inside[:-1] & ~inside[1:]
        s, e = np.flatnonzero(first), np.flatnonzero(last) + 1
        up, down = powers(len(low) + 1)
        total = np.zeros(len(low) + 1, dtype=U)
        np.cumsum((low.astype(U) + U(1)) * up[: len(low)], out=total[1:])
        h = (total[e] - total[s]) * down[s]
        h += (e - s).astype(U) * U(0x9E3779B97F4A7C15)
        hashes.append(mix(h))
        starts_all.append(s + at)
        at = end
    if not hashes:
        return np.zeros(0, U), np.zeros(len(bounds), np.int64)
    return np.concatenate(hashes), np.searchsorted(np.concatenate(starts_all), bounds, side="left")


def _cut(raw: np.ndarray, bounds: np.ndarray, at: int, end: int) -> int:
    """A place near ``end`` where no word is split."""
    k = np.searchsorted(bounds, end, side="right") - 1
    if bounds[k] > at:
        return int(bounds[k])
    part = raw[at:end]
    gaps = np.flatnonzero((part == 32) | ((part >= 9) & (part <= 13)))
    if len(gaps) and gaps[-1]:
        return at + int(gaps[-1])
    stop = int(bounds[min(k + 1, len(bounds) - 1)])  # one word longer than the window
    while end < stop and not (raw[end] == 32 or 9 <= raw[end] <= 13):
        end += 1
    return end


def shingle_sets(raw: np.ndarray, bounds: np.ndarray, width: int) -> list[np.ndarray]:
    """Sorted distinct hashes of each text's ``width``-word shingles.

    With fewer words the whole sequence is one shingle; without words the set is empty.
    """
    h, first = words(raw, bounds)
    n = len(h)
    flat = h[: max(0, n - width + 1)].copy()
    for j in range(1, width):
        flat *= U(0xD6E8FEB86659FD93)
        flat += h[j : n - width + 1 + j]
        flat ^= flat >> U(29)
    mix(flat)
    out = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
        m = b - a
        if m >= width:
            s = np.sort(flat[a : b - width + 1])
            if len(s) > 1:
                keep = np.empty(len(s), dtype=bool)
                keep[0] = True
                np.not_equal(s[1:], s[:-1], out=keep[1:])
                s = s[keep]
        elif m:
            x = U(m)
            with np.errstate(over="ignore"):
                for w in h[a:b]:
                    x = x * U(0x9FB21C651E98DF25) + w
                    x ^= x >> U(29)
            s = mix(np.array([x], dtype=U))
        else:
            s = np.zeros(0, U)
        out.append(s)
    return out


def slices(batch: pa.RecordBatch, column: str, most: int = 2 << 20):
    """Cut a record batch so that each part holds about ``most`` bytes of text (or one row)."""
    _, bounds = buffers(batch.column(batch.schema.get_field_index(column)))
    a, n = 0, batch.num_rows
    while a < n:
        b = int(np.searchsorted(bounds, bounds[a] + most, side="right")) - 1
        b = min(max(b, a + 1), n)
        yield batch.slice(a, b - a)
        a = b
