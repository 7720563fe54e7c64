"""Word and shingle hashing over whole Arrow text columns, in numpy, with bounded working memory.

Words are ``[^\\x20\\x09-\\x0D]+`` over UTF-8 bytes, A-Z folded to lower case.  A word's hash is a
multilinear sum of its bytes with position-wise random odd weights, followed by a mixer; a shingle's
hash is a multilinear sum of its word hashes, mixed again.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

PIECE_BYTES = 1 << 20
_U = np.uint64
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (bijective)."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def stream(n: int, seed: int) -> np.ndarray:
    """n pseudo-random 64-bit words; entry i depends on (seed, i) only."""
    with np.errstate(over="ignore"):
        return mix((np.arange(1, n + 1, dtype=_U) + _U(seed) * _U(0x632BE59BD9B4E019)) * _U(0x9E3779B97F4A7C15))


_weights = [stream(256, 7) | _U(1)]


def _byte_weights(n: int) -> np.ndarray:
    if n > len(_weights[0]):
        _weights[0] = stream(max(n, 2 * len(_weights[0])), 7) | _U(1)
    return _weights[0]


def text_column(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null counts as empty."""
    col = col.cast(pa.large_string()).fill_null("")
    _, off, data = col.buffers()
    off = np.frombuffer(off, dtype=np.int64)[col.offset : col.offset + len(col) + 1] if off is not None and len(col) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def pieces(offsets: np.ndarray, limit: int = PIECE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``limit`` bytes (a longer row stands alone)."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, side="right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def word_spans(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of all words; a word never crosses a row."""
    if not len(raw):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    ink = ~_SPACE[raw]
    edge = np.zeros(len(raw) + 1, dtype=bool)
    edge[offsets] = True
    before = np.empty_like(ink)
    before[0], before[1:] = False, ink[:-1]
    starts = np.flatnonzero(ink & (~before | edge[:-1]))
    after = np.empty_like(ink)
    after[-1], after[:-1] = False, ink[1:]
    ends = np.flatnonzero(ink & (~after | edge[1:])) + 1
    return starts, ends


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    if not len(starts):
        return np.zeros(0, _U)
    lens = ends - starts
    first = np.cumsum(lens) - lens
    pos = np.arange(int(lens.sum()), dtype=np.int64) - np.repeat(first, lens)
    ink = _FOLD[raw[pos + np.repeat(starts, lens)]]
    with np.errstate(over="ignore"):
        part = (ink.astype(_U) + _U(1)) * _byte_weights(int(lens.max()))[pos]
        return mix(np.add.reduceat(part, first) + lens.astype(_U) * _U(0xD6E8FEB86659FD93))


def shingles(raw: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of every word window; a row of fewer words gives its whole sequence as one window."""
    starts, ends = word_spans(raw, offsets)
    w = word_hashes(raw, starts, ends)
    row = np.searchsorted(offsets, starts, side="right") - 1
    mult = stream(width + 1, 11) | _U(1)
    with np.errstate(over="ignore"):
        n = len(w) - width + 1
        if n > 0:
            acc = np.zeros(n, _U)
            for k in range(width):
                acc += w[k : k + n] * mult[k]
            whole = row[:n] == row[width - 1 :]
            rows, hashes = row[:n][whole], mix(acc[whole])
        else:
            rows, hashes = np.zeros(0, np.int64), np.zeros(0, _U)
        count = np.bincount(row, minlength=len(offsets) - 1) if len(row) else np.zeros(len(offsets) - 1, np.int64)
        short = np.flatnonzero((count > 0) & (count < width))
        if len(short):
            at = np.searchsorted(row, short)
            acc = count[short].astype(_U) * mult[width]
            for k in range(width - 1):
                has = count[short] > k
                acc[has] += w[at[has] + k] * mult[k]
            rows, hashes = np.concatenate([rows, short]), np.concatenate([hashes, mix(acc)])
    return rows, hashes


def shingle_sets(col: pa.Array, width: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each row, in order."""
    raw, offsets = text_column(col)
    for i, j in pieces(offsets):
        off = offsets[i : j + 1] - offsets[i]
        rows, hashes = shingles(raw[offsets[i] : offsets[j]], off, width)
        order = np.argsort(rows, kind="stable")
        hashes = hashes[order]
        cut = np.searchsorted(rows[order], np.arange(j - i + 1))
        for k in range(j - i):
            yield np.unique(hashes[cut[k] : cut[k + 1]])
