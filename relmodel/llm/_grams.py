"""Vectorised rolling hashes and content-defined anchors over Arrow text buffers (NumPy).

An *anchor* of a window of ``size`` tokens is the position, inside the window, of the sub-window of
``gram`` tokens with the least hash (leftmost on ties). Equal windows have equal anchors wherever
they stand, so comparing anchors alone finds every repeated window while only about 2 of every
``size - gram`` positions are ever shuffled.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

U = np.uint64
_rng = np.random.default_rng(20240607)
BYTE_VALUES = _rng.integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
BASE, BASE2 = U(0x9E3779B97F4A7C15), U(0xD1342543DE82EF95)
SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
_powers: dict[int, np.ndarray] = {}


def powers(base: U, n: int) -> np.ndarray:
    """base**0 … base**(n-1) modulo 2**64; kept for the process, grown by doubling."""
    got = _powers.get(int(base))
    if got is None or len(got) < n:
        size = 1 << max(12, int(n).bit_length())
        got = np.full(size, base, np.uint64)
        got[0] = 1
        _powers[int(base)] = got = np.multiply.accumulate(got)
    return got[:n]


def inverse(base: U) -> U:
    return U(pow(int(base), -1, 1 << 64))


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def prefix(values: np.ndarray, base: U) -> np.ndarray:
    """Running polynomial hash: entry i covers values[:i]."""
    out = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values * powers(base, len(values)), out=out[1:])
    return out


def span_hash(pre: np.ndarray, start: np.ndarray, end: np.ndarray, base: U) -> np.ndarray:
    """Position-free hash of values[start:end], mixed with the length."""
    return mix((pre[end] - pre[start]) * powers(inverse(base), len(pre))[start] + (end - start).astype(np.uint64))


def rolling(values: np.ndarray, k: int, base: U) -> np.ndarray:
    """Hash of every run of k values."""
    n = len(values) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    pre = prefix(values, base)
    return mix((pre[k : k + n] - pre[:n]) * powers(inverse(base), n))


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column without copying; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    _, off, data = column.buffers()
    offsets = np.frombuffer(off, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw, offsets


def chunks(offsets: np.ndarray, target: int = 1 << 20):
    """Runs of rows of about ``target`` bytes (one row may be longer)."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + target, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def word_spans(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words of a buffer, and for each row the index of its first word (one more at the end)."""
    space = SPACE[raw]
    edge = np.zeros(len(raw) + 1, bool)
    edge[offsets[(offsets >= 0) & (offsets <= len(raw))]] = True
    word = ~space
    begin = word.copy()
    begin[1:] &= space[:-1] | edge[1:-1]
    last = word.copy()
    last[:-1] &= space[1:] | edge[1:-1]
    starts, ends = np.flatnonzero(begin), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_values(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    pre = prefix(BYTE_VALUES[raw], BASE)
    return span_hash(pre, starts, ends, BASE)


def anchor_runs(values: np.ndarray, bounds: np.ndarray, gram: int, size: int):
    """Anchors of all windows of ``size`` values inside rows ``values[bounds[r]:bounds[r+1]]``.

    Returns (row, anchor, first, last, gram hash at the anchor): the windows that begin at
    first…last have this anchor; positions are relative to the buffer. Works block by block, so a
    row of any length needs bounded memory.
    """
    width, step = size - gram + 1, 1 << 18
    rows, anchors, firsts, lasts, hashes = [], [], [], [], []
    for s in range(0, max(0, len(values) - size + 1), step):
        part = values[s : s + step + size - 1]
        h = rolling(part, gram, BASE2)
        m = (h & ~U((1 << 20) - 1)) | np.arange(len(h), dtype=np.uint64)
        have = 1
        while have < width:
            by = min(have, width - have)
            m = np.minimum(m[: len(m) - by], m[by:])
            have += by
        at = (m & U((1 << 20) - 1)).astype(np.int64)
        p = np.arange(len(at)) + s
        row = np.searchsorted(bounds, p, "right") - 1
        ok = p + size <= bounds[np.minimum(row + 1, len(bounds) - 1)]
        p, at, row = p[ok], at[ok], row[ok]
        if not len(p):
            continue
        new = np.ones(len(p), bool)
        new[1:] = (at[1:] != at[:-1]) | (p[1:] != p[:-1] + 1) | (row[1:] != row[:-1])
        k = np.flatnonzero(new)
        rows.append(row[k]), anchors.append(at[k] + s), firsts.append(p[k]), hashes.append(h[at[k]])
        lasts.append(p[np.append(k[1:], len(p)) - 1])
    if not rows:
        z = np.zeros(0, np.int64)
        return z, z, z, z, np.zeros(0, np.uint64)
    return tuple(map(np.concatenate, (rows, anchors, firsts, lasts, hashes)))
