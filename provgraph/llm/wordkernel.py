"""Vectorised word and shingle hashing over batches of texts.

Words are maximal runs without the bytes 0x20 and 0x09-0x0D. A word's hash is a polynomial over
randomly drawn 64-bit values of its bytes, taken as a difference of running sums; a shingle's hash
combines its words' mixed hashes in order. Work is done in slices of about a megabyte.
"""

from __future__ import annotations

import ctypes
import ctypes.util
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE = 1 << 20
_rng = np.random.Generator(np.random.PCG64(20240229))
_TABLE = _rng.integers(1, 2**64 - 1, 256, dtype=np.uint64)
_BASE = int(_rng.integers(1, 2**63, dtype=np.uint64)) | 1
_STEP = np.uint64(int(_rng.integers(1, 2**63, dtype=np.uint64)) | 1)
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 9, 10, 11, 12, 13]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_LOWERED = _TABLE[_LOWER]
_LIBC = ctypes.CDLL(name) if (name := ctypes.util.find_library("c")) and hasattr(ctypes.CDLL(name), "malloc_trim") else None
_pows = (np.ones(1, np.uint64), np.ones(1, np.uint64))


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _pows
    if len(_pows[0]) < n:
        size = max(n, SLICE + (SLICE >> 2))
        both = []
        for base in (_BASE, pow(_BASE, -1, 2**64)):
            a = np.full(size, base, np.uint64)
            a[0] = 1
            both.append(np.multiply.accumulate(a))
        _pows = (both[0], both[1])
    return _pows


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h ^= h >> np.uint64(33)
    h *= np.uint64(0xC4CEB9FE1A85EC53)
    h ^= h >> np.uint64(33)
    return h


def distinct(a: np.ndarray) -> np.ndarray:
    """Sorted distinct values, by sorting; the library's own way by hashing takes ten times as long for random 64-bit numbers."""
    s = np.sort(a)
    return s[np.concatenate(([True], s[1:] != s[:-1]))] if len(s) else s


def _slice(buf: np.ndarray, lower: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    word = ~_SPACE[buf]
    edge = np.flatnonzero(np.diff(np.concatenate(([False], word, [False])).view(np.int8)))
    starts, ends = edge[::2], edge[1::2]
    p, inv = _powers(len(buf) + 1)
    run = np.zeros(len(buf) + 1, np.uint64)
    np.cumsum((_LOWERED if lower else _TABLE)[buf] * p[: len(buf)], out=run[1:])
    return mix((run[ends] - run[starts]) * inv[starts] + (ends - starts).astype(np.uint64)), starts, ends


def words(data: bytes, lower: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, first byte and end of every word of ``data``."""
    buf, at, parts = np.frombuffer(data, np.uint8), 0, []
    while at < len(buf):
        end = min(len(buf), at + SLICE)
        if end < len(buf) and not _SPACE[buf[end]]:
            cut = np.flatnonzero(_SPACE[buf[at:end]])
            if len(cut):
                end = at + int(cut[-1]) + 1
            else:  # a word longer than a slice
                step = end
                while step < len(buf) and not len(cut := np.flatnonzero(_SPACE[buf[step : step + SLICE]])):
                    step += SLICE
                end = step + int(cut[0]) + 1 if step < len(buf) else len(buf)
        h, s, e = _slice(buf[at:end], lower)
        parts.append((h, s + at, e + at))
        at = end
    if not parts:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def joined(texts: list[bytes]) -> tuple[bytes, np.ndarray]:
    """One buffer of all texts, a newline after each, and where each text starts (one more entry for the end)."""
    at = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) + 1 for t in texts], out=at[1:])
    return b"\n".join(texts) + b"\n", at


def give_back() -> None:
    """Returns freed memory to the system: Python workers outlive their tasks, and what they hold adds up on an executor."""
    pa.default_memory_pool().release_unused()
    if _LIBC is not None:
        _LIBC.malloc_trim(0)


def batches(it: Iterator[pa.RecordBatch], col: str = "text", limit: int = SLICE) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    """Pieces of the batches with about ``limit`` bytes of text (a row at least); null text is empty."""
    for batch in it:
        if not batch.num_rows:
            continue
        texts = [t or b"" for t in batch.column(col).cast(pa.large_binary()).to_pylist()]
        ends = np.cumsum([len(t) for t in texts])
        at = 0
        while at < len(texts):
            base = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, base + limit, "right")))
            yield batch.slice(at, to - at), texts[at:to]
            at = to
        del batch, texts
        give_back()


def _combine(w: np.ndarray, k: int) -> np.ndarray:
    n = len(w) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = w[:n].copy()
    for j in range(1, k):
        h *= _STEP
        h += w[j : j + n]
    return mix(h + np.uint64(k))


def window_arrays(texts: list[bytes], k: int, lower: bool = False, whole_if_short: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all k-word windows, text after text; where each text's begin; words of each text; all words' hashes.

    The second has one more entry for the end. ``whole_if_short``: a text with 1 to k-1 words has one window, all of
    its words.
    """
    data, at = joined(texts)
    w, starts, _ = words(data, lower)
    cut = np.searchsorted(starts, at)
    n = np.diff(cut)
    h = _combine(w, k)
    size = np.maximum(n - k + 1, 0)
    begin = np.concatenate([[0], np.cumsum(size)])
    h = h[np.arange(begin[-1]) + np.repeat(cut[:-1] - begin[:-1], size)]
    if whole_if_short and len(short := np.flatnonzero((n > 0) & (n < k))):
        h = np.insert(h, begin[short], [_combine(w[cut[i] : cut[i + 1]], int(n[i]))[0] for i in short])
        size[short] = 1
        begin = np.concatenate([[0], np.cumsum(size)])
    return h, begin, n, w


def windows(texts: list[bytes], k: int, lower: bool = False, whole_if_short: bool = False) -> Iterator[tuple[np.ndarray, int]]:
    """For each text: the hashes of its k-word windows in order, and its number of words."""
    h, begin, n, _ = window_arrays(texts, k, lower, whole_if_short)
    for a, b, m in zip(begin[:-1].tolist(), begin[1:].tolist(), n.tolist(), strict=True):
        yield h[a:b], m
