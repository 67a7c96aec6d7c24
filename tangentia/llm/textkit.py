"""Array kernels over the UTF-8 buffer of an Arrow string column.

Words, their hashes and shingles of a whole batch are found with a few passes of numpy over the raw
bytes, so no Python object is made per word. Texts are cut into runs of about ``RUN_BYTES`` (a longer
text is a run of its own), which bounds the working memory by the larger of that and the longest text.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

RUN_BYTES = 1 << 18
BASE = np.uint64(0x9E3779B97F4A7C15)
BASE_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))

#: Bytes that belong to a word when only space and 09-0D part words.
SPACED = np.ones(256, dtype=bool)
SPACED[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = False
#: Bytes of letters and digits; everything above ASCII counts as a letter.
ALNUM = np.zeros(256, dtype=bool)
for _lo, _hi in ((0x30, 0x3A), (0x41, 0x5B), (0x61, 0x7B), (0x80, 0x100)):
    ALNUM[_lo:_hi] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32

_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = max(n, RUN_BYTES)
        for k, base in enumerate((BASE, BASE_INVERSE)):
            steps = np.full(size, base, np.uint64)
            steps[0] = 1
            _powers[k] = np.cumprod(steps, dtype=np.uint64)
    return _powers[0], _powers[1]


def tidy() -> None:
    """Give freed memory back to the system at the end of a task: workers live on, idle, beside those of the next stage."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift-multiply), so that all bits depend on all bits."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string or binary array; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    buf = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return buf, offs


def runs(buf: np.ndarray, offs: np.ndarray, limit: int = RUN_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first text, end text, bytes, offsets from 0) of runs of texts of about ``limit`` bytes."""
    n, i = len(offs) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offs, offs[i] + limit, side="right")) - 1)
        j = min(j, n)
        yield i, j, buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i]
        i = j


def word_spans(buf: np.ndarray, offs: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text index, start, end) of each word; words never cross texts."""
    n = len(buf)
    if n == 0:
        z = np.zeros(0, np.int64)
        return z, z, z
    w = table[buf]
    cut = np.zeros(n + 1, dtype=bool)
    cut[offs] = True
    before = np.empty(n, dtype=bool)
    before[0] = False
    before[1:] = w[:-1]
    after = np.empty(n, dtype=bool)
    after[-1] = False
    after[:-1] = w[1:]
    starts = np.flatnonzero(w & (~before | cut[:-1]))
    ends = np.flatnonzero(w & (~after | cut[1:])) + 1
    text = np.searchsorted(offs, starts, side="right") - 1
    return text, starts, ends


class SpanHasher:
    """64-bit hashes of spans of one buffer, A-Z lower-cased if asked: prefix sums of a polynomial, then a finaliser."""

    def __init__(self, buf: np.ndarray, lower: bool = True):
        n = len(buf)
        power, self.inverse = _power_tables(n + 1)
        v = (LOWER[buf] if lower else buf).astype(np.uint64)
        v += np.uint64(1)
        v *= power[:n]
        self.total = np.zeros(n + 1, np.uint64)
        np.cumsum(v, out=self.total[1:])

    def __call__(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        h = (self.total[ends] - self.total[starts]) * self.inverse[starts]
        return mix(h + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def span_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool = True) -> np.ndarray:
    return SpanHasher(buf, lower)(starts, ends)


def fold_case(buf: np.ndarray) -> np.ndarray:
    """Lower case of A-Z and of the accented letters of Latin-1, which lie 20 hex below theirs in the same UTF-8 row."""
    out = LOWER[buf]
    if len(out) > 1:
        second = out[1:]
        upper = (buf[:-1] == 0xC3) & (second >= 0x80) & (second <= 0x9E) & (second != 0x97)
        second[upper] += 32
    return out


def text_counts(text: np.ndarray, n: int) -> np.ndarray:
    return np.bincount(text, minlength=n) if len(text) else np.zeros(n, np.int64)


def shingle_sets(buf: np.ndarray, offs: np.ndarray, width: int) -> list[np.ndarray]:
    """Each text's sorted distinct shingle hashes. A text of fewer words has its whole sequence as one; none, the empty set."""
    n = len(offs) - 1
    text, starts, ends = word_spans(buf, offs, SPACED)
    h = span_hashes(buf, starts, ends)
    counts = text_counts(text, n)
    first = np.zeros(n + 1, np.int64)
    np.cumsum(counts, out=first[1:])
    m = len(h)
    combined = np.zeros(max(m - width + 1, 0), np.uint64)
    for k in range(width):
        combined += h[k : m - width + 1 + k] * np.uint64(pow(0xC2B2AE3D27D4EB4F, k + 1, 1 << 64)) if m >= width else np.uint64(0)
    combined = mix(combined)
    out = []
    for i in range(n):
        a, b = first[i], first[i + 1]
        if b - a >= width:
            out.append(np.unique(combined[a : b - width + 1]))
        elif b > a:
            s = np.full(1, b - a, np.uint64)
            for k in range(a, b):
                s = s * BASE + h[k]
            out.append(mix(s))
        else:
            out.append(np.zeros(0, np.uint64))
    return out
