"""Vectorised word, hash and shingle arithmetic over Arrow string batches.

A word is a maximal run of bytes outside 0x20 and 0x09-0x0D, which equals the
regular expression ``[^\\x20\\x09-\\x0D]+`` on the decoded text because those bytes
never occur inside a multi-byte UTF-8 sequence.  All routines take slices of a
batch that hold about ``CHUNK_BYTES`` bytes, so the working memory of a Python
worker is bounded by that figure and by the longest single text.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 1 << 18
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_SEED_RNG = np.random.default_rng(20240229)
_BYTE_CODE = _SEED_RNG.integers(1, 2**63 - 1, size=256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = 0x9E3779B97F4A7C13  # odd, 3 modulo 8, so its powers stay invertible modulo 2**64
_BASE_INVERSE = pow(_BASE, -1, 2**64)
_POSITION_CODE = _SEED_RNG.integers(1, 2**63 - 1, size=64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_POWERS: dict[str, np.ndarray] = {}
LOWER_ASCII = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))


def _powers(base: int, n: int) -> np.ndarray:
    """base**k modulo 2**64 for k < n; grown by doubling and kept per worker."""
    have = _POWERS.get(str(base))
    if have is None or len(have) < n:
        size = 1 << max(12, int(n - 1).bit_length())
        have = np.full(size, np.uint64(base), dtype=np.uint64)
        have[0] = 1
        have = np.multiply.accumulate(have)
        _POWERS[str(base)] = have
    return have[:n]


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def string_buffers(column) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, bytes) of an Arrow string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if column.null_count:
        column = column.fill_null("")
    if not len(column):
        return np.zeros(1, np.int64), np.zeros(0, np.uint8)
    _, offsets, data = column.buffers()
    width = np.int64 if pa.types.is_large_string(column.type) else np.int32
    ends = np.frombuffer(offsets, dtype=width)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return ends, raw


def row_slices(offsets: np.ndarray, limit: int = CHUNK_BYTES):
    """Ranges of rows of about ``limit`` bytes; one longer row stands alone."""
    n, start = len(offsets) - 1, 0
    while start < n:
        stop = int(np.searchsorted(offsets, offsets[start] + limit, side="right")) - 1
        stop = min(max(stop, start + 1), n)
        yield start, stop
        start = stop


class Words:
    """Words of consecutive rows: byte spans, row of each word, first word of each row."""

    def __init__(self, offsets: np.ndarray, raw: np.ndarray, start: int, stop: int, lower: bool = False):
        base = int(offsets[start])
        body = raw[base : int(offsets[stop])]
        if lower:
            body = np.frombuffer(body.tobytes().translate(LOWER_ASCII), dtype=np.uint8)
        self.raw = body
        self.bounds = (offsets[start : stop + 1] - base).astype(np.int64)
        solid = ~_SPACE[body]
        before = np.empty_like(solid)
        before[:1] = False
        before[1:] = solid[:-1]
        inner = self.bounds[1:-1]
        inner = inner[inner < len(body)]
        before[inner] = False  # a word never runs over a row's end
        self.starts = np.flatnonzero(solid & ~before)
        after = np.empty_like(solid)
        after[-1:] = False
        after[:-1] = solid[1:]
        cut = inner[inner > 0] - 1
        after[cut] = False
        self.ends = np.flatnonzero(solid & ~after) + 1
        self.first = np.searchsorted(self.starts, self.bounds, side="left").astype(np.int64)
        self.counts = np.diff(self.first)
        self.row = np.repeat(np.arange(stop - start), self.counts)

    def hashes(self) -> np.ndarray:
        """64-bit hash of every word, equal for equal bytes."""
        n = len(self.raw)
        if not len(self.starts):
            return np.zeros(0, np.uint64)
        running = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum(_BYTE_CODE[self.raw] * _powers(_BASE, n), out=running[1:])
        inside = (running[self.ends] - running[self.starts]) * _powers(_BASE_INVERSE, n + 1)[self.starts]
        return mix64(inside + (self.ends - self.starts).astype(np.uint64))


def gram_hashes(word_hash: np.ndarray, k: int) -> np.ndarray:
    """Hash of the k words from each position on (array shorter by k - 1)."""
    n = len(word_hash) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = np.zeros(n, dtype=np.uint64)
    for j in range(k):
        total += word_hash[j : j + n] * _POSITION_CODE[j]
    return mix64(total)


def shingle_sets(words: Words, k: int) -> list[np.ndarray]:
    """Sorted distinct k-word shingle hashes of each row.

    A row of fewer than k words (but one at least) has its whole sequence as the
    only shingle; a row without words has none.
    """
    h = words.hashes()
    grams = gram_hashes(h, k)
    out = []
    for first, count in zip(words.first[:-1].tolist(), words.counts.tolist(), strict=True):
        if count >= k:
            out.append(np.unique(grams[first : first + count - k + 1]))
        elif count:
            part = np.zeros(1, dtype=np.uint64)
            for j in range(count):
                part += h[first + j : first + j + 1] * _POSITION_CODE[j]
            out.append(mix64(part + _POSITION_CODE[63:] * np.uint64(count)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out
