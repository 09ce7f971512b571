"""Vectorised scans of UTF-8 text: words, word hashes and shingles of many texts at once.

Texts come as Arrow string arrays, whose data buffer is one run of UTF-8 bytes. All work is
NumPy over that buffer, in chunks of bounded size (a longer text is a chunk of its own), so
memory follows the longest text and not the batch.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 1 << 20
_M64 = (1 << 64) - 1
_BASE = 0x9E3779B97F4A7C15
_BASE_INV = pow(_BASE, -1, 1 << 64)
_WORD_MUL = 0xD6E8FEB86659FD93


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective finaliser on uint64."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xC2B2AE3D27D4EB4F)
    return x ^ (x >> np.uint64(29))


@lru_cache(maxsize=2)
def _byte_values(fold: bool = True) -> np.ndarray:
    """A 64-bit value for each byte; with fold, ASCII capitals have those of the small letters."""
    v = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(_BASE))
    if fold:
        v[65:91] = v[97:123]
    return v


_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    have = _POWERS.get("up")
    if have is None or len(have) < n:
        size = max(n, CHUNK_BYTES)
        for key, base in (("up", _BASE), ("down", _BASE_INV)):
            steps = np.full(size, base, dtype=np.uint64)
            steps[0] = 1
            _POWERS[key] = np.multiply.accumulate(steps)
        if n > 8 * CHUNK_BYTES:  # an unusually long text: not kept
            return _POWERS.pop("up"), _POWERS.pop("down")
    return _POWERS["up"][:n], _POWERS["down"][:n]


def byte_class(excluded: str) -> np.ndarray:
    """Mask over bytes: True where the byte can be part of a word."""
    mask = np.ones(256, dtype=bool)
    for ch in excluded:
        mask[ord(ch)] = False
    return mask


#: Words as runs of anything but space, tab, \n, \v, \f, \r.
BLANK_SPLIT = byte_class(" \t\n\v\f\r")
#: Words as runs of digits, letters a-z (capitals are lower-cased first) and non-ASCII.
ALNUM_SPLIT = byte_class("".join(map(chr, [*range(0x30), *range(0x3A, 0x41), *range(0x5B, 0x61), *range(0x7B, 0x80)])))


class Chunk:
    """Some consecutive texts of a batch: bytes, and the start of each text in them."""

    def __init__(self, first: int, data: np.ndarray, offsets: np.ndarray):
        self.first, self.data, self.offsets = first, data, offsets

    def __len__(self) -> int:
        return len(self.offsets) - 1

    def words(self, mask: np.ndarray) -> None:
        """Sets starts and ends of words in bytes, and word_at: the first word of each text."""
        n = len(self.data)
        inside = mask[self.data]
        before = np.empty(n, dtype=bool)
        after = np.empty(n, dtype=bool)
        if n:
            before[0], after[-1] = False, False
            before[1:], after[:-1] = inside[:-1], inside[1:]
            edges = self.offsets[1:-1]
            before[edges[edges < n]] = False
            after[edges[edges > 0] - 1] = False
        self.starts = np.flatnonzero(inside & ~before)
        self.ends = np.flatnonzero(inside & ~after) + 1
        self.word_at = np.searchsorted(self.starts, self.offsets)

    def span_hashes(self, starts: np.ndarray, ends: np.ndarray, fold: bool = True) -> np.ndarray:
        """A hash of the bytes of each span."""
        if not len(starts):
            return np.zeros(0, dtype=np.uint64)
        up, down = _powers(len(self.data) + 1)
        total = np.zeros(len(self.data) + 1, dtype=np.uint64)
        np.cumsum(_byte_values(fold)[self.data] * up[:-1], out=total[1:])
        return mix64((total[ends] - total[starts]) * down[starts])

    def word_hashes(self, fold: bool = True) -> np.ndarray:
        return self.span_hashes(self.starts, self.ends, fold)

    def sums(self, mask: np.ndarray) -> np.ndarray:
        """Bytes of each text for which the mask holds."""
        total = np.concatenate([[0], np.cumsum(mask)])
        return total[self.offsets[1:]] - total[self.offsets[:-1]]

    def shingles(self, k: int = 5, fold: bool = True, short: bool = True) -> tuple[np.ndarray, np.ndarray]:
        """Hash of each run of k words of a text, and the run where each text's begin.

        With short, a text of fewer words, but not none, has one for the whole.
        """
        w = self.word_hashes(fold)
        counts = np.diff(self.word_at)
        runs = np.where(counts >= k, counts - k + 1, (short & (counts > 0)).astype(counts.dtype))
        at = np.concatenate([[0], np.cumsum(runs)])
        out = np.empty(at[-1], dtype=np.uint64)
        mul, acc = 1, np.zeros(max(0, len(w) - k + 1), dtype=np.uint64)
        for j in range(k):
            acc += w[j : j + len(acc)] * np.uint64(mul)
            mul = mul * _WORD_MUL & _M64
        owner = np.repeat(np.arange(len(counts)), runs)
        place = self.word_at[owner] + np.arange(at[-1]) - at[owner]
        full = counts[owner] >= k
        out[full] = mix64(acc[place[full]])
        for d in np.flatnonzero(short & (counts > 0) & (counts < k)):
            v = int(counts[d])
            for x in w[self.word_at[d] : self.word_at[d + 1]].tolist():
                v = (v * _WORD_MUL + x) & _M64
            out[at[d]] = mix64(np.array([v ^ 0xA5A5A5A5], dtype=np.uint64))[0]
        return out, at


def chunks(texts: pa.Array, limit: int = CHUNK_BYTES) -> Iterator[Chunk]:
    """The texts of an Arrow string array; a null is an empty text."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if pa.types.is_large_string(texts.type):
        kind = np.int64
    else:
        kind = np.int32
    if texts.null_count:
        texts = texts.fill_null("")
    n = len(texts)
    if not n:
        return
    _, where, data = texts.buffers()
    offsets = np.frombuffer(where, dtype=kind)[texts.offset : texts.offset + n + 1].astype(np.int64)
    data = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, dtype=np.uint8)
    at = 0
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1
        to = min(n, max(to, at + 1))
        yield Chunk(at, data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at])
        at = to
