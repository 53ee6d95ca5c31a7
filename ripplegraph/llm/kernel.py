"""Vectorised text kernels: words, rolling hashes and minimisers over Arrow string batches.

Texts are handled as UTF-8 bytes. Separators are ASCII bytes, so cutting bytes cuts the same words as
cutting code points. Work goes in slices of about a megabyte, so memory stays flat whatever the batch
size; a single longer text is a slice of its own.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 20
_SEP = np.zeros(256, dtype=bool)
_SEP[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Fixed odd multipliers (bases of the polynomial hashes) and their inverses modulo 2**64.
BASES = tuple(np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93))
_INVERSES = tuple(np.uint64(pow(int(b), -1, 1 << 64)) for b in BASES)
_powers: dict[int, np.ndarray] = {}


def powers(base: np.uint64, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64, kept for slices of usual size."""
    have = _powers.get(int(base))
    if have is None or len(have) < n:
        size = max(n, SLICE_BYTES + 4096)
        have = np.full(size, base, dtype=np.uint64)
        have[0] = 1
        np.multiply.accumulate(have, out=have)
        if size <= 4 * SLICE_BYTES:
            _powers[int(base)] = have
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64: spreads each bit over all."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@dataclass
class Words:
    """Words of the texts ``first .. first + n_docs`` of a batch, in order."""

    first: int
    n_docs: int
    data: np.ndarray  # bytes of the slice
    begin: np.ndarray  # of each word, in data
    end: np.ndarray
    doc: np.ndarray  # of each word, counted from first
    start: np.ndarray  # first word of each text, and the end of the last
    offsets: np.ndarray | None = None  # first byte of each text, and the end of the last

    def hashes(self, base: int = 0) -> np.ndarray:
        """64-bit hashes of the words."""
        n, b = len(self.data), BASES[base]
        sums = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum((self.data.astype(np.uint64) + np.uint64(1)) * powers(b, n), out=sums[1:])
        value = (sums[self.end] - sums[self.begin]) * powers(_INVERSES[base], n + 1)[self.begin]
        return mix(value ^ (self.end - self.begin).astype(np.uint64) * np.uint64(0xFF51AFD7ED558CCD))


def grams(hashed: np.ndarray, k: int, base: int = 1) -> np.ndarray:
    """Hash of the k words from each position on (texts' ends are the caller's matter)."""
    n = len(hashed)
    if n < k:
        return np.zeros(0, dtype=np.uint64)
    sums = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum(hashed * powers(BASES[base], n), out=sums[1:])
    return mix((sums[k:] - sums[:-k]) * powers(_INVERSES[base], n + 1)[: n - k + 1])


def spans_hash(hashed: np.ndarray, begin: np.ndarray, end: np.ndarray, base: int = 1) -> np.ndarray:
    """Hash of the words begin .. end, for many spans at once."""
    n = len(hashed)
    sums = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum(hashed * powers(BASES[base], n), out=sums[1:])
    value = (sums[end] - sums[begin]) * powers(_INVERSES[base], n + 1)[begin]
    return mix(value ^ (end - begin).astype(np.uint64))


def slices(texts: pa.Array, lower: bool = False, separating: np.ndarray = _SEP) -> Iterator[Words]:
    """Cut a batch of texts into words, a slice at a time."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = texts.cast(pa.large_string()).fill_null("")
    n = len(texts)
    if not n:
        return
    offsets = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset : texts.offset + n + 1]
    blob = texts.buffers()[2]
    raw = np.frombuffer(blob, dtype=np.uint8) if blob is not None and blob.size else np.zeros(0, dtype=np.uint8)
    i = 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + SLICE_BYTES, side="right")) - 1)
        j = min(j, n)
        data = raw[offsets[i] : offsets[j]]
        if lower:
            data = _LOWER[data]
        yield cut(data, offsets[i : j + 1] - offsets[i], i, separating)
        i = j


def cut(data: np.ndarray, offsets: np.ndarray, first: int, separating: np.ndarray = _SEP) -> Words:
    n = len(data)
    inside = np.zeros(n + 1, dtype=bool)
    inside[:n] = ~separating[data]
    starts_doc = np.zeros(n + 1, dtype=bool)
    starts_doc[offsets] = True
    before = np.zeros(n + 1, dtype=bool)
    before[1:] = inside[:-1]
    begin = np.flatnonzero(inside & (~before | starts_doc))
    end = np.flatnonzero(before & (~inside | starts_doc))
    start = np.searchsorted(begin, offsets)
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(start))
    return Words(first, len(offsets) - 1, data, begin, end, doc, start, offsets)


def window_min(values: np.ndarray, width: int) -> np.ndarray:
    """Smallest of each run of ``width`` values, by doubling."""
    out, have = values, 1
    while have * 2 <= width:
        out = np.minimum(out[:-have], out[have:])
        have *= 2
    if have < width:
        rest = width - have
        out = np.minimum(out[:-rest], out[rest:])
    return out


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
