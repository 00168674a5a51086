"""Vectorised text kernels on Arrow batches: word boundaries, word hashes, byte-bounded chunks."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 1 << 20

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
WORD_BYTE = np.zeros(256, dtype=bool)
WORD_BYTE[48:58] = WORD_BYTE[97:123] = WORD_BYTE[128:] = True
_MASKS = np.array([(1 << (8 * n)) - 1 for n in range(8)] + [(1 << 64) - 1], dtype=np.uint64)
_ODD = np.uint64(0x9E3779B97F4A7C15)
_ODD_2 = np.uint64(0xC2B2AE3D27D4EB4F)
_HALF = np.uint64(32)


@dataclass
class Words:
    """Words of a chunk of texts. ``low`` holds the lower-cased bytes of all texts, one separator after each."""

    low: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    first: np.ndarray  #: index of the first word of each text, one more entry than texts

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)


def byte_chunks(batch: pa.RecordBatch, column: str, limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of ``batch`` whose texts hold about ``limit`` bytes; a longer text stands alone."""
    at = batch.schema.get_field_index(column)
    values = batch.column(at).cast(pa.large_binary())
    lengths = pa.compute.fill_null(pa.compute.binary_length(values), 0).to_numpy(zero_copy_only=False)
    start, held = 0, 0
    for i, n in enumerate(lengths.tolist()):
        if held and held + n > limit:
            yield batch.slice(start, i - start)
            start, held = i, 0
        held += n
    if start < len(lengths):
        yield batch.slice(start)


def as_bytes(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of a string column; null becomes empty."""
    return [x or b"" for x in column.cast(pa.large_binary()).to_pylist()]


def split_words(texts: list[bytes]) -> Words:
    """Word boundaries of all texts in a few array passes.

    A-Z are lower-cased; a word is a maximal run of digits, a-z and characters beyond ASCII (all
    of whose UTF-8 bytes are above 127, so bytes decide).
    """
    low = LOWER[np.frombuffer(b"\n".join(texts) + b"\n" + bytes(8), dtype=np.uint8)]
    inside = WORD_BYTE[low]
    edges = np.flatnonzero(inside[1:] != inside[:-1]) + 1
    if inside[0]:
        edges = np.concatenate(([0], edges))
    starts, ends = edges[0::2], edges[1::2]
    after = np.cumsum([len(t) + 1 for t in texts], dtype=np.int64)
    first = np.concatenate(([0], np.searchsorted(starts, after)))
    return Words(low, starts, ends, first)


def _mix(h: np.ndarray) -> np.ndarray:
    h = h * _ODD
    h ^= h >> _HALF
    h *= _ODD_2
    h ^= h >> np.uint64(29)
    return h


def hash_words(words: Words) -> np.ndarray:
    """A 64-bit hash of every word: its bytes are read eight at a time and mixed."""
    lanes = np.ndarray((len(words.low) - 7,), dtype="<u8", buffer=words.low.data, strides=(1,))
    at, left = words.starts, words.ends - words.starts
    h = _mix(lanes[at] & _MASKS[np.minimum(left, 8)])
    open_ = np.flatnonzero(left > 8)
    step = 8
    while len(open_):
        rest = left[open_] - step
        h[open_] = _mix(h[open_] ^ (lanes[at[open_] + step] & _MASKS[np.minimum(rest, 8)]))
        open_ = open_[rest > 8]
        step += 8
    return h


def hash_windows(h: np.ndarray, size: int) -> np.ndarray:
    """Order-aware hash of every ``size`` consecutive word hashes (empty if there are fewer)."""
    n = len(h) - size + 1
    if n <= 0:
        return np.empty(0, dtype=np.uint64)
    out = h[:n].copy()
    for k in range(1, size):
        out = out * _ODD_2 + h[k : k + n]
    return _mix(out)
