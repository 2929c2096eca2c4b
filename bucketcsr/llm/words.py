"""Whole texts as flat NumPy arrays: words between ASCII white space, code points, segment sums.

All functions take an Arrow string array (null: empty text) and never loop over words in Python.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[ord("A") : ord("Z") + 1] += 32


def flat(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts in a row, and the n + 1 offsets of the texts."""
    whole = pc.fill_null(texts, "").cast(pa.large_string())
    offsets = np.frombuffer(whole.buffers()[1], np.int64)[whole.offset : whole.offset + len(whole) + 1]
    data = whole.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def sums(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Sum of values between neighbouring offsets (empty segments: 0)."""
    total = np.zeros(len(values) + 1, np.float64 if values.dtype.kind == "f" else np.int64)
    np.cumsum(values, out=total[1:])
    return total[offsets[1:]] - total[offsets[:-1]]


@dataclass
class Words:
    """Words of a batch: their bytes end to end, n + 1 offsets into them, and texts' n + 1 first words."""

    raw: np.ndarray
    offsets: np.ndarray
    first: np.ndarray

    @property
    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))

    def strings(self) -> pa.Array:
        """The words as an Arrow array that shares their bytes."""
        return pa.LargeStringArray.from_buffers(len(self.offsets) - 1, pa.py_buffer(np.ascontiguousarray(self.offsets)), pa.py_buffer(self.raw))

    def encoded(self) -> tuple[np.ndarray, pa.Array]:
        """Each word's number, and the distinct words by number."""
        if len(self.offsets) == 1:
            return np.zeros(0, np.int64), pa.array([], pa.large_string())
        coded = self.strings().dictionary_encode()
        return coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), coded.dictionary


def split(raw: np.ndarray, offsets: np.ndarray, blank: np.ndarray = SPACE) -> Words:
    """Maximal runs of bytes outside `blank`, never across texts."""
    inside = ~blank[raw]
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    edges = offsets[:-1][(offsets[:-1] < len(raw))]
    begins[edges] = inside[edges]
    kept = raw[inside]
    before = np.zeros(len(raw) + 1, np.int64)
    np.cumsum(inside, out=before[1:])
    starts = np.flatnonzero(begins)
    word_offsets = np.append(before[starts], len(kept)).astype(np.int64)
    return Words(kept, word_offsets, np.searchsorted(starts, offsets))


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: spreads small integers over all bits."""
    x = x.astype(np.uint64)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def code_points(strings: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all strings in a row, and their n + 1 offsets."""
    raw, offsets = flat(strings)
    leads = (raw & 0xC0) != 0x80
    points = np.frombuffer(raw.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
    before = np.zeros(len(raw) + 1, np.int64)
    np.cumsum(leads, out=before[1:])
    return points, before[offsets]
