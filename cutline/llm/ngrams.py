"""Hashed character n-grams of whole Arrow text batches, in numpy."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: A-Z lower-cased; digits, ASCII punctuation and controls become spaces. Bytes of other scripts stay.
FOLD = np.array([b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256)], np.uint8)
_ODD = np.uint64(0x9E3779B97F4A7C15)


def chunks(column: pa.Array, most: int = 500_000) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(bytes, starts, ends) for runs of rows with about `most` bytes; each text is lower-cased, folded, and stands between
    spaces. A single text longer than that makes a run of its own. Nulls are empty texts."""
    lowered = pc.utf8_lower(column.cast(pa.large_string()).fill_null(""))
    lengths = pc.binary_length(lowered).to_numpy(zero_copy_only=False)
    ends = np.cumsum(lengths)
    at = 0
    while at < len(lowered):
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + most, "right")))
        own = lengths[at:to]
        raw = np.concatenate([[], *(np.frombuffer(b, np.uint8) for b in _views(lowered.slice(at, to - at)))]).astype(np.uint8)
        # room for one space before each text, and one after the last
        starts = np.cumsum(np.concatenate([[1], own[:-1] + 1]))
        buffer = np.full(int(own.sum()) + len(own) + 1, 32, np.uint8)
        mask = np.ones(len(buffer), bool)
        mask[starts - 1] = False
        mask[-1] = False
        buffer[mask] = FOLD[raw]
        yield buffer, starts - 1, starts + own + 1
        at = to


def _views(column: pa.Array) -> list:
    """The bytes of a string array's rows, as one view."""
    offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    return [column.buffers()[2][int(offsets[0]) : int(offsets[-1])]] if column.buffers()[2] is not None and offsets[-1] > offsets[0] else []


def rolling(buffer: np.ndarray, n: int) -> np.ndarray:
    """A mixed 64-bit hash of each n successive bytes (n up to 8 without collisions)."""
    size = len(buffer) - n + 1
    if size <= 0:
        return np.zeros(0, np.uint64)
    h = buffer[:size].astype(np.uint64)
    for i in range(1, n):
        h <<= np.uint64(8)
        h |= buffer[i : i + size]
    h += np.uint64(n) << np.uint64(59)
    h *= _ODD
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    return h


def spans(starts: np.ndarray, ends: np.ndarray, n: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Where each text's n-grams begin and end among `size` positions."""
    first = np.minimum(starts, size)
    return first, np.maximum(first, np.minimum(ends - n + 1, size))


def sums(values: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """Sums of values[first:last] for each pair."""
    total = np.concatenate([[0], np.cumsum(values, dtype=np.int64)])
    return total[last] - total[first]
