"""Word shingles of whole texts as sorted arrays of 64-bit hashes, in numpy.

Words are runs without ASCII white space, A-Z lower-cased. A text's set is its distinct shingles of WIDTH words; with
fewer words the whole sequence is its one shingle; without words it is empty. A word's hash depends on its bytes alone: words of more than
LONG_WORD bytes have one of their own kind, wherever they stand.
"""

from __future__ import annotations

import functools
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash

WIDTH = 5
SEGMENT = 2_000_000
LONG_WORD = 4096
_BASE = 0x9E3779B97F4A7C55  # odd, so that it has an inverse modulo 2**64
_FOLD = np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)], np.uint64) + np.uint64(1)
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_SPACES = tuple(bytes([b]) for b in np.flatnonzero(_SPACE).tolist())
_NEXT_SPACE = re.compile(b"[" + b"".join(_SPACES) + b"]")


@functools.lru_cache(maxsize=1)
def _powers() -> tuple[np.ndarray, np.ndarray]:
    n = 1 << 21
    up, down = (np.full(n, x, np.uint64) for x in (_BASE, pow(_BASE, -1, 1 << 64)))
    up[0] = down[0] = 1
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


def mixed(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def words_of(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Hash and first byte of each word. Long input is cut between words, so memory doesn't grow with it."""
    if len(raw) <= SEGMENT:
        return _words(raw)
    done, at = [], 0
    while at < len(raw):
        end = min(len(raw), at + SEGMENT)
        if end < len(raw) and not _SPACE[raw[end]]:
            # the word across the end goes to the next segment, or is one of its own
            start = max(raw.rfind(c, at, end) for c in _SPACES) + 1
            if start > at:
                end = start
            else:
                found = _NEXT_SPACE.search(raw, end)
                end = found.start() if found else len(raw)
        done.append((*_words(raw[at:end]), at))
        at = end
    return np.concatenate([d[0] for d in done]), np.concatenate([d[1] + d[2] for d in done])


def _words(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    data = np.frombuffer(raw, np.uint8)
    inside = np.zeros(len(data) + 2, np.int8)
    inside[1:-1] = ~_SPACE[data]
    edge = np.diff(inside)
    starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    up, down = _powers()
    if len(data) > len(up):  # a single word of more than a segment
        hashes = np.zeros(len(starts), np.uint64)
    else:
        total = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(_FOLD[data] * up[: len(data)], out=total[1:])
        hashes = mixed((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64))
    for i in np.flatnonzero(ends - starts > LONG_WORD).tolist():
        hashes[i] = xxhash.xxh64_intdigest(raw[starts[i] : ends[i]].lower())
    return hashes, starts


def _shingled(words: np.ndarray) -> np.ndarray:
    """Hashes of all WIDTH successive words."""
    n = len(words) - WIDTH + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.zeros(n, np.uint64)
    for k in range(WIDTH):
        h = h * np.uint64(0xD6E8FEB86659FD93) + words[k : k + n]
        h ^= h >> np.uint64(32)
    return mixed(h)


def sets(column: pa.Array, most: int = 800_000) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    raw = column.cast(pa.large_binary()) if pa.types.is_large_string(column.type) else column.cast(pa.binary())
    texts = [t or b"" for t in raw.to_pylist()]
    at = 0
    while at < len(texts):
        to, size = at, 0
        while to < len(texts) and (to == at or size + len(texts[to]) < most):
            size += len(texts[to]) + 1
            to += 1
        words, places = words_of(b"\n".join(texts[at:to]))
        bounds = np.searchsorted(places, np.cumsum([0, *(len(t) + 1 for t in texts[at:to])]))
        grams = _shingled(words)
        for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            if b - a >= WIDTH:
                yield np.unique(grams[a : b - WIDTH + 1])
            elif b > a:
                h = np.uint64(b - a)
                for w in words[a:b]:
                    h = np.uint64((int(h) * 0xA24BAED4963EE407 + int(w)) & 0xFFFFFFFFFFFFFFFF)
                yield mixed(np.array([h], np.uint64))
            else:
                yield np.zeros(0, np.uint64)
        at = to


def signature(s: np.ndarray) -> int:
    """A 64-bit signature of a set, as a signed long."""
    return int(mixed(np.array([np.sum(mixed(s + np.uint64(0x1234567)), dtype=np.uint64) + np.uint64(len(s))], np.uint64)).view(np.int64)[0])
