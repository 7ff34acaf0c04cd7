"""Word and shingle hashes of many texts at once, in numpy."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

SHINGLE = 5
_rng = np.random.default_rng(20240117)
_BYTE = _rng.integers(1, 2**63, 256, dtype=np.uint64)
_PLACE = (_rng.integers(1, 2**63, 16, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)
_STEP = 0x9E3779B97F4A7C15
_STEP_INVERSE = pow(_STEP, -1, 2**64)
_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[9, 10, 11, 12, 13, 32]] = True
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit values."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = max(n, 1 << 16)
        for k, base in enumerate((_STEP, _STEP_INVERSE)):
            run = np.full(size, base, np.uint64)
            run[0] = 1
            _powers[k] = np.multiply.accumulate(run)
    return _powers[0], _powers[1]


def word_hashes(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hash and first byte of each word of raw (ASCII white space divides words)."""
    data = np.frombuffer(raw, np.uint8)
    if not len(data):
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    space = _IS_SPACE[data]
    edge = np.flatnonzero(np.diff(space, prepend=True, append=True))
    begin, end = edge[0::2], edge[1::2]
    up, down = _power_tables(len(data) + 1)
    run = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_BYTE[data] * up[: len(data)], out=run[1:])
    return mix((run[end] - run[begin]) * down[begin] + (end - begin).astype(np.uint64)), begin


def grouped_words(texts: list[bytes | None], budget: int = 1 << 19) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """For runs of texts of about `budget` bytes: first text of the run, word hashes, words in each text.

    ASCII capitals are lowered first. A longer text is a run of its own; null is an empty text.
    """
    first = 0
    while first < len(texts):
        last, size = first, 0
        while last < len(texts) and (last == first or size + len(texts[last] or b"") <= budget):
            size += len(texts[last] or b"") + 1
            last += 1
        part = [t or b"" for t in texts[first:last]]
        hashes, begin = word_hashes(b"\n".join(part).lower())
        ends = np.cumsum([len(t) + 1 for t in part])
        yield first, hashes, np.diff(np.searchsorted(begin, ends), prepend=0)
        first = last


def shingle_sets(texts: list[bytes | None], width: int = SHINGLE) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of each text; a text of fewer words is one shingle, without words none."""
    for _, words, counts in grouped_words(texts):
        n = len(words)
        rolled = np.zeros(max(0, n - width + 1), np.uint64)
        for k in range(width):
            rolled += words[k : n - width + 1 + k] * _PLACE[k] if len(rolled) else rolled
        rolled = mix(rolled)
        at = 0
        for count in counts.tolist():
            if count >= width:
                yield np.unique(rolled[at : at + count - width + 1])
            elif count:
                short = (words[at : at + count] * _PLACE[:count]).sum(dtype=np.uint64, keepdims=True)
                yield mix(short + _PLACE[width + count % 8])
            else:
                yield np.empty(0, np.uint64)
            at += count


def overlap(a: np.ndarray, b: np.ndarray) -> int:
    """Common elements of two sorted distinct arrays."""
    if len(a) > len(b):
        a, b = b, a
    if not len(a):
        return 0
    at = np.searchsorted(b, a)
    at[at == len(b)] = len(b) - 1
    return int((b[at] == a).sum())
