"""Word shingles as 64-bit hashes, computed for many texts at once in numpy.

Words are maximal runs of bytes other than the six ASCII white-space characters, after A-Z became a-z. A text's set holds the
hashes of its distinct runs of `width` words; a text with fewer words has its whole sequence as its only element; without words,
or null, the set is empty.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

WIDTH = 5
_BASE = np.uint64(0x9E3779B97F4A7C15 | 5)
_STEP = np.uint64(0xD6E8FEB86659FD93)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every bit."""
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def _byte_values() -> np.ndarray:
    values = mix(np.arange(1, 257, dtype=np.uint64) * _BASE)
    values[65:91] = values[97:123]
    return values


_VALUES = _byte_values()
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_powers = (np.ones(1, np.uint64), np.ones(1, np.uint64))


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, up to n."""
    global _powers
    if len(_powers[0]) <= n:
        grown = []
        for base in (_BASE, _INVERSE):
            factors = np.full(n + n // 4 + 1, base, np.uint64)
            factors[0] = 1
            grown.append(np.multiply.accumulate(factors))
        _powers = tuple(grown)
    return _powers


def word_hashes(joined: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start offset and hash of every word."""
    space = np.concatenate(([True], _SPACE[joined], [True]))
    edges = np.flatnonzero(space[1:] != space[:-1])
    starts, ends = edges[0::2], edges[1::2]
    power, inverse = _power(len(joined))
    sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(_VALUES[joined] * power[: len(joined)])))
    return starts, mix((sums[ends] - sums[starts]) * inverse[starts] + (ends - starts).astype(np.uint64))


def _combined(words: np.ndarray, width: int) -> np.ndarray:
    total = np.zeros(max(0, len(words) - width + 1), np.uint64)
    for k in range(width):
        total = total * _STEP + words[k : len(words) - width + 1 + k]
    return mix(total + np.uint64(width))


def shingle_sets(texts: list[str | None], width: int = WIDTH, piece: int = 2_000_000) -> Iterator[np.ndarray]:
    """The sorted set of each text, in order. Texts are worked on in groups of about `piece` bytes, each whole."""
    group: list[bytes] = []
    total = 0
    for text in texts:
        group.append((text or "").encode("utf-8", "surrogatepass"))
        total += len(group[-1])
        if total >= piece:
            yield from _sets(group, width)
            group, total = [], 0
    yield from _sets(group, width)


def _sets(group: list[bytes], width: int) -> Iterator[np.ndarray]:
    if not group:
        return
    starts, words = word_hashes(np.frombuffer(b"\n".join(group), np.uint8))
    offsets = np.cumsum([0] + [len(g) + 1 for g in group])
    bounds = np.searchsorted(starts, offsets)
    runs = _combined(words, width)
    for first, last in zip(bounds[:-1], bounds[1:], strict=True):
        if last - first >= width:
            yield np.unique(runs[first : last - width + 1])
        elif last > first:
            yield _combined(words[first:last], int(last - first))
        else:
            yield np.zeros(0, np.uint64)
