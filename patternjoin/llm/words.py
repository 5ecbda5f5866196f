"""Digests of all words of a block of texts, without a Python object for a word."""

from __future__ import annotations

from functools import lru_cache

import numpy as np

MIX = np.uint64(0x9E3779B97F4A7C15)
MULT = np.uint64(0xD6E8FEB86659FD93)
#: What each byte weighs in a word's digest: the splitmix sequence.
_BYTE = (np.arange(1, 257, dtype=np.uint64) * MIX)
_BYTE = (_BYTE ^ (_BYTE >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
_BYTE ^= _BYTE >> np.uint64(27)
_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True


@lru_cache(maxsize=2)
def _known_powers(base: int) -> np.ndarray:
    return _count_up(base, 1 << 20)


def _count_up(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[:1] = 1
    return np.cumprod(out)


def _powers(base: int, n: int) -> np.ndarray:
    known = _known_powers(base)
    return known[:n] if n <= len(known) else _count_up(base, n)


_INVERSE = pow(int(MIX), -1, 1 << 64)


def word_digests(raws: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit digests of the words of all texts in one array, and the place of each text's first word.

    A word's digest is the sum of its bytes' weights times powers of an odd base, mixed with its
    length; prefix sums over the whole block give all of them without a Python object for a word.
    """
    data = np.frombuffer(b" ".join(raws).lower() + b" ", np.uint8)
    sizes = np.fromiter(map(len, raws), np.int64, len(raws)) + 1
    space = _IS_SPACE[data]
    edge = np.diff(np.concatenate([[True], space]).astype(np.int8))
    first, stop = np.nonzero(edge < 0)[0], np.nonzero(edge > 0)[0]
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_BYTE[data] * _powers(int(MIX), len(data)), out=sums[1:])
    h = (sums[stop] - sums[first]) * _powers(_INVERSE, len(data))[first]
    h += (stop - first).astype(np.uint64)
    h ^= h >> np.uint64(31)
    h *= MULT
    return h ^ (h >> np.uint64(29)), np.searchsorted(first, np.cumsum(sizes) - sizes)
