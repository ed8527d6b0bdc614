"""64-bit hashes of white-space words of whole texts, vectorised and in bounded pieces."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np

from .common import SPACES, text_bytes

_U = np.uint64
_SPACE = np.zeros(256, bool)
_SPACE[list(SPACES.encode())] = True
_GAP = re.compile(rb"[\x20\x09-\x0d]")
_PIECE = 1 << 18


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads them evenly."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
        return x ^ (x >> _U(31))


class _Powers:
    """Powers of an odd base and of its inverse modulo 2^64, for hashes of any slice from prefix sums."""

    base, inverse = 0x9E3779B97F4A7C15, pow(0x9E3779B97F4A7C15, -1, 1 << 64)
    up = down = np.zeros(0, _U)
    letters = mix(np.arange(1, 257, dtype=_U) * _U(0xD1B54A32D192ED03))

    @classmethod
    def to(cls, n: int) -> None:
        if len(cls.up) < n:
            with np.errstate(over="ignore"):
                cls.up = np.cumprod(np.concatenate([[_U(1)], np.full(n, cls.base, _U)]))
                cls.down = np.cumprod(np.concatenate([[_U(1)], np.full(n, cls.inverse, _U)]))


def _piece_words(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    raw = np.frombuffer(data, np.uint8)
    gap = np.concatenate([[True], _SPACE[raw], [True]])
    starts, ends = np.flatnonzero(gap[:-1] & ~gap[1:]), np.flatnonzero(~gap[:-1] & gap[1:])
    _Powers.to(len(raw))
    with np.errstate(over="ignore"):
        total = np.concatenate([[_U(0)], np.cumsum(_Powers.letters[raw] * _Powers.up[: len(raw)])])
        return mix((total[ends] - total[starts]) * _Powers.down[starts] + (ends - starts).astype(_U)), starts, ends


def word_hashes(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A hash of each word of ``data`` and where it starts and ends; pieces of about a quarter of a megabyte are in work."""
    if len(data) <= 2 * _PIECE:
        return _piece_words(data)
    parts, at = [], 0
    while at < len(data):
        m = _GAP.search(data, at + _PIECE)
        end = m.start() if m else len(data)
        h, s, e = _piece_words(data[at:end])
        parts.append((h, s + at, e + at))
        at = end
    return tuple(np.concatenate([p[i] for p in parts]) for i in range(3))


def slices(texts: list[str | None], most: int = 1 << 20) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about ``most`` characters together, one text at least."""
    lo, size = 0, 0
    for i, t in enumerate(texts):
        n = len(t or "")
        if i > lo and size + n > most:
            yield lo, i
            lo, size = i, 0
        size += n
    if lo < len(texts):
        yield lo, len(texts)


def text_words(texts: list[str | None], lower: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, bytes]:
    """(hashes, (start, end) of each, cuts, bytes): the words of text i are those from cuts[i] up to cuts[i + 1].

    ``lower`` lower-cases A-Z.  The bytes are the texts with a space between, which the places refer to.
    """
    data = [text_bytes(t).lower() if lower else text_bytes(t) for t in texts]
    joined = b" ".join(data)
    hashes, starts, ends = word_hashes(joined)
    begins = np.cumsum([0] + [len(d) + 1 for d in data])
    return hashes, np.stack([starts, ends]), np.searchsorted(starts, begins), joined
