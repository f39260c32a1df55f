"""Word and shingle hashes of whole texts, a block of texts at a time.

Words are runs of bytes between ASCII white space, after A-Z are lower-cased. A word's hash is a
polynomial of its bytes modulo 2^64, finished by a bit mixer; it comes from one running sum over
a window, so its cost does not depend on how many words there are. A shingle's hash mixes the
hashes of its words in order.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

_U = np.uint64
_ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], dtype=_U)
_BASE = 0x5851F42D4C957F2D
#: Bytes looked at at once.
WINDOW = 1 << 19
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_BYTES = (np.arange(1, 257, dtype=_U) * _U(0x9FB21C651E98DF25)) ^ _U(0x2545F4914F6CDD1D)
_POWER = np.ones(1, _U)
_INVERSE = np.ones(1, _U)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective mixer of 64-bit words."""
    x = x ^ (x >> _U(33))
    x = x * _U(0xFF51AFD7ED558CCD)
    x ^= x >> _U(33)
    x *= _U(0xC4CEB9FE1A85EC53)
    x ^= x >> _U(33)
    return x


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse; those of one window are kept."""
    global _POWER, _INVERSE
    if len(_POWER) > n:
        return _POWER, _INVERSE
    size = max(n, WINDOW)
    with np.errstate(over="ignore"):
        power = np.cumprod(np.concatenate([np.ones(1, _U), np.full(size, _BASE, _U)]))
        inverse = np.cumprod(np.concatenate([np.ones(1, _U), np.full(size, pow(_BASE, -1, 1 << 64), _U)]))
    if size == WINDOW:
        _POWER, _INVERSE = power, inverse
    return power, inverse


def _windows(data: np.ndarray) -> Iterator[tuple[int, int]]:
    """Ranges of about ``WINDOW`` bytes that end behind white space; a longer word has its own."""
    at = 0
    while at < len(data):
        stop = at + WINDOW
        if stop < len(data):
            gaps = np.flatnonzero(_SPACE[data[at:stop]])
            if len(gaps):
                stop = at + int(gaps[-1]) + 1
            else:
                while stop < len(data) and not (gaps := np.flatnonzero(_SPACE[data[stop : stop + WINDOW]])).size:
                    stop += WINDOW
                stop = stop + int(gaps[0]) + 1 if stop < len(data) else len(data)
        yield at, min(stop, len(data))
        at = stop


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of all texts, and where each text's words end.

    Bytes are looked at a window at a time, so beside the hashes the memory does not grow with a
    text (only with its longest word).
    """
    data = np.frombuffer(b"\n".join(t.lower() for t in texts) + b"\n", np.uint8)
    hashes, starts = [], []
    for lo, hi in _windows(data):
        part = data[lo:hi]
        power, inverse = _powers(len(part) + 1)
        space = _SPACE[part]
        edge = np.flatnonzero(np.diff(np.concatenate([[True], space, [True]]).astype(np.int8)))
        start, end = edge[0::2], edge[1::2]
        with np.errstate(over="ignore"):
            total = np.concatenate([np.zeros(1, _U), np.cumsum(_BYTES[part] * power[: len(part)])])
            h = (total[end] - total[start]) * inverse[start]
            hashes.append(mix(h + (end - start).astype(_U) * _ODD[0]))
        starts.append(start + lo)
    h, start = (np.concatenate(x) for x in (hashes, starts))
    stop = np.cumsum([len(t) + 1 for t in texts])
    return h, np.searchsorted(start, stop, "left")


def shingle_hashes(texts: list[bytes], width: int = 5) -> list[np.ndarray]:
    """For each text, its distinct shingles in rising order of hash.

    A text of fewer than ``width`` words has its whole word sequence as its one shingle; a text
    without words has none.
    """
    h, ends = word_hashes(texts)
    out: list[np.ndarray] = []
    odd = _ODD if width <= len(_ODD) else mix(np.arange(1, width + 1, dtype=_U)) | _U(1)
    with np.errstate(over="ignore"):
        n = max(0, len(h) - width + 1)
        all_ = np.zeros(n, _U)
        for j in range(width):
            all_ += h[j : j + n] * odd[j]
        all_ = mix(all_)
        at = 0
        for e in ends.tolist():
            if e - at >= width:
                out.append(np.unique(all_[at : e - width + 1]))
            elif e > at:
                own = h[at:e]
                out.append(mix(np.array([(own * odd[: e - at]).sum(dtype=_U) ^ _U(0x51ED270B7F4A7C15 + (e - at))], _U)))
            else:
                out.append(np.zeros(0, _U))
            at = e
    return out
