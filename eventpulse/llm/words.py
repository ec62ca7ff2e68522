"""Words and word shingles of many texts at once, as 64-bit hashes in numpy."""

from __future__ import annotations

import numpy as np

_U = np.uint64
_R = _U(0x9E3779B97F4A7C15 | 1)
_INV = _U(pow(int(_R), -1, 1 << 64))
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_POWERS: dict[str, np.ndarray] = {"up": np.ones(1, _U), "down": np.ones(1, _U)}


def mix(x: np.ndarray) -> np.ndarray:
    """Spread every bit over all others (a bijection of 64-bit numbers)."""
    x = x ^ (x >> _U(32))
    x = x * _U(0xD6E8FEB86659FD93)
    x = x ^ (x >> _U(32))
    x = x * _U(0xD6E8FEB86659FD93)
    return x ^ (x >> _U(32))


_ODD = mix(np.arange(1, 17, dtype=np.uint64) * _R) | _U(1)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS["up"]) < n:
        for name, r in (("up", _R), ("down", _INV)):
            a = np.full(n, r, _U)
            a[0] = 1
            _POWERS[name] = np.cumprod(a, dtype=_U)
    return _POWERS["up"], _POWERS["down"]


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words (runs without ASCII white space), and where each text's begin: the
    words of text i are ``hashes[first[i]:first[i + 1]]``."""
    joined = b" ".join([*texts, b""])
    a = np.frombuffer(joined, dtype=np.uint8)
    starts_of = np.concatenate([[0], np.cumsum([len(t) + 1 for t in texts])]).astype(np.int64)
    gap = np.concatenate([[True], _SPACE[a], [True]])
    begin = np.flatnonzero(gap[:-1] & ~gap[1:])
    end = np.flatnonzero(~gap[:-1] & gap[1:])
    up, down = _powers(len(a) + 1)
    sums = np.zeros(len(a) + 1, _U)
    np.cumsum((a.astype(_U) + _U(1)) * up[: len(a)], out=sums[1:])
    h = (sums[end] - sums[begin]) * down[begin]
    return mix(h + (end - begin).astype(_U) * _ODD[7]), np.searchsorted(begin, starts_of)


def shingle_sets(texts: list[bytes], words: int = 5) -> list[np.ndarray]:
    """Sorted distinct hashes of each text's shingles of ``words`` words. A shorter text's whole
    sequence is its one shingle; a text without words has none."""
    h, first = word_hashes(texts)
    n = max(len(h) - words + 1, 0)
    runs = np.zeros(n, _U)
    for k in range(words):
        runs += h[k : k + n] * _ODD[k]
    runs = mix(runs)
    out = []
    for lo, hi in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if hi - lo >= words:
            s = np.sort(runs[lo : hi - words + 1])
            out.append(s[np.concatenate([[True], s[1:] != s[:-1]])])
        elif hi > lo:
            own = np.sum(h[lo:hi] * _ODD[: hi - lo], keepdims=True) + _ODD[9:10] * _U(hi - lo)
            out.append(mix(own))
        else:
            out.append(np.zeros(0, _U))
    return out
