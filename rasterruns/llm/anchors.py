"""Content-chosen anchors: of every ``span`` bytes, one ``gram`` is picked the same way wherever they stand.

The anchor of a stretch of ``span`` bytes is the gram with the least mixed hash
in it (the leftmost of equals).  Two equal stretches hold the same anchor, so
documents that share a stretch share an anchor hash, at about 2 / (span - gram)
anchors a byte instead of one hash a byte.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

#: Bytes of a repeated stretch and of an anchor within it.
SPAN = 50
GRAM = 20
#: A window that holds an anchor starts at most so far before it.
BEFORE = SPAN - GRAM
#: Bytes hashed at once, and how longer texts overlap when they are cut for it.
_CHUNK = 1 << 20
_OVERLAP = 128
_U = np.uint64


def mixed(x: np.ndarray) -> np.ndarray:
    """64-bit words, bits well spread."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
        return x ^ (x >> _U(31))


def _table(seed: int) -> np.ndarray:
    """256 mixed words, by rule from the seed."""
    with np.errstate(over="ignore"):
        return mixed(np.arange(1, 257, dtype=_U) * _U(0x9E3779B97F4A7C15) + _U(seed))


_BASE, _BASE_C = 0xD6E8FEB86659FD93, 0xA0761D6478BD642F
_T, _TC = _table(1), _table(2)
_powers: dict = {}


def _power_pair(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the context base and of its inverse modulo 2^64."""
    if _powers.get("n", 0) < n:
        inverse = pow(_BASE_C, -1, 1 << 64)
        with np.errstate(over="ignore"):
            for name, base in (("up", _BASE_C), ("down", inverse)):
                p = np.full(n, base, _U)
                p[0] = 1
                _powers[name] = np.cumprod(p)
        _powers["n"] = n
    return _powers["up"], _powers["down"]


def _grams(buf: np.ndarray, k: int) -> np.ndarray:
    """Polynomial hashes of all k-byte strings, by doubling."""
    with np.errstate(over="ignore"):
        whole, size = None, 0
        power, h, width = _BASE, _T[buf], 1
        bits = k
        while bits:
            if bits & 1:
                if whole is None:
                    whole, size = h, width
                else:
                    n = len(buf) - size - width + 1
                    whole, size = whole[:n] * _U(power % (1 << 64)) + h[size : size + n], size + width
            bits >>= 1
            if bits:
                n = len(h) - width
                h = h[:n] * _U(power % (1 << 64)) + h[width : width + n]
                power, width = power * power % (1 << 64), 2 * width
        return whole


def _window_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of every ``w`` neighbours."""
    width = 1
    while 2 * width <= w:
        x = np.minimum(x[:-width], x[width:])
        width *= 2
    return np.minimum(x[: len(x) - (w - width)], x[w - width :]) if w > width else x


def pieces(texts: list[bytes]) -> Iterator[tuple[list[int], list[int], list[bytes]]]:
    """Texts in runs of about _CHUNK bytes: text numbers, offsets of the pieces in their texts, pieces."""
    numbers, starts, parts, size = [], [], [], 0
    for i, t in enumerate(texts):
        for at in range(0, max(len(t), 1), _CHUNK):
            if len(t) < SPAN:
                continue
            lo, hi = max(0, at - _OVERLAP), min(len(t), at + _CHUNK + _OVERLAP)
            if hi - lo < SPAN:
                continue
            numbers.append(i)
            starts.append(lo)
            parts.append(t[lo:hi])
            size += hi - lo
            if size >= _CHUNK:
                yield numbers, starts, parts
                numbers, starts, parts, size = [], [], [], 0
    if parts:
        yield numbers, starts, parts


def find(parts: list[bytes], stretches: bool = True) -> tuple[np.ndarray, ...]:
    """Anchors of pieces: piece number, position in the piece, longest and shortest lead, anchor hash, stretch hash.

    Every SPAN-byte window belongs to the one anchor it picks.  The windows of
    an anchor start ``longest`` to ``shortest`` bytes before it; together they
    are its stretch.  The stretch hash tells equal texts with unlike leads apart.  Without
    ``stretches`` only the piece numbers and anchor hashes are meant.
    """
    lengths = np.array([len(p) for p in parts], np.int64)
    buf = np.frombuffer(b"".join(parts), np.uint8)
    ends = np.cumsum(lengths)
    with np.errstate(over="ignore"):
        g = _grams(buf, GRAM)
        key = ((g * _U(0x9FB21C651E98DF25)) & _U(0xFFFFFFFF00000000)) | np.arange(len(g), dtype=_U)
        least = _window_min(key, SPAN - GRAM + 1)
        window = np.flatnonzero(np.arange(len(least)) + SPAN <= np.repeat(ends, lengths)[: len(least)])
        at = (least[window] & _U(0xFFFFFFFF)).astype(np.int64)
        first = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
        last = np.append(first[1:], len(at)) - 1
        lo, hi, at = window[first], window[last] + SPAN, at[first]
        piece = np.searchsorted(ends, at, "right")
        if not stretches:
            return piece, at, at, at, g[at], at
        up, down = _power_pair(max(len(buf) + 1, _CHUNK + 4 * _OVERLAP))
        total = np.concatenate([np.zeros(1, _U), np.cumsum(_TC[buf] * up[: len(buf)])])
        longest, shortest = at - lo, at - (hi - SPAN)
        stretch = (total[hi] - total[lo]) * down[lo] + longest.astype(_U) * _U(0xE7037ED1A0B428DB) + shortest.astype(_U) * _U(0x8EBC6AF09C88C6E3)
        stretch ^= stretch >> _U(29)
    return piece, at - (ends - lengths)[piece], longest, shortest, g[at], stretch


def pack(at: np.ndarray, longest: np.ndarray, shortest: np.ndarray) -> np.ndarray:
    """Position and both leads (each at most BEFORE, below 32) in one integer."""
    return (at << 10) | (longest << 5) | shortest


def unpack(packed: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return packed >> 10, (packed >> 5) & 31, packed & 31


def anchor_batch(texts: list[bytes], stretches: bool = True) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """``(text number, packed place, anchor hash, stretch hash)`` of a batch of texts, hashes as signed."""
    for numbers, starts, parts in pieces(texts):
        piece, at, longest, shortest, h, c = find(parts, stretches)
        yield np.array(numbers, np.int64)[piece], pack(np.array(starts, np.int64)[piece] + at, longest, shortest), h.view(np.int64), c.view(np.int64)
