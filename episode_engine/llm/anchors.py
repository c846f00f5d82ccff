"""Content-defined anchors: which window of fixed length belongs to which k-gram.

Of the k-grams inside a window the one with the smallest hash (the leftmost of equals) is its anchor. Equal windows
have equal anchors wherever they stand, so windows that two documents share are found among equal anchors.
"""

from __future__ import annotations

import numpy as np

_U = np.uint64
_LOW = _U(2**32 - 1)
_B = 0x9E3779B97F4A7C15 | 1
_powers: dict[str, np.ndarray] = {}


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(32))) * _U(0xD6E8FEB86659FD93)
    x = (x ^ (x >> _U(29))) * _U(0xBF58476D1CE4E5B9)
    return x ^ (x >> _U(32))


def _pow(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2 ** 64."""
    if len(_powers.get("up", ())) < n:
        inverse = pow(_B, -1, 2**64)
        for name, base in (("up", _B), ("down", inverse)):
            x = np.full(n, base, dtype=np.uint64)
            x[0] = 1
            _powers[name] = np.multiply.accumulate(x)
    return _powers["up"][:n], _powers["down"][:n]


def _byte_codes() -> np.ndarray:
    return np.random.default_rng(4).integers(1, 2**63, 256, dtype=np.uint64)


CODES = _byte_codes()


#: Windows that are looked at together, which bounds memory for a text of any length. A run that is cut here is two runs.
STEP = 1 << 19


def anchor_runs(data: np.ndarray, starts: np.ndarray, length: int, k: int) -> tuple[np.ndarray, ...]:
    """Runs of windows with one anchor: first window start, how many, place of the anchor, its hash, hash of all the bytes they cover.

    data: bytes of several documents one after another; starts: where each begins, and the end. No window crosses a border.
    """
    found = []
    for at in range(0, max(1, len(data) - length + 1), STEP):
        part = data[at : at + STEP + length - 1]
        lo, hi = np.searchsorted(starts, (at, at + len(part)), side="right")
        first, count, anchor, gram, cover = _runs(part, starts[lo:hi] - at, length, k)
        found.append((first + at, count, anchor + at, gram, cover))
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def _runs(data: np.ndarray, borders: np.ndarray, length: int, k: int) -> tuple[np.ndarray, ...]:
    n = len(data)
    if n < length:
        return *(np.zeros(0, np.int64) for _ in range(3)), *(np.zeros(0, np.uint64) for _ in range(2))
    up, down = _pow(n + 1)
    total = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum(CODES[data] * up[:n], out=total[1:])
    grams = total[k:] - total[:-k]
    grams *= down[: len(grams)]
    grams = _mix(grams)
    v = (grams & ~_LOW) | np.arange(len(grams), dtype=np.uint64)
    width, have = length - k + 1, 1
    while have < width:  # minimum over `have` neighbours, doubled until it is over `width`
        step = min(have, width - have)
        v = np.minimum(v[:-step], v[step:])
        have += step
    anchor = (v & _LOW).astype(np.int64)
    inside = np.ones(len(anchor), dtype=bool)
    for e in borders.tolist():  # windows that would run over a document's end
        inside[max(0, e - length + 1) : e] = False
    change = np.flatnonzero(np.concatenate(([True], (anchor[1:] != anchor[:-1]) | (inside[1:] != inside[:-1]))))
    ends = np.append(change[1:], len(anchor))
    ok = inside[change]
    first, count = change[ok], (ends - change)[ok]
    stop = first + count - 1 + length
    covered = _mix((total[stop] - total[first]) * down[first] + (stop - first).astype(np.uint64) * _U(0x94D049BB133111EB))
    # Anchors have small hashes by choice; mixed once more, they spread evenly.
    return first, count, anchor[first], _mix(grams[anchor[first]] + _U(1)), covered
