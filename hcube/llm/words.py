"""Words of many texts at once: spans and 64-bit hashes of a joined byte buffer."""

from __future__ import annotations

import numpy as np

U = np.uint64
_BASE = U(0x9E3779B97F4A7C15)
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Bytes that are hashed at once, and numbers that are mixed at once: what they need stays in a core's cache.
PIECE, STEP = 1 << 16, 1 << 15

_powers: list[np.ndarray] = []


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse, modulo 2^64."""
    if not _powers or len(_powers[0]) < n:
        size = max(n, 4 * PIECE + 4096)
        inverse = U(pow(int(_BASE), -1, 1 << 64))
        tables = [np.full(size, b, U) for b in (_BASE, inverse)]
        for t in tables:
            t[0] = 1
            np.multiply.accumulate(t, out=t)
        _powers[:] = tables
    return _powers[0], _powers[1]


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser: every bit of the result depends on every bit of x."""
    out = np.empty(x.shape, U)
    flat, to = x.reshape(-1), out.reshape(-1)
    for a in range(0, len(flat), STEP):
        y, z = flat[a : a + STEP], to[a : a + STEP]
        t = y >> U(30)
        np.bitwise_xor(y, t, out=z)
        for times, by in ((0xBF58476D1CE4E5B9, 27), (0x94D049BB133111EB, 31)):
            z *= U(times)
            np.right_shift(z, U(by), out=t)
            z ^= t
    return out


def distinct(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct keys (hashes), where each was first, and the number of every key.

    Like ``numpy.unique``, several times faster: the upper bits are sorted with the places
    in the lower ones, and the few keys that these can't tell apart are sorted again.
    """
    n = len(keys)
    if not n:
        return keys, np.empty(0, np.int64), np.empty(0, np.int64)
    low = U((1 << max(n - 1, 1).bit_length()) - 1)
    packed = np.sort((keys & ~low) | np.arange(n, dtype=U))
    order = (packed & low).astype(np.int64)
    packed &= ~low
    ranked = keys[order]
    new = ranked[1:] != ranked[:-1]
    same = packed[1:] == packed[:-1]
    if (new & same).any():
        run = np.cumsum(np.r_[False, ~same])
        mixed = np.zeros(run[-1] + 1, bool)
        mixed[run[1:][new & same]] = True
        at = np.flatnonzero(mixed[run])
        again = at[np.lexsort((order[at], ranked[at]))]
        order[at], ranked[at] = order[again], ranked[again]
        new = ranked[1:] != ranked[:-1]
    new = np.r_[True, new]
    number = np.empty(n, np.int64)
    number[order] = np.cumsum(new) - 1
    return ranked[new], order[new], number


def spans(buf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words of a buffer."""
    word = ~_SPACE[buf]
    edge = np.flatnonzero(np.diff(np.r_[False, word, False]))
    return edge[::2], edge[1::2]


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the lower-cased (A-Z) words of all texts, and how many each text has."""
    hashes: list[np.ndarray] = []
    counts: list[np.ndarray] = []
    at = 0
    while at < len(texts):
        upto, size = at, 0
        while upto < len(texts) and (not size or size + len(texts[upto]) < PIECE):
            size += len(texts[upto]) + 1
            upto += 1
        part = texts[at:upto]
        buf = np.frombuffer(b"\n".join(part) + b"\n", np.uint8)
        starts, ends = spans(buf)
        if len(buf) <= 4 * PIECE:
            hashes.append(_hash(buf, starts, ends))
        else:  # one very long text: words in runs, so that the tables stay small
            cuts = np.searchsorted(starts, np.arange(0, len(buf), PIECE))
            for a, b in zip(cuts, [*cuts[1:], len(starts)]):
                if b > a:
                    lo, hi = starts[a], ends[b - 1]
                    hashes.append(_hash(buf[lo:hi], starts[a:b] - lo, ends[a:b] - lo))
        stops = np.cumsum([len(t) + 1 for t in part])
        counts.append(np.diff(np.r_[0, np.searchsorted(starts, stops)]))
        at = upto
    if not hashes:
        return np.empty(0, U), np.zeros(len(texts), np.int64)
    return np.concatenate(hashes), np.concatenate(counts)


def _hash(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    power, inverse = _power_tables(len(buf) + 1)
    sums = np.zeros(len(buf) + 1, U)
    np.cumsum((_LOWER[buf].astype(U) + U(1)) * power[: len(buf)], out=sums[1:])
    return mix((sums[ends] - sums[starts]) * inverse[starts] + (ends - starts).astype(U) * U(0xD6E8FEB86659FD93))
