"""Bit vectors with constant-time rank and select, and variable-length codes with direct access."""

from __future__ import annotations

from functools import cached_property

import numpy as np

WORD = 64


class BitVec:
    """Bits packed in 64-bit words beside the number of ones before each word."""

    def __init__(self, bits: np.ndarray | str | list[int]):
        if isinstance(bits, str):
            bits = np.frombuffer(bits.encode(), np.uint8) - 48
        bits = np.asarray(bits, np.uint8)
        self.n = len(bits)
        padded = np.zeros(-(-max(self.n, 1) // WORD) * WORD, np.uint8)
        padded[: self.n] = bits
        self.words = np.packbits(padded, bitorder="little").view(np.uint64)
        self.before = np.r_[0, np.cumsum(np.bitwise_count(self.words))].astype(np.int64)

    @classmethod
    def from_bytes(cls, raw: bytes, n: int) -> BitVec:
        out = cls.__new__(cls)
        out.n, out.words = n, np.frombuffer(raw, np.uint64)
        out.before = np.r_[0, np.cumsum(np.bitwise_count(out.words))].astype(np.int64)
        return out

    @cached_property
    def zeros(self) -> np.ndarray:
        """Zeros before each word, made once where a select asks for it."""
        return np.arange(len(self.before)) * WORD - self.before

    def to_bytes(self) -> bytes:
        return self.words.tobytes()

    def __len__(self) -> int:
        return self.n

    def get(self, i: int) -> int:
        i = int(i)  # numpy integers would overflow below
        return int(self.words[i // WORD]) >> (i % WORD) & 1

    def rank1(self, i: int) -> int:
        """Ones at positions 0..i (inclusive); 0 for i = -1."""
        if i < 0:
            return 0
        w, r = divmod(int(i) + 1, WORD)
        rest = int(self.words[w]) & ((1 << r) - 1) if r else 0
        return int(self.before[w]) + rest.bit_count()

    def rank0(self, i: int) -> int:
        return i + 1 - self.rank1(i)

    def get_many(self, i: np.ndarray) -> np.ndarray:
        return (self.words[i >> 6] >> (i & 63).astype(np.uint64) & np.uint64(1)).astype(bool)

    def rank1_many(self, i: np.ndarray) -> np.ndarray:
        """``rank1`` of an array of positions, each at least 0."""
        w, r = (i + 1) >> 6, ((i + 1) & 63).astype(np.uint64)
        rest = self.words[np.minimum(w, len(self.words) - 1)] & ((np.uint64(1) << r) - np.uint64(1))
        return self.before[w] + np.bitwise_count(rest).astype(np.int64)

    def select0_many(self, j: np.ndarray) -> np.ndarray:
        """Positions of the j-th zeros, j from 1: the word by its directory, then halves of it by counts."""
        w = np.searchsorted(self.zeros, j, "left") - 1
        word, left = ~self.words[w], (j - self.zeros[w]).astype(np.int64)
        at = w * WORD
        for half in (32, 16, 8, 4, 2, 1):
            below = np.bitwise_count(word & np.uint64((1 << half) - 1)).astype(np.int64)
            hop = left > below
            left -= np.where(hop, below, 0)
            word = np.where(hop, word >> np.uint64(half), word)
            at = at + np.where(hop, half, 0)
        return at

    def select1(self, j: int) -> int:
        """Position of the j-th one, j from 1; -1 for j = 0."""
        if j == 0:
            return -1
        if not 0 < j <= self.before[-1]:
            raise IndexError(j)
        w = int(np.searchsorted(self.before, j, "left")) - 1
        return w * WORD + _nth(int(self.words[w]), j - int(self.before[w]))

    def select0(self, j: int) -> int:
        if j == 0:
            return -1
        if not 0 < j <= self.n - self.before[-1]:
            raise IndexError(j)
        w = int(np.searchsorted(self.zeros, j, "left")) - 1
        return w * WORD + _nth(~int(self.words[w]) & (2**WORD - 1), j - int(self.zeros[w]))

    def size_bits(self, directory: bool = False) -> int:
        return self.n + (64 * len(self.before) if directory else 0)


def _nth(word: int, j: int) -> int:
    for _ in range(j - 1):
        word &= word - 1
    return (word & -word).bit_length() - 1


def zigzag(v: np.ndarray) -> np.ndarray:
    """Signed to unsigned so that small magnitudes stay small."""
    v = np.asarray(v, np.int64)
    return ((v << 1) ^ (v >> 63)).view(np.uint64)


def unzigzag(u: np.ndarray) -> np.ndarray:
    return ((u >> np.uint64(1)) ^ (np.uint64(0) - (u & np.uint64(1)))).view(np.int64)


class Dac:
    """Unsigned numbers in chunks of ``width`` bits; a bit beside each chunk says whether more follow."""

    def __init__(self, values: np.ndarray, width: int = 4):
        left = np.asarray(values, np.uint64)
        self.width, self.n = width, len(left)
        self.chunks: list[np.ndarray] = []
        self.more: list[BitVec] = []
        while True:
            self.chunks.append((left & np.uint64((1 << width) - 1)).astype(np.uint64))
            rest = left >> np.uint64(width)
            go = rest > 0
            self.more.append(BitVec(go))
            if not go.any():
                break
            left = rest[go]

    def get(self, i: int) -> int:
        out = shift = level = 0
        while True:
            out |= int(self.chunks[level][i]) << shift
            if not self.more[level].get(i):
                return out
            i = self.more[level].rank1(i) - 1
            shift, level = shift + self.width, level + 1

    def get_many(self, i: np.ndarray) -> np.ndarray:
        out = np.zeros(len(i), np.uint64)
        left, at = np.arange(len(i)), np.asarray(i, np.int64)
        for level, (chunk, more) in enumerate(zip(self.chunks, self.more)):
            out[left] |= chunk[at] << np.uint64(level * self.width)
            go = more.get_many(at)
            left, at = left[go], more.rank1_many(at[go]) - 1
        return out

    def all(self) -> np.ndarray:
        return self.get_many(np.arange(self.n))

    def to_bytes(self) -> bytes:
        """Width, then per level its length, its chunks of ``width`` bits and its continuation bits."""
        out = [np.array([self.width, len(self.chunks)], np.int64).tobytes()]
        places = np.arange(self.width, dtype=np.uint64)
        for chunk, more in zip(self.chunks, self.more):
            bits = (chunk[:, None] >> places & np.uint64(1)).astype(np.uint8)
            out += [np.array([len(chunk)], np.int64).tobytes(), np.packbits(bits.ravel(), bitorder="little").tobytes(), more.to_bytes()]
        return b"".join(out)

    @classmethod
    def from_bytes(cls, raw: bytes) -> Dac:
        out = cls.__new__(cls)
        width, levels = map(int, np.frombuffer(raw, np.int64, 2))
        out.width, out.chunks, out.more, at = width, [], [], 16
        weights = np.uint64(1) << np.arange(width, dtype=np.uint64)
        for _ in range(levels):
            n = int(np.frombuffer(raw, np.int64, 1, at)[0])
            size, words = -(-n * width // 8), 8 * -(-max(n, 1) // WORD)
            bits = np.unpackbits(np.frombuffer(raw, np.uint8, size, at + 8), bitorder="little")[: n * width]
            out.chunks.append((bits.reshape(n, width) * weights).sum(1, dtype=np.uint64))
            at += 8 + size
            out.more.append(BitVec.from_bytes(raw[at : at + words], n))
            at += words
        out.n = len(out.chunks[0])
        return out

    def size_bits(self) -> int:
        return sum(len(c) for c in self.chunks) * (self.width + 1)


def dac_bits(values: np.ndarray, width: int) -> int:
    """Size of ``Dac(values, width)`` without encoding."""
    return _bits_of_lengths(_lengths(values), width)


def _lengths(values: np.ndarray) -> np.ndarray:
    """How many values have each bit length (at least 1), by length."""
    bounds = np.uint64(1) << np.arange(1, 64, dtype=np.uint64)
    return np.bincount(1 + np.searchsorted(bounds, np.asarray(values, np.uint64), "right"), minlength=65)


def _bits_of_lengths(counts: np.ndarray, width: int) -> int:
    return int((counts * -(-np.arange(len(counts)) // width)).sum()) * (width + 1)


def dac_best_width(values: np.ndarray) -> int:
    return best_width(_lengths(values))[0]


def best_width(lengths: np.ndarray) -> tuple[int, int]:
    """Chunk width of the smallest code for values by bit length, and its bits."""
    bits, width = min((_bits_of_lengths(lengths, w), w) for w in range(1, 17))
    return width, bits


def dac_bits_sql(column: str, width: int, top: int = 63) -> str:
    """SQL for one value's bits by thresholds (exact, no logarithm)."""
    steps = " ".join(f"WHEN {column} < {1 << k} THEN {(k // width) * (width + 1)}" for k in range(width, top, width))
    return f"CASE {steps} ELSE {-(-top // width) * (width + 1)} END"
