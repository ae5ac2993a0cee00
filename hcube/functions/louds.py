"""Level-order unary degree sequences of rooted ordered trees, and moves on them.

Nodes are named by the position where their own degree starts.  Positions count from 0
outside; the identities below are written for 1-based positions with select0(0) = 0 and
a rank of zeros strictly before the node (an inclusive one fails on leaves).
"""

from __future__ import annotations

import numpy as np

from .bits import BitVec


class Louds:
    def __init__(self, degrees: list[int] | None = None, bits: BitVec | None = None):
        self.bits = bits if bits is not None else BitVec([b for d in degrees for b in [1] * d + [0]])

    def _rank0_before(self, i: int) -> int:
        return self.bits.rank0(i - 1)

    def degree(self, i: int) -> int:
        return self.bits.select0(self._rank0_before(i) + 1) - i

    def child(self, i: int, k: int) -> int:
        """k-th child, k from 1."""
        if not 1 <= k <= self.degree(i):
            raise IndexError(k)
        return self.bits.select0(self.bits.rank1(i - 1) + k) + 1

    def parent(self, i: int) -> int:
        if i == 0:
            raise IndexError("the root has no parent")
        one = self.bits.select1(self._rank0_before(i))
        return self.bits.select0(one - self._rank0_before(i) + 1) + 1

    def ordinal(self, i: int) -> int:
        """Place among the parent's children, from 1."""
        return self.bits.select1(self._rank0_before(i)) - self.parent(i) + 1

    def depth(self, i: int) -> int:
        d = 0
        while i:
            i, d = self.parent(i), d + 1
        return d

    def path(self, i: int) -> list[int]:
        """Ordinals (from 0) to follow from the root."""
        out = []
        while i:
            out.append(self.ordinal(i) - 1)
            i = self.parent(i)
        return out[::-1]

    def node(self, number: int) -> int:
        """Position of the node with this number in level order, from 0."""
        return self.bits.select0(number) + 1

    def number(self, i: int) -> int:
        return self._rank0_before(i)


class LevelOrder:
    """Many nodes at once on the bits of a tree, by their numbers in level order.

    The places of ones and zeros are listed once, as select's directory.  ``lows[k]`` is
    the id of the first node of depth k where ids count the nodes of a depth.
    """

    def __init__(self, bits: BitVec, lows: list[int]):
        flat = np.unpackbits(bits.words.view(np.uint8), bitorder="little")[: len(bits)]
        self.ones, ends = np.flatnonzero(flat), np.flatnonzero(flat == 0)
        self.begins = np.r_[0, ends[:-1] + 1]
        self.fan = ends - self.begins
        # Ones before a node's own are the nodes before its first child, the root's left out.
        self.first = self.begins - np.arange(len(ends)) + 1
        self.lows = np.array(lows, np.int64)
        base = [0]
        for _ in lows[1:]:
            base.append(int(self.first[base[-1]]) if base[-1] < len(self.first) else len(ends))
        self.base = np.array(base, np.int64)

    def parents(self, number: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Parents' numbers and the places among their children, both from 0."""
        at = self.ones[number - 1]
        parent = at - (number - 1)
        return parent, at - self.begins[parent]

    def paths(self, depth: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """Children to follow from the root to each node, walked upwards; a row per node."""
        deepest = int(depth.max(initial=0))
        out = np.zeros((len(depth), deepest), np.int64)
        now = np.where(depth > 0, self.base[depth] + ids - self.lows[depth], 0)
        for k in range(deepest, 0, -1):
            on = np.flatnonzero(depth >= k)
            now[on], out[on, k - 1] = self.parents(now[on])
        return out if deepest else np.zeros((len(depth), 1), np.int64)
