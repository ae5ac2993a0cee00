"""Compact form of the regular tree: one bit per block slot, values in level order, box sums by rank.

Every opened block has k^n children, so a child's own children start at its rank times
k^n and no limits are stored.  Shards are the subtrees below the blocks of a cut depth.
"""

from __future__ import annotations

import time
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import BitVec, Dac, dac_best_width, unzigzag, zigzag


class RegularSequences:
    """T (occupancy without the last level) and V of a tree with k children per dimension."""

    def __init__(self, bits: BitVec, values: Dac, n: int, k: int, height: int):
        self.t, self.v, self.n, self.k, self.height = bits, values, n, k, height

    @classmethod
    def build(cls, root: int, levels: list[tuple[np.ndarray, np.ndarray]], n: int, k: int) -> RegularSequences:
        """``levels[d]``: coordinates (rows of n) of the nonempty blocks of depth d + 1 below the root, and sums."""
        bits, values = [], [np.array([root], np.int64)]
        for d, (blocks, value) in enumerate(levels):
            steps = [_slot(blocks // k ** (d - j) % k, k) for j in range(d + 1)]
            order = np.lexsort(steps[::-1])
            above = np.array(steps[:-1], np.int64).reshape(d, len(value))[:, order]
            parent = np.r_[0, np.cumsum((above[:, 1:] != above[:, :-1]).any(0))]
            at = parent * k**n + steps[-1][order]
            level = np.zeros((parent[-1] + 1) * k**n, np.int64)
            level[at] = value[order]
            values.append(level)
            if d < len(levels) - 1:
                full = np.zeros(len(level), np.uint8)
                full[at] = 1
                bits.append(full)
        coded = zigzag(np.concatenate(values))
        return cls(BitVec(np.concatenate(bits) if bits else []), Dac(coded, dac_best_width(coded)), n, k, len(levels))

    def child(self, position: int) -> int | None:
        """Where the children of the block at a slot position start; None where it is empty or a cell."""
        if position >= len(self.t) or not self.t.get(position):
            return None
        return self.t.rank1(position) * self.k**self.n

    def cell(self, point: list[int]) -> int:
        start = 0
        for d in range(1, self.height + 1):
            at = start + int(_slot(np.array([point]) // self.k ** (self.height - d) % self.k, self.k)[0])
            if d == self.height:
                return int(unzigzag(self.v.get_many(np.array([at + 1])))[0])
            if (nxt := self.child(at)) is None:
                return 0
            start = nxt
        return int(unzigzag(self.v.get_many(np.zeros(1, np.int64)))[0])

    def box_sums(self, lo: np.ndarray, hi: np.ndarray, step: int = 1 << 16) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Sums, blocks summed and blocks met for boxes (rows of n bounds, inclusive, from the root's corner)."""
        parts = [self._box_sums(lo[i : i + step], hi[i : i + step]) for i in range(0, len(lo), step)]
        return tuple(np.concatenate(x) for x in zip(*parts)) if parts else (np.empty(0, np.int64),) * 3

    def _box_sums(self, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        n, k, count = self.n, self.k, len(lo)
        whole = ((lo <= 0) & (hi >= k**self.height - 1)).all(1)
        total, summed, met = np.zeros(count, np.int64), whole.astype(np.int64), np.ones(count, np.int64)
        total[whole] = unzigzag(self.v.get_many(np.zeros(1, np.int64)))[0]
        q = np.flatnonzero(~whole)
        corner, start = np.zeros((len(q), n), np.int64), np.zeros(len(q), np.int64)
        for d in range(1, self.height + 1):
            side = k ** (self.height - d)
            # Children that the box reaches, listed dimension by dimension.
            row, digit, slot = np.arange(len(q)), np.empty((len(q), 0), np.int64), np.zeros(len(q), np.int64)
            for i in range(n):
                low = np.maximum(lo[q[row], i] // side - corner[row, i] * k, 0)
                many = np.maximum(np.minimum(hi[q[row], i] // side - corner[row, i] * k, k - 1) - low + 1, 0)
                take = np.repeat(np.arange(len(row)), many)
                mine = low[take] + np.arange(len(take)) - np.repeat(np.cumsum(many) - many, many)
                row, slot = row[take], slot[take] + mine * k**i
                digit = np.c_[digit[take], mine]
            asks, block, at = q[row], corner[row] * k + digit, start[row] + slot
            met += np.bincount(asks, minlength=count)
            inside = ((lo[asks] <= block * side) & (block * side + side - 1 <= hi[asks])).all(1)
            np.add.at(total, asks[inside], unzigzag(self.v.get_many(at[inside] + 1)))
            summed += np.bincount(asks[inside], minlength=count)
            if d == self.height:
                break
            go = ~inside
            go[go] = self.t.get_many(at[go])
            q, corner, start = asks[go], block[go], self.t.rank1_many(at[go]) * k**n
        return total, summed, met

    def size_bits(self) -> dict[str, int]:
        return {"occupancy": len(self.t), "values": self.v.size_bits()}


def _slot(digits: np.ndarray, k: int) -> np.ndarray:
    """Child number from a row of digits, first dimension fastest."""
    return (digits * k ** np.arange(digits.shape[1])).sum(1)


def sequences(tree: dict[int, DataFrame], n: int, k: int) -> RegularSequences:
    """The whole tree as one pair of sequences, for cubes small enough for the driver (fixtures)."""
    b = [f"b{i}" for i in range(1, n + 1)]
    found = [np.array([tuple(r) for r in tree[d].select(*b, "total").collect()], np.int64) for d in range(1, max(tree) + 1)]
    return RegularSequences.build(tree[0].first()["total"], [(x[:, :-1], x[:, -1]) for x in found], n, k)


def choose_cut(tree: dict[int, DataFrame], n: int, k: int, most: int = 1 << 21) -> int:
    """The shallowest depth whose fullest block holds at most ``most`` cells."""
    h = max(tree)
    for cut in range(h):
        side = k ** (h - cut)
        cells = tree[h].groupBy(*[F.expr(f"b{i} div {side}").alias(f"s{i}") for i in range(1, n + 1)]).agg(F.count("*").alias("cells"))
        if (cells.agg(F.max("cells")).first()[0] or 0) <= most:
            return cut
    return h


def pack(tree: dict[int, DataFrame], n: int, k: int, cut: int = 1) -> DataFrame:
    """``(s1..sn, t, n_t, v, bits)``: one row per nonempty block of depth ``cut``, at most k^(n (h - cut)) cells each."""
    h = max(tree)
    b, s = [f"b{i}" for i in range(1, n + 1)], [f"s{i}" for i in range(1, n + 1)]
    parts = []
    for d in range(cut, h + 1):
        reach = k ** (d - cut)
        own = [F.expr(f"{x} div {reach}").alias(y) for x, y in zip(b, s)]
        parts.append(tree[d].select(*own, F.lit(d).alias("depth"), *[F.expr(f"{x} % {reach}").alias(x) for x in b], "total"))

    def one(table: pa.Table) -> pa.Table:
        depth = table["depth"].to_numpy()
        blocks, value = np.stack([table[x].to_numpy() for x in b], 1), table["total"].to_numpy()
        seq = RegularSequences.build(int(value[depth == cut][0]), [(blocks[depth == d], value[depth == d]) for d in range(cut + 1, h + 1) if (depth > cut).any()], n, k)
        return pa.table({**{x: table[x][:1] for x in s}, "t": [seq.t.to_bytes()], "n_t": [len(seq.t)], "v": [seq.v.to_bytes()], "bits": [sum(seq.size_bits().values())]})

    return reduce(DataFrame.unionByName, parts).groupBy(*s).applyInArrow(one, ", ".join(f"{x} long" for x in s) + ", t binary, n_t long, v binary, bits long")


def walk(shards: DataFrame, boxes: DataFrame, n: int, k: int, h: int, cut: int = 1) -> DataFrame:
    """Box sums over shards: ``(qid, total, n_summed, n_visited, nanos)``.

    A box goes to each shard it meets; counts are those of the shards' own walks (what
    lies above the cut is not walked), ``nanos`` the time spent in them.
    """
    side = k ** (h - cut)
    s = [f"s{i}" for i in range(1, n + 1)]
    wide = boxes
    for i in range(1, n + 1):
        wide = wide.withColumn(f"s{i}", F.explode(F.expr(f"sequence(greatest(lo_{i} div {side}, 0L), least(hi_{i} div {side}, {k**cut - 1}L))")))
    wide = wide.select("qid", *s, *[F.expr(f"{e}_{i} - s{i} * {side}").alias(f"{e}_{i}") for e in ("lo", "hi") for i in range(1, n + 1)])

    def run(asked: pa.Table, shard: pa.Table) -> pa.Table:
        count = asked.num_rows
        total, summed, met, took = (np.zeros(count, np.int64) for _ in range(4))
        if shard.num_rows and count:
            x = shard.to_pylist()[0]
            seq = RegularSequences(BitVec.from_bytes(x["t"], x["n_t"]), Dac.from_bytes(x["v"]), n, k, h - cut)
            lo, hi = (np.stack([asked[f"{e}_{i}"].to_numpy() for i in range(1, n + 1)], 1) for e in ("lo", "hi"))
            began = time.perf_counter_ns()
            total, summed, met = seq.box_sums(lo, hi)
            took[0] = time.perf_counter_ns() - began
        return pa.table({"qid": asked["qid"], "total": total, "n_summed": summed, "n_visited": met, "nanos": took})

    found = wide.groupBy(*s).cogroup(shards.groupBy(*s)).applyInArrow(run, "qid long, total long, n_summed long, n_visited long, nanos long")
    values = ("total", "n_summed", "n_visited", "nanos")
    got = found.groupBy("qid").agg(*[F.sum(c).alias(c) for c in values])
    return boxes.select("qid").join(got, "qid", "left").na.fill(0)
