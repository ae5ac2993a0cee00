"""Compact form: occupancy bits, block limits and coded values, in shards of subtrees.

A shard is the subtree below one node of the cut depth, its sequences in level order from its own
root, beside the degree sequences of the hierarchies below that node's members; what lies
above the cut is a crown of a few rows that stays relational.  The cut is the shallowest
depth whose largest subtree holds at most ``CELLS`` cells (``choose_cut``), so one node
may be a whole small cube and no node of a large one is more than a task's work.  Only
whole shards cross into Python.
"""

from __future__ import annotations

import time
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import BitVec, Dac, dac_best_width, unzigzag, zigzag
from ..functions.louds import LevelOrder
from .hast import Tree


class Sequences:
    """T_a (occupancy, without the last level), T_c (unary block limits) and V of one tree."""

    def __init__(self, occupancy: BitVec, limits: BitVec, values: Dac, last: int):
        self.ta, self.tc, self.v, self.last = occupancy, limits, values, last

    @classmethod
    def build(cls, root: int, levels: list[tuple[np.ndarray, np.ndarray]], fans: list[tuple[np.ndarray, np.ndarray]]) -> Sequences:
        """``levels[d]``: slot paths of length d + 1 (rows) and values; ``fans[d]``: paths of length d and children.

        Paths in order are nodes in level order, so a node's parent is its prefix's rank.
        """
        bits, limits, values = [], [], [np.array([root], np.int64)]
        for d, ((paths, value), (parents, fan)) in enumerate(zip(levels, fans)):
            if d:
                fan = fan[np.lexsort(parents.T[::-1])]
            order = np.lexsort(paths.T[::-1])
            paths, value = paths[order], value[order]
            above = paths[:, :-1]
            parent = np.r_[0, np.cumsum((above[1:] != above[:-1]).any(1))]
            ends = np.cumsum(fan)
            at = ends[parent] - fan[parent] + paths[:, -1]
            level = np.zeros(ends[-1], np.int64)
            level[at] = value
            values.append(level)
            limit = np.ones(ends[-1], np.uint8)
            limit[ends - 1] = 0
            limits.append(limit)
            if d < len(levels) - 1:
                full = np.zeros(ends[-1], np.uint8)
                full[at] = 1
                bits.append(full)
        joined = lambda x: np.concatenate(x) if x else np.empty(0, np.uint8)
        coded = zigzag(np.concatenate(values))
        return cls(BitVec(joined(bits)), BitVec(joined(limits)), Dac(coded, dac_best_width(coded)), len(levels))

    def child(self, start: int, slot: int) -> int | None:
        """Start of the block of the children of a node's slot; None where it is empty."""
        i = start + slot
        if i >= len(self.ta) or not self.ta.get(i):
            return None
        # The root's own block comes first, so the j-th occupied slot has the (j + 1)-th block.
        return self.tc.select0(self.ta.rank1(i)) + 1

    def value(self, position: int) -> int:
        """Value at a slot's position; the root is V[0]."""
        return int(unzigzag(np.array([self.v.get(position + 1)], np.uint64))[0])

    def walk(self, path: list[int]) -> tuple[int, int]:
        """Value at a slot path from the root, and nodes met on the way."""
        start, visited = 0, 1
        for k, s in enumerate(path):
            visited += 1
            if k == len(path) - 1:
                return self.value(start + s), visited
            nxt = self.child(start, s)
            if nxt is None:
                return 0, visited
            start = nxt
        return int(unzigzag(np.array([self.v.get(0)], np.uint64))[0]), visited

    def walk_many(self, steps: list[list[int]]) -> tuple[int, int]:
        """Sum over all paths that take one of ``steps[k]`` at each step."""
        frontier, visited = [0], 1
        total = 0
        for k, slots in enumerate(steps):
            nxt = []
            for start in frontier:
                for s in slots(k, start) if callable(slots) else slots:
                    visited += 1
                    if k == len(steps) - 1:
                        total += self.value(start + s)
                    elif (child := self.child(start, s)) is not None:
                        nxt.append(child)
            frontier = nxt
        return total, visited

    def descend(self, hierarchies: list[LevelOrder], depth: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Sums, values summed and nodes met of many label queries at once, one depth of all of them at a time.

        Row q has by dimension the depth of its label below this root and the member's id
        there.  Each label's path is walked up its hierarchy's bits; then all queries go
        down together, in a dimension to the one child towards its label, below a reached
        label to all children, and end where a slot's bit is 0.  Counted are nodes that are
        not empty (at the last depth, whose bits aren't kept, those whose value isn't 0).
        """
        n, count = len(hierarchies), len(depth)
        total, summed, visited = np.zeros(count, np.int64), np.zeros(count, np.int64), np.ones(count, np.int64)
        deepest = depth.max(axis=1) if count else np.zeros(0, np.int64)
        paths = [x.paths(depth[:, i], ids[:, i]) for i, x in enumerate(hierarchies)]
        at_root = deepest == 0
        total[at_root] = unzigzag(self.v.get_many(np.zeros(1, np.int64)))[0]
        summed[at_root] = 1
        q = np.flatnonzero(~at_root)
        start, member = np.zeros(len(q), np.int64), [np.zeros(len(q), np.int64)] * n
        for k in range(1, int(deepest.max(initial=0)) + 1):
            low, many, fans = [], [], []
            every = np.ones(len(q), np.int64)
            for i, x in enumerate(hierarchies):
                fan, on_path = x.fan[member[i]], depth[q, i] >= k
                low.append(np.where(on_path, paths[i][q, min(k, paths[i].shape[1]) - 1], 0))
                many.append(np.where(on_path, 1, fan))
                fans.append(fan)
                every = every * many[i]
            if (every == 1).all():
                row, rest = slice(None), None
            else:
                row = np.repeat(np.arange(len(q)), every)
                rest = np.arange(len(row)) - np.repeat(np.cumsum(every) - every, every)
            at, radix, nxt = start[row].copy(), 1, []
            for i, x in enumerate(hierarchies):
                child = low[i][row]
                if rest is not None:
                    mine = many[i][row]
                    child = child + rest % mine
                    rest = rest // mine
                at += radix * child
                radix = radix * fans[i][row]
                nxt.append(x.first[member[i][row]] + child)
            q = q[row]
            last = deepest[q] == k
            if last.any():
                value = unzigzag(self.v.get_many(at[last] + 1))
                np.add.at(total, q[last], value)
                found = np.bincount(q[last][value != 0], minlength=count)
                summed += found
                visited += found
            full = ~last & (at < len(self.ta))
            full[full] = self.ta.get_many(at[full])
            q, member = q[full], [x[full] for x in nxt]
            visited += np.bincount(q, minlength=count)
            start = self.tc.select0_many(self.ta.rank1_many(at[full])) + 1
        return total, summed, visited

    def size_bits(self) -> dict[str, int]:
        return {"occupancy": len(self.ta), "limits": len(self.tc), "values": self.v.size_bits()}


def sequences_of(t: Tree, measure: str) -> Sequences:
    """The whole tree as one set of sequences, for cubes small enough for the driver (fixtures)."""
    h = t.cube.height
    levels, fans = [], []
    for k in range(1, h + 1):
        paths = [f"p_{j}" for j in range(1, k + 1)]
        for into, rows, width in ((levels, t.nodes[k].select(*paths, measure), k), (fans, _fans(t, k), k - 1)):
            found = np.array([tuple(r) for r in rows.collect()], np.int64).reshape(-1, width + 1)
            into.append((found[:, :-1], found[:, -1]))
    root = t.nodes[0].select(measure).first()[0]
    return Sequences.build(root, levels, fans)


def _fans(t: Tree, k: int) -> DataFrame:
    """Slot path of each nonempty node of depth k - 1 and how many slots it has."""
    paths = [f"p_{j}" for j in range(1, k)]
    rows, fan = t.nodes[k - 1], F.lit(1).cast("long")
    for d in t.cube.dims:
        on = [f"{d.name}_id_{k-1}"] if k > 1 else []
        fans = t.leaf[d.name].select(*[F.col(f"id_{k-1}").alias(c) for c in on], F.col(f"fan_{k}").alias(f"{d.name}_f")).distinct()
        rows = rows.join(F.broadcast(fans), on) if on else rows.crossJoin(F.broadcast(fans))
        fan = fan * F.col(f"{d.name}_f")
    return rows.select(*paths, fan.alias("fan"))


CELLS = 1 << 21
ASKED = 1 << 16


def _cut_keys(cut: int) -> list[str]:
    """Names of a shard's key; a cut at the root has one shard, key 0."""
    return [f"p_{j}" for j in range(1, cut + 1)] or ["p_0"]


def _keyed(rows: DataFrame, cut: int) -> DataFrame:
    return rows if cut else rows.withColumn("p_0", F.lit(0).cast("long"))


def shard_sizes(t: Tree, cut: int) -> DataFrame:
    """Cells below each node of depth ``cut``: what a shard of that cut would hold."""
    return _keyed(t.nodes[t.cube.height], cut).groupBy(*_cut_keys(cut)).agg(F.count("*").alias("cells"))


def choose_cut(t: Tree, most: int = CELLS) -> int:
    """The shallowest depth whose largest subtree holds at most ``most`` cells."""
    for cut in range(t.cube.height):
        if (shard_sizes(t, cut).agg(F.max("cells")).first()[0] or 0) <= most:
            return cut
    return t.cube.height


def hierarchies_below(t: Tree, dim, cut: int) -> DataFrame:
    """``(id, louds, n_louds, lows)`` of each member of depth ``cut``: its subtree's degrees in level order.

    ``lows[k]``: the first of its descendants' ids at depth ``cut + k``, which lie together.
    """
    h, leaf = t.cube.height, t.leaf[dim.name]
    top = F.col(f"id_{cut}") if cut else F.lit(0).cast("long")
    parts = []
    for k in range(cut, h + 1):
        mine = F.col(f"id_{k}") if k else F.lit(0).cast("long")
        fan = F.col(f"fan_{k + 1}") if k < h else F.lit(0)
        parts.append(leaf.select(top.alias("id"), F.lit(k).alias("depth"), mine.alias("member"), fan.cast("long").alias("fan")).distinct())

    def one(table: pa.Table) -> pa.Table:
        depth, member, fan = (table[c].to_numpy() for c in ("depth", "member", "fan"))
        fan = fan[np.lexsort((member, depth))]
        bits = np.ones(int(fan.sum()) + len(fan), np.uint8)
        bits[np.cumsum(fan + 1) - 1] = 0
        lows = [int(member[depth == k].min()) for k in range(cut, h + 1)]
        return pa.table({"id": table["id"][:1], "louds": [BitVec(bits).to_bytes()], "n_louds": [len(bits)], "lows": pa.array([lows], pa.list_(pa.int64()))})

    return reduce(DataFrame.unionByName, parts).groupBy("id").applyInArrow(one, "id long, louds binary, n_louds long, lows array<long>")


def pack(t: Tree, measure: str, cut: int) -> DataFrame:
    """One row per node of depth ``cut``: its subtree's sequences, and its members' hierarchies below it."""
    h, keys = t.cube.height, _cut_keys(cut)
    if not 0 <= cut <= h:
        raise ValueError("the cut is a depth from 0 to the height")
    parts = []
    for k in range(cut, h + 1):
        path = lambda upto: F.array(*[F.col(f"p_{j}") for j in range(cut + 1, upto + 1)]).cast("array<long>")
        parts.append(_keyed(t.nodes[k], cut).select(*keys, F.lit(k).alias("depth"), F.lit(False).alias("is_fan"), path(k).alias("path"), F.col(measure).cast("long").alias("n")))
        if k > cut:
            parts.append(_keyed(_fans(t, k), cut).select(*keys, F.lit(k).alias("depth"), F.lit(True).alias("is_fan"), path(k - 1).alias("path"), F.col("fan").alias("n")))
    rows = reduce(DataFrame.unionByName, parts)

    def one(table: pa.Table) -> pa.Table:
        depth, is_fan = table["depth"].to_numpy(), table["is_fan"].to_numpy()

        def part(k: int, fan: bool) -> tuple[np.ndarray, np.ndarray]:
            mine = table.filter(pa.array((depth == k) & (is_fan == fan)))
            n = mine["n"].to_numpy()
            return mine["path"].combine_chunks().flatten().to_numpy().reshape(len(n), k - cut - fan), n

        root = int(table.filter(pa.array((depth == cut) & ~is_fan))["n"][0].as_py())
        below = range(cut + 1, h + 1) if (depth > cut).any() else ()
        s = Sequences.build(root, [part(k, False) for k in below], [part(k, True) for k in below])
        return pa.table({
            **{c: table[c][:1] for c in keys}, "root": [root], "ta": [s.ta.to_bytes()], "n_ta": [len(s.ta)], "tc": [s.tc.to_bytes()], "n_tc": [len(s.tc)],
            "v": [s.v.to_bytes()], "width": pa.array([s.v.width], pa.int32()), "bits": [sum(s.size_bits().values())],
        })

    shard = ", ".join(f"{c} long" for c in keys) + ", root long, ta binary, n_ta long, tc binary, n_tc long, v binary, width int, bits long"
    out = rows.groupBy(*keys).applyInArrow(one, shard)
    named = _keyed(t.nodes[cut], cut).select(*keys, *[(F.col(f"{d.name}_id_{cut}") if cut else F.lit(0).cast("long")).alias(f"{d.name}_id") for d in t.cube.dims])
    for d in t.cube.dims:
        below = hierarchies_below(t, d, cut).select(F.col("id").alias(f"{d.name}_id"), F.struct("louds", "n_louds", "lows").alias(f"{d.name}_below"))
        named = named.join(below, f"{d.name}_id")
    return out.join(named.drop(*[f"{d.name}_id" for d in t.cube.dims]), keys)


def unpack(row: dict) -> Sequences:
    return Sequences(BitVec.from_bytes(row["ta"], row["n_ta"]), BitVec.from_bytes(row["tc"], row["n_tc"]), Dac.from_bytes(row["v"]), 0)


def label_rows(t: Tree, resolved: DataFrame, cut: int) -> DataFrame:
    """``(qid, key.., <dim>_at, <dim>_member)``: the shards that each query's labels meet, from the crown.

    ``at``: the label's depth below the shard's root, ``member`` its id there.  Labels above
    the cut meet all nodes of the cut below them; there are at most (cut + 1)^n tuples of such depths.
    """
    from ..plans.planner import tuples

    dims, keys, h = t.cube.dims, _cut_keys(cut), t.cube.height
    ok = resolved.filter("status = 'ok'")
    for d in dims:
        member = F.element_at(F.array(F.lit(0).cast("long"), *[F.col(f"{d.name}_id_{k}") for k in range(1, h + 1)]), F.col(f"{d.name}_depth").cast("int") + 1)
        ok = ok.withColumns({f"{d.name}_at": F.greatest(F.col(f"{d.name}_depth") - cut, F.lit(0)).cast("long"), f"{d.name}_member": member})
    out = [c for d in dims for c in (f"{d.name}_at", f"{d.name}_member")]
    if not cut:
        return _keyed(ok, 0).select("qid", *keys, *out)
    parts = []
    for above in sorted({tuple(min(k, cut) for k in depths) for depths in tuples(t, resolved)}):
        mine = ok
        for d, k in zip(dims, above):
            mine = mine.filter(F.least(f"{d.name}_depth", F.lit(cut)) == k)
        on = [f"{d.name}_id_{k}" for d, k in zip(dims, above) if k]
        crown = t.nodes[cut].select(*keys, *on)
        mine = mine.select("qid", *on, *out)
        parts.append((mine.join(crown, on) if on else mine.crossJoin(crown)).select("qid", *keys, *out))
    return reduce(DataFrame.unionByName, parts)


def descend(t: Tree, shards: DataFrame, resolved: DataFrame, cut: int, asked: int = ASKED) -> DataFrame:
    """Label queries answered on the bits of their shards: ``(qid, total, n_summed, n_visited, nanos)``.

    All queries of a shard go down together, at most about ``asked`` in one task; a query
    that spans several shards has a part in each.  ``nanos`` is the time from labels' ids
    to sums inside the tasks.
    """
    dims, keys = [d.name for d in t.cube.dims], [*_cut_keys(cut), "part"]
    rows = label_rows(t, resolved, cut)
    sized = rows.groupBy(*keys[:-1]).agg(F.ceil(F.count("*") / asked).cast("long").alias("parts"))
    rows = rows.join(sized, keys[:-1]).withColumn("part", F.pmod(F.xxhash64("qid"), F.col("parts"))).drop("parts")
    copies = sized.select(*keys[:-1], F.explode(F.expr("sequence(0L, parts - 1)")).alias("part")).join(shards, keys[:-1])
    copies = copies.select(*[F.col(c).alias(f"of_{c}") for c in keys], *[c for c in copies.columns if c not in keys])

    def run(asks: pa.Table, shard: pa.Table) -> pa.Table:
        count = asks.num_rows
        total, summed, visited, took = (np.zeros(count, np.int64) for _ in range(4))
        if shard.num_rows and count:
            row = shard.to_pylist()[0]
            seq = unpack(row)
            below = [LevelOrder(BitVec.from_bytes(x["louds"], x["n_louds"]), x["lows"]) for x in (row[f"{d}_below"] for d in dims)]
            depth, member = (np.stack([asks[f"{d}_{c}"].to_numpy(zero_copy_only=False) for d in dims], 1).astype(np.int64) for c in ("at", "member"))
            began = time.perf_counter_ns()
            total, summed, visited = seq.descend(below, depth, member)
            took[0] = time.perf_counter_ns() - began
        return pa.table({"qid": asks["qid"], "total": total, "n_summed": summed, "n_visited": visited, "nanos": took})

    met = rows.groupBy(*keys).cogroup(copies.groupBy(*[f"of_{c}" for c in keys])).applyInArrow(run, "qid long, total long, n_summed long, n_visited long, nanos long")
    values = ("total", "n_summed", "n_visited", "nanos")
    got = met.groupBy("qid").agg(*[F.sum(c).alias(c) for c in values])
    return resolved.filter("status = 'ok'").select("qid").join(got, "qid", "left").na.fill(0)
