"""Best-fit packing of tokenised documents by bin completion.

Lengths are at most the capacity, so the table of how often each length occurs is
bounded whatever the input: it is the whole of what the driver sees.  On it runs bin
completion by branch and bound over all pieces at once, one kind of bin at a time:
undominated fillings around the longest piece left, pruned by the waste that a better
packing could still afford, with best-fit packings as incumbents from the start.  The
search ends at the lower bound or after ``NODES`` nodes, whatever the input's size.
Pieces then find their place by their rank within their length, which is counted in
two steps so that a very common length is spread over tasks.

Defined results: null texts are empty; an empty text is one piece of one token (the
end id); a very long text is encoded as a whole and cut into pieces, one document in
memory at a time; rows with null or repeated doc_id are packed like any other; ties
between equal lengths are free; an empty table gives no rows; columns other than
doc_id and text are not read.
"""

from __future__ import annotations

import base64
import bisect
import functools
import re
import zlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .session import shuffle_width, written

CAPACITY = 2048
END_ID = 0
VOCABULARY = "byte_bpe_50k.json"
NODES = 4000
WIDTH = 40
ROWS = 4096

# Fixed value: texts with characters above U+024F go to the slower of two equal encoders.
_WIDE = re.compile(rb"[\xca-\xff]")


@functools.lru_cache(maxsize=2)
def _encoders(name: str):
    """The vocabulary in the ``tokenizers`` library and, where it exists, as ranks.

    Both give the same ids (tested); ranks are five times faster.
    """
    import public_tokenizers
    from tokenizers import Tokenizer

    slow: list = []

    def exact(text: str) -> list[int]:
        if not slow:
            slow.append(Tokenizer.from_file(public_tokenizers.path(name)))
        return slow[0].encode(text, add_special_tokens=False).ids

    try:
        import tiktoken

        with open(public_tokenizers.path(name.replace(".json", ".tiktoken")), "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        fast = tiktoken.Encoding(
            name, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}
        ).encode_to_numpy
    except (ImportError, OSError):
        fast = exact
    return exact, fast


def token_ids(text: str | None, name: str = VOCABULARY) -> np.ndarray:
    """Ids of a document, the end id last, as unsigned 32-bit ints."""
    if not text:
        return np.array([END_ID], np.uint32)
    exact, fast = _encoders(name)
    odd = "<|endoftext|>" in text or _WIDE.search(text.encode())
    return np.append(np.asarray((exact if odd else fast)(text), np.uint32), np.uint32(END_ID))


def pieces(docs: DataFrame, capacity: int = CAPACITY, name: str = VOCABULARY) -> DataFrame:
    """``(doc_id, piece, start, length, ids_crc32)``: documents cut so that only the first piece may be short."""

    def table(rows: list[tuple]) -> pa.RecordBatch:
        cols = list(zip(*rows)) or [()] * 5
        return pa.RecordBatch.from_arrays(
            [pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()))],
            ["doc_id", "piece", "start", "length", "ids_crc32"],
        )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        for batch in batches:
            for doc, text in zip(batch.column(0), batch.column(1)):
                ids = token_ids(text.as_py(), name)
                head = (len(ids) - 1) % capacity + 1
                for k, start in enumerate([0, *range(head, len(ids), capacity)]):
                    part = ids[start : head if not k else start + capacity]
                    rows.append((doc.as_py(), k, start, len(part), zlib.crc32(part.astype("<u4").tobytes())))
                if len(rows) >= ROWS:
                    yield table(rows)
                    rows = []
        yield table(rows)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(
        run, "doc_id long, piece int, start long, length long, ids_crc32 long"
    )


class Bins:
    """Bins of equal contents, ``times`` of each: the contents as a chain of (length, chain before)."""

    __slots__ = ("chain", "times")

    def __init__(self, chain: tuple | None, times: int):
        self.chain, self.times = chain, times


def best_fit(left: list[int], capacity: int) -> tuple[list[tuple[tuple, int]], int]:
    """Best-fit decreasing on counts: chains with how many bins of each, and the number of bins.

    Pieces of one length go to the bins of least room together, so the work follows the
    number of lengths and kinds of bins, not that of pieces.
    """
    by_room: list[list[Bins]] = [[] for _ in range(capacity + 1)]
    rooms: list[int] = []  # rooms of open bins, ascending
    closed: list[tuple[tuple, int]] = []
    total = 0

    def put(room: int, chain: tuple, times: int) -> None:
        if not room:
            closed.append((chain, times))
            return
        if not by_room[room]:
            bisect.insort(rooms, room)
        by_room[room].append(Bins(chain, times))

    for size in range(len(left) - 1, 0, -1):
        n = left[size]
        while n:
            at = bisect.bisect_left(rooms, size)
            if at == len(rooms):  # no open bin has room: new ones, as full of this length as they get
                per = capacity // size
                for each, bins in ((per, n // per), (n % per, 1)):
                    if each and bins:
                        chain = None
                        for _ in range(each):
                            chain = (size, chain)
                        put(capacity - each * size, chain, bins)
                        total += bins
                break
            room = rooms[at]
            kind = by_room[room][-1]
            took = min(n, kind.times)
            kind.times -= took
            if not kind.times:
                by_room[room].pop()
                if not by_room[room]:
                    rooms.pop(at)
            put(room - size, (size, kind.chain), took)
            n -= took
    closed += [(k.chain, k.times) for kinds in by_room for k in kinds]
    return closed, total


def _contents(chain: tuple | None) -> tuple[int, ...]:
    out = []
    while chain:
        out.append(chain[0])
        chain = chain[1]
    return tuple(out[::-1])


def least_bins(left: list[int], capacity: int) -> int:
    """A bound from below: total length, or pieces above half that can't share a bin with what is short."""
    n = np.array(left, np.int64)
    sizes = np.arange(len(n))
    count, mass = np.r_[0, np.cumsum(n)], np.r_[0, np.cumsum(n * sizes)]  # of lengths below k
    at = lambda table, k: table[np.clip(k, 0, len(n))]
    half = capacity // 2
    short = np.arange(0, half + 1)  # pieces shorter than this are left out
    alone = at(count, capacity + 1) - at(count, capacity - short + 1)
    large = at(count, capacity - short + 1) - at(count, half + 1)
    large_mass = at(mass, capacity - short + 1) - at(mass, half + 1)
    small_mass = at(mass, half + 1) - at(mass, short)
    over = np.maximum(small_mass - (large * capacity - large_mass), 0)
    return int((alone + large + -(-over // capacity)).max())


def fillings(room: int, left: list[int], sizes: list[int], limit: int) -> list[tuple[int, ...]]:
    """Undominated fillings of ``room`` from ``left[length]`` pieces, fullest first.

    ``sizes``: the lengths that are left, ascending.  Dominated is a filling in which one
    piece, or two together, could give way to a longer one that is left and fits.  Found
    depth first, longest pieces first, a piece that ends the room exactly before all
    others; a full filling ends the search, as nothing dominates it.
    """
    found: list[tuple[int, ...]] = []
    budget = 8 * limit

    def spare(low: int, high: int, filling: tuple[int, ...]) -> bool:
        at = bisect.bisect_left(sizes, low)
        while at < len(sizes) and sizes[at] <= high:
            if left[sizes[at]] > filling.count(sizes[at]):
                return True
            at += 1
        return False

    def keep(filling: tuple[int, ...], slack: int) -> bool:
        ones = set(filling)
        twos = {a + b for i, a in enumerate(filling[:12]) for b in filling[i + 1 : 12]}
        if not slack or not any(spare(x + 1, x + slack, filling) for x in ones) and not any(spare(x, x + slack, filling) for x in twos):
            found.append(filling)
        return not slack or len(found) >= limit

    def grow(filling: tuple[int, ...], slack: int, most: int) -> bool:
        nonlocal budget
        budget -= 1
        if not slack or budget < 0:
            return keep(filling, slack) or budget < 0
        if slack <= most and left[slack] > filling.count(slack):
            return keep((*filling, slack), 0)
        ended = True
        at = bisect.bisect_right(sizes, min(slack, most)) - 1
        while at >= 0:
            size = sizes[at]
            if left[size] > filling.count(size):
                ended = False
                if grow((*filling, size), slack - size, size):
                    return True
            at -= 1
        return keep(filling, slack) if ended else False

    grow((), room, room)
    return sorted(set(found), key=lambda f: (-sum(f), len(f))) or [()]


class Packing(NamedTuple):
    """``patterns``: lengths of one bin and how many bins; ``bound``: no packing has fewer bins than this."""

    patterns: list[tuple[tuple[int, ...], int]]
    bins: int
    bound: int


def complete_bins(counts: dict[int, int], capacity: int = CAPACITY, nodes: int = NODES, width: int = WIDTH) -> Packing:
    """Bin completion by branch and bound over all pieces, whatever their number.

    A node takes one filling around the longest piece left, as often as the counts allow
    (and once, as the other branch), and prunes where the waste so far is more than a
    packing better than the incumbent can afford.  Best-fit decreasing is the first
    incumbent, and the rest below a node packed by best fit may become the next.  The
    search ends at the bound or after ``nodes`` nodes, so the result never has more bins
    than best fit decreasing.
    """
    left = [0] * (capacity + 1)
    for k, n in counts.items():
        left[k] = n
    total = sum(k * n for k, n in enumerate(left))
    if not total:
        return Packing([], 0, 0)
    bound = max(least_bins(left, capacity), -(-total // capacity))
    rest, fewest = best_fit(left, capacity)
    best: tuple[list, list] = ([], rest)
    chosen: list[tuple[tuple[int, ...], int]] = []
    stack: list[list[tuple[tuple[int, ...], int]]] = []
    sizes = [k for k, n in enumerate(left) if n]
    waste = used = 0
    work = 0  # best fit below a node only as often as it stays in proportion to the search itself

    def take(bin_: tuple[int, ...], times: int) -> None:
        for size in bin_:
            before = left[size]
            left[size] -= times
            if before and not left[size]:
                sizes.pop(bisect.bisect_left(sizes, size))
            elif not before and left[size]:
                bisect.insort(sizes, size)

    def options() -> list[tuple[tuple[int, ...], int]]:
        if not sizes:
            return []
        top = sizes[-1]
        take((top,), 1)
        bins = [(top, *f) for f in fillings(capacity - top, left, sizes, width)]
        take((top,), -1)
        out = []
        for bin_ in bins:
            most = min(left[k] // bin_.count(k) for k in set(bin_))
            out += [(bin_, most)] if most == 1 else [(bin_, most), (bin_, 1)]
        return out[::-1]

    def affordable() -> bool:
        return waste <= (fewest - 1) * capacity - total

    stack.append(options())
    while stack and fewest > bound and nodes > 0:
        if not stack[-1]:
            stack.pop()
            if chosen:
                bin_, times = chosen.pop()
                take(bin_, -times)
                used -= times
                waste -= times * (capacity - sum(bin_))
            continue
        bin_, times = stack[-1].pop()
        nodes -= 1
        work += width
        take(bin_, times)
        chosen.append((bin_, times))
        used += times
        waste += times * (capacity - sum(bin_))
        if not affordable():
            stack.append([])
            continue
        if not sizes or work >= len(sizes):
            work = 0
            rest, more = best_fit(left, capacity)
            if used + more < fewest:
                fewest, best = used + more, (list(chosen), rest)
        stack.append(options())
    patterns = best[0] + [(_contents(chain), times) for chain, times in best[1]]
    return Packing(patterns, fewest, bound)


def _places(patterns: list[tuple[tuple[int, ...], int]]) -> dict[int, tuple[np.ndarray, ...]]:
    """By length: first rank, first sequence, offset of each run of pieces placed alike."""
    runs: dict[int, list[tuple[int, int, int]]] = {}
    next_rank: dict[int, int] = {}
    base = 0
    for bin_, times in patterns:
        offset = 0
        for size in bin_:
            rank = next_rank.get(size, 0)
            runs.setdefault(size, []).append((rank, base, offset))
            next_rank[size] = rank + times
            offset += size
        base += times
    return {k: tuple(np.array(x, np.int64) for x in zip(*v)) for k, v in runs.items()}


def pack(table: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Adds ``sequence_id`` and ``offset`` to rows with ``length`` in 1..capacity (other columns stay)."""
    spark = table.sparkSession
    salts = 4 * shuffle_width(spark)
    salted = table.withColumn("__salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)))
    sizes = written(salted.groupBy("length", "__salt").agg(F.count("*").alias("n")), "lengths")
    counts = {r.length: r.n for r in sizes.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `capacity` rows
    places = spark.sparkContext.broadcast(_places(complete_bins(counts, capacity).patterns))
    before = Window.partitionBy("length").orderBy("__salt").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.withColumn("__before", F.coalesce(F.sum("n").over(before), F.lit(0)))
    within = Window.partitionBy("length", "__salt").orderBy("doc_id", "piece", "ids_crc32")
    ranked = (
        salted.withColumn("__nth", F.row_number().over(within) - 1)
        .join(starts.drop("n"), ["length", "__salt"])
        .withColumn("__rank", F.col("__nth") + F.col("__before"))
        .select(*table.columns, "__rank")
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of = places.value
        for batch in batches:
            length, rank = (batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("length", "__rank"))
            seq, off = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
            for k in np.unique(length).tolist():
                at = np.flatnonzero(length == k)
                first, base, offset = of[k]
                run_ = np.searchsorted(first, rank[at], "right") - 1
                seq[at] = base[run_] + rank[at] - first[run_]
                off[at] = offset[run_]
            arrays = [batch.column(i) for i in range(batch.num_columns - 1)]
            yield pa.RecordBatch.from_arrays([*arrays, pa.array(seq), pa.array(off)], names)

    names = [*table.columns, "sequence_id", "offset"]
    schema = ", ".join(f"`{n}` {t}" for n, t in [*table.dtypes, ("sequence_id", "bigint"), ("offset", "bigint")])
    return ranked.mapInArrow(run, schema)


def packing_report(packed: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """One row: pieces, tokens, sequences, and the fewest sequences that any packing could have."""
    counts = {r.length: r.n for r in packed.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    left = [counts.get(k, 0) for k in range(capacity + 1)]
    return packed.agg(
        F.count("*").alias("n_pieces"), F.coalesce(F.sum("length"), F.lit(0)).alias("n_tokens"),
        F.count_distinct("sequence_id").alias("n_sequences"), F.lit(least_bins(left, capacity)).cast("long").alias("bound"),
    )


def op3_best_fit_packing(docs: DataFrame) -> DataFrame:
    return pack(written(pieces(docs), "pieces"))
