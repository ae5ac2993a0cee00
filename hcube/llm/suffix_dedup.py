"""Exact removal of repeated passages: merged positional Burrows-Wheeler transforms.

A byte goes if it lies in a 50-byte string that also starts in a document with a
smaller doc_id.  Suffixes are not sorted over the whole corpus.  Every 50-byte string
has one anchor, the 24-byte string inside it with the smallest hash; equal strings have
equal anchors at equal places.  Only anchors that occur in several documents matter;
around each of their occurrences the strings that it anchors form a context of at most
76 bytes, and contexts of one anchor, laid over each other at the anchor, are shards
whose transforms are built column by column.  Shards are merged by refining their
interleave with one column after the other, reading each shard's transform in order;
the refinement also yields the common prefixes, hence the intervals of contexts that
share a whole 50-byte string, and the smallest document of each.

Steps: (1) texts equal as a whole leave all but the first of them; (2) blocks of
documents send anchors to buckets, which answer what recurs; (3) contexts are cut;
(4) contexts meet by anchor and give spans; (5) spans are cut out of the texts.  An
anchor with more contexts than one task should hold gives up its exact copies in an
aggregate first, and what is left is divided by what its windows share, down to single
windows (again an aggregate), so no task holds an unbounded group and nothing is left out.
Cold anchors decide by bytes; windows of anchors that had to be divided are compared by
64-bit hashes, and so are whole texts in step (1).

Defined results: a null text is empty; a row with a null doc_id neither removes nor
loses anything; rows with one doc_id don't remove from each other; very long texts are
searched whole; an empty table
gives no rows; columns other than doc_id and text are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import shuffle_width, written
from .words import U, mix

LENGTH = 50
ANCHOR = 24
REACH = LENGTH - ANCHOR  # how far a window may start before its anchor
CHUNK = 1 << 20
SLICE = 1 << 15  # places that are hashed at once: what they need stays in a core's cache
BLOCK = 1 << 22
BUCKET_BYTES = 1 << 26
HOT, HOT_MOST = 1000, 100_000
TASK_ROWS = 100_000
SHARDS = 2

_MUL = U(0x2545F4914F6CDD1D)


# -- anchors ------------------------------------------------------------------


def window_minima(buf: np.ndarray, stops: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of the 24 bytes at each place; smallest hash in the window that starts there (0: no window)."""
    h, m = np.empty(len(buf), U), np.empty(len(buf), U)
    for a in range(0, len(buf), SLICE):  # what a window that starts before z needs ends before z + LENGTH
        z = min(a + SLICE, len(buf))
        hashes, least = _minima(buf[a : z + LENGTH])
        h[a:z], m[a:z] = hashes[: z - a], least[: z - a]
    for a, z in zip([0, *stops[:-1].tolist()], stops.tolist()):  # the last 49 places of each part start no window
        m[max(a, z - (LENGTH - 1)) : z] = 0
    return h, m


def _minima(buf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    x = buf.astype(U)
    for k in (1, 2, 4):  # eight bytes at each place
        x[:-k] |= x[k:] << U(8 * k)
    h = mix(x)
    x *= _MUL
    for k in (8, 16):
        y = h[:-k] << U(1)
        y ^= x[k:]
        h[:-k] = mix(y)
    h |= U(1)
    return h, _sliding(np.minimum, h)


def _sliding(least, x: np.ndarray) -> np.ndarray:
    """Of each place and the REACH behind it, the least; at the end of those that are there."""
    out, other, size = x.copy(), np.empty_like(x), 1
    while size < REACH + 1:
        k = min(size, REACH + 1 - size)
        least(out[:-k], out[k:], out=other[:-k])
        other[-k:] = out[-k:]
        out, other, size = other, out, size + k
    return out


def anchors(h: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Places whose hash is the smallest of some window."""
    out = []
    for a in range(0, len(h), SLICE):
        b, z = max(a - REACH, 0), min(a + SLICE, len(h))
        top = _sliding(np.maximum, m[b:z][::-1])[::-1][a - b :]
        out.append(a + np.flatnonzero((top == h[a:z]) & (top > 0)))
    return np.concatenate(out) if out else np.empty(0, np.int64)


def parts_of(texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Buffers of about ``CHUNK`` bytes: bytes, and each part's stop, text number and offset there.

    A longer text comes in parts that overlap by 49 bytes, so each window is in one of them.
    """
    held: list[tuple[int, int, bytes]] = []
    size = 0

    def out():
        raw = b"".join(p for _, _, p in held)
        stops = np.cumsum([len(p) for _, _, p in held])
        return np.frombuffer(raw, np.uint8), stops, np.array([k for k, _, _ in held]), np.array([o for _, o, _ in held])

    for k, text in enumerate(texts):
        at = 0
        while len(text) - at >= LENGTH:
            part = text[at : at + CHUNK] if at or len(text) > CHUNK else text
            held.append((k, at, part))
            size += len(part)
            if size >= CHUNK:
                yield out()
                held, size = [], 0
            if at + len(part) == len(text):
                break
            at += len(part) - (LENGTH - 1)
    if held:
        yield out()


def short(h: np.ndarray) -> np.ndarray:
    """The 40 bits of a hash that are compared to find candidates: a collision is one too many."""
    return (h >> U(1)) & U(2**40 - 1)


def pair_code(row: np.ndarray, h: np.ndarray) -> np.ndarray:
    """One number for (row, short anchor hash)."""
    return mix(row.view(U) + h * _MUL)


def pack_items(h: np.ndarray, rows: np.ndarray) -> tuple[bytes, bytes]:
    """Short hashes, five bytes each, in order of their rows; the rows and how often each comes."""
    order = np.argsort(rows, kind="stable")
    uniq, n = np.unique(rows, return_counts=True)
    five = np.ascontiguousarray(h[order].view(np.uint8).reshape(-1, 8)[:, :5])
    return five.tobytes(), np.stack([uniq, n]).astype(np.int64).tobytes()


def unpack_items(five: bytes, rows: bytes) -> tuple[np.ndarray, np.ndarray]:
    wide = np.zeros((len(five) // 5, 8), np.uint8)
    wide[:, :5] = np.frombuffer(five, np.uint8).reshape(-1, 5)
    uniq, n = np.frombuffer(rows, np.int64).reshape(2, -1) if rows else (np.empty(0, np.int64), np.empty(0, np.int64))
    return wide.view(U).ravel(), np.repeat(uniq, n)


def _texts(batches, columns: int):
    """Rows of a stream, gathered to blocks of about ``BLOCK`` bytes of text (the last column)."""
    held, size = [], 0
    for batch in batches:
        cols = [c.to_pylist() for c in batch.columns]
        for row in zip(*cols):
            held.append(row)
            size += len(row[columns - 1] or b"")
            if size >= BLOCK:
                yield held
                held, size = [], 0
    if held:
        yield held


def _anchor_items(n_buckets: int, n_rows: int):
    """Per block: to each bucket the anchors of one row only; straight on, those of several rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _texts(batches, 2):
            keys = np.array([r[0] for r in rows], np.int64)
            hs, ks = [], []
            for buf, stops, which, _ in parts_of([r[1] for r in rows]):
                h, m = window_minima(buf, stops)
                at = anchors(h, m)
                hs.append(h[at])
                ks.append(keys[which[np.searchsorted(stops, at, "right")]])
            if not hs:
                continue
            h, k = np.concatenate(hs), np.concatenate(ks)
            order = np.lexsort((k, h))
            h, k = h[order], k[order]
            new = np.r_[True, (h[1:] != h[:-1]) | (k[1:] != k[:-1])]
            h, k = h[new], k[new]
            first = np.r_[True, h[1:] != h[:-1]]
            several = np.repeat(np.diff(np.r_[np.flatnonzero(first), len(h)]) > 1, np.diff(np.r_[np.flatnonzero(first), len(h)]))
            bucket = ((h >> U(20)) % U(n_buckets)).astype(np.int64)
            h = short(h)
            out = []
            for kind, mask in ((0, ~several), (1, several & first)):
                b, hh, kk = bucket[mask], h[mask], k[mask]
                for x, sel in _groups(b):
                    out.append((x, kind, *pack_items(hh[sel], kk[sel] if kind == 0 else np.zeros(len(sel), np.int64))))
            # What recurs within the block needs no answer: it goes to the rows' places now.
            to, codes = _row_bucket(k[several], n_rows), pair_code(k[several], h[several])
            out += [(x % n_buckets, 2 + x, codes[sel].tobytes(), b"") for x, sel in _groups(to)]
            cols = list(zip(*out))
            yield pa.RecordBatch.from_arrays(
                [pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[2:])],
                ["bucket", "kind", "hashes", "rows"],
            )

    return run


def _groups(values: np.ndarray):
    order = np.argsort(values, kind="stable")
    v = values[order]
    cuts = np.flatnonzero(np.r_[True, v[1:] != v[:-1]]) if len(v) else np.empty(0, np.int64)
    for a, z in zip(cuts, [*cuts[1:], len(v)]):
        yield int(v[a]), order[a:z]


def _row_bucket(keys: np.ndarray, n_rows: int) -> np.ndarray:
    """A row's place: its number, a hash already, modulo the places (floored, as ``pmod`` is)."""
    return keys % n_rows


def _recurring(n_rows: int):
    """Per bucket: codes of (row, anchor) whose anchor is in several rows, to the rows' places."""

    def answer(items: list[tuple[bytes, bytes]], known: list[bytes]):
        h, k = (np.concatenate(x) for x in zip(*(unpack_items(*i) for i in items)))
        more = np.concatenate([unpack_items(a, b"")[0] for a in known] or [np.empty(0, U)])
        order = np.lexsort((k, h))
        h, k = h[order], k[order]
        same = np.zeros(len(h), bool)
        again = (h[1:] == h[:-1]) & (k[1:] != k[:-1])
        same[1:] |= again
        same[:-1] |= again
        # Runs of one hash with several rows: every member recurs, so spread over the run.
        first = np.flatnonzero(np.r_[True, h[1:] != h[:-1]]) if len(h) else np.empty(0, np.int64)
        if len(h):
            same = np.repeat(np.maximum.reduceat(same, first), np.diff(np.r_[first, len(h)]))
            more = np.sort(more)
            if len(more):
                same |= more[np.minimum(np.searchsorted(more, h), len(more) - 1)] == h
        return k[same], h[same]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items: dict[int, list] = {}
        known: dict[int, list] = {}

        def row(to, blob):
            return pa.RecordBatch.from_arrays([pa.array([to], pa.int32()), pa.array([blob], pa.binary())], ["to", "codes"])

        for batch in batches:
            for bucket, kind, hashes, rows in zip(*(c.to_pylist() for c in batch.columns)):
                if kind >= 2:
                    yield row(kind - 2, hashes)
                elif kind == 1:
                    known.setdefault(bucket, []).append(hashes)
                else:
                    items.setdefault(bucket, []).append((hashes, rows))
        for bucket in list(items):
            k, h = answer(items.pop(bucket), known.pop(bucket, []))
            codes = pair_code(k, h)
            for to, sel in _groups(_row_bucket(k, n_rows)):
                yield row(to, codes[sel].tobytes())

    return run


# -- contexts -----------------------------------------------------------------

_CONTEXTS = "doc_id long, row long, start long, anchor long, off int, ctx binary"


def _cut_contexts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Stream of one place after the other: first its codes and copies, then its texts."""
    codes, copies, place, parts = np.empty(0, U), set(), None, []

    def cut(rows):
        keys, docs = np.array([r[1] for r in rows], np.int64), np.array([r[0] for r in rows], np.int64)
        for buf, stops, which, offset in parts_of([r[2] for r in rows]):
            h, m = window_minima(buf, stops)
            at = anchors(h, m)
            part = np.searchsorted(stops, at, "right")
            code = pair_code(keys[which[part]], short(h[at]))
            hit = codes[np.minimum(np.searchsorted(codes, code), len(codes) - 1)] == code
            at, part = at[hit], part[hit]
            if not len(at):
                continue
            begin = (np.r_[0, stops[:-1]])[part]
            # The windows that this anchor stands for start in one run of places.
            back = np.arange(REACH, -1, -1)
            own = np.maximum(at[:, None] - back, 0)
            mine = (m[own] == h[at][:, None]) & (at[:, None] - back >= begin[:, None])
            lo = at - back[mine.argmax(1)]
            hi = at - back[REACH - mine[:, ::-1].argmax(1)]
            lens = hi + LENGTH - lo
            ends = np.cumsum(lens)
            flat = buf[np.repeat(lo - ends + lens, lens) + np.arange(ends[-1])]
            ctx = pa.Array.from_buffers(
                pa.binary(), len(at), [None, pa.py_buffer(np.r_[0, ends].astype(np.int32)), pa.py_buffer(flat)]
            )
            yield pa.RecordBatch.from_arrays(
                [pa.array(docs[which[part]]), pa.array(keys[which[part]]), pa.array(lo - begin + offset[part]),
                 pa.array(h[at].view(np.int64)), pa.array((at - lo).astype(np.int32)), ctx],
                [f.split()[0] for f in _CONTEXTS.split(", ")],
            )

    held, size = [], 0
    for batch in batches:
        for to, kind, doc, key, blob in zip(*(c.to_pylist() for c in batch.columns)):
            if to != place:
                if held:
                    yield from cut(held)
                held, size, parts, copies, codes, place = [], 0, [], set(), np.empty(0, U), to
            if kind == 0:
                parts.append(np.frombuffer(blob, U))
                continue
            if kind == 1:
                copies.add(key)
                continue
            if parts:
                codes, parts = np.unique(np.concatenate(parts)), []
            if len(codes) and key not in copies:
                held.append((doc, key, blob))
                size += len(blob)
                if size >= BLOCK:
                    yield from cut(held)
                    held, size = [], 0
    if held:
        yield from cut(held)


# -- positional transforms and their merge ------------------------------------

ABSENT = 256
COLUMNS = 2 * REACH


def refine(group: np.ndarray, symbol: np.ndarray, since: np.ndarray, column: int) -> tuple[np.ndarray, np.ndarray]:
    """One step of the order: positions sorted by the column's symbol within their group.

    ``since[i]``: first column from which entries i - 1 and i agree up to this one.
    Returns the old place of each new entry, and the new ``since``.
    """
    code = group * 512 + symbol
    order = np.argsort(code, kind="stable")
    sorted_ = code[order]
    new = np.r_[True, sorted_[1:] != sorted_[:-1]]
    out = np.full(len(order), column + 1, np.int64)
    inner = np.flatnonzero(~new)
    if len(inner):
        # Between two old neighbours of one symbol the agreement is the worst on the way.
        ends = np.empty(2 * len(inner), np.int64)
        ends[0::2], ends[1::2] = order[inner - 1] + 1, order[inner] + 1
        out[inner] = np.maximum.reduceat(np.r_[since, 0], ends)[0::2]
    return order, out


def shard_transform(group: np.ndarray, symbols: np.ndarray) -> np.ndarray:
    """Positional Burrows-Wheeler transform: each column's symbols in the order of what precedes them.

    ``group`` is sorted; ``symbols``: (columns, members).
    """
    out = np.empty_like(symbols)
    order = np.arange(len(group))
    for c, column in enumerate(symbols):
        out[c] = column[order]
        order = order[np.argsort(group * 512 + out[c], kind="stable")]
    return out


def merged_intervals(groups: list[np.ndarray], transforms: list[np.ndarray]):
    """Merges shards; after each column gives (column, shard, its entry, since).

    The interleave says from which shard the next entry comes; entries of one shard keep
    their order in it, so a column's symbols are read off each transform in turn.
    """
    shard = np.repeat(np.arange(len(groups)), [len(g) for g in groups])
    entry = np.concatenate([np.arange(len(g)) for g in groups])
    order = np.argsort(np.concatenate(groups), kind="stable")
    group, shard, entry = np.concatenate(groups)[order], shard[order], entry[order]
    since = np.where(np.r_[True, group[1:] != group[:-1]], 1, 0).astype(np.int64)
    for c in range(len(transforms[0])):
        symbol = np.empty(len(group), np.int64)
        for k, t in enumerate(transforms):
            symbol[shard == k] = t[c]
        order, since = refine(group, symbol, since, c)
        shard, entry = shard[order], entry[order]
        yield c, shard, entry, group, since


def shared_windows(group, symbols, first, left, right, lo=0, hi=REACH):
    """Least and greatest start distance of a window that an earlier document has too (-1: none).

    Members are contexts, aligned at their anchor: ``symbols`` (52, members) are the bytes
    left and right of it, ``left`` and ``right`` how many there are; ``first`` the smallest
    document of each; only distances ``lo..hi`` count.  ``group`` must be sorted.
    """
    n = len(group)
    least, most = np.full(n, -1, np.int64), np.full(n, -1, np.int64)
    members = [np.arange(k, n, SHARDS) for k in range(SHARDS) if k < n]
    transforms = [shard_transform(group[m], symbols[:, m]) for m in members]
    far = np.int64(2**63 - 1)
    for c, shard, entry, grp, since in merged_intervals([group[m] for m in members], transforms):
        start = c + 1 - REACH
        o = REACH - start
        if start < 0 or not lo <= o <= hi:
            continue
        who = np.empty(n, np.int64)
        for k, m in enumerate(members):
            who[shard == k] = m[entry[shard == k]]
        valid = (left[who] >= o) & (right[who] >= REACH - o)
        doc = np.where(valid, first[who], far)
        block = np.flatnonzero((since > start) | np.r_[True, grp[1:] != grp[:-1]])
        early = np.repeat(np.minimum.reduceat(doc, block), np.diff(np.r_[block, n]))
        hit = who[valid & (early < doc)]
        most[hit] = np.where(most[hit] < 0, o, most[hit])  # distances come from the greatest down
        least[hit] = o
    return least, most


def aligned(ctx: pa.Array, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Columns left and right of the anchor, the anchor as three words, bytes at the left and right."""
    offsets = np.frombuffer(ctx.buffers()[1], np.int32)[ctx.offset : ctx.offset + len(ctx) + 1].astype(np.int64)
    data = np.frombuffer(ctx.buffers()[2], np.uint8)
    lens = np.diff(offsets)
    n = len(ctx)
    table = np.full((n, 2 * REACH + ANCHOR), ABSENT, np.int16)
    to = np.repeat(np.arange(n) * (2 * REACH + ANCHOR) + REACH - off - (np.cumsum(lens) - lens), lens) + np.arange(lens.sum())
    table.ravel()[to] = data[offsets[0] : offsets[-1]]
    words = np.ascontiguousarray(table[:, REACH : REACH + ANCHOR].astype(np.uint8)).view(U)
    symbols = np.ascontiguousarray(np.hstack([table[:, :REACH], table[:, REACH + ANCHOR :]]).T)
    return symbols, words, off, lens - off - ANCHOR


def _ids(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order by keys (first is most important) and group number of each place of that order."""
    order = np.lexsort(keys[::-1])
    new = np.zeros(len(order), bool)
    for k in keys:
        s = k[order]
        new[1:] |= s[1:] != s[:-1]
    return order, np.cumsum(new)


def _by_key(batches, index: int, rows: int):
    """Record batches of whole keys: a stream sorted by column ``index`` cut between keys."""
    held, size = [], 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        size += batch.num_rows
        if size >= rows:
            table = pa.Table.from_batches(held).combine_chunks()
            keys = table.column(index).to_numpy()
            cut = int(np.flatnonzero(keys == keys[-1])[0])
            if cut:
                yield table.slice(0, cut)
            held = table.slice(cut).to_batches()
            size = table.num_rows - cut
    if size:
        yield pa.Table.from_batches(held).combine_chunks()


def _spans_of_anchor(n_rows: int):
    """Contexts of whole anchors to spans: copies of a context, then shared windows of its first document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _by_key(batches, 3, TASK_ROWS):
            doc, row, start, off = (table.column(c).to_numpy() for c in ("doc_id", "row", "start", "off"))
            ctx = table.column("ctx").combine_chunks()
            ctx = ctx.chunk(0) if isinstance(ctx, pa.ChunkedArray) else ctx
            off = off.astype(np.int64)
            symbols, words, left, right = aligned(ctx, off)
            length = left + right + ANCHOR
            body = np.ascontiguousarray(symbols.T)  # (rows, 52) int16: 13 words a row
            packed = body.view(U).reshape(len(off), -1)
            keys = [words[:, 0], words[:, 1], words[:, 2], *packed.T]
            order, klass = _ids(*keys)
            heads = np.flatnonzero(np.r_[True, klass[1:] != klass[:-1]])
            first = np.minimum.reduceat(doc[order], heads)
            whole = doc[order] > first[klass]
            lo, hi = np.zeros(len(order), np.int64), np.zeros(len(order), np.int64)
            hi[whole] = length[order][whole]
            # Classes: one member each; those alone in their anchor share nothing.
            rep = order[heads]
            _, group = _ids(*(words[rep, k] for k in range(3)))  # classes are sorted by anchor already
            size = np.bincount(group)
            several = np.flatnonzero(size[group] > 1)
            least, most = np.full(len(rep), -1, np.int64), np.full(len(rep), -1, np.int64)
            if len(several):
                r = rep[several]
                least[several], most[several] = shared_windows(
                    group[several], symbols[:, r].astype(np.int64), first[several], left[r], right[r]
                )
            part = ~whole & (most[klass] >= 0)
            lo[part] = (left[order] - most[klass])[part]
            hi[part] = (left[order] - least[klass])[part] + LENGTH
            keep = whole | part
            yield from _packed_spans(row[order][keep], (start[order] + lo)[keep], (start[order] + hi)[keep], n_rows)

    return run


def _packed_spans(row, start, end, n_rows):
    for to, sel in _groups(_row_bucket(row, n_rows)):
        yield pa.RecordBatch.from_arrays(
            [pa.array([to], pa.int32()), pa.array([np.stack([row[sel], start[sel], end[sel]]).astype(np.int64).tobytes()], pa.binary())],
            ["to", "spans"],
        )


def _hot_spans(contexts: DataFrame, hot_rows: int, n_rows: int) -> DataFrame:
    """Spans of anchors with many contexts: copies by aggregate and join, the rest by ever smaller cells."""
    classes = written(contexts.groupBy("anchor", "off", "ctx").agg(F.min("doc_id").alias("first")), "hot-classes")
    classes = classes.withColumn("id", F.xxhash64("anchor", "off", "ctx"))
    found = []
    cells = classes.select("id", "off", "ctx", "first", F.lit(0).alias("a"), F.lit(REACH).alias("b"), F.xxhash64("anchor").alias("cell"))
    while True:
        sized = written(cells.join(cells.groupBy("cell").agg(F.count("*").alias("n")).filter("n > 1"), "cell"), "hot-cells")
        small = sized.filter((F.col("n") <= hot_rows) & (F.col("a") < F.col("b")))
        found.append(
            small.select("id", "off", "ctx", "first", "a", "b", "cell").repartition("cell").sortWithinPartitions("cell")
            .mapInArrow(_cell_windows, "id long, least long, most long")
        )
        # A single window: the cell is the window itself, so its smallest document decides.
        single = sized.filter("a = b")
        least = single.groupBy("cell").agg(F.min("first").alias("least"))
        found.append(
            single.join(least, "cell").filter("least < first").select("id", F.col("a").cast("long").alias("least"), F.col("a").cast("long").alias("most"))
        )
        large = sized.filter((F.col("n") > hot_rows) & (F.col("a") < F.col("b")))
        if large.isEmpty():
            break
        halves = large.withColumn("half", F.explode(F.expr(
            "array(named_struct('a', a, 'b', (a + b) div 2), named_struct('a', (a + b) div 2 + 1, 'b', b))"
        ))).select("id", "off", "ctx", "first", F.col("half.a").cast("int").alias("a"), F.col("half.b").cast("int").alias("b"), F.col("cell").alias("was"))
        # All windows of distances a..b hold a bytes before the anchor and REACH - b behind it.
        shared = F.expr(f"substring(ctx, off - a + 1, a + {ANCHOR} + {REACH} - b)")
        cells = halves.filter(f"off >= a AND length(ctx) - off >= {ANCHOR} + {REACH} - b").select(
            "id", "off", "ctx", "first", "a", "b", F.xxhash64("was", "a", "b", shared).alias("cell")
        )
    windows = found[0]
    for x in found[1:]:
        windows = windows.unionByName(x)
    windows = windows.groupBy("id").agg(F.min("least").alias("least"), F.max("most").alias("most"))
    marked = classes.join(windows, "id", "left").select("anchor", "off", "ctx", "first", "least", "most")
    whole = F.col("doc_id") > F.col("first")
    spans = contexts.join(marked, ["anchor", "off", "ctx"]).filter(whole | F.col("most").isNotNull()).select(
        "row",
        F.when(whole, F.col("start")).otherwise(F.col("start") + F.col("off") - F.col("most")).alias("start"),
        F.when(whole, F.col("start") + F.length("ctx")).otherwise(F.col("start") + F.col("off") - F.col("least") + LENGTH).alias("end"),
    )

    def run(batches):
        for batch in batches:
            yield from _packed_spans(*(batch.column(k).to_numpy() for k in range(3)), n_rows)

    return spans.mapInArrow(run, "to int, spans binary")


def _cell_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for table in _by_key(batches, 6, TASK_ROWS):
        id_, off, first, a, b, cell = (table.column(c).to_numpy().astype(np.int64) for c in ("id", "off", "first", "a", "b", "cell"))
        ctx = table.column("ctx").combine_chunks()
        ctx = ctx.chunk(0) if isinstance(ctx, pa.ChunkedArray) else ctx
        symbols, words, left, right = aligned(ctx, off)
        # Cells are hashes: the anchor's own bytes and the range keep different ones apart.
        order, group = _ids(cell, a, b, words[:, 0], words[:, 1], words[:, 2])
        for x, y in {(int(p), int(q)) for p, q in zip(a, b)}:
            mine = (a[order] == x) & (b[order] == y)
            o = order[mine]
            least, most = shared_windows(group[mine], symbols[:, o].astype(np.int64), first[o], left[o], right[o], x, y)
            hit = most >= 0
            yield pa.RecordBatch.from_arrays([pa.array(id_[o][hit]), pa.array(least[hit]), pa.array(most[hit])], ["id", "least", "most"])


# -- the whole ----------------------------------------------------------------


def _union_spans(starts: np.ndarray, ends: np.ndarray) -> list[tuple[int, int]]:
    """Maximal runs of the union; runs that touch are one."""
    order = np.argsort(starts, kind="stable")
    s, e = starts[order], np.maximum.accumulate(ends[order])
    new = np.r_[True, s[1:] > e[:-1]]
    return list(zip(s[new].tolist(), e[np.r_[np.flatnonzero(new)[1:] - 1, len(s) - 1]].tolist()))


def cut_spans(text: bytes, spans: list[tuple[int, int]]) -> bytes:
    at, parts = 0, []
    for a, z in spans:
        parts.append(text[at:a])
        at = z
    parts.append(text[at:])
    return b"".join(parts)


def _apply(batches: Iterator[pa.RecordBatch], emit) -> Iterator[pa.RecordBatch]:
    """Stream of one place after the other: first its spans and copies, then its texts."""
    place, copies, blobs, table = None, set(), [], None
    for batch in batches:
        out = []
        for to, kind, doc, key, blob, *rest in zip(*(c.to_pylist() for c in batch.columns)):
            if to != place:
                place, copies, blobs, table = to, set(), [], None
            if kind == 0:
                blobs.append(np.frombuffer(blob, np.int64).reshape(3, -1))
            elif kind == 1:
                copies.add(key)
            else:
                if table is None:
                    table = np.hstack(blobs) if blobs else np.empty((3, 0), np.int64)
                    table = table[:, np.argsort(table[0], kind="stable")]
                    blobs = []
                text = blob or b""
                if key in copies:
                    spans = [(0, len(text))]
                else:
                    a, z = np.searchsorted(table[0], key), np.searchsorted(table[0], key, "right")
                    spans = _union_spans(table[1, a:z], table[2, a:z]) if z > a else []
                out.append((doc, text, spans, rest))
        if out:
            yield emit(out)


def _sources(docs: DataFrame) -> DataFrame:
    """``(doc_id, row, text)``; row is one number for the row's id and text."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("t")).select(
        "doc_id", F.xxhash64("doc_id", "t").alias("row"), F.col("t").cast("binary").alias("text")
    )


def _streamed(first: DataFrame, copies: DataFrame, texts: DataFrame, n_rows: int, extra: list = ()) -> DataFrame:
    """What a place must know, then its texts, in one sorted stream."""
    to = F.pmod(F.col("row"), F.lit(n_rows)).cast("int")
    none = [F.lit(None).cast(t).alias(n) for n, t in extra]
    head = first.select("to", F.lit(0).alias("kind"), F.lit(None).cast("long").alias("doc_id"), F.lit(None).cast("long").alias("row"), F.col(first.columns[1]).alias("blob"), *none)
    same = copies.select(to.alias("to"), F.lit(1).alias("kind"), F.lit(None).cast("long").alias("doc_id"), "row", F.lit(None).cast("binary").alias("blob"), *none)
    body = texts.select(to.alias("to"), F.lit(2).alias("kind"), "doc_id", "row", F.col("text").alias("blob"), *[F.col(n) for n, _ in extra])
    return head.unionByName(same).unionByName(body).repartition(n_rows, "to").sortWithinPartitions("to", "kind")


def spans(docs: DataFrame, hot_rows: int | None = None):
    """Packed spans by place, rows that go as a whole, and the number of places.

    An anchor is hot above ``hot_rows`` contexts, by default an eighth of a task's mean
    share within ``HOT .. HOT_MOST``; results don't depend on it.
    """
    spark = docs.sparkSession
    source = _sources(docs)
    keys = written(source.select("doc_id", "row", F.length("text").alias("n"), F.md5("text").alias("digest")), "rows")
    total = int(keys.agg(F.sum("n")).first()[0] or 0)
    n_places = max(shuffle_width(spark), total // BUCKET_BYTES)
    firsts = keys.groupBy("digest", "n").agg(F.min("doc_id").alias("first"))
    copies = written(keys.filter(F.col("n") >= LENGTH).join(firsts, ["digest", "n"]).filter("doc_id > first").select("row").distinct(), "copies")
    long_ = source.filter((F.length("text") >= LENGTH) & F.col("doc_id").isNotNull())
    items = long_.select("row", "text").mapInArrow(_anchor_items(n_places, n_places), "bucket int, kind int, hashes binary, rows binary")
    answers = items.repartition(n_places, "bucket").mapInArrow(_recurring(n_places), "to int, codes binary")
    contexts = written(_streamed(answers, copies, long_, n_places).mapInArrow(_cut_contexts, _CONTEXTS), "contexts")
    if hot_rows is None:
        hot_rows = min(max(contexts.count() // (8 * shuffle_width(spark)), HOT), HOT_MOST)
    often = contexts.groupBy("anchor").agg(F.count("*").alias("n")).filter(F.col("n") > hot_rows).select("anchor")
    often = written(often, "hot-anchors", release=False)
    cold = contexts.join(often, "anchor", "left_anti").select(*contexts.columns)
    out = cold.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(_spans_of_anchor(n_places), "to int, spans binary")
    if not often.isEmpty():
        out = out.unionByName(_hot_spans(contexts.join(often, "anchor").select(*contexts.columns), hot_rows, n_places))
    return written(out, "spans"), copies, n_places


_REPORT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def _report(rows) -> pa.RecordBatch:
    out = []
    for doc, text, spans_, _ in rows:
        gone = sum(z - a for a, z in spans_)
        out.append((doc, len(text), gone, len(spans_), hashlib.sha256(cut_spans(text, spans_)).hexdigest()))
    cols = list(zip(*out))
    return pa.RecordBatch.from_arrays(
        [*(pa.array(c, pa.int64()) for c in cols[:4]), pa.array(cols[4], pa.string())], [f.split()[0] for f in _REPORT.split(", ")]
    )


def op5_suffix_dedup(docs: DataFrame, hot_rows: int | None = None) -> DataFrame:
    found, copies, n_places = spans(docs, hot_rows)
    return _streamed(found, copies, _sources(docs), n_places).mapInArrow(lambda b: _apply(b, _report), _REPORT)


def without_repeats(docs: DataFrame, hot_rows: int | None = None) -> DataFrame:
    """``docs`` with the repeated passages cut out of ``text``, its other columns and rows unchanged.

    A cut inside a character leaves the bytes that still form characters.
    """
    found, copies, n_places = spans(docs, hot_rows)
    others = [(f"__{k}", t) for k, (n, t) in enumerate(docs.dtypes) if n != "text"]
    names = [n for n in docs.columns if n != "text"]
    source = docs.select(
        F.col("doc_id").cast("long").alias("__id"), F.coalesce(F.col("text"), F.lit("")).alias("__t"),
        *[F.col(f"`{n}`").alias(k) for n, (k, _) in zip(names, others)],
    ).select(F.col("__id").alias("doc_id"), F.xxhash64("__id", "__t").alias("row"), F.col("__t").cast("binary").alias("text"), *[k for k, _ in others])
    schema = ", ".join(["__text string", *(f"{k} {t}" for k, t in others)])

    def emit(rows):
        texts = [cut_spans(t, s).decode("utf-8", "ignore") for _, t, s, _ in rows]
        cols = [pa.array(c, t) for c, t in zip(zip(*(r[3] for r in rows)), kinds)]
        return pa.RecordBatch.from_arrays([pa.array(texts, pa.string()), *cols], ["__text", *(k for k, _ in others)])

    from pyspark.sql.pandas.types import to_arrow_type

    by_name = {f.name: f.dataType for f in docs.schema}
    kinds = [to_arrow_type(by_name[n]) for n in names]
    out = _streamed(found, copies, source, n_places, others).mapInArrow(lambda b: _apply(b, emit), schema)
    back = dict(zip(names, (k for k, _ in others)))
    return out.select(*[F.col("__text").alias("text") if c == "text" else F.col(back[c]).alias(c) for c in docs.columns])
