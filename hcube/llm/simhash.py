"""SimHash near-duplicates: fingerprints linked through a forest of BK-trees.

Texts with equal fingerprints are one node from the start, so copies cost one row
each.  Distinct fingerprints go to shards: two that differ in at most three of 64
bits agree in one of four 16-bit blocks.  A shard above ``SHARD`` rows is split by
six blocks of 11 bits, and what is still above by pairs of chunks, so that no
task holds an unbounded shard and no link is lost.  Each task builds the BK-trees of
its shards at once (children by Hamming distance to their parent) and walks, for
each member, the edges within the radius.  Only a spanning star of each group of
linked members leaves the task; the groups are joined up by ``graph.components``.

Defined results: null or empty texts have fingerprint zero and link like any other;
a null doc_id keeps its row and counts as no smallest id; repeated rows stay;
columns other than doc_id and text are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import components
from .session import written

SEED = 42
RADIUS = 3
WORDS = 3
SHARD = 1000


def fingerprint(text: bytes, words: int = WORDS, seed: int = SEED) -> int:
    """64-bit majority of the XXH64 of the text's shingles, as an unsigned int."""
    import xxhash

    parts = text.lower().split()  # bytes: lower() is A-Z only, split() is \x20 and \x09-\x0d
    if not parts:
        return 0
    if len(parts) <= words:
        return xxhash.xxh64_intdigest(b" ".join(parts), seed)
    joined = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = [0, *(ends[:-1] + 1).tolist()]
    digest = xxhash.xxh64_intdigest
    hashes = np.array(
        [digest(joined[a:b], seed) for a, b in zip(starts, ends[words - 1 :].tolist())], np.uint64
    )
    ones = np.zeros(64, np.int64)
    for k in range(0, len(hashes), 65536):  # bounded memory for very long texts
        part = hashes[k : k + 65536]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    bits = (2 * ones > len(hashes)).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame) -> DataFrame:
    """``(doc_id, fp)``; fp is the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.array([fingerprint(t or b"") for t in batch.column(1).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps.view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("binary")).mapInArrow(
        run, "doc_id long, fp long"
    )


def bk_forest(shard: np.ndarray, fps: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """BK-trees of consecutive shards: each member's root, sorted edge codes, edge ends.

    An edge code is ``65 * parent + distance``; all trees grow together, one level a
    step: members hanging below the same parent at the same distance make their first
    one a node and move below it.  Members of a shard must be distinct.
    """
    first = np.flatnonzero(np.r_[True, shard[1:] != shard[:-1]])
    root = np.repeat(first, np.diff(np.r_[first, len(shard)]))
    below = root.copy()
    left = np.flatnonzero(below != np.arange(len(shard)))
    codes, ends = [], []
    while len(left):
        code = below[left] * 65 + np.bitwise_count(fps[left] ^ fps[below[left]])
        order = np.argsort(code, kind="stable")
        left, code = left[order], code[order]
        new = np.r_[True, code[1:] != code[:-1]]
        codes.append(code[new])
        ends.append(left[new])
        below[left] = left[new][np.cumsum(new) - 1]
        left = left[~new]
    codes = np.concatenate(codes) if codes else np.empty(0, np.int64)
    ends = np.concatenate(ends) if ends else np.empty(0, np.int64)
    order = np.argsort(codes)
    return root, codes[order], ends[order]


def bk_links(
    shard: np.ndarray, fps: np.ndarray, radius: int = RADIUS, step: int = 2048
) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of members of one shard within ``radius``, in slices of ``step`` members."""
    root, codes, ends = bk_forest(shard, fps)
    for k in range(0, len(fps), step):
        asks = np.arange(k, min(k + step, len(fps)))
        nodes = root[asks]
        found = []
        while len(asks):
            far = np.bitwise_count(fps[asks] ^ fps[nodes]).astype(np.int64)
            hit = (far <= radius) & (asks > nodes)
            found.append((asks[hit], nodes[hit]))
            lo = np.searchsorted(codes, nodes * 65 + np.maximum(far - radius, 0), "left")
            n = np.searchsorted(codes, nodes * 65 + np.minimum(far + radius, 64), "right") - lo
            at = np.repeat(lo - np.cumsum(n) + n, n) + np.arange(n.sum())
            asks, nodes = np.repeat(asks, n), ends[at]
        yield tuple(map(np.concatenate, zip(*found)))


def local_roots(n: int, pairs) -> np.ndarray:
    """Smallest member reachable from each of n members over slices of pairs."""
    label = np.arange(n)
    for a, b in pairs:
        while True:
            la, lb = label[a], label[b]
            apart = la != lb
            if not apart.any():
                break
            a, b, la, lb = a[apart], b[apart], la[apart], lb[apart]
            low = np.minimum(la, lb)
            np.minimum.at(label, la, low)
            np.minimum.at(label, lb, low)
            while not np.array_equal(nxt := label[label], label):
                label = nxt
    return label


def _stars(radius: int):
    def links(shard: np.ndarray, fps: np.ndarray) -> pa.RecordBatch:
        # A shard's members are made distinct, so the trees have no edge of length 0.
        order = np.lexsort((fps, shard))
        shard, fps = shard[order], fps[order]
        new = np.r_[True, (shard[1:] != shard[:-1]) | (fps[1:] != fps[:-1])]
        shard, fps = shard[new], fps[new].view(np.uint64)
        root = local_roots(len(fps), bk_links(shard, fps, radius))
        mine = np.flatnonzero(root != np.arange(len(fps)))
        return pa.RecordBatch.from_arrays(
            [pa.array(fps[mine].view(np.int64)), pa.array(fps[root[mine]].view(np.int64))], ["a", "b"]
        )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
            size += batch.num_rows
            if size >= 20000:
                shard, fps = (np.concatenate(x) for x in zip(*held))
                cut = np.searchsorted(shard, shard[-1])  # the last shard may go on
                if cut:
                    yield links(shard[:cut], fps[:cut])
                held, size = [(shard[cut:], fps[cut:])], len(shard) - cut
        if size:
            yield links(*(np.concatenate(x) for x in zip(*held)))

    return run


def near_links(fps: DataFrame, radius: int = RADIUS, shard_rows: int = SHARD) -> DataFrame:
    """Edges ``(a, b)`` that join all of ``fps (fp)``, distinct, linked within ``radius <= 3``."""
    if radius > 3:
        raise ValueError("four blocks find all links up to radius 3 only")
    shards = fps.select(
        "fp", F.explode(F.expr("transform(sequence(0, 3), i -> xxhash64(i, shiftrightunsigned(fp, 16 * i) & 65535))")).alias("k"),
        F.lit(0).alias("level"),
    )
    sized = shards.join(shards.groupBy("k").agg(F.count("*").alias("n")).filter("n > 1"), "k")
    cold = sized.filter(F.col("n") <= shard_rows).select("k", "fp")
    # Hot shards: six blocks of 11 bits of the whole word; three flips leave at least
    # three of them alike, so a link within the shard survives in one of its parts.
    hot = shards.select(
        "k", "fp"
    ).join(sized.filter(F.col("n") > shard_rows).select("k").distinct(), "k").select(
        "fp", F.explode(F.expr("transform(sequence(0, 5), i -> xxhash64(k, i, shiftrightunsigned(fp, 11 * i) & 2047))")).alias("k")
    )
    hot_sized = hot.join(hot.groupBy("k").agg(F.count("*").alias("n")).filter("n > 1"), "k")
    warm = hot_sized.filter(F.col("n") <= shard_rows).select("k", "fp")
    # What stays hot after that is a dense cloud of near copies: chunks, pair by pair.
    chunked = (
        hot_sized.filter(F.col("n") > shard_rows)
        .withColumn("parts", F.ceil(F.col("n") / shard_rows).cast("long"))
        .withColumn("mine", F.pmod(F.xxhash64("fp"), F.col("parts")))
        .withColumn("other", F.explode(F.expr("sequence(0L, parts - 1)")))
        .select(F.expr("xxhash64(k, least(mine, other), greatest(mine, other))").alias("k"), "fp")
    )
    groups = cold.unionByName(warm).unionByName(chunked)
    return groups.repartition("k").sortWithinPartitions("k").mapInArrow(_stars(radius), "a long, b long").distinct()


def near_duplicates(docs: DataFrame, radius: int = RADIUS, shard_rows: int = SHARD) -> DataFrame:
    """``(doc_id, fp, component_id)``, one row per row of ``docs``."""
    prints = written(fingerprints(docs), "fingerprints")
    nodes = written(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "nodes")
    roots = components(near_links(nodes.select("fp"), radius, shard_rows))
    placed = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select(
        "fp", "least", F.coalesce("root", "fp").alias("root")
    )
    ids = placed.groupBy("root").agg(F.min("least").alias("component_id"))
    by_print = placed.join(ids, "root").select("fp", "component_id")
    return prints.join(by_print, "fp").select("doc_id", "fp", "component_id")


def op1_simhash(docs: DataFrame) -> DataFrame:
    return near_duplicates(docs).select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )
