"""Near copies by shingles: texts whose five-word shingles have a Jaccard similarity of 0.8 or more.

The SimHash operator comes first: fingerprints of the five-word shingles within its radius
are linked through its BK-trees, and links whose shingle sets are similar enough stand.
Its radius finds the closest copies only, so an exact join finds what is left and no
similar pair is lost.  The distinct shingles of a text stand in an order that all texts
share (common ones last); two similar texts of n and m shingles have one
in common among the first n - ceil(0.8 n) + 1 of the one and of the other.  Texts that
share such a key are compared by their whole shingle sets, in two steps, so that a
large group of copies isn't multiplied out: for some rounds each text only with a member
of its keys' groups that shares most with the others and with two that change from round
to round, then all pairs of different components that share a key behind which enough is
left in both to reach the similarity.

How common a shingle is is counted over all texts, in a fixed number of counters by its
hash; shingles of equal counters stand by hash.  Shingles and sets are compared by 64-bit hashes.

Defined results: texts of fewer than five words are one shingle; null and empty texts
are copies of each other; very long texts are one set; a null doc_id counts as no
smallest id; repeated rows and ties share their class; an empty table gives no rows;
columns other than doc_id and text are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import components
from .session import discard, free, shuffle_width, written
from .simhash import near_links
from .words import U, distinct, mix, word_hashes

WORDS = 5
# The similarity is 4 / 5; both are written out in the conditions below.
GROUP = 500
ROUNDS = 2
COUNTERS, SLICE = 1 << 22, 1 << 16
KEYS = 1 << 20
_STEP = U(0xC2B2AE3D27D4EB4F)
_BYTE = 256 * np.arange(8, dtype=np.int64)
_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.float64)


def shingle_sets(texts: list[bytes], words: int = WORDS) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    hashes, counts = word_hashes(texts)
    n = len(hashes)
    wide = np.r_[hashes, np.zeros(words, U)]
    rolled = np.zeros(n, U)
    for k in range(words):
        rolled = rolled * _STEP + wide[k : k + n]
    rolled = mix(rolled)
    out = []
    for a, c in zip((np.cumsum(counts) - counts).tolist(), counts.tolist()):
        if 0 < c < words:
            short = np.zeros(1, U)
            for x in [*hashes[a : a + c], *[U(0)] * (words - c)]:
                short = short * _STEP + x
            out.append(mix(short))
        else:
            s = np.sort(rolled[a : a + max(c - words + 1, 0)])
            new = np.empty(len(s), bool)
            new[:1] = True
            np.not_equal(s[1:], s[:-1], out=new[1:])
            out.append(s[new])
    return out


def set_name(shingles: np.ndarray) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(shingles.tobytes()) - 2**63


def set_fingerprint(shingles: np.ndarray) -> int:
    """Majority of the bits of a text's distinct shingle hashes, as a signed 64-bit number."""
    places = np.zeros(8 * 256, np.int64)  # of each of the eight bytes, how often it has each value
    for k in range(0, len(shingles), 65536):
        places += np.bincount((shingles[k : k + 65536].view(np.uint8).reshape(-1, 8) + _BYTE).ravel(), minlength=8 * 256)
    ones = (places.astype(np.float64).reshape(8, 256) @ _BITS).ravel()  # whole numbers, far below 2^53
    return int(np.packbits(2 * ones > len(shingles), bitorder="little").view(np.int64)[0])


def shared_counts(docs: DataFrame, counters: int = COUNTERS) -> np.ndarray:
    """Of every shingle of all texts its number of texts, added up in ``counters`` places by its hash."""
    if not counters:
        return np.zeros(1, np.int64)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mine = np.zeros(counters, np.int64)
        for batch in batches:
            for s in shingle_sets([t or b"" for t in batch.column(0).to_pylist()]):
                np.add.at(mine, (s % U(counters)).astype(np.int64), 1)
        cuts = range(0, counters, SLICE)
        packed = [zstandard.compress(mine[a : a + SLICE].tobytes(), 1) for a in cuts]
        yield pa.RecordBatch.from_arrays([pa.array(cuts, pa.int64()), pa.array(packed, pa.binary())], ["first", "n"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for first, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                sums[first] = sums.get(first, 0) + np.frombuffer(zstandard.decompress(n), np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), pa.array([zstandard.compress(x.tobytes(), 1) for x in sums.values()], pa.binary())], ["first", "n"])

    kind = "first long, n binary"
    rows = docs.select(F.col("text").cast("binary")).mapInArrow(count, kind).repartition("first").mapInArrow(add, kind).collect()
    out = np.zeros(counters, np.int64)
    for r in rows:
        out[r.first : r.first + SLICE] = np.frombuffer(zstandard.decompress(bytes(r.n)), np.int64)
    return out


def prints(docs: DataFrame, counts: np.ndarray) -> DataFrame:
    """``(doc_id, th, node, fp, size, keys)``: hash of the text, name, fingerprint and size of its set, its first shingles."""
    shared = docs.sparkSession.sparkContext.broadcast(counts.astype(np.uint32))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = shared.value
        for batch in batches:
            sets = shingle_sets([t or b"" for t in batch.column(1).to_pylist()])
            keys = []
            for s in sets:
                s = s[np.argsort(held[(s % U(len(held))).astype(np.int64)], kind="stable")]
                keys.append(s[: len(s) - (4 * len(s) + 4) // 5 + 1].view(np.int64))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(2), pa.array([set_name(s) for s in sets], pa.int64()), pa.array([set_fingerprint(s) for s in sets], pa.int64()),
                 pa.array([len(s) for s in sets], pa.int64()), pa.array(keys, pa.list_(pa.int64()))],
                ["doc_id", "th", "node", "fp", "size", "keys"],
            )

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("binary"), F.xxhash64("text").alias("th")).mapInArrow(
        run, "doc_id long, th long, node long, fp long, size long, keys array<long>"
    )


def shared_keys(nodes: DataFrame, keys: int = KEYS) -> DataFrame:
    """``(node, size, pos, k, n)``: every key of ``nodes (node, size, keys)`` that n > 1 of them have, and its place.

    Keys go to buckets of about ``keys`` packed together, as most are alone and end there.
    """
    total = nodes.agg(F.sum(F.expr("size div 5 + 1"))).first()[0] or 0
    n_buckets = max(shuffle_width(nodes.sparkSession), int(total) // keys)

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            node, size = (batch.column(c).to_numpy() for c in (0, 1))
            lists = batch.column(2)
            n = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            k = lists.flatten().to_numpy().view(U)
            of = np.repeat(np.arange(len(n), dtype=np.int32), n)
            pos = (np.arange(len(k)) - np.repeat(np.cumsum(n) - n, n)).astype(np.int32)
            bucket = (k >> U(16)) % U(n_buckets)
            order = np.argsort(bucket.astype(np.uint16 if n_buckets <= 1 << 16 else np.int64), kind="stable")
            cuts = np.flatnonzero(np.r_[True, np.diff(bucket[order].view(np.int64)) != 0]) if len(k) else []
            for a, z in zip(cuts, [*cuts[1:], len(k)]):
                mine = order[a:z]
                rows, each = np.unique(of[mine], return_counts=True)
                parts = (k[mine], pos[mine], node[rows], size[rows], each)
                yield pa.RecordBatch.from_arrays([pa.array([int(bucket[mine[0]])], pa.int32()), *(pa.array([x.tobytes()], pa.binary()) for x in parts)], names)

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[bytes]] = []
        for batch in batches:
            held += zip(*(c.to_pylist() for c in batch.columns[1:]))
        if not held:
            return
        kinds = (U, np.int32, np.int64, np.int64, np.int64)
        k, pos, node, size, each = (np.concatenate([np.frombuffer(b, t) for b in c]) for c, t in zip(zip(*held), kinds))
        held.clear()
        uniq, _, number = distinct(k)
        n = np.bincount(number, minlength=len(uniq))[number]
        del uniq, number
        more = np.flatnonzero(n > 1)
        of = np.repeat(np.arange(len(each)), each)[more]
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (node[of], size[of], pos[more], k[more].view(np.int64), n[more])], ["node", "size", "pos", "k", "n"])

    names = ["bucket", "hashes", "pos", "node", "size", "each"]
    sent = nodes.select("node", "size", "keys").mapInArrow(send, "bucket int, hashes binary, pos binary, node binary, size binary, each binary")
    return sent.repartitionById(n_buckets, "bucket").mapInArrow(meet, "node long, size long, pos int, k long, n long")


def sets_of(docs: DataFrame, nodes: DataFrame) -> DataFrame:
    """``(node, shingles binary)`` of ``nodes (th)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = shingle_sets([t or b"" for t in batch.column(0).to_pylist()])
            yield pa.RecordBatch.from_arrays(
                [pa.array([set_name(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], ["node", "shingles"]
            )

    asked = docs.select(F.xxhash64("text").alias("th"), "text").join(nodes.select("th"), "th", "left_semi")
    return asked.groupBy("th").agg(F.first("text").alias("text")).select(F.col("text").cast("binary")).mapInArrow(run, "node long, shingles binary")


def similar(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Those of ``pairs (a, b)`` whose sets are 4/5 alike."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = np.zeros(batch.num_rows, bool)
            for i, (x, y) in enumerate(zip(batch.column(2), batch.column(3))):
                x, y = np.frombuffer(x.as_buffer(), U), np.frombuffer(y.as_buffer(), U)
                keep[i] = 9 * len(np.intersect1d(x, y, assume_unique=True)) >= 4 * (len(x) + len(y))
            yield batch.select(["a", "b"]).filter(pa.array(keep))

    of = lambda c: sets.select(F.col("node").alias(c), F.col("shingles").alias(f"s{c}"))
    return pairs.join(of("a"), "a").join(of("b"), "b").select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long")


def close_pairs(nodes: DataFrame) -> DataFrame:
    """Pairs of nodes that the SimHash operator links: each with the one that stands for its linked fingerprint."""
    heads = nodes.groupBy("fp").agg(F.min("node").alias("head"))
    same = nodes.join(heads, "fp").filter("node <> head").select(F.col("head").alias("a"), F.col("node").alias("b"))
    links = near_links(heads.select("fp"))
    of = lambda c: heads.select(F.col("fp").alias(c), F.col("head").alias(f"h{c}"))
    near = links.join(of("a"), "a").join(of("b"), "b").select(F.least("ha", "hb").alias("a"), F.greatest("ha", "hb").alias("b"))
    return same.unionByName(near).distinct()


def star_pairs(keyed: DataFrame, labels: DataFrame, turn: int) -> DataFrame:
    """Each node with up to three members of its keys' groups, of other components, that stand for their groups.

    A group is stood for by the member whose keys are the most shared, and by two that the
    turn picks.  A node takes the one of these that most of its keys name, and two more.
    """
    rows = keyed.select("k", "node", "size", "weight").join(labels, "node", "left").withColumn("label", F.coalesce("root", "node")).drop("root")
    member = F.struct("node", "size", "label")
    heads = rows.groupBy("k").agg(
        F.max_by(member, F.struct("weight", "node")).alias("first"), *[f(member, F.struct(F.xxhash64("node", F.lit(turn)), "node")).alias(c) for f, c in ((F.max_by, "second"), (F.min_by, "third"))],
        F.min("label").alias("l0"), F.max("label").alias("l1"),
    ).filter("l0 <> l1")
    named = rows.join(heads.select("k", "first", "second", "third"), "k").select("node", "size", "label", F.explode(F.array("first", "second", "third")).alias("head"))
    named = named.filter("label <> head.label AND 5 * least(size, head.size) >= 4 * greatest(size, head.size)")
    # Two similar texts share many of their keys, so what shares one or two can wait for the exact join.
    counted = named.groupBy("node", "size", F.col("head.node").alias("head")).agg(F.count("*").alias("m")).filter("50 * m >= size")
    best = counted.groupBy("node").agg(
        F.max_by("head", F.struct("m", "head")).alias("x"), *[f("head", F.struct(F.xxhash64("node", "head", F.lit(turn)), "head")).alias(c) for f, c in ((F.max_by, "y"), (F.min_by, "z"))]
    )
    return best.select("node", F.explode(F.array("x", "y", "z")).alias("head")).select(F.least("node", "head").alias("a"), F.greatest("node", "head").alias("b")).distinct()


def other_pairs(keyed: DataFrame, labels: DataFrame, group: int = GROUP) -> DataFrame:
    """All pairs of different components that can be similar by sizes and the places of a shared key."""
    rows = keyed.select("k", "node", "size", "pos").join(labels, "node", "left").withColumn("label", F.coalesce("root", "node")).drop("root")
    mixed = rows.groupBy("k").agg(F.min("label").alias("l0"), F.max("label").alias("l1"), F.count("*").alias("n")).filter("l0 <> l1")
    rows = rows.join(mixed.select("k", "n"), "k").withColumn("parts", F.ceil(F.col("n") / group).cast("long"))
    # A large group is divided: each of its parts meets each, so that no task holds all of it.
    rows = rows.withColumn("mine", F.pmod(F.xxhash64("node"), F.col("parts"))).withColumn("other", F.explode(F.expr("sequence(0L, parts - 1)")))
    rows = rows.selectExpr("k", "node", "size", "pos", "label", "mine", "least(mine, other) AS p", "greatest(mine, other) AS q")
    left, right = (rows.select("k", "p", "q", *[F.col(c).alias(f"{c}_{x}") for c in ("node", "size", "pos", "label", "mine")]) for x in "ab")
    # Of what two similar texts share, the first key of the common order has enough behind it in both.
    met = left.join(right, ["k", "p", "q"]).filter(
        "node_a < node_b AND label_a <> label_b AND (mine_a <> mine_b OR p = q) AND 9 * least(size_a - pos_a, size_b - pos_b) >= 4 * (size_a + size_b)"
    )
    return met.select(F.col("node_a").alias("a"), F.col("node_b").alias("b")).distinct()


def near_copies(docs: DataFrame, group: int = GROUP, counters: int = COUNTERS, rounds: int = ROUNDS) -> DataFrame:
    """``(doc_id, component_id)``, one row per row of ``docs``; component_id is the smallest doc_id linked to it."""
    docs = docs.select("doc_id", "text")
    table = written(prints(docs, shared_counts(docs, counters)), "shingle-prints")
    # Texts with equal sets are one node.
    one = table.groupBy("node").agg(*[F.min(c).alias(a) for c, a in (("doc_id", "least"), ("th", "th"), ("fp", "fp"))], F.first("size").alias("size"), F.first("keys").alias("keys"))
    nodes = written(one, "shingle-nodes")
    keyed = written(shared_keys(nodes), "shingle-keys")
    of_node, names = written(table.select("doc_id", "node"), "shingle-docs"), written(nodes.select("node", "least", "th", "fp"), "shingle-names")
    discard(table, nodes)
    weights = keyed.groupBy("node").agg(F.sum("n").alias("weight"))
    plain, keyed = keyed, written(keyed.drop("n").join(weights, "node"), "shingle-weights")
    discard(plain)
    del one, weights, plain
    near = written(close_pairs(names.select("node", "fp")), "shingle-close")

    def linked(pairs: DataFrame, labels: DataFrame | None = None) -> DataFrame | None:
        """Labels of all nodes linked so far, or None if ``pairs`` has no similar one."""
        pairs = written(pairs, "shingle-pairs")
        ends = pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct()
        free(docs.sparkSession, 2)
        sets = written(sets_of(docs, names.join(ends, "node", "left_semi")), "shingle-sets")
        free(docs.sparkSession, 2)
        found = written(similar(pairs, sets), "shingle-links")
        discard(pairs, sets)
        if not found.take(1):
            return None
        if labels is not None:
            found = found.unionByName(labels.select(F.col("node").alias("a"), F.col("root").alias("b")))
        return written(components(found), "shingle-labels")

    labels = names.select("node", F.col("node").alias("root")).limit(0)
    for turn in range(rounds):
        pairs = star_pairs(keyed, labels, turn)
        more = linked(pairs if turn else pairs.unionByName(near).distinct(), labels if turn else None)
        if more is None:
            break
        labels = more
    roots = linked(other_pairs(keyed, labels, group), labels) or labels
    placed = names.select("node", "least").join(roots, "node", "left").select("node", "least", F.coalesce("root", "node").alias("root"))
    ids = placed.groupBy("root").agg(F.min("least").alias("component_id"))
    return of_node.join(placed.join(ids, "root").select("node", "component_id"), "node").select("doc_id", "component_id")


def keep_one(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose doc_id is the smallest of its group of near copies.

    Rows with a null doc_id stay; rows that repeat a kept doc_id stay with it.
    """
    kept = near_copies(docs).filter("doc_id = component_id").select(F.col("doc_id").alias("__kept")).distinct()
    return docs.join(kept, F.col("doc_id") == F.col("__kept"), "left").filter(
        "__kept IS NOT NULL OR doc_id IS NULL"
    ).select(*[F.col(f"`{c}`") for c in docs.columns])
