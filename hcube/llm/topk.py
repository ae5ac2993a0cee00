"""Exact top-k by inner product: columnar branch-and-bound.

Vectors are floored to integers and packed into chunks in vertical layout (one run
of memory per dimension).  Queries form blocks of bounded size; every chunk meets
every block through an equi-join on the block's number.  For each query, products
are accumulated dimension block by dimension block; by Cauchy-Schwarz no candidate
can gain more than the product of the two remaining lengths, and the columns of
those that can no longer reach the k-th best score are left out of what follows.

Defined results: null vectors, and vectors with null, NaN or infinite components,
take no part; only vectors of one length are compared; rows with a null vec_id are
candidates for none and no queries; one row equal to the query in id and vector is
taken to be the query's own, further ones count; ties go to the smaller vec_id; an empty
table gives no rows; columns other than vec_id and embedding are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .session import shuffle_width, written

SCALE = 1024
K = 10
STRIDE = 100
CHUNK = 4096
BLOCK = 256
DIMS = 8


def integer_vectors(table: DataFrame, scale: int = SCALE) -> DataFrame:
    """``(vec_id, v array<long>)`` of the rows that take part."""
    return table.filter(
        F.expr("vec_id IS NOT NULL AND embedding IS NOT NULL AND forall(embedding, x -> x IS NOT NULL "
               "AND NOT isnan(x) AND abs(cast(x as double)) < double('Infinity'))")
    ).select(
        F.col("vec_id").cast("long").alias("vec_id"),
        F.expr(f"transform(embedding, x -> cast(floor({scale}D * cast(x as double)) as bigint))").alias("v"),
    )


def _pack(rows: int):
    def blob(ids, flat, dim):
        m = np.asarray(flat, np.int64).reshape(-1, dim) if dim else np.empty((len(ids), 0), np.int64)
        return np.asarray(ids, np.int64).tobytes(), np.ascontiguousarray(m.T).tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}

        def out(dim):
            ids, parts = held.pop(dim)
            a, b = blob(np.concatenate(ids), np.concatenate(parts), dim)
            return pa.RecordBatch.from_arrays([pa.array([dim]), pa.array([a]), pa.array([b])], ["dim", "ids", "cols"])

        for batch in batches:
            ids = batch.column(0).to_numpy()
            vecs = batch.column(1)
            lens = np.diff(vecs.offsets.to_numpy())
            flat = vecs.flatten().to_numpy()
            starts = np.cumsum(lens) - lens
            for dim in np.unique(lens).tolist():
                at = np.flatnonzero(lens == dim)
                for k in range(0, len(at), rows):
                    part = at[k : k + rows]
                    cells = flat[(starts[part][:, None] + np.arange(dim)).ravel()]
                    have = held.setdefault(dim, ([], []))
                    have[0].append(ids[part])
                    have[1].append(cells)
                    if sum(map(len, have[0])) >= rows:
                        yield out(dim)
        for dim in list(held):
            yield out(dim)

    return run


def search_chunk(q: np.ndarray, cols: np.ndarray, lengths: np.ndarray, q_rest: np.ndarray, floor: float) -> tuple:
    """Positions and scores of the columns of ``cols`` that may reach ``floor``.

    ``lengths[b]`` and ``q_rest[b]`` are the lengths of what remains after block b.
    """
    alive = None
    part = np.zeros(cols.shape[1], cols.dtype)
    for b, k in enumerate(range(0, len(q), DIMS)):
        block = cols[k : k + DIMS] if alive is None else cols[k : k + DIMS][:, alive]
        part = part + q[k : k + DIMS] @ block
        if floor > -np.inf:
            rest = lengths[b] if alive is None else lengths[b][alive]
            keep = part + q_rest[b] * rest * (1 + 1e-9) + 1e-3 >= floor
            if not keep.all():
                part = part[keep]
                alive = np.flatnonzero(keep) if alive is None else alive[keep]
                if not len(alive):
                    break
    return (np.arange(len(part)) if alive is None else alive), part


def _best(ids: np.ndarray, scores: np.ndarray, k: int) -> tuple:
    if len(ids) > k:
        edge = np.partition(scores, len(scores) - k)[len(scores) - k]
        near = scores >= edge
        ids, scores = ids[near], scores[near]
    order = np.lexsort((ids, -scores))[:k]
    return ids[order], scores[order]


def _search(k: int):
    def rests(cols):
        sq = cols.astype(np.float64) ** 2
        tail = np.cumsum(sq[::-1], axis=0)[::-1]
        return np.sqrt(np.stack([tail[min(b + DIMS, len(tail)) :][:1].sum(0) for b in range(0, max(len(cols), 1), DIMS)]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: dict[tuple[int, int], tuple] = {}
        asked: dict[tuple[int, int], int] = {}
        for batch in batches:
            for row in batch.to_pylist():
                dim = row["dim"]
                c_ids, q_ids = (np.frombuffer(row[x], np.int64) for x in ("ids", "q_ids"))
                cols, qs = (np.frombuffer(row[x], np.int64).reshape(dim, -1) for x in ("cols", "q_cols"))
                if not dim:
                    cols, qs = np.empty((0, len(c_ids)), np.int64), np.empty((0, len(q_ids)), np.int64)
                top = max([1, *(int(np.abs(x).max()) for x in (cols, qs) if x.size)])
                kind = np.float64 if top * top * max(dim, 1) < 2**52 else object  # exact either way
                cols, qs = cols.astype(kind), qs.astype(kind)
                spread = np.argsort(-np.abs(cols.astype(np.float64)).sum(1), kind="stable")  # heavy dimensions first
                cols, qs = np.ascontiguousarray(cols[spread]), qs[spread]
                lengths, q_rest = rests(cols), rests(qs)
                for j in range(len(q_ids)):
                    key = (row["block"], j)
                    asked[key] = int(q_ids[j])
                    ids, scores = best.get(key, (np.empty(0, np.int64), np.empty(0, kind)))
                    floor = scores[k] if len(scores) > k else -np.inf
                    # The query's own row is still among the candidates: keep k + 1.
                    for a, b in ((0, 8 * k), (8 * k, cols.shape[1])) if floor == -np.inf else ((0, cols.shape[1]),):
                        if a >= cols.shape[1]:
                            continue
                        at, got = search_chunk(np.ascontiguousarray(qs[:, j]), cols[:, a:b], lengths[:, a:b], q_rest[:, j], float(floor))
                        ids, scores = _best(np.r_[ids, c_ids[a:b][at]], np.r_[scores, got], k + 1)
                        floor = scores[k] if len(scores) > k else -np.inf
                    best[key] = (ids, scores)
        for (block, j), (ids, scores) in best.items():
            n = len(ids)
            yield pa.RecordBatch.from_arrays(
                [pa.array([block] * n, pa.int64()), pa.array([j] * n, pa.int64()), pa.array([asked[block, j]] * n, pa.int64()),
                 pa.array(ids, pa.int64()), pa.array([int(x) for x in scores], pa.int64())],
                ["block", "place", "query_id", "vec_id", "score"],
            )

    return run


def top_k(queries: DataFrame, table: DataFrame, k: int = K) -> DataFrame:
    """``(query_id, rank, vec_id, score)``: the k best rows of ``table`` for each row of ``queries``.

    Both come from ``integer_vectors``; a query's own row in ``table`` is left out.
    """
    spark = table.sparkSession
    n_blocks = max(1, -(-queries.count() // BLOCK))
    packed = queries.repartition(n_blocks).mapInArrow(_pack(BLOCK), "dim long, ids binary, cols binary")
    # Written once: a block's number must stay the same for whoever reads it.
    blocks = written(packed, "query-blocks").withColumn("block", F.xxhash64("dim", "ids", "cols")).select(
        "dim", "block", F.pmod("block", F.lit(n_blocks)).alias("lane"),
        F.col("ids").alias("q_ids"), F.col("cols").alias("q_cols"),
    )
    salts = max(1, 2 * shuffle_width(spark) // n_blocks)
    chunks = table.mapInArrow(_pack(CHUNK), "dim long, ids binary, cols binary").select(
        "dim", "ids", "cols", F.pmod(F.xxhash64("ids"), F.lit(salts)).alias("salt"),
        F.explode(F.expr(f"sequence(0L, {n_blocks - 1}L)")).alias("lane"),
    )
    asked = blocks.withColumn("salt", F.explode(F.expr(f"sequence(0L, {salts - 1}L)")))
    found = chunks.join(asked, ["dim", "lane", "salt"]).select(
        "dim", "block", "ids", "cols", "q_ids", "q_cols"
    ).mapInArrow(_search(k), "block long, place long, query_id long, vec_id long, score long")
    # The own row: the first with the query's id and the query's score with itself.
    own = queries.select(
        F.col("vec_id").alias("query_id"), F.expr("aggregate(v, 0L, (a, x) -> a + x * x)").alias("self")
    ).distinct()
    found = found.join(own.groupBy("query_id").agg(F.collect_set("self").alias("selves")), "query_id")
    by_query = Window.partitionBy("block", "place").orderBy(F.desc("score"), "vec_id")
    mine = (F.col("vec_id") == F.col("query_id")) & F.array_contains("selves", F.col("score"))
    first = F.sum(mine.cast("int")).over(by_query.rowsBetween(Window.unboundedPreceding, 0))
    return (
        found.withColumn("__own", mine & (first == 1)).filter("NOT __own")
        .withColumn("rank", F.row_number().over(by_query)).filter(F.col("rank") <= k)
        .select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
    )


def op4_exact_topk(embeddings: DataFrame) -> DataFrame:
    table = integer_vectors(embeddings.select("vec_id", "embedding"))
    return top_k(table.filter(F.pmod("vec_id", F.lit(STRIDE)) == 0), table)
