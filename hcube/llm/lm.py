"""Hierarchical Pitman-Yor language model of word triples, gathered and sampled in Spark.

Every pair of words before a token is a context with a restaurant of its own; its parent
drops the farther word, the parent's parent is the root that all share, and the root's
base is uniform over the known words and one unknown.  Customers of a pair are the
training tokens behind it; every table sends a customer to the parent.  No context is
left out, so the restaurants grow with the corpus.

How it runs.  Texts become blocks of about two million tokens (a written table; texts are
read once).  A block adds up its triples and sends each to the bucket of its middle
word, where the pair's restaurant, its parent and their tables meet.  Middle words with
more than ``HOT`` training tokens are dealt by the farther word too; their parents
are then kept with the root.  The chain, one for the whole corpus:

1. buckets sample the tables of pairs and parents for a few sweeps (``Chain.early``), under
   a root taken from the counts of the commonest words;
2. the tables of all buckets are added up by word, and the root and the parents of hot
   words are sampled (``Chain.root``);
3. buckets go on from where they were under that root, for ``Chain.burn_in`` sweeps and
   then ``Chain.samples`` more over which the predictive probabilities are averaged.

A sweep is a Gibbs step that reseats all customers of every dish at once: the number of
tables is drawn from its conditional given the other dishes of the sweep before, that is
generalised Stirling numbers times the weights of new tables (``draw_tables``).  Draws
are hashes of the dish and the sweep, so scores don't depend on blocks, buckets or
partitions.  Step 3 repeats step 1 instead of reading it: draws are the same.

Defined results: null and empty texts have only the end token; very long texts are
hashed in runs and may fill a block alone; a null doc_id keeps its row and trains (its
checksum is null, so it is not held out); repeated rows count and score each; an empty
table gives no rows; without training rows all words are unknown; columns other than
doc_id, held and text are not read.  Words are compared by 64-bit hashes.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import Broadcast, TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import discard, free, shuffle_width, written
from .words import U, distinct, mix, word_hashes

END, START = U(0x0E0D5EED0E0D5EED), U(0x57A7757A7757A775)
BLOCK_TOKENS = 1 << 21
BUCKET_TOKENS = 1 << 21
CODED = 1 << 19  # words that travel as their rank; the others as 48 bits of their hash
HOT, HOT_SHARE = 1 << 20, 1 << 20
ROUNDS = 4  # in which blocks meet their answers
#: Discounts and strengths of pairs, single words and the root.
DISCOUNTS, STRENGTHS = (0.85, 0.75, 0.65), (1.0, 1.0, 1.0)
EXACT = 256
SEED = U(20)


class Chain(NamedTuple):
    """Sweeps of each step of the chain."""

    early: int = 2
    root: int = 3
    burn_in: int = 2
    samples: int = 3


_BLOCK = "block long, doc_ids array<long>, held binary, n_tokens binary, words binary, ids binary, n_train long"


def ragged(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Places first, first + 1, ... of every run, behind each other."""
    return np.repeat(first - np.cumsum(n) + n, n) + np.arange(n.sum())


def _packed(x: np.ndarray) -> bytes:
    """Bytes of an array plane by plane, compressed: counts, numbers and rounded logs are small."""
    planes = np.ascontiguousarray(x).view(np.uint8).reshape(len(x), x.dtype.itemsize).T
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(planes).tobytes())


def _unpacked(b: bytes, kind: type) -> np.ndarray:
    planes = np.frombuffer(zstandard.decompress(b), np.uint8).reshape(np.dtype(kind).itemsize, -1)
    return np.ascontiguousarray(planes.T).reshape(-1).view(kind)


def text_blocks(docs: DataFrame, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """Blocks of about ``block_tokens`` tokens from ``(doc_id, held, text binary)``."""

    def block(name: int, rows) -> pa.RecordBatch:
        doc_ids = [d for part in rows for d in part[0]]
        held = np.concatenate([p[1] for p in rows])
        hashes, counts = np.concatenate([p[2] for p in rows]), np.concatenate([p[3] for p in rows])
        # The end token of each text goes behind its words.
        n = counts + 1
        tokens = np.full(n.sum(), END, U)
        inner = np.ones(len(tokens), bool)
        inner[np.cumsum(n) - 1] = False
        tokens[inner] = hashes
        words, _, ids = distinct(tokens)
        # Common words get small numbers, which compress better.
        common = np.argsort(-np.bincount(ids), kind="stable")
        place = np.empty(len(words), np.int64)
        place[common] = np.arange(len(words))
        words, ids = words[common], place[ids]
        cols = [
            pa.array([name]), pa.array([doc_ids], pa.list_(pa.int64())),
            *(pa.array([_packed(x)], pa.binary()) for x in (held, n.astype(np.int64), words, ids.astype(np.uint32))),
            pa.array([int(n[~held].sum())]),
        ]
        return pa.RecordBatch.from_arrays(cols, [f.split()[0] for f in _BLOCK.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name = TaskContext.get().partitionId() << 32
        rows, size = [], 0
        for batch in batches:
            ids, held, texts = batch.column(0).to_pylist(), batch.column(1).to_numpy(zero_copy_only=False), batch.column(2)
            k = 0
            while k < len(ids):
                upto, mass = k, 0
                while upto < len(ids) and mass < 1 << 21:
                    mass += len(texts[upto].as_buffer() or b"") if texts[upto].is_valid else 0
                    upto += 1
                hashes, counts = word_hashes([t or b"" for t in texts[k:upto].to_pylist()])
                rows.append((ids[k:upto], held[k:upto], hashes, counts))
                size += len(hashes) + upto - k
                k = upto
                if size >= block_tokens:
                    yield block(name, rows)
                    name, rows, size = name + 1, [], 0
        if rows:
            yield block(name, rows)

    return docs.mapInArrow(run, _BLOCK)


class Words(NamedTuple):
    """What is known of the training words before triples are gathered.

    ``hot``: hashes of middle words that are dealt to several buckets, start and end
    among them, with ``hot_counts``; ``coded``: hashes of at most ``CODED`` commonest
    words sorted by hash, ``ranks`` and ``shares``: their places by frequency and their
    shares of the tokens, ``by_rank``: the hashes by frequency, one place more at the end.
    """

    hot: np.ndarray
    hot_counts: np.ndarray
    coded: np.ndarray
    ranks: np.ndarray
    shares: np.ndarray
    by_rank: np.ndarray
    n_train: int
    known: int
    chain: Chain = Chain()

    def first_root(self, codes: np.ndarray) -> np.ndarray:
        """The root's probabilities before its first sample, by the words' codes: counted shares, the rest uniform."""
        rest = max(1.0 - self.shares.sum(), 0.0) + 1.0 / (self.n_train + 1)
        by_code = np.full(len(self.coded) + 1, rest / (self.known - len(self.coded) + 1))
        by_code[self.ranks] = self.shares
        return by_code[codes]


def training_words(blocks: DataFrame, coded: int = CODED, hot: int | None = None) -> Words:
    """Counts all training words; brings the commonest and those that are hot to the driver (both bounded)."""

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                words, ids, n = _unpacked(row["words"], U), _unpacked(row["ids"], np.uint32), _unpacked(row["n_tokens"], np.int64)
                train = np.bincount(ids[np.repeat(~_unpacked(row["held"], bool), n)], minlength=len(words))
                yield pa.RecordBatch.from_arrays([pa.array(words[train > 0].view(np.int64)), pa.array(train[train > 0])], ["w", "n"])

    counts = written(
        blocks.select("words", "ids", "n_tokens", "held").mapInArrow(run, "w long, n long").groupBy("w").agg(F.sum("n").alias("n")), "lm-words"
    )
    size = counts.agg(F.sum("n").alias("n"), F.count("*").alias("v")).first()
    n_train, known = int(size.n or 0), int(size.v)
    top = counts.orderBy(F.desc("n"), "w").limit(coded).toArrow()
    many = max(HOT, n_train // HOT_SHARE) if hot is None else hot
    marks = [int(x.view(np.int64)) for x in (START, END)]
    over = counts.filter((F.col("n") > many) | F.col("w").isin(marks)).collect()
    found = {x: 0 for x in marks} | {r.w: r.n for r in over}
    discard(counts)
    hot = sorted(found, key=lambda x: x & (2**64 - 1))
    w, n = top["w"].to_numpy().view(U), top["n"].to_numpy()
    ranks = np.lexsort((w, -n)).argsort()
    order = np.argsort(w)
    return Words(
        np.array(hot, np.int64).view(U), np.array([found[x] for x in hot], np.int64), w[order], ranks[order].astype(np.uint32), n[order] / max(n_train, 1),
        np.append(w[np.argsort(ranks)], U(0)), n_train, known,
    )


def block_triples(row: dict, words: np.ndarray) -> tuple[np.ndarray, ...]:
    """Distinct triples of a block as numbers (middle, farther, word), training counts, each token's triple.

    Numbers are places in ``words``; the start of a text has the number behind them.
    """
    n, ids = _unpacked(row["n_tokens"], np.int64), _unpacked(row["ids"], np.uint32).view(np.int32)
    held = _unpacked(row["held"], bool)
    width = len(words) + 1
    begin = np.cumsum(n) - n
    middle, far = np.empty_like(ids), np.empty_like(ids)
    middle[1:], far[2:] = ids[:-1], ids[:-2]
    middle[begin] = far[begin] = width - 1
    far[begin[n > 1] + 1] = width - 1
    if width <= 1 << 21:  # three numbers in 63 bits; a product with an odd number keeps them apart
        key = middle.astype(np.int64)
        for x in (far, ids):
            key *= width
            key += x
        key = key.view(U)
        key *= U(0x9E3779B97F4A7C15)
    else:  # a very long text: by 64-bit hashes
        key = mix(mix((middle.astype(np.int64) * width + far).view(U)) + ids.astype(U))
    _, first, of = distinct(key)
    train = np.bincount(of[np.repeat(~held, n)], minlength=len(first))
    return middle[first], far[first], ids[first], train, of


def _codes(words: np.ndarray, known: Words) -> np.ndarray:
    """Ranks of words, one beyond the last for those that have none."""
    if not len(known.coded):
        return np.zeros(len(words), np.uint32)
    at = np.minimum(np.searchsorted(known.coded, words), len(known.coded) - 1)
    return np.where(known.coded[at] == words, known.ranks[at], len(known.coded)).astype(np.uint32)


def _decoded(rows: list[dict], codes: str, rest: str, known: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Words of all rows behind each other, how many each row has, and the words' codes."""
    parts = [_unpacked(r[codes], np.uint32) for r in rows]
    every = np.concatenate(parts)
    out = known.by_rank[every]
    out[every == len(known.coded)] = np.concatenate([_unpacked(r[rest], U) for r in rows])
    return out, np.array([len(x) for x in parts]), every


def _order(row: dict, words: np.ndarray, known: Words, n_buckets: int):
    """A block's triples in the order of its requests: by bucket, then by middle word."""
    middle, far, word, train, of = block_triples(row, words)
    names = np.r_[words, START]
    hot = known.hot[np.minimum(np.searchsorted(known.hot, names), len(known.hot) - 1)] == names
    cold_bucket = ((names >> U(16)) % U(n_buckets)).astype(np.int64)
    bucket = cold_bucket[middle]
    dealt = np.flatnonzero(hot[middle])
    bucket[dealt] = (mix(names[middle[dealt]] + mix(names)[far[dealt]]) >> U(16)) % U(n_buckets)
    low, high = (max(n - 1, 1).bit_length() for n in (len(middle), len(names)))
    if low + high + n_buckets.bit_length() <= 64:  # bucket, middle word and place sorted as one number
        packed = np.sort((bucket.astype(U) << U(high) | middle.astype(U)) << U(low) | np.arange(len(middle), dtype=U))
        order = (packed & U((1 << low) - 1)).astype(np.int64)
    else:
        order = np.lexsort((middle, bucket))
    return middle, far, word, train, of, names, bucket, order


_ASKED = "block long, bucket int, middle binary, middle_rest binary, n_triples binary, codes binary, rest binary, train binary, answer binary"


def _requests(row: dict, known: Words, n_buckets: int) -> pa.RecordBatch:
    middle, far, word, train, of, names, bucket, order = _order(row, _unpacked(row["words"], U), known, n_buckets)
    del of
    b_sorted, m_sorted, codes = bucket[order], middle[order], _codes(names, known)
    del bucket, middle
    cuts = np.flatnonzero(np.r_[True, b_sorted[1:] != b_sorted[:-1]])
    out = []
    for a, z in zip(cuts, [*cuts[1:], len(order)]):
        first = a + np.flatnonzero(np.r_[True, np.diff(m_sorted[a:z]) != 0])
        both = np.r_[far[order[a:z]], word[order[a:z]]]
        sent = codes[both]
        mine = codes[m_sorted[first]]
        out.append((row["block"], int(b_sorted[a]), _packed(mine), _packed(names[m_sorted[first[mine == len(known.coded)]]]), _packed(np.diff(np.r_[first, z]).astype(np.uint32)),
                    _packed(sent), _packed(names[both[sent == len(known.coded)]] & U((1 << 48) - 1)), _packed(train[order[a:z]].astype(np.uint32))))
    cols = list(zip(*out))
    return pa.RecordBatch.from_arrays(
        [pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[2:]),
         pa.nulls(len(out), pa.binary())],
        [f.split()[0] for f in _ASKED.split(", ")],
    )


def requests(blocks: DataFrame, shared: Broadcast, n_buckets: int) -> DataFrame:
    """What each block asks of each bucket: middle words, their triples and training counts."""

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                yield _requests(row, shared.value, n_buckets)

    return blocks.select("block", "held", "n_tokens", "words", "ids").mapInArrow(run, _ASKED)


# ---- the sampler ----


@functools.lru_cache(maxsize=8)
def stirling_logs(discount: float, most: int = EXACT) -> np.ndarray:
    """Logs of generalised Stirling numbers, row c and column t: seatings of c customers at t tables, weighted."""
    out = np.full((most + 1, most + 1), -np.inf)
    out[1, 1] = 0.0
    t = np.arange(most + 1)
    with np.errstate(divide="ignore", invalid="ignore"):
        for c in range(1, most):
            stay = np.where(t <= c, out[c] + np.log(np.maximum(c - discount * t, 1e-300)), -np.inf)
            out[c + 1] = np.logaddexp(stay, np.r_[-np.inf, out[c, :-1]])
    return out


def uniform(keys: np.ndarray, turn: int) -> np.ndarray:
    """A number in (0, 1) for each dish and turn."""
    x = mix(keys + mix(np.array([turn], U) * U(0x9E3779B97F4A7C15) + SEED)[0])
    return ((x >> U(11)).astype(np.float64) + 0.5) * 2.0**-53


class Weights(NamedTuple):
    """How likely a further table is for dishes that have k: (strength + discount * (tables + k)) * p(k).

    ``tables``: of the restaurant without this dish's own.  p(k), the parent's probability
    with k customers from here, is ``p`` if ``rest`` is None, else
    ``(max(rest + k - held * (1 + slope * (rest + k - 1)), 0) + p) / (room + k)``:
    ``rest`` and ``room`` are the parent's customers without this dish's, of the dish and
    in all, and its tables are taken in proportion to its customers.
    """

    strength: float
    discount: float
    tables: np.ndarray
    p: np.ndarray
    rest: np.ndarray | None = None
    held: float = 0.0
    slope: np.ndarray | None = None
    room: np.ndarray | None = None

    def at(self, i: np.ndarray, k: np.ndarray) -> np.ndarray:
        """Weights of dishes ``i`` (column) with ``k`` tables (row or as i)."""
        of = (lambda x: x[i][:, None]) if k.ndim == 2 else (lambda x: x[i])
        new = self.strength + self.discount * (of(self.tables) + k)
        if self.rest is None:
            return new * of(self.p)
        n = of(self.rest) + k
        return new * (np.maximum(n - self.held * (1 + of(self.slope) * (n - 1)), 0) + of(self.p)) / (of(self.room) + k)


def draw_tables(counts: np.ndarray, now: np.ndarray, weights: Weights, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Numbers of tables of dishes with ``counts`` customers, each from its conditional.

    Up to ``EXACT`` customers by their weights: Stirling numbers times the product of the
    weights of the tables opened.  Above, tables are clusters of a Poisson number tilted to
    the count of customers, with the weight held at the present number of tables: its mean
    and variance given the count are known, one table is always there.
    """
    logs = stirling_logs(weights.discount)
    out = np.minimum(counts, 1).astype(np.int64)
    width = 2
    while width <= EXACT:
        group = np.flatnonzero((counts > width // 2) & (counts <= width) & (counts > 1))
        k = np.arange(1, width)[None, :]
        step = max(1, (1 << 18) // width)
        for a in range(0, len(group), step):
            i = group[a : a + step]
            table = logs[counts[i], 1 : width + 1]
            table[:, 1:] += np.cumsum(np.log(weights.at(i, k)), axis=1)
            table = np.exp(table - table.max(axis=1, keepdims=True))
            table = np.cumsum(table, axis=1)
            out[i] = np.minimum(1 + (table < (u[i] * table[:, -1])[:, None]).sum(axis=1), counts[i])
        width *= 2
    big = np.flatnonzero(counts > EXACT)
    if len(big):
        d, c = weights.discount, counts[big].astype(np.float64)
        a = weights.at(big, now[big])
        # y in (0, 1] solves a (1 - y) y^(d - 1) = c, so that clusters have c customers in the mean.
        low, high = np.full(len(big), -700.0), np.zeros(len(big))
        for _ in range(60):
            mid = (low + high) / 2
            up = np.log(a) + np.log1p(-np.exp(mid)) + (d - 1) * mid > np.log(c)
            low, high = np.where(up, mid, low), np.where(up, high, mid)
        y = np.exp((low + high) / 2)
        mean = a / d * (1 - y**d)
        spread = np.maximum(mean - c * y / (1 - d * (1 - y)), 0.01)
        normal = np.sqrt(-2 * np.log(u[big])) * np.cos(2 * np.pi * v[big])
        drawn = np.rint(mean + np.sqrt(spread) * normal)
        few = np.flatnonzero(mean < 20)
        if len(few):
            part = np.exp(-mean[few])
            upto, n = part.copy(), np.zeros(len(few))
            for k in range(1, 100):
                n += u[big][few] > upto
                part = part * mean[few] / k
                upto += part
            drawn[few] = n
        out[big] = 1 + np.clip(drawn, 0, c - 1).astype(np.int64)
    return out


class Bucket:
    """The restaurants of one bucket: triples ``(middle, far, word)`` with training counts, added up.

    Pairs and parents are numbered in the order of the sorted triples; ``asked`` gives the
    place of every triple that was asked for.
    """

    def __init__(self, middle: np.ndarray, far: np.ndarray, word: np.ndarray, train: np.ndarray, known: Words, codes: np.ndarray | None = None):
        self.known = known
        # Pairs, dishes of parents and triples are compared by 64-bit hashes.
        key = word * U(0xA0761D6478BD642F)
        key += middle
        dish_name = mix(key)
        np.multiply(far, U(0xD6E8FEB86659FD93), out=key)
        key += middle
        far_name = mix(key)
        np.multiply(dish_name, U(0x9E3779B97F4A7C15), out=key)
        key += far_name
        self.key, first, self.asked = distinct(key)
        del key
        far_name, dish_name = far_name[first], dish_name[first]
        self.c = np.bincount(self.asked, weights=train, minlength=len(first)).astype(np.int64)
        pair_names, _, self.pair = distinct(far_name)
        del far_name
        self.dish_names, at, self.dish = distinct(dish_name)
        del dish_name
        at = first[at]
        self.dish_word = word[at]
        self.dish_code = _codes(self.dish_word, known) if codes is None else codes[at]
        self.middles, _, self.dish_middle = distinct(middle[at])
        self.hot = np.isin(self.middles, known.hot)
        self.hot_dish = self.hot[self.dish_middle]
        # What stays as it is: triples of one customer, and parents' dishes that get one at most.
        self.pair_c = np.bincount(self.pair, weights=self.c, minlength=len(pair_names)).astype(np.int64)
        dish_c = np.bincount(self.dish, weights=self.c, minlength=len(at))
        self.middle_c = np.bincount(self.dish_middle, weights=dish_c, minlength=len(self.middles)).astype(np.int64)
        self.busy, one = np.flatnonzero(self.c > 1), self.c == 1
        self.pair_one = np.bincount(self.pair, weights=one, minlength=len(pair_names))
        self.dish_one = np.bincount(self.dish, weights=one, minlength=len(at))
        self.t = np.minimum(self.c, 1)
        self._add_up()
        self.dish_t = np.where(self.hot_dish, 0, np.minimum(self.n, 1))
        self.busy_dish = np.flatnonzero(~self.hot_dish & (dish_c > 1))
        idle = np.ones(len(at), bool)
        idle[self.busy_dish] = False
        of = lambda x: np.bincount(self.dish_middle[idle], weights=x[idle], minlength=len(self.middles))
        self.size_one, self.tables_one = of(self.n), of(self.dish_t)
        self.turn = 0

    def _add_up(self) -> None:
        """Customers of the parents, from the tables of the pairs."""
        of = lambda x, one: one + np.bincount(x[self.busy], weights=self.t[self.busy], minlength=len(one))
        self.n, self.pair_t = of(self.dish, self.dish_one).astype(np.int64), of(self.pair, self.pair_one)

    def _parent_sizes(self) -> tuple[np.ndarray, np.ndarray]:
        """Customers and tables of the parents, by middle word."""
        m, i = self.dish_middle[self.busy_dish], self.busy_dish
        of = lambda x, one: one + np.bincount(m, weights=x[i], minlength=len(one))
        return of(self.n, self.size_one), of(self.dish_t, self.tables_one)

    def parents(self, root: np.ndarray) -> np.ndarray:
        """Parents' probabilities; of hot middle words they are what ``root`` says."""
        n, t, m = self.n, self.dish_t, self.dish_middle
        size, tables = self._parent_sizes()
        p = (n - DISCOUNTS[1] * t + (STRENGTHS[1] + DISCOUNTS[1] * tables[m]) * root) / (STRENGTHS[1] + size[m])
        return np.where(self.hot_dish, root, p)

    def sweep(self, root: np.ndarray) -> None:
        m, i = self.dish_middle, self.busy
        d = self.dish[i]
        size, tables = self._parent_sizes()
        hot = self.hot_dish[d]
        own, pair = self.t[i], self.pair[i]
        draw = [uniform(self.key[i], 4 * self.turn + k) for k in (0, 1)]
        others = self.pair_t[pair] - own
        new = np.empty(len(i), np.int64)
        a = np.flatnonzero(hot)
        if len(a):
            w = Weights(STRENGTHS[0], DISCOUNTS[0], others[a], root[d[a]])
            new[a] = draw_tables(self.c[i[a]], own[a], w, draw[0][a], draw[1][a])
        a = np.flatnonzero(~hot)
        if len(a):
            e = d[a]
            slope = (self.dish_t[e] - 1) / np.maximum(self.n[e] - 1, 1)
            w = Weights(
                STRENGTHS[0], DISCOUNTS[0], others[a], (STRENGTHS[1] + DISCOUNTS[1] * tables[m[e]]) * root[e],
                self.n[e] - own[a], DISCOUNTS[1], slope, STRENGTHS[1] + size[m[e]] - own[a],
            )
            new[a] = draw_tables(self.c[i[a]], own[a], w, draw[0][a], draw[1][a])
        self.t[i] = new
        self._add_up()
        e = self.busy_dish
        n, own = self.n[e], np.minimum(np.maximum(self.dish_t[e], 1), self.n[e])
        self.dish_t[e] = own
        _, tables = self._parent_sizes()
        w = Weights(STRENGTHS[1], DISCOUNTS[1], tables[m[e]] - own, root[e])
        names = self.dish_names[e]
        self.dish_t[e] = draw_tables(n, own, w, uniform(names, 4 * self.turn + 2), uniform(names, 4 * self.turn + 3))
        self.turn += 1

    def predictive(self, root: np.ndarray) -> np.ndarray:
        p = self.parents(root)[self.dish]
        return (self.c - DISCOUNTS[0] * self.t + (STRENGTHS[0] + DISCOUNTS[0] * self.pair_t[self.pair]) * p) / (STRENGTHS[0] + self.pair_c[self.pair])

    def early(self) -> None:
        root = self.known.first_root(self.dish_code)
        for _ in range(self.known.chain.early):
            self.sweep(root)

    def late(self, root: np.ndarray) -> np.ndarray:
        """Averaged probabilities of the triples under ``root`` (by dish)."""
        mean, chain = np.zeros(len(self.c)), self.known.chain
        for k in range(chain.burn_in + chain.samples):
            self.sweep(root)
            if k >= chain.burn_in:
                mean += self.predictive(root)
        return mean / chain.samples

    def sent(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """What the root is told: (hot middle word or 0, word, customers), and the place of every dish there.

        A word's customers from all cold middle words here are one row.
        """
        name = np.where(self.hot_dish, self.middles[self.dish_middle], U(0))
        _, first, of = distinct(mix(self.dish_word ^ mix(name)))
        n = np.bincount(of, weights=np.where(self.hot_dish, self.n, self.dish_t), minlength=len(first)).astype(np.int64)
        return name[first], self.dish_word[first], n, of


def _buckets(batches, known: Words) -> Iterator[tuple[int, list[tuple[int, int, int]], Bucket, list[dict]]]:
    """The buckets of a partition: name, (block, middle words, triples) of each request, restaurants, root's answers.

    What a bucket is made from is let go before it is handed on; callers drop it before they ask for the next.
    """

    def finish(bucket: int, taken: list[dict]):
        said = [r for r in taken if r["answer"] is not None]
        rows = sorted((r for r in taken if r["answer"] is None), key=lambda r: r["block"])
        taken.clear()
        if not rows:
            return None
        middles, n_middles, _ = _decoded(rows, "middle", "middle_rest", known)
        # Each row has its farther words and then its words.
        both, n_both, codes = _decoded(rows, "codes", "rest", known)
        n = n_both // 2
        first = ragged(np.cumsum(n_both) - n_both, n)
        far = both[first]
        first += np.repeat(n, n)
        word, codes = both[first], codes[first]
        each, train = (np.concatenate([_unpacked(r[c], np.uint32) for r in rows]) for c in ("n_triples", "train"))
        asked = [(r["block"], mine, int(k)) for r, mine, k in zip(rows, np.split(middles, np.cumsum(n_middles)[:-1]), n)]
        del both, first, rows
        return bucket, asked, Bucket(np.repeat(middles, each), far, word, train, known, codes), said

    rows, mine = [], None
    for batch in batches:
        for row in batch.to_pylist():
            if row["bucket"] != mine:
                if rows:
                    yield from filter(None, [finish(mine, rows)])
                rows, mine = [], row["bucket"]
            rows.append(row)
    if rows:
        yield from filter(None, [finish(mine, rows)])


# ---- the root ----

_TOLD = "bucket int, part int, hot binary, codes binary, rest binary, n binary"


def _told(asked: DataFrame, shared: Broadcast, n_buckets: int) -> DataFrame:
    """Step 1: the tables of each bucket by word, for the parts that keep the root."""

    return asked.mapInArrow(lambda batches: _tell(batches, shared.value, n_buckets), _TOLD)


def _tell(batches, known: Words, n_buckets: int) -> Iterator[pa.RecordBatch]:
    for bucket, _, rooms, _ in _buckets(batches, known):
        rooms.early()
        hot, word, n, _ = rooms.sent()
        del rooms, _
        codes = _codes(word, known)
        part = ((word >> U(16)) % U(n_buckets)).astype(np.int32)
        order = np.argsort(part, kind="stable")
        cuts = np.flatnonzero(np.r_[True, np.diff(part[order]) != 0])
        for a, z in zip(cuts, [*cuts[1:], len(order)]):
            mine = order[a:z]
            yield pa.RecordBatch.from_arrays(
                [pa.array([bucket], pa.int32()), pa.array([part[mine[0]]], pa.int32()),
                 *(pa.array([_packed(x)], pa.binary()) for x in (hot[mine], codes[mine], word[mine[codes[mine] == len(known.coded)]], n[mine]))],
                [f.split()[0] for f in _TOLD.split(", ")],
            )


class Root:
    """A part of the root: words with their customers from cold middle words, and the parents of hot ones."""

    def __init__(self, hot: np.ndarray, word: np.ndarray, n: np.ndarray, known: Words):
        names, first, self.asked = distinct(mix(word ^ mix(hot)))
        self.names, self.hot, word = names, hot[first], word[first]
        self.n = np.bincount(self.asked, weights=n, minlength=len(first)).astype(np.int64)
        self.parent = np.flatnonzero(self.hot > 0)
        self.which = np.searchsorted(known.hot, self.hot[self.parent])
        self.words, _, self.of = distinct(word)
        self.word_names = mix(self.words)
        self.cold = np.bincount(self.of, weights=np.where(self.hot > 0, 0, self.n), minlength=len(self.words)).astype(np.int64)
        self.t = np.minimum(self.n[self.parent], 1)
        self.known = known
        self._add_up()
        self.root_t = np.minimum(self.customers, 1)

    def _add_up(self) -> None:
        self.customers = self.cold + np.bincount(self.of[self.parent], weights=self.t, minlength=len(self.words)).astype(np.int64)

    def totals(self) -> tuple[int, int, np.ndarray, np.ndarray]:
        """Customers and tables here, and of the parents of each hot word."""
        size = lambda x: np.bincount(self.which, weights=x, minlength=len(self.known.hot)).astype(np.int64)
        return int(self.customers.sum()), int(self.root_t.sum()), size(self.n[self.parent]), size(self.t)

    def probabilities(self, all_n: int, all_t: int) -> np.ndarray:
        flat = (STRENGTHS[2] + DISCOUNTS[2] * all_t) / (self.known.known + 1)
        return (self.customers - DISCOUNTS[2] * self.root_t + flat) / (STRENGTHS[2] + all_n)

    def sweep(self, turn: int, totals) -> None:
        all_n, all_t, hot_n, hot_t = totals
        p = self.probabilities(all_n, all_t)
        i = np.flatnonzero(self.n[self.parent] > 0)
        w = Weights(STRENGTHS[1], DISCOUNTS[1], (hot_t[self.which] - self.t)[i], p[self.of[self.parent]][i])
        names = self.names[self.parent][i]
        self.t[i] = draw_tables(self.n[self.parent][i], self.t[i], w, uniform(names, 4 * turn), uniform(names, 4 * turn + 1))
        self._add_up()
        self.root_t = np.minimum(np.maximum(self.root_t, 1), self.customers)
        i = np.flatnonzero(self.customers > 0)
        flat = np.full(len(i), 1.0 / (self.known.known + 1))
        w = Weights(STRENGTHS[2], DISCOUNTS[2], (all_t - self.root_t)[i], flat)
        self.root_t[i] = draw_tables(self.customers[i], self.root_t[i], w, uniform(self.word_names[i], 4 * turn + 2), uniform(self.word_names[i], 4 * turn + 3))

    def answers(self, totals) -> np.ndarray:
        """Probability of every row asked: of a hot word's parent, or of the root."""
        all_n, all_t, hot_n, hot_t = totals
        p = self.probabilities(all_n, all_t)[self.of]
        base, j = p[self.parent], self.which
        p[self.parent] = (self.n[self.parent] - DISCOUNTS[1] * self.t + (STRENGTHS[1] + DISCOUNTS[1] * hot_t[j]) * base) / (STRENGTHS[1] + hot_n[j])
        return p[self.asked]


def _parts(batches, known: Words) -> Iterator[tuple[int, list[tuple[int, int]], Root]]:
    def finish(part: int, rows: list[dict]):
        rows.sort(key=lambda r: r["bucket"])
        word, n, _ = _decoded(rows, "codes", "rest", known)
        hot, customers = (np.concatenate([_unpacked(r[k], t) for r in rows]) for k, t in (("hot", U), ("n", np.int64)))
        return part, [(r["bucket"], int(k)) for r, k in zip(rows, n)], Root(hot, word, customers, known)

    rows, mine = [], None
    for batch in batches:
        for row in batch.to_pylist():
            if row["part"] != mine:
                if rows:
                    yield finish(mine, rows)
                rows, mine = [], row["part"]
            rows.append(row)
    if rows:
        yield finish(mine, rows)


def _root_totals(told: DataFrame, shared: Broadcast, earlier: list) -> tuple:
    """Totals of the root after the sweeps that ``earlier`` totals allow: each sweep sees those of the one before."""

    def run(batches):
        for _, _, root in _parts(batches, shared.value):
            for turn, totals in enumerate(earlier):
                root.sweep(turn, totals)
            n, t, hot_n, hot_t = root.totals()
            some = np.flatnonzero(hot_n)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.r_[-1, some]), pa.array(np.r_[n, hot_n[some]]), pa.array(np.r_[t, hot_t[some]])], ["i", "n", "t"]
            )

    # One row for the root and one for each hot word, of which there are at most HOT_SHARE.
    rows = told.mapInArrow(run, "i long, n long, t long").groupBy("i").agg(F.sum("n").alias("n"), F.sum("t").alias("t")).collect()
    hot_n, hot_t = np.zeros((2, len(shared.value.hot)), np.int64)
    all_n = all_t = 0
    for r in rows:
        if r.i < 0:
            all_n, all_t = r.n, r.t
        else:
            hot_n[r.i], hot_t[r.i] = r.n, r.t
    return all_n, all_t, hot_n, hot_t


def _root_answers(told: DataFrame, shared: Broadcast, trace: list) -> DataFrame:
    def run(batches):
        for part, asked, root in _parts(batches, shared.value):
            for turn, totals in enumerate(trace[:-1]):
                root.sweep(turn, totals)
            p, at = root.answers(trace[-1]), 0
            for bucket, n in asked:
                yield pa.RecordBatch.from_arrays(
                    [pa.array([part], pa.int64()), pa.array([bucket], pa.int32()), pa.array([_packed(p[at : at + n])], pa.binary())], ["block", "bucket", "answer"]
                )
                at += n

    return told.mapInArrow(run, "block long, bucket int, answer binary")


# ---- scores ----

_ANSWER = "block long, bucket int, counts binary, logs binary"
_SCALE = 2.0**28  # logs travel as whole multiples of 1 / _SCALE, and are added up as such


def _answers(asked: DataFrame, shared: Broadcast, n_buckets: int) -> DataFrame:
    """Step 3: counts of the middle words and log10 probabilities of the triples, for the blocks that asked."""

    def run(batches):
        for bucket, asks, rooms, said in _buckets(batches, shared.value):
            rooms.early()
            _, word, _, of = rooms.sent()
            part = ((word >> U(16)) % U(n_buckets)).astype(np.int32)
            root = np.empty(len(word))
            said.sort(key=lambda r: r["block"])
            root[np.argsort(part, kind="stable")] = np.concatenate([_unpacked(r["answer"], np.float64) for r in said])
            logs = np.rint(np.log10(rooms.late(root[of])) * -_SCALE).astype(np.int64).astype(np.uint32)[rooms.asked]
            at = 0
            for block, mine, n in asks:
                yield pa.RecordBatch.from_arrays(
                    [pa.array([block]), pa.array([bucket], pa.int32()),
                     pa.array([_packed(rooms.middle_c[np.searchsorted(rooms.middles, mine)])], pa.binary()),
                     pa.array([_packed(logs[at : at + n])], pa.binary())],
                    [f.split()[0] for f in _ANSWER.split(", ")],
                )
                at += n
            del rooms, word, of, _, part, root, said, logs, asks, mine

    return asked.mapInArrow(run, _ANSWER)


_SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _score(row: dict, answers: list[dict], known: Words, n_buckets: int) -> pa.RecordBatch:
    words, ids, n = _unpacked(row["words"], U), _unpacked(row["ids"], np.uint32), _unpacked(row["n_tokens"], np.int64)
    middle, _, _, _, of, names, bucket, order = _order(row, words, known, n_buckets)
    # A bucket's answers are in the order of the requests: by bucket, then middle word, farther word and word.
    answers.sort(key=lambda a: a["bucket"])
    logs = np.empty(len(order), np.int64)
    logs[order] = np.concatenate([_unpacked(a["logs"], np.uint32) for a in answers])
    counts = np.zeros(len(names), np.int64)
    pairs = (bucket * len(names) + middle)[order]
    counts[pairs[np.r_[True, pairs[1:] != pairs[:-1]]] % len(names)] = np.concatenate([_unpacked(a["counts"], np.int64) for a in answers])
    at = np.minimum(np.searchsorted(known.hot, names), len(known.hot) - 1)
    hot = known.hot[at] == names
    counts[hot] = known.hot_counts[at[hot]]
    first = np.cumsum(n) - n
    base = np.log10((counts + 0.5) / (known.n_train + 0.5 * (known.known + 1)))
    total = lambda x: np.add.reduceat(x, first)  # noqa: E731  every text has its end token
    held = _unpacked(row["held"], bool)
    cols = [pa.array(row["doc_ids"], pa.int64()), pa.array(held), pa.array(n), pa.array(total((counts > 0).astype(np.int64)[ids])),
            pa.array(np.full(len(n), known.n_train)), pa.array(total(base[ids])), pa.array(total(logs[of]) / -_SCALE)]
    return pa.RecordBatch.from_arrays(cols, [f.split()[0] for f in _SCORES.split(", ")])


def score(docs: DataFrame, block_tokens: int = BLOCK_TOKENS, coded: int = CODED, hot: int | None = None, chain: Chain = Chain()) -> DataFrame:
    """``docs (doc_id, held, text)``: trains on the rows not held out, scores all."""
    spark = docs.sparkSession
    source = docs.select("doc_id", F.coalesce("held", F.lit(False)), F.col("text").cast("binary"))
    blocks = written(text_blocks(source, block_tokens), "lm-blocks")
    known = training_words(blocks, coded, hot)._replace(chain=chain)
    shared = spark.sparkContext.broadcast(known)
    n_buckets = max(shuffle_width(spark), known.n_train // BUCKET_TOKENS)

    def dealt(df: DataFrame, key: str) -> DataFrame:
        return df.repartitionById(n_buckets, key).sortWithinPartitions(key)

    asked = requests(blocks, shared, n_buckets)
    told = written(dealt(_told(dealt(asked, "bucket"), shared, n_buckets), "part"), "lm-root")
    trace = [_root_totals(told, shared, [])]
    for _ in range(chain.root):
        trace.append(_root_totals(told, shared, trace))
        free(spark, 2)
    root = _root_answers(told, shared, trace)
    answers = written(_answers(dealt(asked.unionByName(root, allowMissingColumns=True), "bucket"), shared, n_buckets), "lm-answers")
    discard(told)
    del asked, root
    both = blocks.drop("n_train").unionByName(answers, allowMissingColumns=True)

    def run(batches):
        row, got = None, []
        for batch in batches:
            for r in batch.to_pylist():
                if r["bucket"] is not None:
                    got.append(r)
                    continue
                if row is not None:
                    yield _score(row, got, shared.value, n_buckets)
                row, got = r, []
        if row is not None:
            yield _score(row, got, shared.value, n_buckets)

    # Blocks meet their answers in rounds, so that only a part of both lies in shuffle files beside the tables.
    rounds = min(ROUNDS, max(1, known.n_train // (ROUNDS * block_tokens)))
    parts = []
    for r in range(rounds):
        free(spark, 3)
        mine = both.filter(F.pmod(F.xxhash64("block"), F.lit(rounds)) == r)
        parts.append(written(dealt_by_block(mine).mapInArrow(run, _SCORES), "lm-scores"))
    discard(blocks, answers)
    return functools.reduce(DataFrame.unionByName, parts)


def dealt_by_block(rows: DataFrame) -> DataFrame:
    """Each block's row, its answers behind it."""
    return rows.repartition("block").sortWithinPartitions("block", F.col("bucket").asc_nulls_first())


def op9_language_model(docs: DataFrame) -> DataFrame:
    held = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(5)) == 1
    return score(docs.select("doc_id", held.alias("held"), "text"))


def perplexity(scores: DataFrame) -> DataFrame:
    """Perplexity by part: of the model and of the add-half unigram base."""
    return scores.groupBy("held_out").agg(
        F.sum("n_tokens").alias("n_tokens"),
        F.pow(F.lit(10.0), -F.sum("score") / F.sum("n_tokens")).alias("perplexity"),
        F.pow(F.lit(10.0), -F.sum("base_score") / F.sum("n_tokens")).alias("base_perplexity"),
    )
