"""The language model against a plain sampler, its sums of probabilities, and its independence of partitions."""

import collections
import math
import random

import numpy as np
import pytest

from hcube.llm import lm


def corpus(n=60):
    rng = random.Random(5)
    words = [f"w{k}" for k in range(30)]
    out = []
    for d in range(n):
        at, text = 0, []
        for _ in range(rng.randint(0, 25)):
            at = (at * 3 + rng.choice([0, 0, 0, 1, 2, 7])) % 30
            text.append(words[at])
        out.append((d, d % 5 == 1, " ".join(text)))
    return [*out, (900, False, None), (901, True, "never seen before w1"), (None, False, out[3][2]), (7, False, out[7][2])]


class Plain:
    """A restaurant per context, customers one by one."""

    def __init__(self, rng):
        self.rng, self.rooms = rng, collections.defaultdict(lambda: collections.defaultdict(list))

    def p(self, context, word, known):
        if context is None:
            return 1 / (known + 1)
        k = 2 - len(context)
        room = self.rooms[context]
        n, t = sum(map(sum, room.values())), sum(map(len, room.values()))
        mine = room.get(word, [])
        up = self.p(context[1:] if context else None, word, known)
        return (sum(mine) - lm.DISCOUNTS[k] * len(mine) + (lm.STRENGTHS[k] + lm.DISCOUNTS[k] * t) * up) / (lm.STRENGTHS[k] + n)

    def sit(self, context, word, known):
        if context is None:
            return
        k = 2 - len(context)
        room = self.rooms[context]
        t = sum(map(len, room.values()))
        up = self.p(context[1:] if context else None, word, known)
        mine = room[word]
        weights = [x - lm.DISCOUNTS[k] for x in mine] + [(lm.STRENGTHS[k] + lm.DISCOUNTS[k] * t) * up]
        at = self.rng.choices(range(len(weights)), weights)[0]
        if at < len(mine):
            mine[at] += 1
        else:
            mine.append(1)
            self.sit(context[1:] if context else None, word, known)

    def leave(self, context, word):
        if context is None:
            return
        mine = self.rooms[context][word]
        at = self.rng.choices(range(len(mine)), mine)[0]
        mine[at] -= 1
        if not mine[at]:
            mine.pop(at)
            self.leave(context[1:] if context else None, word)


def triples(rows, train):
    for d, held, text in rows:
        if held and train:
            continue
        tokens = [*(text or "").split(), "<end>"]
        for k, w in enumerate(tokens):
            yield d, (tokens[k - 2] if k > 1 else "<start>", tokens[k - 1] if k else "<start>"), w


def plain_scores(rows, sweeps=400, burn_in=80):
    rng = random.Random(1)
    model, known = Plain(rng), len({w for _, _, w in triples(rows, True)})
    customers = [(c, w) for _, c, w in triples(rows, True)]
    for c, w in customers:
        model.sit(c, w, known)
    asked = [(i, c, w) for i, row in enumerate(rows) for _, c, w in triples([row], False)]
    mean = np.zeros(len(asked))
    for k in range(sweeps):
        for c, w in customers:
            model.leave(c, w)
            model.sit(c, w, known)
        if k >= burn_in:
            mean += [model.p(c, w, known) for _, c, w in asked]
    out = np.zeros(len(rows))
    np.add.at(out, [i for i, _, _ in asked], np.log10(mean / (sweeps - burn_in)))
    return out


SCHEMA = "doc_id long, held boolean, text string"


@pytest.mark.parametrize("hot", [None, 10])
def test_scores_are_those_of_a_plain_sampler(spark, hot):
    rows = corpus()
    want = plain_scores(rows)
    got = [r.score for r in lm.score(spark.createDataFrame(rows, SCHEMA).coalesce(1), hot=hot, chain=lm.Chain(20, 20, 20, 300)).orderBy("doc_id", "n_tokens").collect()]
    order = sorted(range(len(rows)), key=lambda i: (rows[i][0] is not None, rows[i][0] or 0, len((rows[i][2] or "").split())))
    lengths = np.array([len((rows[i][2] or "").split()) + 1 for i in order])
    off = (np.array(got) - want[order]) / lengths
    # A hot word's parent is sampled with the root, once; here every word that occurs more than ten times is hot.
    mean, most = (0.06, 0.15) if hot else (0.02, 0.08)
    assert abs(off).mean() < mean and abs(off).max() < most, (abs(off).mean(), abs(off).max())


@pytest.mark.parametrize("hot", [None, 10])
def test_partitions_do_not_change_a_digit(spark, hot):
    rows = corpus()
    seen = set()
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for width, parts, tokens in ((4, 1, 1 << 20), (16, 7, 50), (211, 2, 400)):
            spark.conf.set("spark.sql.shuffle.partitions", width)
            df = lm.score(spark.createDataFrame(rows, SCHEMA).repartition(parts), tokens, hot=hot)
            seen.add(tuple(sorted((r.doc_id or -1, r.n_tokens, r.n_known, r.base_score, r.score) for r in df.collect())))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert len(seen) == 1


def test_probabilities_sum_to_one():
    """All known words and the unknown one behind one context."""
    known = lm.Words(np.sort(np.array([lm.START, lm.END], lm.U)), np.zeros(2, np.int64), np.empty(0, lm.U), np.empty(0, np.uint32), np.empty(0), np.zeros(1, lm.U), 50, 5)
    U = lm.U
    rng = np.random.default_rng(3)
    word = np.r_[np.arange(1, 7), rng.integers(1, 6, 60)].astype(U)
    middle, far = np.full(66, 77, U), np.full(66, 88, U)
    train = np.r_[np.zeros(6), np.ones(60)].astype(np.int64)
    rooms = lm.Bucket(middle, far, word, train, known)
    rooms.early()
    p = rooms.late(np.full(len(rooms.dish_word), 1 / 6))
    assert abs(p.sum() - 1) < 1e-9 and len(p) == 6


@pytest.mark.parametrize("c, a", [(40, 0.5), (300, 0.2), (300, 5.0), (300, 80.0), (300, 900.0)])
def test_drawn_tables_follow_their_conditional(c, a, monkeypatch):
    """Above EXACT customers, where the draw is of a tilted Poisson, against the Stirling numbers."""
    d, many = 0.75, 20_000
    logs = lm.stirling_logs(d, 512)[c, 1 : c + 1] + np.arange(c) * math.log(a)
    p = np.exp(logs - logs.max())
    p /= p.sum()
    mean = (p * np.arange(1, c + 1)).sum()
    spread = math.sqrt((p * np.arange(1, c + 1) ** 2).sum() - mean**2)
    u = lm.uniform(np.arange(many, dtype=lm.U), 1), lm.uniform(np.arange(many, dtype=lm.U), 2)
    flat = lm.Weights(a, d, np.full(many, 0.0), np.ones(many))
    monkeypatch.setattr(lm.Weights, "at", lambda self, i, k: np.full((len(i), k.shape[1]) if k.ndim == 2 else len(i), a))
    t = lm.draw_tables(np.full(many, c), np.full(many, 3), flat, *u)
    assert t.min() >= 1 and t.max() <= c
    assert abs(t.mean() - mean) < 0.03 * mean + 0.05, (t.mean(), mean)
    assert abs(t.std() - spread) < 0.1 * spread + 0.1, (t.std(), spread)


def test_one_bucket_is_held_at_a_time(monkeypatch):
    """What one bucket needs is let go before the next is made."""
    import weakref

    import pyarrow as pa

    rng = np.random.default_rng(2)
    words = np.unique(rng.integers(1, 2**63, 400).astype(lm.U))
    n = np.full(50, 20)
    row = {"block": 1, "n_tokens": lm._packed(n), "ids": lm._packed(rng.integers(0, len(words), n.sum()).astype(np.uint32)), "held": lm._packed(np.zeros(50, bool)), "words": lm._packed(words)}
    known = lm.Words(np.sort(np.array([lm.START, lm.END], lm.U)), np.zeros(2, np.int64), np.empty(0, lm.U), np.empty(0, np.uint32), np.empty(0), np.zeros(1, lm.U), 1000, len(words))
    asked = lm._requests(row, known, 9)
    alive, most, make = [], [], lm.Bucket

    def counted(*a):
        most.append(sum(r() is not None for r in alive))
        out = make(*a)
        alive.append(weakref.ref(out))
        return out

    monkeypatch.setattr(lm, "Bucket", counted)
    told = pa.Table.from_batches(list(lm._tell([asked], known, 9)))
    assert len(alive) == 9 and max(most) == 0 and told.num_rows >= 9


def test_blocks_meet_their_answers_in_rounds(spark, monkeypatch):
    """Of the tables of blocks and answers only a part is dealt at once, and neither stays."""
    from pyspark.sql import functions as F

    rows = [(k, False, " ".join(f"w{(k * 7 + i) % 90}" for i in range(60))) for k in range(80)]
    dealt, gone, by_block, drop = [], [], lm.dealt_by_block, lm.discard

    def count(table):
        dealt.append({r.block for r in table.select("block").distinct().collect()})
        return by_block(table)

    monkeypatch.setattr(lm, "dealt_by_block", count)
    monkeypatch.setattr(lm, "discard", lambda *tables: (gone.extend(t.written_to.rsplit("/", 1)[1][:6] for t in tables), drop(*tables)))
    df = spark.createDataFrame(rows, SCHEMA).repartition(24)
    got = lm.score(df, 200)
    every = set().union(*dealt)
    assert len(dealt) == lm.ROUNDS and sum(map(len, dealt)) == len(every) > 10 and 4 * max(map(len, dealt)) < 3 * len(every)
    assert {"lm-blo", "lm-ans"} <= set(gone)
    assert got.agg(F.count("*"), F.countDistinct("doc_id"), F.sum("n_tokens")).first() == (80, 80, 80 * 61)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, lm.score(df, 1 << 21).collect()))
