"""The pipeline's near copies against brute force over all pairs of texts."""

import random

import pytest

from hcube.llm import shingles


def sets(text):
    w = (text or "").encode().lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


@pytest.mark.parametrize(("group", "limit"), [(500, 200_000), (2, 0)])
def test_all_pairs_of_similarity_are_linked(spark, group, limit):
    random.seed(7)
    vocabulary = [f"w{k}" for k in range(400)]
    passage = " ".join(random.choices(vocabulary, k=40))
    texts = [None, "", "one two", "One  two", "one two three"]
    for _ in range(25):
        base = random.choices(vocabulary, k=random.randint(6, 150))
        texts.append(" ".join(base))
        for _ in range(random.randint(0, 7)):  # edits around the similarity, some of them on edited texts
            base = list(base)
            for _ in range(random.randint(0, max(1, len(base) // 40))):
                base[random.randrange(len(base))] = random.choice(vocabulary)
            texts.append(" ".join(base))
        texts.append(passage + " " + " ".join(random.choices(vocabulary, k=30)))
    ids = random.sample(range(1000), len(texts))
    all_sets = [sets(t) for t in texts]
    root = list(range(len(texts)))

    def up(i):
        while root[i] != i:
            i = root[i]
        return i

    wide = 0
    for i, x in enumerate(all_sets):
        for j, y in enumerate(all_sets[:i]):
            if 5 * len(x & y) >= 4 * len(x | y):
                root[up(i)] = up(j)
                wide += x != y
    assert wide > 50
    least = {}
    for i, d in enumerate(ids):
        least[up(i)] = min(least.get(up(i), d), d)
    df = spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in shingles.near_copies(df, group, limit).collect()}
    assert got == {d: least[up(i)] for i, d in enumerate(ids)}
    if group == 500 and limit:
        import corpus_pipeline

        kept = {r.doc_id for r in dict(corpus_pipeline.STAGES)["near_copies"](spark, df, "").collect()}
        assert kept == set(least.values())


def test_shingles_of_all_texts_are_counted(spark):
    texts = [f"one two three four five w{k % 3} x{k}" for k in range(9000)]
    df = spark.createDataFrame([(t,) for t in texts], "text string").repartition(7)
    got = shingles.shared_counts(df, 1 << 16)
    assert got.sum() == 3 * len(texts)
    for words, n in (("one two three four five", 9000), ("two three four five w1", 3000)):
        (s,) = shingles.shingle_sets([words.encode()])[0]
        assert n <= got[int(s) % (1 << 16)] < n + 50


def test_pairs_that_share_late_keys_only_are_not_made(spark):
    """150 texts of one group whose first shared key leaves too little behind it, and one pair where it doesn't."""
    rows = [(1, k, 100, 15) for k in range(150)] + [(2, 200, 100, 3), (2, 201, 100, 4)]
    keyed = spark.createDataFrame(rows, "k long, node long, size long, pos long")
    found = shingles.other_pairs(keyed, spark.createDataFrame([], "node long, root long"), 40)
    assert [tuple(r) for r in found.collect()] == [(200, 201)]
    joins = [x for x in found._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join Inner" in x and "node_a" in x]
    assert joins and all("pos_a" in x for x in joins)


@pytest.mark.parametrize("keys", [1 << 20, 40])
def test_only_shared_keys_become_rows(spark, keys):
    """Keys travel packed: no row of a key that one text has alone, one of each other with its place and count."""
    random.seed(3)
    nodes = [(k - 150, 10 + k, [-(2**62), *random.sample(range(-900, 900), k % 9), 5000 + k][k % 2 :]) for k in range(300)] + [(999, 0, [])]
    have = {}
    for node, size, ks in nodes:
        for pos, k in enumerate(ks):
            have.setdefault(k, []).append((node, size, pos, k))
    df = spark.createDataFrame(nodes, "node long, size long, keys array<long>").repartition(5)
    found = shingles.shared_keys(df, keys)
    assert sorted(map(tuple, found.collect())) == sorted((*x, len(v)) for v in have.values() if len(v) > 1 for x in v)
    assert "Generate" not in found._jdf.queryExecution().toString() and "Join" not in found._jdf.queryExecution().toString()
    assert shingles.shared_keys(df.limit(0), keys).count() == 0
