"""Operators against brute force, over nulls, empty and repeated rows, and empty tables."""

import bisect
import collections
import hashlib
import random
import re
import zlib

import numpy as np
import pytest
import xxhash

from hcube.llm import chat, htmltext, licences, lm, packing, quality, sentencepieces, simhash, suffix_dedup, topk

SCHEMA = "doc_id long, text string"


@pytest.fixture(scope="module")
def rows():
    random.seed(3)
    words = "the of and storm river la der cat house green Licence über naïve".split()
    base = [" ".join(random.choice(words) + random.choice(["", "s", "x"]) for _ in range(random.randint(30, 120))) for _ in range(12)]
    out = []
    for d in range(150):
        t = random.choice(base)
        kind = random.random()
        if kind < 0.3:
            t = t.replace("storm", "storms", 1)
        elif kind < 0.6:
            a, b = sorted(random.sample(range(len(t)), 2))
            t = random.choice(base)[:80] + t[a:b] + "\n" + str(d)
        out.append((d, t))
    return [*out, (200, None), (201, ""), (202, "   \n\t"), (203, "one"), (None, base[0]), (5, base[1]), (5, base[1]), (204, "a" * 400), (205, "a" * 130), (206, "é" * 90)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def fingerprint(text):
    w = (text or "").encode().lower().split()
    if not w:
        return 0
    h = [xxhash.xxh64_intdigest(b" ".join(w[i : i + 3]), 42) for i in range(max(1, len(w) - 2))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


@pytest.mark.parametrize("shard", [1000, 2])
def test_simhash(docs, rows, shard):
    fps = [fingerprint(t) for _, t in rows]
    root = list(range(len(fps)))
    for _ in root:
        for i, a in enumerate(fps):
            for j, b in enumerate(fps):
                if (a ^ b).bit_count() <= 3:
                    root[i] = root[j] = min(root[i], root[j])
    least = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[root[i]] = min(least.get(root[i], d), d)
    want = collections.Counter((d, fps[i], least.get(root[i])) for i, (d, _) in enumerate(rows))
    got = collections.Counter((r.doc_id, r.fp & (2**64 - 1), r.component_id) for r in simhash.near_duplicates(docs, shard_rows=shard).collect())
    assert got == want


def test_bk_forest_finds_all_links():
    rng = np.random.default_rng(1)
    fps = np.unique(np.r_[rng.integers(0, 2**63, 300), 1 << np.arange(60)].astype(np.uint64))
    shard = np.zeros(len(fps), np.int64)
    got = {(int(a), int(b)) for x, y in simhash.bk_links(shard, fps) for a, b in zip(x, y)}
    want = {(i, j) for i in range(len(fps)) for j in range(i) if int(fps[i] ^ fps[j]).bit_count() <= 3}
    assert got == want


@pytest.mark.parametrize("hot", [None, 3])
def test_suffix_dedup(docs, rows, hot):
    first = {}
    for d, t in rows:
        b = (t or "").encode()
        for i in range(len(b) - 49 if d is not None else 0):
            first[b[i : i + 50]] = min(first.get(b[i : i + 50], d), d)
    want = collections.Counter()
    for d, t in rows:
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for i in range(len(b) - 49 if d is not None else 0):
            if first[b[i : i + 50]] < d:
                gone[i : i + 50] = True
        runs = int((np.diff(np.r_[0, gone.astype(int)]) == 1).sum())
        want[d, len(b), int(gone.sum()), runs, hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~gone])).hexdigest()] += 1
    assert collections.Counter(map(tuple, suffix_dedup.op5_suffix_dedup(docs, hot).collect())) == want


def test_packing(docs, rows):
    r = packing.pack(packing.pieces(docs, 64), 64).toPandas()
    by = r.sort_values(["sequence_id", "offset"]).groupby("sequence_id")
    assert all((g.offset.values == np.r_[0, np.cumsum(g.length.values)[:-1]]).all() and g.length.sum() <= 64 for _, g in by)
    want = collections.Counter()
    for d, t in rows:
        ids = packing.token_ids(t)
        head = (len(ids) - 1) % 64 + 1
        for k, s in enumerate([0, *range(head, len(ids), 64)]):
            part = ids[s : head if not k else s + 64]
            want[d, k, s, len(part), zlib.crc32(part.tobytes())] += 1
    got = collections.Counter((None if np.isnan(x.doc_id) else int(x.doc_id), x.piece, x.start, x.length, x.ids_crc32) for x in r.itertuples())
    assert got == want
    rooms = []  # no worse than first-fit decreasing
    for n in sorted(r.length, reverse=True):
        at = next((i for i, x in enumerate(rooms) if x >= n), None)
        if at is None:
            rooms.append(64 - n)
        else:
            rooms[at] -= n
    assert r.sequence_id.nunique() <= len(rooms)


def test_token_ids_equal_the_library():
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path(packing.VOCABULARY))
    for s in ("Hello  world\n\n x", "naïve über 12345 'tis", "日本語 text", "a" * 3000, "x<|endoftext|>y", "   z"):
        assert packing.token_ids(s).tolist() == [*t.encode(s, add_special_tokens=False).ids, 0]


def test_bins_are_as_few_as_can_be():
    random.seed(2)

    def fewest(items, room):
        best = len(items)

        def go(i, bins):
            nonlocal best
            if len(bins) >= best:
                return
            if i == len(items):
                best = len(bins)
                return
            for j in {b: j for j, b in enumerate(bins)}.values():
                if bins[j] + items[i] <= room:
                    bins[j] += items[i]
                    go(i + 1, bins)
                    bins[j] -= items[i]
            go(i + 1, [*bins, items[i]])

        go(0, [])
        return best

    for _ in range(60):
        room = random.choice([10, 17, 30])
        items = sorted((random.randint(1, room) for _ in range(random.randint(0, 8))), reverse=True)
        found = packing.complete_bins(dict(collections.Counter(items)), room)
        assert collections.Counter(x for b, n in found.patterns for x in b for _ in range(n)) == collections.Counter(items)
        assert sum(n for _, n in found.patterns) == found.bins == fewest(items, room) >= found.bound


@pytest.mark.parametrize("low, high, n", [(300, 1499, 1500), (500, 900, 3000), (1, 2048, 20000), (2048, 2048, 5)])
def test_bins_are_no_more_than_best_fit_decreasing(low, high, n):
    rng = random.Random(n)
    counts = collections.Counter(rng.randint(low, high) for _ in range(n))
    rooms, plain = [], 0
    for size in sorted(counts.elements(), reverse=True):
        at = bisect.bisect_left(rooms, size)
        room = rooms.pop(at) if at < len(rooms) else 2048
        plain += room == 2048
        bisect.insort(rooms, room - size)
    found = packing.complete_bins(dict(counts))
    assert found.bound <= found.bins <= plain
    got = collections.Counter()
    for bin_, times in found.patterns:
        assert sum(bin_) <= 2048
        for size in bin_:
            got[size] += times
    assert got == counts


def test_packing_of_very_long_and_wide_texts(spark):
    long = "word " * 300_000 + "日本語"
    r = packing.op3_best_fit_packing(spark.createDataFrame([(1, long), (2, "x")], SCHEMA))
    report = packing.packing_report(r).first()
    assert report.n_tokens == len(packing.token_ids(long)) + len(packing.token_ids("x")) and report.n_sequences == report.bound


def test_topk(spark):
    random.seed(4)
    data = [(i, [random.uniform(-2, 2) for _ in range(20)]) for i in range(0, 400, 5)]
    data += [(900, data[3][1]), (900, data[3][1]), (901, None), (902, [1.0, None] * 10), (903, [float("nan")] * 20), (904, [1.0]), (None, data[0][1])]
    table = topk.integer_vectors(spark.createDataFrame(data, "vec_id long, embedding array<float>"))
    got = collections.Counter(map(tuple, topk.top_k(table.filter("vec_id % 100 = 0"), table, 4).collect()))
    vecs = [(i, [int(np.floor(1024 * float(np.float32(x)))) for x in v]) for i, v in data if i is not None and v and all(x is not None and x == x for x in v)]
    want = collections.Counter()
    for a, (q, x) in enumerate(vecs):
        if q % 100 == 0:
            scored = sorted((-sum(p * r for p, r in zip(x, y)), i) for b, (i, y) in enumerate(vecs) if b != a and len(y) == len(x))
            for k, (s, i) in enumerate(scored[:4], 1):
                want[q, k, i, -s] += 1
    assert got == want


def test_quality(docs, rows):
    got = collections.Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in quality.op8_quality_rules(docs).collect())
    want = collections.Counter()
    for d, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        n = collections.Counter(zip(w, w[1:], w[2:]))
        cover = {i + k for i, g in enumerate(zip(w, w[1:], w[2:])) if n[g] > 1 for k in range(3)}
        lines = [x for x in (t or "").split("\n") if x.strip(" \t\r\x0b\x0c")]
        want[d, len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(cover), len(w) < 50 or 100 * len(cover) > 50 * len(w)] += 1
    assert got == want
    # A filter on the measures must not blow the plan up.
    assert quality.op8_quality_rules(docs).filter("kept").count() == quality.keep_good(docs).count()


def test_language_model(docs, rows):
    r = lm.op9_language_model(docs).collect()
    c = collections.Counter()
    for d, t in rows:
        if d is None or zlib.crc32(str(d).encode()) % 5 != 1:
            c.update([*(t or "").encode().lower().split(), "end"])
    n, v = sum(c.values()), len(c)
    want = collections.Counter()
    for d, t in rows:
        w = [*(t or "").encode().lower().split(), "end"]
        want[d, len(w), sum(c[x] > 0 for x in w), n, round(sum(np.log10((c[x] + 0.5) / (n + 0.5 * (v + 1))) for x in w), 6)] += 1
    assert collections.Counter((x.doc_id, x.n_tokens, x.n_known, x.train_tokens, round(x.base_score, 6)) for x in r) == want
    by = {x.held_out: x for x in lm.perplexity(docs.sparkSession.createDataFrame(r)).collect()}
    assert all(x.perplexity < x.base_perplexity for x in by.values()) and all(x.score < 0 for x in r)


def test_sentencepieces(docs, rows):
    import public_tokenizers
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(sentencepieces.MODEL))
    got = collections.Counter((r.doc_id, tuple(r.ids)) for r in sentencepieces.encoded(docs).collect())
    assert got == collections.Counter((d, tuple(sp.encode(t or ""))) for d, t in rows)
    assert all(r.round_trip for r in sentencepieces.op10_sentencepiece(docs).collect())
    back = sentencepieces.decoded(sentencepieces.encoded(docs.filter("doc_id <> 5")))
    want = {d: t or "" for d, t in rows if d not in (None, 5)}
    assert {r.doc_id: r.text for r in back.collect()} == want


def test_a_long_unit_equals_the_library():
    import time

    import public_tokenizers
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(sentencepieces.MODEL))
    random.seed(8)
    enc = sentencepieces.encoder()
    for n, letters in ((3000, "abcdefghij"), (5000, "aab"), (4000, "日本語の文字列中国人民")):
        text = "".join(random.choices(letters, k=n)) + " and words"
        assert enc.encode([text])[0].tolist() == sp.encode(text)
    began = time.process_time()
    enc.encode(["".join(random.choices("etaoinshrdlu", k=300_000))])
    assert time.process_time() - began < 60


def test_pages(spark):
    page = "<html><head><title>T</title></head><body><nav>menu</nav><header><h1>Site</h1></header><article><h1>A &amp; B</h1><p>One <i>two</i><br>three<p>Four</p><form>f</form><div id='comments'>no</div></article><div class='cookie-notice'>c</div><footer>x"
    shared = "<div><p>Our office is open from nine</p></div>"
    pages = [(1, "https://a.example/x", page), (2, None, None), (3, "http://b.example", ""), (4, "x", "plain <b>text")]
    pages += [(10 + k, "https://s.example/p", f"<body>{shared}<p>story {k}</p></body>") for k in range(6)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    for limit in (htmltext.BROADCAST_HASHES, 0):
        got = {r.page_id: r.text for r in htmltext.extract(df, limit).collect()}
        assert got[1] == "A & B\nOne two three\nFour" and got[2] == got[3] == "" and got[4] == "plain text"
        assert all(got[10 + k] == f"story {k}" for k in range(6))


PAGES = "page_id long, url string, html string"


@pytest.mark.parametrize("limit", [htmltext.BROADCAST_HASHES, 0])
def test_templates_are_those_of_many_different_pages(spark, limit):
    """Against a plain count of subtrees by host; copies of a page count once."""
    menu, box = "<div class='x'><p>Our office is open</p></div>", "<section><p>Call us <b>now</b></p></section>"
    pages = [(k, f"http://h{k % 2}.example/{k}", f"<body>{menu if k % 3 else ''}<div><p>story {k}</p></div>{box if k < 4 else ''}</body>") for k in range(24)]
    pages += [(100 + k, "http://h0.example/c", "<body><div><p>copied page</p></div></body>") for k in range(9)]
    got = {r.page_id: r.text for r in htmltext.extract(spark.createDataFrame(pages, PAGES), limit).collect()}
    for k, url, html in pages:
        text = "copied page" if k >= 100 else f"story {k}" + ("\nCall us now" if k < 4 else "")
        assert got[k] == text


def test_class_words_inside_an_article():
    """Words of a class drop an element of an article only if no word says otherwise."""
    say = lambda body: htmltext.Page(f"<article><p>start</p>{body}</article>").text(set())
    for kept in ('<p class="promo-code-history">a</p>', '<section id="related-work">a</section>', '<div class="social-policy">a</div>'):
        assert say(kept) == "start\na"
    for gone in ('<div class="share-buttons">a</div>', '<div id="comments">a</div>', '<section class="x related">a</section>', "<aside>a</aside>", "<form>a</form>"):
        assert say(gone) == "start"


@pytest.mark.parametrize(
    "html", ["<a " * 350_000, "<div>x" * 150_000, "<b>" * 150_000 + "</i>" * 150_000, "<p><table>" + "<b>" * 100_000 + "<div></div>" * 50_000, "<!--" * 250_000, "<script>" * 120_000, "<a '\"" * 200_000 + ">"]
)
def test_a_megabyte_of_broken_markup(html):
    import time

    began = time.process_time()
    htmltext.Page(html).text(set())
    assert time.process_time() - began < 30


def test_licences(spark):
    mit = (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and\nassociated files. "
        "The above copyright notice and this permission notice shall be included in all copies. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED."
    )
    df = spark.createDataFrame([(1, mit), (2, "x\nLicensed under the Apache License, Version 2.0.\ny"), (3, None), (4, "nothing"), (5, "Copyright 2020 someone.")], SCHEMA)
    got = {r.doc_id: (r.licences, r.leftover) for r in licences.op7_licence_scan(df).collect()}
    assert got == {1: ("MIT", ""), 2: ("Apache-2.0", ""), 3: ("", ""), 4: ("", ""), 5: ("", "unknown")}


def test_chat(spark):
    turns = [(1, 0, 0, "user", "hi"), (1, 1, 0, "user", "hi"), (1, 0, 1, "assistant", "good"), (1, 1, 1, "assistant", "bad"), (2, 0, 0, None, None), (3, 1, 0, "assistant", "z"), (None, 0, 0, "user", "q")]
    got = {r.pair_id: r for r in chat.preference_pairs(spark.createDataFrame(turns, "pair_id long, side int, turn long, role string, text string")).collect()}
    assert set(got) == {1, 2, 3}
    one = got[1]
    assert (one.n_prompt_turns, one.prompt) == (1, "<|user|>\nhi<|end|>\n")
    span = one.chosen_spans[0]
    assert one.chosen[span.start : span.end] == "good<|end|>\n" and one.rejected.startswith("<|assistant|>\nbad")
    assert got[2].rejected is None and got[3].chosen is None


def test_empty_tables(spark, none):
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    vectors = spark.createDataFrame([], "vec_id long, embedding array<float>")
    turns = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    for op, table in (
        (simhash.op1_simhash, none), (chat.op2_preference_format, turns), (packing.op3_best_fit_packing, none), (topk.op4_exact_topk, vectors),
        (suffix_dedup.op5_suffix_dedup, none), (htmltext.op6_main_text, pages), (licences.op7_licence_scan, none), (quality.op8_quality_rules, none),
        (lm.op9_language_model, none), (sentencepieces.op10_sentencepiece, none),
    ):
        assert op(table).count() == 0


def test_pipeline_with_clashing_columns(spark, rows):
    import corpus_pipeline

    df = spark.createDataFrame([(d, t, "x", 1, 2) for d, t in rows], "doc_id long, text string, fp string, row int, n_words int")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, df, "")
        assert out.columns == df.columns
        df = out
    df.count()
