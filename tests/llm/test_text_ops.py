"""Token counts, language mixtures, packing, near duplicates, decontamination."""

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from postpool.llm import decontaminate as D, language_id as L, near_dup as N, packing, queries, token_counts as T, tokens

from ..twins import assert_twin, connect
from .hostile import LONG, PLAIN, documents, empty

VOCAB, RANKS = public_tokenizers.path("word_bpe_49k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")


def texts_of(df):
    return [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]


# ---------------------------------------------------------------- token counts


def histogram_by_hand(lengths):
    n, total = len(lengths), sum(lengths)
    return sorted((x, c, x * c, sum(v >= x for v in lengths), sum(v for v in lengths if v >= x), sum(min(v, x) for v in lengths), n, total, sum(v <= x for v in lengths) / n) for x, c in Counter(lengths).items())


def test_length_histogram(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    enc = tokens.ranked(RANKS, public_tokenizers.PATTERN)
    want = histogram_by_hand([len(enc.encode_ordinary(t)) for _, t in texts_of(docs)])
    got = sorted(map(tuple, queries.op1_length_histogram(spark, sf).collect()))
    assert got == want


def test_length_answers(spark):
    lengths = [0, 0, 3, 5, 5, 2000, 4100, 1023, 1024]
    hist = T.length_histogram(spark.createDataFrame([(n,) for n in lengths], "n_tokens long"))
    assert sorted(map(tuple, hist.collect())) == histogram_by_hand(lengths)
    got = {r.limit: (r.docs_within, r.truncated_total, r.lost) for r in T.at_limits(hist, [4, 1024, 9999]).collect()}
    assert got == {m: (sum(n <= m for n in lengths), sum(min(n, m) for n in lengths), sum(max(0, n - m) for n in lengths)) for m in (4, 1024, 9999)}
    assert T.at_limits(hist.where("n_tokens < 0"), [5]).count() == 0
    s = sorted(lengths)
    assert {r.share: r.n_tokens for r in T.quantiles(hist, [0.0, 0.5, 1.0]).collect()} == {0.0: s[0], 0.5: s[4], 1.0: s[-1]}
    by = T.length_histogram(spark.createDataFrame([("a", 1), ("a", 1), (None, 7)], "g string, n_tokens long"), ("g",))
    assert sorted((r.g or "", r.n_tokens, r.n_docs, r.total_docs) for r in by.collect()) == [("", 7, 1, 1), ("a", 1, 2, 2)]


def test_length_edges(spark):
    lengths = T.encoded_lengths(documents(spark), RANKS, public_tokenizers.PATTERN)
    hist = T.length_histogram(lengths)
    assert hist.agg(F.sum("n_docs")).first()[0] == 11 and hist.where("n_tokens = 0").first().n_docs == 3
    assert T.length_histogram(T.encoded_lengths(empty(spark), RANKS, public_tokenizers.PATTERN)).count() == 0


# ---------------------------------------------------------------- language


def test_held_out_accuracy(spark):
    out = queries.op2_mixture(spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in out if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in out)
    assert len(held) > 100 and sum(r.lang_pred == r.lang for r in held) / len(held) > 0.98
    assert all(0 <= r.score <= 1 for r in out)


def test_mixtures(spark, sf):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    names, table = L.train(docs)
    by = {}
    for r in docs.collect():
        by.setdefault(r.lang, []).append(" ".join(r.text.split()[:80]))
    mixed = L.proportions([by["en"][3] + " " + by["de"][3], by["en"][4], by["fr"][2] + " " + by["es"][2]], table)
    share = lambda i, lang: mixed[i][names.index(lang)]
    assert 0.3 < share(0, "en") < 0.7 and 0.3 < share(0, "de") < 0.7 and share(0, "en") + share(0, "de") > 0.9
    assert share(1, "en") > 0.95
    assert 0.3 < share(2, "fr") < 0.7 and 0.3 < share(2, "es") < 0.7


def test_language_sets_against_all_subsets(spark):
    """The chosen set is the best of all sets of languages by penalised likelihood, each fitted for itself."""
    from itertools import combinations

    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    names, table = L.train(docs)
    by = {}
    for r in docs.orderBy("doc_id").collect():
        by.setdefault(r.lang, []).append(r.text.split())
    part = lambda lang, i, n: " ".join(by[lang][i][:n])
    texts = [part("en", 3, 60), part("fr", 2, 9), part("en", 4, 40) + " " + part("de", 3, 40), part("es", 5, 50) + " " + part("fr", 6, 25), part("de", 7, 30) + " " + part("en", 8, 30) + " " + part("es", 9, 40)]
    got = L.proportions(texts, table)
    for text, row in zip(texts, got):
        grams, first, _ = L.trigrams([text])
        ll = np.add.reduceat(table[grams].astype(float), first, axis=0)
        w = np.exp(ll - ll.max(axis=1)[:, None])

        def value(chosen):
            pi = np.zeros(len(names))
            pi[list(chosen)] = 1 / len(chosen)
            for _ in range(200):
                r = w * pi
                pi = (r / r.sum(axis=1, keepdims=True)).mean(axis=0)
            return np.log((w * pi).sum(axis=1)).sum() - (len(chosen) - 1) * L.PRICE * np.log(len(w) + 1)  # noqa: B023

        best = max((c for k in range(1, len(names) + 1) for c in combinations(range(len(names)), k)), key=value)
        assert {names[i] for i in np.flatnonzero(row)} == {names[i] for i in best}


def test_mixture_likelihood_rises():
    """EM never lowers the likelihood, and the sum of proportions is 1."""
    rng = np.random.default_rng(0)
    w = rng.random((50, 3))
    doc, first, n = np.repeat([0, 1], [20, 30]), np.array([0, 20]), np.array([20, 30])
    pi, last = np.full((2, 3), 1 / 3), -np.inf
    for _ in range(8):
        pi, ll = L._em(w, doc, first, n, pi, 1)
        assert ll.sum() >= last - 1e-9 and np.allclose(pi.sum(axis=1), 1)
        last = ll.sum()


def test_language_edges(spark):
    out = {(r.doc_id, r.lang_pred, r.score) for r in L.learn_and_predict(documents(spark)).collect() if r.doc_id in (3, 4, 5)}
    assert out == {(3, "und", 0.0), (4, "und", 0.0), (5, "und", 0.0)}
    assert L.learn_and_predict(documents(spark)).count() == 11
    assert L.learn_and_predict(empty(spark)).count() == 0
    unlabelled = documents(spark).withColumn("lang", F.lit(None).cast("string"))
    assert {r.lang_pred for r in L.learn_and_predict(unlabelled).collect()} == {"und"}
    kept = L.keep_identified(documents(spark), L.train(documents(spark)))
    assert kept.columns == documents(spark).columns and kept.where("doc_id IN (3, 4, 5)").isEmpty() and kept.where("doc_id IN (1, 6, 7)").count() == 3
    model = L.train(documents(spark))
    same = L.predict(documents(spark).where("doc_id = 1 OR doc_id = 2"), model).select("lang_pred", "score").distinct()
    assert same.count() == 1


# ---------------------------------------------------------------- packing


def test_encoder_gives_the_tokenizers_ids():
    enc = tokens.ChunkEncoder(VOCAB)
    t = Tokenizer.from_file(VOCAB)
    odd = ["ΣΑΣ été", "it's I'LL 'tis !!'s ''s x'd'm", "á b c\x85d \x1c e", "½ ² 12ab3", "İstanbul ŉ ǅ ß ÀÖ×÷ªº", "<|endoftext|> hi", "日本語 テスト", "\t\r\n a\tb", "é x", "　全角", "a_b-c__d", "Ωμ€ “q”", "", " ", "ﬁ ①", "'S 'RE we'Re", PLAIN]
    for text in odd * 2:
        assert np.frombuffer(enc.encode(text), "<u4").tolist() == t.encode(text, add_special_tokens=False).ids


def first_fit_by_hand(lengths, limit):
    rooms, out = [], []
    for n in lengths:
        i = next((i for i, r in enumerate(rooms) if r >= n), len(rooms))
        if i == len(rooms):
            rooms.append(limit)
        out.append((i, limit - rooms[i]))
        rooms[i] -= n
    return out


def test_tournament_tree_is_first_fit():
    r = random.Random(5)
    for _ in range(100):
        lengths = sorted((r.randint(1, 40) for _ in range(r.randint(0, 60))), reverse=True)
        assert packing.first_fit_decreasing(lengths, 40) == first_fit_by_hand(lengths, 40)


def check_packing(rows, texts, limit=4096):
    t = Tokenizer.from_file(VOCAB)
    by_doc, by_seq = {}, {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_seq.setdefault(r.sequence_id, []).append(r)
    for doc, text in texts:
        ids = np.array(t.encode(text or "", add_special_tokens=False).ids + [2], "<u4")
        at = 0
        for p in sorted(by_doc[doc], key=lambda p: p.start):
            assert p.start == at and p.doc_tokens == len(ids) and p.ids_crc32 == zlib.crc32(ids[at : at + p.length].tobytes())
            at += p.length
        assert at == len(ids)
    for pieces in by_seq.values():
        at = 0
        for p in sorted(pieces, key=lambda p: p.offset):
            assert p.offset == at and p.length > 0
            at += p.length
        assert at <= limit
    return by_seq


def test_packing(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    packed = queries.op4_first_fit(spark, sf)
    check_packing(packed.collect(), texts_of(docs))
    p = packing.padding(packed).first()
    assert p.padding / p.tokens < 0.06  # of 200 documents; the last sequence weighs


def test_packing_groups(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    packed = packing.pack(docs, VOCAB, group=40)
    check_packing(packed.collect(), texts_of(docs))
    assert packed.select((F.col("sequence_id") / (1 << 32)).cast("long")).distinct().count() > 2


def test_packing_edges(spark):
    docs = documents(spark).where("doc_id IS NOT NULL AND doc_id <> 2")
    check_packing(packing.pack(docs, VOCAB).collect(), texts_of(docs))
    whole = packing.pack(documents(spark), VOCAB).collect()
    assert sum(r.start == 0 for r in whole) == 11 and sum(r.doc_id is None for r in whole) == 2
    assert packing.pack(empty(spark), VOCAB).count() == 0


# ---------------------------------------------------------------- near duplicates


def brute_classes(rows):
    """Classes by exact Jaccard over all pairs."""
    words = [re.findall(r"[^\W_]+", (t or "").lower()) for _, t in rows]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set() for w in words]
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            same = rows[i][1] is not None and rows[i][1] == rows[j][1]
            if same or (sets[i] and sets[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    first = {}
    for i, (doc, _) in enumerate(rows):
        r = find(i)
        first[r] = min(x for x in (first.get(r), doc) if x is not None) if (first.get(r) is not None or doc is not None) else None
    return {rows[i][0]: first[find(i)] for i in range(len(rows))}


def test_near_duplicates_against_all_pairs(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = texts_of(docs)
    got = {r.doc_id: r.class_id for r in queries.op7_prob_minhash(spark, sf).collect()}
    assert got == brute_classes(rows)
    assert any(k != v for k, v in got.items())


def test_near_duplicate_twin(spark, sf):
    assert_twin(queries.op7_prob_minhash(spark, sf), connect(sf), queries.OP7_SQL)


def test_near_duplicates_lose_nothing_at_larger_size(spark):
    """An exact shingle join over 1,000 documents gives the same classes."""
    d = "/root/testdata/sf0.01"
    assert_twin(queries.op7_prob_minhash(spark, d), connect(d), queries.OP7_SQL)


@pytest.mark.parametrize("times", [1, 5, 20, 50, 200])
def test_bands_meet_whatever_lines_repeat(times):
    """Share of pairs at a Jaccard similarity of 0.8 and a little more that have a common band, lines repeated on one side."""
    r = random.Random(times)
    word = lambda: f"w{r.randint(0, 10**9)}"
    met, n = 0, 300
    for _ in range(n):
        lines = [" ".join(word() for _ in range(12)) for _ in range(20)]
        a = " ".join(lines).split()
        b = " ".join(x for i, x in enumerate(lines) for _ in range(times if i % 3 == 0 else 1)).split()
        for _ in range(2):
            b[r.randrange(len(b))] = word()
        hashes = N.Hasher()
        found = [np.unique(N.shingle_hashes(hashes(x)), return_counts=True) for x in (a, b)]
        both = len(np.intersect1d(found[0][0], found[1][0]))
        if both < 0.8 * (len(found[0][0]) + len(found[1][0]) - both):
            n -= 1
            continue
        plain = N.band_hashes([x for x, _ in found], [np.ones(len(c)) for _, c in found], N.BANDS, N.ROWS)
        met += bool(set(plain[0].tolist()) & set(plain[1].tolist()))
    assert n > 50 and met / n >= 0.99


def test_families_that_meet(spark):
    """Two families of copies with links across: found in blocks, without a row for each pair."""
    r = random.Random(12)
    base = [f"w{r.randint(0, 10**6)}" for _ in range(100)]
    other = base[:50] + [f"x{r.randint(0, 10**6)}" for _ in range(9)] + base[59:]

    def edited(words, n):
        w = list(words)
        for _ in range(n):
            w[r.randrange(100)] = f"e{r.randint(0, 10**6)}"
        return " ".join(w)

    rows = [(i, edited(base if i % 2 else other, r.randint(0, 3))) for i in range(160)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_classes(rows)
    for block in (8, 96):
        assert {x.doc_id: x.class_id for x in N.near_duplicates(docs, block=block).collect()} == want


def test_meeting_rows(spark):
    """Families meet once over all their buckets, and only where labels differ."""
    rows = [(b, rep, hub, rep if hub == 1 else 50, 1) for b in (10, 11) for rep, hub in ((1, 1), (2, 1), (3, 2), (4, 2))] + [(12, 1, 1, 7, 1), (12, 9, 3, 7, 1)]
    known = spark.createDataFrame(rows, "bucket long, rep long, hub long, label long, main long")
    got = sorted(map(tuple, N.meeting_rows(known).collect()))
    assert got == [(1, 2, False, 3, 50), (1, 2, False, 4, 50), (1, 2, True, 1, 1), (1, 2, True, 2, 2)]


def test_dense_family(spark):
    """Edited copies that are near some others and far from the rest: no link within a bucket is lost."""
    r = random.Random(11)
    base = [f"w{r.randint(0, 10**6)}" for _ in range(120)]
    rows = []
    for i in range(90):
        w = list(base)
        for _ in range(r.randint(0, 6)):
            w[r.randrange(120)] = f"e{r.randint(0, 10**6)}"
        rows.append((i, " ".join(w)))
    rows += [(100 + i, " ".join(f"z{r.randint(0, 10**6)}" for _ in range(60))) for i in range(20)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_classes(rows)
    for block in (8, 96):
        got = {x.doc_id: x.class_id for x in N.near_duplicates(docs, bands=40, rows=3, block=block).collect()}
        assert got == want


def test_pairs_apart_by_a_repeated_line(spark):
    """Links whose weighted similarity is far below their Jaccard similarity, with production parameters."""
    r = random.Random(4)
    rows = []
    for i in range(20):
        text, line = (" ".join(f"w{r.randint(0, 10**9)}" for _ in range(n)) for n in (104, 15 + i % 4))
        rows += [(2 * i, text), (2 * i + 1, f"{text} {' '.join([line] * r.choice([200, 500, 1000]))}")]
    want = brute_classes(rows)
    assert all(want[2 * i + 1] == 2 * i for i in range(20))
    got = {x.doc_id: x.class_id for x in N.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == want


def test_sketch_estimates_probability_jaccard():
    """Equal registers against the exact weighted similarity."""
    rng = np.random.default_rng(2)
    ids = rng.integers(0, 2**63, 300).astype(np.uint64)
    x, y = np.zeros(300), np.zeros(300)
    x[:200], y[80:280] = rng.integers(1, 5, 200), rng.integers(1, 5, 200)
    exact = sum(1 / np.maximum(x / x[i], y / y[i]).sum() for i in range(300) if x[i] and y[i])
    m = 6000
    sketch = lambda w: N.prob_minhash(ids[w > 0], w[w > 0], np.zeros((w > 0).sum(), int), 1, m)[0]
    assert abs(N.estimate(sketch(x), sketch(y)) - exact) < 4 * np.sqrt(exact * (1 - exact) / m)
    assert N.estimate(sketch(x), sketch(3 * x)) == 1.0  # only ratios of weights count


def test_near_duplicate_edges(spark):
    out = N.near_duplicates(documents(spark)).collect()
    assert len(out) == 11
    by = {}
    for r in out:
        by.setdefault(r.doc_id, set()).add(r.class_id)
    assert by[1] == by[2] == {1} and by[3] == {3} and by[4] == {4} and by[5] == {5} and by[6] == {6} and by[7] == {7} and by[8] == {8}
    assert N.near_duplicates(empty(spark)).count() == 0
    kept = N.keep_one(documents(spark))
    assert kept.columns == documents(spark).columns
    assert sorted(r.doc_id for r in kept.collect() if r.doc_id is not None) == [1, 3, 4, 5, 6, 7, 8]
    assert N.keep_one(empty(spark)).count() == 0


def test_one_id_with_two_texts(spark):
    """Each row is linked by its own text, and keep_one takes rows, not ids."""
    r = random.Random(8)
    text = lambda: " ".join(f"w{r.randint(0, 10**9)}" for _ in range(100))
    a, b, c, d = text(), text(), text(), text()
    rows = [(1, a), (5, b), (5, a + " end"), (7, b + " end"), (8, c), (8, c + " end"), (None, d), (None, a + " null")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((x.doc_id or 0, x.class_id or 0) for x in N.near_duplicates(docs).collect())
    assert got == [(0, 0), (0, 1), (1, 1), (5, 1), (5, 5), (7, 5), (8, 8), (8, 8)]
    kept = sorted((x.doc_id or 0, x.text) for x in N.keep_one(docs).collect())
    assert [i for i, _ in kept] == [0, 1, 5, 8] and kept[:3] == [(0, d), (1, a), (5, b)] and kept[3][1] in (c, c + " end")


def test_large_group_of_copies(spark):
    """A third of all rows are one text, another share are one text with a different ending."""
    rows = [(i, PLAIN + " " + PLAIN[::-1]) for i in range(400)] + [(1000 + i, PLAIN + " " + PLAIN[::-1] + f" end{i % 50}") for i in range(300)] + [(5000 + i, hashlib.md5(str(i).encode()).hexdigest()) for i in range(400)]
    out = {r.doc_id: r.class_id for r in N.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {out[i] for i in range(400)} == {0} and {out[1000 + i] for i in range(300)} == {0}
    assert all(out[5000 + i] == 5000 + i for i in range(400))


# ---------------------------------------------------------------- decontamination


def naive(docs, items, window=13):
    out = []
    for doc, text in docs:
        w = D.words(text)
        hit, found = set(), set()
        for item, t in items:
            b = D.words(t)
            n = min(window, len(b))
            spots = {tuple(b[o : o + n]) for o in range(len(b) - n + 1)} if n else set()
            for i in range(len(w) - n + 1 if n else 0):
                if tuple(w[i : i + n]) in spots:
                    hit.update(range(i, i + n))
                    found.add("null" if item is None else str(item))
        out.append((doc, len(w), len(hit), sorted(found)))
    return sorted(out, key=str)


def digest(df):
    return sorted(((r.doc_id, r.n_words, r.n_hit, list(r.item_ids)) for r in df.collect()), key=str)


def test_decontamination_twin(spark, sf):
    assert_twin(queries.op9_suffix_arrays(spark, sf), connect(sf), queries.OP9_SQL)


@pytest.mark.parametrize("shard_words", [7, 40, 1 << 20])
def test_decontamination_against_brute_force(spark, shard_words):
    r = random.Random(9)
    word = lambda: r.choice("ab")
    items = [(i, " ".join(word() for _ in range(r.randint(0, 9)))) for i in range(6)] + [(None, "b a, b! a"), (3, "b b b"), (50, "é"), (51, None)]
    docs = [(i, " ".join(r.choice(["a", "b", "c"]) for _ in range(r.randint(0, 30)))) for i in range(40)] + [(90, None), (91, "B-A.b\na"), (92, "É é")]
    found = D.find(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), window=4, shard_words=shard_words)
    assert digest(found) == naive(docs, items, window=4)
    for row in found.collect():
        assert sum(h.length for h in row.hits) == row.n_hit and all(a.start + a.length < b.start for a, b in zip(row.hits, row.hits[1:]))


def test_longest_matches(spark):
    docs = [(1, "x y the cat sat on z"), (2, "the cat sat on the mat today"), (3, "nothing here")]
    items = [(7, "the cat sat on the mat")]
    got = {r.start: (r.length, r.doc_id, r.place) for r in D.longest_matches(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), shard_words=5).collect()}
    assert got == {0: (6, 2, 0), 1: (5, 2, 1), 2: (4, 2, 2), 3: (3, 2, 3), 4: (2, 2, 4), 5: (1, 2, 5)}


@pytest.mark.parametrize("part", [1, 60, 1 << 20])
def test_benchmark_in_parts(spark, part):
    """Hits that overlap or touch across parts count once; parts change no result."""
    r = random.Random(3)
    items = [(i, " ".join(r.choice("ab") for _ in range(r.randint(0, 9)))) for i in range(8)] + [(None, "c d e"), (9, "e f g"), (10, None)]
    docs = [(i, " ".join(r.choice("abcdefg") for _ in range(r.randint(0, 30)))) for i in range(30)] + [(90, "x c d e f g x"), (91, None), (92, "c d e e f g")]
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    found = D.find(d, b, window=3, part=part)
    want = naive(docs, items, window=3)
    assert digest(found) == want
    for row in found.collect():
        assert sum(h.length for h in row.hits) == row.n_hit and all(x.start + x.length < y.start for x, y in zip(row.hits, row.hits[1:]))
    kept = {x.doc_id for x in D.drop_contaminated(d, b, window=3, part=part).collect()}
    assert kept == {i for i, n, hit, _ in want if not (hit and 20 * hit >= n)}
    lengths = lambda p: sorted((x.item_id or -1, x.start, x.length) for x in D.longest_matches(d, b, part=p).collect())
    assert lengths(part) == lengths(1 << 20)


def longest_by_hand(doc, items, window):
    """(words, place) of the longest run that a text shares with an item from the start of a window on."""
    w, best = D.words(doc), (0, None)
    for _, t in items:
        b = D.words(t)
        n = min(window, len(b))
        for i in range(len(w)):
            for o in range(len(b) - n + 1 if n else 0):
                k = 0
                while i + k < len(w) and o + k < len(b) and w[i + k] == b[o + k]:
                    k += 1
                if k >= n and (k > best[0] or k == best[0] and i < best[1]):
                    best = (k, i)
    return best


@pytest.mark.parametrize("part,shard_words", [(1, 9), (50, 1 << 20), (1 << 20, 9), (1 << 20, 1 << 20)])
def test_longest_match_of_documents(spark, part, shard_words):
    r = random.Random(21)
    items = [(i, " ".join(r.choice("abc") for _ in range(r.randint(0, 14)))) for i in range(7)] + [(20, "q r"), (21, "a b c a b c a b c a b c"), (22, None)]
    docs = [(i, " ".join(r.choice("abcx") for _ in range(r.randint(0, 25)))) for i in range(30)] + [(50, "x a b c a b c a b c a b c x a b c a b"), (51, "q r q r"), (52, None)]
    found = D.find(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), window=4, shard_words=shard_words, part=part)
    got = {x.doc_id: (x.longest_match, x.longest_at) for x in found.collect()}
    assert got == {doc: longest_by_hand(text, items, 4) for doc, text in docs} and got[50] == (12, 1) and got[51] == (2, 0)


def test_a_long_item_stays_small():
    """100,000 words: a matrix of the item's whole suffixes would be 40 GB."""
    import tracemalloc

    tracemalloc.start()
    text = " ".join(f"w{i}" for i in range(100_000))
    wanted = D.targets([(1, text), (2, "w5 w6 z " * 4)])
    (n, hit, ids, hits, longest, at), = D.search(["x " + text + " y"], wanted)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert (n, hit, ids, hits, longest, at) == (100_002, 100_000, ["1"], [{"start": 1, "length": 100_000}], 100_000, 1)
    assert peak < 500 << 20


def test_decontamination_edges(spark):
    bench = spark.createDataFrame([(1, PLAIN)], "item_id long, text string")
    out = D.find(documents(spark), bench)
    assert out.count() == 11 and {r.n_hit for r in out.where("doc_id IN (1, 2)").collect()} == {len(PLAIN.split())}
    kept = D.drop_contaminated(documents(spark), bench)
    assert kept.columns == documents(spark).columns and kept.count() == 8
    nothing = spark.createDataFrame([], "item_id long, text string")
    assert D.drop_contaminated(documents(spark), nothing).count() == 11
    assert D.find(empty(spark), bench).count() == 0
    with pytest.raises(ValueError):
        D.find(documents(spark), bench, limit=10)
    assert len(LONG.split()) == out.where("doc_id = 6").first().n_words
