"""Query sets over parts of the documents, against brute force."""

import numpy as np
import pytest

from postpool.operators import parts, retrieval as R


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.fixture(scope="module")
def small(spark):
    """Lists of uneven length over ids far apart, and queries: repeated, of one word, unknown words, twice the same word."""
    rng = np.random.default_rng(5)
    ids = np.sort(rng.choice(10**12, 400, replace=False)).tolist()
    rows = [(f"t{i}", ids[d], float(rng.integers(1, 40)) / 8) for i in range(12) for d in rng.choice(400, 2 + 33 * i, replace=False).tolist()]
    asked = [["t1"], ["t11", "t10", "t9"], ["t9", "t10", "t11"], ["t5", "x"], ["x"], ["t3", "t3"], []] + [[f"t{i}" for i in rng.choice(12, 3, replace=False)] for _ in range(20)]
    return rows, asked, spark.createDataFrame(rows, "term string, doc_id long, w double"), spark.createDataFrame(list(enumerate(asked)), "query_id long, terms array<string>")


@pytest.mark.parametrize("missing", ["empty", "ignore"])
def test_intersections(small, monkeypatch, missing):
    rows, asked, postings, queries = small
    monkeypatch.setattr(parts, "PART", 500)
    has, known = {}, {t for t, _, _ in rows}
    for t, d, _ in rows:
        has.setdefault(d, set()).add(t)
    want = []
    for q, terms in enumerate(asked):
        need = {t for t in terms if t in known or missing == "empty"}
        want += [(q, d) for d, there in has.items() if need and need <= there]
    out = R.intersect(postings, queries, missing)
    assert sorted(map(tuple, out.collect())) == sorted(want)
    assert "HashAggregate(keys=[query_id" not in plan(out)  # no row for each match


def test_best(small, monkeypatch):
    rows, asked, weights, queries = small
    monkeypatch.setattr(parts, "PART", 500)
    w = {(t, d): x for t, d, x in rows}
    for k in (1, 7, 1000):
        want = []
        for q, terms in enumerate(asked):
            scores = {}
            for (t, d), x in w.items():
                if t in terms:
                    scores[d] = scores.get(d, 0) + x
            want += [(q, i + 1, d, s) for i, (d, s) in enumerate(sorted(scores.items(), key=lambda e: (-e[1], e[0]))[:k])]
        out = R.exhaustive(weights, queries, k)
        assert sorted(map(tuple, out.collect())) == want
        assert "HashAggregate(keys=[query_id" not in plan(out)


def test_best_of_many_equal():
    """Documents that tie go by id, also beyond the stretches that bound the k-th best."""
    n = 1000
    part = parts.Part(np.repeat([0, 1], n), np.tile(np.arange(n)[::-1] * 3, 2), np.repeat([0.25, 0.5], n))
    docs, scores = part.best((0, 1), 5)
    assert docs.tolist() == [0, 3, 6, 9, 12] and scores.tolist() == [0.75] * 5
