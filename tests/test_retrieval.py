import random

import numpy as np
import pytest

from postpool.config import IndexConfig
from postpool.operators import kernels, measures, retrieval as R
from postpool.operators.index import build_index
from postpool.plans import workloads as W
from postpool.sources.io import read_table


def test_gallop():
    r = random.Random(3)
    for _ in range(300):
        v = sorted(r.sample(range(400), r.randint(0, 60)))
        lo, target = r.randint(0, len(v)), r.randint(0, 400)
        at, probes = kernels.gallop(v, target, lo)
        assert at == lo + int(np.searchsorted(v[lo:], target)) and probes <= 2 * (max(1, at - lo + 2)).bit_length() + 2


@pytest.fixture(scope="module")
def ix(spark, sf):
    return build_index(read_table(spark, sf, "documents"), IndexConfig(block=8, cap_log2=2, df_threshold=5, n_shards=3))


def test_conjunctive_ways_agree(spark, sf, ix):
    for which in ("E", "W"):
        q = W.query_set(spark, sf, which)
        rows = lambda df: sorted((r.query_id, r.doc_id) for r in df.collect())
        truth = rows(R.intersect(ix.postings, q))
        assert rows(kernels.svs(ix.segments, q)) == truth
        assert rows(R.intersect_by_joins(ix.postings, ix.dictionary, q)) == truth


def test_query_edges(spark, ix):
    term = ix.dictionary.orderBy("df").first().term
    n = ix.dictionary.where(f"term = '{term}'").first().df
    q = spark.createDataFrame([(1, [term]), (2, [term, term]), (3, [term, "no_such_term"]), (4, ["no_such_term"])], "query_id long, terms array<string>")
    counts = lambda df: {r["query_id"]: r["count"] for r in df.groupBy("query_id").count().collect()}
    assert counts(kernels.svs(ix.segments, q)) == counts(R.intersect(ix.postings, q)) == {1: n, 2: n}
    assert counts(R.intersect(ix.postings, q, missing="ignore")) == {1: n, 2: n, 3: n}


@pytest.mark.parametrize("k", [1, 10, 1000])
def test_wand_equals_exhaustive(spark, sf, ix, k):
    weights = R.scored(ix.postings, ix.dictionary, ix.stats, ix.coll)
    most = {r.term: r.max_contrib for r in R.term_bounds(weights).collect()}
    assert all(abs(most[r.term] - r.max_contrib) < 1e-12 for r in ix.dictionary.collect())
    rows = lambda df: sorted((r.query_id, r.rank, r.doc_id, r.score) for r in df.collect())
    q = W.query_set(spark, sf, "W")
    truth = rows(R.exhaustive(weights, q, k))
    for segs in (ix.served, ix.segments):
        assert rows(kernels.wand(segs, q, ix.dictionary, ix.coll, k)) == truth
        assert rows(kernels.wand(segs, q, ix.dictionary, ix.coll, k, by_block=True)) == truth


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_queries_shuffle_no_blocks(spark, sf, ix):
    """Shards are read where they lie, one task each; only top-k lists meet after the kernel."""
    q = W.query_set(spark, sf, "E")
    found = kernels.svs(ix.served, q)
    assert "hashpartitioning(slot" not in plan(found) and "Exchange" not in plan(found).split("FlatMapGroupsInArrow")[0]
    found.collect()
    assert "hashpartitioning(slot" not in plan(found) and "Bucketed: true" in plan(found)
    sizes = ix.served.select("slot", "shard").distinct().collect()
    assert len({r.slot for r in sizes}) == len(sizes) == 3
    per_task = ix.served.groupBy("slot").count().rdd.glom().map(len).collect()
    assert max(per_task) == 1


def test_query_batches(spark, sf, ix, monkeypatch):
    """Sets beyond the bound are run in batches, with the same answers."""
    q = W.query_set(spark, sf, "W")
    rows = lambda df: sorted(map(tuple, df.collect()))
    weights = R.scored(ix.postings, ix.dictionary, ix.stats, ix.coll)
    one = [rows(kernels.svs(ix.served, q)), rows(kernels.wand(ix.served, q, ix.dictionary, ix.coll, 5)), rows(R.intersect(ix.postings, q)), rows(R.exhaustive(weights, q, 5))]
    whole = R.query_batches
    for module in (R, kernels):
        monkeypatch.setattr(module, "query_batches", lambda queries: whole(queries, 40))
    assert len(whole(q, 40)) > 2
    assert [rows(kernels.svs(ix.served, q)), rows(kernels.wand(ix.served, q, ix.dictionary, ix.coll, 5)), rows(R.intersect(ix.postings, q)), rows(R.exhaustive(weights, q, 5))] == one


def test_decoded_blocks_are_bounded(spark, sf, ix):
    """A small cache gives the same answers and counts."""
    import pyarrow as pa

    table = pa.Table.from_pylist([r.asDict() for r in ix.served.where("shard = 0").collect()], schema=pa.schema([("slot", pa.int32()), ("shard", pa.int32()), ("term", pa.string()), ("seg_no", pa.int64()), ("n_docs", pa.int32()), ("first_doc", pa.int64()), ("last_doc", pa.int64()), ("d_block", pa.binary()), ("f_block", pa.binary()), ("lengths", pa.list_(pa.int32())), ("bound", pa.float64())]))
    big, small = kernels.Lists.of_table(table), kernels.Lists.of_table(table)
    small.kept = 2
    about = {r.term: (1.0, float(r.max_contrib), r.term_id) for r in ix.dictionary.collect()}
    for q in W.query_set(spark, sf, "W").collect():
        a, b = kernels.new_work(), kernels.new_work()
        assert kernels.small_versus_small(big, q.terms, a) == kernels.small_versus_small(small, q.terms, b) and a == b
        known = {t: about[t] for t in q.terms if t in about}
        assert kernels.weak_and(big, known, 5, 100.0, a) == kernels.weak_and(small, known, 5, 100.0, b)
        assert len(small.blocks) <= 2


def test_layouts_do_the_same_work(spark, sf, ix):
    q = W.query_set(spark, sf, "E")
    work = lambda segs: sorted(map(tuple, kernels.svs(segs, q, counters=True).collect()))
    assert work(ix.segments) == work(ix.relaid("linked", 0)) == work(ix.relaid("contiguous"))


def test_jumps_fall_with_the_cap(spark, sf, ix):
    from postpool.operators import pool

    jumps = [pool.jumps(ix.relaid("linked" if m == 0 else "capped", m)).first().jumps for m in range(4)] + [pool.jumps(ix.relaid("contiguous")).first().jumps]
    assert jumps == sorted(jumps, reverse=True) and jumps[-1] == 0


def test_printed_intervals(spark):
    """At 32b seven of the eight cells of both tables overlap with contiguous; the one of L and E does not."""
    rows = measures.slowdowns(W.printed_latencies(spark)).where("layout = '32b'").collect()
    apart = [(r.algo, r.collection, r.set) for r in rows if not r.overlaps]
    assert len(rows) == 8 and apart == [("svs", "L", "E")]
    worst = measures.slowdowns(W.printed_latencies(spark)).where("algo = 'wand' AND layout = '1b'").agg({"slowdown": "max"}).first()[0]
    assert worst < 0.07


def test_confidence():
    mean, half = measures.confidence([1.0, 2.0, 3.0, 4.0, 5.0])
    assert mean == 3.0 and abs(half - 2.776 * 1.5811 / 5**0.5) < 1e-3
    assert measures.overlap((1.0, 0.2), (1.3, 0.1)) and not measures.overlap((1.0, 0.1), (1.3, 0.1))


def test_phrases(spark):
    from postpool.operators import postings as P

    docs = spark.createDataFrame([(1, "a b a b"), (2, "b a"), (3, "a a a")], "doc_id long, text string")
    q = spark.createDataFrame([(1, ["a", "b"]), (2, ["a", "a"])], "query_id long, terms array<string>")
    got = {(r.query_id, r.doc_id): r.n_matches for r in R.phrase(P.build_postings(docs), q).collect()}
    assert got == {(1, 1): 2, (2, 3): 2}


def test_stemmer(spark):
    from pyspark.sql import functions as F

    from postpool.functions import analyze

    words = {"walking": "walk", "nations": "nation", "sing": "sing", "ran": "ran", "parties": "part", "kindly": "kind", "bees": "bee"}
    df = spark.createDataFrame([(w,) for w in words], "w string").select("w", analyze.stem(F.col("w")).alias("s"))
    assert {r.w: r.s for r in df.collect()} == words
