"""What queries move: plans that grew faster than their input, or made a Python call for each tiny group."""

import pyarrow as pa
import pytest
from pyspark.sql import Row, functions as F

from postpool.config import IndexConfig
from postpool.operators import baselines, pool, retrieval as R
from postpool.plans import catalog, support, workloads as W


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_merges_move_blocks_not_postings(spark, sf, monkeypatch):
    """Also with parts of two blocks, so that run blocks lie in several parts."""
    plans, write = {}, baselines.materialise
    monkeypatch.setattr(baselines, "materialise", lambda df, tag: plans.setdefault(tag, plan(df)) and write(df, tag))
    monkeypatch.setattr(baselines, "PART", 2, raising=False)
    rows = W.parsed(spark, sf).where("doc_id < 120")
    cfg = IndexConfig(block=4, df_threshold=1)
    _, merged = baselines.full_flush_index(rows, cfg, rows.count() // 7)
    assert "positions" not in plans["merged"]
    got = {(r.term, r.seg_no): (r.n_docs, r.first_doc, r.last_doc) for r in merged.collect()}
    lists = {}
    for r in rows.select("term", "doc_id").collect():
        lists.setdefault(r.term, []).append(r.doc_id)
    want = {(t, i // 4): (len(d[i : i + 4]), d[i], d[i : i + 4][-1]) for t, d in ((t, sorted(d)) for t, d in lists.items()) for i in range(0, len(d), 4)}
    assert got == want
    digest = lambda df: sorted(map(tuple, catalog.posting_digest(df).collect()))
    assert digest(baselines.pool.decode(merged)) == digest(rows)


def test_block_shapes_read_heads(spark, sf):
    for name in ("block_sizes", "pool_size"):
        found = plan(catalog.QUERIES[name](spark, sf))
        assert "positions" not in found and "collect_list" not in found


def test_groups_share_python_calls(spark, sf):
    assert "AggregateInPandas" not in plan(support.udaf(spark, sf))


def test_recursion_takes_stretches(spark, sf):
    segs = catalog.index(spark, sf).placed
    pieces = support.stretches(segs, 4).groupBy("term").agg(F.count(F.lit(1)).alias("n"), F.sum("hops").alias("hops"))
    sizes = segs.groupBy("term").agg(F.count(F.lit(1)).alias("segments"))
    rows = pieces.join(sizes, "term").collect()
    assert max(r.segments for r in rows) > 8
    assert all(r.n == -(-r.segments // 4) and r.hops == r.segments for r in rows)


def test_phrases_share_positions(spark):
    """A word in many phrases isn't repeated for each of them."""
    texts = ["a b a b a", "b b b a", "a", None, "c a b c"]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    asked = [["a", "b"], ["b", "b"], ["a", "b"], ["b", "a", "b"], ["c"], ["x", "a"]]
    phrases = spark.createDataFrame([Row(query_id=i, terms=t) for i, t in enumerate(asked)])
    out = R.phrase(catalog.P.build_postings(docs), phrases)
    want = {}
    for d, t in enumerate(texts):
        words = (t or "").split()
        for q, p in enumerate(asked):
            n = sum(words[i : i + len(p)] == p for i in range(len(words) - len(p) + 1))
            if n:
                want[q, d] = n
    assert {(r.query_id, r.doc_id): r.n_matches for r in out.collect()} == want
    assert "LeftSemi" in plan(out)


def test_matches_are_counted_where_they_arise(spark, sf):
    for name in ("svs_relational", "svs_edge", "bm25_topk_w"):
        lines = plan(catalog.QUERIES[name](spark, sf)).splitlines()
        assert not [x for x in lines if "Exchange hashpartitioning(query_id" in x and "doc_id" in x.split("),")[0]], name


def test_intervals_come_from_a_table(spark, sf):
    out = catalog.QUERIES["ci_overlap"](spark, sf)
    assert out.count() > 0 and any("lineitem" in f for f in out.inputFiles())


def test_lists_are_walked_together():
    """Rows of several lists by address, some with pointers back; broken ones are told by their term."""
    rows = [("a", 0, 40, 7, True), ("a", 0, 50, None, False), ("a", 0, 7, 50, False), ("b", 1, 3, None, True), ("c", 2, 60, 90, False), ("c", 2, 90, None, False), ("c", 2, 95, 60, True)]
    rows = sorted(rows, key=lambda r: (r[1], r[2]))
    table = lambda rows: pa.table({n: pa.array(c, k) for n, c, k in zip(["term", "term_id", "addr", "next_addr", "is_head"], zip(*rows), [pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.bool_()])})
    assert [rows[i][2] for i in pool.walked(table(rows), [0, 3, 4])] == [40, 7, 50, 3, 95, 60, 90]
    for bad in (8, 95, None):
        broken = [("c", 2, 60, bad, False) if r[2] == 60 else r for r in rows]
        with pytest.raises(ValueError, match="'c' is broken"):
            pool.walked(table(broken), [0, 3, 4])


def test_lists_go_on_in_the_next_arrow_batch(spark, sf):
    segs = catalog.index(spark, sf).segments
    want = pool.traverse(segs).select("term", "doc_id", "tf", "positions").exceptAll(catalog.index(spark, sf).postings.select("term", "doc_id", "tf", "positions"))
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 3)
    try:
        assert pool.traverse(segs).count() == catalog.index(spark, sf).postings.count() and want.count() == 0
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
