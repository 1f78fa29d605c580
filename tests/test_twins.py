"""Every query of the catalog against its SQL twin."""

import pytest

from postpool.plans import catalog, support  # noqa: F401

from .twins import assert_twin, connect


@pytest.fixture(scope="module")
def con(sf):
    return connect(sf)


@pytest.mark.parametrize("name", sorted(catalog.SQL))
def test_twin(spark, sf, con, name):
    assert_twin(catalog.QUERIES[name](spark, sf), con, catalog.SQL[name])


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - set(catalog.SQL)))
def test_rows(spark, sf, name):
    assert catalog.QUERIES[name](spark, sf).count() > 0


def test_work_counters_do_not_depend_on_layout(spark, sf):
    by = {}
    for r in catalog.QUERIES["work_counters_wand"](spark, sf).collect():
        by.setdefault((r.query_set, r.query_id), set()).add((r.segments_decoded, r.postings_decoded, r.probes, r.pivots, r.scored))
    assert all(len(v) == 1 for v in by.values()) and any(v != {(0, 0, 0, 0, 0)} for v in by.values())


def test_stream_groups_equal_batch(spark, sf):
    got = {(r.term, r.group_no): r.n_docs for r in catalog.QUERIES["stream_index"](spark, sf).collect()}
    want = {(r.term, r.group_no): r.last_rank - r.first_rank + 1 for r in catalog.QUERIES["flush_groups"](spark, sf).select("term", "group_no", "first_rank", "last_rank").collect()}
    assert got == want


def test_approximate_vocabulary(spark, sf):
    exact = {r.source: r.terms for r in catalog.QUERIES["agg_distinct"](spark, sf).collect()}
    near = {r.source: r.terms for r in catalog.QUERIES["agg_approx"](spark, sf).collect()}
    assert exact.keys() == near.keys() and all(abs(near[s] - n) <= max(5, 0.1 * n) for s, n in exact.items())


def test_flagship(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).columns == ["query_id", "doc_id"]
    assert set(entry.oracle_sql()) <= set(entry.queries())
