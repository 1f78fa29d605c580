import pytest

from postpool.config import IndexConfig
from postpool.operators import relops
from postpool.operators.index import build_index
from postpool.sources import io
from postpool.sources.segpool import SegmentPool


@pytest.mark.parametrize("kind", ["parquet", "orc", "json", "csv"])
def test_documents_in_other_formats(spark, tmp_path, kind):
    docs = spark.createDataFrame([(1, 'a "b", c'), (2, "é\nf")], "doc_id long, text string")
    w = docs.write.option("header", True).option("escape", '"') if kind == "csv" else docs.write
    w.format(kind).save(f"{tmp_path}/x")
    assert sorted(map(tuple, io.read_docs(spark, f"{tmp_path}/x", kind).collect())) == [(1, 'a "b", c'), (2, "é\nf")]


def test_text_lines(spark, tmp_path):
    (tmp_path / "a.txt").write_text("one two\nthree\n")
    assert [r.text for r in io.read_docs(spark, f"{tmp_path}/a.txt", "text").orderBy("doc_id").collect()] == ["one two", "three"]


def test_pool_files(spark, sf, tmp_path):
    ix = build_index(io.read_table(spark, sf, "documents"), IndexConfig(block=16, n_shards=2))
    spark.dataSource.register(SegmentPool)
    rows = ix.segments.repartition(2, "shard").sortWithinPartitions("shard", "addr").select("shard", "addr", "next_addr", "d_block", "f_block", "p_blocks")
    rows.write.format("segpool").mode("append").save(f"{tmp_path}/pool")
    back = spark.read.format("segpool").load(f"{tmp_path}/pool")
    key = lambda df: sorted((r.shard, r.addr, r.next_addr or -1, bytes(r.d_block), bytes(r.f_block), tuple(map(bytes, r.p_blocks))) for r in df.collect())
    assert key(back) == key(rows)


def test_segments_prune(spark, sf, tmp_path):
    ix = build_index(io.read_table(spark, sf, "documents"), IndexConfig(block=16, n_shards=2))
    io.write_segments(ix.segments, f"{tmp_path}/s", by_term=True)
    df = spark.read.parquet(f"{tmp_path}/s").where("shard = 1 AND term_id = 3").select("d_block")
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(shard" in plan and "EqualTo(term_id,3)" in plan and "p_blocks" not in plan


def test_joins_against_brute_force(spark):
    pts = [(i, (i * 37) % 100) for i in range(50)]
    rngs = [(i, (i * 13) % 90, (i * 13) % 90 + i % 11) for i in range(30)]
    p, r = spark.createDataFrame(pts, "p long, x long"), spark.createDataFrame(rngs, "r long, a long, z long")
    got = sorted((x.p, x.r) for x in relops.range_join(p, r, "x", "a", "z", 7).collect())
    assert got == sorted((i, j) for i, x in pts for j, a, z in rngs if a <= x <= z)
    a, b = p, p.selectExpr("p AS q", "x AS y")
    got = sorted((x.p, x.q) for x in relops.interval_join(a, b, "x", "y", 9).collect())
    assert got == sorted((i, j) for i, x in pts for j, y in pts if y - 9 <= x < y)
    log = spark.createDataFrame([(10, "a"), (40, "b"), (41, "c")], "x long, v string")
    got = {x.p: x.v for x in relops.as_of(p, log, "x", "v", 8).collect()}
    assert got == {i: None if x < 10 else "a" if x < 40 else "b" if x < 41 else "c" for i, x in pts}


def test_salted_join(spark):
    from pyspark.sql import functions as F

    left = spark.createDataFrame([(1, i) for i in range(100)] + [(2, 0)], "k long, v long")
    right = spark.createDataFrame([(1, "a"), (2, "b"), (3, "c")], "k long, w string")
    out = relops.salted_join(left, right, "k", 8, F.xxhash64("v"))
    assert out.count() == 101 and out.columns == ["k", "v", "w"]


def test_observed_counters(spark, sf):
    from postpool.plans import catalog

    df, seen = relops.observed(catalog.QUERIES["work_counters_wand"](spark, sf), "work", "segments_decoded", "pivots")
    rows = df.collect()
    assert seen.get == {"rows": len(rows), "segments_decoded": sum(r.segments_decoded for r in rows), "pivots": sum(r.pivots for r in rows)}


def test_sinks(spark, sf, tmp_path):
    io.write_json(spark.range(3), f"{tmp_path}/j")
    assert spark.read.json(f"{tmp_path}/j").count() == 3
    docs = io.read_table(spark, sf, "documents").select("doc_id", "text")
    docs.write.parquet(f"{tmp_path}/d")
    stream = spark.readStream.schema("doc_id long, text string").parquet(f"{tmp_path}/d")
    q = stream.select("doc_id").writeStream.format("memory").queryName("pp_sink").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("pp_sink").count() == docs.count()
    stream.where("doc_id = 0").select("doc_id").writeStream.format("console").trigger(availableNow=True).start().awaitTermination()
