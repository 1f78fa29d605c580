import numpy as np
import pytest
from pyspark.sql import functions as F

from postpool.config import IndexConfig
from postpool.functions import codec
from postpool.operators.index import build_index
from postpool.plans import catalog, support
from postpool.sources.io import read_table
from postpool.streaming import stream

CFG = IndexConfig(block=4, cap_log2=2, df_threshold=3)
STEEP = IndexConfig(block=4, cap_log2=2)


def source(spark, path):
    return spark.readStream.schema("doc_id long, text string").option("maxFilesPerTrigger", 1).parquet(path)


@pytest.mark.parametrize("codec", ["raw", "vbyte"])
def test_stream_equals_batch(spark, sf, tmp_path, codec):
    """Blocks, addresses, links and the dictionary of the stream are those of the batch index, byte by byte."""
    docs = read_table(spark, sf, "documents").select("doc_id", "text").where("doc_id < 50")
    stream.split_for_stream(docs, f"{tmp_path}/in", 3)
    stream.run(source(spark, f"{tmp_path}/in"), CFG, f"{tmp_path}/out", f"{tmp_path}/state", buffer_codec=codec)
    n = spark.read.parquet(f"{tmp_path}/out").count()
    stream.run(source(spark, f"{tmp_path}/in"), CFG, f"{tmp_path}/out", f"{tmp_path}/state", buffer_codec=codec)  # nothing new: a restart repeats nothing
    assert spark.read.parquet(f"{tmp_path}/out").count() == n
    dictionary, segments = stream.finish(spark, f"{tmp_path}/out", f"{tmp_path}/state", CFG, codec)
    ix = build_index(docs, CFG)
    names = ["term", "seg_no", "group_no", "n_docs", "first_doc", "last_doc", "n_bytes", "addr", "next_addr", "is_head", "is_tail", "d_block", "f_block", "p_blocks"]
    rows = lambda df: sorted((tuple(r) for r in df.select(*names).collect()), key=lambda r: r[:2])
    assert rows(segments) == rows(ix.segments)
    ends = {r.term: r.addr for r in ix.segments.where("is_tail").collect()}
    got = {r.term: (r.term_id, r.df, r.tail_addr) for r in dictionary.collect()}
    assert got == {r.term: (r.term_id, r.df, ends[r.term]) for r in ix.dictionary.collect()}


def test_squeezed_buffers_are_smaller(spark, sf, tmp_path):
    docs = read_table(spark, sf, "documents").select("doc_id", "text").where("doc_id < 20")
    stream.split_for_stream(docs, f"{tmp_path}/in", 2)
    sizes = {}
    for codec in ("raw", "vbyte"):
        stream.run(source(spark, f"{tmp_path}/in"), CFG, f"{tmp_path}/out-{codec}", f"{tmp_path}/state-{codec}", buffer_codec=codec)
        sizes[codec] = stream.state_bytes(spark, f"{tmp_path}/state-{codec}", codec).first()[0]
    assert 0 < sizes["vbyte"] < sizes["raw"] / 2
    assert list(stream.unsqueeze(stream.squeeze([3, 9, 500], [[1, 4], [7], [200, 70000]]))) == [(3, [1, 4]), (9, [7]), (500, [200, 70000])]


def test_late_document_gets_the_next_number(spark, tmp_path):
    for rows in [[(5, "x"), (6, "x")], [(2, "x")]]:
        spark.createDataFrame(rows, "doc_id long, text string").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        stream.run(source(spark, f"{tmp_path}/in"), CFG, f"{tmp_path}/out", f"{tmp_path}/state")
    assert sorted(r.doc_id for r in stream.buffered(spark, f"{tmp_path}/state").collect()) == [5, 6, 7]


def test_queries_between_batches(spark, tmp_path):
    """A query sees flushed segments and live buffers, and only terms that have reached the threshold by then."""
    texts = ["a b", "a", "a b", "a b c", "a", "b c", "a b", "a"]
    q = spark.createDataFrame([(1, ["a", "b"]), (2, ["b"]), (3, ["c", "a"]), (4, ["zz"])], "query_id long, terms array<string>")
    seen = 0
    for step in ([0, 1, 2], [3, 4, 5], [6, 7]):
        spark.createDataFrame([(i, texts[i]) for i in step], "doc_id long, text string").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        stream.run(source(spark, f"{tmp_path}/in"), CFG, f"{tmp_path}/out", f"{tmp_path}/state")
        seen += len(step)
        docs = {t: {i for i in range(seen) if t in texts[i].split()} for t in "abc"}
        docs = {t: d for t, d in docs.items() if len(d) >= CFG.df_threshold}
        want = sorted((r.query_id, i) for r in q.collect() if all(t in docs for t in r.terms) for i in set.intersection(*(docs[t] for t in r.terms)))
        assert sorted(map(tuple, stream.answers(spark, f"{tmp_path}/out", f"{tmp_path}/state", CFG, q).collect())) == want
        everything = sorted((r.term, r.doc_id) for r in stream.visible(spark, f"{tmp_path}/out", f"{tmp_path}/state", CFG).collect())
        assert everything == sorted((t, i) for i in range(seen) for t in texts[i].split())


def test_watermark_drops_late_aggregates_only(spark, tmp_path):
    path = f"{tmp_path}/ev"
    spark.sql("SELECT timestamp'2024-01-01 10:00:00' AS ts, 1 AS v UNION ALL SELECT timestamp'2024-01-01 15:00:00', 1").coalesce(1).write.mode("append").parquet(path)
    schema = "ts timestamp, v int"

    def counted():
        e = spark.readStream.schema(schema).parquet(path).withWatermark("ts", "1 hour")
        return e.groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))

    run = lambda: counted().writeStream.format("parquet").option("path", f"{tmp_path}/o").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start().awaitTermination()
    run()
    spark.sql("SELECT timestamp'2024-01-01 10:30:00' AS ts, 1 AS v UNION ALL SELECT timestamp'2024-01-01 20:00:00', 1").coalesce(1).write.mode("append").parquet(path)
    run()
    rows = {str(r.window.start)[11:13]: r.n for r in spark.read.parquet(f"{tmp_path}/o").collect()}
    assert rows["10"] == 1


def test_stream_dedup_and_static_join(spark, sf, tmp_path):
    docs = read_table(spark, sf, "documents").select("doc_id", "text")
    docs.repartition(3).write.parquet(f"{tmp_path}/in")
    labels = read_table(spark, sf, "labels")
    s = spark.readStream.schema("doc_id long, text string").parquet(f"{tmp_path}/in")
    out = s.withColumn("ts", F.timestamp_seconds("doc_id")).withWatermark("ts", "10 days").dropDuplicatesWithinWatermark(["text"]).join(labels, "doc_id")
    rows = support.run_stream(out.select("doc_id", "text", "quality"), "dedup")
    assert rows.select("text").distinct().count() == rows.count() <= docs.select("text").distinct().count()


def test_state_is_of_parts_not_of_terms(spark, sf, tmp_path):
    """A micro-batch calls for parts of the vocabulary."""
    docs = read_table(spark, sf, "documents").select("doc_id", "text").where("doc_id < 60")
    stream.split_for_stream(docs, f"{tmp_path}/in", 3)
    stream.run(source(spark, f"{tmp_path}/in"), CFG, f"{tmp_path}/out", f"{tmp_path}/state")
    state = spark.read.format("statestore").option("stateVarName", "numbers").load(f"{tmp_path}/state")
    about = {r.term: r for r in stream.numbers(spark, f"{tmp_path}/state", CFG).collect()}
    assert 0 < state.count() <= stream.PARTS < len(about)
    lists = {}
    for r in catalog.P.build_postings(docs).collect():
        lists.setdefault(r.term, []).append(r.doc_id)
    held = {}
    for r in stream.buffered(spark, f"{tmp_path}/state").collect():
        held.setdefault(r.term, []).append(r.doc_id)
    assert about.keys() == lists.keys()
    for term, docs_ in lists.items():
        docs_, r, end, groups = sorted(docs_), about[term], 0, 0
        while end + (CFG.block << min(groups, CFG.cap)) <= len(docs_):
            end, groups = end + (CFG.block << min(groups, CFG.cap)), groups + 1
        assert (r.seen, r.n, r.groups, r.segments, r.last, r.first_doc) == (len(docs_), len(docs_) - end, groups, end // CFG.block, docs_[-1], docs_[0])
        assert sorted(held.get(term, [])) == docs_[end:]


def test_groups_of_long_lists():
    seen = np.arange(0, 3000)
    groups = stream.full_groups(seen, STEEP)
    ends = stream.group_ends(groups, STEEP)
    assert (ends <= seen).all() and (stream.group_ends(groups + 1, STEEP) > seen).all()
    assert stream.group_ends(np.arange(6), STEEP).tolist() == [0, 4, 12, 28, 44, 60]


@pytest.mark.parametrize("kind", ["raw", "vbyte"])
def test_chunks_give_lists_back(kind):
    lists = stream.Lists(["é", "b"], np.array([2, 1]), np.array([-3, 5, 1 << 40]), np.array([1, 2, 1]), np.array([1, 70000, 3, 128]))
    back = stream.Lists.unpacked(*lists.packed(kind), kind)
    assert back.terms == lists.terms and all((getattr(back, c) == getattr(lists, c)).all() for c in ("counts", "docs", "tfs", "gaps"))
    parts = list(lists.cut(2))
    assert [p.terms for p in parts] == [["é"], ["b"]] and parts[1].docs.tolist() == [1 << 40] and parts[1].gaps.tolist() == [128]


def test_late_documents_of_one_batch(spark, tmp_path):
    """Late documents take the next numbers, list by list, and others keep theirs."""
    for rows in [[(5, "x y"), (9, "x")], [(2, "x y"), (3, "x"), (20, "x y z"), (20, "z")]]:
        spark.createDataFrame(rows, "doc_id long, text string").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        stream.run(source(spark, f"{tmp_path}/in"), IndexConfig(block=16, df_threshold=3), f"{tmp_path}/out", f"{tmp_path}/state", buffer_codec="vbyte")
    got = sorted((r.term, r.doc_id) for r in stream.buffered(spark, f"{tmp_path}/state", "vbyte").collect())
    assert got == [("x", 5), ("x", 9), ("x", 10), ("x", 11), ("x", 20), ("y", 5), ("y", 6), ("y", 20), ("z", 20), ("z", 21)]


def test_variable_bytes_of_all_sizes():
    values = np.array([0, 1, 127, 128, 16383, 16384, (1 << 35) + 5, (1 << 62) + 7, 3])
    data = codec.vbyte_encode(values)
    assert codec.vbyte_decode(data).tolist() == values.tolist() and len(data) == 1 + 1 + 1 + 2 + 2 + 3 + 6 + 9 + 1
    assert codec.vbyte_encode([]) == b"" and len(codec.vbyte_decode(b"")) == 0


def test_many_tasks_read_a_file(spark, tmp_path):
    docs = spark.range(4000).select(F.col("id").alias("doc_id"), F.concat_ws(" ", *(F.sha2((F.col("id") * 100 + i).cast("string"), 512) for i in range(20))).alias("text"))
    stream.split_for_stream(docs, f"{tmp_path}/in", 1)
    rows = spark.read.schema("doc_id long, text string").parquet(f"{tmp_path}/in")
    assert len(rows.inputFiles()) == 1 and rows.rdd.getNumPartitions() > 1
    assert sum(r.n > 0 for r in rows.groupBy(F.spark_partition_id()).agg(F.count(F.lit(1)).alias("n")).collect()) > 1
