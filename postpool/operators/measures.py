"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, functions as F

from ..config import IndexConfig
from ..functions import codec, schedule
from . import pool

#: Two-sided 95% points of Student's t by degrees of freedom (fixed values).
T95 = {1: 12.706, 2: 4.303, 3: 3.182, 4: 2.776, 5: 2.571, 6: 2.447, 7: 2.365, 8: 2.306, 9: 2.262}


def buffer_memory(dictionary: DataFrame, cfg: IndexConfig, caps=range(8)) -> DataFrame:
    """(cap, docid_bytes, tf_bytes, pos_bytes, ratio_to_1b): all kept terms at their largest buffer at once."""
    b = cfg.block
    caps_df = dictionary.sparkSession.range(1).select(F.explode(F.array(*(F.lit(c).cast("long") for c in caps))).alias("cap"))
    rows = dictionary.select("df", "cf").join(F.broadcast(caps_df))
    blocks = F.least(schedule.power_of_two(F.col("cap")), schedule.power_of_two(schedule.log2_floor(F.floor(F.col("df") / F.lit(b)).cast("long") + 1)))
    rows = rows.withColumn("l", blocks)
    ints = 4 * b * F.col("l")
    pos = 4 * b * F.ceil(F.least(F.col("df"), b * F.col("l")) * (F.col("cf") / F.col("df")) / b)
    out = rows.groupBy("cap").agg(F.sum(ints).alias("docid_bytes"), F.sum(ints).alias("tf_bytes"), F.sum(pos).cast("long").alias("pos_bytes"))
    total = F.col("docid_bytes") + F.col("tf_bytes") + F.col("pos_bytes")
    base = out.where("cap = 0").select(total.alias("base"))
    return out.join(F.broadcast(base)).select("cap", "docid_bytes", "tf_bytes", "pos_bytes", F.round(total / F.col("base"), 6).alias("ratio_to_1b"))


def pool_size(encoded: DataFrame) -> DataFrame:
    """(part, bytes): docids, tfs, positions, and what packing adds, in one pass over the heads of compressed blocks."""
    sums = pool.block_shapes(encoded).groupBy("part").agg(F.sum("n_bytes").alias("bytes"), F.count(F.lit(1)).alias("n"))
    of = lambda value, *parts: F.sum(F.when(F.col("part").isin(*parts), F.col(value)))
    row = sums.agg(*(of("bytes", p).alias(p) for p in "DFP"), (F.coalesce(F.sum("n"), F.lit(0)) * pool.LENGTH).alias("lengths"), (F.coalesce(of("n", "D"), F.lit(0)) * pool.POINTER).alias("pointers"))
    return row.select(F.expr("stack(5, 'D', D, 'F', F, 'P', P, 'lengths', lengths, 'pointers', pointers) AS (part, bytes)")).where("bytes IS NOT NULL")


def buffer_classes(dictionary: DataFrame, block: int, last_bar: str = "series") -> DataFrame:
    """(class_blocks, n_terms, share)."""
    rows = dictionary.groupBy(schedule.buffer_class(F.col("df"), block, last_bar=last_bar).alias("class_blocks")).agg(F.count(F.lit(1)).alias("n_terms"))
    total = rows.agg(F.sum("n_terms").alias("t"))
    return rows.join(F.broadcast(total)).select("class_blocks", "n_terms", F.round(F.col("n_terms") / F.col("t"), 6).alias("share"))


def segment_size_by_class(segments: DataFrame, dictionary: DataFrame, block: int) -> DataFrame:
    """(class, n_segments, avg_bytes) for lists of class 1b, 2b and beyond."""
    c = schedule.buffer_class(F.col("df"), block)
    name = F.when(c == 1, "1b").when(c == 2, "2b").otherwise(">2b")
    rows = segments.select("term", "n_bytes").join(dictionary.select("term", name.alias("class")), "term")
    return rows.groupBy("class").agg(F.count(F.lit(1)).alias("n_segments"), F.round(F.avg("n_bytes"), 6).alias("avg_bytes"))


def vocabulary(dictionary: DataFrame, thresholds: list[int]) -> DataFrame:
    """(threshold, terms, postings, tokens) of an unpruned dictionary."""
    spark = dictionary.sparkSession
    ts = spark.range(1).select(F.explode(F.array(*(F.lit(t).cast("long") for t in thresholds))).alias("threshold"))
    rows = dictionary.select("df", "cf").join(F.broadcast(ts), F.col("df") >= F.col("threshold"))
    return rows.groupBy("threshold").agg(F.count(F.lit(1)).alias("terms"), F.sum("df").alias("postings"), F.sum("cf").alias("tokens"))


def buffer_codecs(segments: DataFrame) -> DataFrame:
    """(codec, part, bytes): buffered values raw, in variable bytes, and in Rice codes with each buffer's own parameter."""
    arrays = {"D": pool.doc_gaps(F.col("docs")), "F": F.col("tfs"), "P": F.col("gaps")}
    rows = segments.select(F.explode(F.array(*(F.struct(F.lit(p).alias("part"), F.transform(a, lambda v: v.cast("long")).alias("v")) for p, a in arrays.items()))).alias("x")).select("x.part", "x.v")
    total = lambda f: F.aggregate(F.transform("v", f), F.lit(0).cast("long"), lambda a, x: a + x)
    rows = rows.withColumn("s", F.floor(total(lambda v: v) / F.size("v")).cast("long"))
    rows = rows.withColumn("k", F.when(F.col("s") > 0, schedule.log2_floor(F.col("s"))).otherwise(0).cast("int"))
    rice = F.ceil(F.aggregate("v", F.lit(0).cast("long"), lambda a, v: a + F.floor(v / schedule.power_of_two(F.col("k"))).cast("long") + 1 + F.col("k")) / F.lit(8))
    sized = rows.select("part", (4 * F.size("v")).cast("long").alias("raw"), total(codec.vbyte_size).alias("vbyte"), rice.cast("long").alias("rice"))
    sums = sized.groupBy("part").agg(*(F.sum(c).alias(c) for c in ("raw", "vbyte", "rice")))
    return sums.select("part", F.expr("stack(3, 'raw', raw, 'vbyte', vbyte, 'rice', rice) AS (codec, bytes)")).select("codec", "part", "bytes")


def recall_at_k(found: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(query_id, k, found, hit, recall) against the true first k."""
    truth = truth.where(F.col("rank") <= k).select("query_id", "doc_id")
    both = truth.join(found.where(F.col("rank") <= k).select("query_id", "doc_id").withColumn("h", F.lit(1)), ["query_id", "doc_id"], "left")
    out = both.groupBy("query_id").agg(F.count(F.lit(1)).alias("found"), F.count("h").alias("hit"))
    return out.select("query_id", F.lit(k).cast("long").alias("k"), "found", "hit", F.round(F.col("hit") / F.col("found"), 6).alias("recall"))


def same_sets(a: DataFrame, b: DataFrame) -> DataFrame:
    """(only_a, only_b): sizes of the differences."""
    return a.exceptAll(b).agg(F.count(F.lit(1)).alias("only_a")).join(b.exceptAll(a).agg(F.count(F.lit(1)).alias("only_b")))


def confidence(trials: list[float]) -> tuple[float, float]:
    """(mean, half width of the 95% interval)."""
    n = len(trials)
    mean = sum(trials) / n
    if n < 2:
        return mean, 0.0
    return mean, T95.get(n - 1, 1.96) * math.sqrt(sum((x - mean) ** 2 for x in trials) / (n - 1) / n)


def overlap(a: tuple[float, float], b: tuple[float, float]) -> bool:
    return abs(a[0] - b[0]) <= a[1] + b[1] + 1e-12


def slowdowns(latencies: DataFrame, reference: str = "contiguous") -> DataFrame:
    """(algo, collection, set, layout, slowdown, overlaps) of (…, mean, half) against the reference layout."""
    keys = ["algo", "collection", "set"]
    base = latencies.where(F.col("layout") == reference).select(*keys, F.col("mean").alias("m0"), F.col("half").alias("h0"))
    rows = latencies.where(F.col("layout") != reference).join(base, keys)
    touch = F.round(F.abs(F.col("mean") - F.col("m0")), 6) <= F.round(F.col("half") + F.col("h0"), 6)
    return rows.select(*keys, "layout", F.round(F.col("mean") / F.col("m0") - 1, 6).alias("slowdown"), touch.alias("overlaps"))


def timed(run: Callable[[], object], trials: int = 5) -> list[float]:
    """Wall milliseconds of each trial."""
    out = []
    for _ in range(trials):
        t = time.perf_counter()
        run()
        out.append((time.perf_counter() - t) * 1e3)
    return out


def capacity(memory: DataFrame, pool_bytes: DataFrame, n_docs: DataFrame) -> DataFrame:
    """(cap, bytes_per_doc, docs_per_gib): documents that fit in a GiB of pool and buffers."""
    rows = memory.join(F.broadcast(pool_bytes)).join(F.broadcast(n_docs))
    per = (F.col("docid_bytes") + F.col("tf_bytes") + F.col("pos_bytes") + F.col("pool_bytes")) / F.col("n_docs")
    return rows.select("cap", F.round(per, 6).alias("bytes_per_doc"), F.floor(F.lit(float(1 << 30)) / per).cast("long").alias("docs_per_gib"))


def jumps_of_queries(segments: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, segments, jumps): segments of a query's lists, and links between them that leave the spot."""
    terms = queries.select("query_id", F.explode(F.array_distinct("terms")).alias("term"))
    gap = F.col("next_addr") - F.col("addr") - F.col("n_bytes")
    lists = segments.groupBy("term").agg(F.count(F.lit(1)).alias("s"), F.coalesce(F.sum((gap != 0).cast("long")), F.lit(0)).alias("j"))
    return lists.join(F.broadcast(terms), "term").groupBy("query_id").agg(F.sum("s").alias("segments"), F.sum("j").alias("jumps"))


def work_between_jumps(stretches: DataFrame, dictionary: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, postings, stretches, postings_per_stretch): a list is read in stretches of side by side segments, and a
    stretch's postings are what is decoded before the next jump."""
    terms = queries.select("query_id", F.explode(F.array_distinct("terms")).alias("term"))
    lists = stretches.select("term", "groups").join(dictionary.select("term", "df"), "term").join(F.broadcast(terms), "term")
    sums = lists.groupBy("query_id").agg(F.sum("df").alias("postings"), F.sum("groups").alias("stretches"))
    return sums.select("query_id", "postings", "stretches", F.round(F.col("postings") / F.col("stretches"), 6).alias("postings_per_stretch"))


def seen_by_queries(ix, queries: DataFrame) -> DataFrame:
    """(query_id, docs_visible, list_segments, list_postings, buffered_postings, postings_per_doc) of (query_id, terms,
    at): a query that arrives with document `at` sees groups flushed by then, and buffers."""
    terms = queries.select("query_id", "at", F.explode(F.array_distinct("terms")).alias("term"))
    events = pool.events_of_segments(ix.blocks, ix.cfg).select("shard", "term", "group_no", "trigger_doc")
    groups = ix.placed.join(ix.blocks.select("shard", "term_id", "seg_no", "n_docs"), ["shard", "term_id", "seg_no"]).groupBy("shard", "term", "group_no").agg(F.count(F.lit(1)).alias("s"), F.sum("n_docs").alias("p"))
    written = events.join(groups, ["shard", "term", "group_no"]).join(F.broadcast(terms), "term").where("trigger_doc <= at").groupBy("query_id").agg(F.sum("s").alias("list_segments"), F.sum("p").alias("flushed"))
    there = ix.postings.select("term", "doc_id").join(F.broadcast(terms), "term").where("doc_id <= at").groupBy("query_id").agg(F.count(F.lit(1)).alias("list_postings"))
    out = queries.select("query_id", (F.col("at") + 1).alias("docs_visible")).join(there, "query_id", "left").join(written, "query_id", "left").fillna(0)
    return out.select("query_id", "docs_visible", "list_segments", "list_postings", (F.col("list_postings") - F.col("flushed")).alias("buffered_postings"), F.round(F.col("list_postings") / F.col("docs_visible"), 6).alias("postings_per_doc"))
