"""Queries of methods, baselines, measures and workloads with their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..config import IndexConfig
from ..functions import analyze, schedule
from ..operators.index import serve
from ..operators import baselines, kernels, measures, pool, postings as P, retrieval as R
from ..runtime import materialise
from ..sources.io import read_table
from . import workloads as W
from .oracle import WORDS, twin

CFG = IndexConfig(block=16, cap_log2=5, df_threshold=10, n_shards=1)
SEARCH = IndexConfig(block=16, cap_log2=5, df_threshold=10, n_shards=4)
K = 10

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return add


def docs(spark, sf_dir):
    return W.collection(spark, sf_dir)


def index(spark, sf_dir, cfg=CFG, name="documents"):
    return W.index_for(spark, sf_dir, cfg, name)


# ---------------------------------------------------------------- indexing


@query("tokens_count", twin("SELECT doc_id, CAST(len(w) AS BIGINT) AS n_tokens, CAST(len(list_distinct(w)) AS BIGINT) AS n_terms FROM docw"))
def tokens_count(spark, sf_dir):
    w = docs(spark, sf_dir).select("doc_id", analyze.words(F.col("text")).alias("w"))
    return w.select("doc_id", F.size("w").cast("long").alias("n_tokens"), F.size(F.array_distinct("w")).cast("long").alias("n_terms"))


POSTINGS_SQL = twin("SELECT term, doc_id, tf, first_pos, last_pos, pos_sum FROM post")
KEPT_SQL = twin("SELECT term, doc_id, tf, first_pos, last_pos, pos_sum FROM kept")


def posting_digest(rows):
    return rows.select("term", "doc_id", F.col("tf").cast("long").alias("tf"), F.get("positions", F.lit(0)).cast("long").alias("first_pos"), F.element_at("positions", -1).cast("long").alias("last_pos"), F.aggregate("positions", F.lit(0).cast("long"), lambda a, x: a + x).alias("pos_sum"))


@query("postings", POSTINGS_SQL)
def postings(spark, sf_dir):
    return posting_digest(P.build_postings(docs(spark, sf_dir)))


@query("postings_of_tokens", POSTINGS_SQL)
def postings_of_tokens(spark, sf_dir):
    return posting_digest(P.postings_of_tokens(P.tokenize(docs(spark, sf_dir))))


@query("dictionary", twin("SELECT term_id, term, df, cf, first_doc, first_pos FROM dict"))
def dictionary(spark, sf_dir):
    return P.build_dictionary(P.build_postings(docs(spark, sf_dir)), CFG).select("term_id", "term", "df", "cf", "first_doc", "first_pos")


@query("buffer_rank", twin("SELECT term, doc_id, rank, seg_no, slot FROM rseg"))
def buffer_rank(spark, sf_dir):
    rows = P.build_postings(docs(spark, sf_dir))
    return pool.with_groups(P.rank_postings(rows, P.build_dictionary(rows, CFG)), CFG).select("term", "doc_id", "rank", "seg_no", "slot")


@query("flush_groups", twin("SELECT term, group_no, min(rank) AS first_rank, max(rank) AS last_rank, count(DISTINCT seg_no) AS n_segments FROM rgrp GROUP BY term, group_no"))
def flush_groups(spark, sf_dir):
    rows = pool.with_groups(index(spark, sf_dir).postings, CFG)
    out = rows.groupBy("term", "group_no").agg(F.min("rank").alias("first_rank"), F.max("rank").alias("last_rank"))
    return out.withColumn("n_segments", schedule.segment_no(F.col("last_rank"), CFG.block) - schedule.segment_no(F.col("first_rank"), CFG.block) + 1)


@query("flush_events", twin("SELECT term, group_no, trigger_doc, trigger_pos FROM events_"))
def flush_events(spark, sf_dir):
    return pool.flush_events(index(spark, sf_dir).postings, CFG).select("term", "group_no", "trigger_doc", "trigger_pos")


@query("final_flush", twin("SELECT term, count(*) AS n_left, count(DISTINCT seg_no) AS n_segments FROM rgrp r WHERE NOT EXISTS (SELECT 1 FROM events_ e WHERE e.term = r.term AND e.group_no = r.group_no) GROUP BY term"))
def final_flush(spark, sf_dir):
    return pool.final_flush(index(spark, sf_dir).dictionary, CFG)


CAPS = {"caps": "SELECT m FROM range(0, 8) r(m)", "mspan": "SELECT m, g, n, CAST(coalesce(sum(n) OVER (PARTITION BY m ORDER BY g ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS s0 FROM (SELECT m, g, CAST(pow(2, least(g, m)) AS BIGINT) AS n FROM caps, range(0, 4000) r(g))"}


@query("groups_by_cap", twin("SELECT m AS cap, CAST(sum(ns) AS BIGINT) AS segments, CAST(sum(ng) AS BIGINT) AS groups, CAST(sum(ng) - count(*) AS BIGINT) AS jumps_max, max(lg) AS largest_group FROM (SELECT m, term, sum(sz) AS ns, count(*) AS ng, CAST(max(sz) AS BIGINT) AS lg FROM (SELECT m, term, least(n, (df + {b} - 1) // {b} - s0) AS sz FROM dict JOIN mspan ON s0 < (df + {b} - 1) // {b}) GROUP BY m, term) GROUP BY m", **CAPS))
def groups_by_cap(spark, sf_dir):
    d, out = index(spark, sf_dir).dictionary, None
    for cap in range(8):
        one = pool.schedule_counts(d, CFG.block, cap).select(F.lit(cap).cast("long").alias("cap"), "segments", "groups", (F.col("groups") - F.col("terms")).alias("jumps_max"), F.col("largest_group").cast("long").alias("largest_group"))
        out = one if out is None else out.unionByName(one)
    return out


@query("group_adjacency", twin("SELECT count(*) AS violations FROM (SELECT term, group_no, max(addr + n_bytes) - min(addr) AS span, sum(n_bytes) AS used FROM pooled GROUP BY term, group_no) WHERE span <> used"))
def group_adjacency(spark, sf_dir):
    segs = index(spark, sf_dir).placed
    g = segs.groupBy("term", "group_no").agg((F.max(F.col("addr") + F.col("n_bytes")) - F.min("addr")).alias("span"), F.sum("n_bytes").alias("used"))
    return g.agg(F.coalesce(F.sum((F.col("span") != F.col("used")).cast("long")), F.lit(0)).alias("violations"))


def vocab_sql(ts):
    return twin(f"SELECT t AS threshold, count(*) AS terms, CAST(sum(df) AS BIGINT) AS postings, CAST(sum(cf) AS BIGINT) AS tokens FROM dict1 JOIN (SELECT CAST(unnest({ts}) AS BIGINT) AS t) ON df >= t GROUP BY t")


@query("vocab_threshold", vocab_sql([1, 10]))
def vocab_threshold(spark, sf_dir):
    return measures.vocabulary(P.build_dictionary(P.build_postings(docs(spark, sf_dir)), IndexConfig(df_threshold=1)), [1, 10])


@query("vocab_by_threshold", vocab_sql([1, 5, 10, 50]))
def vocab_by_threshold(spark, sf_dir):
    return measures.vocabulary(P.build_dictionary(P.build_postings(docs(spark, sf_dir)), IndexConfig(df_threshold=1)), [1, 5, 10, 50])


BLOCKS = (8, 16, 64, 128, 256)


@query("segments_by_block", twin(f"SELECT CAST(z AS BIGINT) AS block, CAST(sum((df + z - 1) // z) AS BIGINT) AS segments, CAST(sum(df // z) AS BIGINT) AS full_segments, CAST(sum(CASE WHEN df % z > 0 THEN 1 ELSE 0 END) AS BIGINT) AS short_segments FROM dict, (SELECT unnest({list(BLOCKS)}) AS z) GROUP BY z"))
def segments_by_block(spark, sf_dir):
    d = index(spark, sf_dir).dictionary.select("df", F.explode(F.array(*(F.lit(b).cast("long") for b in BLOCKS))).alias("block"))
    full, short = F.floor(F.col("df") / F.col("block")), (F.col("df") % F.col("block") > 0).cast("long")
    return d.groupBy("block").agg(F.sum(full + short).alias("segments"), F.sum(full).alias("full_segments"), F.sum(short).alias("short_segments"))


@query("position_gaps", twin("SELECT term, doc_id, string_agg(CAST(gap AS VARCHAR), ',' ORDER BY pos) AS gaps FROM gaps GROUP BY term, doc_id"))
def position_gaps(spark, sf_dir):
    return index(spark, sf_dir).postings.select("term", "doc_id", F.array_join(F.transform(analyze.position_gaps(F.col("positions")), lambda x: x.cast("string")), ",").alias("gaps"))


@query("block_sizes", twin("SELECT term, seg_no, part, n_values, CAST(width AS BIGINT) AS width, exceptions, CAST(n_bytes AS BIGINT) AS n_bytes FROM shape"))
def block_sizes(spark, sf_dir):
    return pool.block_shapes(index(spark, sf_dir).blocks)


@query("segment_bytes", twin("SELECT term, seg_no, n_bytes FROM segb"))
def segment_bytes(spark, sf_dir):
    """From the encoded blocks themselves; the twin has the size formula."""
    blocks = F.lit(pool.POINTER) + F.length("d_block") + F.length("f_block") + 2 * pool.LENGTH + F.aggregate("p_blocks", F.lit(0), lambda a, b: a + F.length(b) + pool.LENGTH)
    return index(spark, sf_dir).blocks.select("term", "seg_no", blocks.cast("long").alias("n_bytes"))


@query("segment_bytes_nopos", twin("SELECT term, seg_no, CAST(8 + sum(4 + n_bytes) AS BIGINT) AS n_bytes FROM shape WHERE part <> 'P' GROUP BY term, seg_no"))
def segment_bytes_nopos(spark, sf_dir):
    cfg = IndexConfig(block=16, positional=False)
    return pool.segment_bytes(pool.assemble(index(spark, sf_dir).postings, cfg), cfg).select("term", "seg_no", "n_bytes")


@query("segment_roundtrip", KEPT_SQL)
def segment_roundtrip(spark, sf_dir):
    return posting_digest(pool.decode(index(spark, sf_dir).blocks))


@query("traverse_lists", KEPT_SQL)
def traverse_lists(spark, sf_dir):
    """Lists by their links: from each head the next pointers are walked, and segments are decoded as they are reached."""
    return posting_digest(pool.traverse(index(spark, sf_dir).segments))


LAYOUTS = (("linked", 0), ("capped", 5), ("contiguous", 5))


@query("pool_addresses", "SELECT 'linked' AS layout, * FROM (" + twin("SELECT term, seg_no, addr, n_bytes FROM pooled", cap=0) + ") UNION ALL SELECT 'capped', * FROM (" + twin("SELECT term, seg_no, addr, n_bytes FROM pooled") + ") UNION ALL SELECT 'contiguous', * FROM (" + twin("SELECT term, seg_no, addr, n_bytes FROM contig") + ")")
def pool_addresses(spark, sf_dir):
    ix, out = index(spark, sf_dir), None
    for layout, cap in LAYOUTS:
        one = ix.addresses(layout, cap).select(F.lit(layout).alias("layout"), "term", "seg_no", "addr", "n_bytes")
        out = one if out is None else out.unionByName(one)
    return out


@query("pool_links", twin("SELECT term, seg_no, addr, lead(addr) OVER w AS next_addr, seg_no = 0 AS is_head, lead(addr) OVER w IS NULL AS is_tail FROM pooled WINDOW w AS (PARTITION BY term ORDER BY seg_no)"))
def pool_links(spark, sf_dir):
    return index(spark, sf_dir).placed.select("term", "seg_no", "addr", "next_addr", "is_head", "is_tail")


CONTIGUOUS_SQL = twin("SELECT term, seg_no, addr FROM contig")


@query("pool_contiguous", CONTIGUOUS_SQL)
def pool_contiguous(spark, sf_dir):
    return index(spark, sf_dir).addresses("contiguous").select("term", "seg_no", "addr")


@query("two_pass_layout", CONTIGUOUS_SQL)
def two_pass_layout(spark, sf_dir):
    """Pass 1 adds up each term's bytes, pass 2 fills the exact space from each term's start."""
    from ..operators.numbering import running_sum

    segs = index(spark, sf_dir).placed.select("term", "term_id", "seg_no", "n_bytes")
    sizes = segs.groupBy("term_id").agg(F.sum("n_bytes").alias("size"))
    starts = running_sum(sizes, F.col("size"), [], schedule.div(F.col("term_id"), P.RANGE), [F.col("term_id")], "base")
    inner = running_sum(segs, F.col("n_bytes"), ["term", "term_id"], schedule.div(F.col("seg_no"), P.RANGE), [F.col("seg_no")], "inside")
    return inner.join(starts.select("term_id", "base"), "term_id").select("term", "seg_no", (F.col("base") + F.col("inside")).alias("addr"))


def _jumps_sql():
    parts = []
    for layout, cap in [("linked", 0), *(("capped", m) for m in range(1, 8)), ("contiguous", 5)]:
        source = "contig" if layout == "contiguous" else "pooled"
        body = f"SELECT '{layout}' AS layout, CAST({cap} AS BIGINT) AS cap, count(nx) AS links, CAST(coalesce(sum(CASE WHEN nx <> addr + n_bytes THEN 1 ELSE 0 END), 0) AS BIGINT) AS jumps, CAST(coalesce(sum(abs(nx - addr - n_bytes)), 0) AS BIGINT) AS jump_bytes FROM (SELECT *, lead(addr) OVER (PARTITION BY term ORDER BY seg_no) AS nx FROM {source})"
        parts.append("SELECT * FROM (" + twin(body, cap=cap) + ")")
    return " UNION ALL ".join(parts)


@query("pool_jumps", _jumps_sql())
def pool_jumps(spark, sf_dir):
    ix, out = index(spark, sf_dir), None
    for layout, cap in [("linked", 0), *(("capped", m) for m in range(1, 8)), ("contiguous", 5)]:
        one = pool.jumps(ix.addresses(layout, cap)).select(F.lit(layout).alias("layout"), F.lit(cap).cast("long").alias("cap"), "links", "jumps", "jump_bytes")
        out = one if out is None else out.unionByName(one)
    return out


@query("pos16_loss", twin("SELECT 'drop' AS policy, count(*) FILTER (len(w) > 65535) AS docs, CAST(coalesce(sum(len(w)) FILTER (len(w) > 65535), 0) AS BIGINT) AS tokens_lost FROM docw UNION ALL SELECT 'truncate', count(*) FILTER (len(w) > 65535), CAST(coalesce(sum(len(w) - 65535) FILTER (len(w) > 65535), 0) AS BIGINT) FROM docw"))
def pos16_loss(spark, sf_dir):
    most, n = 65535, F.col("doc_len")
    s = P.doc_stats(docs(spark, sf_dir)).agg(F.coalesce(F.sum((n > most).cast("long")), F.lit(0)).alias("docs"), F.coalesce(F.sum(F.when(n > most, n)), F.lit(0)).alias("d"), F.coalesce(F.sum(F.when(n > most, n - most)), F.lit(0)).alias("t"))
    return s.select("docs", F.expr("stack(2, 'drop', d, 'truncate', t) AS (policy, tokens_lost)")).select("policy", "docs", "tokens_lost")


@query("short_positions", twin("SELECT policy, count(*) AS postings, CAST(sum(tf) AS BIGINT) AS tokens, CAST(max(p) AS BIGINT) AS max_pos FROM (SELECT policy, doc_id, term, count(*) AS tf, max(pos) AS p FROM (SELECT policy, doc_id, unnest(v) AS term, unnest(range(1, len(v) + 1)) AS pos FROM (SELECT 'truncate' AS policy, doc_id, w[1:255] AS v FROM docw UNION ALL SELECT 'drop', doc_id, CASE WHEN len(w) > 255 THEN [] ELSE w END FROM docw)) GROUP BY policy, doc_id, term) GROUP BY policy"))
def short_positions(spark, sf_dir):
    """The index option for narrow positions, at 8 bits, so that documents here are long enough to feel it."""
    out = None
    for policy in ("truncate", "drop"):
        rows = materialise(P.parsed(docs(spark, sf_dir), cfg=IndexConfig(pos_bits=8, overflow=policy)), "parsed").select("doc_id", F.inline("occ"))
        one = rows.agg(F.count(F.lit(1)).alias("postings"), F.sum("tf").alias("tokens"), F.max(F.array_max("positions")).cast("long").alias("max_pos")).select(F.lit(policy).alias("policy"), "postings", "tokens", "max_pos")
        out = one if out is None else out.unionByName(one)
    return out


@query("buffer_bytes_by_codec", twin("""SELECT codec, part, CAST(sum(bytes) AS BIGINT) AS bytes FROM (
  SELECT 'raw' AS codec, part, 4 * n AS bytes FROM per UNION ALL SELECT 'vbyte', part, vb FROM per UNION ALL SELECT 'rice', part, (bits + 7) // 8 FROM rice) GROUP BY codec, part""",
    per="SELECT term, seg_no, part, count(*) AS n, sum(greatest(1, (bl + 6) // 7)) AS vb, CASE WHEN sum(v) // count(*) > 0 THEN length(bin(CAST(sum(v) // count(*) AS BIGINT))) - 1 ELSE 0 END AS kk FROM lens GROUP BY term, seg_no, part",
    rice="SELECT l.term, l.seg_no, l.part, sum(v // CAST(pow(2, kk) AS BIGINT) + 1 + kk) AS bits FROM lens l JOIN per USING (term, seg_no, part) GROUP BY l.term, l.seg_no, l.part"))
def buffer_bytes_by_codec(spark, sf_dir):
    return measures.buffer_codecs(pool.assemble(index(spark, sf_dir).postings, CFG))


@query("sharded_dictionary", twin("SELECT CAST(doc_id // per AS INTEGER) AS shard, term, count(*) AS df, CAST(sum(tf) AS BIGINT) AS cf FROM kept, (SELECT (max(doc_id) + 4) // 4 AS per FROM documents) GROUP BY ALL"))
def sharded_dictionary(spark, sf_dir):
    rows = index(spark, sf_dir, SEARCH).postings
    return rows.groupBy("shard", "term").agg(F.count(F.lit(1)).alias("df"), F.sum("tf").alias("cf"))


@query("shard_thresholds", twin("SELECT shard, term, df FROM (SELECT CAST(doc_id // per AS INTEGER) AS shard, term, count(*) AS df FROM post, (SELECT (max(doc_id) + 4) // 4 AS per FROM documents) GROUP BY ALL) WHERE df >= 10"))
def shard_thresholds(spark, sf_dir):
    """Separate servers drop terms by their own counts."""
    from dataclasses import replace

    return index(spark, sf_dir, replace(SEARCH, threshold_scope="shard")).dictionary.select("shard", "term", "df")


# ---------------------------------------------------------------- retrieval


def kept_postings(spark, sf_dir):
    return index(spark, sf_dir, SEARCH).postings


@query("svs_set_e", twin("SELECT query_id, doc_id FROM and_e"))
def svs_set_e(spark, sf_dir):
    return kernels.svs(index(spark, sf_dir, SEARCH).served, W.query_set(spark, sf_dir, "E"))


@query("svs_set_w", twin("SELECT query_id, doc_id FROM and_w"))
def svs_set_w(spark, sf_dir):
    return kernels.svs(index(spark, sf_dir, SEARCH).served, W.query_set(spark, sf_dir, "W"))


@query("svs_relational", twin("SELECT query_id, doc_id FROM and_w"))
def svs_relational(spark, sf_dir):
    return R.intersect(kept_postings(spark, sf_dir), W.query_set(spark, sf_dir, "W"))


@query("svs_joins", twin("SELECT query_id, doc_id FROM and_e"))
def svs_joins(spark, sf_dir):
    ix = index(spark, sf_dir, SEARCH)
    return R.intersect_by_joins(ix.postings, ix.dictionary, W.query_set(spark, sf_dir, "E"))


@query("svs_edge", twin("SELECT query_id, doc_id FROM (SELECT qw.query_id, doc_id, count(*) AS n, any_value(need) AS need FROM qw JOIN kept USING (term) JOIN (SELECT query_id, count(*) AS need FROM qw JOIN dict USING (term) GROUP BY query_id) USING (query_id) GROUP BY qw.query_id, doc_id) WHERE n = need"))
def svs_edge(spark, sf_dir):
    """Unknown and dropped terms are skipped instead."""
    return R.intersect(kept_postings(spark, sf_dir), W.query_set(spark, sf_dir, "W"), missing="ignore")


@query("svs_orders", "SELECT CAST(a.l_suppkey AS VARCHAR) AS supplier, b.l_returnflag AS flag, a.l_orderkey AS order_id FROM (SELECT DISTINCT l_suppkey, l_orderkey FROM lineitem) a JOIN (SELECT DISTINCT l_returnflag, l_orderkey FROM lineitem) b USING (l_orderkey)")
def svs_orders(spark, sf_dir):
    """Every supplier list against every flag list, met on the order."""
    lines = read_table(spark, sf_dir, "lineitem")
    a = W.order_lists(lines, "l_suppkey").select(F.col("term").alias("supplier"), "doc_id")
    b = W.order_lists(lines, "l_returnflag").select(F.col("term").alias("flag"), "doc_id")
    return a.join(b, "doc_id").select("supplier", "flag", F.col("doc_id").alias("order_id"))


def weights(spark, sf_dir, queries=None):
    """Of all postings, or of those of the queries' terms."""
    ix = index(spark, sf_dir, SEARCH)
    if queries is None:
        return R.scored(ix.postings, ix.dictionary, ix.stats, ix.coll)
    return R.scored(R.of_queries(ix.postings, queries), F.broadcast(R.of_queries(ix.dictionary, queries)), ix.stats, ix.coll)


@query("term_bounds", twin("SELECT term, df, round(max(wt), 6) AS max_contrib FROM wts GROUP BY term, df"))
def term_bounds(spark, sf_dir):
    return R.term_bounds(weights(spark, sf_dir)).select("term", "df", F.round("max_contrib", 6).alias("max_contrib"))


@query("bm25_topk", twin("SELECT query_id, rank, doc_id, score FROM top_e"))
def bm25_topk(spark, sf_dir):
    q = W.query_set(spark, sf_dir, "E")
    return R.exhaustive(weights(spark, sf_dir, q), q, K)


@query("bm25_topk_w", twin("SELECT query_id, rank, doc_id, score FROM top_w"))
def bm25_topk_w(spark, sf_dir):
    q = W.query_set(spark, sf_dir, "W")
    return R.exhaustive(weights(spark, sf_dir, q), q, K)


def run_wand(spark, sf_dir, which, k=K, by_block=False, counters=False):
    ix = index(spark, sf_dir, SEARCH)
    return kernels.wand(ix.served, W.query_set(spark, sf_dir, which), ix.dictionary, ix.coll, k, by_block, counters)


@query("wand_set_e", twin("SELECT query_id, rank, doc_id, score FROM top_e"))
def wand_set_e(spark, sf_dir):
    return run_wand(spark, sf_dir, "E")


@query("wand_set_w", twin("SELECT query_id, rank, doc_id, score FROM top_w"))
def wand_set_w(spark, sf_dir):
    return run_wand(spark, sf_dir, "W")


@query("wand_top1000", twin("SELECT query_id, rank, doc_id, score FROM top_e", k=1000))
def wand_top1000(spark, sf_dir):
    return run_wand(spark, sf_dir, "E", k=1000)


@query("bmw_final", twin("SELECT query_id, rank, doc_id, score FROM top_e"))
def bmw_final(spark, sf_dir):
    return run_wand(spark, sf_dir, "E", by_block=True)


@query("bmw_stale_recall")
def bmw_stale_recall(spark, sf_dir):
    """Block bounds with the statistics known when a block was flushed: recall may fall below 1."""
    ix = index(spark, sf_dir, SEARCH)
    stale = ix.served.drop("bound").join(R.bounds_at_flush(ix.postings, ix.stats, ix.cfg), ["shard", "term", "seg_no"])
    found = kernels.wand(stale, W.query_set(spark, sf_dir, "E"), ix.dictionary, ix.coll, K, by_block=True)
    return measures.recall_at_k(found, bm25_topk(spark, sf_dir), K)


@query("bmw_refresh_cost", twin("SELECT (SELECT count(*) FROM documents) AS statistics_changes, CAST(coalesce(sum((SELECT max(doc_id) FROM documents) - trigger_doc), 0) AS BIGINT) AS bounds_recomputed FROM (SELECT e.trigger_doc, s.seg_no FROM events_ e JOIN segg s ON s.term = e.term AND s.group_no = e.group_no)"))
def bmw_refresh_cost(spark, sf_dir):
    """Each arriving document changes the statistics, and with them the bound of every segment flushed before."""
    ix = index(spark, sf_dir)
    e = pool.flush_events(ix.postings, CFG)
    n = schedule.power_of_two(F.least(F.col("group_no"), F.lit(CFG.cap)))
    d = docs(spark, sf_dir).agg(F.count(F.lit(1)).alias("statistics_changes"), F.max("doc_id").alias("last"))
    return e.join(F.broadcast(d)).agg(F.max("statistics_changes").alias("statistics_changes"), F.coalesce(F.sum(n * (F.col("last") - F.col("trigger_doc"))), F.lit(0)).alias("bounds_recomputed"))


POINTS = {
    "pts": "SELECT i AS point, (SELECT max(doc_id) + 1 FROM documents) * i // 4 - 1 AS upto FROM range(1, 5) r(i)",
    "pdf": "SELECT point, term, count(*) AS dfp FROM pts JOIN kept ON doc_id <= upto GROUP BY point, term",
    "pco": "SELECT point, count(*) AS n, avg(len(w)) AS a FROM pts JOIN docw ON doc_id <= upto GROUP BY point",
    "gone": "SELECT point, s.term, s.seg_no FROM pts JOIN events_ e ON e.trigger_doc <= upto JOIN segg s ON s.term = e.term AND s.group_no = e.group_no",
    "fresh": "SELECT point, term, seg_no, max(ln(1 + (n - dfp + 0.5) / (dfp + 0.5)) * tf * 1.9 / (tf + 0.9 * (1 - 0.4 + 0.4 * len(w) / a))) AS bd FROM gone JOIN rseg USING (term, seg_no) JOIN pdf USING (point, term) JOIN pco USING (point) JOIN docw USING (doc_id) GROUP BY point, term, seg_no",
}


@query("bmw_refresh_points", twin("SELECT point, count(*) AS segments, round(max(bd), 6) AS max_bound, round(min(bd), 6) AS min_bound FROM fresh GROUP BY point", **POINTS))
def bmw_refresh_points(spark, sf_dir):
    """Bounds of all segments in the pool computed anew at each quarter of the collection, with the statistics then."""
    ix, out = index(spark, sf_dir), None
    top = ix.stats.agg(F.max("doc_id")).first()[0] or 0
    flushed = pool.events_of_segments(ix.blocks, CFG).select("shard", "term", "group_no", "trigger_doc")
    thin = ix.placed.select("shard", "term", "seg_no", "group_no")
    for i in range(1, 5):
        at = (top + 1) * i // 4 - 1
        there = thin.join(flushed.where(F.col("trigger_doc") <= at), ["shard", "term", "group_no"], "left_semi").select("shard", "term", "seg_no")
        fresh = R.bounds_as_of(ix.postings, ix.stats, ix.cfg, at).join(there, ["shard", "term", "seg_no"], "left_semi")
        one = fresh.agg(F.count(F.lit(1)).alias("segments"), F.round(F.max("bound"), 6).alias("max_bound"), F.round(F.min("bound"), 6).alias("min_bound")).select(F.lit(i).cast("long").alias("point"), "segments", "max_bound", "min_bound").where("segments > 0")
        out = one if out is None else out.unionByName(one)
    return out


@query("bmw_refreshed", twin("SELECT query_id, rank, doc_id, score FROM top_e"))
def bmw_refreshed(spark, sf_dir):
    """With bounds refreshed at the last document the answers are exact again."""
    ix = index(spark, sf_dir, SEARCH)
    top = ix.stats.agg(F.max("doc_id")).first()[0] or 0
    fresh = ix.served.drop("bound").join(R.bounds_as_of(ix.postings, ix.stats, ix.cfg, top), ["shard", "term", "seg_no"])
    return kernels.wand(fresh, W.query_set(spark, sf_dir, "E"), ix.dictionary, ix.coll, K, by_block=True)


@query("wand_recall", twin("SELECT query_id, CAST(10 AS BIGINT) AS k, count(*) AS found, count(*) AS hit, CAST(1.0 AS DOUBLE) AS recall FROM top_e GROUP BY query_id"))
def wand_recall(spark, sf_dir):
    return measures.recall_at_k(wand_set_e(spark, sf_dir), bm25_topk(spark, sf_dir), K)


@query("candidates", twin("SELECT query_id, doc_id, score, CAST(len(w) AS BIGINT) AS doc_len, quality, toxic FROM top_e JOIN docw USING (doc_id) LEFT JOIN labels USING (doc_id)"))
def candidates(spark, sf_dir):
    ix = index(spark, sf_dir, SEARCH)
    return R.candidates(bm25_topk(spark, sf_dir), ix.stats, read_table(spark, sf_dir, "labels"), K)


@query("phrase_match", twin("SELECT q.query_id, a.doc_id, count(*) AS n_matches FROM bp q JOIN tok a ON a.term = q.x JOIN tok b ON b.term = q.y AND a.doc_id = b.doc_id AND b.pos = a.pos + 1 GROUP BY q.query_id, a.doc_id", bp="SELECT item_id * 100000 + i AS query_id, w[i] AS x, w[i + 1] AS y FROM (SELECT item_id, w, unnest(range(1, len(w))) AS i FROM bw)"))
def phrase_match(spark, sf_dir):
    return R.phrase(P.build_postings(docs(spark, sf_dir)), W.phrases(spark, sf_dir))


@query("work_by_len", twin("SELECT n_terms, count(*) AS queries, CAST(sum(p) AS BIGINT) AS postings_read, CAST(sum(s) AS BIGINT) AS segments_read, CAST(sum(r) AS BIGINT) AS results FROM (SELECT query_id, count(*) AS n_terms, coalesce(sum(df), 0) AS p, coalesce(sum((df + {b} - 1) // {b}), 0) AS s FROM qw LEFT JOIN dict USING (term) GROUP BY query_id) JOIN (SELECT query_id, count(doc_id) AS r FROM (SELECT DISTINCT query_id FROM qw) LEFT JOIN and_w USING (query_id) GROUP BY query_id) USING (query_id) GROUP BY n_terms"))
def work_by_len(spark, sf_dir):
    ix, q = index(spark, sf_dir, SEARCH), W.query_set(spark, sf_dir, "W")
    lists = R.query_terms(q).join(ix.dictionary.select("term", "df"), "term", "left").groupBy("query_id", "n_terms").agg(F.coalesce(F.sum("df"), F.lit(0)).alias("p"), F.coalesce(F.sum(F.ceil(F.col("df") / F.lit(CFG.block))), F.lit(0)).alias("s"))
    found = kernels.svs(ix.served, q, sizes=True).select("query_id", F.col("n_docs").alias("r"))
    return lists.join(found, "query_id", "left").groupBy("n_terms").agg(F.count(F.lit(1)).alias("queries"), F.sum("p").alias("postings_read"), F.sum("s").alias("segments_read"), F.sum(F.coalesce("r", F.lit(0))).alias("results"))


#: A shard's lists cut into segments; a query's lists there, shortest first; how many of them, in that order, have a
#: document; the segments that a document of all lists before falls into.
SVS_WORK = {
    "spost": "SELECT shard, term, doc_id, (row_number() OVER (PARTITION BY shard, term ORDER BY doc_id) - 1) // {b} AS seg_no FROM (SELECT CAST(doc_id // per AS INTEGER) AS shard, term, doc_id FROM kept, (SELECT (max(doc_id) + 4) // 4 AS per FROM documents))",
    "sseg": "SELECT shard, term, seg_no, min(doc_id) AS a, max(doc_id) AS z, count(*) AS n FROM spost GROUP BY ALL",
    "ssize": "SELECT shard, term, sum(n) AS df FROM sseg GROUP BY ALL",
    "qq": "SELECT 'E' AS qset, query_id, term FROM qe UNION ALL SELECT 'W', query_id, term FROM qw",
    "qshard": "SELECT qset, query_id, shard, term, row_number() OVER (PARTITION BY qset, query_id, shard ORDER BY df, term) AS k, count(df) OVER (PARTITION BY qset, query_id, shard) AS have, count(*) OVER (PARTITION BY qset, query_id, shard) AS want FROM qq CROSS JOIN (SELECT DISTINCT shard FROM ssize) LEFT JOIN ssize USING (shard, term)",
    "qfull": "SELECT * FROM qshard WHERE have = want",
    "qdocs": "SELECT qset, query_id, shard, doc_id, max(k) FILTER (WHERE k = rn) AS prefix FROM (SELECT f.qset, f.query_id, f.shard, f.k, p.doc_id, row_number() OVER (PARTITION BY f.qset, f.query_id, f.shard, p.doc_id ORDER BY f.k) AS rn FROM qfull f JOIN spost p USING (shard, term)) GROUP BY ALL",
    "touched": "SELECT f.qset, f.query_id, f.shard, f.term, g.seg_no, g.n FROM qfull f JOIN sseg g USING (shard, term) WHERE f.k = 1 UNION ALL SELECT DISTINCT f.qset, f.query_id, f.shard, f.term, g.seg_no, g.n FROM qfull f JOIN sseg g USING (shard, term) JOIN qdocs d ON d.qset = f.qset AND d.query_id = f.query_id AND d.shard = f.shard AND d.doc_id BETWEEN g.a AND g.z AND d.prefix >= f.k - 1 WHERE f.k > 1",
    "counted": "SELECT q.qset, q.query_id, coalesce(x.d, 0) AS d, coalesce(x.n, 0) AS n FROM (SELECT DISTINCT qset, query_id FROM qq) q LEFT JOIN (SELECT qset, query_id, count(*) AS d, sum(n) AS n FROM touched GROUP BY qset, query_id) x USING (qset, query_id)",
}


@query("work_counters", twin("SELECT qset AS query_set, query_id, 'svs' AS algo, layout, CAST(d AS BIGINT) AS segments_decoded, CAST(n AS BIGINT) AS postings_decoded FROM counted, (SELECT unnest(['linked', 'capped', 'contiguous']) AS layout)", **SVS_WORK))
def work_counters(spark, sf_dir):
    """Segments and postings that SvS decodes: layouts don't change the work, only where segments lie."""
    return counters_by_layout(spark, sf_dir, "svs").select("query_set", "query_id", "algo", "layout", "segments_decoded", "postings_decoded")


@query("work_counters_wand")
def work_counters_wand(spark, sf_dir):
    """WAND's counters, comparisons and pivots too, which no relation tells."""
    return counters_by_layout(spark, sf_dir, "wand")


def served_in(spark, sf_dir, layout, cap):
    """The served table of a layout, written once a session."""
    ix = index(spark, sf_dir, SEARCH)
    return ix.served if layout == "capped" else W.once(spark, ("served", sf_dir, layout, cap), lambda: serve(ix.relaid(layout, cap), SEARCH.n_shards))


def counters_by_layout(spark, sf_dir, algo):
    ix, out = index(spark, sf_dir, SEARCH), None
    for which in ("E", "W"):
        q = W.query_set(spark, sf_dir, which)
        for layout, cap in LAYOUTS:
            segs = served_in(spark, sf_dir, layout, cap)
            one = kernels.svs(segs, q, counters=True) if algo == "svs" else kernels.wand(segs, q, ix.dictionary, ix.coll, 1000, counters=True)
            one = one.withColumns({"algo": F.lit(algo), "layout": F.lit(layout), "query_set": F.lit(which)})
            out = one if out is None else out.unionByName(one)
    return out


@query("query_jumps", twin("SELECT query_id, CAST(sum(s) AS BIGINT) AS segments, CAST(sum(j) AS BIGINT) AS jumps FROM qe JOIN (SELECT term, count(*) AS s, coalesce(sum(CASE WHEN nx <> addr + n_bytes THEN 1 ELSE 0 END), 0) AS j FROM (SELECT *, lead(addr) OVER (PARTITION BY term ORDER BY seg_no) AS nx FROM pooled) GROUP BY term) USING (term) GROUP BY query_id"))
def query_jumps(spark, sf_dir):
    return measures.jumps_of_queries(index(spark, sf_dir).placed, W.query_set(spark, sf_dir, "E"))


def _hidden_sql():
    parts = []
    for layout, cap in LAYOUTS:
        source = "contig" if layout == "contiguous" else "pooled"
        body = f"SELECT '{layout}' AS layout, query_id, CAST(sum(df) AS BIGINT) AS postings, CAST(sum(j) AS BIGINT) AS stretches, round(sum(df) / sum(j), 6) AS postings_per_stretch FROM qe JOIN dict USING (term) JOIN (SELECT term, sum(CASE WHEN nx IS NULL OR nx <> addr + n_bytes THEN 1 ELSE 0 END) AS j FROM (SELECT *, lead(addr) OVER (PARTITION BY term ORDER BY seg_no) AS nx FROM {source}) GROUP BY term) USING (term) GROUP BY query_id"
        parts.append("SELECT * FROM (" + twin(body, cap=cap) + ")")
    return " UNION ALL ".join(parts)


@query("hidden_latency", _hidden_sql())
def hidden_latency(spark, sf_dir):
    """Postings to decode between two jumps: what a jump's latency can hide behind."""
    ix, out, q = index(spark, sf_dir), None, W.query_set(spark, sf_dir, "E")
    for layout, cap in LAYOUTS:
        one = measures.work_between_jumps(baselines.adjacent_groups(ix.addresses(layout, cap)), ix.dictionary, q).withColumn("layout", F.lit(layout))
        out = one if out is None else out.unionByName(one)
    return out


ARRIVAL = {"arrive": "SELECT query_id, term, (query_id * 7919) % (SELECT max(doc_id) + 1 FROM documents) AS upto FROM qe"}


@query("interleaved_queries", twin("SELECT query_id, upto + 1 AS docs_visible, CAST(coalesce(sum(s), 0) AS BIGINT) AS list_segments, CAST(coalesce(sum(p), 0) AS BIGINT) AS list_postings, CAST(coalesce(sum(p), 0) - coalesce(sum(f), 0) AS BIGINT) AS buffered_postings, round(coalesce(sum(p), 0) / (upto + 1), 6) AS postings_per_doc FROM (SELECT a.query_id, a.upto, (SELECT count(*) FROM kept k WHERE k.term = a.term AND k.doc_id <= a.upto) AS p, (SELECT count(*) FROM events_ e JOIN rgrp r ON r.term = e.term AND r.group_no = e.group_no WHERE e.term = a.term AND e.trigger_doc <= a.upto) AS f, (SELECT count(*) FROM events_ e JOIN segg g ON g.term = e.term AND g.group_no = e.group_no WHERE e.term = a.term AND e.trigger_doc <= a.upto) AS s FROM arrive a) GROUP BY query_id, upto", **ARRIVAL))
def interleaved_queries(spark, sf_dir):
    """Queries that arrive while documents do: what a query's lists hold at that moment, in the pool and in buffers, and
    the work a document costs, free of the index's growth."""
    ix = index(spark, sf_dir)
    top = ix.stats.agg(F.max("doc_id")).first()[0] or 0
    q = W.query_set(spark, sf_dir, "E").withColumn("at", F.col("query_id") * 7919 % (top + 1))
    return measures.seen_by_queries(ix, q)


# ---------------------------------------------------------------- baselines


def all_postings(spark, sf_dir):
    return W.parsed(spark, sf_dir)


def budget_of(rows, percent):
    return max(1, rows.count() * percent // 100)


RUNS = {"runs5": "SELECT doc_id, n, before // (SELECT greatest(1, p * 5 // 100) FROM total) AS run FROM dcum", "runs1": "SELECT doc_id, n, before // (SELECT greatest(1, p * 1 // 100) FROM total) AS run FROM dcum"}


@query("full_flush_runs", twin("SELECT run, min(doc_id) AS first_doc, max(doc_id) AS last_doc, count(DISTINCT term) AS terms, count(*) AS postings FROM post JOIN runs5 USING (doc_id) GROUP BY run", **RUNS))
def full_flush_runs(spark, sf_dir):
    rows = all_postings(spark, sf_dir)
    return baselines.full_flush(rows, budget_of(rows, 5))


@query("merged_runs", twin("SELECT term, doc_id, row_number() OVER (PARTITION BY term ORDER BY doc_id) AS rank FROM post"))
def merged_runs(spark, sf_dir):
    rows = all_postings(spark, sf_dir)
    return baselines.merged_runs(rows, budget_of(rows, 5)).select("term", "doc_id", "rank")


@query("geometric_merges", twin("SELECT a.run, a.j AS target_partition, CAST(sum(b.postings) AS BIGINT) AS postings_rewritten FROM (SELECT run, n, (SELECT CAST(max(i) + 1 AS BIGINT) FROM range(0, 30) r(i) WHERE n % CAST(pow(3, i) AS BIGINT) = 0) AS j FROM numbered_) a JOIN numbered_ b ON b.n <= a.n AND b.n > a.n - a.n % CAST(pow(3, a.j) AS BIGINT) GROUP BY a.run, a.j", numbered_="SELECT run, row_number() OVER (ORDER BY run) AS n, CAST(sum(n) AS BIGINT) AS postings FROM runs1 GROUP BY run", **RUNS))
def geometric_merges(spark, sf_dir):
    rows = all_postings(spark, sf_dir)
    runs = baselines.full_flush(rows, budget_of(rows, 1)).select("run", "postings")
    return baselines.geometric_merges(runs).select("run", "target_partition", "postings_rewritten")


RIVAL = IndexConfig(block=128, df_threshold=1)


def rival(spark, sf_dir, design, percent):
    """Runs and merged segments of a design with a memory of so many percent of all postings, built once a session."""
    rows = all_postings(spark, sf_dir)
    make = {"full": baselines.full_flush_index, "geometric": baselines.geometric_index}[design]
    return W.once(spark, (sf_dir, design, percent), lambda: make(rows, RIVAL, budget_of(rows, percent)))


@query("full_flush_lists", POSTINGS_SQL)
def full_flush_lists(spark, sf_dir):
    """Lists decoded from the final merge of compressed runs."""
    return posting_digest(pool.decode(rival(spark, sf_dir, "full", 5)[1]))


@query("full_flush_run_lists", twin("SELECT run, term, count(*) AS n_postings, CAST((count(*) + 127) // 128 AS BIGINT) AS n_segments, min(doc_id) AS first_doc, max(doc_id) AS last_doc FROM post JOIN runs5 USING (doc_id) GROUP BY run, term", **RUNS))
def full_flush_run_lists(spark, sf_dir):
    """What each run has of each term, from its compressed segments."""
    runs = rival(spark, sf_dir, "full", 5)[0]
    return runs.groupBy("run", "term").agg(F.sum("n_docs").alias("n_postings"), F.count(F.lit(1)).alias("n_segments"), F.min("first_doc").alias("first_doc"), F.max("last_doc").alias("last_doc"))


MERGES = RUNS | {
    "numbered_": "SELECT run, row_number() OVER (ORDER BY run) AS n, CAST(sum(n) AS BIGINT) AS postings FROM runs1 GROUP BY run",
    "merge_": "SELECT run, n, (SELECT CAST(max(i) + 1 AS BIGINT) FROM range(0, 30) r(i) WHERE n % CAST(pow(3, i) AS BIGINT) = 0) AS j FROM numbered_",
    "alive": "SELECT run, n, j, n - n % CAST(pow(3, j) AS BIGINT) AS after FROM merge_ m WHERE NOT EXISTS (SELECT 1 FROM merge_ l WHERE l.n > m.n AND l.j >= m.j)",
    "piece": "SELECT a.run AS part, n.run FROM alive a JOIN numbered_ n ON n.n <= a.n AND n.n > a.after",
}


@query("geometric_lists", POSTINGS_SQL)
def geometric_lists(spark, sf_dir):
    """Lists put together from the partitions that are left in the end."""
    _, merged, log = rival(spark, sf_dir, "geometric", 1)
    left = merged.join(F.broadcast(log.where("stays").select(F.col("run").alias("target"))), "target", "left_semi")
    return posting_digest(pool.decode(left))


@query("geometric_pieces", twin("SELECT term, count(DISTINCT part) AS pieces, count(*) AS postings FROM post JOIN runs1 USING (doc_id) JOIN piece USING (run) GROUP BY term", **MERGES))
def geometric_pieces(spark, sf_dir):
    """Pieces a list is in at the end: one for each partition that has the term."""
    _, merged, log = rival(spark, sf_dir, "geometric", 1)
    left = merged.join(F.broadcast(log.where("stays").select(F.col("run").alias("target"))), "target", "left_semi")
    return left.groupBy("term").agg(F.countDistinct("target").alias("pieces"), F.sum("n_docs").alias("postings"))


@query("rival_postings_written", twin("SELECT 'full' AS design, (SELECT p FROM total) AS in_runs, (SELECT p FROM total) AS in_merges UNION ALL SELECT 'geometric', (SELECT p FROM total), (SELECT CAST(sum(b.postings) AS BIGINT) FROM merge_ a JOIN numbered_ b ON b.n <= a.n AND b.n > a.n - a.n % CAST(pow(3, a.j) AS BIGINT))", **MERGES))
def rival_postings_written(spark, sf_dir):
    """Postings compressed into runs, and again in merges."""
    out = None
    for design, percent in (("full", 5), ("geometric", 1)):
        runs, merged = rival(spark, sf_dir, design, percent)[:2]
        one = runs.agg(F.sum("n_docs").alias("in_runs")).join(merged.agg(F.sum("n_docs").alias("in_merges"))).select(F.lit(design).alias("design"), "in_runs", "in_merges")
        out = one if out is None else out.unionByName(one)
    return out


@query("remerge_copied", twin("SELECT term, CAST(sum(old) AS BIGINT) AS bytes_copied FROM (SELECT term, coalesce(sum(bb) OVER (PARTITION BY term ORDER BY group_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS old FROM (SELECT term, group_no, sum(n_bytes) AS bb FROM segg JOIN segb USING (term, seg_no) GROUP BY term, group_no)) GROUP BY term"))
def remerge_copied(spark, sf_dir):
    return baselines.remerge(index(spark, sf_dir).placed)


def _in_place_sql(slack: str) -> str:
    fold = f"""SELECT term, seg_no, n_bytes AS used, n_bytes + ({slack.format(u='n_bytes')}) AS reserved, CAST(0 AS BIGINT) AS relocations, CAST(0 AS BIGINT) AS copied FROM segb WHERE seg_no = 0
      UNION ALL SELECT s.term, s.seg_no, f.used + s.n_bytes, CASE WHEN f.used + s.n_bytes <= f.reserved THEN f.reserved ELSE f.used + s.n_bytes + ({slack.format(u='(f.used + s.n_bytes)')}) END,
        f.relocations + CASE WHEN f.used + s.n_bytes <= f.reserved THEN 0 ELSE 1 END, f.copied + CASE WHEN f.used + s.n_bytes <= f.reserved THEN 0 ELSE f.used END
      FROM fold f JOIN segb s ON s.term = f.term AND s.seg_no = f.seg_no + 1"""
    text = twin("SELECT 1 FROM segb")
    return text[: text.rindex(" SELECT 1 FROM segb")].replace("WITH ", "WITH RECURSIVE ", 1) + f", fold AS ({fold}) SELECT term, reserved, used, reserved - used AS wasted, relocations, copied FROM fold f WHERE seg_no = (SELECT max(seg_no) FROM segb s WHERE s.term = f.term)"


@query("inplace_constant", _in_place_sql("512"))
def inplace_constant(spark, sf_dir):
    return baselines.in_place(index(spark, sf_dir).placed, lambda used: F.lit(512).cast("long"))


@query("inplace_mean", _in_place_sql("2 * (SELECT CAST(floor(avg(n_bytes)) AS BIGINT) FROM segb)"))
def inplace_mean(spark, sf_dir):
    """Slack of two mean segments."""
    segs = index(spark, sf_dir).placed
    slack = 2 * int(segs.agg(F.avg("n_bytes")).first()[0] or 0)
    return baselines.in_place(segs, lambda used: F.lit(slack).cast("long"))


@query("inplace_proportional", _in_place_sql("{u} // 2"))
def inplace_proportional(spark, sf_dir):
    return baselines.in_place(index(spark, sf_dir).placed, lambda used: F.floor(used / F.lit(2)).cast("long"))


@query("eager_waste", twin("SELECT term, max(used) OVER () AS reserved, used, max(used) OVER () - used AS wasted, CAST(0 AS BIGINT) AS relocations, CAST(0 AS BIGINT) AS copied FROM (SELECT term, CAST(sum(n_bytes) AS BIGINT) AS used FROM segb GROUP BY term)"))
def eager_waste(spark, sf_dir):
    return baselines.eager(index(spark, sf_dir).placed)


@query("size_class_waste", twin("SELECT CAST(sum(pow(2, ceil(log2(n_bytes)))) AS BIGINT) AS allocated, CAST(sum(n_bytes) AS BIGINT) AS used, CAST(sum(pow(2, ceil(log2(n_bytes)))) - sum(n_bytes) AS BIGINT) AS wasted FROM segb"))
def size_class_waste(spark, sf_dir):
    return baselines.size_classes(index(spark, sf_dir).placed)


@query("one_group_limit", twin("SELECT term, (df + {b} - 1) // {b} AS segments, CAST(1 AS BIGINT) AS groups FROM dict"))
def one_group_limit(spark, sf_dir):
    """Buffers that hold everything: the pool is laid out by the final flush alone, and its stretches are counted."""
    return baselines.adjacent_groups(baselines.unbounded_buffers(index(spark, sf_dir).blocks, CFG))


@query("groups_laid_out", twin("SELECT term, count(*) AS segments, CAST(sum(CASE WHEN nx IS NULL OR nx <> addr + n_bytes THEN 1 ELSE 0 END) AS BIGINT) AS groups FROM (SELECT *, lead(addr) OVER (PARTITION BY term ORDER BY seg_no) AS nx FROM pooled) GROUP BY term"))
def groups_laid_out(spark, sf_dir):
    """The same count in the capped layout."""
    return baselines.adjacent_groups(index(spark, sf_dir).placed)


# ---------------------------------------------------------------- measures


MEM = {"bl_": "SELECT m AS cap, least(CAST(pow(2, m) AS BIGINT), CAST(pow(2, length(bin(df // {b} + 1)) - 1) AS BIGINT)) AS l, df, cf FROM dict, range(0, 8) r(m)", "mem": "SELECT cap, CAST(sum(4 * {b} * l) AS BIGINT) AS docid_bytes, CAST(sum(4 * {b} * l) AS BIGINT) AS tf_bytes, CAST(sum(4 * {b} * ceil(least(df, {b} * l) * (cf / df) / {b})) AS BIGINT) AS pos_bytes FROM bl_ GROUP BY cap"}


@query("buffer_memory", twin("SELECT cap, docid_bytes, tf_bytes, pos_bytes, round((docid_bytes + tf_bytes + pos_bytes) / (SELECT docid_bytes + tf_bytes + pos_bytes FROM mem WHERE cap = 0), 6) AS ratio_to_1b FROM mem", **MEM))
def buffer_memory(spark, sf_dir):
    return measures.buffer_memory(index(spark, sf_dir).dictionary, CFG)


def pool_bytes(ix):
    return ix.placed.agg(F.sum("n_bytes").alias("pool_bytes"))


@query("buffer_pool_ratio", twin("SELECT cap, docid_bytes + tf_bytes + pos_bytes AS buffer_bytes, p AS pool_bytes, round((docid_bytes + tf_bytes + pos_bytes) / p, 6) AS ratio FROM mem, (SELECT CAST(sum(n_bytes) AS BIGINT) AS p FROM segb)", **MEM))
def buffer_pool_ratio(spark, sf_dir):
    ix = index(spark, sf_dir)
    total = F.col("docid_bytes") + F.col("tf_bytes") + F.col("pos_bytes")
    return measures.buffer_memory(ix.dictionary, CFG).join(F.broadcast(pool_bytes(ix))).select("cap", total.alias("buffer_bytes"), "pool_bytes", F.round(total / F.col("pool_bytes"), 6).alias("ratio"))


@query("pool_size", twin("SELECT part, CAST(sum(n_bytes) AS BIGINT) AS bytes FROM shape GROUP BY part UNION ALL SELECT 'lengths', 4 * count(*) FROM shape UNION ALL SELECT 'pointers', 8 * count(*) FROM segb"))
def pool_size(spark, sf_dir):
    return measures.pool_size(index(spark, sf_dir).blocks)


CLASS_SQL = "CAST(pow(2, least(7, length(bin(df // {b} + 1)) - 1)) AS BIGINT)"


@query("buffer_classes", twin(f"SELECT c AS class_blocks, count(*) AS n_terms, round(count(*) / (SELECT count(*) FROM dict), 6) AS share FROM (SELECT {CLASS_SQL} AS c FROM dict) GROUP BY c"))
def buffer_classes(spark, sf_dir):
    return measures.buffer_classes(index(spark, sf_dir).dictionary, CFG.block)


@query("segment_size_by_class", twin(f"SELECT class, count(*) AS n_segments, round(avg(n_bytes), 6) AS avg_bytes FROM segb JOIN (SELECT term, CASE {CLASS_SQL} WHEN 1 THEN '1b' WHEN 2 THEN '2b' ELSE '>2b' END AS class FROM dict) USING (term) GROUP BY class"))
def segment_size_by_class(spark, sf_dir):
    ix = index(spark, sf_dir)
    return measures.segment_size_by_class(ix.placed, ix.dictionary, CFG.block)


#: Intervals of the lines' quantities, as of latencies: a return flag stands for the algorithm, a line status for the
#: collection, the ship year's parity for the query set, and the line's number for the layout, 7 being the reference.
#: Whole numbers are summed, so that means don't depend on the order of rows.
LINES_SQL = "SELECT algo, collection, \"set\", layout, s / n AS mean, 1.96 * sqrt(greatest(q - s * s / n, 0) / (n - 1) / n) AS half FROM (SELECT l_returnflag AS algo, l_linestatus AS collection, CAST(extract(year FROM l_shipdate) % 2 AS VARCHAR) AS \"set\", CAST(l_linenumber AS VARCHAR) AS layout, CAST(count(*) AS DOUBLE) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS s, CAST(sum(CAST(l_quantity AS BIGINT) * CAST(l_quantity AS BIGINT)) AS DOUBLE) AS q FROM lineitem GROUP BY ALL) WHERE n > 1"


@query("ci_overlap", f"SELECT a.algo, a.collection, a.set, a.layout, round(a.mean / b.mean - 1, 6) AS slowdown, round(abs(a.mean - b.mean), 6) <= round(a.half + b.half, 6) AS overlaps FROM ({LINES_SQL}) a JOIN ({LINES_SQL}) b ON a.algo = b.algo AND a.collection = b.collection AND a.set = b.set AND b.layout = '7' WHERE a.layout <> '7'")
def ci_overlap(spark, sf_dir):
    """Which groups differ from their reference by more than both 95% intervals, over the lines of orders."""
    q = F.col("l_quantity").cast("long")
    groups = read_table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("algo"), F.col("l_linestatus").alias("collection"), (F.year("l_shipdate") % 2).cast("string").alias("set"), F.col("l_linenumber").cast("string").alias("layout"))
    sums = groups.agg(F.count(F.lit(1)).cast("double").alias("n"), F.sum(q).cast("double").alias("s"), F.sum(q * q).cast("double").alias("q")).where("n > 1")
    half = 1.96 * F.sqrt(F.greatest(F.col("q") - F.col("s") * F.col("s") / F.col("n"), F.lit(0.0)) / (F.col("n") - 1) / F.col("n"))
    return measures.slowdowns(sums.select("algo", "collection", "set", "layout", (F.col("s") / F.col("n")).alias("mean"), half.alias("half")), reference="7")


@query("capacity_estimate", twin("SELECT cap, round((docid_bytes + tf_bytes + pos_bytes + p) / nd, 6) AS bytes_per_doc, CAST(floor(1073741824.0::DOUBLE / ((docid_bytes + tf_bytes + pos_bytes + p) / nd)) AS BIGINT) AS docs_per_gib FROM mem, (SELECT CAST(sum(n_bytes) AS BIGINT) AS p FROM segb), (SELECT count(*) AS nd FROM documents)", **MEM))
def capacity_estimate(spark, sf_dir):
    ix = index(spark, sf_dir)
    return measures.capacity(measures.buffer_memory(ix.dictionary, CFG), pool_bytes(ix), docs(spark, sf_dir).agg(F.count(F.lit(1)).alias("n_docs")))


def _churn_sql():
    parts = [twin(f"SELECT greatest(1, p * {pc} // 100) AS budget, run, count(*) AS terms_touched, count(*) FILTER (n = 1) AS terms_once FROM (SELECT p, before // greatest(1, p * {pc} // 100) AS run, term, count(*) AS n FROM post JOIN dcum USING (doc_id), total GROUP BY ALL) GROUP BY ALL") for pc in (1, 5, 25, 100)]
    return " UNION ALL ".join(f"SELECT * FROM ({p})" for p in parts)


@query("term_churn", _churn_sql())
def term_churn(spark, sf_dir):
    rows = all_postings(spark, sf_dir)
    n = rows.count()
    return baselines.term_churn(rows, [max(1, n * pc // 100) for pc in (1, 5, 25, 100)])


def _strip(x):
    for pattern in (r"<script.*?</script>", r"<style.*?</style>", r"<!--.*?-->", r"<[^>]*>", r"&[a-zA-Z]+;|&#[0-9]+;"):
        x = f"regexp_replace({x}, '{pattern}', ' ', 'gs')"
    return x


@query("html_vocab", "WITH p AS (SELECT 'raw' AS variant, page_id, coalesce(html, '') AS x FROM pages UNION ALL SELECT 'stripped', page_id, " + _strip("coalesce(html, '')") + f" FROM pages), k AS (SELECT variant, page_id, unnest({WORDS.format('x')}) AS term FROM p), d AS (SELECT variant, term, count(*) AS n, count(DISTINCT page_id) AS df FROM k GROUP BY variant, term) SELECT variant, CAST(sum(n) AS BIGINT) AS tokens, count(*) AS terms, count(*) FILTER (df >= 10) AS terms_kept FROM d GROUP BY variant")
def html_vocab(spark, sf_dir):
    pages = W.collection(spark, sf_dir, "pages", "page_id")
    out = None
    for variant, text in (("raw", F.col("html")), ("stripped", analyze.strip_markup(F.col("html")))):
        rows = P.build_postings(pages.select("page_id", text.alias("text")), "page_id")
        d = P.build_dictionary(rows, IndexConfig(df_threshold=1))
        one = d.agg(F.sum("cf").alias("tokens"), F.count(F.lit(1)).alias("terms"), F.sum((F.col("df") >= 10).cast("long")).alias("terms_kept")).withColumn("variant", F.lit(variant))
        out = one if out is None else out.unionByName(one)
    return out.select("variant", "tokens", "terms", "terms_kept")


KINDS = ("l_partkey", "l_suppkey", "l_returnflag", "l_linestatus")


def _lists_sql():
    one = lambda k: f"SELECT '{k}' AS kind, CAST({k} AS VARCHAR) AS term, count(DISTINCT l_orderkey) AS df FROM lineitem GROUP BY {k}"
    lists = " UNION ALL ".join(map(one, KINDS))
    span = "SELECT g, n, CAST(coalesce(sum(n) OVER (ORDER BY g ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS s0 FROM (SELECT g, CAST(pow(2, least(g, 5)) AS BIGINT) AS n FROM range(0, 4000) r(g))"
    return f"WITH l AS ({lists}), s AS ({span}) SELECT kind, count(*) AS terms, min(df) AS min_df, max(df) AS max_df, CAST(sum((df + 127) // 128) AS BIGINT) AS segments, CAST(sum((SELECT count(*) FROM s WHERE s0 < (df + 127) // 128)) AS BIGINT) AS groups FROM l GROUP BY kind"


@query("lineitem_lists", _lists_sql())
def lineitem_lists(spark, sf_dir):
    lines, out = read_table(spark, sf_dir, "lineitem"), None
    for kind in KINDS:
        d = W.order_lists(lines, kind).groupBy("term").agg(F.count(F.lit(1)).alias("df"))
        one = d.agg(F.count(F.lit(1)).alias("terms"), F.min("df").alias("min_df"), F.max("df").alias("max_df"), F.sum(F.ceil(F.col("df") / F.lit(128))).alias("segments"), F.sum(schedule.groups_of_list(F.col("df"), 128, 5)).alias("groups")).withColumn("kind", F.lit(kind))
        out = one if out is None else out.unionByName(one)
    return out.select("kind", "terms", "min_df", "max_df", "segments", "groups")


CLOCK = {"clock": "SELECT event_id, CAST((epoch_us(ts) - t0) AS HUGEINT) * nd // (t1 - t0 + 1) AS d FROM events, (SELECT min(epoch_us(ts)) AS t0, max(epoch_us(ts)) AS t1 FROM events), (SELECT count(*) AS nd FROM documents)", "flog": "SELECT e.trigger_doc, count(*) AS s FROM events_ e JOIN segg g ON g.term = e.term AND g.group_no = e.group_no GROUP BY e.trigger_doc"}


@query("asof_visible_docs", twin("SELECT event_id, (SELECT max(trigger_doc) FROM flog WHERE trigger_doc <= d) AS last_flush_doc, CAST(d + 1 AS BIGINT) AS docs_visible, CAST(coalesce((SELECT sum(s) FROM flog WHERE trigger_doc <= d), 0) AS BIGINT) AS segments_visible FROM clock", **CLOCK))
def asof_visible_docs(spark, sf_dir):
    """Documents arrive evenly over the clock of events; each event sees the last flush before it."""
    from ..operators.relops import as_of

    ix = index(spark, sf_dir)
    e = pool.flush_events(ix.postings, CFG)
    n = schedule.power_of_two(F.least(F.col("group_no"), F.lit(CFG.cap)))
    log = e.groupBy("trigger_doc").agg(F.sum(n).alias("s"))
    from ..operators.numbering import running_sum

    log = running_sum(log, F.col("s"), [], schedule.div(F.col("trigger_doc"), P.RANGE), [F.col("trigger_doc")], "before").select(F.col("trigger_doc").alias("at"), F.struct("trigger_doc", (F.col("before") + F.col("s")).alias("segments")).alias("flush"))
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    ev = read_table(spark, sf_dir, "events").select("event_id", us.alias("us"))
    span = ev.agg(F.min("us").alias("t0"), F.max("us").alias("t1"))
    nd = docs(spark, sf_dir).agg(F.count(F.lit(1)).alias("nd"))
    at = F.expr("CAST(CAST(us - t0 AS DECIMAL(20, 0)) * nd DIV (t1 - t0 + 1) AS BIGINT)")
    clock = ev.join(F.broadcast(span)).join(F.broadcast(nd)).select("event_id", at.alias("at"))
    seen = as_of(clock, log, "at", "flush", P.RANGE)
    return seen.select("event_id", F.col("flush.trigger_doc").alias("last_flush_doc"), (F.col("at") + 1).alias("docs_visible"), F.coalesce("flush.segments", F.lit(0).cast("long")).alias("segments_visible"))


# ---------------------------------------------------------------- the second collection, and blocks of 128


WIDE = IndexConfig(block=128, cap_log2=5, df_threshold=10, n_shards=1)
WIDE_SEARCH = IndexConfig(block=128, cap_log2=5, df_threshold=10, n_shards=4)
PAGES = {"docw": "SELECT page_id AS doc_id, " + WORDS.format(_strip("coalesce(html, '')")) + " AS w FROM pages"}

for _which in ("E", "W"):
    _set = _which.lower()

    @query(f"svs_pages_{_set}", twin(f"SELECT query_id, doc_id FROM and_{_set}", **PAGES))
    def _svs_pages(spark, sf_dir, which=_which):
        return kernels.svs(index(spark, sf_dir, SEARCH, "pages").served, W.query_set(spark, sf_dir, which))

    @query(f"wand_pages_{_set}", twin(f"SELECT query_id, rank, doc_id, score FROM top_{_set}", **PAGES))
    def _wand_pages(spark, sf_dir, which=_which):
        ix = index(spark, sf_dir, SEARCH, "pages")
        return kernels.wand(ix.served, W.query_set(spark, sf_dir, which), ix.dictionary, ix.coll, K)

    @query(f"svs_wide_{_set}", twin(f"SELECT query_id, doc_id FROM and_{_set}", b=128))
    def _svs_wide(spark, sf_dir, which=_which):
        return kernels.svs(index(spark, sf_dir, WIDE_SEARCH).served, W.query_set(spark, sf_dir, which))


#: Collections and block sizes of the memory measures beside documents in blocks of 16: (suffix, collection, index, SQL).
OTHERS = (("pages", "pages", CFG, {"b": 16} | PAGES), ("wide", "documents", WIDE, {"b": 128}), ("pages_wide", "pages", WIDE, {"b": 128} | PAGES))

for _name, _coll, _cfg, _more in OTHERS:

    @query(f"buffer_memory_{_name}", twin("SELECT cap, docid_bytes, tf_bytes, pos_bytes, round((docid_bytes + tf_bytes + pos_bytes) / (SELECT docid_bytes + tf_bytes + pos_bytes FROM mem WHERE cap = 0), 6) AS ratio_to_1b FROM mem", **(MEM | _more)))
    def _memory(spark, sf_dir, coll=_coll, cfg=_cfg):
        return measures.buffer_memory(index(spark, sf_dir, cfg, coll).dictionary, cfg)

    @query(f"buffer_pool_ratio_{_name}", twin("SELECT cap, docid_bytes + tf_bytes + pos_bytes AS buffer_bytes, p AS pool_bytes, round((docid_bytes + tf_bytes + pos_bytes) / p, 6) AS ratio FROM mem, (SELECT CAST(sum(n_bytes) AS BIGINT) AS p FROM segb)", **(MEM | _more)))
    def _ratio(spark, sf_dir, coll=_coll, cfg=_cfg):
        ix = index(spark, sf_dir, cfg, coll)
        total = F.col("docid_bytes") + F.col("tf_bytes") + F.col("pos_bytes")
        return measures.buffer_memory(ix.dictionary, cfg).join(F.broadcast(pool_bytes(ix))).select("cap", total.alias("buffer_bytes"), "pool_bytes", F.round(total / F.col("pool_bytes"), 6).alias("ratio"))

    @query(f"buffer_classes_{_name}", twin(f"SELECT c AS class_blocks, count(*) AS n_terms, round(count(*) / (SELECT count(*) FROM dict), 6) AS share FROM (SELECT {CLASS_SQL} AS c FROM dict) GROUP BY c", **_more))
    def _classes(spark, sf_dir, coll=_coll, cfg=_cfg):
        return measures.buffer_classes(index(spark, sf_dir, cfg, coll).dictionary, cfg.block)

    @query(f"segment_size_by_class_{_name}", twin(f"SELECT class, count(*) AS n_segments, round(avg(n_bytes), 6) AS avg_bytes FROM segb JOIN (SELECT term, CASE {CLASS_SQL} WHEN 1 THEN '1b' WHEN 2 THEN '2b' ELSE '>2b' END AS class FROM dict) USING (term) GROUP BY class", **_more))
    def _sizes(spark, sf_dir, coll=_coll, cfg=_cfg):
        ix = index(spark, sf_dir, cfg, coll)
        return measures.segment_size_by_class(ix.placed, ix.dictionary, cfg.block)
