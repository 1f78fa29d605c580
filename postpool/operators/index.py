"""Whole indexes: built once, kept as tables in the shared folder."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import cached_property

from pyspark.sql import DataFrame, functions as F

from ..config import IndexConfig
from ..functions import schedule
from ..runtime import materialise, materialise_buckets
from . import pool, postings as P, retrieval as R


@dataclass
class Index:
    """dictionary: (term, term_id, df, cf, ..., max_contrib); postings: ranked; blocks: segments with their compressed
    blocks, zone maps and BM25 bounds; placed: addresses and links in the index's own layout; stats and coll: document
    lengths and collection statistics."""

    cfg: IndexConfig
    dictionary: DataFrame
    postings: DataFrame
    blocks: DataFrame
    placed: DataFrame
    stats: DataFrame
    coll: DataFrame
    _layouts: dict = field(default_factory=dict)

    @cached_property
    def segments(self) -> DataFrame:
        """Blocks with their addresses and links, written once when first asked for; retrieval doesn't need them."""
        return materialise(joined(self.blocks, self.placed), "segments")

    @cached_property
    def served(self) -> DataFrame:
        """What retrieval reads, in a table of one bucket for each shard, by term: a query batch shuffles nothing."""
        return serve(self.blocks, self.cfg.n_shards)

    def addresses(self, layout: str, cap_log2: int | None = None) -> DataFrame:
        """(shard, term, term_id, seg_no, group_no, n_bytes, addr, next_addr, is_head, is_tail) in another layout; no
        block and no posting is read."""
        cfg = replace(self.cfg, layout=layout, cap_log2=self.cfg.cap_log2 if cap_log2 is None else cap_log2)
        return addresses(self.blocks, cfg)

    def relaid(self, layout: str, cap_log2: int | None = None) -> DataFrame:
        """Segments with addresses and links of another layout; the blocks stay as they are."""
        return joined(self.blocks, self.addresses(layout, cap_log2))


THIN = ("shard", "term", "term_id", "seg_no", "n_bytes", "n_docs", "last_doc", "last_pos")


def addresses(blocks: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Placed and linked segments without their blocks: only numbers take part."""
    thin = blocks.select(*THIN)
    events = pool.events_of_segments(thin, cfg)
    rows = thin.select("shard", "term", "term_id", "seg_no", schedule.group_of_segment(F.col("seg_no"), cfg.cap).alias("group_no"), "n_bytes")
    return pool.link(pool.place(rows, events, cfg, ("shard",)), ("shard",))


def joined(blocks: DataFrame, placed: DataFrame) -> DataFrame:
    return blocks.drop("group_no").join(placed.select("shard", "term_id", "seg_no", "group_no", "addr", "next_addr", "is_head", "is_tail"), ["shard", "term_id", "seg_no"])


SERVED = ("shard", "term", "seg_no", "n_docs", "first_doc", "last_doc", "d_block", "f_block", "lengths", "bound")


def serve(segments: DataFrame, n_shards: int) -> DataFrame:
    """SERVED columns and `slot`, a number that Spark's hash sends to a bucket of the shard's own."""
    spark = segments.sparkSession
    seen = spark.range(64 * n_shards + 64).select(F.col("id").cast("int").alias("slot")).withColumn("bucket", F.pmod(F.hash("slot"), F.lit(n_shards)))
    slots = {r.bucket: r.slot for r in seen.groupBy("bucket").agg(F.min("slot").alias("slot")).collect()}
    spare = max(slots.values()) + 1
    by_shard = F.array(*(F.lit(slots.get(i, spare + i)).cast("int") for i in range(n_shards)))
    rows = segments.select(F.get(by_shard, F.col("shard")).alias("slot"), *SERVED)
    return materialise_buckets(rows, "served", "slot", n_shards, ["term", "seg_no"])


def build_index(docs: DataFrame, cfg: IndexConfig, id_col: str = "doc_id", text_col: str = "text", encode: bool = True) -> Index:
    """Documents to a compressed index. Shards are document ranges. A document is parsed once, into a row of its own;
    postings move with their rank and then by segment; addresses follow from sizes and triggers of segments. Parsed
    documents, ranked postings and blocks are written to the shared folder, so that nothing is parsed or encoded twice
    and a lost executor costs one stage."""
    per_shard = None
    if cfg.n_shards > 1:
        top = docs.agg(F.max(id_col)).first()[0] or 0
        per_shard = -(-(top + 1) // cfg.n_shards)
    rows = materialise(P.parsed(docs, id_col, text_col, cfg).withColumn("shard", P.shard_of(F.col("doc_id"), per_shard)), "parsed")
    stats = rows.select("doc_id", "doc_len")
    coll = materialise(P.collection_stats(stats).coalesce(1), "collection")
    occ = rows.select("shard", "doc_id", "doc_len", F.inline("occ"))
    keys = ("shard",) if cfg.threshold_scope == "shard" else ()
    dictionary = materialise(P.build_dictionary(occ, cfg, keys), "dictionary")
    kept = occ.join(dictionary.select(*keys, "term", "term_id", "df"), [*keys, "term"])
    ranked = materialise(P.numbered(kept, ["shard", "term"], schedule.div(F.col("doc_id"), P.RANGE), [F.col("doc_id")], "rank", first=1), "postings")
    segments = with_bounds(pool.assemble(ranked, cfg, ("shard",)), coll)
    blocks = materialise(pool.encode(segments, cfg) if encode else pool.segment_bytes(segments, cfg), "blocks")
    placed = materialise(addresses(blocks, cfg), "placed")
    most = blocks.groupBy(*keys, "term").agg(F.max("bound").alias("max_contrib"))
    return Index(cfg, materialise(dictionary.join(most, [*keys, "term"]), "dictionary"), ranked.drop("df"), blocks, placed, stats, coll)


def with_bounds(segments: DataFrame, coll: DataFrame) -> DataFrame:
    """Adds bound: the largest BM25 part of a posting in the segment, with the collection's final statistics (one row)."""
    rows = segments.join(F.broadcast(coll.select("n_docs", "avg_len").withColumnsRenamed({"n_docs": "_n", "avg_len": "_a"})))
    parts = F.zip_with("tfs", "lengths", lambda tf, n: R.contribution(tf, F.col("df"), n, F.col("_n"), F.col("_a")))
    return rows.withColumn("bound", F.array_max(parts)).drop("_n", "_a", "df")
