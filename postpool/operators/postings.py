"""Tokens, postings and dictionaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..config import IndexConfig
from ..functions import analyze, schedule
from .numbering import numbered

#: Documents of one bucket of the two-level ranks.
RANGE = 4096


def tokenize(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, pos, term), positions from 1."""
    words = docs.select(F.col(id_col).alias("doc_id"), analyze.words(F.col(text_col)).alias("w"))
    return words.select("doc_id", F.posexplode("w").alias("p", "term")).select("doc_id", (F.col("p") + 1).alias("pos"), "term")


def doc_stats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, doc_len): all words count, those of dropped terms too."""
    return docs.select(F.col(id_col).alias("doc_id"), F.size(analyze.words(F.col(text_col))).cast("long").alias("doc_len"))


def collection_stats(stats: DataFrame) -> DataFrame:
    return stats.agg(F.count(F.lit(1)).alias("n_docs"), F.sum("doc_len").alias("sum_len"), F.avg("doc_len").alias("avg_len"))


def build_postings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", positional: bool = True) -> DataFrame:
    """(doc_id, term, tf, positions): each document is inverted inside its row, so nothing is shuffled."""
    rows = docs.select(F.col(id_col).alias("doc_id"), analyze.row_postings(analyze.words(F.col(text_col))).alias("occ"))
    rows = rows.select("doc_id", F.inline(analyze.cut(F.col("occ"))))
    return rows if positional else rows.select("doc_id", "term", "tf", F.array(F.get("positions", F.lit(0))).alias("positions"))


def parsed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", cfg: IndexConfig = IndexConfig()) -> DataFrame:
    """(doc_id, doc_len, occ): a row for each document, inverted inside it; occ is an array of (term, tf, positions).
    Documents with more words than positions have numbers for are cut or emptied (doc_len too)."""
    w = analyze.words(F.col(text_col))
    if cfg.pos_bits < 32:
        most = (1 << cfg.pos_bits) - 1
        w = F.when(F.size(w) <= most, w).otherwise(F.slice(w, 1, most) if cfg.overflow == "truncate" else F.array().cast("array<string>"))
    rows = docs.select(F.col(id_col).alias("doc_id"), analyze.row_postings(w).alias("occ"))
    rows = rows.select("doc_id", F.size("occ").cast("long").alias("doc_len"), analyze.cut(F.col("occ")).alias("occ"))
    if not cfg.positional:
        rows = rows.withColumn("occ", F.transform("occ", lambda o: F.struct(o["term"].alias("term"), o["tf"].alias("tf"), F.slice(o["positions"], 1, 1).alias("positions"))))
    return rows


def postings_of_tokens(tokens: DataFrame) -> DataFrame:
    """The same from a table of tokens (already parsed input): one shuffle, on (document, term)."""
    return tokens.groupBy("doc_id", "term").agg(F.count(F.lit(1)).cast("int").alias("tf"), F.sort_array(F.collect_list("pos")).alias("positions"))


def shard_of(doc_id: Column, per_shard: int | None) -> Column:
    return F.lit(0) if not per_shard else schedule.div(doc_id, per_shard).cast("int")


def build_dictionary(postings: DataFrame, cfg: IndexConfig, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, term, term_id, df, cf, max_tf, first_doc, first_pos) of kept terms, ids in order of first sight."""
    first = F.min_by(F.get("positions", F.lit(0)).cast("long"), "doc_id")  # a document has a term once; all sums hash
    terms = postings.groupBy(*keys, "term").agg(F.count(F.lit(1)).alias("df"), F.sum("tf").alias("cf"), F.max("tf").alias("max_tf"), F.min("doc_id").alias("first_doc"), first.alias("first_pos"))
    terms = apply_threshold(terms, cfg.df_threshold)
    return numbered(terms, list(keys), schedule.div(F.col("first_doc"), RANGE), [F.col("first_doc"), F.col("first_pos")], "term_id")


def apply_threshold(dictionary: DataFrame, threshold: int) -> DataFrame:
    """A term is kept once its small first buffer of `threshold` postings fills."""
    return dictionary.where(F.col("df") >= threshold)


def rank_postings(postings: DataFrame, dictionary: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Postings of kept terms with term_id and rank (from 1) in their list, by document.

    Lists of frequent terms are ranked document range by document range, so none sits in one task."""
    kept = postings.join(dictionary.select(*keys, "term", "term_id"), [*keys, "term"])
    return numbered(kept, [*keys, "term"], schedule.div(F.col("doc_id"), RANGE), [F.col("doc_id")], "rank", first=1)
