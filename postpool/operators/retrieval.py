"""BM25, conjunctive and disjunctive retrieval as relations, and the plan of a query set."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..config import IndexConfig
from ..functions import schedule
from .numbering import numbered, running_sum
from .parts import over_parts, query_batches
from .postings import RANGE

K1, B = 0.9, 0.4


def query_terms(queries: DataFrame) -> DataFrame:
    """(query_id, term, n_terms): distinct terms of each query, n_terms of them."""
    q = queries.select("query_id", F.array_distinct("terms").alias("terms"))
    return q.select("query_id", F.explode("terms").alias("term"), F.size("terms").cast("long").alias("n_terms"))


def intersect(postings: DataFrame, queries: DataFrame, missing: str = "empty") -> DataFrame:
    """(query_id, doc_id) with every term of the query. An unknown or dropped term empties the answer, or is skipped
    (missing='ignore'). Lists meet where their documents lie; only answers leave a part."""
    return over_parts(postings, queries, [], lambda part, terms: [part.having(terms)], "query_id long, doc_id long", query_batches(queries), missing == "ignore")


def intersect_by_joins(postings: DataFrame, dictionary: DataFrame, queries: DataFrame) -> DataFrame:
    """The same by a chain of semi joins, shortest list first: the running set only shrinks. Queries advance together,
    one term each a step; a query with an unknown term has left before the first."""
    terms = query_terms(queries).join(dictionary.select("term", "df"), "term", "left")
    lists = terms.groupBy("query_id").agg(F.sort_array(F.collect_list(F.struct(F.coalesce("df", F.lit(-1)).alias("df"), "term"))).alias("l"))
    lists = lists.where(F.get("l", F.lit(0))["df"] > 0)
    most = lists.agg(F.max(F.size("l"))).first()[0] or 0
    step = lambda i: lists.where(F.size("l") > i).select("query_id", F.get("l", F.lit(i))["term"].alias("term"))
    if not most:
        return postings.join(step(0), "term").select("query_id", "doc_id").limit(0)
    running = postings.select("term", "doc_id").join(step(0), "term").select("query_id", "doc_id")
    for i in range(1, most):
        more = postings.select("term", "doc_id").join(step(i), "term").select("query_id", "doc_id")
        done = running.join(lists.where(F.size("l") <= i).select("query_id"), "query_id", "left_semi")
        running = done.unionByName(running.join(more, ["query_id", "doc_id"], "left_semi"))
    return running


def idf(df: Column, n_docs: Column) -> Column:
    """Never negative, so that maxima are bounds."""
    return F.log1p((n_docs - df + 0.5) / (df + 0.5))


def contribution(tf: Column, df: Column, doc_len: Column, n_docs: Column, avg_len: Column, k1: float = K1, b: float = B) -> Column:
    return idf(df, n_docs) * tf * (k1 + 1) / (tf + k1 * (1 - b + b * doc_len / avg_len))


def scored(postings: DataFrame, dictionary: DataFrame, stats: DataFrame, coll: DataFrame) -> DataFrame:
    """(term, term_id, df, doc_id, tf, w): each posting's BM25 part with final statistics; coll is one row. Postings that
    carry their document's length don't meet stats."""
    known = ["doc_len"] if "doc_len" in postings.columns else []
    rows = postings.select("term", "doc_id", "tf", *known).join(dictionary.select("term", "term_id", "df"), "term")
    rows = (rows if known else rows.join(stats, "doc_id")).join(F.broadcast(coll))
    return rows.select("term", "term_id", "df", "doc_id", "tf", contribution(F.col("tf"), F.col("df"), F.col("doc_len"), F.col("n_docs"), F.col("avg_len")).alias("w"))


def term_bounds(weights: DataFrame) -> DataFrame:
    return weights.groupBy("term").agg(F.max("df").alias("df"), F.max("w").alias("max_contrib"))


def bounds_at_flush(postings: DataFrame, stats: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(shard, term, seg_no, bound) with the statistics known when a segment's last document arrived. Documents seen and
    a term's df so far are two-level counts; no list is ordered as a whole."""
    by_range = schedule.div(F.col("doc_id"), RANGE)
    seen = running_sum(stats, F.col("doc_len"), [], by_range, [F.col("doc_id")], "sum_before")
    seen = numbered(seen, [], by_range, [F.col("doc_id")], "n_docs", first=1)
    seen = seen.select(F.col("doc_id").alias("flushed"), "n_docs", ((F.col("sum_before") + F.col("doc_len")) / F.col("n_docs")).alias("avg_len"))
    rows = numbered(postings.select("shard", "term", "doc_id", "tf", "doc_len", "rank"), ["term"], by_range, [F.col("doc_id")], "df_then", first=1)
    rows = rows.withColumn("seg_no", schedule.segment_no(F.col("rank"), cfg.block))
    ends = rows.groupBy("shard", "term", "seg_no").agg(F.max("doc_id").alias("flushed"), F.max("df_then").alias("df"))
    known = rows.join(ends.join(seen, "flushed"), ["shard", "term", "seg_no"])
    return known.groupBy("shard", "term", "seg_no").agg(F.max(contribution(F.col("tf"), F.col("df"), F.col("doc_len"), F.col("n_docs"), F.col("avg_len"))).alias("bound"))


def bounds_as_of(postings: DataFrame, stats: DataFrame, cfg: IndexConfig, at: int) -> DataFrame:
    """(shard, term, seg_no, bound): bounds refreshed when document `at` has arrived, of what has arrived by then."""
    rows = postings.where(F.col("doc_id") <= at).select("shard", "term", "doc_id", "tf", "doc_len", schedule.segment_no(F.col("rank"), cfg.block).alias("seg_no"))
    df = rows.groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    coll = stats.where(F.col("doc_id") <= at).agg(F.count(F.lit(1)).alias("n_docs"), F.avg("doc_len").alias("avg_len"))
    known = rows.join(df, "term").join(F.broadcast(coll))
    return known.groupBy("shard", "term", "seg_no").agg(F.max(contribution(F.col("tf"), F.col("df"), F.col("doc_len"), F.col("n_docs"), F.col("avg_len"))).alias("bound"))


def ranked(scores: DataFrame, k: int) -> DataFrame:
    """(query_id, rank, doc_id, score): scores rounded to 6 places, ties to the smaller document."""
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "doc_id")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("long").alias("rank"), "doc_id", "score")


def of_queries(rows: DataFrame, queries: DataFrame) -> DataFrame:
    """Rows of terms that some query has."""
    return rows.join(F.broadcast(queries.select(F.explode("terms").alias("term")).distinct()), "term", "left_semi")


def exhaustive(weights: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """Every posting of every query term is scored: the truth that WAND must equal. Unknown terms add nothing. Weights
    are dealt by document, so that scores are added up where they arise; a part's first k of each query are shuffled."""
    return ranked(over_parts(weights, queries, ["w"], lambda part, terms: list(part.best(terms, k)), "query_id long, doc_id long, score double", query_batches(queries)), k)


def phrase(postings: DataFrame, phrases: DataFrame) -> DataFrame:
    """(query_id, doc_id, n_matches): documents where the terms stand in a row. A term may stand several times in a
    phrase.

    Positions that phrases' terms have in a document meet there once, whatever the number of phrases that a term is in:
    words in a row are looked up among the different phrases of that length, and equal phrases share their matches."""
    named = phrases.groupBy("terms").agg(F.collect_list("query_id").alias("ids")).withColumn("need", F.size("terms"))
    lengths = [r.need for r in named.select("need").distinct().collect()]
    words = F.broadcast(phrases.select(F.explode("terms").alias("term")).distinct())
    rows = postings.select("term", "doc_id", "positions").join(words, "term", "left_semi").select("doc_id", "term", F.explode("positions").alias("pos"))
    behind = Window.partitionBy("doc_id").orderBy("pos")
    out = []
    for need in lengths:
        ahead = [(F.col("term"), F.col("pos")), *((F.lead("term", i).over(behind), F.lead("pos", i).over(behind)) for i in range(1, need))]
        found = rows.select("doc_id", F.array(*(t for t, _ in ahead)).alias("terms"), (ahead[-1][1] - F.col("pos")).alias("far")).where(F.col("far") == need - 1)
        found = found.select("doc_id", "terms").join(F.broadcast(named.where(F.col("need") == need).select("terms", "ids")), "terms").groupBy("doc_id", "ids").agg(F.count(F.lit(1)).alias("n_matches"))
        out.append(found.select(F.explode("ids").alias("query_id"), "doc_id", "n_matches"))
    return reduce(DataFrame.unionByName, out) if out else postings.select(F.lit(0).cast("long").alias("query_id"), "doc_id", F.lit(0).cast("long").alias("n_matches")).limit(0)


def filtered(results: DataFrame, *filters: DataFrame) -> DataFrame:
    """Results restricted to documents that every filter table holds."""
    return reduce(lambda r, f: r.join(f.select("doc_id"), "doc_id", "left_semi"), filters, results)


def candidates(results: DataFrame, stats: DataFrame, labels: DataFrame, k: int) -> DataFrame:
    """Feature rows for a later ranker: the first k of each query with document length and labels."""
    top = results.where(F.col("rank") <= k).select("query_id", "doc_id", "score")
    return top.join(stats, "doc_id").join(labels.select("doc_id", "quality", "toxic"), "doc_id", "left").select("query_id", "doc_id", "score", "doc_len", "quality", "toxic")
