"""Token counts: an exact histogram of encoded lengths, whose suffix sums answer every context limit.

Edge cases: a null or empty text has length 0 and is counted; repeated rows count each; an empty table gives an empty
histogram; columns other than the text (and the optional groups) are ignored.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from .common import batches
from .tokens import ranked

#: Lengths in one block of the two-level suffix sums.
BLOCK = 1024


def encoded_lengths(docs: DataFrame, vocab: str, pattern: str, text: str = "text", by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., n_tokens): one row per document, each whole text encoded by the byte-pair ranks in the file `vocab`."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        encoding = ranked(vocab, pattern)
        n = [len(encoding.encode_ordinary(t)) if t else 0 for t in batch.column(0).to_pylist()]
        return pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(n, pa.int64())], names=[*by, "n_tokens"])

    rows = docs.select(F.col(f"`{text}`").cast("string").alias("text"), *(F.col(f"`{c}`").cast("string").alias(c) for c in by))
    return rows.mapInArrow(batches(kernel), ", ".join([*(f"`{c}` string" for c in by), "n_tokens long"]))


def _suffix(value: Column, by: list[str], fine: str, coarse: str) -> Column:
    """Sum over rows at or beyond a row's length: those of its own block, then whole later blocks."""
    own = Window.partitionBy(*by, coarse).orderBy(F.desc(fine)).rowsBetween(Window.unboundedPreceding, 0)
    return F.sum(value).over(own)


def length_histogram(lengths: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """One row per (by..., n_tokens) that occurs, with suffix sums.

    n_docs; n_tokens_all = tokens of those documents; docs_ge and tokens_ge over documents of at least n_tokens;
    truncated_total = tokens left if every document is cut to n_tokens; total_docs and total_tokens of the group;
    quantile = share of documents of at most n_tokens.
    Only the histogram is sorted: its rows are bounded by the longest document, and windows run block by block.
    """
    by = list(by)
    hist = lengths.groupBy(*by, "n_tokens").agg(F.count(F.lit(1)).alias("n_docs")).withColumn("block", F.expr(f"n_tokens div {BLOCK}"))
    blocks = hist.groupBy(*by, "block").agg(F.sum("n_docs").alias("d"), F.sum(F.col("n_docs") * F.col("n_tokens")).alias("t"))
    later = Window.partitionBy(*(by or [F.lit(0)])).orderBy(F.desc("block")).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy(*(by or [F.lit(0)]))
    blocks = blocks.select(*(F.col(c).alias(f"b_{c}") for c in [*by, "block"]), F.coalesce(F.sum("d").over(later), F.lit(0)).alias("d_after"), F.coalesce(F.sum("t").over(later), F.lit(0)).alias("t_after"), F.sum("d").over(whole).alias("total_docs"), F.sum("t").over(whole).alias("total_tokens"))
    same = F.lit(True)
    for c in [*by, "block"]:
        same = same & F.col(c).eqNullSafe(F.col(f"b_{c}"))
    tokens = F.col("n_docs") * F.col("n_tokens")
    out = hist.join(blocks, same).withColumns({"docs_ge": _suffix(F.col("n_docs"), by, "n_tokens", "block") + F.col("d_after"), "tokens_ge": _suffix(tokens, by, "n_tokens", "block") + F.col("t_after")})
    return out.select(*by, "n_tokens", "n_docs", tokens.alias("n_tokens_all"), "docs_ge", "tokens_ge", (F.col("total_tokens") - F.col("tokens_ge") + F.col("docs_ge") * F.col("n_tokens")).alias("truncated_total"), "total_docs", "total_tokens", ((F.col("total_docs") - F.col("docs_ge") + F.col("n_docs")) / F.col("total_docs")).alias("quantile"))


def at_limits(hist: DataFrame, limits: list[int]) -> DataFrame:
    """(limit, total_docs, total_tokens, docs_within, truncated_total, lost) for any list of context limits, from the
    suffix sums of the first length beyond a limit."""
    spark = hist.sparkSession
    asked = spark.sql("SELECT explode(array(" + ",".join(f"{int(x)}L" for x in limits) + ")) AS `limit`")
    whole = hist.agg(F.max("total_docs").alias("total_docs"), F.max("total_tokens").alias("total_tokens")).where("total_docs IS NOT NULL")
    beyond = hist.select("n_tokens", "docs_ge", "tokens_ge").join(F.broadcast(asked), F.col("n_tokens") > F.col("limit"))
    beyond = beyond.groupBy("limit").agg(F.min(F.struct("n_tokens", "docs_ge", "tokens_ge")).alias("s"))
    out = asked.distinct().join(F.broadcast(whole)).join(beyond, "limit", "left")
    more, tokens = F.coalesce("s.docs_ge", F.lit(0)), F.coalesce("s.tokens_ge", F.lit(0))
    out = out.select("limit", "total_docs", "total_tokens", (F.col("total_docs") - more).alias("docs_within"), (F.col("total_tokens") - tokens + more * F.col("limit")).alias("truncated_total"))
    return out.withColumn("lost", F.col("total_tokens") - F.col("truncated_total"))


def quantiles(hist: DataFrame, shares: list[float]) -> DataFrame:
    """(share, n_tokens): the least length that at least this share of documents don't exceed; exact, from docs_ge."""
    spark = hist.sparkSession
    asked = spark.sql("SELECT explode(array(" + ",".join(f"{float(x)}D" for x in shares) + ")) AS share")
    upto = F.col("total_docs") - F.col("docs_ge") + F.col("n_docs")
    return hist.join(F.broadcast(asked), upto >= F.ceil(F.col("share") * F.col("total_docs"))).groupBy("share").agg(F.min("n_tokens").alias("n_tokens"))
