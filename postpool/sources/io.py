"""Readers and writers: tables by name, text-like sources, index tables in Parquet."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "conversations": "conv_id long, turn long, role string, text string",
    "labels": "doc_id long, quality int, toxic int",
}


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A Parquet table; schemas of text tables are declared, never inferred."""
    reader = spark.read.schema(SCHEMAS[name]) if name in SCHEMAS else spark.read
    return reader.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def spread(df: DataFrame, key: str) -> DataFrame:
    """Rows over all cores if the input has fewer splits (a table of one small file); large tables stay as they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores, key) if df.rdd.getNumPartitions() < cores else df


def read_docs(spark: SparkSession, path: str, kind: str = "parquet", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text) from parquet, orc, json, csv (with header) or plain text (a line is a document, numbered by file order)."""
    if kind == "text":
        lines = spark.read.text(path).select("value", F.monotonically_increasing_id().alias("doc_id"))
        return lines.select("doc_id", F.col("value").alias("text"))
    schema = T.StructType([T.StructField(id_col, T.LongType()), T.StructField(text_col, T.StringType())])
    reader = spark.read.schema(schema)
    if kind == "csv":
        reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    return reader.format(kind).load(path).select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))


def write_segments(segments: DataFrame, path: str, by_term: bool = False) -> None:
    """The pool as files of a shard each, in address order (or by term, for row-group skipping on term_id)."""
    order = ["shard", "term_id", "seg_no"] if by_term else ["shard", "addr"]
    segments.repartition("shard").sortWithinPartitions(*order).write.partitionBy("shard").option("compression", "uncompressed").parquet(path)


def write_json(df: DataFrame, path: str) -> None:
    df.write.json(path)
