"""Packing: first-fit decreasing by a tournament tree of bin capacities, in randomised groups of documents.

Documents longer than a sequence are cut into full pieces and one remainder; only remainders compete for bins. Edge
cases: a null or empty text is its end token alone; equal lengths go by document id, start and checksum; repeated rows
and null ids are packed like any others; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, functions as F

from ..runtime import materialise, shuffle_partitions
from .common import pick
from .tokens import chunked

#: Pieces that share one run of first-fit decreasing.
GROUP = 8192
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, salt long"
PACKED = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def cut_pieces(docs: DataFrame, vocab: str, end_id: int, limit: int) -> DataFrame:
    """PIECES: each document's ids and the end id, cut every `limit` ids; salt is a pseudo-random number of the row."""
    end = struct.pack("<I", end_id)

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, task, seen = chunked(vocab), TaskContext.get().partitionId(), 0
        for batch in it:
            out: list[list] = [[] for _ in range(6)]
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids = encoder.encode(text) + end
                total = len(ids) // 4
                for start in range(0, total, limit):
                    piece = ids[4 * start : 4 * (start + limit)]
                    seen += 1
                    row = (doc, start, len(piece) // 4, zlib.crc32(piece), total, zlib.crc32(b"%d:%d" % (task, seen)))
                    for column, value in zip(out, row):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "salt"])

    return pick(docs, doc_id="long", text="string").mapInArrow(kernel, PIECES)


def first_fit_decreasing(lengths: list[int], limit: int) -> list[tuple[int, int]]:
    """(bin, offset) of each length, given in decreasing order: the first bin with room, found from the root of a
    tournament tree whose inner nodes hold the largest room below them."""
    size = 1
    while size < max(1, len(lengths)):
        size *= 2
    room = [limit] * (2 * size)
    placed = []
    for n in lengths:
        node = 1
        while node < size:
            node *= 2
            if room[node] < n:
                node += 1
        placed.append((node - size, limit - room[node]))
        room[node] -= n
        node //= 2
        while node:
            most = room[2 * node] if room[2 * node] >= room[2 * node + 1] else room[2 * node + 1]
            if room[node] == most:
                break
            room[node] = most
            node //= 2
    return placed


def pack(docs: DataFrame, vocab: str, end_id: int = 2, limit: int = 4096, group: int = GROUP) -> DataFrame:
    """PACKED: each piece with its sequence and its offset there.

    Texts are encoded once; the small table of pieces is written to the shared folder, so that the random groups are
    drawn from fixed rows, whatever is run again. A group has about `group` pieces at any input size.
    """
    pieces = materialise(cut_pieces(docs, vocab, end_id, limit), "pieces")
    groups = max(1, -(-pieces.count() // group))

    def kernel(table: pa.Table) -> pa.Table:
        table = table.sort_by([("length", "descending"), ("doc_id", "ascending"), ("start", "ascending"), ("ids_crc32", "ascending"), ("salt", "ascending")])
        number = table.column("bin_group")[0].as_py()
        placed = first_fit_decreasing(table.column("length").to_pylist(), limit)
        kept = table.select(["doc_id", "start", "length", "ids_crc32", "doc_tokens"])
        kept = kept.append_column("sequence_id", pa.array([(number << 32) + b for b, _ in placed], pa.int64()))
        return kept.append_column("offset", pa.array([o for _, o in placed], pa.int64()))

    dealt = pieces.withColumn("bin_group", F.col("salt") % groups)
    if groups > shuffle_partitions(docs.sparkSession):
        dealt = dealt.repartition(groups, "bin_group")
    return dealt.groupBy("bin_group").applyInArrow(kernel, PACKED)


def padding(packed: DataFrame, limit: int = 4096) -> DataFrame:
    """(sequences, tokens, padded_tokens, padding): a sequence is padded to `limit`, unless its length is a power of two."""
    filled = packed.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    stored = F.when(F.bit_count("n") == 1, F.col("n")).otherwise(F.lit(limit))
    out = filled.agg(F.count(F.lit(1)).alias("sequences"), F.coalesce(F.sum("n"), F.lit(0)).alias("tokens"), F.coalesce(F.sum(stored), F.lit(0)).alias("padded_tokens"))
    return out.withColumn("padding", F.col("padded_tokens") - F.col("tokens"))
