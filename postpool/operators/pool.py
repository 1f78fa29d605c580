"""Segments and the pool: flush schedule, encoding, placement, links."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..config import IndexConfig
from ..functions import analyze, codec, schedule
from .numbering import running_sum
from .postings import RANGE

POINTER, LENGTH = 8, 4


def with_groups(ranked: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Adds seg_no, slot and group_no to ranked postings."""
    seg = schedule.segment_no(F.col("rank"), cfg.block)
    return ranked.withColumns({"seg_no": seg, "slot": schedule.slot(F.col("rank"), cfg.block), "group_no": schedule.group_of_segment(seg, cfg.cap)})


def flush_events(ranked: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(term, group_no, trigger_doc, trigger_pos): the posting that fills a group flushes it; leftovers fire nothing."""
    rows = with_groups(ranked, cfg)
    full = rows.where(F.col("rank") == schedule.group_end(F.col("group_no"), cfg.block, cfg.cap))
    return full.select(*(c for c in ("shard",) if c in ranked.columns), "term", "term_id", "group_no", F.col("doc_id").alias("trigger_doc"), F.get("positions", F.lit(0)).cast("long").alias("trigger_pos"))


def events_of_segments(segments: DataFrame, cfg: IndexConfig) -> DataFrame:
    """The same from segments alone, for any cap: a group's trigger is the last posting of its last segment, if full."""
    group = schedule.group_of_segment(F.col("seg_no"), cfg.cap)
    full = segments.where((F.col("n_docs") == cfg.block) & ((F.col("seg_no") + 1) * cfg.block == schedule.group_end(group, cfg.block, cfg.cap)))
    return full.select(*(c for c in ("shard",) if c in segments.columns), "term", "term_id", group.alias("group_no"), F.col("last_doc").alias("trigger_doc"), F.col("last_pos").alias("trigger_pos"))


def final_flush(dictionary: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(term, n_left, n_segments): what the last flush writes, from list lengths alone."""
    last = schedule.groups_of_list(F.col("df"), cfg.block, cfg.cap) - 1
    begin = F.when(last > 0, schedule.group_end(last - 1, cfg.block, cfg.cap)).otherwise(0)
    left = F.when(F.col("df") == schedule.group_end(last, cfg.block, cfg.cap), 0).otherwise(F.col("df") - begin)
    out = dictionary.select("term", left.alias("n_left")).where("n_left > 0")
    return out.withColumn("n_segments", F.ceil(F.col("n_left") / F.lit(cfg.block)))


def assemble(ranked: DataFrame, cfg: IndexConfig, keys: tuple[str, ...] = ()) -> DataFrame:
    """One row per segment (at most `block` postings): doc ids, tfs and position gaps in document order. last_pos is
    the term's first place in last_doc; lengths (of documents) and df come along if the postings have them."""
    rows = with_groups(ranked, cfg)
    known = "doc_len" in ranked.columns
    one = F.struct("doc_id", "tf", analyze.position_gaps(F.col("positions")).alias("gaps"), *(["doc_len"] if known else []))
    df = [F.first("df").alias("df")] if "df" in ranked.columns else []
    segs = rows.groupBy(*keys, "term", "term_id", "seg_no", "group_no").agg(F.sort_array(F.collect_list(one)).alias("p"), F.max("rank").alias("last_rank"), *df)
    docs = F.transform("p", lambda x: x["doc_id"])
    return segs.select(
        *keys, "term", "term_id", "seg_no", "group_no", "last_rank", docs.alias("docs"), F.transform("p", lambda x: x["tf"]).alias("tfs"), F.flatten(F.transform("p", lambda x: x["gaps"])).alias("gaps"),
        F.get(docs, F.lit(0)).alias("first_doc"), F.element_at(docs, -1).alias("last_doc"), F.size("p").alias("n_docs"), F.array_max(F.transform("p", lambda x: x["tf"])).alias("max_tf"),
        F.get(F.element_at("p", -1)["gaps"], F.lit(0)).cast("long").alias("last_pos"), *([F.transform("p", lambda x: x["doc_len"].cast("int")).alias("lengths")] if known else []), *(["df"] if df else []),
    )


def doc_gaps(docs):
    """First document id, then differences: a segment decodes alone."""
    return F.transform(docs, lambda d, i: F.when(i == 0, d).otherwise(d - F.get(docs, i - 1)))


def segment_bytes(segments: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Adds n_bytes without encoding: pointer, lengths and the sizes of all blocks."""
    size = F.lit(POINTER) + LENGTH + codec.pfor_size(doc_gaps(F.col("docs"))) + LENGTH + codec.pfor_size(F.col("tfs"))
    if cfg.positional:
        size = size + F.aggregate(F.transform(codec.in_blocks(F.col("gaps"), cfg.block), lambda b: codec.pfor_size(b) + LENGTH), F.lit(0).cast("long"), lambda a, x: a + x)
    return segments.withColumn("n_bytes", size.cast("long"))


def block_sizes(segments: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(term, seg_no, part, n_values, width, exceptions, n_bytes), a row for each block."""
    one = lambda part, v: F.struct(F.lit(part).alias("part"), codec.block_shape(v).alias("s"))
    parts = F.concat(F.array(one("D", doc_gaps(F.col("docs"))), one("F", F.col("tfs"))), F.transform(codec.in_blocks(F.col("gaps"), cfg.block), lambda b: one("P", b)))
    return segments.select("term", "seg_no", F.explode(parts).alias("x")).select("term", "seg_no", "x.part", "x.s.*")


def block_shapes(encoded: DataFrame) -> DataFrame:
    """The same rows from compressed segments: a block says its own shape in its head, so no value is decoded and no
    posting is read."""
    byte = lambda b, i: F.conv(F.hex(F.substring(b, i, 1)), 16, 10).cast("long")
    one = lambda part, b: F.struct(F.lit(part).alias("part"), (byte(b, 1) + 256 * byte(b, 2)).alias("n_values"), byte(b, 3).alias("width"), byte(b, 4).alias("exceptions"), F.length(b).cast("long").alias("n_bytes"))
    parts = F.concat(F.array(one("D", F.col("d_block")), one("F", F.col("f_block"))), F.transform("p_blocks", lambda b: one("P", b)))
    return encoded.select("term", "seg_no", F.explode(parts).alias("x")).select("term", "seg_no", "x.*")


ENCODED = "d_block binary, f_block binary, p_blocks array<binary>"


def encode(segments: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Adds the compressed blocks and n_bytes, drops the arrays. Arrow batches to numpy; a row is a segment."""
    kept = [f for f in segments.schema.fields if f.name not in ("docs", "tfs", "gaps", "n_bytes")]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept), "n_bytes long", ENCODED])
    block, positional = cfg.block, cfg.positional
    names = [f.name for f in kept]

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in it:
            for start in range(0, whole.num_rows, SLICE):
                batch = whole.slice(start, SLICE)
                column = lambda c: batch.column(batch.schema.get_field_index(c))  # noqa: E731,B023
                size, columns = packed(*(column(c) for c in ("docs", "tfs", "gaps")), block, positional)
                yield pa.RecordBatch.from_arrays([*(column(n) for n in names), size, *columns], names=[*names, "n_bytes", "d_block", "f_block", "p_blocks"])

    return segments.mapInArrow(kernel, schema)


#: Segments whose blocks are coded together.
SLICE = 2000


def binary_array(data: np.ndarray, offsets: np.ndarray) -> pa.Array:
    return pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(data)])


def packed(docs: pa.Array, tfs: pa.Array, gaps: pa.Array, block: int, positional: bool = True) -> tuple[pa.Array, list[pa.Array]]:
    """n_bytes and ENCODED columns of segments from their list columns, all blocks at once."""
    flat = lambda c: (c.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.diff(c.offsets.to_numpy()).astype(np.int64))
    (d, n), (f, _), (g, m) = flat(docs), flat(tfs), flat(gaps)
    starts = np.cumsum(n) - n
    d_gaps = np.diff(d, prepend=0)
    d_gaps[starts] = d[starts]
    d_data, d_at = codec.pfor_encode_many(d_gaps, n)
    f_data, f_at = codec.pfor_encode_many(f, n)
    if not positional:
        g, m = g[:0], np.zeros_like(m)
    count = -(-m // block)
    owner = np.repeat(np.arange(len(m)), count)
    sizes = np.minimum(block, m[owner] - block * (np.arange(len(owner)) - (np.cumsum(count) - count)[owner]))
    p_data, p_at = codec.pfor_encode_many(g, sizes)
    last = np.concatenate([[0], np.cumsum(count)])
    size = POINTER + 2 * LENGTH + np.diff(d_at) + np.diff(f_at) + p_at[last[1:]] - p_at[last[:-1]] + LENGTH * count
    return pa.array(size, pa.int64()), [binary_array(d_data, d_at), binary_array(f_data, f_at), pa.ListArray.from_arrays(pa.array(last, pa.int32()), binary_array(p_data, p_at))]


DECODED = "term string, seg_no long, doc_id long, tf int, positions array<int>"


def decode(encoded: DataFrame, positions: bool = True, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, term, seg_no, doc_id, tf, positions) from the compressed blocks; only the asked-for columns are read."""
    wanted = ["term", "seg_no", "d_block", "f_block", *(["p_blocks"] if positions else []), *keys]
    types = {f.name: f.dataType.simpleString() for f in encoded.schema.fields}

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in it:
            for start in range(0, whole.num_rows, SLICE):
                yield unpacked(whole.slice(start, SLICE), positions, keys)

    return encoded.select(*wanted).mapInArrow(kernel, ", ".join([*(f"`{k}` {types[k]}" for k in keys), DECODED]))


def values_of(blocks: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(values, sizes) of a column of blocks."""
    return codec.pfor_decode_many(*bytes_of(blocks))


def bytes_of(blocks: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, where each block begins) of a column of blocks, not copied."""
    if not len(blocks):
        return np.zeros(0, np.uint8), np.zeros(0, np.int64)
    _, offsets, data = blocks.cast(pa.binary()).buffers()
    return np.frombuffer(data, np.uint8), np.frombuffer(offsets, np.int32)[blocks.offset : blocks.offset + len(blocks)]


def sums_within(values: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Running sums that start anew with each group."""
    total = np.cumsum(values)
    starts = np.cumsum(sizes) - sizes
    held = sizes > 0
    return total - np.repeat((total[starts[held]] - values[starts[held]]), sizes[held])


def unpacked(batch: pa.RecordBatch, positions: bool, keys: tuple[str, ...] = ()) -> pa.RecordBatch:
    """(keys, DECODED) rows of a batch of segments, all blocks at once."""
    column = lambda c: batch.column(batch.schema.get_field_index(c))
    d, n = values_of(column("d_block"))
    tfs = values_of(column("f_block"))[0]
    owner = pa.array(np.repeat(np.arange(len(n)), n))
    places = pa.nulls(len(d), pa.list_(pa.int32()))
    if positions:
        gaps = values_of(column("p_blocks").flatten())[0]
        if len(gaps):
            places = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(tfs)]), pa.int32()), pa.array(sums_within(gaps, tfs), pa.int32()))
    columns = [column("term").take(owner), column("seg_no").take(owner), pa.array(sums_within(d, n), pa.int64()), pa.array(tfs, pa.int32()), places]
    return pa.RecordBatch.from_arrays([*(column(k).take(owner) for k in keys), *columns], names=[*keys, "term", "seg_no", "doc_id", "tf", "positions"])


def traverse(segments: DataFrame, positions: bool = True) -> DataFrame:
    """(term, seg_no, doc_id, tf, positions) by walking each list: from the head, the next pointer names the address of
    the segment that is decoded next. ValueError for a pointer to nowhere, or if segments stay that no pointer reaches.

    Lists move whole to a task (a shard bounds them) and come one after the other, in pool order; those of an Arrow batch
    are walked and decoded together."""
    rows = segments.select("shard", "term_id", "addr", "next_addr", "is_head", "term", "seg_no", "d_block", "f_block", *(["p_blocks"] if positions else []))
    rows = rows.repartition("shard", "term_id").sortWithinPartitions("shard", "term_id", "addr")

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []  # from the first segment of a list on that may go on
        for batch in it:
            if not batch.num_rows:
                continue
            starts = list_starts([*(b.slice(b.num_rows - 1) for b in held[-1:]), batch])[1:]
            if starts:
                last = starts[-1] - bool(held)
                yield from _walked_and_decoded([*held, batch.slice(0, last)], positions)
                held = [batch.slice(last)]
            else:
                held.append(batch)
        if held:
            yield from _walked_and_decoded(held, positions)

    return rows.mapInArrow(kernel, DECODED)


def list_starts(batches: list[pa.RecordBatch]) -> list[int]:
    """Rows where a list begins."""
    shard, term = (np.concatenate([b.column(b.schema.get_field_index(c)).to_numpy() for b in batches]) for c in ("shard", "term_id"))
    return [0, *(np.flatnonzero((np.diff(shard) != 0) | (np.diff(term) != 0)) + 1).tolist()]


def _walked_and_decoded(batches: list[pa.RecordBatch], positions: bool) -> Iterator[pa.RecordBatch]:
    table = pa.Table.from_batches(batches)
    if table.num_rows:
        for start in range(0, table.num_rows, SLICE):
            if not start:
                table = table.take(pa.array(walked(table, list_starts(batches))))
            yield unpacked(table.slice(start, SLICE).combine_chunks().to_batches()[0], positions)


def walked(rows: pa.Table, starts: list[int]) -> list[int]:
    """Rows in the order of their lists' pointers; a list's rows are together, by address."""
    n = rows.num_rows
    addr, after, head = rows["addr"].to_numpy(), rows["next_addr"].to_numpy(), rows["is_head"].to_pylist()
    has = ~np.isnan(after) if after.dtype.kind == "f" else np.ones(n, bool)
    if after.dtype.kind == "f":  # nulls; addresses are read whole
        after = rows["next_addr"].fill_null(-1).to_numpy()
    rank = np.unique(np.concatenate([addr, after]), return_inverse=True)[1]
    own = np.repeat(np.arange(len(starts)), np.diff([*starts, n])) * 2 * n
    at = np.searchsorted(own + rank[:n], own + rank[n:])
    found = (own + rank[:n])[np.minimum(at, n - 1)] == own + rank[n:]
    to = np.where(has, np.where(found, at, -2), -1).tolist()  # -1: the end; -2: nowhere
    out: list[int] = []
    for a, z in zip(starts, [*starts[1:], n]):
        row, left = next((i for i in range(a, z) if head[i]), -2), z - a
        while row >= 0 and left:
            out.append(row)
            row, left = to[row], left - 1
        if row != -1 or left:
            raise ValueError(f"the list of term {rows['term'][a].as_py()!r} is broken")
    return out


def flush_order(segments: DataFrame, events: DataFrame | None, cfg: IndexConfig, keys: tuple[str, ...] = ()) -> DataFrame:
    """Adds what orders the pool: is_final, then trigger document and place of the term there, or term id at the end.
    Without events, segments have their triggers."""
    out = segments
    if events is not None:
        out = segments.join(events.select(*keys, "term_id", "group_no", "trigger_doc", "trigger_pos"), [*keys, "term_id", "group_no"], "left")
    return out.withColumns({"is_final": F.col("trigger_doc").isNull(), "order_a": F.coalesce("trigger_doc", "term_id"), "order_b": F.coalesce("trigger_pos", F.lit(0).cast("long"))})


def place(segments: DataFrame, events: DataFrame | None, cfg: IndexConfig, keys: tuple[str, ...] = ()) -> DataFrame:
    """Adds addr: running sum of n_bytes in the order of writing (contiguous: by term and segment)."""
    if cfg.layout == "contiguous":
        return running_sum(segments, F.col("n_bytes"), list(keys), schedule.div(F.col("term_id"), RANGE), [F.col("term_id"), F.col("seg_no")], "addr").drop("trigger_doc", "trigger_pos")
    ordered = flush_order(segments, events, cfg, keys)
    bucket = schedule.div(F.col("order_a"), RANGE) + F.when(F.col("is_final"), F.lit(1 << 40)).otherwise(0)
    placed = running_sum(ordered, F.col("n_bytes"), list(keys), bucket, [F.col("is_final"), F.col("order_a"), F.col("order_b"), F.col("seg_no")], "addr")
    return placed.drop("is_final", "order_a", "order_b", "trigger_doc", "trigger_pos")


def link(placed: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Adds next_addr (null at the end), is_head and is_tail. A segment meets the one with the next number in an equi
    join, so no list is ordered as a whole."""
    after = placed.select(*(F.col(k).alias(f"_{k}") for k in keys), F.col("term_id").alias("_term_id"), (F.col("seg_no") - 1).alias("_seg_no"), F.col("addr").alias("next_addr"))
    on = (F.col("term_id") == F.col("_term_id")) & (F.col("seg_no") == F.col("_seg_no"))
    for k in keys:
        on = on & (F.col(k) == F.col(f"_{k}"))
    return placed.join(after, on, "left").select(*placed.columns, "next_addr", (F.col("seg_no") == 0).alias("is_head"), F.col("next_addr").isNull().alias("is_tail"))


def jumps(linked: DataFrame) -> DataFrame:
    """(links, jumps, jump_bytes): a jump is a next segment that doesn't lie right behind; its bytes are the distance."""
    gap = F.col("next_addr") - F.col("addr") - F.col("n_bytes")
    is_jump = (gap != 0).cast("long")
    return linked.agg(F.count("next_addr").alias("links"), F.coalesce(F.sum(is_jump), F.lit(0)).alias("jumps"), F.coalesce(F.sum(F.abs(gap)), F.lit(0)).alias("jump_bytes"))


def schedule_counts(dictionary: DataFrame, block: int, cap: int) -> DataFrame:
    """(segments, groups, largest group in segments) over all lists, from their lengths alone."""
    segs = F.ceil(F.col("df") / F.lit(block)).cast("long")
    groups = schedule.groups_of_list(F.col("df"), block, cap)
    tail = segs - F.when(groups > 1, schedule.group_end(groups - 2, block, cap) / F.lit(block)).otherwise(0).cast("long")
    largest = F.greatest(tail, F.when(groups > 1, schedule.power_of_two(F.least(groups - 2, F.lit(cap)))).otherwise(0))
    return dictionary.agg(F.sum(segs).alias("segments"), F.sum(groups).alias("groups"), F.count(F.lit(1)).alias("terms"), F.max(largest).alias("largest_group"))
