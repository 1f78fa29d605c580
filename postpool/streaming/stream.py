"""The incremental index as a stream: documents arrive, full buffers leave as groups of compressed segments.

A shard's terms are dealt to parts by hash, and state is a part's: its terms' buffered postings with positions, in chunks
of many terms that are appended as they come and rewritten only by a flush, and a few numbers a term (postings seen, last
document, first sight; what has been flushed follows from postings seen). A micro-batch makes a call for a part, and the
call handles its terms as arrays. A term's first buffer is no larger than the df threshold, and only terms that fill it
get into the final index. A group leaves when the buffer holds as many postings as the group has room for; what is left
when the stream ends is read from the state. Buffers are rows of numbers or, with codec 'vbyte', bytes of variable length.

Documents of a micro-batch are put in id order; a late document (an id below one already seen) is never dropped: it
takes the next number instead of its own id, as lists only grow.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..config import IndexConfig
from ..functions import analyze, codec, schedule
from ..operators import pool, postings as P, retrieval as R
from ..operators.numbering import numbered
from ..runtime import materialise, shuffle_partitions

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
#: A flushed segment; trigger: the posting that filled the buffer.
SEGMENT = "shard int, term string, seg_no long, group_no long, n_docs int, first_doc long, last_doc long, trigger_doc long, trigger_pos long, n_bytes long, d_block binary, f_block binary, p_blocks array<binary>"
NAMES = [c.split()[0] for c in SEGMENT.split(", ")]
NUMBERS = "n long, seen long, groups long, segments long, last long, first_doc long, first_pos long"
CHUNKS = "terms binary, chunk binary"
#: Parts of a shard. A checkpoint is bound to it.
PARTS = 256
#: Postings of a chunk, about, and of the documents that a task deals to parts together.
CHUNK, DEALT = 1 << 16, 1 << 20


def full_groups(seen: np.ndarray, cfg: IndexConfig) -> np.ndarray:
    """Groups that this many postings of a list have filled."""
    grown = cfg.block * ((2 << cfg.cap) - 1)
    small = np.searchsorted(cfg.block * (np.left_shift(1, np.arange(1, cfg.cap + 2)) - 1), seen, "right")
    return np.where(seen < grown, small, cfg.cap + 1 + (seen - grown) // (cfg.block << cfg.cap))


def group_ends(groups: np.ndarray, cfg: IndexConfig) -> np.ndarray:
    """Postings of the first so many groups."""
    return cfg.block * (np.left_shift(1, np.minimum(groups, cfg.cap + 1)) - 1 + np.maximum(groups - cfg.cap - 1, 0) * (1 << cfg.cap))


def squeeze(docs: list[int], positions: list[list[int]]) -> bytes:
    """Postings in variable bytes: how many, then for each the document, its tf and gaps of its positions."""
    numbers = [len(docs)]
    for doc, pos in zip(docs, positions):
        numbers += [doc, len(pos), *np.diff(pos, prepend=0).tolist()]
    return codec.vbyte_encode(np.array(numbers, np.int64))


def unsqueeze(chunk: bytes) -> Iterator[tuple[int, list[int]]]:
    numbers = codec.vbyte_decode(bytes(chunk)).tolist()
    at = 1
    for _ in range(numbers[0]):
        doc, tf = numbers[at], numbers[at + 1]
        yield doc, np.cumsum(numbers[at + 2 : at + 2 + tf]).tolist()
        at += 2 + tf


def starts_of(sizes: np.ndarray) -> np.ndarray:
    return np.cumsum(sizes) - sizes


def stretches(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Places of stretches of these sizes, one after the other."""
    return np.arange(sizes.sum()) + np.repeat(starts - starts_of(sizes), sizes)


@dataclass
class Lists:
    """Postings of many terms: how many each term has, then documents, tfs and gaps of positions, list after list."""

    terms: list[str]
    counts: np.ndarray
    docs: np.ndarray
    tfs: np.ndarray
    gaps: np.ndarray

    def picked(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(docs, tfs, gaps) of the postings at these places."""
        tfs = self.tfs[places]
        return self.docs[places], tfs, self.gaps[stretches(starts_of(self.tfs)[places], tfs)]

    def kept(self, there: np.ndarray) -> Lists:
        """Without the postings that aren't there, and without terms that have none left."""
        counts = np.bincount(np.repeat(np.arange(len(self.counts)), self.counts)[there], minlength=len(self.counts))
        return Lists([t for t, n in zip(self.terms, counts.tolist()) if n], counts[counts > 0], *self.picked(np.flatnonzero(there)))

    def cut(self, most: int = CHUNK) -> Iterator[Lists]:
        """In chunks of about so many postings; a list isn't cut."""
        ends = np.cumsum(self.counts)
        rows, terms = np.concatenate([[0], ends]), np.concatenate([[0], np.cumsum(self.tfs)])
        edges = [0, *(np.flatnonzero(np.diff(rows[:-1] // most)) + 1).tolist(), len(ends)] if len(ends) else [0]
        for a, z in zip(edges, edges[1:]):
            i, j = rows[a], rows[z]
            yield Lists(self.terms[a:z], self.counts[a:z], self.docs[i:j], self.tfs[i:j], self.gaps[terms[i] : terms[j]])

    def packed(self, buffer_codec: str) -> tuple[bytes, bytes]:
        """A CHUNKS row: terms, which have no line breaks, and numbers."""
        gaps = np.diff(self.docs, prepend=0)
        first = starts_of(self.counts)
        gaps[first] = self.docs[first] << 1 ^ self.docs[first] >> 63  # ids below 0 too
        sizes = [len(self.counts), len(self.docs)]
        if buffer_codec == "raw":
            parts = ((sizes, np.int64), (gaps, np.int64), (self.counts, np.int32), (self.tfs, np.int32), (self.gaps, np.int32))
            chunk = b"".join(np.asarray(v, t).tobytes() for v, t in parts)
        else:
            chunk = codec.vbyte_encode(np.concatenate([sizes, gaps, self.counts, self.tfs, self.gaps]))
        return "\n".join(self.terms).encode(), chunk

    @classmethod
    def unpacked(cls, terms: bytes, chunk: bytes, buffer_codec: str) -> Lists:
        if buffer_codec == "raw":
            n, m = np.frombuffer(chunk, np.int64, 2).tolist()
            gaps, rest = np.frombuffer(chunk, np.int64, m, 16), np.frombuffer(chunk, np.int32, offset=16 + 8 * m).astype(np.int64)
        else:
            numbers = codec.vbyte_decode(chunk)
            n, m = numbers[:2].tolist()
            gaps, rest = numbers[2 : 2 + m], numbers[2 + m :]
        counts, gaps = rest[:n], gaps.copy()
        first = starts_of(counts)
        gaps[first] = gaps[first] >> 1 ^ -(gaps[first] & 1)
        return cls(bytes(terms).decode().split("\n"), counts, pool.sums_within(gaps, counts), rest[n : n + m], rest[n + m :])


def gathered(parts: list[Lists]) -> Lists:
    """One list a term, by document; of one document the earlier part is first."""
    names = pa.array([t for p in parts for t in p.terms], pa.string()).dictionary_encode()
    counts = np.concatenate([p.counts for p in parts])
    owner = np.repeat(names.indices.to_numpy().astype(np.int64), counts)
    every = Lists([], counts, *(np.concatenate([getattr(p, c) for p in parts]) for c in ("docs", "tfs", "gaps")))
    order = np.lexsort((every.docs, owner))
    return Lists(names.dictionary.to_pylist(), np.bincount(owner, minlength=len(names.dictionary)), *every.picked(order))


#: Numbers of a term that a part keeps.
KEPT = ("seen", "last", "first_doc", "first_pos")


def known(row: tuple | None) -> tuple[list[str], np.ndarray]:
    """(terms, a row of KEPT for each) of a CHUNKS row."""
    if row is None:
        return [], np.zeros((0, len(KEPT)), np.int64)
    return bytes(row[0]).decode().split("\n"), np.frombuffer(row[1], np.int64).reshape(-1, len(KEPT))


class Buffers(StatefulProcessor):
    """The buffers of a part's terms."""

    def __init__(self, cfg: IndexConfig, buffer_codec: str = "raw"):
        self.cfg, self.codec = cfg, buffer_codec

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.numbers = handle.getValueState("numbers", CHUNKS)
        self.postings = handle.getListState("postings", CHUNKS)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        new = gathered([Lists.unpacked(t, c, "vbyte") for some in rows for t, c in zip(some["terms"], some["chunk"])])
        terms, numbers = known(self.numbers.get() if self.numbers.exists() else None)
        at = pc.index_in(pa.array(new.terms, pa.string()), value_set=pa.array(terms, pa.string())).fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)
        first = starts_of(new.counts)
        fresh = np.flatnonzero(at < 0)
        if len(fresh):
            at[fresh] = len(terms) + np.arange(len(fresh))
            terms = [*terms, *(new.terms[i] for i in fresh.tolist())]
            sight = new.gaps[starts_of(new.tfs)[first[fresh]]]
            numbers = np.concatenate([numbers, np.stack([np.zeros_like(sight), np.full_like(sight, -1), np.maximum(new.docs[first[fresh]], 0), sight], 1)])
        else:
            numbers = numbers.copy()
        seen, last = numbers[at, 0], numbers[at, 1]
        step = np.diff(new.docs, prepend=0)
        step[first] = new.docs[first] - last
        for i in np.unique(np.repeat(np.arange(len(first)), new.counts)[step <= 0]).tolist():  # lists with late documents
            own, place = new.docs[first[i] : first[i] + new.counts[i]], np.arange(new.counts[i])
            own[:] = np.maximum(np.maximum.accumulate(own - place), last[i] + 1) + place
        numbers[at, 0], numbers[at, 1] = seen + new.counts, new.docs[first + new.counts - 1]
        begin, end = full_groups(seen, self.cfg), full_groups(seen + new.counts, self.cfg)
        if (begin == end).all():
            self.postings.appendList([c.packed(self.codec) for c in new.cut()])
        else:
            begin, end = (dict(zip(new.terms, group_ends(g, self.cfg).tolist())) for g in (begin, end))
            held = [Lists.unpacked(t, c, self.codec) for t, c in self.postings.get()] if self.postings.exists() else []
            every = gathered([*held, new])
            low, leave = (np.array([ends.get(t, 0) for t in every.terms], np.int64) for ends in (begin, end))
            leave -= low
            there = np.arange(len(every.docs)) - np.repeat(starts_of(every.counts), every.counts) < np.repeat(leave, every.counts)
            rest = every.kept(~there)
            if len(rest.docs):
                self.postings.put([c.packed(self.codec) for c in rest.cut()])
            else:
                self.postings.clear()
            yield from self._segments(int(key[0]), every, there, low, leave)
        self.numbers.update(("\n".join(terms).encode(), numbers.tobytes()))

    def _segments(self, shard: int, every: Lists, there: np.ndarray, low: np.ndarray, leave: np.ndarray) -> Iterator[pd.DataFrame]:
        """SEGMENT rows of whole groups: so many postings of each list leave, after so many that have left before."""
        block = self.cfg.block
        out = every.kept(there)
        has = leave > 0
        many = leave[has] // block
        seg = np.repeat(low[has] // block, many) + np.arange(many.sum()) - np.repeat(starts_of(many), many)
        group = full_groups(seg * block, self.cfg)
        trigger = (np.arange(len(seg)) + group_ends(group + 1, self.cfg) // block - seg) * block - 1
        first_gap = out.gaps[starts_of(out.tfs)]
        lists = encoded(out.docs, out.tfs, out.gaps, np.full(len(seg), block), self.cfg)
        columns = {"shard": np.full(len(seg), shard, np.int32), "term": np.repeat(np.array(out.terms, object), many), "seg_no": seg, "group_no": group, "trigger_doc": out.docs[trigger], "trigger_pos": first_gap[trigger]}
        yield pd.DataFrame(columns | {n: c.to_pylist() for n, c in lists.items()})[NAMES]

    def close(self) -> None:
        pass


def encoded(docs: np.ndarray, tfs: np.ndarray, gaps: np.ndarray, sizes: np.ndarray, cfg: IndexConfig) -> dict[str, pa.Array]:
    """Segments of these sizes, one after the other: n_docs, first and last document, n_bytes and the compressed blocks."""
    ends, at = np.cumsum(sizes), np.concatenate([[0], np.cumsum(sizes)])
    lists = lambda v, edges: pa.ListArray.from_arrays(pa.array(edges, pa.int32()), pa.array(v, pa.int64()))
    size, blocks = pool.packed(lists(docs, at), lists(tfs, at), lists(gaps, np.concatenate([[0], np.cumsum(tfs)])[at]), cfg.block, cfg.positional)
    return {"n_docs": pa.array(sizes, pa.int32()), "first_doc": pa.array(docs[ends - sizes]), "last_doc": pa.array(docs[ends - 1]), "n_bytes": size, **dict(zip(("d_block", "f_block", "p_blocks"), blocks))}


def dealt(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(shard, part, CHUNKS) rows of (shard, doc_id, term, positions)."""
    held, n = [], 0
    for batch in it:
        held.append(batch)
        n += batch.num_rows
        if n >= DEALT:
            yield _deal(pa.Table.from_batches(held))
            held, n = [], 0
    if n:
        yield _deal(pa.Table.from_batches(held))


def _deal(rows: pa.Table) -> pa.RecordBatch:
    shard, docs = (rows[c].to_numpy().astype(np.int64) for c in ("shard", "doc_id"))
    names = rows["term"].combine_chunks()
    names = (names.chunk(0) if isinstance(names, pa.ChunkedArray) else names).dictionary_encode()
    part = np.array([zlib.crc32(t.encode()) % PARTS for t in names.dictionary.to_pylist()], np.int64)
    code = names.indices.to_numpy().astype(np.int64)
    key = shard * PARTS + part[code]
    order = np.lexsort((docs, code, key))
    positions = [c for c in rows["positions"].chunks if len(c)]
    tfs = np.concatenate([np.diff(c.offsets.to_numpy()) for c in positions]).astype(np.int64)
    places = np.concatenate([c.flatten().to_numpy(zero_copy_only=False) for c in positions]).astype(np.int64)
    gaps = np.diff(places, prepend=0)
    gaps[starts_of(tfs)] = places[starts_of(tfs)]
    key, code = key[order], code[order]
    docs, tfs, gaps = Lists([], tfs, docs, tfs, gaps).picked(order)
    heads = np.flatnonzero((np.diff(key, prepend=-1) != 0) | (np.diff(code, prepend=-1) != 0))
    terms = names.dictionary.take(pa.array(code[heads])).to_pylist()
    every = Lists(terms, np.diff(heads, append=len(code)), docs, tfs, gaps)
    keys = key[heads]
    edges = [*np.flatnonzero(np.diff(keys, prepend=-1)).tolist(), len(keys)]
    ends = np.concatenate([heads, [len(code)]])
    at = np.concatenate([[0], np.cumsum(tfs)])
    out = []
    for a, z in zip(edges, edges[1:]):
        i, j = ends[a], ends[z]
        one = Lists(terms[a:z], every.counts[a:z], docs[i:j], tfs[i:j], gaps[at[i] : at[j]])
        out.append((int(keys[a]) // PARTS, int(keys[a]) % PARTS, *one.packed("vbyte")))
    kinds = (pa.int32(), pa.int32(), pa.binary(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=["shard", "part", "terms", "chunk"])


def index_stream(docs: DataFrame, cfg: IndexConfig, per_shard: int | None = None, buffer_codec: str = "raw") -> DataFrame:
    """SEGMENT rows of a stream of (doc_id, text), as buffers fill."""
    occ = docs.select("doc_id", analyze.row_postings(analyze.words(F.col("text"))).alias("occ"))
    rows = occ.select("doc_id", F.inline(analyze.cut(F.col("occ")))).select(P.shard_of(F.col("doc_id"), per_shard).alias("shard"), "doc_id", "term", "positions")
    parts = rows.mapInArrow(dealt, f"shard int, part int, {CHUNKS}")
    return parts.groupBy("shard", "part").transformWithStateInPandas(Buffers(cfg, buffer_codec), SEGMENT, "append", "none")


def run(docs: DataFrame, cfg: IndexConfig, out: str, checkpoint: str, per_shard: int | None = None, buffer_codec: str = "raw") -> None:
    """Run to the end of what is there; a later call with the same folders goes on from the state. Parts are dealt to no
    more tasks than there are cores, as each task has a state store with files of its own."""
    spark = docs.sparkSession
    tasks = min(shuffle_partitions(spark), spark.sparkContext.defaultParallelism)
    settings = {"spark.sql.streaming.stateStore.providerClass": ROCKS, "spark.sql.shuffle.partitions": str(tasks)}
    before = {k: spark.conf.get(k, None) for k in settings}
    try:
        for k, v in settings.items():
            spark.conf.set(k, v)
        q = index_stream(docs, cfg, per_shard, buffer_codec).writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        for k, v in before.items():
            spark.conf.set(k, v) if v else spark.conf.unset(k)


def flushed(spark: SparkSession, out: str) -> DataFrame:
    return spark.read.schema(SEGMENT).parquet(out)


def _state(spark: SparkSession, checkpoint: str, name: str) -> DataFrame:
    """(shard, part, CHUNKS) rows of a stopped stream's state, which may be another session's."""
    spark.streams  # starts the coordinator that readers of state ask
    state = spark.read.format("statestore").option("stateVarName", name)
    if name == "numbers":
        return state.load(checkpoint).select("key.*", "value.*")
    return state.option("flattenCollectionTypes", True).load(checkpoint).select("key.*", "list_element.*")


def numbers(spark: SparkSession, checkpoint: str, cfg: IndexConfig) -> DataFrame:
    """(shard, term, NUMBERS) of every term that the stream has seen."""

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for row in batch.to_pylist():
                terms, kept = known((row["terms"], row["chunk"]))
                seen, last, first_doc, first_pos = kept.T
                groups = full_groups(seen, cfg)
                left = group_ends(groups, cfg)
                columns = (seen - left, seen, groups, left // cfg.block, last, first_doc, first_pos)
                names = ["shard", "term", *(c.split()[0] for c in NUMBERS.split(", "))]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(terms), row["shard"]), pa.int32()), pa.array(terms, pa.string()), *(pa.array(c, pa.int64()) for c in columns)], names=names)

    return _state(spark, checkpoint, "numbers").mapInArrow(kernel, f"shard int, term string, {NUMBERS}")


def buffered(spark: SparkSession, checkpoint: str, buffer_codec: str = "raw") -> DataFrame:
    """(shard, term, doc_id, tf, positions): postings that are in buffers, from the state of a stopped stream."""

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for row in batch.to_pylist():
                held = Lists.unpacked(row["terms"], row["chunk"], buffer_codec)
                terms = pa.array(held.terms, pa.string()).take(pa.array(np.repeat(np.arange(len(held.terms)), held.counts)))
                places = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(held.tfs)]), pa.int32()), pa.array(pool.sums_within(held.gaps, held.tfs), pa.int32()))
                columns = [pa.array(np.full(len(terms), row["shard"]), pa.int32()), terms, pa.array(held.docs, pa.int64()), pa.array(held.tfs, pa.int32()), places]
                yield pa.RecordBatch.from_arrays(columns, names=["shard", "term", "doc_id", "tf", "positions"])

    return _state(spark, checkpoint, "postings").mapInArrow(kernel, "shard int, term string, doc_id long, tf int, positions array<int>")


def state_bytes(spark: SparkSession, checkpoint: str, buffer_codec: str = "raw") -> DataFrame:
    """(buffer_bytes): what buffered values take, 4 bytes a number or as coded."""
    if buffer_codec == "raw":
        rows = buffered(spark, checkpoint)
        return rows.agg(F.coalesce(F.sum(8 + 4 * F.size("positions")), F.lit(0)).alias("buffer_bytes"))
    return _state(spark, checkpoint, "postings").agg(F.coalesce(F.sum(F.length("chunk")), F.lit(0)).cast("long").alias("buffer_bytes"))


def last_flush(spark: SparkSession, checkpoint: str, cfg: IndexConfig, buffer_codec: str = "raw") -> DataFrame:
    """SEGMENT rows of what buffers of kept terms hold, without triggers: a part's lists are cut where they lie."""
    names = [n for n in NAMES if n not in ("trigger_doc", "trigger_pos")]
    schema = ", ".join(c for c in SEGMENT.split(", ") if c.split()[0] in names)
    kinds = dict(zip(names, (pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.list_(pa.binary()))))

    def kernel(key: tuple, held: pa.Table, about: pa.Table) -> pa.Table:
        if not held.num_rows:
            return pa.table({n: pa.array([], k) for n, k in kinds.items()})
        every = gathered([Lists.unpacked(r["terms"], r["chunk"], buffer_codec) for r in held.to_pylist()])
        terms, kept = known((about["terms"][0].as_py(), about["chunk"][0].as_py()))
        seen = kept[pc.index_in(pa.array(every.terms, pa.string()), value_set=pa.array(terms, pa.string())).to_numpy(), 0]
        keep = seen >= cfg.df_threshold
        every, seen = every.kept(np.repeat(keep, every.counts)), seen[keep]
        group = full_groups(seen, cfg)
        many = -(-every.counts // cfg.block)
        place = np.arange(many.sum()) - np.repeat(starts_of(many), many)
        sizes = np.minimum(cfg.block, np.repeat(every.counts, many) - cfg.block * place)
        owner = np.repeat(np.arange(len(many)), many)
        columns = encoded(every.docs, every.tfs, every.gaps, sizes, cfg) | {"shard": np.full(len(owner), key[0].as_py()), "term": pa.array(every.terms, pa.string()).take(pa.array(owner)), "seg_no": (group_ends(group, cfg) // cfg.block)[owner] + place, "group_no": group[owner]}
        return pa.table({n: columns[n] if isinstance(columns[n], pa.Array) else pa.array(columns[n], k) for n, k in kinds.items()})

    held, about = (_state(spark, checkpoint, n).groupBy("shard", "part") for n in ("postings", "numbers"))
    return held.cogroup(about).applyInArrow(kernel, schema)


def finish(spark: SparkSession, out: str, checkpoint: str, cfg: IndexConfig, buffer_codec: str = "raw") -> tuple[DataFrame, DataFrame]:
    """(dictionary, segments) of the whole index: flushed segments and the final flush of terms that reached the df
    threshold, with ids by first sight, addresses in flush order, and links. A term that the threshold drops never filled
    a block, so nothing of it is in the pool."""
    kept = numbers(spark, checkpoint, cfg).where(F.col("seen") >= cfg.df_threshold)
    dictionary = numbered(kept.withColumnRenamed("seen", "df"), ["shard"], schedule.div(F.col("first_doc"), P.RANGE), [F.col("first_doc"), F.col("first_pos")], "term_id")
    none = F.lit(None).cast("long")
    dictionary = materialise(dictionary, "stream-dictionary")
    last = materialise(last_flush(spark, checkpoint, cfg, buffer_codec), "last-flush").withColumns({"trigger_doc": none, "trigger_pos": none}).select(*NAMES)
    segments = flushed(spark, out).select(*NAMES).unionByName(last)
    thin = segments.select("shard", "term", "seg_no", "group_no", "n_bytes", "trigger_doc", "trigger_pos").join(dictionary.select("shard", "term", "term_id"), ["shard", "term"])
    placed = materialise(pool.place(thin, None, cfg, ("shard",)), "stream-placed")  # blocks are moved once, for all this
    linked = pool.link(placed, ("shard",))
    ends = linked.groupBy("shard", "term_id").agg(F.max(F.when(F.col("is_head"), F.col("addr"))).alias("head_addr"), F.max(F.when(F.col("is_tail"), F.col("addr"))).alias("tail_addr"))
    dictionary = dictionary.join(ends, ["shard", "term_id"]).select("shard", "term", "term_id", "df", "first_doc", "first_pos", "head_addr", "tail_addr")
    return dictionary, segments.drop("trigger_doc", "trigger_pos").join(linked.drop("group_no", "n_bytes"), ["shard", "term", "seg_no"])


def visible(spark: SparkSession, out: str, checkpoint: str, cfg: IndexConfig, buffer_codec: str = "raw") -> DataFrame:
    """(term, doc_id, tf): what a query sees between two micro-batches: flushed segments, decoded, and live buffers. The
    cost is that of segments and buffers; no log of postings is kept."""
    written = pool.decode(flushed(spark, out), positions=False).select("term", "doc_id", "tf")
    live = buffered(spark, checkpoint, buffer_codec).select("term", "doc_id", "tf")
    return written.unionByName(live)


def answers(spark: SparkSession, out: str, checkpoint: str, cfg: IndexConfig, queries: DataFrame, buffer_codec: str = "raw") -> DataFrame:
    """(query_id, doc_id): conjunctive answers at this moment. Only terms over the df threshold are in the dictionary;
    segments and buffers of other terms than the queries' are left where they are."""
    used = queries.select(F.explode("terms").alias("term")).distinct()
    kept = numbers(spark, checkpoint, cfg).where(F.col("seen") >= cfg.df_threshold).groupBy("term").agg(F.count(F.lit(1)).alias("shards")).join(F.broadcast(used), "term", "left_semi").select("term")
    written = flushed(spark, out).join(F.broadcast(used), "term", "left_semi")
    live = buffered(spark, checkpoint, buffer_codec).join(F.broadcast(used), "term", "left_semi").select("term", "doc_id")
    rows = pool.decode(written, positions=False).select("term", "doc_id").unionByName(live).join(kept, "term", "left_semi")
    return R.intersect(rows, queries)


#: Row groups of a file that documents arrive in: small ones, so that many tasks read a file.
ROW_GROUP = 2 << 20


def split_for_stream(docs: DataFrame, path: str, files: int) -> None:
    """Write documents as `files` files of id ranges, one after the other, as a file source replays by time of writing.
    A range is one file, as a micro-batch of several could be cut anywhere and its ids come late."""
    low, high = docs.agg(F.min("doc_id"), F.max("doc_id")).first()
    low, high = low or 0, high or 0
    width = -(-(high - low + 1) // files)
    for i in range(files):
        part = docs.where(F.col("doc_id").between(low + i * width, low + (i + 1) * width - 1))
        part.repartition(1).sortWithinPartitions("doc_id").write.mode("append").option("parquet.block.size", ROW_GROUP).parquet(path)
