"""Other index designs: full-flush runs and their merges with compressed segments, and in-place lists as folds and
counters over the same lists."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..config import IndexConfig
from ..functions import schedule
from ..runtime import materialise
from . import pool
from .numbering import numbered, running_sum
from .postings import RANGE


def runs_of(postings: DataFrame, budget: int) -> DataFrame:
    """(doc_id, n, run): memory holds `budget` postings; when it is full everything is written as a run."""
    docs = postings.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    counted = running_sum(docs, F.col("n"), [], schedule.div(F.col("doc_id"), RANGE), [F.col("doc_id")], "before")
    return counted.select("doc_id", "n", F.floor(F.col("before") / F.lit(budget)).cast("long").alias("run"))


def full_flush(postings: DataFrame, budget: int) -> DataFrame:
    """(run, first_doc, last_doc, terms, postings) of each run."""
    runs = runs_of(postings, budget)
    rows = postings.select("doc_id", "term").join(runs.select("doc_id", "run"), "doc_id")
    by_term = rows.groupBy("run", "term").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("a"), F.max("doc_id").alias("z"))
    return by_term.groupBy("run").agg(F.min("a").alias("first_doc"), F.max("z").alias("last_doc"), F.count(F.lit(1)).alias("terms"), F.sum("n").alias("postings"))


RUN_SEGMENT = "run long, term string, seg_no long, n_docs int, first_doc long, last_doc long, n_bytes long, d_block binary, f_block binary, p_blocks array<binary>"


def _numbered(it: Iterator[pa.RecordBatch], block: int) -> Iterator[pa.Table]:
    """Sorted postings (key, term, doc_id, tf, positions) with the seg_no that their place in their list gives."""
    held, before = None, 0
    for batch in it:
        if not batch.num_rows:
            continue
        fresh = _changes([batch.column(0), batch.column(1)])
        starts = np.flatnonzero(fresh)
        place = np.arange(len(fresh)) - np.repeat(starts, np.diff([*starts, len(fresh)]))
        if (batch.column(0)[0].as_py(), batch.column(1)[0].as_py()) == held:
            place[: starts[1] if len(starts) > 1 else None] += before
        held, before = (batch.column(0)[-1].as_py(), batch.column(1)[-1].as_py()), int(place[-1]) + 1
        yield pa.table([batch.column(0), batch.column(1), pa.array(place // block, pa.int64()), *batch.columns[2:5]], names=POSTING)


POSTING = ["key", "term", "seg_no", "doc_id", "tf", "positions"]


def _changes(columns: list) -> np.ndarray:
    """Where a row differs from the one before; the first does."""
    out = np.zeros(len(columns[0]), bool)
    out[0] = True
    for c in columns:
        out[1:] |= pc.not_equal(c[1:], c[:-1]).to_numpy(zero_copy_only=False)
    return out


def _written(tables: Iterator[pa.Table], key: str, cfg: IndexConfig) -> Iterator[pa.RecordBatch]:
    """RUN_SEGMENT rows of POSTING rows that come sorted: a task holds one Arrow batch and at most a block beside it."""
    rest = None

    def done(t: pa.Table, starts: np.ndarray) -> pa.RecordBatch:
        t = t.combine_chunks()
        column = lambda c: t[c].combine_chunks() if isinstance(t[c], pa.ChunkedArray) else t[c]
        at = pa.array([*starts, len(t)], pa.int32())
        docs, tfs, first = column("doc_id"), column("tf"), pa.array(starts)
        p = column("positions")
        counts = np.diff(p.offsets.to_numpy())
        places = p.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
        gaps = np.diff(places, prepend=0)
        begin = (np.cumsum(counts) - counts)[counts > 0]
        gaps[begin] = places[begin]
        ends = np.concatenate([[0], np.cumsum(counts)])[at.to_numpy()]
        size, blocks = pool.packed(pa.ListArray.from_arrays(at, docs), pa.ListArray.from_arrays(at, tfs), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(gaps)), cfg.block, cfg.positional)
        last = pa.array(at.to_numpy()[1:] - 1)
        columns = [column("key").take(first), column("term").take(first), column("seg_no").take(first), pa.array(np.diff(at.to_numpy()), pa.int32()), docs.take(first), docs.take(last), size, *blocks]
        return pa.RecordBatch.from_arrays(columns, names=[key, *(c.split()[0] for c in RUN_SEGMENT.split(", ")[1:])])

    for table in tables:
        if not len(table):
            continue
        table = table if rest is None else pa.concat_tables([rest, table])
        starts = np.flatnonzero(_changes([table[c].combine_chunks() for c in ("key", "term", "seg_no")]))
        if len(starts) > 1:
            yield done(table.slice(0, int(starts[-1])), starts[:-1])
        rest = table.slice(int(starts[-1]))
    if rest is not None:
        yield done(rest, np.zeros(1, np.int64))


def write_runs(postings: DataFrame, cfg: IndexConfig, budget: int) -> DataFrame:
    """RUN_SEGMENT rows: whenever memory holds `budget` postings, all lists so far are compressed and written as a run.
    A list of a run streams through a task, and is no longer than the budget."""
    runs = runs_of(postings, budget).select("doc_id", "run")
    rows = postings.join(runs, "doc_id").select("run", "term", "doc_id", "tf", "positions")
    rows = rows.repartition("run", "term").sortWithinPartitions("run", "term", "doc_id")
    block = cfg.block
    return materialise(rows.mapInArrow(lambda it: _written(_numbered(it, block), "run", cfg), RUN_SEGMENT), "runs")


#: Blocks of a list that a merge writes in one go; longer lists are merged in such parts.
PART = 64


def merge_runs(runs: DataFrame, plan: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Segments by `target`, of (target, run): a merge reads the blocks of its runs, and compresses the joined lists
    anew. Merges of a plan are independent of each other, as each goes back to its runs; what it reads and writes is
    what a merge of earlier targets would.

    Runs are document ranges, so that a posting's rank in the merged list is its rank in its run's plus the lengths of
    the runs before. Compressed blocks move, by target, term and part of the list; no posting is shuffled. A block that
    lies in two parts goes to both, and each takes its own of it."""
    wide = PART * cfg.block
    counts = runs.groupBy("run", "term").agg(F.sum("n_docs").alias("n")).join(plan.select("target", "run"), "run")
    before = F.coalesce(F.sum("n").over(Window.partitionBy("target", "term").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rank = F.col("before") + F.col("seg_no") * cfg.block
    rows = runs.select("run", "term", "seg_no", "n_docs", "d_block", "f_block", "p_blocks").join(counts.select("target", "run", "term", before.alias("before")), ["run", "term"]).withColumn("rank", rank)
    part = F.sequence(schedule.div(F.col("rank"), wide), schedule.div(F.col("rank") + F.col("n_docs") - 1, wide))
    rows = rows.select("target", "term", F.explode(part).alias("part"), "rank", "seg_no", "d_block", "f_block", "p_blocks")
    rows = rows.repartition("target", "term", "part").sortWithinPartitions("target", "term", "part", "rank")

    def opened(it: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
        for whole in it:
            for start in range(0, whole.num_rows, pool.SLICE):
                batch = whole.slice(start, pool.SLICE)
                rows = pool.unpacked(batch, cfg.positional, ("target", "part", "rank"))
                part, rank = (rows.column(i).to_numpy() for i in (1, 2))
                n = np.diff(np.flatnonzero([*_changes([rows.column(i) for i in (0, 1, 2, 3)]), True])) if rows.num_rows else np.zeros(0, np.int64)
                rank = rank + np.arange(len(rank)) - np.repeat(np.cumsum(n) - n, n)
                own = pa.array(rank // wide == part)
                columns = [rows.column(0), rows.column(3), pa.array(rank // cfg.block, pa.int64()), *(rows.column(i) for i in (5, 6, 7))]
                yield pa.table(columns, names=POSTING).filter(own)

    return materialise(rows.mapInArrow(lambda it: _written(opened(it), "target", cfg), RUN_SEGMENT.replace("run", "target", 1)), "merged")


def full_flush_index(postings: DataFrame, cfg: IndexConfig, budget: int) -> tuple[DataFrame, DataFrame]:
    """(runs, merged): one merge of all runs at the end; lists are then whole."""
    runs = write_runs(postings, cfg, budget)
    return runs, merge_runs(runs, runs.select(F.lit(0).cast("long").alias("target"), "run").distinct(), cfg)


def geometric_index(postings: DataFrame, cfg: IndexConfig, budget: int, ratio: int = 3) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(runs, merged, log): merges as `geometric_merges` schedules them, a target for each, named by its last run; the
    log says which targets stay. Lists are as many pieces as there are partitions in the end."""
    runs = write_runs(postings, cfg, budget)
    counts = runs.groupBy("run").agg(F.sum("n_docs").alias("postings"))
    log = materialise(geometric_merges(counts, ratio), "merges")
    plan = log.select(F.col("run").alias("target"), F.explode(F.sequence(F.col("first_run"), F.col("run"))).alias("run"))
    return runs, merge_runs(runs, plan, cfg), log


def merged_runs(postings: DataFrame, budget: int) -> DataFrame:
    """(term, doc_id, rank): the final merge concatenates a term's runs in run order; document ranges don't overlap, so
    ranks follow from documents and no list is ordered as a whole."""
    rows = postings.join(runs_of(postings, budget).select("doc_id", "run"), "doc_id")
    return numbered(rows, ["term"], schedule.div(F.col("doc_id"), RANGE), [F.col("doc_id")], "rank", first=1)


def term_churn(postings: DataFrame, budgets: list[int]) -> DataFrame:
    """(budget, run, terms_touched, terms_once): how many terms a buffered document range touches, and touches once."""
    out = None
    for budget in budgets:
        rows = postings.select("doc_id", "term").join(runs_of(postings, budget).select("doc_id", "run"), "doc_id")
        by_term = rows.groupBy("run", "term").agg(F.count(F.lit(1)).alias("n"))
        one = by_term.groupBy("run").agg(F.count(F.lit(1)).alias("terms_touched"), F.sum((F.col("n") == 1).cast("long")).alias("terms_once")).withColumn("budget", F.lit(budget).cast("long"))
        out = one if out is None else out.unionByName(one)
    return out.select("budget", "run", "terms_touched", "terms_once")


def geometric_merges(runs: DataFrame, ratio: int = 3) -> DataFrame:
    """(run, target_partition, postings_rewritten, first_run, stays) of (run, postings), runs in order of their number;
    first_run is the first of those merged, and stays says that no later merge takes the result.

    Partition j holds at most (ratio-1) * ratio**(j-1) runs, so that the n-th run cascades as far as n has trailing
    zeros in base `ratio`, and the partition it lands in then holds the last n mod ratio**j runs."""
    rows = numbered(runs.select("run", "postings"), [], schedule.div(F.col("run"), RANGE), [F.col("run")], "n", first=1)
    zeros = F.size(F.filter(F.sequence(F.lit(1), F.lit(39 if ratio == 3 else 30)), lambda i: F.col("n") % F.pow(F.lit(ratio), i).cast("long") == 0))
    rows = rows.withColumn("target_partition", (zeros + 1).cast("long"))
    rows = rows.withColumn("held", F.col("n") % F.pow(F.lit(ratio), F.col("target_partition")).cast("long"))
    rows = running_sum(rows, F.col("postings"), [], schedule.div(F.col("n"), RANGE), [F.col("n")], "before")
    start = rows.select((F.col("n") - 1).alias("start"), F.col("before").alias("base"), F.col("run").alias("first_run"))  # run numbers may have gaps
    out = rows.withColumn("start", F.col("n") - F.col("held")).join(start, "start")
    total = rows.agg(F.max("n").alias("total"))
    alive = F.floor(F.col("total") / F.pow(F.lit(ratio), F.col("target_partition") - 1)) * F.pow(F.lit(ratio), F.col("target_partition") - 1)
    return out.join(F.broadcast(total)).select("run", "target_partition", (F.col("before") + F.col("postings") - F.col("base")).alias("postings_rewritten"), "first_run", (F.col("n") == alive).alias("stays"))


def _lists(segments: DataFrame) -> list[str]:
    """A list is a term's in one shard: each shard has a pool of its own."""
    return [c for c in ("shard", "term") if c in segments.columns]


def remerge(segments: DataFrame) -> DataFrame:
    """(term, bytes_copied): at each flush of a group the list so far moves to a new region."""
    keys = _lists(segments)
    groups = segments.groupBy(*keys, "group_no").agg(F.sum("n_bytes").alias("b"))
    moved = running_sum(groups, F.col("b"), keys, schedule.div(F.col("group_no"), RANGE), [F.col("group_no")], "old")
    return moved.groupBy("term").agg(F.sum("old").alias("bytes_copied"))


def in_place(segments: DataFrame, slack) -> DataFrame:
    """(term, reserved, used, wasted, relocations, copied): free space of slack(used) bytes is left behind a list; a
    segment that doesn't fit moves the list. A fold over the sizes of one shard's segments of a term; sums over shards."""
    keys = _lists(segments)
    sizes = segments.groupBy(*keys).agg(F.transform(F.sort_array(F.collect_list(F.struct("seg_no", "n_bytes"))), lambda s: s["n_bytes"]).alias("sizes"))
    zero = F.lit(0).cast("long")
    state = lambda r, u, n, c: F.struct(r.cast("long").alias("reserved"), u.cast("long").alias("used"), n.cast("long").alias("relocations"), c.cast("long").alias("copied"))

    def step(s: Column, size: Column) -> Column:
        used = s["used"] + size
        moved = state(used + slack(used), used, s["relocations"] + F.when(s["used"] > 0, 1).otherwise(0), s["copied"] + s["used"])
        return F.when(used <= s["reserved"], state(s["reserved"], used, s["relocations"], s["copied"])).otherwise(moved)

    done = sizes.select("term", F.aggregate("sizes", state(zero, zero, zero, zero), step).alias("s"))
    done = done.groupBy("term").agg(*(F.sum(f"s.{c}").alias(c) for c in ("reserved", "used", "relocations", "copied")))
    return done.select("term", "reserved", "used", (F.col("reserved") - F.col("used")).alias("wasted"), "relocations", "copied")


def unbounded_buffers(segments: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Placed and linked segments if buffers hold everything: nothing is flushed before the end, and the final flush
    writes each list as one group."""
    thin = segments.select("shard", "term", "term_id", "seg_no", F.lit(0).cast("long").alias("group_no"), "n_bytes")
    none = segments.select("shard", "term_id", F.lit(0).cast("long").alias("group_no"), F.lit(0).cast("long").alias("trigger_doc"), F.lit(0).cast("long").alias("trigger_pos")).where(F.lit(False))
    return pool.link(pool.place(thin, none, cfg, ("shard",)), ("shard",))


def adjacent_groups(linked: DataFrame) -> DataFrame:
    """(term, segments, groups): how many stretches of side by side segments a list is laid out in."""
    apart = F.col("next_addr").isNull() | (F.col("next_addr") != F.col("addr") + F.col("n_bytes"))
    return linked.groupBy("term").agg(F.count(F.lit(1)).alias("segments"), F.sum(apart.cast("long")).alias("groups"))


def eager(segments: DataFrame) -> DataFrame:
    """Every list reserves what the longest needs; nothing moves."""
    used = segments.groupBy("term").agg(F.sum("n_bytes").alias("used"))
    most = used.agg(F.max("used").alias("reserved"))
    zero = F.lit(0).cast("long")
    return used.join(F.broadcast(most)).select("term", "reserved", "used", (F.col("reserved") - F.col("used")).alias("wasted"), zero.alias("relocations"), zero.alias("copied"))


def size_classes(segments: DataFrame) -> DataFrame:
    """(allocated, used, wasted): a heap allocation for each segment, rounded up to a power of two."""
    up = schedule.power_of_two(F.length(F.bin(F.col("n_bytes") - 1)))
    return segments.agg(F.sum(up).alias("allocated"), F.sum("n_bytes").alias("used"), (F.sum(up) - F.sum("n_bytes")).alias("wasted"))
