import numpy as np
import pytest
from pyspark.sql import functions as F

from postpool.config import IndexConfig
from postpool.functions import codec
from postpool.operators import baselines, pool, postings as P
from postpool.operators.index import build_index
from postpool.sources.io import read_table

from .sim import simulate, words


@pytest.mark.parametrize("block, cap", [(8, 0), (16, 3), (128, 5)])
def test_batch_equals_loop(spark, sf, block, cap):
    docs = read_table(spark, sf, "documents")
    threshold = min(10, block)  # the small first buffer is no larger than a block
    ix = build_index(docs, IndexConfig(block=block, cap_log2=cap, df_threshold=threshold))
    dictionary, segments = simulate([(r.doc_id, r.text) for r in docs.orderBy("doc_id").collect()], block, cap, threshold)
    kept = [s for s in segments if s["term"] in dictionary]
    assert {r.term: (r.term_id, r.df) for r in ix.dictionary.collect()} == dictionary
    assert len(kept) == len(segments)  # a term that fills a buffer is kept
    got = {(r.term, r.seg_no): r for r in ix.segments.collect()}
    assert len(got) == len(kept)
    for s in kept:
        r = got[s["term"], s["seg_no"]]
        assert (r.group_no, r.addr, r.next_addr, r.n_bytes) == (s["group_no"], s["addr"], s["next_addr"], s["n_bytes"])
        assert (bytes(r.d_block), bytes(r.f_block), [bytes(p) for p in r.p_blocks]) == s["blocks"]


def test_pool_is_tight(spark, sf):
    ix = build_index(read_table(spark, sf, "documents"), IndexConfig(block=8, cap_log2=2, df_threshold=8))
    for segs in (ix.segments, ix.relaid("linked", 0), ix.relaid("contiguous")):
        rows = sorted((r.addr, r.n_bytes) for r in segs.collect())
        assert rows[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(rows, rows[1:]))
        blanks = segs.groupBy("term").agg(F.sum(F.col("next_addr").isNull().cast("int")).alias("n")).where("n <> 1")
        assert blanks.isEmpty() and segs.where("next_addr <= addr").isEmpty()
    assert pool.jumps(ix.relaid("contiguous")).first().jumps == 0


def test_every_layout_has_the_same_lists(spark, sf):
    ix = build_index(read_table(spark, sf, "documents"), IndexConfig(block=8, cap_log2=2))
    rows = lambda df: sorted((r.term, r.doc_id, r.tf, tuple(r.positions)) for r in df.collect())
    truth = rows(ix.postings)
    for segs in (ix.segments, ix.relaid("linked", 0), ix.relaid("contiguous")):
        assert rows(pool.decode(segs)) == truth


def test_a_broken_list_is_noticed(spark, sf):
    ix = build_index(read_table(spark, sf, "documents"), IndexConfig(block=8, cap_log2=2))
    rows = lambda df: sorted((r.term, r.doc_id, r.tf, tuple(r.positions)) for r in df.collect())
    assert rows(pool.traverse(ix.segments)) == rows(ix.postings)
    longest = ix.segments.groupBy("term").count().orderBy(F.desc("count")).first().term
    cut = ix.segments.withColumn("next_addr", F.when((F.col("term") == longest) & (F.col("seg_no") == 1), None).otherwise(F.col("next_addr")))
    with pytest.raises(Exception, match="broken"):
        pool.traverse(cut).count()
    loop = ix.segments.withColumn("next_addr", F.when((F.col("term") == longest) & (F.col("seg_no") == 2), F.col("addr")).otherwise(F.col("next_addr")))
    with pytest.raises(Exception, match="broken"):
        pool.traverse(loop).count()


@pytest.mark.parametrize("cap", [0, 1, 3])
def test_events_of_segments(spark, sf, cap):
    """Triggers read off segments are those of the postings."""
    cfg = IndexConfig(block=8, cap_log2=cap)
    ix = build_index(read_table(spark, sf, "documents"), cfg, encode=False)
    rows = lambda df: sorted(map(tuple, df.select("term", "group_no", "trigger_doc", "trigger_pos").collect()))
    assert rows(pool.events_of_segments(ix.blocks, cfg)) == rows(pool.flush_events(ix.postings, cfg))


@pytest.mark.parametrize("overflow", ["truncate", "drop"])
def test_short_positions(spark, sf, overflow):
    docs = read_table(spark, sf, "documents")
    ix = build_index(docs, IndexConfig(block=16, df_threshold=1, pos_bits=8, overflow=overflow), encode=False)
    want = {r.doc_id: len(words(r.text)) for r in docs.collect()}
    got = {r.doc_id: r.doc_len for r in ix.stats.collect()}
    assert max(want.values()) > 255 and got == {d: n if n <= 255 else 255 if overflow == "truncate" else 0 for d, n in want.items()}
    assert ix.postings.agg(F.max(F.array_max("positions"))).first()[0] <= 255


def test_threshold_edges(spark):
    docs = spark.createDataFrame([(i, " ".join(w for w, n in (("nine", 9), ("ten", 10), ("eleven", 11)) if i < n)) for i in range(12)], "doc_id long, text string")
    d = P.build_dictionary(P.build_postings(docs), IndexConfig(df_threshold=10))
    assert {r.term: r.term_id for r in d.collect()} == {"ten": 0, "eleven": 1}


def test_empty_and_null_documents(spark):
    cfg = IndexConfig(block=8, df_threshold=1)
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert build_index(empty, cfg).segments.isEmpty()
    docs = spark.createDataFrame([(0, None), (1, ""), (2, "a b a"), (3, "!!")], "doc_id long, text string")
    ix = build_index(docs, cfg)
    assert {r.term: r.df for r in ix.dictionary.collect()} == {"a": 1, "b": 1}
    assert {r.doc_id: r.doc_len for r in ix.stats.collect()} == {0: 0, 1: 0, 2: 3, 3: 0}


@pytest.mark.parametrize("shards", [1, 3, 8])
def test_shards_add_up(spark, sf, shards):
    docs = read_table(spark, sf, "documents")
    ix = build_index(docs, IndexConfig(block=16, n_shards=shards), encode=False)
    whole = {r.term: r.df for r in ix.dictionary.collect()}
    parts = ix.postings.groupBy("term").agg(F.count(F.lit(1)).alias("n")).collect()
    assert whole == {r.term: r.n for r in parts}
    assert ix.postings.select("shard").distinct().count() == shards


def test_first_sight_order(spark, sf):
    docs = [(r.doc_id, r.text) for r in read_table(spark, sf, "documents").orderBy("doc_id").collect()]
    seen = list(dict.fromkeys(w for _, t in docs for w in words(t)))
    d = P.build_dictionary(P.build_postings(read_table(spark, sf, "documents")), IndexConfig(df_threshold=1))
    assert [r.term for r in d.orderBy("term_id").collect()] == seen


class MoveToFront:
    """A chained hash table that may move what it finds to the front of its chain."""

    def __init__(self, slots, move):
        self.chains, self.move, self.probes = [[] for _ in range(slots)], move, 0

    def get(self, key):
        chain = self.chains[hash(key) % len(self.chains)]
        for i, (k, v) in enumerate(chain):
            self.probes += 1
            if k == key:
                if self.move and i:
                    chain.insert(0, chain.pop(i))
                return v
        chain.append((key, sum(map(len, self.chains))))
        return chain[-1][1]


def test_move_to_front_saves_probes(spark, sf):
    stream = [w for r in read_table(spark, sf, "documents").limit(60).collect() for w in words(r.text)]
    plain, moving = MoveToFront(64, False), MoveToFront(64, True)
    for w in stream:
        plain.get(w), moving.get(w)
    assert moving.probes < plain.probes


def test_merged_runs_equal_the_lists(spark, sf):
    rows = P.build_postings(read_table(spark, sf, "documents"))
    merged = baselines.merged_runs(rows, 2000)
    w = {}
    for r in merged.orderBy("term", "rank").collect():
        w.setdefault(r.term, []).append(r.doc_id)
    assert all(d == sorted(d) for d in w.values())


def test_geometric_partitions_against_a_loop(spark):
    n, ratio = 200, 3
    held, log = {}, []
    for run in range(n):
        carry, j = [run], 1
        while len(held.get(j, [])) + len(carry) > (ratio - 1) * ratio ** (j - 1):
            carry = held.pop(j, []) + carry
            j += 1
        held[j] = held.get(j, []) + carry
        log.append((run, j, sum(10 + x for x in held[j])))
    runs = spark.createDataFrame([(i, 10 + i) for i in range(n)], "run long, postings long")
    got = [(r.run, r.target_partition, r.postings_rewritten) for r in baselines.geometric_merges(runs, ratio).orderBy("run").collect()]
    assert got == log


def test_slack_fold(spark):
    segs = spark.createDataFrame([("t", i, n) for i, n in enumerate([100, 50, 60, 300, 10])], "term string, seg_no long, n_bytes long")
    r = baselines.in_place(segs, lambda used: F.lit(60).cast("long")).first()
    # 100 (+60), 150 fits, 210 moves 150 (+60), 510 moves 210 (+60), 520 fits
    assert (r.reserved, r.used, r.wasted, r.relocations, r.copied) == (570, 520, 50, 2, 360)


def test_zone_maps(spark, sf):
    ix = build_index(read_table(spark, sf, "documents"), IndexConfig(block=8))
    for r in ix.segments.limit(200).collect():
        docs = np.cumsum(codec.pfor_decode(bytes(r.d_block)))
        assert (r.first_doc, r.last_doc, r.n_docs) == (docs[0], docs[-1], len(docs))


def test_index_without_positions(spark, sf):
    docs = read_table(spark, sf, "documents")
    full, bare = build_index(docs, IndexConfig(block=16)), build_index(docs, IndexConfig(block=16, positional=False))
    rows = lambda df: sorted((r.term, r.doc_id, r.tf) for r in df.collect())
    assert rows(pool.decode(bare.segments, positions=False)) == rows(full.postings)
    size = lambda ix: ix.segments.agg(F.sum("n_bytes")).first()[0]
    assert size(bare) < size(full) and bare.segments.where(F.size("p_blocks") > 0).isEmpty()
