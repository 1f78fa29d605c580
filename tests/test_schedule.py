import pytest
from pyspark.sql import functions as F

from postpool.functions import schedule


def loop(n, block, cap):
    """(segment, group) of each rank by a loop over buffers."""
    out, room, level, group, held = [], block, 0, 0, 0
    for rank in range(1, n + 1):
        out.append(((rank - 1) // block, group))
        held += 1
        if held == room:
            held, group, level = 0, group + 1, min(level + 1, cap)
            room = block << level
    return out


@pytest.mark.parametrize("cap", [0, 1, 3, 5, 7])
def test_groups_equal_the_loop(spark, cap):
    block, n = 2, 2000
    seg = schedule.segment_no(F.col("id"), block)
    rows = spark.range(1, n + 1).select("id", seg.alias("s"), schedule.group_of_segment(seg, cap).alias("g")).orderBy("id").collect()
    assert [(r.s, r.g) for r in rows] == loop(n, block, cap)


def test_thirteen_postings(spark):
    """b=2, cap 2b: groups {0} {1,2} {3,4} {5,6}; flushes at ranks 2, 6, 10, the rest at the end."""
    seg = schedule.segment_no(F.col("id"), 2)
    rows = spark.range(1, 14).select("id", schedule.group_of_segment(seg, 1).alias("g")).withColumn("end", schedule.group_end(F.col("g"), 2, 1)).collect()
    assert [r.id for r in rows if r.id == r.end] == [2, 6, 10]
    assert [r.g for r in rows] == [0, 0, 1, 1, 1, 1, 2, 2, 2, 2, 3, 3, 3]


@pytest.mark.parametrize("rule, expected", [("series", [1, 2, 2, 4, 4, 8, 64, 128, 128, 128]), ("literal", [1, 2, 2, 4, 4, 8, 64, 64, 64, 128])])
def test_classes(spark, rule, expected):
    dfs = [127, 128, 383, 384, 895, 896, 16255, 16256, 16384, 16385]
    df = spark.createDataFrame([(i, d) for i, d in enumerate(dfs)], "i int, df long")
    assert [r.c for r in df.select("i", schedule.buffer_class(F.col("df"), 128, last_bar=rule).alias("c")).orderBy("i").collect()] == expected


def test_golden_groups(spark):
    """Counts that FIXTURES.md lists for sf0.001 and sf0.01."""
    from postpool.config import IndexConfig
    from postpool.operators import pool, postings as P
    from postpool.sources.io import read_table

    rows = P.build_postings(read_table(spark, "/root/testdata/sf0.01", "documents"))
    d = P.build_dictionary(rows, IndexConfig(df_threshold=10)).cache()
    assert [pool.schedule_counts(d, 16, m).first().groups for m in range(8)] == [9276, 7262, 6710, 6574, 6550, 6550, 6550, 6550]
    from postpool.operators import measures

    assert {r.class_blocks: r.n_terms for r in measures.buffer_classes(d, 16).collect()} == {1: 1617, 2: 1638, 4: 376, 8: 114, 16: 37, 32: 9}
    m = {r.cap: r for r in measures.buffer_memory(d, IndexConfig(block=16)).collect()}
    assert (m[0].docid_bytes + m[0].tf_bytes, m[0].pos_bytes) == (485248, 397504) and (m[5].docid_bytes + m[5].tf_bytes, m[5].pos_bytes) == (1048192, 973376) and round(m[5].ratio_to_1b, 3) == 2.290
