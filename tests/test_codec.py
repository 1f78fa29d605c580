import numpy as np
import pytest
from hypothesis import given, settings, strategies as st

from postpool.functions import codec

VALUES = st.lists(st.one_of(st.integers(0, 5), st.integers(0, 300), st.integers(0, 2**31 - 1)), min_size=1, max_size=256)


def size(v):
    """The size formula in plain Python."""
    lengths = sorted((int(x).bit_length() for x in v), reverse=True)
    w = lengths[len(v) // 10]
    e = sum(x > w for x in lengths)
    return 4 + 4 * -(-len(v) * w // 32) + 4 * -(-e // 4) + 4 * e


@settings(max_examples=150, deadline=None)
@given(VALUES)
def test_pfor(v):
    block = codec.pfor_encode(np.array(v))
    assert codec.pfor_decode(block).tolist() == v and len(block) == size(v)


@pytest.mark.parametrize("v", [[0] * 128, [7] * 128, list(range(1, 129)), [1] * 127 + [2**31 - 1], [1] * 116 + [2**20] * 12, [1] * 115 + [2**20] * 13, [0], [5], list(range(127))])
def test_pfor_edges(v):
    block = codec.pfor_encode(np.array(v))
    assert codec.pfor_decode(block).tolist() == v and len(block) == size(v)


def test_exception_limit():
    """12 of 128 may be exceptions, 13 may not."""
    assert codec.pfor_encode(np.array([1] * 116 + [2**20] * 12))[2] == 1
    assert codec.pfor_encode(np.array([1] * 115 + [2**20] * 13))[2] == 21


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 100000), min_size=1, max_size=60), st.integers(8, 12))
def test_bytes_and_rice(v, k):
    assert codec.vbyte_decode(codec.vbyte_encode(np.array(v))).tolist() == v
    assert codec.rice_decode(codec.rice_encode(np.array(v), k), len(v), k).tolist() == v


def test_sizes_as_expressions(spark):
    from pyspark.sql import functions as F

    rows = [([0, 0, 0],), (list(range(1, 129)),), ([1] * 116 + [2**20] * 12,), ([2**31 - 1],)]
    df = spark.createDataFrame(rows, "v array<long>").select("v", codec.pfor_size(F.col("v")).alias("n"), F.transform("v", codec.vbyte_size).alias("b"))
    for r in df.collect():
        assert r.n == len(codec.pfor_encode(np.array(r.v)))
        assert sum(r.b) == len(codec.vbyte_encode(np.array(r.v)))


def test_position_code_has_four_readings(spark):
    """One code, four pairs of lists: only the term frequencies tell them apart."""
    from pyspark.sql import functions as F

    from postpool.functions import analyze

    code = [1, 4, 4, 3, 13]
    readings = [([1], [4, 8, 11, 24]), ([1, 5], [4, 7, 20]), ([1, 5, 9], [3, 16]), ([1, 5, 9, 12], [13])]
    df = spark.createDataFrame([(i, list(a), list(b)) for i, (a, b) in enumerate(readings)], "i int, a array<int>, b array<int>")
    gaps = F.concat(analyze.position_gaps(F.col("a")), analyze.position_gaps(F.col("b")))
    back = analyze.restore_positions(gaps, F.array(F.size("a"), F.size("b")))
    for r in df.select("a", "b", gaps.alias("g"), back.alias("p")).collect():
        assert r.g == code and r.p == [r.a, r.b]
