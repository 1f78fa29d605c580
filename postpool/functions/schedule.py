"""What the buffers do, as arithmetic on a posting's rank in its list (from 1).

A buffer of one block is flushed when full and then doubled, up to 2**cap blocks. Groups therefore hold 1, 2, 4, ...
blocks, and everything about a flush follows from the rank; no buffer is simulated.
"""

from __future__ import annotations

from pyspark.sql import Column, functions as F


def div(a: Column, n) -> Column:
    """Whole-number division, exact for any BIGINT."""
    return F.call_function("div", a.cast("long"), F.lit(n).cast("long"))


def power_of_two(exponent: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), exponent.cast("int"))


def segment_no(rank: Column, block: int) -> Column:
    return div(rank - 1, block)


def slot(rank: Column, block: int) -> Column:
    return (rank - 1) % block


def log2_floor(n: Column) -> Column:
    """Exact, by the length of the binary form."""
    return F.length(F.bin(n)).cast("long") - 1


def group_of_segment(seg: Column, cap: int) -> Column:
    """Group number of a segment number (both from 0)."""
    full = (1 << (cap + 1)) - 1
    return F.when(seg < full, log2_floor(seg + 1)).otherwise(cap + 1 + div(seg - full, 1 << cap))


def group_end(group: Column, block: int, cap: int) -> Column:
    """Rank of the posting that fills a group."""
    growing = power_of_two(F.least(group, F.lit(cap)).cast("int") + 1) - 1
    return F.lit(block) * (growing + F.greatest(group - cap, F.lit(0)) * (1 << cap))


def groups_of_list(df: Column, block: int, cap: int) -> Column:
    """How many groups a list of df postings has (the last may be short)."""
    return group_of_segment(segment_no(df, block), cap) + 1


def buffer_class(df: Column, block: int, cap: int | None = None, last_bar: str = "series", top: int = 7) -> Column:
    """Blocks of the largest buffer that a list of df postings reaches: 1, 2, 4, ...

    By the series, the next class begins when all buffers so far are full. last_bar='literal' lets the top class begin
    only above 2**top blocks of postings."""
    blocks = div(df, block) + 1
    level = F.least(log2_floor(blocks), F.lit(top if cap is None else cap))
    if last_bar == "literal":
        level = F.when((level >= top) & (df <= block << top), F.lit(top - 1)).otherwise(level)
    return power_of_two(level)
