"""Python functions for what has no expression: variable-byte lengths, block sizes, segment decoding."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from . import codec


@F.pandas_udf("long")
def vbyte_length(gaps: pd.Series) -> pd.Series:
    """Bytes of an int array in variable bytes, a whole Arrow batch at once."""
    sizes = gaps.map(len).to_numpy()
    flat = np.concatenate(gaps.to_list()) if len(gaps) else np.zeros(0, np.int64)
    bits = codec.bit_lengths(flat)
    per = np.maximum(1, -(-bits // 7))
    ends = np.cumsum(sizes)
    total = np.concatenate([[0], np.cumsum(per)])
    return pd.Series(total[ends] - total[ends - sizes])


@F.pandas_udf("long")
def block_bytes(values: pd.Series) -> int:
    """Size of the compressed block of a group's values."""
    return len(codec.pfor_encode(values.to_numpy()))


@F.pandas_udf("long")
def sizes_of_blocks(values: pd.Series) -> pd.Series:
    """The same of collected groups (at most a block each), a whole Arrow batch at once: groups are too many and too
    small for a Python call each."""
    sizes = values.map(len).to_numpy(np.int64)
    return pd.Series(codec.pfor_shapes(np.concatenate(values.to_list()).astype(np.int64), sizes)[2] if len(values) else sizes)


@F.udtf(returnType="doc_id: long, tf: long")
class DecodeSegment:
    """A segment's blocks to its postings."""

    def eval(self, d_block: bytes, f_block: bytes) -> Iterator[tuple[int, int]]:
        docs = np.cumsum(codec.pfor_decode(bytes(d_block))).tolist()
        yield from zip(docs, codec.pfor_decode(bytes(f_block)).tolist())
