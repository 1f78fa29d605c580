"""Many blocks at once against one after the other."""

import numpy as np
import pytest

from postpool.functions import codec


@pytest.mark.parametrize("seed", range(4))
def test_many_blocks_are_the_single_ones(seed):
    rng = np.random.default_rng(seed)
    sizes = rng.integers(1, 257, 300)
    values = rng.integers(0, 1 << rng.integers(1, 33, sizes.sum()), dtype=np.int64)
    values[rng.random(len(values)) < 0.2] = 0
    data, offsets = codec.pfor_encode_many(values, sizes)
    parts = np.split(values, np.cumsum(sizes)[:-1])
    single = [codec.pfor_encode(p) for p in parts]
    assert [data[a:z].tobytes() for a, z in zip(offsets, offsets[1:])] == single
    back, n = codec.pfor_decode_many(np.concatenate([np.zeros(5, np.uint8), data]), offsets[:-1] + 5)
    assert (back == values).all() and (n == sizes).all()
    assert codec.pfor_shapes(values, sizes)[2].tolist() == list(map(len, single))
