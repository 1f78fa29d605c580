"""SvS and WAND over arrays against their posting loops."""

import numpy as np
import pyarrow as pa
import pytest

from postpool.functions import codec
from postpool.operators import kernels


def shard_table(rng, terms, block=8):
    rows = []
    for i in range(terms):
        docs = np.sort(rng.choice(3000, rng.integers(1, 1500), replace=False))
        for s in range(0, len(docs), block):
            d = docs[s : s + block]
            rows.append({"term": f"t{i}", "seg_no": s // block, "n_docs": len(d), "first_doc": int(d[0]), "last_doc": int(d[-1]), "d_block": codec.pfor_encode(np.diff(d, prepend=0)), "f_block": codec.pfor_encode(rng.integers(1, 9, len(d))), "lengths": (50 + d % 90).tolist(), "bound": 0.0})
    return pa.Table.from_pylist([rows[i] for i in rng.permutation(len(rows))])


@pytest.mark.parametrize("seed,kept,window", [(0, 1 << 22, 1 << 12), (1, 100, 64), (2, 2000, 16)])
def test_arrays_are_the_loops(monkeypatch, seed, kept, window):
    monkeypatch.setattr(kernels, "WINDOW", window)
    rng = np.random.default_rng(seed)
    table = shard_table(rng, 12)
    lists, shard = kernels.Lists.of_table(table), kernels.Shard(table, kept)
    for _ in range(60):
        terms = [f"t{i}" for i in rng.choice(13, rng.integers(1, 6), replace=False)]
        a, b = kernels.new_work(), kernels.new_work()
        assert kernels.small_versus_small(lists, terms, a) == shard.svs(tuple(terms), b).tolist()
        assert (a["segments_decoded"], a["postings_decoded"]) == (b["segments_decoded"], b["postings_decoded"])
        # bounds hold: idf * 1.9 is more than any posting's part
        about = {t: (0.5 + int(t[1:]), (0.5 + int(t[1:])) * 1.9, int(t[1:])) for t in terms}
        for k in (3, 200):
            assert kernels.weak_and(lists, about, k, 90.0, kernels.new_work()) == shard.wand(about, k, 90.0)


def test_empty_shard_and_shared_answers():
    shard = kernels.Shard(shard_table(np.random.default_rng(0), 1).slice(0, 0))
    assert len(shard.svs(("t0",), kernels.new_work())) == 0 and shard.wand({"t0": (1.0, 2.0, 0)}, 3, 9.0) == []
    assert kernels.by_terms([(1, ["a", "b"]), (2, ["c"]), (3, ["b", "a"])]) == [(("a", "b"), [1, 3]), (("c",), [2])]


def test_segments_are_decoded_once_for_all_queries(monkeypatch):
    """Also with windows smaller than a list, and when no decoded list could be kept."""
    monkeypatch.setattr(kernels, "WINDOW", 50)
    rng, values = np.random.default_rng(3), []
    table = shard_table(rng, 12)
    decode = codec.pfor_decode_many
    monkeypatch.setattr(codec, "pfor_decode_many", lambda data, at: values.append(0) or (lambda out: values.append(len(out[0])) or out)(decode(data, at)))
    asked = [tuple(f"t{i}" for i in rng.choice(13, rng.integers(1, 6), replace=False)) for _ in range(60)]
    about = {f"t{i}": (0.5 + i, (0.5 + i) * 1.9, i) for i in range(13)}
    found = kernels.Shard(table, 1).wands(asked, about, 7, 90.0)
    used = {t for terms in asked for t in terms}
    assert sum(values) == 2 * sum(n for t, n in zip(table["term"].to_pylist(), table["n_docs"].to_pylist()) if t in used)
    lists = kernels.Lists.of_table(table)
    for terms, (docs, scores) in zip(asked, found):
        assert kernels.weak_and(lists, {t: about[t] for t in terms}, 7, 90.0, kernels.new_work()) == list(zip(scores.tolist(), docs.tolist()))


@pytest.mark.parametrize("seed,block", [(0, 8), (1, 1), (2, 16), (3, 5)])
def test_counted_work_is_the_loops(seed, block):
    rng = np.random.default_rng(seed)
    table = shard_table(rng, 12, block)
    lists, shard = kernels.Lists.of_table(table), kernels.Shard(table)
    passed = 0
    for _ in range(40):
        terms = [f"t{i}" for i in rng.choice(13, rng.integers(1, 7), replace=False)]
        about = {t: (0.5 + int(t[1:]), (0.5 + int(t[1:])) * 1.9, int(t[1:])) for t in terms}
        for k in (1, 3, 200, 5000):
            want = kernels.new_work()
            kernels.weak_and(lists, about, k, 90.0, want)
            got = shard.wand_work(about, k, 90.0)
            assert [got[c] for c in kernels.COUNTERS] == [want[c] for c in kernels.COUNTERS]
            passed += want["pivots"] > want["scored"]
    assert passed > 20
    assert kernels._rounded(np.array([0.0000005, 1.0000015, 2.5, 7.1234565])).tolist() == [round(x, 6) for x in (0.0000005, 1.0000015, 2.5, 7.1234565)]


def test_places_in_the_union():
    for docs in ([np.array([3, 5, 9]), np.array([4, 5])], [np.array([3, 5, 10**12]), np.array([4, 5])], [np.array([7])]):
        union = sorted({int(d) for some in docs for d in some})
        place, n = kernels._met(docs)
        assert n == len(union) and [p.tolist() for p in place] == [[union.index(d) for d in some] for some in docs]
