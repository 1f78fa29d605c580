"""Benchmark decontamination by suffix arrays of the training text.

Documents are cut into shards of about SHARD_WORDS words. Each shard gets a word-level suffix array (prefix doubling
that refines only the suffixes still tied), in which every benchmark suffix is looked up by binary search with its
first WINDOW words. A window is WINDOW consecutive words of an item, or the whole of a shorter one; a suffix that
begins with a window and is found leads to all places of it, and a document word inside an occurrence is hit. From
each such place the verbatim match goes on as far as any benchmark suffix does: the longest one and its place are
given for each document. `longest_matches` gives the same per benchmark suffix, shorter matches too.

Words outside the benchmark's vocabulary can't take part in a match: they all have number 0 and start no suffix.

Edge cases: null or wordless texts have no words, hits or items; repeated documents and items count each for
themselves, an item id once a document; a null item id is listed as `null`; a document longer than a shard is a shard
of its own; empty tables give no rows, or no hits; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, functions as F

from .common import filter_rows, pick

WINDOW, SHARD_WORDS = 13, 1 << 20
#: Characters of a part of the benchmark, unless one item is longer. Each batch of documents is searched for part after
#: part and its hit words are united, so that a larger benchmark takes more parts and is never refused.
PART_CHARS = 4 << 20
#: Suffixes that are looked up together.
SLICE = 1 << 16
_WORD = re.compile(rb"[0-9a-z\x80-\xff]+")


def words(text: str | None) -> list[bytes]:
    """ASCII letters in lower case; words are runs of digits, letters and anything beyond ASCII."""
    return _WORD.findall(text.encode("utf-8", "replace").lower()) if text else []


@dataclass
class Targets:
    """A part of the benchmark: all items' word numbers in one array, and its suffixes.

    flat: words of the items, a 0 after each; suffixes: where they start in flat; items: the item of each suffix;
    rows: their distinct first words, filled with 0; order: suffixes sorted by all their words; owners: items of each
    row that is a window; window_rows: those rows."""

    names: list[int | None]
    vocabulary: dict[bytes, int]
    flat: np.ndarray
    suffixes: np.ndarray
    items: np.ndarray
    bases: np.ndarray
    rows: np.ndarray
    lengths: np.ndarray
    order: np.ndarray
    owners: dict[int, list[int]]
    window_rows: np.ndarray
    window: int


def targets(items: list[tuple[int | None, str | None]], window: int = WINDOW) -> Targets:
    vocabulary: dict[bytes, int] = {}
    seqs = [[vocabulary.setdefault(w, len(vocabulary) + 1) for w in words(text)] for _, text in items]
    sizes = np.array([len(s) for s in seqs], np.int64)
    flat = np.fromiter((n for s in seqs for n in (*s, 0)), np.int32, int(sizes.sum()) + len(seqs))
    bases = np.cumsum(np.concatenate([[0], sizes + 1]))[:-1] if len(seqs) else np.zeros(0, np.int64)
    suffixes = np.flatnonzero(flat)
    item = np.repeat(np.arange(len(seqs)), sizes)
    room = (bases + sizes)[item] - suffixes
    span = np.arange(window)
    first = np.where(span < room[:, None], np.concatenate([flat, np.zeros(window, np.int32)])[suffixes[:, None] + span], 0)
    rows, row = np.unique(first, axis=0, return_inverse=True) if len(suffixes) else (np.zeros((0, window), np.int32), np.zeros(0, np.int64))
    row = row.reshape(-1)
    begins = room >= np.minimum(window, sizes[item])
    owners: dict[int, list[int]] = {}
    for r, i in np.unique(np.stack([row[begins], item[begins]], axis=1), axis=0).tolist() if begins.any() else []:
        owners.setdefault(r, []).append(i)
    order = suffix_array(flat, int(sizes.max(initial=1)))
    return Targets([item for item, _ in items], vocabulary, flat, suffixes, item, bases, rows, (rows > 0).sum(axis=1), order, owners, np.array(sorted(owners), np.int64), window)


def suffix_array(ids: np.ndarray, depth: int) -> np.ndarray:
    """Starts of the suffixes that begin with a known word, in order of their first `depth` words or up to a 0."""
    at = np.flatnonzero(ids)
    rank = np.zeros(len(ids) + depth + 1, np.int64)
    rank[: len(ids)] = ids
    top = int(ids.max(initial=0)) + 1
    key = rank[at] * top + rank[at + 1]
    order = np.argsort(key, kind="stable")
    at, key = at[order], key[order]
    done = 2
    opens = np.empty(len(at), bool)
    opens[:1], opens[1:] = True, key[1:] != key[:-1]
    group = np.flatnonzero(opens)
    lead = np.repeat(group, np.diff(np.append(group, len(at))))  # a group's rank is its first place plus 1
    rank[at] = lead + 1
    todo = np.flatnonzero(np.bincount(lead, minlength=len(at))[lead] > 1)
    while done < depth and len(todo):
        todo = todo[rank[at[todo] + done] > 0] if done < len(ids) else todo[:0]
        # what meets an unknown word goes first in its group, so the others' places follow it
        sub, base = at[todo], lead[todo]
        whole = np.flatnonzero(np.isin(lead, np.unique(base)))
        sub, base = at[whole], lead[whole]
        order = np.lexsort((rank[sub + done], base))
        sub, base, second = sub[order], base[order], rank[sub + done][order]
        at[whole] = sub
        opens = np.empty(len(sub), bool)
        opens[:1], opens[1:] = True, (base[1:] != base[:-1]) | (second[1:] != second[:-1])
        group = np.flatnonzero(opens)
        size = np.diff(np.append(group, len(sub)))
        fresh = np.repeat(whole[group], size)
        lead[whole] = fresh
        rank[sub] = fresh + 1
        todo = whole[np.repeat(size, size) > 1]
        done *= 2
    return at


def bound(ids: np.ndarray, array: np.ndarray, patterns: np.ndarray, right: bool = False) -> np.ndarray:
    """For each pattern row (words, then 0 as filling) the first place whose suffix is not below it, or is above it
    and everything that starts with it. All rows are searched together, one step of the bisection at a time."""
    width = patterns.shape[1]
    padded = np.concatenate([ids, np.zeros(width, ids.dtype)])
    lo, hi = np.zeros(len(patterns), np.int64), np.full(len(patterns), len(array), np.int64)
    real = patterns > 0
    span = np.arange(width)
    while True:
        live = np.flatnonzero(lo < hi)
        if not len(live):
            return lo
        mid = (lo[live] + hi[live]) // 2
        text = padded[array[mid][:, None] + span]
        want = patterns[live]
        differs = (text != want) & real[live]
        some = differs.any(axis=1)
        first = differs.argmax(axis=1)
        rows = np.arange(len(live))
        below = np.where(some, text[rows, first] < want[rows, first], right)
        lo[live[below]] = mid[below] + 1
        hi[live[~below]] = mid[~below]


def common_prefix(a: np.ndarray, at: np.ndarray, b: np.ndarray, bt: np.ndarray, step: int = 16) -> np.ndarray:
    """Equal words of a[at:] and b[bt:], up to a 0, for each pair of places; `step` words at a time while they agree."""
    length, live = np.zeros(len(at), np.int64), np.arange(len(at))
    a, b = np.concatenate([a, np.zeros(step, a.dtype)]), np.concatenate([b, np.zeros(step, b.dtype)])
    span = np.arange(step)
    while len(live):
        x, y = a[(at[live] + length[live])[:, None] + span], b[(bt[live] + length[live])[:, None] + span]
        same = (x == y) & (x > 0)
        whole = same.all(axis=1)
        length[live] += np.where(whole, step, same.argmin(axis=1))
        live = live[whole]
    return length


def longest_in(ids: np.ndarray, array: np.ndarray, other: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(length, place in ids) of the longest match of each suffix other[at:] among the sorted suffixes of ids: it lies
    beside the place that the suffix would take. The first of equally long ones in ids order isn't guaranteed."""
    if not len(array) or not len(at):
        return np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
    lo, hi = np.zeros(len(at), np.int64), np.full(len(at), len(array), np.int64)
    end, other_end = np.append(ids, 0), np.append(other, 0)
    while True:
        live = np.flatnonzero(lo < hi)
        if not len(live):
            break
        mid = (lo[live] + hi[live]) // 2
        n = common_prefix(ids, array[mid], other, at[live])
        below = end[array[mid] + n] < other_end[at[live] + n]
        lo[live[below]] = mid[below] + 1
        hi[live[~below]] = mid[~below]
    before, after = array[np.maximum(lo - 1, 0)], array[np.minimum(lo, len(array) - 1)]
    a, b = common_prefix(ids, before, other, at), common_prefix(ids, after, other, at)
    return np.maximum(a, b), np.where(a >= b, before, after)


def occurrences(ids: np.ndarray, array: np.ndarray, wanted: Targets) -> tuple[np.ndarray, np.ndarray]:
    """(place, row) of every occurrence in the shard of every window. All suffixes' rows are looked up; the end of the
    range is searched for only where a window was found."""
    places, which = [], []
    span = np.arange(wanted.window)
    padded = np.concatenate([ids, np.zeros(wanted.window, ids.dtype)])
    for begin in range(0, len(wanted.rows) if len(array) else 0, SLICE):
        rows = wanted.rows[begin : begin + SLICE]
        lo = bound(ids, array, rows)
        found = lo < len(array)
        found[found] = ((padded[array[lo[found]][:, None] + span] == rows[found]) | (rows[found] == 0)).all(axis=1)
        found[found] = np.isin(begin + np.flatnonzero(found), wanted.window_rows)
        at = np.flatnonzero(found)
        count = bound(ids, array, rows[at], right=True) - lo[at]
        starts = np.repeat(lo[at] - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum()) if len(at) else np.zeros(0, np.int64)
        places.append(array[starts])
        which.append(np.repeat(begin + at, count))
    empty = [np.zeros(0, np.int64)]
    return np.concatenate(places or empty), np.concatenate(which or empty)


def longest_matches_of_docs(ids: np.ndarray, starts: np.ndarray, place: np.ndarray, which: np.ndarray, wanted: Targets) -> dict[int, tuple[int, int]]:
    """{document: (words, place)} of the longest verbatim match that begins with a window, the first of equally long ones."""
    spots, back = np.unique(place, return_inverse=True)
    own = np.zeros(len(spots), np.int64)
    np.maximum.at(own, back, wanted.lengths[which])
    reach, _ = longest_in(wanted.flat, wanted.order, ids, spots)
    reach = np.where(reach >= wanted.window, reach, own)
    doc = np.searchsorted(starts, spots, "right") - 1
    out: dict[int, tuple[int, int]] = {}
    for i in np.lexsort((-spots, reach)).tolist():
        out[int(doc[i])] = int(reach[i]), int(spots[i] - starts[doc[i]])
    return out


def _shards(it: Iterator[pa.RecordBatch], vocabulary: dict[bytes, int], size: int) -> Iterator[tuple[list, np.ndarray, np.ndarray]]:
    """(document ids, word numbers with a 0 after each document, start of each document)."""
    docs, parts, n, get = [], [], 0, vocabulary.get
    for batch in it:
        for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            numbers = np.array([get(w, 0) for w in words(text)] + [0], np.int32)
            if n and n + len(numbers) > size:
                yield docs, np.concatenate(parts), np.cumsum([0, *map(len, parts)])
                docs, parts, n = [], [], 0
            docs.append(doc)
            parts.append(numbers)
            n += len(numbers)
    if docs:
        yield docs, np.concatenate(parts), np.cumsum([0, *map(len, parts)])


def parts(benchmark: DataFrame, limit: int | None = None, part: int = PART_CHARS) -> list[Broadcast]:
    """The benchmark's items in broadcasts of at most `part` characters, or of one longer item; an item counts 16 more.
    ValueError if a limit is given and all of them are beyond it."""
    items = pick(benchmark, item_id="long", text="string")
    if limit is not None:
        chars, n = items.agg(F.coalesce(F.sum(F.length("text")), F.lit(0)), F.count(F.lit(1))).first()
        if chars + 16 * n > limit:
            raise ValueError(f"a benchmark of {chars} characters is beyond the limit of {limit}")
    send = benchmark.sparkSession.sparkContext.broadcast
    out, some, size = [], [], 0
    for r in items.toLocalIterator():
        n = len(r.text or "") + 16
        if some and size + n > part:
            out.append(send(some))
            some, size = [], 0
        some.append((r.item_id, r.text))
        size += n
    return [*out, send(some)] if some or not out else out


class Wanted:
    """Targets of a benchmark's parts, built one part at a time in a worker; those of a single part are kept."""

    def __init__(self, shared: list[Broadcast], window: int):
        self.shared, self.window, self.kept = shared, window, None

    def __iter__(self) -> Iterator[Targets]:
        if len(self.shared) == 1:
            self.kept = self.kept or targets(self.shared[0].value, self.window)
            yield self.kept
            return
        for one in self.shared:
            yield targets(one.value, self.window)
            one.__dict__.pop("_value", None)  # read again from the worker's disk for the next batch


FOUND = "n_words long, n_hit long, item_ids array<string>, hits array<struct<start:long,length:long>>, longest_match long, longest_at long"
Found = tuple[int, int, list[str], list[dict], int, int | None]


def search(texts: list[str | None], wanted: Targets, shard_words: int = SHARD_WORDS) -> Iterator[Found]:
    """FOUND of each text, shard by shard."""
    table = pa.RecordBatch.from_arrays([pa.array(range(len(texts)), pa.int64()), pa.array(texts, pa.string())], names=["row", "text"])
    for _, ids, starts in _shards(iter([table]), wanted.vocabulary, shard_words):
        place, which = occurrences(ids, suffix_array(ids, wanted.window), wanted)
        marks = np.zeros(len(ids) + 1, np.int64)
        np.add.at(marks, place, 1)
        np.add.at(marks, place + wanted.lengths[which], -1)
        doc = np.searchsorted(starts, place, "right") - 1
        listed: dict[int, set] = {}
        for d, w in np.unique(np.stack([doc, which], axis=1), axis=0).tolist() if len(doc) else []:
            listed.setdefault(d, set()).update(wanted.owners[w])
        longest = longest_matches_of_docs(ids, starts, place, which, wanted) if len(doc) else {}
        covered = np.cumsum(marks)[:-1] > 0
        total = np.concatenate([[0], np.cumsum(covered)])
        hits = total[starts[1:]] - total[starts[:-1]]
        for d, n_hit in enumerate(hits.tolist()):
            runs = []
            if n_hit:
                edge = np.flatnonzero(np.diff(np.concatenate([[0], covered[starts[d] : starts[d + 1]], [0]]).astype(np.int8)))
                runs = [{"start": int(a), "length": int(b - a)} for a, b in zip(edge[::2], edge[1::2])]
            names = {wanted.names[i] for i in listed.get(d, ())}
            yield int(starts[d + 1] - starts[d] - 1), n_hit, sorted("null" if i is None else str(i) for i in names), runs, *longest.get(d, (0, None))


def united(found: tuple[Found, ...]) -> Found:
    """FOUND of a text from its FOUND by each part of the benchmark: hits of several parts may overlap or touch."""
    runs: list[dict] = []
    for r in sorted((r for f in found for r in f[3]), key=lambda r: r["start"]):
        if runs and r["start"] <= runs[-1]["start"] + runs[-1]["length"]:
            runs[-1]["length"] = max(runs[-1]["length"], r["start"] + r["length"] - runs[-1]["start"])
        else:
            runs.append(dict(r))
    longest = min(((-f[4], f[5]) for f in found if f[4]), default=(0, None))
    return found[0][0], sum(r["length"] for r in runs), sorted({i for f in found for i in f[2]}), runs, -longest[0], longest[1]


def search_parts(texts: list[str | None], wanted: Wanted, shard_words: int = SHARD_WORDS) -> list[Found]:
    """FOUND of each text by all parts of the benchmark."""
    out: list = []
    for one in wanted:
        found = list(search(texts, one, shard_words))
        out = [united(pair) if pair[1][1] else pair[0] for pair in zip(out, found)] if out else found
    return out


def find(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, shard_words: int = SHARD_WORDS, limit: int | None = None, part: int = PART_CHARS) -> DataFrame:
    """(doc_id, FOUND): hits are maximal runs of hit words. No shuffle; the benchmark is broadcast in parts."""
    wanted = Wanted(parts(benchmark, limit, part), window)

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(), pa.int64(), pa.list_(pa.string()), pa.list_(pa.struct([("start", pa.int64()), ("length", pa.int64())])), pa.int64(), pa.int64())
        for batch in it:
            if batch.num_rows:
                found = zip(*search_parts(batch.column(1).to_pylist(), wanted, shard_words))
                yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(found, kinds))], names=["doc_id", "n_words", "n_hit", "item_ids", "hits", "longest_match", "longest_at"])

    return pick(docs, doc_id="long", text="string").mapInArrow(kernel, f"doc_id long, {FOUND}")


#: A document goes if its hits are at least one word in so many.
SHARE = 20


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: int = SHARE, limit: int | None = None, part: int = PART_CHARS) -> DataFrame:
    """docs without the contaminated rows, all columns as they were."""
    wanted = Wanted(parts(benchmark, limit, part), window)
    return filter_rows(docs, "text", lambda texts: [not (hit > 0 and share * hit >= n) for n, hit, *_ in search_parts(texts, wanted)])


def is_contaminated():
    """The contract's rule over FOUND: a hit, and hits are at least a twentieth of the words."""
    return (F.col("n_hit") > 0) & (SHARE * F.col("n_hit") >= F.col("n_words"))


def longest_matches(docs: DataFrame, benchmark: DataFrame, shard_words: int = SHARD_WORDS, part: int = PART_CHARS) -> DataFrame:
    """(item_id, start, length, doc_id, place): for every benchmark suffix its longest verbatim match over all shards
    and a document and word place that has it (the smallest id of those that the shards name); length 0 and null where no word occurs. The documents
    are read once for each part of the benchmark."""

    def searched(shared: Broadcast) -> DataFrame:
        def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            wanted = targets(shared.value)
            for docs, ids, starts in _shards(it, wanted.vocabulary, shard_words):
                array = suffix_array(ids, max(1, len(wanted.flat)))
                for begin in range(0, len(wanted.suffixes), SLICE):
                    some, item = wanted.suffixes[begin : begin + SLICE], wanted.items[begin : begin + SLICE]
                    length, place = longest_in(ids, array, wanted.flat, some)
                    doc = np.searchsorted(starts, place, "right") - 1
                    rows = [(wanted.names[i], o, n, docs[d] if n else None, p if n else None) for i, o, n, d, p in zip(item.tolist(), (some - wanted.bases[item]).tolist(), length.tolist(), doc.tolist(), (place - starts[doc]).tolist())]
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], names=["item_id", "start", "length", "doc_id", "place"])

        return pick(docs, doc_id="long", text="string").mapInArrow(kernel, "item_id long, start long, length long, doc_id long, place long")

    out = reduce(DataFrame.unionByName, map(searched, parts(benchmark, part=part)))
    best = F.min(F.struct((-F.col("length")).alias("n"), "doc_id", "place"))
    return out.groupBy("item_id", "start").agg(best.alias("b")).select("item_id", "start", (-F.col("b.n")).alias("length"), "b.doc_id", "b.place")
