"""SvS and WAND over compressed segments, a shard at a time, with counters of the work done."""

from __future__ import annotations

import heapq
from collections import OrderedDict
from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from ..functions import codec
from ..runtime import ship
from . import pool
from .parts import Part, answers, by_terms, collected, query_batches
from .retrieval import B, K1, ranked

#: Decoded blocks that a kernel keeps.
KEPT_BLOCKS = 1 << 14


def gallop(values, target: int, lo: int = 0) -> tuple[int, int]:
    """(first index at or after lo with value >= target, comparisons): doubling steps, then bisection in the last."""
    n, step, probes = len(values), 1, 0
    hi = lo
    while hi < n:
        probes += 1
        if values[hi] >= target:
            break
        lo, hi, step = hi + 1, hi + step, step * 2
    hi = min(hi, n)
    while lo < hi:
        mid = (lo + hi) // 2
        probes += 1
        if values[mid] < target:
            lo = mid + 1
        else:
            hi = mid
    return lo, probes


@dataclass
class TermList:
    """One term's segments in a shard: zone maps, and blocks by segment number, which stay compressed. Bounds are of
    whole segments; lengths are of the documents in a segment."""

    first: list[int]
    last: list[int]
    size: int
    d: Sequence
    f: Sequence
    lengths: Sequence | None = None
    bounds: list[float] | None = None


class Rows:
    """A list's values in an Arrow column, by segment number."""

    def __init__(self, column: pa.ChunkedArray, order: np.ndarray):
        self.column, self.order = column, order

    def __getitem__(self, i: int):
        one = self.column[int(self.order[i])]
        return one.values.to_pylist() if pa.types.is_list(one.type) else one.as_buffer()


class Lists:
    """A shard's lists. Decoded blocks are kept up to a number, the least recently used go first."""

    def __init__(self, kept: int = KEPT_BLOCKS):
        self.terms: dict[str, TermList] = {}
        self.blocks: OrderedDict[tuple, list[int]] = OrderedDict()
        self.kept = kept

    @classmethod
    def of_table(cls, table: pa.Table) -> Lists:
        """From rows of segments (term, seg_no, n_docs, first_doc, last_doc, d_block, and f_block, lengths, bound if
        there); the blocks stay in their Arrow buffers."""
        out = cls()
        if not table.num_rows:
            return out
        order = pc.sort_indices(table.select(["term", "seg_no"]), [("term", "ascending"), ("seg_no", "ascending")]).to_numpy()
        terms = table["term"].take(pa.array(order)).combine_chunks()
        cut = np.flatnonzero(pc.not_equal(terms[1:], terms[:-1]).to_numpy(zero_copy_only=False)) + 1 if len(terms) > 1 else np.zeros(0, np.int64)
        starts = [0, *cut.tolist()]
        first, last, sizes = (table[c].to_numpy()[order] for c in ("first_doc", "last_doc", "n_docs"))
        bound = table["bound"].to_numpy()[order] if "bound" in table.column_names else None
        for a, z in zip(starts, [*starts[1:], len(order)]):
            part = order[a:z]
            column = lambda c: Rows(table[c], part) if c in table.column_names else None  # noqa: E731,B023
            out.terms[terms[a].as_py()] = TermList(first[a:z].tolist(), last[a:z].tolist(), int(sizes[a:z].sum()), column("d_block"), column("f_block"), column("lengths"), None if bound is None else bound[a:z].tolist())
        return out

    def _block(self, kind: str, term: str, i: int, make) -> list[int]:
        key = (kind, term, i)
        found = self.blocks.get(key)
        if found is None:
            found = self.blocks[key] = make()
            if len(self.blocks) > self.kept:
                self.blocks.popitem(last=False)
        else:
            self.blocks.move_to_end(key)
        return found

    def docs(self, term: str, i: int, work: dict) -> list[int]:
        out = self._block("d", term, i, lambda: np.cumsum(codec.pfor_decode(self.terms[term].d[i])).tolist())
        if (term, i) not in work["seen"]:
            work["seen"].add((term, i))
            work["segments_decoded"] += 1
            work["postings_decoded"] += len(out)
        return out

    def tfs(self, term: str, i: int) -> list[int]:
        return self._block("f", term, i, lambda: codec.pfor_decode(self.terms[term].f[i]).tolist())

    def lengths(self, term: str, i: int) -> list[int]:
        return self._block("n", term, i, lambda: self.terms[term].lengths[i])


def new_work() -> dict:
    return {"seen": set(), "segments_decoded": 0, "postings_decoded": 0, "probes": 0, "pivots": 0, "scored": 0}


def small_versus_small(lists: Lists, terms: list[str], work: dict) -> list[int]:
    """The whole intersection: shortest list first, then the running set gallops through each next list, from segment to
    segment over the zone maps and then within one. A segment is decoded only if a candidate falls between its first and
    last document; probes are comparisons made."""
    terms = list(dict.fromkeys(terms))
    if not terms or any(t not in lists.terms for t in terms):
        return []
    terms.sort(key=lambda t: (lists.terms[t].size, t))
    found = [d for i in range(len(lists.terms[terms[0]].last)) for d in lists.docs(terms[0], i, work)]
    for term in terms[1:]:
        first, last = lists.terms[term].first, lists.terms[term].last
        kept, at, docs, slot, probes = [], 0, None, 0, 0
        for doc in found:
            if last[at] < doc:
                at, n = gallop(last, doc, at + 1)
                probes += n
                if at == len(last):
                    break
                docs = None
            if first[at] > doc:
                continue
            if docs is None:
                docs, slot = lists.docs(term, at, work), 0
            slot, n = gallop(docs, doc, slot)
            probes += n
            if docs[slot] == doc:
                kept.append(doc)
        work["probes"] += probes
        found = kept
        if not found:
            break
    return found


class Cursor:
    """A place in one list, moved to the first document at or after a target; segments before it aren't decoded."""

    def __init__(self, lists: Lists, term: str, bound: float, order: int, work: dict):
        self.lists, self.term, self.bound, self.order, self.work = lists, term, bound, order, work
        self.list = lists.terms[term]
        self.first, self.last = self.list.first, self.list.last
        self.i = self.j = 0
        self.held = self.beside = None
        self.doc = self.first[0]

    def seek(self, target: int) -> None:
        if self.doc >= target:
            return
        if target > self.last[self.i]:
            self.i, probes = gallop(self.last, target, self.i + 1)
            self.work["probes"] += probes
            self.held = self.beside = None
            self.j = 0
            if self.i >= len(self.last):
                self.doc = None
                return
            if target <= self.first[self.i]:
                self.doc = self.first[self.i]
                return
        docs = self._docs()
        self.j, probes = gallop(docs, target, self.j)
        self.work["probes"] += probes
        self.doc = docs[self.j]

    def _docs(self) -> list[int]:
        if self.held is None:
            self.held = self.lists.docs(self.term, self.i, self.work)
        return self.held

    def weight(self, idf: float, avg: float) -> float:
        """BM25 part of the posting at the cursor; its document's length lies beside it."""
        if self.beside is None:
            self._docs()
            self.beside = self.lists.tfs(self.term, self.i), self.lists.lengths(self.term, self.i)
        tf, length = self.beside[0][self.j], self.beside[1][self.j]
        return idf * tf * (K1 + 1) / (tf + K1 * (1 - B + B * length / avg))

    def block(self, target: int) -> int | None:
        """Segment that would hold the target."""
        i, probes = gallop(self.last, target, self.i)
        self.work["probes"] += probes
        return i if i < len(self.last) else None


def weak_and(lists: Lists, terms: dict[str, tuple[float, float, int]], k: int, avg: float, work: dict, by_block: bool = False) -> list[tuple[float, int]]:
    """The k best (score, doc). terms: idf, bound and order of each term; by_block: the block-max test with the bounds of
    segments.

    Scores are rounded to 6 places, and a document is passed over only if its bound can't reach the k-th score even so."""
    cursors = [Cursor(lists, t, bound, order, work) for t, (_, bound, order) in terms.items() if t in lists.terms]
    heap: list[tuple[float, int]] = []
    slack = 1e-6
    while cursors:
        cursors.sort(key=lambda c: (c.doc, c.order))
        least = heap[0][0] if len(heap) == k else -1.0
        total, pivot = 0.0, None
        for n, c in enumerate(cursors):
            total += c.bound
            if total * (1 + 1e-9) + slack >= least:
                pivot = n
                break
        if pivot is None:
            break
        doc = cursors[pivot].doc
        while pivot + 1 < len(cursors) and cursors[pivot + 1].doc == doc:
            pivot += 1
        work["pivots"] += 1
        if by_block:
            held = [(c, c.block(doc)) for c in cursors[: pivot + 1]]
            best = sum(c.list.bounds[i] for c, i in held if i is not None)
            if best * (1 + 1e-9) + slack < least:
                leave = min([c.last[i] + 1 for c, i in held if i is not None] + ([cursors[pivot + 1].doc] if pivot + 1 < len(cursors) else []))
                leave = max(leave, doc + 1)
                for c in cursors[: pivot + 1]:
                    c.seek(leave)
                cursors = [c for c in cursors if c.doc is not None]
                continue
        if cursors[0].doc == doc:
            score = sum((c.weight(terms[c.term][0], avg) for c in sorted((c for c in cursors[: pivot + 1] if c.doc == doc), key=lambda c: c.order)), 0.0)
            work["scored"] += 1
            entry = (round(score, 6), -doc)
            if len(heap) < k:
                heapq.heappush(heap, entry)
            elif entry > heap[0]:
                heapq.heapreplace(heap, entry)
            for c in cursors[: pivot + 1]:
                c.seek(doc + 1)
        else:
            for c in cursors[:pivot]:
                if c.doc < doc:
                    c.seek(doc)
                    break
        cursors = [c for c in cursors if c.doc is not None]
    return [(s, -d) for s, d in sorted(heap, key=lambda e: (-e[0], -e[1]))]


#: Decoded documents that a shard's kernel keeps, beside at most one list more.
KEPT_VALUES = 1 << 22
#: Postings that are tested together: the first window, and how far windows grow while thresholds rise.
WINDOW, WIDEST = 1 << 18, 1 << 21


@dataclass
class Run:
    """One term's segments from number `a` of the shard on: zone maps, and documents of the segments decoded so far."""

    a: int
    first: np.ndarray
    last: np.ndarray
    n: np.ndarray
    starts: np.ndarray
    docs: np.ndarray
    known: np.ndarray
    weights: np.ndarray | None = None


class Shard:
    """A shard's lists as arrays, for whole query sets: SvS and WAND take many documents a step, and blocks are decoded
    together when a query first falls into them. Lists used least recently go when there are too many values."""

    def __init__(self, table: pa.Table, kept: int = KEPT_VALUES):
        table = table.take(pc.sort_indices(table, [("term", "ascending"), ("seg_no", "ascending")])).combine_chunks() if table.num_rows else table
        self.kept, self.values, self.runs = kept, 0, OrderedDict()
        self.spans: dict[str, tuple[int, int]] = {}
        if not table.num_rows:
            return
        column = lambda c: table[c].combine_chunks() if isinstance(table[c], pa.ChunkedArray) and table[c].num_chunks != 1 else table[c].chunk(0)
        terms = column("term")
        cut = np.flatnonzero(pc.not_equal(terms[1:], terms[:-1]).to_numpy(zero_copy_only=False)) + 1
        for a, z in zip([0, *cut.tolist()], [*cut.tolist(), len(terms)]):
            self.spans[terms[a].as_py()] = (a, z)
        self.first, self.last, self.n = (column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("first_doc", "last_doc", "n_docs"))
        self.before = np.concatenate([[0], np.cumsum(self.n)])
        self.d = pool.bytes_of(column("d_block"))
        if "f_block" in table.column_names:
            self.f = pool.bytes_of(column("f_block"))
            self.lengths = column("lengths").flatten().to_numpy(zero_copy_only=False)

    def size(self, term: str) -> int:
        a, z = self.spans[term]
        return int(self.before[z] - self.before[a])

    def run(self, term: str) -> Run:
        found = self.runs.get(term)
        if found is None:
            a, z = self.spans[term]
            n = self.n[a:z]
            found = self.runs[term] = Run(a, self.first[a:z], self.last[a:z], n, np.cumsum(n) - n, np.zeros(self.size(term), np.int64), np.zeros(z - a, bool))
            self.values += len(found.docs)
            while self.values > self.kept and len(self.runs) > 1:
                self.values -= len(self.runs.popitem(last=False)[1].docs)
        else:
            self.runs.move_to_end(term)
        return found

    def docs(self, run: Run, segments: np.ndarray) -> np.ndarray:
        """Documents of these segments, in order; only those are decoded, each once."""
        new = segments[~run.known[segments]]
        if len(new):
            gaps, n = codec.pfor_decode_many(self.d[0], self.d[1][run.a + new])
            run.docs[_places(run.starts[new], n)] = pool.sums_within(gaps, n)
            run.known[new] = True
        return run.docs if len(segments) == len(run.n) else run.docs[_places(run.starts[segments], run.n[segments])]

    def svs(self, terms: tuple[str, ...], work: dict) -> np.ndarray:
        """As `small_versus_small`; probes are the comparisons of the bisections."""
        if not terms or any(t not in self.spans for t in terms):
            return np.zeros(0, np.int64)
        found = None
        for term in sorted(terms, key=lambda t: (self.size(t), t)):
            run = self.run(term)
            if found is None:
                segments = np.arange(len(run.n))
                found = self.docs(run, segments)
            else:
                at = np.searchsorted(run.last, found)
                work["probes"] += len(found) * len(run.last).bit_length()
                found, at = found[at < len(run.last)], at[at < len(run.last)]
                inside = run.first[at] <= found
                found, at = found[inside], at[inside]
                segments = at[np.flatnonzero(np.diff(at, prepend=-1))]
                docs = self.docs(run, segments)
                work["probes"] += len(found) * len(docs).bit_length()
                found = found[docs[np.searchsorted(docs, found)] == found] if len(found) else found
            work["segments_decoded"] += len(segments)
            work["postings_decoded"] += int(run.n[segments].sum())
            if not len(found):
                break
        return found

    def weights(self, run: Run, idf: float, avg: float) -> np.ndarray:
        """BM25 part of each posting."""
        if run.weights is None:
            tf = codec.pfor_decode_many(self.f[0], self.f[1][run.a : run.a + len(run.n)])[0]
            low = self.before[run.a]
            run.weights = idf * tf * (K1 + 1) / (tf + K1 * (1 - B + B * self.lengths[low : low + len(tf)] / avg))
        return run.weights

    def wand_work(self, terms: dict[str, tuple[float, float, int]], k: int, avg: float) -> dict:
        """The counters of `weak_and`, comparison for comparison, without its steps one by one.

        The threshold before a document is the k-th best score before it, as documents passed over are below the
        threshold anyway. So which documents are scored follows from their bounds, and after each of them all cursors
        stand at their next document: what happens between two scored documents depends on nothing else, and all these
        stretches advance together, a cursor each a step."""
        work = new_work()
        held = sorted((order, t, idf, bound) for t, (idf, bound, order) in terms.items() if t in self.spans)
        if not held:
            return work
        runs, docs, parts = [], [], []
        for _, term, idf, _ in held:
            run = self.run(term)
            runs.append(run)
            docs.append(self.docs(run, np.arange(len(run.n))))
            parts.append(self.weights(run, idf, avg))
        bound, reach = np.array([h[3] for h in held]), lambda total: total * (1 + 1e-9) + 1e-6
        place, u = _met(docs)
        m = len(docs)
        there = np.zeros((m, u), bool)
        score, lost, total = np.zeros(u), np.zeros(u), np.zeros(u)
        for i, (p, w) in enumerate(zip(place, parts)):
            there[i, p] = True
            old = score[p]
            score[p] = new = old + w
            lost[p] += np.where(np.abs(old) >= np.abs(w), (old - new) + w, (w - new) + old)  # as Python's sum
            total[p] += bound[i]
        before = np.zeros((m, u + 1), np.int64)
        np.cumsum(there, axis=1, out=before[:, 1:])
        least = _thresholds(_rounded(score + lost), k)
        scored = reach(total) >= least
        work["scored"] = work["pivots"] = int(scored.sum())
        seen = [np.zeros(len(r.n), bool) for r in runs]
        owner = [np.repeat(np.arange(len(r.n)), r.n) for r in runs]
        for i, run in enumerate(runs):
            ranks = before[i, :u][scored & there[i]]
            seen[i][owner[i][ranks]] = True
            ends = ranks + 1 == (run.starts + run.n)[owner[i][ranks]]
            work["probes"] += int(2 * (~ends).sum() + ends.sum()) - int(len(ranks) and ranks[-1] + 1 == len(docs[i]))
        starts = np.concatenate([[0], np.flatnonzero(scored) + 1])
        starts = starts[starts < u]
        starts = starts[~scored[starts]]
        low = least[starts]
        ahead = [np.append(p, u) for p in place]
        at = np.stack([a[b[starts]] for a, b in zip(ahead, before)], axis=1)
        moves = []
        while len(at):
            order = np.argsort(at, axis=1, kind="stable")
            sorted_at = np.take_along_axis(at, order, axis=1)
            enough = (reach(np.cumsum(np.where(sorted_at < u, bound[order], 0.0), axis=1)) >= low[:, None]) & (sorted_at < u)
            n = enough.argmax(axis=1)
            rows = np.arange(len(at))
            pivot = sorted_at[rows, n]
            go = np.flatnonzero(enough[rows, n] & (sorted_at[:, 0] < pivot))
            if not len(go):
                break
            at, low, pivot, first = at[go], low[go], pivot[go], order[go, 0]
            here, rows = at[np.arange(len(go)), first], np.arange(len(go))
            moves.append((first, before[first, here], before[first, pivot]))
            for i in range(m):
                mine = first == i
                at[rows[mine], i] = ahead[i][before[i, pivot[mine]]]
        if moves:
            first, a, b = (np.concatenate(x) for x in zip(*moves))
            work["pivots"] += len(first)
            for i, run in enumerate(runs):
                mine = first == i
                work["probes"] += _seeks(run, owner[i], a[mine], b[mine], seen[i])
        for i, run in enumerate(runs):
            work["segments_decoded"] += int(seen[i].sum())
            work["postings_decoded"] += int(run.n[seen[i]].sum())
        return work

    def wand(self, terms: dict[str, tuple[float, float, int]], k: int, avg: float) -> list[tuple[float, int]]:
        """The k best (score, doc), as `weak_and`."""
        docs, scores = self.wands([tuple(terms)], terms, k, avg)[0]
        return list(zip(scores.tolist(), docs.tolist()))

    def wands(self, asked: list[tuple[str, ...]], about: dict[str, tuple[float, float, int]], k: int, avg: float) -> list[tuple[np.ndarray, np.ndarray]]:
        """(documents, scores) of the k best of each query, as `weak_and`, with its test for a window of documents at a
        time: a document can be a pivot only if the bounds of the lists that hold it reach the threshold as it stood
        before the window. All queries meet a window before the next one, so that a segment is decoded once for all."""
        used = sorted({t for terms in asked for t in terms if t in self.spans and t in about}, key=lambda t: about[t][2])
        numbers = {t: i for i, t in enumerate(used)}
        queries = [sorted({numbers[t] for t in terms if t in numbers}) for terms in asked]
        idf, bound = (np.array([about[t][i] for t in used]) for i in (0, 1))
        top = [(np.zeros(0, np.int64), np.zeros(0)) for _ in asked]
        for window in self._windows(used, idf, avg):
            pivots = Pivots(window, bound)
            for q, terms in enumerate(queries):
                if here := [t for t in terms if t in window.spans]:
                    top[q] = pivots.better(here, k, *top[q])
        return top

    def _windows(self, used: list[str], idf: np.ndarray, avg: float) -> Iterator[Part]:
        """Lists and weights of stretches of documents, in order. Postings of a segment that reaches beyond its window
        wait for theirs."""
        if not used:
            return
        rows = np.concatenate([np.arange(*self.spans[t]) for t in used])
        owner = np.repeat(np.arange(len(used)), [z - a for a, z in (self.spans[t] for t in used)])
        order = np.argsort(self.first[rows], kind="stable")
        rows, owner = rows[order], owner[order]
        total, at, width = np.cumsum(self.n[rows]), 0, WINDOW
        left = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        while at < len(rows):
            end = min(len(rows), int(np.searchsorted(total, (total[at - 1] if at else 0) + width)) + 1)
            some, at, width = slice(at, end), end, min(2 * width, WIDEST)
            gaps, n = codec.pfor_decode_many(self.d[0], self.d[1][rows[some]])
            tf = codec.pfor_decode_many(self.f[0], self.f[1][rows[some]])[0]
            term = np.repeat(owner[some], n)
            w = idf[term] * tf * (K1 + 1) / (tf + K1 * (1 - B + B * self.lengths[_places(self.before[rows[some]], n)] / avg))
            held = [np.concatenate(x) for x in zip(left, (term, pool.sums_within(gaps, n), w))]
            inside = held[1] < self.first[rows[end]] if end < len(rows) else np.ones(len(held[1]), bool)
            left = tuple(x[~inside] for x in held)
            if inside.any():
                yield Part(*(x[inside] for x in held))


class Pivots:
    """The test of a window's documents against a query's threshold. bound: of each list."""

    def __init__(self, window: Part, bound: np.ndarray):
        self.window, self.bound = window, bound
        self.most, self.score = np.zeros(len(window.docs)), np.zeros(len(window.docs))
        self.rows: dict[int, np.ndarray] = {}

    def bounds(self, term: int) -> np.ndarray:
        if term not in self.rows:
            self.rows[term] = np.where(self.window.row(term) > 0, self.bound[term], 0.0)
        return self.rows[term]

    def better(self, terms: list[int], k: int, best: np.ndarray, scores: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The k best so far, with this window's."""
        window, most, score = self.window, self.most, self.score
        least = scores[-1] if len(scores) == k else -1.0
        low = (least - 1e-6) / (1 + 1e-9)
        if self.bound[terms].sum() < low:
            return best, scores
        lists = [(t, window.row(t), *window.spans[t]) for t in terms]
        places: slice | np.ndarray = slice(None)
        if least > 0:
            most[:] = 0
            for t, row, a, z in lists:
                if row is None:
                    most[window.place[a:z]] += self.bound[t]
                else:
                    most += self.bounds(t)
            pivots = np.flatnonzero(most >= low)
            if not len(pivots):
                return best, scores
            places = pivots if 4 * len(pivots) < len(most) else places
        score[:] = 0
        for _, row, a, z in lists:
            if row is None:
                score[window.place[a:z]] += window.w[a:z]
            elif isinstance(places, slice):
                score += row
        sums = score if isinstance(places, slice) else score[places] + sum(row[places] for _, row, _, _ in lists if row is not None)
        good = np.flatnonzero((sums >= least - 1e-6) & (sums > 0))
        sums = sums[good]
        if not isinstance(places, slice):
            good = places[good]
        if len(good) > 2 * k:
            good = good[sums >= np.partition(sums, -k)[-k] - 1e-6]
        if not len(good):
            return best, scores
        exact, lost = np.zeros(len(good)), np.zeros(len(good))
        for x in lists:
            more = self.at(x, good)
            new = exact + more
            lost += np.where(np.abs(exact) >= np.abs(more), (exact - new) + more, (more - new) + exact)  # as Python's sum
            exact = new
        best = np.concatenate([best, window.docs[good]])
        scores = np.concatenate([scores, np.array([round(x, 6) for x in (exact + lost).tolist()])])
        first = np.lexsort((best, -scores))[:k]
        return best[first], scores[first]

    def at(self, one: tuple, places: np.ndarray) -> np.ndarray:
        """A list's weights at these places, 0 where it has none."""
        _, row, a, z = one
        if row is not None:
            return row[places]
        some = self.window.place[a:z]
        i = np.minimum(np.searchsorted(some, places), len(some) - 1)
        return np.where(some[i] == places, self.window.w[a + i], 0.0)


def _met(docs: list[np.ndarray], sparse: int = 16) -> tuple[list[np.ndarray], int]:
    """Places of the lists' documents in the union of the lists, and its length."""
    low = min(d[0] for d in docs)
    span = int(max(d[-1] for d in docs) - low) + 1
    if span > sparse * sum(map(len, docs)):
        union = np.unique(np.concatenate(docs))
        return [np.searchsorted(union, d) for d in docs], len(union)
    there = np.zeros(span, bool)
    for d in docs:
        there[d - low] = True
    place = np.cumsum(there) - 1
    return [place[d - low] for d in docs], int(place[-1]) + 1


def _rounded(x: np.ndarray) -> np.ndarray:
    """Python's round(x, 6) of each."""
    scaled = x * 1e6
    out = np.rint(scaled) / 1e6
    near = np.flatnonzero(np.abs(scaled - np.floor(scaled) - 0.5) < 1e-4)
    out[near] = [round(v, 6) for v in x[near].tolist()]
    return out


def _thresholds(scores: np.ndarray, k: int, step: int = 512) -> np.ndarray:
    """The k-th best of the scores before each, -1 where there are fewer."""
    out = np.full(len(scores), -1.0)
    if len(scores) <= k:
        return out
    heap = scores[:k].tolist()
    heapq.heapify(heap)
    since, values, replace = [k], [heap[0]], heapq.heapreplace
    for a in range(k, len(scores), step):
        some = scores[a : a + step]
        places = np.flatnonzero(some > heap[0])
        for i, x in zip(places.tolist(), some[places].tolist()):
            if x > heap[0]:
                replace(heap, x)
                since.append(a + i + 1)
                values.append(heap[0])
    out[k:] = np.array(values)[np.searchsorted(since, np.arange(k, len(scores)), side="right") - 1]
    return out


def _gallops(lo: np.ndarray, n: np.ndarray, found: np.ndarray) -> int:
    """Comparisons that `gallop` makes from `lo` among `n` values to the place found."""
    lo, hi, step, probes = lo.copy(), lo.copy(), 1, 0
    moving = np.flatnonzero(hi < n)
    while len(moving):
        probes += len(moving)
        moving = moving[found[moving] > hi[moving]]
        lo[moving] = hi[moving] + 1
        hi[moving] += step
        step *= 2
        moving = moving[hi[moving] < n[moving]]
    hi = np.minimum(hi, n)
    moving = np.flatnonzero(lo < hi)
    while len(moving):
        probes += len(moving)
        mid = (lo[moving] + hi[moving]) // 2
        less = mid < found[moving]
        lo[moving[less]] = mid[less] + 1
        hi[moving[~less]] = mid[~less]
        moving = moving[lo[moving] < hi[moving]]
    return probes


def _seeks(run: Run, owner: np.ndarray, a: np.ndarray, b: np.ndarray, seen: np.ndarray) -> int:
    """Comparisons of a cursor's moves from its a-th to its b-th posting, as `Cursor.seek`; segments that it decodes for
    them are seen."""
    here, there = owner[a], np.append(owner, len(run.n))[b]
    leave = there > here
    probes = _gallops(here[leave] + 1, np.full(int(leave.sum()), len(run.n)), there[leave])
    inside = b < len(owner)
    inside[inside] &= ~leave[inside] | (b[inside] > run.starts[there[inside]])
    segment = there[inside]
    seen[segment] = True
    return probes + _gallops(np.where(leave, 0, a - run.starts[here])[inside], run.n[segment], b[inside] - run.starts[segment])


def _places(starts: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Places of stretches that begin at `starts`, one after the other."""
    return np.arange(n.sum()) + np.repeat(starts - (np.cumsum(n) - n), n)


def by_shard(segments: DataFrame, queries: DataFrame, columns: list[str], kernel, schema: str) -> DataFrame:
    """The kernel over each shard's segments of terms that some query has, with only the asked-for columns.

    A table of `index.serve` is bucketed by `slot`, so that its shards are read where they lie; other segments are
    shuffled by shard. A worker holds the compressed blocks of one shard's query terms: shards, being document ranges,
    are to be cut so that these fit."""
    ship(segments.sparkSession)
    key = "slot" if "slot" in segments.columns else "shard"
    terms = queries.select(F.explode("terms").alias("term")).distinct()
    rows = segments.select(key, "term", "seg_no", "n_docs", "first_doc", "last_doc", *columns).join(F.broadcast(terms), "term", "left_semi")
    return rows.groupBy(key).applyInArrow(kernel, schema)


COUNTERS = ("segments_decoded", "postings_decoded", "probes", "pivots", "scored")
COUNTED = "query_id long, " + ", ".join(f"{c} long" for c in COUNTERS)


def _counted(counts: list[tuple[int, dict]]) -> pa.Table:
    rows = [(q, *(work[c] for c in COUNTERS)) for q, work in counts]
    return pa.table({n: pa.array(c, pa.int64()) for n, c in zip(["query_id", *COUNTERS], zip(*rows) if rows else [()] * (1 + len(COUNTERS)))})


def _over_batches(queries: DataFrame, one) -> DataFrame:
    """Answers of query batches are disjoint by query."""
    return reduce(DataFrame.unionByName, map(one, query_batches(queries)))


def svs(segments: DataFrame, queries: DataFrame, counters: bool = False, sizes: bool = False) -> DataFrame:
    """(query_id, doc_id), or (query_id, counters) with counters=True, or (query_id, n_docs) of queries with answers with
    sizes=True. Each shard answers all queries; answers of shards are disjoint, so nothing is shuffled after the kernel.
    Queries of the same terms are answered once."""

    def one(part: DataFrame) -> DataFrame:
        batch = segments.sparkSession.sparkContext.broadcast(by_terms(collected(part)))

        def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            shard = Shard(pa.Table.from_batches(list(it)))

            def parts() -> Iterator[tuple[list[int], list[np.ndarray]]]:
                for terms, ids in batch.value:
                    work = new_work()
                    found = shard.svs(terms, work)
                    if counters:
                        yield ids, [np.array([work[c]]) for c in COUNTERS]
                    else:
                        yield ids, [np.array([len(found)] if len(found) else [], np.int64)] if sizes else [found]

            names = ["query_id", *(COUNTERS if counters else ["n_docs" if sizes else "doc_id"])]
            yield from answers(parts(), names, [pa.int64()] * len(names))

        return by_shard(segments, part, ["d_block"], kernel, COUNTED if counters else f"query_id long, {'n_docs' if sizes else 'doc_id'} long")

    out = _over_batches(queries, one)
    if counters:
        return out.groupBy("query_id").agg(*(F.sum(c).alias(c) for c in COUNTERS))
    return out.groupBy("query_id").agg(F.sum("n_docs").alias("n_docs")) if sizes else out


def wand(segments: DataFrame, queries: DataFrame, dictionary: DataFrame, coll: DataFrame, k: int, by_block: bool = False, counters: bool = False) -> DataFrame:
    """(query_id, rank, doc_id, score). dictionary: (term, term_id, df, max_contrib) with statistics of the whole
    collection, so that scores of shards compare; by_block turns on the block-max test with the segments' `bound`.

    Of the dictionary only the terms of a query batch come to the driver. A document's length is read from the segment
    under the cursor."""
    spark = segments.sparkSession
    n_docs, avg = coll.select("n_docs", "avg_len").first()

    def one(part: DataFrame) -> DataFrame:
        used = part.select(F.explode("terms").alias("term")).distinct()
        idf = F.log1p((F.lit(n_docs) - F.col("df") + 0.5) / (F.col("df") + 0.5))
        info = {r.term: (float(r.idf), float(r.max_contrib), int(r.term_id)) for r in dictionary.join(F.broadcast(used), "term", "left_semi").select("term", "term_id", "max_contrib", idf.alias("idf")).collect()}
        batch = spark.sparkContext.broadcast((collected(part), info))

        def whole(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            shard = Shard(pa.Table.from_batches(list(it)))
            wanted, about = batch.value

            asked = by_terms(wanted)
            top = shard.wands([terms for terms, _ in asked], about, k, avg)
            yield from answers(((ids, list(columns)) for (_, ids), columns in zip(asked, top)), ["query_id", "doc_id", "score"], [pa.int64(), pa.int64(), pa.float64()])

        def counted(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            shard = Shard(pa.Table.from_batches(list(it)))
            wanted, about = batch.value
            works = ((ids, shard.wand_work({t: about[t] for t in terms if t in about}, k, avg)) for terms, ids in by_terms(wanted))
            yield from answers(((ids, [np.array([work[c]]) for c in COUNTERS]) for ids, work in works), ["query_id", *COUNTERS], [pa.int64()] * (1 + len(COUNTERS)))

        def kernel(table: pa.Table) -> pa.Table:
            lists, out, counts = Lists.of_table(table), [], []
            wanted, about = batch.value
            for query, terms in wanted:
                work = new_work()
                top = weak_and(lists, {t: about[t] for t in terms if t in about}, k, avg, work, by_block)
                out += [(query, d, s) for s, d in top]
                counts.append((query, work))
            if counters:
                return _counted(counts)
            kinds = {"query_id": pa.int64(), "doc_id": pa.int64(), "score": pa.float64()}
            return pa.table({n: pa.array(c, t) for (n, t), c in zip(kinds.items(), zip(*out) if out else [()] * 3)})

        step = kernel if by_block else counted if counters else whole  # the block-max test is that of the posting loop
        return by_shard(segments, part, ["d_block", "f_block", "lengths", *(["bound"] if by_block else [])], step, COUNTED if counters else "query_id long, doc_id long, score double")

    found = _over_batches(queries, one)
    return found.groupBy("query_id").agg(*(F.sum(c).alias(c) for c in COUNTERS)) if counters else ranked(found, k)
