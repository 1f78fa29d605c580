"""Retrieval over parts of the documents: postings of the query terms are dealt by document, and a task answers the whole
query set over its part's lists as arrays."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, functions as F

from ..runtime import ship

#: Query terms that are sent to every executor at once; larger query sets are run in batches.
BATCH_TERMS = 200_000
#: Postings of a part, about.
PART = 1 << 22
#: A list with more than one in so many of a part's documents is kept as a value for each of them.
DENSE = 4
#: Scores below the k-th best by less than this can be equal to it once rounded.
SLACK = 1e-6


def query_batches(queries: DataFrame, most: int | None = None) -> list[DataFrame]:
    """The query set in batches of about `most` terms, by a hash of the query."""
    n = queries.agg(F.coalesce(F.sum(F.size("terms")), F.lit(0))).first()[0]
    parts = max(1, -(-n // (most or BATCH_TERMS)))
    return [queries] if parts == 1 else [queries.where(F.pmod(F.xxhash64("query_id"), F.lit(parts)) == i) for i in range(parts)]


def collected(queries: DataFrame) -> list[tuple[int, list[str]]]:
    """A query batch, on the driver."""
    return [(r.query_id, list(dict.fromkeys(r.terms))) for r in queries.select("query_id", "terms").collect()]


def by_terms(batch: list[tuple[int, list[str]]]) -> list[tuple[tuple[str, ...], list[int]]]:
    """(terms, query ids): queries of the same terms have the same answer."""
    out: dict[tuple[str, ...], list[int]] = {}
    for query, terms in batch:
        out.setdefault(tuple(sorted(terms)), []).append(query)
    return list(out.items())


#: Rows of an answer batch, about.
ANSWER_ROWS = 1 << 17


def answers(parts: Iterator[tuple[list[int], list[np.ndarray]]], names: list[str], kinds: list[pa.DataType]) -> Iterator[pa.RecordBatch]:
    """(query_id, columns) rows in batches: every query id of a part with all of its rows."""
    held, rows = [[] for _ in names], 0

    def out() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(c) if c else [], t) for c, t in zip(held, kinds)], names=names)

    for ids, columns in parts:
        for query in ids if len(columns[0]) else []:
            for c, v in zip(held, [np.full(len(columns[0]), query), *columns]):
                c.append(v)
            rows += len(columns[0])
            if rows >= ANSWER_ROWS:
                yield out()
                held, rows = [[] for _ in names], 0
    yield out()


class Part:
    """Lists of a part's documents, by term number; a document is its place among them."""

    def __init__(self, term: np.ndarray, doc: np.ndarray, w: np.ndarray | None = None):
        self.docs, place = np.unique(doc, return_inverse=True)
        order = np.argsort(term.astype(np.int64) * max(1, len(self.docs)) + place)
        term = term[order]
        starts = np.flatnonzero(np.diff(term, prepend=-1))
        self.spans = dict(zip(term[starts].tolist(), zip(starts.tolist(), [*starts[1:].tolist(), len(term)])))
        self.place, self.w = place[order], None if w is None else w[order]
        self.rows: dict[int, np.ndarray] = {}
        self.sums = np.zeros(-(-len(self.docs) // 64) * 64)

    def row(self, term: int) -> np.ndarray | None:
        """A long list's value for each document: whether the term is there, or its weight."""
        found = self.rows.get(term)
        if found is None:
            a, z = self.spans[term]
            if (z - a) * DENSE > len(self.docs):
                found = self.rows[term] = np.zeros(len(self.docs), bool if self.w is None else np.float64)
                found[self.place[a:z]] = True if self.w is None else self.w[a:z]
        return found

    def having(self, terms: tuple[int, ...]) -> np.ndarray:
        """Documents with all the terms, the shortest list first."""
        if not terms or any(t not in self.spans for t in terms):
            return np.zeros(0, np.int64)
        size = lambda t: self.spans[t][1] - self.spans[t][0]
        found = None
        for term in sorted(terms, key=size):
            a, z = self.spans[term]
            if found is None:
                found = self.place[a:z]
            elif (row := self.row(term)) is not None:
                found = found[row[found]]
            else:
                some = self.place[a:z]
                found = found[some[np.minimum(np.searchsorted(some, found), len(some) - 1)] == found]
            if not len(found):
                break
        return self.docs[found]

    def best(self, terms: tuple[int, ...], k: int) -> tuple[np.ndarray, np.ndarray]:
        """(documents, rounded scores) of the part's k best: every posting of every term is added up."""
        here = [t for t in terms if t in self.spans]
        if not here:
            return np.zeros(0, np.int64), np.zeros(0)
        self.sums[:] = 0
        sums = self.sums[: len(self.docs)]
        for term in here:
            if (row := self.row(term)) is not None:
                sums += row
            else:
                a, z = self.spans[term]
                sums[self.place[a:z]] += self.w[a:z]
        tops = self.sums.reshape(-1, 64).max(axis=1)  # k stretches with a document each that good
        least = np.partition(tops, -k)[-k] if len(tops) > k else 0.0
        good = np.flatnonzero((sums > 0) & (sums >= least - SLACK))
        if len(good) > 2 * k:
            good = good[sums[good] >= np.partition(sums[good], -k)[-k] - SLACK]
        scores = np.array([round(x, 6) for x in sums[good].tolist()])
        first = np.lexsort((good, -scores))[:k]
        return self.docs[good[first]], scores[first]


def over_parts(postings: DataFrame, queries: DataFrame, columns: list[str], answer: Callable[[Part, tuple[int, ...]], list[np.ndarray]], schema: str, batches: list[DataFrame], known_only: bool = False) -> DataFrame:
    """What `answer` gives for each query over each part, with the query's id. postings: (term, doc_id, columns);
    batches: the queries in batches.

    Postings of query terms are dealt once, by document, to parts of about PART, and batches of queries are met there one
    after the other: the matches, which are many more, are neither shuffled nor kept. Queries of the same terms are
    answered once. known_only: terms without a posting are left out of the queries, else their lists are empty."""
    spark = postings.sparkSession
    ship(spark)
    words = [r.term for r in queries.select(F.explode("terms").alias("term")).distinct().collect()]
    chunks = [list(enumerate(words))[i : i + BATCH_TERMS] for i in range(0, max(1, len(words)), BATCH_TERMS)]
    named = [F.broadcast(spark.createDataFrame(chunk, "no int, term string")) for chunk in chunks]
    rows = reduce(DataFrame.unionByName, (postings.select("term", "doc_id", *columns).join(some, "term").select("no", "doc_id", *columns) for some in named))
    sizes = {r.no: r["count"] for r in rows.groupBy("no").count().collect()}
    numbers = {t: i for i, t in enumerate(words) if not known_only or i in sizes}

    def batch(part: DataFrame) -> Broadcast:
        asked = [(q, [numbers[t] for t in terms if t in numbers]) for q, terms in collected(part)]
        return spark.sparkContext.broadcast(by_terms(asked))

    sent = [batch(part) for part in batches]
    names = ["query_id", *(f.split()[0] for f in schema.split(", ")[1:])]
    kinds = [{"long": pa.int64(), "double": pa.float64()}[f.split()[1]] for f in schema.split(", ")]

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(it)) if (it := [b for b in it if b.num_rows]) else None
        if table is None:
            return
        part = Part(*(table[c].to_numpy() for c in ("no", "doc_id", *columns)))
        del table
        yield from answers(((ids, answer(part, terms)) for b in sent for terms, ids in b.value), names, kinds)

    n = max(spark.sparkContext.defaultParallelism, -(-sum(sizes.values()) // PART))
    return rows.repartition(n, "doc_id").mapInArrow(kernel, schema)
