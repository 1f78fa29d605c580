"""Language ID as mixture inference: each document is a mixture of languages, word by word.

Training counts letter trigrams (with word edges) of every labelled text in hashed buckets, per language: partial
counts in each task, summed by Spark; the model has languages x buckets numbers, both fixed parameters. Inference: a
word's likelihood under a language is the product of its trigrams'; expectation-maximisation over a document's words
gives the language proportions; the set of languages is the one of best penalised likelihood among the nested sets
that the full mixture orders. Documents whose full mixture can't beat the best single language by the penalty stop
there, which is exact, as no subset has a higher likelihood than the full set.

Edge cases: a null, empty or letterless text is `und` with score 0, as is everything if no labelled text has a letter;
ties between languages go to the alphabetically first; null labels don't train; equal texts get equal answers; a very
long text is worked on whole, apart from others; other columns are ignored.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import filter_rows, pick

UNKNOWN = "und"
#: Trigram buckets, the most languages a model may have, letters of one unit (longer runs of letters are cut).
BUCKETS, MOST_LANGUAGES, UNIT = 1 << 16, 512, 24
#: Weight of the uniform part of each language's trigram distribution, power of a trigram's likelihood (neighbours share
#: letters, so they aren't independent), EM steps, characters of one slice, price of one more language in log n.
SMOOTHING, TEMPER, STEPS, SLICE, PRICE = 0.02, 1 / 3, 15, 1 << 20, 2.0


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    """Code point to lower-case code point, 0 for what is no letter (marks inside words count as letters)."""
    out = np.zeros(0x110000, np.uint32)
    for c in range(0x110000):
        if 0xD800 <= c < 0xE000:
            continue
        ch = chr(c)
        if ch.isalpha():
            low = ch.lower()
            out[c] = ord(low) if len(low) == 1 else c
        elif 0x300 <= c < 0x20000 and unicodedata.category(ch)[0] == "M":
            out[c] = c
    return out


def trigrams(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bucket of each letter's trigram, first trigram of each word, text of each word)."""
    joined = "\0".join(texts).encode("utf-32-le", "replace")
    raw = np.frombuffer(joined, np.uint32)
    s = np.zeros(len(raw) + 2, np.uint32)
    s[1:-1] = _letters()[raw]
    at = np.flatnonzero(s)
    if not len(at):
        return np.zeros(0, np.int32), np.zeros(0, np.int64), np.zeros(0, np.int64)
    h = (s[at - 1] * np.uint32(0x9E3779B1)) ^ (s[at] * np.uint32(0x85EBCA6B)) ^ (s[at + 1] * np.uint32(0xC2B2AE35))
    h = ((h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D)) >> np.uint32(16)
    opens = np.empty(len(at), bool)
    opens[0] = True
    opens[1:] = at[1:] != at[:-1] + 1
    first = np.flatnonzero(opens)
    run = np.arange(len(at)) - np.repeat(first, np.diff(np.append(first, len(at))))
    first = np.flatnonzero(run % UNIT == 0)
    ends = np.cumsum([len(t) + 1 for t in texts])
    return h.astype(np.int32), first, np.searchsorted(ends, at[first] - 1, "right")


def _slices(texts: list[str]) -> Iterator[tuple[int, list[str]]]:
    """(first text, texts) of about SLICE characters; a longer text is a slice of its own."""
    start, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t) > SLICE:
            yield start, texts[start:i]
            start, size = i, 0
        size += len(t) + 1
    if start < len(texts):
        yield start, texts[start:]


def count_trigrams(labelled: DataFrame) -> DataFrame:
    """(lang, bucket, n) over all rows of (text, lang)."""

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, np.ndarray] = {}
        for batch in it:
            texts, langs = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for lang in set(langs):
                total = counts.setdefault(lang, np.zeros(BUCKETS, np.int64))
                if len(counts) > MOST_LANGUAGES:
                    raise ValueError(f"more than {MOST_LANGUAGES} languages")
                for _, part in _slices([t for t, x in zip(texts, langs) if x == lang]):
                    total += np.bincount(trigrams(part)[0], minlength=BUCKETS)
        for lang, total in counts.items():
            used = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(used), pa.string()), pa.array(used, pa.int32()), pa.array(total[used], pa.int64())], names=["lang", "bucket", "n"])

    rows = pick(labelled, text="string", lang="string").where("text IS NOT NULL AND lang IS NOT NULL")
    return rows.mapInArrow(kernel, "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))


def train(labelled: DataFrame) -> tuple[list[str], np.ndarray]:
    """(languages, log likelihoods [BUCKETS, languages]): a row for each language comes to the driver, with at most
    BUCKETS numbers."""
    rows = count_trigrams(labelled).groupBy("lang").agg(F.collect_list(F.struct("bucket", "n")).alias("counts"))
    found = rows.orderBy("lang").limit(MOST_LANGUAGES + 1).toArrow()
    names = found.column("lang").to_pylist()
    if len(names) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages")
    counts = np.zeros((BUCKETS, len(names)))
    for i in range(len(names)):
        one = found.column("counts")[i].values
        counts[one.field("bucket").to_numpy(), i] = one.field("n").to_numpy()
    if names:
        counts = (1 - SMOOTHING) * counts / counts.sum(axis=0) + SMOOTHING / BUCKETS
    return names, (TEMPER * np.log(counts)).astype(np.float32)


def _sums(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    return np.add.reduceat(values, first, axis=0)


def _em(w: np.ndarray, doc: np.ndarray, first: np.ndarray, n: np.ndarray, pi: np.ndarray, steps: int) -> tuple[np.ndarray, np.ndarray]:
    """(proportions, log likelihood) of each document, from starting proportions; languages at 0 stay out."""
    for _ in range(steps):
        r = w * pi[doc]
        r /= np.maximum(r.sum(axis=1, keepdims=True), 1e-30)
        pi = _sums(r, first) / n[:, None]
    total = np.log(np.maximum((w * pi[doc]).sum(axis=1), 1e-30))
    return pi, _sums(total, first)


def proportions(texts: list[str], table: np.ndarray) -> np.ndarray:
    """[texts, languages] proportions, rows of zeros for texts without a letter."""
    k = table.shape[1]
    out = np.zeros((len(texts), k))
    for start, part in _slices(texts):
        grams, first, owner = trigrams(part)
        if not len(first) or not k:
            continue
        ll = _sums(table[grams], first)
        top = ll.max(axis=1)
        w = np.exp(ll - top[:, None]).astype(np.float64)
        docs, begin, n = np.unique(owner, return_index=True, return_counts=True)
        doc = np.repeat(np.arange(len(docs)), n)
        single = _sums(ll.astype(np.float64), begin) - _sums(top.astype(np.float64), begin)[:, None]
        best = single.argmax(axis=1)
        pi = np.zeros((len(docs), k))
        pi[np.arange(len(docs)), best] = 1.0
        score = single[np.arange(len(docs)), best]
        price = PRICE * np.log(n + 1.0)
        open_ = np.flatnonzero(-score > price)  # the likelihood of any mixture is at most 0 here
        if k > 1 and len(open_):

            def only(chosen: np.ndarray) -> tuple[np.ndarray, ...]:
                keep = np.isin(doc, chosen)
                counts = n[chosen]
                return w[keep], np.repeat(np.arange(len(chosen)), counts), np.concatenate([[0], np.cumsum(counts)[:-1]]), counts

            args = only(open_)
            full, reach = _em(*args, np.full((len(open_), k), 1.0 / k), STEPS)
            order = np.argsort(-full, axis=1, kind="stable")
            more = reach - score[open_] > price[open_]
            chosen, order, full, reach = open_[more], order[more], full[more], reach[more]
            for size in range(2, k + 1):
                still = reach - score[chosen] > 0
                if not still.any():
                    break
                chosen, order, full, reach = chosen[still], order[still], full[still], reach[still]
                mask = np.zeros_like(full)
                np.put_along_axis(mask, order[:, :size], 1.0, axis=1)
                fit, value = _em(*only(chosen), mask / size, STEPS)
                value = value - (size - 1) * price[chosen]
                better = value > score[chosen]
                score[chosen[better]], pi[chosen[better]] = value[better], fit[better]
                reach = reach - price[chosen]
        lettered = [any(map(str.isalpha, part[d])) for d in docs]
        out[start + docs] = pi * np.array(lettered)[:, None]
    return out


PREDICTED = "lang_pred string, score double, languages array<struct<lang:string,share:double>>"


def predict(docs: DataFrame, model: tuple[list[str], np.ndarray], id_type: str = "long") -> DataFrame:
    """(doc_id, PREDICTED): the language of the largest share, that share, and all shares above zero, largest first."""
    names, table = model
    shared = docs.sparkSession.sparkContext.broadcast((names, table))  # at most MOST_LANGUAGES x BUCKETS floats

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, table = shared.value
        kind = pa.list_(pa.struct([("lang", pa.string()), ("share", pa.float64())]))
        for batch in it:
            shares = proportions([t or "" for t in batch.column(1).to_pylist()], table)
            order = np.argsort(-shares, axis=1, kind="stable") if names else None
            preds, scores, lists = [], [], []
            for i, row in enumerate(shares):
                found = [{"lang": names[j], "share": float(row[j])} for j in order[i] if row[j] > 0] if names else []
                preds.append(found[0]["lang"] if found else UNKNOWN)
                scores.append(min(1.0, found[0]["share"]) if found else 0.0)
                lists.append(found)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(preds, pa.string()), pa.array(scores, pa.float64()), pa.array(lists, kind)], names=["doc_id", "lang_pred", "score", "languages"])

    return pick(docs, doc_id=id_type, text="string").mapInArrow(kernel, f"doc_id {id_type}, {PREDICTED}")


def held_out(doc_id: str = "doc_id", folds: int = 5):
    """True for the fold that no model sees: crc32 of the id as text, modulo the folds, is 0."""
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")) % folds == 0


def learn_and_predict(docs: DataFrame) -> DataFrame:
    """(doc_id, held_out, PREDICTED): learn from the labelled rows outside the held-out fold, predict every row."""
    model = train(docs.where(~held_out()))
    out = predict(docs, model)
    return out.select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "languages")


def keep_identified(docs: DataFrame, model: tuple[list[str], np.ndarray], least: float = 0.5) -> DataFrame:
    """docs, all columns as they were, without the rows whose text has no letter or no language of at least this share."""
    shared = docs.sparkSession.sparkContext.broadcast(model[1])  # at most MOST_LANGUAGES x BUCKETS floats
    return filter_rows(docs, "text", lambda texts: (proportions([t or "" for t in texts], shared.value).max(axis=1, initial=0.0) >= least).tolist())
