"""Near duplicates by ProbMinHash over word shingles, banding and exact verification.

Sketch: each shingle is a Poisson process whose rate is its weight; an arrival draws a register, and a register keeps
the shingle of its first arrival. Shingles leave as soon as their next arrival is later than every register's, so few
of them go beyond one step. Equal registers estimate the probability Jaccard similarity. Every text has the bands of a
sketch with unit weights, whose similarity is the plain Jaccard similarity of the link rule, so that a link's chance to
share a bucket doesn't depend on how often a shingle repeats. A text with repeated shingles also has the bands of a
sketch with weights 1 + ln(count); without repeats the two sketches are the same.

Classes: texts with equal words are first collapsed to one representative, named by a number of its own and not by a
document id; its text is the row's with its smallest id and text digest. Bands of registers are bucket keys;
every representative is verified against its buckets' centres, and connected components join what passes. What the
centres leave apart is compared in full, with links as the only output: members of one family outside its largest
component against the family, and members of different families that share a bucket, both in blocks of a bounded
number of rows. So no similar pair that shares a bucket stays unlinked. Verification is exact: Jaccard of the sets of five-word shingles, at least the threshold.

Edge cases: texts without a word form classes by equal text; a null text is a class of its own (by row id if that is
null too: all such rows share class null); texts of fewer words than a shingle are one shingle; repeated rows get the
same class; equal ids with different texts are linked through their own texts, and each row gets its own class (two
unlike classes can have the same smallest id, and keep_one keeps a row of each); rows without id are linked alike, and
a class of them alone has class null; empty
tables give no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..runtime import materialise, shuffle_partitions
from .common import pick

WORDS, THRESHOLD = 5, 0.8
#: Bands and registers of a band: a pair whose shingle sets are at the threshold misses all bands of unit weights with
#: probability 3e-5, whatever the counts of its shingles are.
BANDS, ROWS = 20, 4
_WORD = re.compile(r"[^\W_]+")
_M = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser, for pseudo-random numbers that depend on the element alone."""
    x = x + _M[0]
    x = (x ^ (x >> np.uint64(30))) * _M[1]
    x = (x ^ (x >> np.uint64(27))) * _M[2]
    return x ^ (x >> np.uint64(31))


def split_words(text: str | None) -> list[str]:
    """Runs of letters and digits, in lower case."""
    return _WORD.findall(text.lower()) if text else []


class Hasher:
    """Word to 64-bit hash, remembered within a worker up to a bound."""

    def __init__(self, most: int = 100_000):
        self.known: dict[str, int] = {}
        self.most = most

    def __call__(self, words: list[str]) -> np.ndarray:
        import xxhash

        known = self.known
        try:
            return np.array([known[w] for w in words], np.uint64)
        except KeyError:
            if len(known) > self.most:
                known.clear()
            for w in words:
                if w not in known:
                    known[w] = xxhash.xxh3_64_intdigest(w)
            return np.array([known[w] for w in words], np.uint64)


def shingle_hashes(hashes: np.ndarray, size: int = WORDS) -> np.ndarray:
    """One hash for each run of `size` words, or for all words if there are fewer."""
    size = min(size, len(hashes))
    if not size:
        return hashes
    n = len(hashes) - size + 1
    out = np.zeros(n, np.uint64)
    for j in range(size):
        out = mix(out ^ hashes[j : j + n])
    return out


def prob_minhash(elements: np.ndarray, weights: np.ndarray, owner: np.ndarray, n_docs: int, registers: int) -> np.ndarray:
    """[n_docs, registers] element of the first arrival in each register; element i with weight belongs to a document.

    All documents advance together: one arrival of every element still in play a step."""
    first = np.full(n_docs * registers, np.inf)
    held = np.zeros(n_docs * registers, np.uint64)
    state, at = mix(elements), np.zeros(len(elements))
    weights = weights.astype(float)
    while len(elements):
        state = mix(state)
        at = at - np.log1p(-((state >> np.uint64(11)).astype(float) * 2.0**-53)) / weights
        slot = owner * registers + (mix(state ^ _M[1]) % np.uint64(registers)).astype(np.int64)
        early = at < first[slot]
        np.minimum.at(first, slot[early], at[early])
        won = early & (at == first[slot])
        held[slot[won]] = elements[won]
        latest = first.reshape(n_docs, registers).max(axis=1)
        go = at < latest[owner]
        elements, weights, owner, state, at = elements[go], weights[go], owner[go], state[go], at[go]
    return held.reshape(n_docs, registers)


def band_hashes(elements: list[np.ndarray], weights: list[np.ndarray], bands: int, rows: int) -> np.ndarray:
    """[documents, bands] hash of each band of the documents' sketches."""
    owner = np.repeat(np.arange(len(elements)), [len(e) for e in elements])
    held = prob_minhash(np.concatenate(elements), np.concatenate(weights), owner, len(elements), bands * rows)
    mixed = np.zeros((len(elements), bands), np.uint64)
    for j in range(rows):
        mixed = mix(mixed ^ held.reshape(-1, bands, rows)[:, :, j])
    return mixed ^ mix(np.arange(bands, dtype=np.uint64))


def estimate(a: np.ndarray, b: np.ndarray) -> float:
    """Estimated probability Jaccard similarity of two sketches."""
    return float((a == b).mean())


#: Documents that are sketched together.
SLICE = 250
SKETCH = "doc_id long, mark binary, key binary, n_shingles long, bands array<long>"


def marked(docs: DataFrame) -> DataFrame:
    """(doc_id, text, mark): a row is known by its id and mark, the digest of its text."""
    return pick(docs, doc_id="long", text="string").withColumn("mark", F.unhex(F.md5("text")))


def sketch(docs: DataFrame, bands: int = BANDS, rows: int = ROWS, size: int = WORDS) -> DataFrame:
    """SKETCH: digests of the text and of the word sequence (of the text if it has no word, null for null), and the distinct hashes of
    its bands: `bands` of unit weights, and for a text with repeated shingles as many of its weights."""

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Hasher()
        for whole in it:
            for start in range(0, whole.num_rows, SLICE):
                batch = whole.slice(start, SLICE)
                keys, elements, counts = [], [], []
                for text in batch.column(1).to_pylist():
                    words = split_words(text)
                    keys.append(hashlib.md5(" ".join(words).encode() if words else b"\0" + text.encode()).digest() if text is not None else None)
                    found, n = np.unique(shingle_hashes(hasher(words), size), return_counts=True)
                    elements.append(found), counts.append(n)
                plain = band_hashes(elements, [np.ones(len(n)) for n in counts], bands, rows)
                lists = [m if len(n) else [] for m, n in zip(plain.view(np.int64).tolist(), counts)]
                again = [i for i, n in enumerate(counts) if n.max(initial=1) > 1]
                if again:
                    weighted = band_hashes([elements[i] for i in again], [1 + np.log(counts[i]) for i in again], bands, rows)
                    for i, m in zip(again, weighted.view(np.int64).tolist()):
                        lists[i] = list(dict.fromkeys(lists[i] + m))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(keys, pa.binary()), pa.array(map(len, counts), pa.int64()), pa.array(lists, pa.list_(pa.int64()))], names=["doc_id", "mark", "key", "n_shingles", "bands"])
        pa.default_memory_pool().release_unused()

    return marked(docs).mapInArrow(kernel, SKETCH)


def jaccard(pairs: DataFrame, size: int = WORDS) -> DataFrame:
    """(a, b, similarity) of (a, b, text_a, text_b): exact Jaccard similarity of the shingle sets."""

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher, last, held = Hasher(), None, None
        for batch in it:
            out = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                if y != last:
                    last, held = y, np.unique(shingle_hashes(hasher(split_words(y)), size))
                other = np.unique(shingle_hashes(hasher(split_words(x)), size))
                both = len(np.intersect1d(other, held, assume_unique=True))
                out.append(both / max(1, len(other) + len(held) - both))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.float64())], names=["a", "b", "similarity"])
        pa.default_memory_pool().release_unused()

    return pairs.select("a", "b", "text_a", "text_b").mapInArrow(kernel, "a long, b long, similarity double")


def met(rows: DataFrame, other: DataFrame, key: str | list[str], how: str = "inner") -> DataFrame:
    """An equi join of two tables that grow with the input. It is never broadcast, whatever the session's threshold is:
    a side that is small today would be collected and hashed on the driver, dozens of times a run."""
    return rows.join(other.hint("merge"), key, how)


def verified(pairs: DataFrame, texts: DataFrame, threshold: float, size: int) -> DataFrame:
    """Distinct (a, b) whose texts are similar. Texts move by row id; only those of candidates are joined."""
    left = texts.select(F.col("rep").alias("a"), F.col("text").alias("text_a"))
    right = texts.select(F.col("rep").alias("b"), F.col("text").alias("text_b"))
    return jaccard(met(met(pairs, right, "b"), left, "a"), size).where(F.col("similarity") >= threshold).select("a", "b")


def components(links: DataFrame) -> DataFrame:
    """(node, label): the smallest node of each connected component, for nodes with a link.

    Labels spread over links and then jump to their label's label; each round is written to the shared folder."""
    files = files_for(links, 2 * links.count())
    both = materialise(links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct().coalesce(files), "links")
    labels = materialise(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("label")).select(F.col("a").alias("node"), "label").coalesce(files), "labels")
    while True:
        heard = met(both, labels.withColumnRenamed("node", "b"), "b").groupBy("a").agg(F.min("label").alias("heard"))
        near = met(labels, heard.withColumnRenamed("a", "node"), "node", "left").select("node", "label", F.least("label", "heard").alias("next"))
        jump = labels.select(F.col("node").alias("next"), F.col("label").alias("far"))
        new = materialise(met(near, jump, "next", "left").select("node", "label", F.least("next", "far").alias("fresh")).coalesce(files), "labels")
        if new.where("fresh < label").isEmpty():
            return labels
        labels = new.select("node", F.col("fresh").alias("label"))


#: Rows of a written table's file, as long as there are fewer than the shuffle partitions.
FILE_ROWS = 10_000


def files_for(df: DataFrame, rows: int) -> int:
    """How many files a table of so many rows gets: small tables shouldn't be thousands of tiny files."""
    return min(shuffle_partitions(df.sparkSession), max(4, -(-rows // FILE_ROWS)))


def centred(reps: DataFrame, files: int) -> DataFrame:
    """(bucket, rep, n, centre, weight) of buckets with several representatives. A bucket's centre is the member that
    meets most others over all its buckets (`weight`), as an original among its edited copies does; ties to the smaller."""
    member = reps.select("rep", "n", F.explode("bands").alias("bucket"))
    sizes = member.groupBy("bucket").agg(F.count(F.lit(1)).alias("size")).where("size > 1")
    shared = materialise(met(member, sizes, "bucket").coalesce(files), "buckets")
    weight = shared.groupBy("rep").agg(F.sum("size").alias("weight"))
    shared = materialise(met(shared, weight, "rep").select("bucket", "rep", "n", "weight").coalesce(files), "buckets")
    centre = shared.groupBy("bucket").agg(F.max(F.struct("weight", (-F.col("rep")).alias("c"))).alias("m"))
    return materialise(met(shared.drop("weight"), centre, "bucket").select("bucket", "rep", "n", (-F.col("m.c")).alias("centre"), F.col("m.weight").alias("weight")).coalesce(files), "buckets")


#: Parts that rows of one key are dealt to in a join with a row for each key.
SALTS = 32


def spread_join(rows: DataFrame, per_key: DataFrame, key: list[str]) -> DataFrame:
    """rows with the columns of per_key (a row for each key). One key may have a third of all rows: its rows are dealt to
    SALTS parts by `rep`, and each row of per_key goes to all of them."""
    salted = per_key.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    dealt = rows.withColumn("salt", F.pmod(F.xxhash64("rep"), F.lit(SALTS)).cast("int"))
    return dealt.join(salted.hint("merge"), [*key, "salt"]).drop("salt")  # families grow with the input: never broadcast


def links_in_blocks(rows: DataFrame, key: list[str], texts: DataFrame, threshold: float, size: int, block: int) -> DataFrame:
    """(a, b) links from (key, side, rep, label): within a key every row of the true side meets every row of the false
    one, in blocks of about `block` rows a side. A block pair emits no pairs but the links that join components it still
    sees apart, fewer than it has rows."""
    counts = rows.groupBy(*key).agg(F.sum(F.col("side").cast("int")).alias("n"), F.sum((~F.col("side")).cast("int")).alias("m"))
    parts = lambda c: F.greatest(F.ceil(F.col(c) / F.lit(block)), F.lit(1)).cast("int")
    rows = met(spread_join(rows, counts.where("n > 0 AND m > 0").select(*key, parts("n").alias("rows"), parts("m").alias("cols")), key), texts, "rep")
    deal = lambda n: F.pmod(F.xxhash64("rep"), n).cast("int")
    other = F.when(F.col("side"), F.col("cols")).otherwise(F.col("rows"))
    rows = rows.select(*key, "side", "rep", "label", "text", deal(F.when(F.col("side"), F.col("rows")).otherwise(F.col("cols"))).alias("mine"), F.explode(F.sequence(F.lit(0), other - 1)).alias("theirs"))
    rows = rows.withColumns({"i": F.when(F.col("side"), F.col("mine")).otherwise(F.col("theirs")), "j": F.when(F.col("side"), F.col("theirs")).otherwise(F.col("mine"))})

    def kernel(table: pa.Table) -> pa.Table:
        hasher, group = Hasher(), {}
        side, reps, labels, texts = (table.column(c).to_pylist() for c in ("side", "rep", "label", "text"))
        known = {r: np.unique(shingle_hashes(hasher(split_words(t)), size)) for r, t in dict(zip(reps, texts)).items()}
        sets = [known[r] for r in reps]

        def find(x: int) -> int:
            while group.setdefault(x, x) != x:
                group[x] = group[group[x]]
                x = group[x]
            return x

        theirs = [i for i, m in enumerate(side) if not m]
        found = []
        if theirs and len(theirs) < len(side):
            vocabulary, number = np.unique(np.concatenate([sets[i] for i in theirs]), return_inverse=True)
            lengths = np.array([len(sets[i]) for i in theirs])
            starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
            mark = np.zeros(len(vocabulary), np.int32)
            for i in (i for i, m in enumerate(side) if m):
                at = np.minimum(np.searchsorted(vocabulary, sets[i]), len(vocabulary) - 1)
                at = at[vocabulary[at] == sets[i]]
                mark[at] = 1
                both = np.add.reduceat(mark[number], starts)
                mark[at] = 0
                for k in np.flatnonzero(both >= threshold * (lengths + len(sets[i]) - both) - 1e-9).tolist():
                    x, y = find(labels[i]), find(labels[theirs[k]])
                    if x != y:
                        group[max(x, y)] = min(x, y)
                        found.append((reps[i], reps[theirs[k]]))
        return pa.table({"a": pa.array([a for a, _ in found], pa.int64()), "b": pa.array([b for _, b in found], pa.int64())})

    return rows.drop("mine", "theirs").groupBy(*key, "i", "j").applyInArrow(kernel, "a long, b long")


def family_rows(families: DataFrame) -> DataFrame:
    """(hub, side, rep, label) from (rep, hub, label): members outside a family's largest component, and all members."""
    counts = families.groupBy("hub", "label").agg(F.count(F.lit(1)).alias("n"))
    whole = counts.groupBy("hub").agg(F.sum("n").alias("members"), F.max(F.struct("n", (-F.col("label")).alias("l"))).alias("main")).where("members > main.n")
    rows = spread_join(families, whole.select("hub", (-F.col("main.l")).alias("main")), ["hub"]).select("hub", "rep", "label", "main")
    minor = rows.where("label <> main").select("hub", F.lit(True).alias("side"), "rep", "label")
    return minor.unionByName(rows.select("hub", F.lit(False).alias("side"), "rep", "label"))


def meeting_rows(known: DataFrame) -> DataFrame:
    """(h0, h1, side, rep, label) from (bucket, rep, hub, label, main): for families that meet in a bucket where one is
    another's than the centre's, the members that lie in a bucket with the other family. Two families meet once,
    however many buckets they share."""
    hubs = known.select("bucket", "hub", "main").distinct()
    pairs = met(hubs.where("hub <> main").select("bucket", F.col("hub").alias("x")), hubs.select("bucket", F.col("hub").alias("y")), "bucket").where("x <> y")
    pairs = pairs.select("bucket", F.least("x", "y").alias("h0"), F.greatest("x", "y").alias("h1")).distinct()
    sides = pairs.select("bucket", "h0", "h1", F.explode(F.array(F.struct(F.lit(True).alias("side"), F.col("h0").alias("hub")), F.struct(F.lit(False).alias("side"), F.col("h1").alias("hub")))).alias("s")).select("bucket", "h0", "h1", "s.*")
    rows = met(known, sides, ["bucket", "hub"]).select("h0", "h1", "side", "rep", "label").distinct()
    apart = rows.groupBy("h0", "h1").agg(F.min("label").alias("l0"), F.max("label").alias("l1")).where("l0 < l1").select("h0", "h1")
    return spread_join(rows, apart, ["h0", "h1"])


#: Rows a side of a block pair.
BLOCK = 96


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, size: int = WORDS, block: int = BLOCK) -> DataFrame:
    """(doc_id, class_id): one row per input row; class_id is the smallest document id of its class."""
    return classified(docs, threshold, bands, rows, size, block).select("doc_id", "class_id")


def classified(docs: DataFrame, threshold: float, bands: int, rows: int, size: int, block: int = BLOCK) -> DataFrame:
    """(doc_id, mark, label, class_id) of each row; label tells classes apart, and is null for null texts."""
    docs = pick(docs, doc_id="long", text="string")
    sketches = materialise(sketch(docs, bands, rows, size), "sketches")
    files = files_for(docs, sketches.count())
    # the smallest id with its mark; rows without id only where there is no other
    row = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "mark"))
    reps = sketches.where("key IS NOT NULL").groupBy("key").agg(row.alias("row"), F.any_value("bands").alias("bands"), F.any_value("n_shingles").alias("n"))
    # numbers are given as the table is written, once
    reps = materialise(reps.coalesce(files).select(F.monotonically_increasing_id().alias("rep"), "key", "row.doc_id", "row.mark", "bands", "n"), "representatives")

    shared = centred(reps, files)
    pairs = materialise(shared.where("rep <> centre").select(F.greatest("rep", "centre").alias("a"), F.least("rep", "centre").alias("b")).distinct().coalesce(files), "pairs")
    # a representative's text: the row of its id and mark
    wanted = met(reps, shared.select("rep").distinct(), "rep", "left_semi").select("rep", F.col("doc_id").alias("its_id"), F.col("mark").alias("its_mark"))
    texts = marked(docs).where("text IS NOT NULL").join(wanted.hint("merge"), (F.col("mark") == F.col("its_mark")) & F.col("doc_id").eqNullSafe(F.col("its_id"))).groupBy("rep").agg(F.min("text").alias("text"))
    texts = materialise(texts.coalesce(files), "texts")
    links = materialise(verified(pairs, texts, threshold, size).repartition(files), "verified")  # few rows of many tasks
    labels = components(links)

    # what the centres leave open: components of one family (members with the same heaviest centre) ...
    hubs = shared.groupBy("rep").agg(F.max(F.struct("weight", (-F.col("centre")).alias("c"))).alias("m")).select("rep", (-F.col("m.c")).alias("hub"))
    labelled = met(hubs, labels.withColumnRenamed("node", "rep"), "rep", "left").select("rep", "hub", F.coalesce("label", "rep").alias("label"))
    labelled = materialise(labelled.coalesce(files), "families")
    inside = materialise(links_in_blocks(family_rows(labelled), ["hub"], texts, threshold, size, block).repartition(files), "verified")

    # ... and buckets where families meet: members of another family than the centre's against the others
    known = met(shared.select("bucket", "rep", "centre"), labelled, "rep")
    mixed = known.groupBy("bucket").agg(F.min("hub").alias("h0"), F.max("hub").alias("h1"), F.min("label").alias("l0"), F.max("label").alias("l1"), F.min(F.when(F.col("rep") == F.col("centre"), F.col("hub"))).alias("main")).where("h0 < h1 AND l0 < l1").select("bucket", "main")
    known = materialise(met(known, mixed, "bucket").select("bucket", "rep", "hub", "label", "main").coalesce(files), "mixed")
    across = links_in_blocks(meeting_rows(known), ["h0", "h1"], texts, threshold, size, block)
    more = materialise(inside.unionByName(across.repartition(files)), "verified")
    if not more.isEmpty():
        labels = components(links.unionByName(more))

    named = met(reps, labels.withColumnRenamed("node", "rep"), "rep", "left").select("key", "doc_id", F.coalesce("label", "rep").alias("label"))
    named = materialise(named.coalesce(files), "classes")
    smallest = named.groupBy("label").agg(F.min("doc_id").alias("class_id"))
    final = materialise(met(named.drop("doc_id"), smallest, "label").coalesce(files), "classes")
    out = met(sketches.select("doc_id", "mark", "key"), final, "key", "left")
    return out.select("doc_id", "mark", "label", F.when(F.col("label").isNull(), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"))


def keep_one(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, size: int = WORDS) -> DataFrame:
    """docs, all columns as they were, with the document of the smallest id of each class (of several texts of that id
    the one with the smallest digest); repeated rows of one id and text stay once. Of rows without id each text stays
    that no row with an id is like."""
    classes = classified(docs, threshold, bands, rows, size)
    counted = classes.where(F.col("doc_id").eqNullSafe(F.col("class_id"))).groupBy("label", "doc_id", "mark").agg(F.count(F.lit(1)).alias("n"))
    counted = materialise(counted.coalesce(files_for(docs, counted.count())), "kept")
    first = counted.where("label IS NOT NULL AND doc_id IS NOT NULL").groupBy("label").agg(F.min(F.struct("mark", "doc_id", "n")).alias("m")).select("m.*")
    alone = counted.where("label IS NULL OR doc_id IS NULL").select("mark", "doc_id", "n")
    kept = first.unionByName(alone).select(F.col("doc_id").alias("kept_id"), F.col("mark").alias("kept_mark"), "n")
    kept = materialise(kept.coalesce(files_for(docs, kept.count())), "kept")
    same = docs["doc_id"].cast("long").eqNullSafe(F.col("kept_id")) & F.unhex(F.md5(docs["text"].cast("string"))).eqNullSafe(F.col("kept_mark"))
    once = docs.join(kept.where("n = 1").hint("merge"), same, "left_semi")  # one plan at any size: ids of kept rows grow with the input
    if kept.where("n > 1").isEmpty():
        return once
    return once.unionByName(docs.join(kept.where("n > 1").hint("merge"), same, "left_semi").dropDuplicates(["doc_id", "text"]))
