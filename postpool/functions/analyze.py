"""Text to terms, as expressions."""

from __future__ import annotations

from pyspark.sql import Column, functions as F

SEPARATORS = r"[^\p{L}\p{N}]+"
#: Suffixes of the light stemmer, longest first (fixed values).
SUFFIXES = "ations ation ments ment ings ing edly ely ies ed ly es s".split()


def words(text: Column) -> Column:
    """Lower-case runs of letters and digits; none for null."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), SEPARATORS), lambda w: w != "")


def stem(term: Column) -> Column:
    """Strip one suffix if at least three characters stay."""
    return F.regexp_replace(term, f"(?<=.{{3}})(?:{'|'.join(SUFFIXES)})$", "")


def strip_markup(html: Column) -> Column:
    """Drop scripts, styles, comments, tags and character references."""
    out = F.coalesce(html, F.lit(""))
    for pattern in (r"(?s)<script.*?</script>", r"(?s)<style.*?</style>", r"(?s)<!--.*?-->", r"<[^>]*>", r"&[a-zA-Z]+;|&#[0-9]+;"):
        out = F.regexp_replace(out, pattern, " ")
    return out


def row_postings(words: Column) -> Column:
    """Within one row: array of (term, tf, positions) of a document's words. Word occurrences are sorted once and cut
    where the term changes, so that inverting a document needs no shuffle."""
    occ = F.sort_array(F.transform(words, lambda w, i: F.struct(w.alias("term"), (i + 1).alias("pos"))))
    return occ


def cut(occurrences: Column) -> Column:
    """array of (term, tf, positions) from the sorted occurrences of `row_postings`."""
    n = F.size(occurrences)
    starts = F.filter(F.when(n > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>")), lambda i: (i == 0) | (F.get(occurrences, i)["term"] != F.get(occurrences, i - 1)["term"]))
    ends = F.concat(F.slice(starts, 2, F.greatest(F.size(starts), F.lit(1))), F.array(n))
    return F.zip_with(
        starts, F.slice(ends, 1, F.size(starts)),
        lambda s, e: F.struct(F.get(occurrences, s)["term"].alias("term"), (e - s).alias("tf"), F.transform(F.slice(occurrences, s + 1, e - s), lambda o: o["pos"]).alias("positions")),
    )


def position_gaps(positions: Column) -> Column:
    """First position, then successive differences; starts anew in each document."""
    return F.transform(positions, lambda p, i: F.when(i == 0, p).otherwise(p - F.get(positions, i - 1)))


def restore_positions(gaps: Column, tfs: Column) -> Column:
    """array of position arrays: term frequencies cut the gaps of a list, running sums undo them."""
    ends = F.aggregate(tfs, F.array().cast("array<int>"), lambda acc, t: F.concat(acc, F.array((F.coalesce(F.try_element_at(acc, F.lit(-1)), F.lit(0)) + t).cast("int"))))
    parts = F.zip_with(tfs, ends, lambda t, e: F.slice(gaps, (e - t + 1).cast("int"), t.cast("int")))
    return F.transform(parts, lambda g: F.aggregate(g, F.array().cast("array<int>"), lambda acc, x: F.concat(acc, F.array((F.coalesce(F.try_element_at(acc, F.lit(-1)), F.lit(0)) + x).cast("int")))))
