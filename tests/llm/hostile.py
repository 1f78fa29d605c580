"""Small tables with everything an operator must bear."""

CLASH = ", key string, rep long, label string, bucket long, n long, slot long, shard string, payload binary, digest string, row long, turns string, bands string, salt long"
EXTRA = ("k", 1, "l", 2, 3, 4, "s", b"p", "d", 5, "t", "b", 6)

LONG = "lorem ipsum dolor sit amet " * 20000
PLAIN = "the quick brown fox jumps over the lazy dog and then it runs away from the big bad wolf in the dark wood near the old mill"


def documents(spark, rows=None):
    """doc_id, text, lang, source, n_chars and columns whose names clash with the operators' own."""
    rows = rows if rows is not None else [
        (1, PLAIN, "en", "a", 1), (2, PLAIN, "en", "a", 1), (2, PLAIN, "en", "a", 1), (3, None, "en", None, None), (4, "", None, "a", 0), (5, "!!! ...", "fr", "a", 7),
        (6, LONG, None, None, None), (None, "un texte sans nom mais avec des mots", "fr", "a", 2), (None, None, None, None, None), (7, "x", "en", "b", 1), (8, "été à la plage 日本語 \U0001f600 \x00  ", "fr", "b", 1),
    ]
    return spark.createDataFrame([(*r, *EXTRA) for r in rows], "doc_id long, text string, lang string, source string, n_chars long" + CLASH)


def empty(spark):
    return documents(spark, [])
