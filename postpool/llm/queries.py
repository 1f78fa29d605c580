"""The queries of this folder's operators with production parameters, and their SQL where SQL can express them."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession, functions as F

from . import chat, decontaminate, flac, html_extract, language_id, near_dup, packing, sharding, token_counts, warc
from .common import table


def op1_length_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    lengths = token_counts.encoded_lengths(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    return token_counts.length_histogram(lengths)


def op2_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.learn_and_predict(table(spark, sf_dir, "documents"))


def op3_flac(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flac.features(flac.stored(table(spark, sf_dir, "documents")))


def op4_first_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op5_boosted_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.main_text(table(spark, sf_dir, "pages"))


def op6_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.sql("SELECT -1L AS conv_id, turn, role, '</s>[INST] ok [/INST]' AS text FROM VALUES (0L, 'user'), (1L, 'assistant') AS t(turn, role)")
    back = chat.read_back(chat.format_chats(rows.unionByName(probe)))
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join("loss_texts", "")
    return back.select("conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2(said, 256).alias("turns_sha256"), F.length(loss).cast("long").alias("loss_chars"), F.sha2(loss, 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"))


OP6_SQL = r"""
WITH r AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
           UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
o AS (SELECT *, row_number() OVER w AS k, lag(role) OVER w AS before FROM r WINDOW w AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text)),
c AS (SELECT *, before IS NULL OR before <> role AS opens,
             length(text) + length(regexp_replace(text, '[^\\<\[]', '', 'g')) AS n, length(role) + length(regexp_replace(role, '[^\\<\[]', '', 'g')) AS nr FROM o)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY k)) AS turns_sha256,
       CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY k) FILTER (role = 'assistant'), '')) AS loss_sha256,
       CAST(sum(n + CASE WHEN NOT opens THEN 5 WHEN role = 'user' THEN 13 WHEN role = 'assistant' THEN 7 ELSE 19 + nr END) AS BIGINT) AS formatted_chars
FROM c GROUP BY conv_id
"""


def op7_prob_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(table(spark, sf_dir, "documents"))


#: Exact: rows with equal words are one node; pairs that share one of their rarest shingles (as many as a pair at 0.8
#: must share one of) are counted in full; then the closure of the links.
OP7_SQL = r"""
WITH RECURSIVE d AS (SELECT row_number() OVER () AS r, doc_id, text, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') AS w FROM documents),
k AS (SELECT *, CASE WHEN text IS NULL THEN 'n' || r WHEN len(w) = 0 THEN 't' || text ELSE 'w' || array_to_string(w, ' ') END AS key FROM d),
node AS (SELECT key, min(r) AS n, any_value(w) AS w FROM k GROUP BY key),
sh AS (SELECT DISTINCT n, array_to_string(w[i : i + 4], ' ') AS s FROM (SELECT n, w, unnest(range(1, greatest(len(w) - 3, 2))) AS i FROM node WHERE len(w) > 0)),
rare AS (SELECT s, count(*) AS c FROM sh GROUP BY s HAVING count(*) > 1),
placed AS (SELECT n, s, c, row_number() OVER (PARTITION BY n ORDER BY coalesce(c, 1), s) AS pos, count(*) OVER (PARTITION BY n) AS size FROM sh LEFT JOIN rare USING (s)),
lead_ AS (SELECT n, s, size FROM placed WHERE c > 1 AND pos <= size - (4 * size + 4) // 5 + 1),
cand AS (SELECT DISTINCT a.n AS a, b.n AS b, a.size AS x, b.size AS y FROM lead_ a JOIN lead_ b ON a.s = b.s AND a.n < b.n WHERE 5 * least(a.size, b.size) >= 4 * greatest(a.size, b.size)),
link AS (SELECT a, b FROM cand JOIN sh p ON p.n = a JOIN sh q ON q.n = b AND q.s = p.s GROUP BY a, b, x, y HAVING 5 * count(*) >= 4 * (x + y - count(*))),
edge AS (SELECT a, b FROM link UNION ALL SELECT b, a FROM link),
reach(n, m) AS (SELECT a, a FROM edge UNION SELECT reach.n, edge.b FROM reach JOIN edge ON edge.a = reach.m),
class AS (SELECT node.key, coalesce(min(m), any_value(node.n)) AS c FROM node LEFT JOIN reach ON reach.n = node.n GROUP BY node.key)
SELECT doc_id, min(doc_id) OVER (PARTITION BY c) AS class_id FROM k JOIN class USING (key)
"""


def op8_lookup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.place(table(spark, sf_dir, "documents").select("doc_id"), "doc_id")


def _op8_sql() -> str:
    owners = ", ".join(map(str, sharding.lookup_table()))
    key = f"left(md5(coalesce(CAST(doc_id AS VARCHAR), '')), {sharding.DIGITS})"
    return f"""
WITH owners AS (SELECT [{owners}] AS o), keyed AS (SELECT doc_id, CAST('0x' || {key} AS BIGINT) % {sharding.SLOTS} AS slot FROM documents)
SELECT doc_id, slot, 'shard-' || lpad(CAST(o[slot + 1] AS VARCHAR), 3, '0') AS shard FROM keyed, owners
"""


def op9_suffix_arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.find(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"), decontaminate.is_contaminated().alias("contaminated"), "longest_match", "longest_at")


OP9_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT row_number() OVER () AS br, item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(13, len(w)) AS n, array_to_string(w[i : i + least(13, len(w)) - 1], ' ') AS win
       FROM (SELECT *, unnest(range(1, len(w) - least(13, len(w)) + 2)) AS i FROM b WHERE len(w) > 0)),
ns AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT r, i, n, array_to_string(w[i : i + n - 1], ' ') AS win FROM (SELECT r, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, ns WHERE len(w) >= n)),
m AS (SELECT dw.r, dw.i, dw.n, bw.item_id FROM dw JOIN bw ON dw.n = bw.n AND dw.win = bw.win),
h AS (SELECT r, count(DISTINCT p) AS n_hit FROM (SELECT r, unnest(range(i, i + n)) AS p FROM (SELECT DISTINCT r, i, n FROM m)) GROUP BY r),
bo AS (SELECT br, least(13, len(w)) AS n, i AS o, array_to_string(w[i : i + least(13, len(w)) - 1], ' ') AS win
       FROM (SELECT *, unnest(range(1, len(w) - least(13, len(w)) + 2)) AS i FROM b WHERE len(w) > 0)),
lm AS (SELECT dw.r, bo.br, dw.n, dw.i, dw.i - bo.o AS diagonal FROM dw JOIN bo ON dw.n = bo.n AND dw.win = bo.win),
runs AS (SELECT r, min(i) - 1 AS spot, count(*) + any_value(n) - 1 AS reach FROM (SELECT *, i - row_number() OVER (PARTITION BY r, br, diagonal ORDER BY i) AS g FROM lm) GROUP BY r, br, diagonal, g),
l AS (SELECT r, max(reach) AS longest_match, min(spot) FILTER (WHERE reach = top) AS longest_at FROM (SELECT *, max(reach) OVER (PARTITION BY r) AS top FROM runs) GROUP BY r),
k AS (SELECT r, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS ids FROM (SELECT DISTINCT r, coalesce(CAST(item_id AS VARCHAR), 'null') AS s FROM m) GROUP BY r)
SELECT doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated,
       coalesce(longest_match, 0) AS longest_match, longest_at
FROM d LEFT JOIN h USING (r) LEFT JOIN k USING (r) LEFT JOIN l USING (r)
"""


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    bundles = warc.archive(table(spark, sf_dir, "pages"))
    return warc.read_records(bundles, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP10_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html, octet_length(encode(coalesce(html, ''))) AS n FROM pages),
d AS (SELECT *, sha1(html) AS digest, max(page_id) OVER (PARTITION BY html) AS owner FROM p)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, digest AS payload_digest,
       CASE WHEN n >= 1000 AND owner IS DISTINCT FROM page_id AND owner IS NOT NULL THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 1000 AND owner IS DISTINCT FROM page_id THEN owner END AS refers_to
FROM d
"""

QUERIES = {
    "op1_length_histogram": op1_length_histogram,
    "op2_mixture": op2_mixture,
    "op3_flac": op3_flac,
    "op4_first_fit": op4_first_fit,
    "op5_boosted_trees": op5_boosted_trees,
    "op6_chat": op6_chat,
    "op7_prob_minhash": op7_prob_minhash,
    "op8_lookup": op8_lookup,
    "op9_suffix_arrays": op9_suffix_arrays,
    "op10_warc": op10_warc,
}


def oracle_sql() -> dict[str, str]:
    return {"op6_chat": OP6_SQL, "op7_prob_minhash": OP7_SQL, "op8_lookup": _op8_sql(), "op9_suffix_arrays": OP9_SQL, "op10_warc": OP10_SQL}
