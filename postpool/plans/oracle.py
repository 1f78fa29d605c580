"""Common table expressions for the SQL twins, in DuckDB's dialect; `twin` adds those that a statement names.

They follow the definitions (loops over ranks become joins with a table of groups), not the closed forms of the engine.
"""

from __future__ import annotations

import re

WORDS = r"list_filter(string_split_regex(lower(coalesce({0}, '')), '[^\p{{L}}\p{{N}}]+'), lambda x: x <> '')"

CTES = {
    "docw": f"SELECT doc_id, {WORDS.format('text')} AS w FROM documents",
    "tok": "SELECT doc_id, unnest(w) AS term, unnest(range(1, len(w) + 1)) AS pos FROM docw",
    "post": "SELECT term, doc_id, count(*) AS tf, min(pos) AS first_pos, max(pos) AS last_pos, CAST(sum(pos) AS BIGINT) AS pos_sum FROM tok GROUP BY term, doc_id",
    "dict1": "SELECT term, count(*) AS df, CAST(sum(tf) AS BIGINT) AS cf, max(tf) AS max_tf, min(doc_id) AS first_doc, arg_min(first_pos, doc_id) AS first_pos FROM post GROUP BY term",
    "dict": "SELECT *, row_number() OVER (ORDER BY first_doc, first_pos) - 1 AS term_id FROM dict1 WHERE df >= {t}",
    "ranked": "SELECT p.*, d.term_id, d.df, d.cf, row_number() OVER (PARTITION BY p.term ORDER BY p.doc_id) AS rank FROM post p JOIN dict d USING (term)",
    "gsize": "SELECT g, CAST(pow(2, least(g, {cap})) AS BIGINT) AS n FROM range(0, 4000) r(g)",
    "gspan": "SELECT g, n, CAST(coalesce(sum(n) OVER (ORDER BY g ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS s0 FROM gsize",
    "rseg": "SELECT *, (rank - 1) // {b} AS seg_no, (rank - 1) % {b} AS slot FROM ranked",
    "rgrp": "SELECT r.*, s.g AS group_no, s.s0, s.n AS group_size FROM rseg r JOIN gspan s ON r.seg_no >= s.s0 AND r.seg_no < s.s0 + s.n",
    "events_": "SELECT term, term_id, group_no, doc_id AS trigger_doc, first_pos AS trigger_pos FROM rgrp WHERE rank = (s0 + group_size) * {b}",
    "gaps": "SELECT s.term, s.seg_no, s.doc_id, k.pos, k.pos - coalesce(lag(k.pos) OVER (PARTITION BY k.doc_id, k.term ORDER BY k.pos), 0) AS gap FROM tok k JOIN rseg s ON s.term = k.term AND s.doc_id = k.doc_id",
    "vals": """SELECT term, seg_no, 'D' AS part, 0 AS blk, doc_id - coalesce(lag(doc_id) OVER (PARTITION BY term, seg_no ORDER BY doc_id), 0) AS v FROM rseg
      UNION ALL SELECT term, seg_no, 'F', 0, tf FROM rseg
      UNION ALL SELECT term, seg_no, 'P', (row_number() OVER (PARTITION BY term, seg_no ORDER BY doc_id, pos) - 1) // {b}, gap FROM gaps""",
    "lens": "SELECT *, CASE WHEN v > 0 THEN length(bin(v)) ELSE 0 END AS bl FROM vals",
    "shape0": "SELECT term, seg_no, part, blk, count(*) AS n_values, list_reverse_sort(list(bl))[count(*) // 10 + 1] AS width, list(bl) AS all_bl FROM lens GROUP BY term, seg_no, part, blk",
    "shape1": "SELECT term, seg_no, part, blk, n_values, width, CAST(len(list_filter(all_bl, lambda x: x > width)) AS BIGINT) AS exceptions FROM shape0",
    "shape": "SELECT *, 4 + 4 * ((n_values * width + 31) // 32) + 4 * ((exceptions + 3) // 4) + 4 * exceptions AS n_bytes FROM shape1",
    "segb": "SELECT term, seg_no, CAST(8 + sum(4 + n_bytes) AS BIGINT) AS n_bytes FROM shape GROUP BY term, seg_no",
    "segg": "SELECT DISTINCT term, term_id, seg_no, group_no FROM rgrp",
    "pooled": """SELECT s.term, s.term_id, s.seg_no, s.group_no, b.n_bytes,
      CAST(coalesce(sum(b.n_bytes) OVER (ORDER BY (e.trigger_doc IS NULL), coalesce(e.trigger_doc, s.term_id), coalesce(e.trigger_pos, 0), s.seg_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS addr
      FROM segg s JOIN segb b USING (term, seg_no) LEFT JOIN events_ e ON e.term = s.term AND e.group_no = s.group_no""",
    "contig": "SELECT s.term, s.term_id, s.seg_no, b.n_bytes, CAST(coalesce(sum(b.n_bytes) OVER (ORDER BY s.term_id, s.seg_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS addr FROM segg s JOIN segb b USING (term, seg_no)",
    "bw": f"SELECT item_id, {WORDS.format('text')} AS w FROM benchmark",
    "bt": "SELECT item_id, term, min(pos) AS p FROM (SELECT item_id, unnest(w) AS term, unnest(range(1, len(w) + 1)) AS pos FROM bw) GROUP BY item_id, term",
    "qe": "SELECT query_id, term FROM (SELECT item_id AS query_id, term, row_number() OVER (PARTITION BY item_id ORDER BY p) AS k FROM bt) WHERE k <= 2 + query_id % 5",
    "cw": f"SELECT conv_id * 1000 + turn AS query_id, 1 + (conv_id * 31 + turn) % 6 AS take, {WORDS.format('text')} AS w FROM conversations WHERE role = 'user'",
    "ct": "SELECT query_id, take, term, min(pos) AS p FROM (SELECT query_id, take, unnest(w) AS term, unnest(range(1, len(w) + 1)) AS pos FROM cw) GROUP BY query_id, take, term",
    "qw": "SELECT query_id, term FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY p) AS k FROM ct) WHERE k <= take",
    "kept": "SELECT p.* FROM post p JOIN dict USING (term)",
    "need_e": "SELECT query_id, count(*) AS need FROM qe GROUP BY query_id",
    "need_w": "SELECT query_id, count(*) AS need FROM qw GROUP BY query_id",
    "and_e": "SELECT query_id, doc_id FROM qe JOIN kept USING (term) JOIN need_e USING (query_id) GROUP BY query_id, doc_id, need HAVING count(*) = need",
    "and_w": "SELECT query_id, doc_id FROM qw JOIN kept USING (term) JOIN need_w USING (query_id) GROUP BY query_id, doc_id, need HAVING count(*) = need",
    "coll": "SELECT count(*) AS n_docs, avg(len(w)) AS avg_len, CAST(sum(len(w)) AS BIGINT) AS sum_len FROM docw",
    "wts": "SELECT p.term, p.doc_id, d.df, ln(1 + (n_docs - d.df + 0.5) / (d.df + 0.5)) * p.tf * 1.9 / (p.tf + 0.9 * (1 - 0.4 + 0.4 * len(w) / avg_len)) AS wt FROM post p JOIN dict d USING (term) JOIN docw USING (doc_id), coll",
    "or_e": "SELECT query_id, doc_id, round(sum(wt), 6) AS score FROM qe JOIN wts USING (term) GROUP BY query_id, doc_id",
    "or_w": "SELECT query_id, doc_id, round(sum(wt), 6) AS score FROM qw JOIN wts USING (term) GROUP BY query_id, doc_id",
    "top_e": "SELECT * FROM (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id) AS rank, doc_id, score FROM or_e) WHERE rank <= {k}",
    "top_w": "SELECT * FROM (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id) AS rank, doc_id, score FROM or_w) WHERE rank <= {k}",
    "dcum": "SELECT doc_id, n, CAST(coalesce(sum(n) OVER (ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS before FROM (SELECT doc_id, count(*) AS n FROM post GROUP BY doc_id)",
    "total": "SELECT count(*) AS p FROM post",
}


def twin(body: str, b: int = 16, t: int = 10, cap: int = 5, k: int = 10, **more: str) -> str:
    """The statement with the CTEs it needs in front; `more` adds its own CTEs."""
    ctes = CTES | more
    need: list[str] = []

    def visit(text: str) -> None:
        for name in ctes:
            if name not in need and re.search(rf"\b{name}\b", text):
                visit(ctes[name])
                if name not in need:
                    need.append(name)

    visit(body)
    fill = lambda s: s.replace("{b}", str(b)).replace("{t}", str(t)).replace("{cap}", str(cap)).replace("{k}", str(k))
    head = ", ".join(f"{n} AS ({fill(ctes[n])})" for n in need)
    recursive = "RECURSIVE " if any("RECURSIVE_" in ctes[n] for n in need) else ""
    return f"WITH {recursive}{head} {fill(body)}".replace("/*RECURSIVE_*/", "") if need else fill(body)
