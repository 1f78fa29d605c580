"""Queries of the operators around the methods, with their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from ..config import IndexConfig
from ..functions import analyze, schedule
from ..operators import pool, postings as P, relops
from ..runtime import materialise
from ..sources.io import read_table
from . import workloads as W
from .catalog import CFG, KEPT_SQL, docs, index, posting_digest, query
from .oracle import WORDS, twin

HOUR = 3_600_000_000


def table(spark, sf_dir, name) -> DataFrame:
    return read_table(spark, sf_dir, name)


def events(spark, sf_dir):
    return table(spark, sf_dir, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))


@query("scan_parquet", "SELECT doc_id, lang, n_chars FROM documents WHERE lang = 'en' AND n_chars > 500")
def scan_parquet(spark, sf_dir):
    return docs(spark, sf_dir).where("lang = 'en' AND n_chars > 500").select("doc_id", "lang", "n_chars")


@query("project_filter", "SELECT doc_id, n_chars * 2 AS twice, source LIKE 'src1%' AS in_1, text IS NULL AS no_text FROM documents WHERE lang IN ('en', 'fr') AND n_chars BETWEEN 100 AND 5000 AND source LIKE 'src%'")
def project_filter(spark, sf_dir):
    d = docs(spark, sf_dir).where(F.col("lang").isin("en", "fr") & F.col("n_chars").between(100, 5000) & F.col("source").like("src%"))
    return d.select("doc_id", (F.col("n_chars") * 2).alias("twice"), F.col("source").like("src1%").alias("in_1"), F.col("text").isNull().alias("no_text"))


@query("lang_filter_search", twin("SELECT query_id, doc_id FROM and_e JOIN documents USING (doc_id) JOIN labels USING (doc_id) WHERE lang = 'en' AND quality = 1"))
def lang_filter_search(spark, sf_dir):
    from ..operators import retrieval as R
    from .catalog import svs_set_e

    return R.filtered(svs_set_e(spark, sf_dir), docs(spark, sf_dir).where("lang = 'en'"), table(spark, sf_dir, "labels").where("quality = 1"))


@query("join_hash", twin("SELECT term_id, doc_id, tf FROM kept JOIN dict USING (term)"))
def join_hash(spark, sf_dir):
    d = index(spark, sf_dir).dictionary.select("term", "term_id")
    return P.build_postings(docs(spark, sf_dir)).join(d.hint("shuffle_hash"), "term").select("term_id", "doc_id", F.col("tf").cast("long").alias("tf"))


@query("join_broadcast", twin("SELECT query_id, term, term_id, df FROM qe JOIN dict USING (term)"))
def join_broadcast(spark, sf_dir):
    from ..operators import retrieval as R

    out, d = None, index(spark, sf_dir).dictionary
    for part in R.query_batches(W.query_set(spark, sf_dir, "E")):
        q = R.query_terms(part).select("query_id", "term")
        one = d.join(F.broadcast(q), "term").select("query_id", "term", "term_id", "df")
        out = one if out is None else out.unionByName(one)
    return out


@query("join_merge", twin("SELECT term, doc_id, CAST(len(w) AS BIGINT) AS doc_len FROM post JOIN docw USING (doc_id)"))
def join_merge(spark, sf_dir):
    d = docs(spark, sf_dir)
    return P.build_postings(d).select("term", "doc_id").join(P.doc_stats(d).hint("merge"), "doc_id").select("term", "doc_id", "doc_len")


@query("join_nested_loop", twin("SELECT a.term AS a, b.term AS b FROM often a JOIN often b ON a.df >= 2 * b.df AND a.df <= 3 * b.df", often="SELECT * FROM dict WHERE 5 * df >= (SELECT count(*) FROM documents)"))
def join_nested_loop(spark, sf_dir):
    """Terms in a fifth of the documents or more are at most five times the words of a mean document, however many
    documents and terms there are; one side is broadcast."""
    ix = index(spark, sf_dir)
    d = ix.dictionary.join(F.broadcast(ix.coll.select("n_docs"))).where("5 * df >= n_docs").select("term", "df")
    a, b = d.select(F.col("term").alias("a"), F.col("df").alias("x")), d.select(F.col("term").alias("b"), F.col("df").alias("y"))
    return a.join(b, (F.col("x") >= 2 * F.col("y")) & (F.col("x") <= 3 * F.col("y"))).select("a", "b")


@query("join_range", twin("SELECT l.doc_id, s.term, s.seg_no FROM (SELECT doc_id FROM labels WHERE toxic = 1) l JOIN (SELECT term, seg_no, min(doc_id) AS a, max(doc_id) AS z FROM rseg WHERE df >= 100 GROUP BY term, seg_no) s ON l.doc_id BETWEEN a AND z"))
def join_range(spark, sf_dir):
    ix = index(spark, sf_dir)
    segs = ix.blocks.join(ix.dictionary.where("df >= 100").select("term"), "term", "left_semi").select("term", "seg_no", "first_doc", "last_doc")
    return relops.range_join(table(spark, sf_dir, "labels").where("toxic = 1").select("doc_id"), segs, "doc_id", "first_doc", "last_doc", 256).select("doc_id", "term", "seg_no")


@query("join_interval", f"SELECT a.event_id, count(b.event_id) AS before FROM events a JOIN events b ON epoch_us(b.ts) < epoch_us(a.ts) AND epoch_us(b.ts) >= epoch_us(a.ts) - {HOUR} GROUP BY a.event_id")
def join_interval(spark, sf_dir):
    e = events(spark, sf_dir)
    a, b = e.select("event_id", F.col("us").alias("at")), e.select(F.col("event_id").alias("other"), F.col("us").alias("then"))
    return relops.interval_join(b, a, "then", "at", HOUR).groupBy("event_id").agg(F.count(F.lit(1)).alias("before"))


@query("join_semi", twin("SELECT term, doc_id FROM kept"))
def join_semi(spark, sf_dir):
    return P.build_postings(docs(spark, sf_dir)).select("term", "doc_id").join(index(spark, sf_dir).dictionary, "term", "left_semi")


@query("join_anti", twin("SELECT term, doc_id FROM post WHERE term NOT IN (SELECT term FROM dict)"))
def join_anti(spark, sf_dir):
    return P.build_postings(docs(spark, sf_dir)).select("term", "doc_id").join(index(spark, sf_dir).dictionary, "term", "left_anti")


@query("join_outer", twin("SELECT coalesce(a.term, b.term) AS term, coalesce(a.df, 0) AS in_docs, coalesce(b.n, 0) AS in_queries FROM dict a FULL OUTER JOIN (SELECT term, count(*) AS n FROM bt GROUP BY term) b ON a.term = b.term"))
def join_outer(spark, sf_dir):
    q = table(spark, sf_dir, "benchmark").select(F.explode(F.array_distinct(analyze.words(F.col("text")))).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("n"))
    return index(spark, sf_dir).dictionary.select("term", "df").join(q, "term", "full_outer").select("term", F.coalesce("df", F.lit(0)).alias("in_docs"), F.coalesce("n", F.lit(0)).alias("in_queries"))


@query("agg_hash", twin("SELECT term, df, cf FROM dict1"))
def agg_hash(spark, sf_dir):
    return P.build_postings(docs(spark, sf_dir)).groupBy("term").agg(F.count(F.lit(1)).alias("df"), F.sum("tf").alias("cf"))


@query("agg_sort", twin("SELECT term, doc_id, string_agg(CAST(pos AS VARCHAR), ' ' ORDER BY pos) AS places FROM tok GROUP BY term, doc_id"))
def agg_sort(spark, sf_dir):
    t = P.tokenize(docs(spark, sf_dir)).groupBy("term", "doc_id").agg(F.sort_array(F.collect_list("pos")).alias("p"))
    return t.select("term", "doc_id", F.array_join(F.transform("p", lambda x: x.cast("string")), " ").alias("places"))


@query("agg_distinct", twin("SELECT source, count(DISTINCT term) AS terms FROM post JOIN documents USING (doc_id) GROUP BY source"))
def agg_distinct(spark, sf_dir):
    return source_terms(spark, sf_dir).groupBy("source").agg(F.count_distinct("term").alias("terms"))


def source_terms(spark, sf_dir):
    d = docs(spark, sf_dir).select("source", F.explode(F.array_distinct(analyze.words(F.col("text")))).alias("term"))
    return d


@query("agg_approx")
def agg_approx(spark, sf_dir):
    return source_terms(spark, sf_dir).groupBy("source").agg(F.approx_count_distinct("term", 0.02).alias("terms"))


def by_source(spark, sf_dir):
    d = docs(spark, sf_dir).select("lang", "source", analyze.words(F.col("text")).alias("w"))
    return d.select("lang", "source", F.size(F.array_distinct("w")).cast("long").alias("p"), F.size("w").cast("long").alias("t"))


def summed(grouped):
    return grouped.agg(F.sum("p").alias("postings"), F.sum("t").alias("tokens"))


def _groups_sql(how):
    return twin(f"SELECT lang, source, CAST(sum(len(list_distinct(w))) AS BIGINT) AS postings, CAST(sum(len(w)) AS BIGINT) AS tokens FROM docw JOIN documents USING (doc_id) GROUP BY {how}")


@query("grouping_sets", _groups_sql("GROUPING SETS ((lang), (source), ())"))
def grouping_sets(spark, sf_dir):
    return summed(by_source(spark, sf_dir).groupingSets([[F.col("lang")], [F.col("source")], []], "lang", "source")).select("lang", "source", "postings", "tokens")


@query("cube", _groups_sql("CUBE (lang, source)"))
def cube(spark, sf_dir):
    return summed(by_source(spark, sf_dir).cube("lang", "source"))


@query("rollup", _groups_sql("ROLLUP (lang, source)"))
def rollup(spark, sf_dir):
    return summed(by_source(spark, sf_dir).rollup("lang", "source"))


@query("agg_stats", "SELECT event_type, count(*) AS n, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS sd, round(quantile_cont(value, 0.5), 6) AS median, round(1.96 * stddev_samp(value) / sqrt(count(*)), 6) AS half FROM events GROUP BY event_type")
def agg_stats(spark, sf_dir):
    sd = F.stddev_samp("value")
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 6).alias("mean"), F.round(sd, 6).alias("sd"), F.round(F.percentile("value", F.lit(0.5)), 6).alias("median"), F.round(1.96 * sd / F.sqrt(F.count(F.lit(1))), 6).alias("half"))


@query("histogram_pivot", twin("SELECT lang, " + ", ".join(f"count(*) FILTER (c = {1 << m}) AS c{1 << m}" for m in range(8)) + " FROM (SELECT lang, CAST(pow(2, least(7, length(bin(n // {b} + 1)) - 1)) AS BIGINT) AS c FROM (SELECT lang, term, count(*) AS n FROM post JOIN documents USING (doc_id) GROUP BY lang, term)) GROUP BY lang"))
def histogram_pivot(spark, sf_dir):
    d = docs(spark, sf_dir).select("lang", F.explode(F.array_distinct(analyze.words(F.col("text")))).alias("term")).groupBy("lang", "term").agg(F.count(F.lit(1)).alias("n"))
    classes = [1 << m for m in range(8)]
    rows = d.select("lang", schedule.buffer_class(F.col("n"), CFG.block).alias("c"))
    out = rows.groupBy("lang").pivot("c", classes).agg(F.count(F.lit(1)))
    return out.select("lang", *(F.coalesce(F.col(f"`{c}`"), F.lit(0)).alias(f"c{c}") for c in classes))


@query("win_rank", twin("SELECT lang, term, n, rk, dr, rn, nt, round(pr, 6) AS pr FROM (SELECT lang, term, n, rank() OVER w AS rk, dense_rank() OVER w AS dr, row_number() OVER v AS rn, ntile(4) OVER v AS nt, percent_rank() OVER w AS pr FROM (SELECT lang, term, count(*) AS n FROM post JOIN documents USING (doc_id) GROUP BY lang, term) WINDOW w AS (PARTITION BY lang ORDER BY n DESC), v AS (PARTITION BY lang ORDER BY n DESC, term))"))
def win_rank(spark, sf_dir):
    d = docs(spark, sf_dir).select("lang", F.explode(F.array_distinct(analyze.words(F.col("text")))).alias("term")).groupBy("lang", "term").agg(F.count(F.lit(1)).alias("n"))
    w, v = Window.partitionBy("lang").orderBy(F.desc("n")), Window.partitionBy("lang").orderBy(F.desc("n"), "term")
    return d.select("lang", "term", "n", F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.row_number().over(v).cast("long").alias("rn"), F.ntile(4).over(v).cast("long").alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("win_analytic", "SELECT event_id, user_id, lag(value) OVER w AS prev, lead(value) OVER w AS next, first_value(value) OVER w AS first, last_value(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_analytic(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf_dir, "events").select("event_id", "user_id", F.lag("value").over(w).alias("prev"), F.lead("value").over(w).alias("next"), F.first("value").over(w).alias("first"), F.last("value").over(whole).alias("last"))


@query("win_frame", f"SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 6) AS running, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS moving, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN {24 * HOUR} PRECEDING AND CURRENT ROW) AS day FROM events")
def win_frame(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    day = Window.partitionBy("user_id").orderBy("us").rangeBetween(-24 * HOUR, 0)
    return events(spark, sf_dir).select("event_id", F.round(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 6).alias("running"), F.round(F.avg("value").over(w.rowsBetween(-2, 0)), 6).alias("moving"), F.count(F.lit(1)).over(day).alias("day"))


@query("sort_limit", twin("SELECT term, df FROM dict1 ORDER BY df DESC, term LIMIT 20 OFFSET 5"))
def sort_limit(spark, sf_dir):
    d = P.build_postings(docs(spark, sf_dir)).groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    return d.orderBy(F.desc("df"), "term").offset(5).limit(20)


@query("topk_per_group", twin("SELECT lang, term, n FROM (SELECT lang, term, count(*) AS n, row_number() OVER (PARTITION BY lang ORDER BY count(*) DESC, term) AS k FROM post JOIN documents USING (doc_id) GROUP BY lang, term) WHERE k <= 5"))
def topk_per_group(spark, sf_dir):
    d = docs(spark, sf_dir).select("lang", F.explode(F.array_distinct(analyze.words(F.col("text")))).alias("term")).groupBy("lang", "term").agg(F.count(F.lit(1)).alias("n"))
    return d.withColumn("k", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "term"))).where("k <= 5").select("lang", "term", "n")


@query("set_ops", "WITH a AS (SELECT doc_id FROM documents WHERE lang = 'en'), b AS (SELECT doc_id FROM labels WHERE quality = 1) SELECT 'all' AS op, doc_id FROM a UNION ALL SELECT 'all', doc_id FROM b UNION ALL SELECT 'union', doc_id FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'intersect', doc_id FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'except', doc_id FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b)")
def set_ops(spark, sf_dir):
    a, b = docs(spark, sf_dir).where("lang = 'en'").select("doc_id"), table(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    parts = {"all": a.unionByName(b), "union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.exceptAll(b)}
    out = None
    for op, df in parts.items():
        one = df.select(F.lit(op).alias("op"), "doc_id")
        out = one if out is None else out.unionByName(one)
    return out


@query("fn_string", "SELECT item_id, lower(text) AS low, length(text) AS n, substring(text, 3, 7) AS mid, replace(text, 'the', '_') AS rep, translate(text, 'abc', 'xyz') AS tr, len(string_split(text, ' ')) AS parts, regexp_replace(text, '[aeiou]', '', 'g') AS bare, concat(left(text, 3), '-', right(text, 2)) AS ends FROM benchmark")
def fn_string(spark, sf_dir):
    t = F.col("text")
    return table(spark, sf_dir, "benchmark").select("item_id", F.lower(t).alias("low"), F.length(t).cast("long").alias("n"), F.substring(t, 3, 7).alias("mid"), F.replace(t, F.lit("the"), F.lit("_")).alias("rep"), F.translate(t, "abc", "xyz").alias("tr"), F.size(F.split(t, " ")).cast("long").alias("parts"), F.regexp_replace(t, "[aeiou]", "").alias("bare"), F.concat(F.left(t, F.lit(3)), F.lit("-"), F.right(t, F.lit(2))).alias("ends"))


@query("stem_stop", twin("SELECT count(*) AS tokens, count(DISTINCT term) AS words FROM tok WHERE term NOT IN (SELECT term FROM (SELECT term, row_number() OVER (ORDER BY df DESC, term) AS r FROM dict1) WHERE r <= 50)"))
def stem_stop(spark, sf_dir):
    """The 50 terms of the most documents are stop words; what is left is counted."""
    tokens = P.tokenize(docs(spark, sf_dir))
    stops = P.build_postings(docs(spark, sf_dir)).groupBy("term").agg(F.count(F.lit(1)).alias("df")).orderBy(F.desc("df"), "term").limit(50)
    return tokens.join(F.broadcast(stops), "term", "left_anti").agg(F.count(F.lit(1)).alias("tokens"), F.count_distinct("term").alias("words"))


@query("fn_date", "SELECT event_id, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS hour, extract(year FROM ts) AS y, extract(month FROM ts) AS m, extract(day FROM ts) AS d, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS days, epoch_us(ts) // 3600000000 AS bucket FROM events")
def fn_date(spark, sf_dir):
    ts = F.col("ts")
    return events(spark, sf_dir).select("event_id", F.date_format(F.date_trunc("hour", ts), "yyyy-MM-dd HH:mm:ss").alias("hour"), F.year(ts).cast("long").alias("y"), F.month(ts).cast("long").alias("m"), F.dayofmonth(ts).cast("long").alias("d"), F.datediff(F.to_date(ts), F.to_date(F.lit("2024-01-01"))).cast("long").alias("days"), F.floor(F.col("us") / F.lit(HOUR)).alias("bucket"))


@query("fn_math", "SELECT doc_id, length(bin(n_chars + 1)) - 1 AS log2, round(ln(n_chars + 1), 6) AS ln, CAST(floor(n_chars / 7.0) AS BIGINT) AS f, n_chars << 2 AS up, n_chars >> 2 AS down, ((n_chars - 1000) % 97 + 97) % 97 AS pm, round(sqrt(n_chars), 6) AS root FROM documents")
def fn_math(spark, sf_dir):
    n = F.col("n_chars")
    return docs(spark, sf_dir).select("doc_id", schedule.log2_floor(n + 1).alias("log2"), F.round(F.log(n + 1), 6).alias("ln"), F.floor(n / 7.0).alias("f"), F.shiftleft(n, 2).alias("up"), F.shiftright(n, 2).alias("down"), F.pmod(n - 1000, F.lit(97)).alias("pm"), F.round(F.sqrt(n), 6).alias("root"))


@query("fn_array", twin("SELECT term, doc_id, pos_sum, CAST(last_pos - first_pos AS BIGINT) AS span, tf FROM kept"))
def fn_array(spark, sf_dir):
    """Positions restored from their gaps, then folded."""
    rows = index(spark, sf_dir).postings
    back = F.get(analyze.restore_positions(analyze.position_gaps(F.col("positions")), F.array(F.col("tf"))), F.lit(0))
    rows = rows.select("term", "doc_id", "tf", back.alias("p"))
    return rows.select("term", "doc_id", F.aggregate("p", F.lit(0).cast("long"), lambda a, x: a + x).alias("pos_sum"), (F.array_max("p") - F.array_min("p")).cast("long").alias("span"), F.size(F.filter("p", lambda x: x > 0)).cast("long").alias("tf"))


@query("fn_map", twin("SELECT doc_id, term, tf * 2 AS twice FROM post"))
def fn_map(spark, sf_dir):
    d = docs(spark, sf_dir).select("doc_id", analyze.row_postings(analyze.words(F.col("text"))).alias("occ"))
    tf = F.map_from_entries(F.transform(analyze.cut(F.col("occ")), lambda p: F.struct(p["term"], p["tf"].cast("long"))))
    return d.select("doc_id", F.explode(F.transform_values(tf, lambda k, v: v * 2)).alias("term", "twice"))


@query("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, '{\"id\":' || event_id || '}' AS packed FROM events")
def fn_json(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"), F.to_json(F.struct(F.col("event_id").alias("id"))).alias("packed"))


@query("subqueries", "SELECT doc_id, n_chars FROM documents d WHERE n_chars > (SELECT avg(n_chars) FROM documents) AND EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.quality = 1) AND n_chars > (SELECT avg(n_chars) FROM documents e WHERE e.source = d.source)")
def subqueries(spark, sf_dir):
    docs(spark, sf_dir).createOrReplaceTempView("pp_documents")
    table(spark, sf_dir, "labels").createOrReplaceTempView("pp_labels")
    return spark.sql("SELECT doc_id, n_chars FROM pp_documents d WHERE n_chars > (SELECT avg(n_chars) FROM pp_documents) AND EXISTS (SELECT 1 FROM pp_labels l WHERE l.doc_id = d.doc_id AND l.quality = 1) AND n_chars > (SELECT avg(n_chars) FROM pp_documents e WHERE e.source = d.source)")


@query("cte_recursive", twin("SELECT term, count(*) AS hops FROM segb GROUP BY term"))
def cte_recursive(spark, sf_dir):
    """All lists walked from head to blank by their pointers. A round of the recursion takes a stretch of a list: inside
    a stretch the pointers are followed from segment to segment as far as they name the next one's address."""
    segs = index(spark, sf_dir).placed.select("term", "addr", "next_addr", "is_head", "seg_no")
    stretches(segs).createOrReplaceTempView("pp_stretches")
    return spark.sql("""
        WITH RECURSIVE walk(term, next_addr, hops) MAX RECURSION LEVEL 100000 AS (
          SELECT term, next_addr, hops FROM pp_stretches WHERE is_head
          UNION ALL SELECT s.term, s.next_addr, w.hops + s.hops FROM walk w JOIN pp_stretches s ON s.addr = w.next_addr AND s.term = w.term)
        SELECT term, max(hops) AS hops FROM walk GROUP BY term""")


def stretches(segments: DataFrame, wide: int = P.RANGE) -> DataFrame:
    """(term, addr, is_head, next_addr, hops): from the first of at most `wide` segments the pointers are followed as
    long as they stay in the stretch; next_addr is where they leave it (null: the list's end), after so many segments.
    A stretch whose pointers don't name the next segment breaks up: each piece is entered at its own address. Written
    once, as every round of a recursion reads it."""
    w = Window.partitionBy("term", "part").orderBy("seg_no")
    rows = segments.withColumn("part", schedule.div(F.col("seg_no"), wide))
    rows = rows.withColumn("enters", F.coalesce((F.lag("next_addr").over(w) != F.col("addr")).cast("long"), F.lit(1)))
    rows = rows.withColumn("piece", F.sum("enters").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    out = rows.groupBy("term", "part", "piece").agg(F.min_by("addr", "seg_no").alias("addr"), F.max("is_head").alias("is_head"), F.max_by("next_addr", "seg_no").alias("next_addr"), F.count(F.lit(1)).alias("hops"))
    return materialise(out.select("term", "addr", "is_head", "next_addr", "hops"), "stretches")


def _stream(spark, sf_dir):
    path = f"{sf_dir.rstrip('/')}/events.parquet"
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(path if spark.read.parquet(path).inputFiles()[0].rstrip("/").rpartition("/")[2] != name else f"{folder}/{name[:-8]}*.parquet")


def run_stream(df, tag, mode="append"):
    """Run a streaming frame to its end into the shared folder and read the result."""
    from ..runtime import scratch_path

    spark = df.sparkSession
    out, state = scratch_path(spark, tag), scratch_path(spark, f"{tag}-state")
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start()
    else:
        q = df.writeStream.outputMode(mode).foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(out)).option("checkpointLocation", state).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


def _named(col):
    return F.date_format(col, "yyyy-MM-dd HH:mm:ss")


@query("stream_tumbling", "SELECT strftime(to_timestamp((epoch_us(ts) // 3600000000) * 3600), '%Y-%m-%d %H:%M:%S') AS hour, count(*) AS n, round(sum(value), 6) AS total FROM events GROUP BY 1")
def stream_tumbling(spark, sf_dir):
    e = _stream(spark, sf_dir).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
    out = e.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    rows = run_stream(out, "tumbling", "complete")
    return rows.select(_named(F.col("w.start")).alias("hour"), "n", F.round("total", 6).alias("total"))


@query("stream_sliding", "SELECT strftime(to_timestamp(s * 1800), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT unnest([epoch_us(ts) // 1800000000 - 1, epoch_us(ts) // 1800000000]) AS s FROM events) GROUP BY s")
def stream_sliding(spark, sf_dir):
    e = _stream(spark, sf_dir).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
    out = e.groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return run_stream(out, "sliding", "complete").select(_named(F.col("w.start")).alias("start"), "n")


@query("stream_session", "SELECT user_id, CAST(n AS BIGINT) AS n, strftime(a, '%Y-%m-%d %H:%M:%S') AS start FROM (SELECT user_id, s, count(*) AS n, min(ts) AS a FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL OR epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) > 14400000000 THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, s)")
def stream_session(spark, sf_dir):
    """Sessions of a user with gaps of at most four hours; those still open when the source ends are in the result."""
    e = _stream(spark, sf_dir).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
    out = e.groupBy("user_id", F.session_window("ts", "4 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return run_stream(out, "session", "complete").select("user_id", "n", _named(F.col("w.start")).alias("start"))


@query("udf_scalar", twin("SELECT term, doc_id, CAST(sum(greatest(1, (CASE WHEN gap > 0 THEN length(bin(gap)) ELSE 0 END + 6) // 7)) AS BIGINT) AS n FROM gaps GROUP BY term, doc_id"))
def udf_scalar(spark, sf_dir):
    from ..functions import udfs

    return index(spark, sf_dir).postings.select("term", "doc_id", udfs.vbyte_length(analyze.position_gaps(F.col("positions"))).alias("n"))


@query("udaf", twin("SELECT term, seg_no, CAST(n_bytes AS BIGINT) AS n FROM shape WHERE part = 'F'"))
def udaf(spark, sf_dir):
    from ..functions import udfs

    rows = pool.with_groups(index(spark, sf_dir).postings, CFG)
    return rows.groupBy("term", "seg_no").agg(F.collect_list("tf").alias("tfs")).select("term", "seg_no", udfs.sizes_of_blocks("tfs").alias("n"))


@query("udtf_decode", twin("SELECT term, doc_id, tf FROM kept"))
def udtf_decode(spark, sf_dir):
    from ..functions import udfs

    spark.udtf.register("pp_decode", udfs.DecodeSegment)
    index(spark, sf_dir).segments.select("term", "d_block", "f_block").createOrReplaceTempView("pp_blocks")
    return spark.sql("SELECT b.term, d.doc_id, d.tf FROM pp_blocks b, LATERAL pp_decode(b.d_block, b.f_block) d")


@query("sql_surface", twin("SELECT query_id, term, df FROM qe JOIN dict USING (term) WHERE df > 20"))
def sql_surface(spark, sf_dir):
    index(spark, sf_dir).dictionary.createOrReplaceTempView("pp_dictionary")
    W.query_set(spark, sf_dir, "E").createOrReplaceTempView("pp_queries")
    return spark.sql("SELECT q.query_id, d.term, d.df FROM (SELECT query_id, explode(terms) AS term FROM pp_queries) q JOIN pp_dictionary d USING (term) WHERE d.df > 20")


@query("sample", "SELECT conv_id * 1000 + turn AS query_id FROM conversations WHERE role = 'user' AND (conv_id * 7919 + turn * 104729) % 10 = 3")
def sample(spark, sf_dir):
    """A reproducible tenth of the query log: sampling is what this operator does."""
    c = table(spark, sf_dir, "conversations").where("role = 'user'")
    return c.where((F.col("conv_id") * 7919 + F.col("turn") * 104729) % 10 == 3).select((F.col("conv_id") * 1000 + F.col("turn")).alias("query_id"))


STREAM = IndexConfig(block=16, cap_log2=5, df_threshold=10)


def streamed(spark, sf_dir):
    """Folders of the documents replayed as a stream, once a session."""
    from ..runtime import scratch_path
    from ..streaming import stream

    def make():
        base = scratch_path(spark, "stream")
        stream.split_for_stream(read_table(spark, sf_dir, "documents").select("doc_id", "text"), f"{base}/in", 4)
        source = spark.readStream.schema("doc_id long, text string").option("maxFilesPerTrigger", 1).parquet(f"{base}/in")
        stream.run(source, STREAM, f"{base}/out", f"{base}/state", buffer_codec="vbyte")
        return base

    base = W.once(spark, ("stream", sf_dir), make)
    return f"{base}/out", f"{base}/state"


@query("stream_index", twin("SELECT p.term, p.term_id, p.seg_no, p.group_no, p.n_bytes, p.addr, g.n AS n_docs FROM pooled p JOIN (SELECT term, seg_no, count(*) AS n FROM rseg GROUP BY term, seg_no) g USING (term, seg_no)"))
def stream_index(spark, sf_dir):
    """Documents replayed as a stream: groups as buffers filled, the final flush from state, addresses in flush order."""
    from ..streaming import stream

    _, segments = stream.finish(spark, *streamed(spark, sf_dir), STREAM, "vbyte")
    return segments.select("term", "term_id", "seg_no", "group_no", "n_bytes", "addr", F.col("n_docs").cast("long").alias("n_docs"))


@query("stream_lists", KEPT_SQL)
def stream_lists(spark, sf_dir):
    """The stream's lists by their pointers."""
    from ..streaming import stream

    return posting_digest(pool.traverse(stream.finish(spark, *streamed(spark, sf_dir), STREAM, "vbyte")[1]))


@query("stream_answers", twin("SELECT query_id, doc_id FROM and_e"))
def stream_answers(spark, sf_dir):
    """Conjunctive answers from flushed segments and live buffers, before any final flush."""
    from ..streaming import stream

    return stream.answers(spark, *streamed(spark, sf_dir), STREAM, W.query_set(spark, sf_dir, "E"), "vbyte")
