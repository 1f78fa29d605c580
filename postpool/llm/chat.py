"""Chat formatting by relational expressions: collect and sort turns, merge neighbours of one role, concatenate.

Template. A block holds neighbouring turns of one role, with [SEP] between their texts:
user ``[INST]..[/INST]``, assistant ``<s>..</s>``, any other role ``[ROLE]role[BODY]..[/ROLE]``. In texts and roles
``\\`` becomes ``\\\\``, ``[`` becomes ``\\b`` and ``<`` becomes ``\\l``: no control string can occur inside, and the
escapes are read back exactly.

Edge cases: a null text or role is empty; turns go by turn (null first), then role, then text, and repeated rows are
kept; a null conv_id is one conversation of its own; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from .common import pick

USER, ASSISTANT, OTHER = ("[INST]", "[/INST]"), ("<s>", "</s>"), ("[ROLE]", "[/ROLE]")
BODY, SEP = "[BODY]", "[SEP]"


def escape(text: Column) -> Column:
    return F.replace(F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("["), F.lit("\\b")), F.lit("<"), F.lit("\\l"))


def unescape(text: Column) -> Column:
    """Pairs of backslashes are found from the left, so each escape is read at its own start."""
    parts = F.split(text, r"\\\\", -1)
    return F.array_join(F.transform(parts, lambda p: F.replace(F.replace(p, F.lit("\\b"), F.lit("[")), F.lit("\\l"), F.lit("<"))), "\\")


def collect_turns(rows: DataFrame) -> DataFrame:
    """(conv_id, turns): sorted structs (turn, role, text). Partial lists are built before the shuffle."""
    rows = pick(rows, conv_id="long", turn="long", role="string", text="string")
    one = F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.groupBy("conv_id").agg(F.sort_array(F.collect_list(one)).alias("turns"))


def format_chats(rows: DataFrame) -> DataFrame:
    """(conv_id, formatted, loss_spans): spans are (start, length) in code points, from 0, of escaped assistant texts."""
    df = collect_turns(rows)
    last = F.size("turns")
    starts = F.filter(F.sequence(F.lit(0), last - 1), lambda i: (i == 0) | (F.get("turns", i)["role"] != F.get("turns", i - 1)["role"]))
    df = df.withColumn("starts", starts)
    ends = F.transform("starts", lambda s, i: F.coalesce(F.get("starts", i + 1), last))
    df = df.withColumn("blocks", F.zip_with("starts", ends, lambda s, e: F.struct(F.get("turns", s)["role"].alias("role"), F.transform(F.slice("turns", s + 1, e - s), lambda t: escape(t["text"])).alias("texts"))))

    def pieces(b: Column) -> Column:
        """The block as (text, is_loss) pieces."""
        is_a = b["role"] == "assistant"
        head = F.when(is_a, F.lit(ASSISTANT[0])).when(b["role"] == "user", F.lit(USER[0])).otherwise(F.concat(F.lit(OTHER[0]), escape(b["role"]), F.lit(BODY)))
        tail = F.when(is_a, F.lit(ASSISTANT[1])).when(b["role"] == "user", F.lit(USER[1])).otherwise(F.lit(OTHER[1]))
        body = F.flatten(F.transform(b["texts"], lambda t, i: F.array(F.struct(F.when(i == 0, F.lit("")).otherwise(F.lit(SEP)).alias("text"), F.lit(False).alias("loss")), F.struct(t.alias("text"), is_a.alias("loss")))))
        return F.concat(F.array(F.struct(head.alias("text"), F.lit(False).alias("loss"))), body, F.array(F.struct(tail.alias("text"), F.lit(False).alias("loss"))))

    df = df.withColumn("pieces", F.flatten(F.transform("blocks", pieces)))
    none = F.array().cast("array<struct<start:long,length:long>>")
    walked = F.aggregate(
        "pieces", F.struct(F.lit(0).cast("long").alias("at"), none.alias("spans")),
        lambda acc, p: F.struct((acc["at"] + F.length(p["text"])).alias("at"), F.when(p["loss"], F.concat(acc["spans"], F.array(F.struct(acc["at"].alias("start"), F.length(p["text"]).cast("long").alias("length"))))).otherwise(acc["spans"]).alias("spans")),
        lambda acc: acc["spans"],
    )
    return df.select("conv_id", F.array_join(F.transform("pieces", lambda p: p["text"]), "").alias("formatted"), walked.alias("loss_spans"))


def read_back(formatted: DataFrame) -> DataFrame:
    """(conv_id, turns, loss_texts, formatted, loss_spans): turns (role, text) parsed from the formatted string alone."""
    blocks = F.filter(F.split("formatted", r"\[/INST\]|</s>|\[/ROLE\]", -1), lambda b: b != "")

    def parse(b: Column) -> Column:
        named = F.split(b, r"\[BODY\]", 2)
        role = F.when(b.startswith(USER[0]), F.lit("user")).when(b.startswith(ASSISTANT[0]), F.lit("assistant")).otherwise(unescape(F.substring(named[0], len(OTHER[0]) + 1, 1 << 30)))
        body = F.when(b.startswith(USER[0]), F.substring(b, len(USER[0]) + 1, 1 << 30)).when(b.startswith(ASSISTANT[0]), F.substring(b, len(ASSISTANT[0]) + 1, 1 << 30)).otherwise(F.get(named, F.lit(1)))
        return F.transform(F.split(body, r"\[SEP\]", -1), lambda t: F.struct(role.alias("role"), unescape(t).alias("text")))

    turns = F.flatten(F.transform(blocks, parse))
    spans = F.transform("loss_spans", lambda s: unescape(F.col("formatted").substr((s["start"] + 1).cast("int"), s["length"].cast("int"))))
    return formatted.select("conv_id", turns.alias("turns"), spans.alias("loss_texts"), "formatted", "loss_spans")
