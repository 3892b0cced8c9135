"""Chat formatting by prefix-target expansion, in Spark expressions only.

Every assistant turn becomes an example of its own: all turns before it are
context, and only its reply is under the loss mask.  Turns after the last reply
form one more example without a trainable part, so that no turn is lost.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The template's marks.
OPEN, SPLIT, CLOSE = "<|turn|>", "<|text|>", "<|end|>"


def escape(text: Column) -> Column:
    """Reversible: afterwards no mark can occur, as each needs the two characters ``<|``."""
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\s")), F.lit("<|"), F.lit("\\l|"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("\\l|"), F.lit("<|")), F.lit("\\s"), F.lit("\\"))


def expand(conversations: DataFrame) -> DataFrame:
    """``conv_id, example, formatted, loss_start, loss_stop`` (code points, stop exclusive).

    Takes ``conv_id, turn, role, text``.  Turns go by ``turn`` (nulls first), ties by
    role and text; null roles and texts are empty; a row that repeats is a turn each
    time.  Rows with a null conv_id form one conversation.  Empty tables give none.
    """
    turn = F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    df = conversations.groupBy("conv_id").agg(F.array_sort(F.collect_list(turn)).alias("turns"))
    head = F.transform("turns", lambda t: F.concat(F.lit(OPEN), escape(t["role"]), F.lit(SPLIT)))
    body = F.transform("turns", lambda t: escape(t["text"]))
    df = df.select("conv_id", F.transform("turns", lambda t: t["role"] == "assistant").alias("reply"), head.alias("head"), body.alias("body"))
    df = df.withColumn("full", F.zip_with("head", "body", lambda h, b: F.concat(h, b, F.lit(CLOSE))))
    last = F.size("full") - 1
    ends = F.filter(F.sequence(F.lit(0), last), lambda i: F.get("reply", i) | (i == last))
    df = df.select("*", F.posexplode(ends).alias("example", "at"))
    context = F.array_join(F.slice("full", F.lit(1), F.col("at")), "")
    df = df.withColumn("context", context)
    trains = F.get("reply", F.col("at"))
    own = F.get("full", F.col("at"))
    start = F.length("context") + F.length(F.get("head", F.col("at")))
    size = F.length(F.get("body", F.col("at")))
    return df.select("conv_id", F.col("example").cast("long").alias("example"), F.concat("context", own).alias("formatted"), F.when(trains, start).cast("long").alias("loss_start"), F.when(trains, start + size).cast("long").alias("loss_stop"))


def read_back(examples: DataFrame) -> DataFrame:
    """Recover conversations from formatted examples alone: turns from the longest, replies from the masks."""
    masked = F.when(F.col("loss_start").isNotNull(), unescape(F.expr("substring(formatted, cast(loss_start + 1 as int), cast(loss_stop - loss_start as int))")))
    one = examples.select("conv_id", "example", "formatted", masked.alias("reply"), F.length("formatted").cast("long").alias("n"))
    got = one.groupBy("conv_id").agg(F.max_by("formatted", "example").alias("longest"), F.array_sort(F.collect_list(F.when(F.col("reply").isNotNull(), F.struct("example", "reply")))).alias("replies"), F.sum("n").alias("formatted_chars"), F.count("*").alias("n_examples"))
    parts = F.filter(F.split("longest", r"<\|end\|>", -1), lambda p: p != "")
    turns = F.transform(parts, _turn)
    return got.select("conv_id", turns.alias("turns"), F.transform("replies", lambda r: r["reply"]).alias("replies"), "formatted_chars", "n_examples")


def _turn(part: Column) -> Column:
    two = F.split(F.substring(part, F.lit(len(OPEN) + 1), F.length(part)), r"<\|text\|>", 2)
    return F.struct(unescape(F.get(two, F.lit(0))).alias("role"), unescape(F.get(two, F.lit(1))).alias("text"))


def chat_digest(conversations: DataFrame) -> DataFrame:
    """Per conversation, read back from the formatted examples: digests of its turns and of the text under the loss mask."""
    got = read_back(expand(conversations))
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join("replies", "")
    return got.select(
        "conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2(said, 256).alias("turns_sha256"), F.length(loss).cast("long").alias("loss_chars"),
        F.sha2(loss, 256).alias("loss_sha256"), F.col("formatted_chars").cast("long").alias("formatted_chars"), F.col("n_examples").cast("long").alias("n_examples"),
    )
