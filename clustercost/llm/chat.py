"""Chat formatting with Spark expressions only.

A conversation's turns are collected as structs, sorted, folded so that adjacent turns of
one role share a block, and concatenated.  Control strings: ``<|im_start|>role`` and a line
feed open a block, ``<|turn|>`` stands between the turns of a block, ``<|im_end|>`` and a
line feed close it.  Inside roles and texts ``\\`` is doubled and ``<|`` becomes ``<\\|``, so
no text can form a control string and the escape can be undone.  The loss mask is a list
of spans (code points of the output) over the assistant texts, without any control string.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

START, TURN, END = "<|im_start|>", "<|turn|>", "<|im_end|>"


def escape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def escape_role(role: Column) -> Column:
    return F.replace(escape(role), F.lit("\n"), F.lit("<\\n>"))


def unescape_role(role: Column) -> Column:
    return unescape(F.replace(role, F.lit("<\\n>"), F.lit("\n")))


def format_chats(conversations: DataFrame, learn: str = "assistant") -> DataFrame:
    """Per conversation: ``conv_id, formatted, loss array<struct<start, length>>``.

    Turns are ordered by turn, then role, then text.  A null role or text is empty; an empty
    text keeps its turn; a null conv_id is a conversation of its own; repeated rows are
    repeated turns; an empty table gives no rows; further columns are not read.  A
    conversation is one output value, so it has to fit in a row.
    """
    rows = conversations.select("conv_id", F.col("turn").alias("t"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("r"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("x"))
    turns = rows.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("t", "r", "x"))).alias("turns"))
    n = F.size("turns")

    def piece(turn: Column, i: Column) -> Column:
        """What a turn adds: the control string before it, its text, and a closing when its block ends."""
        same_before = (i > 0) & (F.get("turns", i - 1)["r"] == turn["r"])
        same_after = (i < n - 1) & (F.get("turns", i + 1)["r"] == turn["r"])
        return F.struct(
            F.when(same_before, F.lit(TURN)).otherwise(F.concat(F.lit(START), escape_role(turn["r"]), F.lit("\n"))).alias("before"),
            escape(turn["x"]).alias("text"),
            F.when(same_after, F.lit("")).otherwise(F.lit(END + "\n")).alias("after"),
            (turn["r"] == F.lit(learn)).alias("learn"),
        )

    parts = turns.withColumn("parts", F.transform("turns", piece))
    text = F.array_join(F.transform("parts", lambda p: F.concat(p["before"], p["text"], p["after"])), "")
    zero = F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast("array<struct<start:bigint,length:bigint>>").alias("spans"))

    def step(state: Column, p: Column) -> Column:
        start = state["at"] + F.length(p["before"])
        size = F.length(p["text"]).cast("bigint")
        spans = F.when(p["learn"], F.concat(state["spans"], F.array(F.struct(start.alias("start"), size.alias("length"))))).otherwise(state["spans"])
        return F.struct((start + size + F.length(p["after"])).alias("at"), spans.alias("spans"))

    return parts.select("conv_id", text.alias("formatted"), F.aggregate("parts", zero, step)["spans"].alias("loss"))


def read_back(formatted: Column) -> Column:
    """The turns of a formatted conversation: ``array<struct<role, text>>``."""
    blocks = F.filter(F.split(formatted, r"<\|im_end\|>\n"), lambda b: b != "")

    return F.flatten(F.transform(blocks, _block_turns))


def _block_turns(block: Column) -> Column:
    body = F.substr(block, F.lit(len(START) + 1))
    role = F.substring_index(body, "\n", 1)
    texts = F.split(F.substr(body, F.length(role) + 2), r"<\|turn\|>")
    return F.transform(texts, lambda x: F.struct(unescape_role(role).alias("role"), unescape(x).alias("text")))


def loss_text(formatted: Column, loss: Column) -> Column:
    """All text under the loss mask, unescaped."""
    return F.array_join(F.transform(loss, lambda s: unescape(F.substr(formatted, (s["start"] + 1).cast("int"), s["length"].cast("int")))), "")


def report(conversations: DataFrame) -> DataFrame:
    """Digests of what is read back from the output."""
    chats = format_chats(conversations)
    back = chats.select("conv_id", "formatted", read_back(F.col("formatted")).alias("turns"), loss_text(F.col("formatted"), F.col("loss")).alias("learned"))
    lines = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id",
        F.size("turns").cast("bigint").alias("n_turns"),
        F.sha2(lines, 256).alias("turns_sha256"),
        F.length("learned").cast("bigint").alias("loss_chars"),
        F.sha2(F.col("learned"), 256).alias("loss_sha256"),
        F.length("formatted").cast("bigint").alias("formatted_chars"),
    )
