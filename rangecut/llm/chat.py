"""Chat formatting with a grammar that reads back what was written. DataFrame functions only.

A conversation becomes ``<|im_start|>role NEWLINE text<|im_end|> NEWLINE`` for
each turn. The parser is deterministic: it cuts at every start mark, the role
ends at the first newline, the text at the end mark that closes the turn, and a
mark whose inside begins with backslashes loses one of them. A conversation is
first written as it is and parsed again. Where the turns read back differ from
the source (a text or role holds marks, escaped marks or a newline in the
role), the conflicting content is escaped and the round trip repeated. The
first form that reads back identically is kept, and the level that it took is
returned.

Cases: a null text or role counts as empty; turns of equal number are ordered
by role, then text, null numbers first; repeated rows are repeated turns; rows
of a null id form one conversation; an empty table gives no rows; other columns
are ignored. A conversation is one row and so has to fit into a task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed values of the format.
START, END = "<|im_start|>", "<|im_end|>"
MARK = r"<(\\*)\|(im_start|im_end)\|>"
ESCAPED_MARK = r"<\\(\\*)\|(im_start|im_end)\|>"

TURNS = "array<struct<role:string,text:string>>"


def escape_text(text: Column) -> Column:
    """Adds a backslash inside every mark, escaped or not."""
    return F.regexp_replace(text, MARK, r"<\\$1|$2|>")


def unescape_text(text: Column) -> Column:
    return F.regexp_replace(text, ESCAPED_MARK, r"<$1|$2|>")


def escape_role(role: Column) -> Column:
    """A role also may not hold a newline; ``%`` leads its codes."""
    return F.replace(F.replace(escape_text(role), F.lit("%"), F.lit("%25")), F.lit("\n"), F.lit("%0A"))


def unescape_role(role: Column) -> Column:
    return unescape_text(F.replace(F.replace(role, F.lit("%0A"), F.lit("\n")), F.lit("%25"), F.lit("%")))


def render(turns: Column, level: int) -> Column:
    """Level 0 writes turns as they are, level 1 escapes texts, level 2 roles as well."""

    def one(turn: Column) -> Column:
        role = escape_role(turn["role"]) if level > 1 else turn["role"]
        text = escape_text(turn["text"]) if level > 0 else turn["text"]
        return F.concat(F.lit(START), role, F.lit("\n"), text, F.lit(END + "\n"))

    return F.array_join(F.transform(turns, one), "")


def _pieces(formatted: Column) -> Column:
    """What follows each start mark; what precedes the first belongs to no turn."""
    parts = F.split(formatted, r"<\|im_start\|>", -1)
    return F.slice(parts, F.lit(2), F.size(parts))


def _body(piece: Column) -> Column:
    """Of a piece, what stands between its first newline and its last end mark, as written."""
    after = F.substring(piece, F.instr(piece, F.lit("\n")) + 1, F.length(piece))
    tail = len(END) + 1
    return F.when(F.endswith(after, F.lit(END + "\n")), F.substring(after, F.lit(1), F.length(after) - tail)).otherwise(after)


def parse(formatted: Column) -> Column:
    """The turns of a formatted conversation."""
    return F.transform(
        _pieces(formatted),
        lambda p: F.struct(
            unescape_role(F.substring_index(p, "\n", 1)).alias("role"),
            unescape_text(_body(p)).alias("text"),
        ),
    )


def loss_spans(formatted: Column) -> Column:
    """(start, length) in code points of the assistant's texts as written: the loss mask."""

    def step(state: Column, piece: Column) -> Column:
        begin = state["at"] + len(START)
        role = F.substring_index(piece, "\n", 1)
        span = F.struct(
            (begin + F.length(role) + 1).cast("long").alias("start"),
            F.length(_body(piece)).cast("long").alias("length"),
        )
        spans = F.when(unescape_role(role) == "assistant", F.concat(state["spans"], F.array(span))).otherwise(state["spans"])
        return F.struct((begin + F.length(piece)).alias("at"), spans.alias("spans"))

    empty = F.array().cast("array<struct<start:bigint,length:bigint>>")
    return F.aggregate(
        _pieces(formatted),
        F.struct(F.lit(0).cast("int").alias("at"), empty.alias("spans")),
        step,
        lambda s: s["spans"],
    )


def format_conversations(conversations: DataFrame) -> DataFrame:
    """One row for each conversation: conv_id, formatted, level, spans.

    A level is only tried where the one before failed its round trip.
    """
    rows = conversations.select(
        "conv_id",
        "turn",
        F.coalesce("role", F.lit("")).alias("role"),
        F.coalesce("text", F.lit("")).alias("text"),
    )
    whole = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("rows"))
    turns = whole.select("conv_id", F.transform("rows", lambda r: F.struct(r["role"].alias("role"), r["text"].alias("text"))).alias("turns"))
    tried = turns.withColumn("formatted", render(F.col("turns"), 0)).withColumn("level", F.lit(0))
    for level in (1, 2):
        failed = ~parse(F.col("formatted")).eqNullSafe(F.col("turns"))
        tried = tried.withColumn("failed", failed).select(
            "conv_id",
            "turns",
            F.when(F.col("failed"), render(F.col("turns"), level)).otherwise(F.col("formatted")).alias("formatted"),
            F.when(F.col("failed"), F.lit(level)).otherwise(F.col("level")).alias("level"),
        )
    return tried.select(
        "conv_id",
        "formatted",
        "level",
        parse(F.col("formatted")).eqNullSafe(F.col("turns")).alias("identical"),
        loss_spans(F.col("formatted")).alias("spans"),
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of what a reader of ``format_conversations`` gets back."""
    lines = F.array_join(F.transform(F.col("turns"), lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    masked = F.transform(F.col("spans"), lambda s: unescape_text(F.substring(F.col("formatted"), s["start"].cast("int") + 1, s["length"].cast("int"))))
    return (
        formatted.withColumn("turns", parse(F.col("formatted")))
        .withColumn("loss", F.array_join(masked, ""))
        .select(
            "conv_id",
            F.size("turns").cast("long").alias("n_turns"),
            F.sha2(lines, 256).alias("turns_sha256"),
            F.length("loss").cast("long").alias("loss_chars"),
            F.sha2("loss", 256).alias("loss_sha256"),
            F.length("formatted").cast("long").alias("formatted_chars"),
        )
    )
