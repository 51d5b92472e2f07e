"""Chat template whose output a deterministic parser reads back exactly.

Turns are first rendered as they are.  The rendering is parsed again and the
turns compared with the source.  Where they are not identical, or a turn holds
control strings, the turns that hold one or do not come back alone are rendered
escaped and the whole is parsed again; if it is still not identical every turn
is escaped.  Escaping is reversible, so the last step always succeeds.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed values of the template.
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"
TAIL = CLOSE + "\n"
TURN = "array<struct<role:string,text:string>>"


def _swap(c: Column, a: str, b: str) -> Column:
    return F.replace(c, F.lit(a), F.lit(b))


def escape(c: Column) -> Column:
    """No control string and no line end is left, and every ``&`` starts an entity."""
    return _swap(_swap(_swap(c, "&", "&amp;"), "<|", "&lt;|"), "\n", "&#10;")


def escape_text(c: Column) -> Column:
    """As :func:`escape`, but line ends stay."""
    return _swap(_swap(c, "&", "&amp;"), "<|", "&lt;|")


def unescape(c: Column) -> Column:
    return _swap(_swap(_swap(c, "&#10;", "\n"), "&lt;|", "<|"), "&amp;", "&")


def has_control(t: Column) -> Column:
    """Whether a turn holds the start of a control string, which is never left as it is."""
    return t["role"].contains("<|") | t["text"].contains("<|")


def plain(turns: Column) -> Column:
    return F.transform(turns, lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text")))


def needs_escape(t: Column) -> Column:
    """Whether a turn holds control strings or, rendered alone and parsed, does not come back."""
    alone = F.array(F.struct(t["role"].alias("role"), t["text"].alias("text")))
    return has_control(t) | (plain(parse(render(alone, lambda x: F.lit(False)))) != alone)


def render(turns: Column, escaped) -> Column:
    """Formatted text; ``escaped(turn)`` says which turns are escaped."""

    def one(t: Column) -> Column:
        e = escaped(t)
        return F.concat(F.lit(OPEN), F.when(e, escape(t["role"])).otherwise(t["role"]), F.lit("\n"), F.when(e, escape_text(t["text"])).otherwise(t["text"]), F.lit(TAIL))

    return F.array_join(F.transform(turns, one), "")


def parse(formatted: Column) -> Column:
    """Turns of a formatted text with their place in it: role, text, and the offsets of the raw text."""
    parts = F.split(formatted, r"<\|im_start\|>", -1)
    body = F.slice(parts, F.lit(2), F.greatest(F.size(parts) - 1, F.lit(0)))
    first = F.struct(F.length(parts[0]).alias("at"), F.expr("cast(array() as array<struct<role:string,text:string,start:int,end:int>>)").alias("turns"))

    def step(acc: Column, p: Column) -> Column:
        head = F.length(F.substring_index(p, "\n", 1))
        start = acc["at"] + len(OPEN) + head + 1
        end = acc["at"] + len(OPEN) + F.length(p) - len(TAIL)
        raw = F.substr(p, head + 2, F.length(p) - head - 1 - len(TAIL))
        one = F.struct(unescape(F.substring_index(p, "\n", 1)).alias("role"), unescape(raw).alias("text"), start.alias("start"), end.alias("end"))
        return F.struct((acc["at"] + len(OPEN) + F.length(p)).alias("at"), F.concat(acc["turns"], F.array(one)).alias("turns"))

    return F.aggregate(body, first, step, lambda acc: acc["turns"])


def format_conversations(conversations: DataFrame) -> DataFrame:
    """One row for each conversation: formatted text, the turns read back from it, loss spans, and how often it was rendered anew.

    Turns are ordered by turn, then role and text; null roles and texts are
    empty, null turns come first, rows with a null conv_id form one
    conversation; repeated rows are turns of their own.  Columns other than
    conv_id, turn, role and text are not read; an empty table gives no rows.
    Loss spans are the offsets, in code points of the formatted text, of each
    assistant turn's text.
    """
    empty = lambda c: F.coalesce(F.col(c), F.lit(""))
    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.struct(F.col("turn").cast("long").alias("turn"), empty("role").alias("role"), empty("text").alias("text")).alias("t"))
    g = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("ts"))
    g = g.select("conv_id", F.transform("ts", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))
    g = g.withColumn("first", render(F.col("turns"), lambda t: F.lit(False)))
    back = plain(parse(F.col("first"))) == F.col("turns")
    g = g.withColumn("rounds", F.when(back & ~F.exists("turns", has_control), 0).otherwise(1))
    g = g.withColumn("second", F.when(F.col("rounds") == 0, F.col("first")).otherwise(render(F.col("turns"), needs_escape)))
    g = g.withColumn("again", parse(F.col("second")))
    g = g.withColumn("rounds", F.when((F.col("rounds") > 0) & (plain(F.col("again")) != F.col("turns")), 2).otherwise(F.col("rounds")))
    g = g.withColumn("formatted", F.when(F.col("rounds") < 2, F.col("second")).otherwise(render(F.col("turns"), lambda t: F.lit(True))))
    g = g.withColumn("parsed", F.when(F.col("rounds") < 2, F.col("again")).otherwise(parse(F.col("formatted"))))
    loss = F.transform(F.filter("parsed", lambda t: t["role"] == "assistant"), lambda t: F.struct(t["start"].alias("start"), t["end"].alias("end")))
    return g.select("conv_id", "formatted", "parsed", loss.alias("loss_spans"), "rounds")


def format_digest(conversations: DataFrame) -> DataFrame:
    """Digests of :func:`format_conversations`, all taken from the formatted text."""
    f = format_conversations(conversations)
    loss = F.array_join(F.transform("loss_spans", lambda s: unescape(F.substr(F.col("formatted"), s["start"] + 1, s["end"] - s["start"]))), "")
    f = f.withColumn("loss", loss)
    nl = F.lit("\n")
    turns = F.array_join(F.transform("parsed", lambda t: F.concat(t["role"], nl, t["text"], nl)), "")
    return f.select(
        "conv_id", F.size("parsed").cast("long").alias("n_turns"), F.sha2(turns.cast("binary"), 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"), F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"),
    )
