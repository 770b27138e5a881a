"""Chat template with a grammar that is read back (built-in functions only).

A conversation becomes ``<|im_start|>role\\ntext<|im_end|>\\n`` per turn. The
grammar is deterministic: a turn ends at the first end mark with a line end, its
role at the first line end, and ``<|im_`` inside a role or text is an error. Every turn is
rendered plain, read by the parser and compared with its source; where that isn't
identical its content is escaped (in every ``<`` + any number of backslashes +
``|`` one backslash is added; roles have backslashes and line ends escaped
besides), read and compared again, and a turn that still differs fails the
job. So is the whole conversation read and compared once its turns are
joined. ``formatted`` carries whether a turn is escaped in its start mark
(``<|im_start|>`` plain, ``<|im_start_x|>`` escaped), so reading needs nothing else.

Defined results: null text and null role are empty strings; turns stand by
turn, then role, then text, nulls first; repeated rows stay; rows with a null conv_id are one
conversation; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import let

START, START_X, END = "<|im_start|>", "<|im_start_x|>", "<|im_end|>"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, r"<(\\*)\|", r"<\\$1|")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"<\\(\\*)\|", r"<$1|")


def escape_role(role: Column) -> Column:
    return F.replace(F.replace(escape(role), F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n"))


def unescape_role(role: Column) -> Column:
    # an escaped backslash is two; what is left before n is a line end
    parts = F.transform(F.split(role, r"\\\\"), lambda x: F.replace(x, F.lit("\\n"), F.lit("\n")))
    return unescape(F.array_join(parts, "\\"))


def parse(formatted: Column) -> Column:
    """Array of (role, text, head, body, size): the turns, and where each turn's text starts and
    how long it is in its piece of the formatted string, in code points. A piece outside the
    grammar has a null role and text."""
    pieces = F.filter(F.split(formatted, r"<\|im_end\|>\n"), lambda p: F.length(p) > 0)

    def turn(p: Column) -> Column:
        escaped, plain = F.startswith(p, F.lit(START_X)), F.startswith(p, F.lit(START))
        rest = F.substr(p, F.when(escaped, len(START_X) + 1).otherwise(len(START) + 1))
        cut = F.instr(rest, "\n")
        sound = (escaped | plain) & (cut > 0) & ~F.contains(rest, F.lit("<|im_"))
        role, body = F.substr(rest, F.lit(1), cut - 1), F.substr(rest, cut + 1)
        return F.struct(F.when(sound, F.when(escaped, unescape_role(role)).otherwise(role)).alias("role"), F.when(sound, F.when(escaped, unescape(body)).otherwise(body)).alias("text"), (F.length(p) - F.length(body)).alias("head"), F.length(body).alias("body"), F.length(p).alias("size"))

    return F.transform(pieces, turn)


def comes_back(formatted: Column, turns: Column) -> Column:
    """Whether the parser reads exactly these turns (array of role, text) from the string."""
    read = F.transform(parse(formatted), lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text")))
    return read.eqNullSafe(turns)


def render_turn(role: Column, text: Column) -> Column:
    """One turn, plain if the parser gives it back as it is, else escaped if that comes back."""
    plain = F.concat(F.lit(START), role, F.lit("\n"), text, F.lit(f"{END}\n"))
    safe = F.concat(F.lit(START_X), escape_role(role), F.lit("\n"), escape(text), F.lit(f"{END}\n"))
    source = F.array(F.struct(role.alias("role"), text.alias("text")))
    ready = lambda out, other: F.when(comes_back(out, source), out).otherwise(other)
    return let(plain, lambda p: ready(p, let(safe, lambda s: ready(s, F.raise_error(F.lit("a turn doesn't survive its round trip")).cast("string")))))


def format_chats(turns: DataFrame) -> DataFrame:
    """conv_id, formatted and loss: the assistant texts, as start and length in code points
    of ``formatted``, and the turn's number."""
    clean = turns.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    rendered = clean.select("*", render_turn(F.col("role"), F.col("text")).alias("out"))
    # places by a window that shares the grouping's exchange: no list grows inside a row
    mine = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    upto = mine.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    read = F.element_at(parse(F.col("out")), 1)
    placed = rendered.withColumn("n", F.row_number().over(mine)).withColumn("end", F.sum(F.length("out")).over(upto).cast("int")).withColumn("body", read["body"])
    start = F.col("end") - F.lit(len(END) + 1) - F.col("body")
    span = F.when(F.col("role") == "assistant", F.struct(F.col("n"), start.alias("start"), F.col("body").alias("length")))
    grouped = placed.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("n", "role", "text", "out"))).alias("t"), F.sort_array(F.collect_list(span)).alias("s"))
    source = F.transform("t", lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text")))
    whole = let(F.array_join(F.col("t.out"), ""), lambda f: F.when(comes_back(f, source), f).otherwise(F.raise_error(F.lit("a conversation doesn't survive its round trip")).cast("string")))
    return grouped.select("conv_id", whole.alias("formatted"), F.transform("s", lambda x: F.struct(x["start"].alias("start"), x["length"].alias("length"), x["n"].alias("turn"))).alias("loss"))


def read_back(formatted: DataFrame) -> DataFrame:
    """conv_id, turns, masked (all text under the loss mask, unescaped) and formatted_chars, from the output alone."""

    def under(pieces: Column) -> Column:
        def text(span: Column) -> Column:
            piece = F.element_at(pieces, span["turn"])
            body = F.substr(piece, F.length(piece) - span["length"] + 1)
            return F.when(F.startswith(piece, F.lit(START_X)), unescape(body)).otherwise(body)

        return F.array_join(F.transform("loss", text), "")

    return formatted.select("conv_id", parse(F.col("formatted")).alias("turns"), let(F.split("formatted", r"<\|im_end\|>\n"), under).alias("masked"), F.length("formatted").cast("long").alias("formatted_chars"))
