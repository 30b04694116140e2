"""Chat formatting: a role automaton checks the turn order, a declarative template emits text segments with loss flags."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class ChatTemplate:
    """What to print around a turn, which roles are trained on, and which role may follow which.

    ``headers`` has the header of each known role; any other role is printed, escaped, between the two strings of
    ``other``. ``controls`` are broken up inside texts; none may overlap itself. ``moves`` maps a state to the roles that
    may come next ("" is the start); ``final`` are the states in which a conversation may end.
    """

    headers: dict = field(default_factory=lambda: {"system": "### System: ", "user": "### User: ", "assistant": "### Assistant: "})
    other: tuple = ("### Role ", ": ")
    end: str = " </turn>\n"
    controls: tuple = ("### ", "</turn>")
    loss_roles: tuple = ("assistant",)
    moves: dict = field(default_factory=lambda: {"": ("system", "user"), "system": ("user",), "user": ("assistant",), "assistant": ("user",)})
    final: tuple = ("assistant",)


def escape(text: Column, template: ChatTemplate) -> Column:
    """Double every backslash, then put one after the first character of each control string."""
    out = F.replace(text, F.lit("\\"), F.lit("\\\\"))
    for c in template.controls:
        out = F.replace(out, F.lit(c), F.lit(f"{c[0]}\\{c[1:]}"))
    return out


def unescape(text: Column) -> Column:
    """A backslash stands for the character after it."""
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def _header(role: Column, template: ChatTemplate) -> Column:
    other = F.concat(F.lit(template.other[0]), F.replace(escape(role, template), F.lit(":"), F.lit("\\:")), F.lit(template.other[1]))
    out = other
    for name, header in template.headers.items():
        out = F.when(role == name, F.lit(header)).otherwise(out)
    return out


def _verdict(turns: Column, template: ChatTemplate) -> Column:
    """Run the automaton over the roles; state "!" is the sink of a forbidden move."""
    edges = [x for a, bs in template.moves.items() for b in bs for x in (F.lit(f"{a}>{b}"), F.lit(b))]
    step = F.create_map(*edges)
    last = F.aggregate(turns, F.lit(""), lambda s, t: F.coalesce(F.element_at(step, F.concat(s, F.lit(">"), t["role"])), F.lit("!")))
    return last.isin(*template.final)


def format_conversations(rows: DataFrame, template: ChatTemplate | None = None) -> DataFrame:
    """One row per conversation: ``conv_id, n_turns, valid, segments array<struct<text, loss>>, formatted``.

    Turns come in order of ``turn``, ties in order of role and text, so repeated rows give repeated turns. A null text or
    role counts as empty, a null turn comes first, a null conv_id is a conversation of its own. Conversations whose turn
    order the automaton refuses are formatted too and have ``valid`` false. Other columns are ignored. An empty table
    gives no rows. A conversation is one row of the result, so its texts must fit in a row; nothing else is gathered.
    """
    template = template or ChatTemplate()
    turn = F.struct(F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    turns = rows.select("conv_id", turn.alias("t")).groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("turns"))
    piece = lambda text, loss: F.struct(text.alias("text"), loss.alias("loss"))
    segments = F.flatten(F.transform("turns", lambda t: F.array(
        piece(_header(t["role"], template), F.lit(False)),
        piece(escape(t["text"], template), t["role"].isin(*template.loss_roles)),
        piece(F.lit(template.end), F.lit(False)),
    )))
    out = turns.select("conv_id", F.size("turns").cast("long").alias("n_turns"), _verdict(F.col("turns"), template).alias("valid"), segments.alias("segments"))
    return out.withColumn("formatted", F.array_join(F.transform("segments", lambda s: s["text"]), ""))


def segment_rows(formatted: DataFrame) -> DataFrame:
    """One row per segment: ``conv_id, segment_no, text, loss``, for a trainer that masks token by token."""
    return formatted.select("conv_id", F.posexplode("segments").alias("segment_no", "s")).select("conv_id", "segment_no", "s.text", "s.loss")


def parse_turns(formatted: Column, template: ChatTemplate | None = None) -> Column:
    """``array<struct<role, text>>`` read back from a formatted string; the inverse of formatting."""
    template = template or ChatTemplate()
    quoted = "\\Q" + template.end + "\\E"
    pieces = F.split(formatted, quoted, -1)
    pieces = F.slice(pieces, F.lit(1), F.size(pieces) - 1)

    def turn(p: Column) -> Column:
        pattern = rf"(?s)^\Q{template.other[0]}\E((?:[^\\:]|\\.)*)\Q{template.other[1]}\E(.*)$"
        out = F.struct(unescape(F.regexp_extract(p, pattern, 1)).alias("role"), unescape(F.regexp_extract(p, pattern, 2)).alias("text"))
        for name, header in template.headers.items():
            out = F.when(F.startswith(p, F.lit(header)), F.struct(F.lit(name).alias("role"), unescape(F.substring(p, len(header) + 1, 2**31 - 1)).alias("text"))).otherwise(out)
        return out

    return F.transform(pieces, turn)


def digest(formatted: DataFrame, template: ChatTemplate | None = None) -> DataFrame:
    """Digests of what the formatted output says, for comparison with the input: turns are counted and read back from the string."""
    read = formatted.withColumn("read", parse_turns(F.col("formatted"), template))
    turns = F.array_join(F.transform("read", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join(F.transform(F.filter("segments", lambda s: s["loss"]), lambda s: unescape(s["text"])), "")
    return read.select("*", turns.alias("turn_text"), loss.alias("loss_text")).select(
        "conv_id", F.size("read").cast("long").alias("n_turns"), F.sha2("turn_text", 256).alias("turns_sha256"), F.length("loss_text").cast("long").alias("loss_chars"),
        F.sha2("loss_text", 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"), "valid",
    )
