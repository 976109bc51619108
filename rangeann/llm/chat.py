"""Chat formatting by a grammar round trip, in DataFrame functions alone.

The grammar of a formatted conversation::

    conversation := ["\\\\"] turn*
    turn         := "<s>[INST]" role "[/INST]" text "</s>"

Neither role nor text may hold one of the four control strings.  A conversation is rendered
plainly, parsed back by that grammar, and compared with its source turns; where they differ, or
the parser refuses a control string, it is rendered with escapes (a backslash behind a control
string's first character, backslashes doubled; the leading backslash says so) and parsed and
compared again.  Escaped text holds no control string, so the second round is identical; the
column ``identical`` states it for each row.

A conversation's turns meet in one row, since its text is one string; turns are brought
together by an aggregation on the conversation alone.

Cases: null text and null role read as empty; turns of equal number are ordered by role, then text, and
repeated rows are turns each; a null conversation id is a conversation of its own; an empty table
gives no rows; other columns of the input are ignored.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The control strings, and their escaped forms.
BEGIN, OPEN, CLOSE, END = "<s>", "[INST]", "[/INST]", "</s>"
ESCAPED = {BEGIN: "<\\s>", END: "<\\/s>", OPEN: "[\\INST]", CLOSE: "[\\/INST]"}
FLAG = "\\"
LOSS_ROLE = "assistant"


def swap(text: Column, pairs: list[tuple[str, str]]) -> Column:
    return reduce(lambda c, p: F.replace(c, F.lit(p[0]), F.lit(p[1])), pairs, text)


def escape(text: Column) -> Column:
    return swap(text, [("\\", "\\\\"), *ESCAPED.items()])


def unescape(text: Column) -> Column:
    return swap(text, [*((b, a) for a, b in ESCAPED.items()), ("\\\\", "\\")])


def holds_control(text: Column) -> Column:
    return reduce(lambda a, b: a | b, [F.contains(text, F.lit(c)) for c in ESCAPED])


def render(turns: Column, escaped: bool) -> Column:
    """The conversation as one string."""
    form = escape if escaped else (lambda c: c)
    body = F.transform(turns, lambda t: F.concat(F.lit(BEGIN + OPEN), form(t["role"]), F.lit(CLOSE), form(t["text"]), F.lit(END)))
    return F.concat(F.lit(FLAG if escaped else ""), F.array_join(body, ""))


def parse(formatted: Column) -> Column:
    """The turns that the grammar reads, null where it refuses the string."""
    escaped = F.startswith(formatted, F.lit(FLAG))
    pieces = F.split(F.when(escaped, F.substring(formatted, 2, 2**31 - 1)).otherwise(formatted), F.lit(END), -1)
    bodies = F.slice(pieces, F.lit(1), F.greatest(F.size(pieces) - 1, F.lit(0)))
    form = lambda c: F.when(escaped, unescape(c)).otherwise(c)
    head = BEGIN + OPEN

    def turn(piece: Column) -> Column:
        rest = F.substring(piece, len(head) + 1, 2**31 - 1)
        role = F.substring_index(rest, CLOSE, 1)
        text = rest.substr(F.length(role) + len(CLOSE) + 1, F.length(rest))
        fine = F.startswith(piece, F.lit(head)) & F.contains(rest, F.lit(CLOSE)) & ~holds_control(role) & ~holds_control(text)
        return F.when(fine, F.struct(form(role).alias("role"), form(text).alias("text")))

    turns = F.transform(bodies, turn)
    return F.when((F.element_at(pieces, -1) == "") & ~F.exists(turns, lambda t: t.isNull()), turns)


def pieces_of(formatted: Column) -> Column:
    """The turns as they stand in the string, each without its end."""
    pieces = F.split(formatted, F.lit(END), -1)
    return F.slice(pieces, F.lit(1), F.greatest(F.size(pieces) - 1, F.lit(0)))


def turn_mask(formatted: Column, role: str = LOSS_ROLE) -> Column:
    """The loss mask by turns: code points to skip, code points of text behind them, and whether a model learns from that text."""
    escaped = F.startswith(formatted, F.lit(FLAG))
    head = F.when(escaped, F.concat(F.lit(FLAG + BEGIN + OPEN), escape(F.lit(role)), F.lit(CLOSE))).otherwise(F.lit(BEGIN + OPEN + role + CLOSE))

    def turn(piece: Column, i: Column) -> Column:
        skip = F.length(F.substring_index(piece, CLOSE, 1)) + len(CLOSE)
        own = F.when(i > 0, F.ltrim(head, F.lit(FLAG))).otherwise(head)
        return F.struct(skip.cast("long").alias("skip"), (F.length(piece) - skip).cast("long").alias("length"), F.startswith(piece, own).alias("learn"))

    return F.transform(pieces_of(formatted), turn)


def loss_mask(formatted: Column, role: str = LOSS_ROLE) -> Column:
    """The stretches ``start, end`` (code points, end excluded) of the formatted string that a model learns from."""
    kind = "array<struct<start:long,end:long,learn:boolean>>"

    def step(state: Column, turn: Column) -> Column:
        start = state["at"] + turn["skip"]
        end = start + turn["length"]
        return F.struct((end + len(END)).alias("at"), F.concat(state["found"], F.array(F.struct(start.alias("start"), end.alias("end"), turn["learn"].alias("learn")))).alias("found"))

    zero = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast(kind).alias("found"))
    every = F.aggregate(turn_mask(formatted, role), zero, step, lambda s: s["found"])
    return F.transform(F.filter(every, lambda s: s["learn"]), lambda s: F.struct(s["start"], s["end"]))


def masked_text(formatted: Column, mask: Column) -> Column:
    """All text under a mask of ``turn_mask``, read from the formatted string and unescaped, nothing between."""
    escaped = F.startswith(formatted, F.lit(FLAG))
    under = F.zip_with(pieces_of(formatted), mask, lambda piece, m: F.when(m["learn"], piece.substr((m["skip"] + 1).cast("int"), m["length"].cast("int"))).otherwise(F.lit("")))
    return F.array_join(F.transform(under, lambda t: F.when(escaped, unescape(t)).otherwise(t)), "")


def conversations(rows: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """A row a conversation: its id and its turns in order."""
    turn = F.struct(F.col(turn_col).alias("turn"), F.coalesce(F.col(role_col), F.lit("")).alias("role"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return rows.groupBy(F.col(conv_col).alias(conv_col)).agg(F.array_sort(F.collect_list(turn)).alias("turns"))


def format_chats(rows: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """Rows ``id, formatted, turns`` (read back) ``, identical`` for every conversation."""
    source = conversations(rows, conv_col, turn_col, role_col, text_col).select(conv_col, F.transform("turns", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("source"))
    plain = source.withColumn("plain", render(F.col("source"), escaped=False))
    settled = plain.withColumn("formatted", F.when(F.coalesce(parse(F.col("plain")) == F.col("source"), F.lit(False)), F.col("plain")).otherwise(render(F.col("source"), escaped=True)))
    back = settled.withColumn("turns", parse(F.col("formatted")))
    return back.select(conv_col, "formatted", "turns", F.coalesce(F.col("turns") == F.col("source"), F.lit(False)).alias("identical"))


def digests(chats: DataFrame, conv_col: str = "conv_id") -> DataFrame:
    """What is read back from the formatted strings, as counts and digests: turns by the parser, learnt text by the loss mask."""
    chats = chats.withColumn("mask", turn_mask(F.col("formatted"))).withColumn("learnt", masked_text(F.col("formatted"), F.col("mask")))
    learnt = F.col("learnt")
    return chats.select(
        conv_col,
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "").cast("binary"), 256).alias("turns_sha256"),
        F.length(learnt).cast("long").alias("loss_chars"),
        F.sha2(learnt.cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
        "identical",
    )
