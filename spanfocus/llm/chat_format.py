"""Chat formatting by event-sourced reconstruction, in DataFrame expressions only.

A log is a stream of events on messages of conversations: streamed deltas, edits and regenerations. The
log is folded per message and then per conversation into final messages, which a template renders; the
rendered text can be parsed back without loss.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# The control strings of the template.
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"
_CLOSE_LINE = r"<\|im_end\|>\n"

DELTA, EDIT, REGENERATE = "delta", "edit", "regenerate"


def fold_events(
    log: DataFrame, conversation: str = "conv_id", message: str = "message", sequence: str = "seq",
    kind: str = "kind", role: str = "role", text: str = "text",
) -> DataFrame:
    """(conversation, message, role, text): the final messages of an event log.

    ``delta`` appends to its message, ``edit`` replaces the message's text, ``regenerate`` discards the
    message's text and every later message that had begun before it. Events apply in order of ``sequence``;
    ties in the order delta, edit, regenerate, then by text. Null texts count as empty, an unknown kind as a
    delta; the message's role is that of its last event with one, else empty. Repeated delta rows append
    again. Null conversations and messages form groups of their own. Other columns are not read.
    """
    place = F.when(F.col(kind) == REGENERATE, 2).when(F.col(kind) == EDIT, 1).otherwise(0)
    events = log.select(
        conversation,
        message,
        F.struct(
            F.col(sequence).alias("seq"), place.alias("kind"), F.coalesce(F.col(text), F.lit("")).alias("text"), F.col(role).alias("role")
        ).alias("e"),
    )
    folded = events.groupBy(conversation, message).agg(
        F.sort_array(F.collect_list("e")).alias("es"),
        F.min("e.seq").alias("begun"),
        F.max(F.when(F.col("e.kind") == 2, F.col("e.seq"))).alias("again"),
    )
    # The text is what follows the last reset: one pass finds it, one slice takes it.
    reset = F.coalesce(F.array_max(F.transform("es", lambda e, i: F.when(e["kind"] > 0, i))), F.lit(0))
    kept = F.slice("es", reset + 1, F.size("es") - reset)
    body = F.array_join(F.transform(kept, lambda e: F.when(e["kind"] == 2, F.lit("")).otherwise(e["text"])), "")
    roles = F.filter(F.transform("es", lambda e: e["role"]), lambda r: r.isNotNull())
    last_role = F.when(F.size(roles) > 0, F.element_at(roles, -1)).otherwise("")
    earlier = Window.partitionBy(conversation).orderBy(message).rowsBetween(Window.unboundedPreceding, -1)
    undone = F.coalesce(F.max("again").over(earlier) > F.col("begun"), F.lit(False))
    return (
        folded.select(conversation, message, last_role.alias("role"), body.alias("text"), "again", "begun")
        .withColumn("undone", undone)
        .where(~F.col("undone"))
        .select(conversation, message, "role", "text")
    )


def escaped(text: Column) -> Column:
    """Text without control strings: backslashes double, and a backslash splits every ``<|``."""
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescaped(text: Column) -> Column:
    return F.regexp_replace(text, r"\\([\s\S])", "$1")


def escaped_role(role: Column) -> Column:
    """As a text, and line breaks get a backslash as well, since the role ends its line."""
    return F.replace(escaped(role), F.lit("\n"), F.lit("\\\n"))


def render(messages: DataFrame, conversation: str = "conv_id", message: str = "message", role: str = "role", text: str = "text") -> DataFrame:
    """(conversation, formatted): one rendered string per conversation, messages in ascending order."""
    turn = F.concat(F.lit(OPEN), escaped_role(F.col(role)), F.lit("\n"), escaped(F.col(text)), F.lit(CLOSE + "\n"))
    rows = messages.select(conversation, F.struct(F.col(message).alias("m"), turn.alias("t")).alias("x"))
    return rows.groupBy(conversation).agg(
        F.array_join(F.transform(F.sort_array(F.collect_list("x")), lambda x: x["t"]), "").alias("formatted")
    )


def parse(formatted: Column) -> Column:
    """Array of (role, text) read back from a rendered string; texts hold no control string, so cuts are sure."""
    pieces = F.split(formatted, _CLOSE_LINE)
    pieces = F.slice(pieces, 1, F.size(pieces) - 1)  # after the last close nothing follows
    head = rf"^<\|im_start\|>((?:[^\\\n]|\\[\s\S])*+)\n"

    def turn(piece: Column) -> Column:
        raw = F.regexp_extract(piece, head, 1)
        body = F.substring(piece, F.length(raw) + F.lit(len(OPEN) + 2), F.length(piece))
        return F.struct(unescaped(raw).alias("role"), unescaped(body).alias("text"))

    return F.transform(pieces, turn)


def with_loss_mask(rendered: DataFrame, trained_role: str = "assistant") -> DataFrame:
    """Adds ``turns`` read back from the output and ``loss_text``: the trained role's texts, nothing between."""
    turns = rendered.withColumn("turns", parse(F.col("formatted")))
    spoken = F.filter("turns", lambda t: t["role"] == trained_role)
    return turns.withColumn("loss_text", F.array_join(F.transform(spoken, lambda t: t["text"]), ""))


def format_conversations(
    turns: DataFrame, conversation: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text"
) -> DataFrame:
    """Format a table of finished turns: each row is one event on a message of its own.

    Rows are ordered by turn; rows of one turn by role, then text. Null roles and texts count as empty.
    Returns (conversation, formatted, turns, loss_text); an empty table gives an empty result.
    """
    # Folding needs a message id of its own for each row, also where a turn number repeats.
    order = Window.partitionBy(conversation).orderBy(turn, role, text)
    log = turns.select(
        conversation, F.row_number().over(order).alias("message"), F.lit(DELTA).alias("kind"), F.col(turn).alias("seq"),
        F.col(role).alias("role"), F.col(text).alias("text"),
    )
    return with_loss_mask(render(fold_events(log, conversation), conversation))
