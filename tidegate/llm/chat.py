"""Chat formatting from an event log: fold deltas, edits and regenerations into final messages, then render.

Only DataFrame functions. Events are (conv_id, seq, msg, kind, role, text):

    open        message `msg` begins, with its role and a first text
    delta       text is appended to the message
    edit        the message's text is replaced
    regenerate  the message starts anew with this text; later messages that were opened before it go
    retract     the message goes, until it is opened again

Messages of a conversation are ordered by `msg`. The template writes each message as

    <|turn|>role<|body|>text<|end|>

In roles and texts each of the characters < [ \\ is followed by a backslash, so that no control string, of this
template or of others that begin with < or [, occurs inside; unescape() takes the backslashes away again.

Events are folded in order of (seq, kind as listed above, text, role): each message on its own, in one group of its events;
then a conversation's messages meet in one task, as its string does, so a conversation must fit one.

Defined results: null role and null text are empty; a null conv_id is a conversation of its own; events of a kind
that is not listed, and events of messages never opened, are ignored; null seq come first; repeated events count each time;
an empty log gives no rows; extra columns are left out, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TURN, BODY, END = "<|turn|>", "<|body|>", "<|end|>"
KINDS = ("open", "delta", "edit", "regenerate", "retract")


def escape(c: Column) -> Column:
    return F.regexp_replace(c, r"([<\[\\])", r"$1\\")


def unescape(c: Column) -> Column:
    return F.regexp_replace(c, r"([<\[\\])\\", "$1")


def turns_as_events(rows: DataFrame) -> DataFrame:
    """A log that leads to a conversation table (conv_id, turn, role, text): each row's message is opened and its text streamed
    in two deltas; of every three messages, one is streamed as a draft first and then edited, and one drafted, regenerated and
    streamed again.

    Repeated turns stay apart: messages are numbered by (turn, role, text).
    """
    by = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    numbered = rows.select("conv_id", "turn", "role", F.coalesce("text", F.lit("")).alias("text"), F.row_number().over(by).cast("long").alias("msg"))
    half = F.expr("length(text) div 2")
    head, tail, none, way = F.expr("left(text, length(text) div 2)"), F.substring("text", half + 1, F.length("text")), F.lit(None).cast("string"), F.col("msg") % 3
    event = lambda step, kind, role, text: F.struct((F.col("msg") * 8 + step).alias("seq"), F.lit(kind).alias("kind"), role.alias("role"), text.alias("text"))
    opened, ended = event(0, "open", F.col("role"), none), event(4, "delta", none, tail)
    streamed = F.array(opened, event(3, "delta", none, head), ended)
    edited = F.array(opened, event(1, "delta", none, F.lit("a draft")), event(2, "edit", none, head), ended)
    redone = F.array(opened, event(1, "delta", none, F.lit("a draft")), event(2, "regenerate", none, F.lit("")), event(3, "delta", none, head), ended)
    made = F.when(way == 0, streamed).when(way == 1, edited).otherwise(redone)
    return numbered.select("conv_id", "msg", F.explode(made).alias("e")).select("conv_id", "msg", "e.*")


def fold_messages(events: DataFrame) -> DataFrame:
    """(conv_id, msg, role, text) of the messages that are left.

    The fold of a message's events in order is what its last resetting event begins, and what deltas after it add.
    """
    kinds = F.array(*map(F.lit, KINDS))
    known = events.where(F.col("kind").isin(*KINDS)).select("conv_id", "msg", F.struct("seq", F.array_position(kinds, F.col("kind")).cast("int").alias("step"), F.coalesce("text", F.lit("")).alias("text"), "role").alias("e"))
    folded = known.groupBy("conv_id", "msg").agg(F.sort_array(F.collect_list("e")).alias("log"))
    opens, regenerates, retracts = KINDS.index("open") + 1, KINDS.index("regenerate") + 1, KINDS.index("retract") + 1
    last = lambda test: F.coalesce(F.array_max(F.transform("log", lambda e, i: F.when(test(e["step"]), i))), F.lit(-1))
    folded = folded.select(
        "conv_id", "msg", "log", last(lambda k: k.isin(*(KINDS.index(x) + 1 for x in ("open", "edit", "regenerate")))).alias("since"),
        last(lambda k: k == opens).alias("opened"), last(lambda k: k == retracts).alias("retracted"),
        F.array_max(F.transform("log", lambda e: F.when(e["step"] == regenerates, e["seq"]))).alias("regenerated"),
    )
    live = F.filter(F.slice("log", F.col("since") + 1, F.size("log")), lambda e: e["step"] != retracts)
    opening = F.get("log", F.col("opened"))
    earlier = Window.partitionBy("conv_id").orderBy("msg").rowsBetween(Window.unboundedPreceding, -1)
    return (
        folded.withColumn("cut", F.max("regenerated").over(earlier))
        .where((F.col("opened") >= 0) & (F.col("retracted") < F.col("opened")))
        .where(F.col("cut").isNull() | (F.col("cut") < opening["seq"]))
        .select("conv_id", "msg", F.coalesce(opening["role"], F.lit("")).alias("role"), F.array_join(F.transform(live, lambda e: e["text"]), "").alias("text"))
    )


def render(messages: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """(conv_id, n_turns, formatted, loss_spans): what training counts, as spans (start, length) in code points of `formatted`;
    the same place is also given as the turn's number and its code points before the span (turn, at)."""
    head, body = F.concat(F.lit(TURN), escape(F.col("role")), F.lit(BODY)), escape(F.col("text"))
    order = Window.partitionBy("conv_id").orderBy("msg")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    pieces = messages.select("conv_id", "msg", "role", head.alias("head"), body.alias("body")).withColumn("piece", F.concat("head", "body", F.lit(END)))
    placed = pieces.withColumn("start", F.coalesce(F.sum(F.length("piece")).over(before), F.lit(0)) + F.length("head")).withColumn("turn", F.row_number().over(order) - 1)
    span = F.when(F.col("role") == loss_role, F.struct(F.col("start").cast("long").alias("start"), F.length("body").cast("long").alias("length"), "turn", F.length("head").alias("at")))
    one = placed.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("msg", "piece", span.alias("span")))).alias("all"))
    return one.select(
        "conv_id",
        F.size("all").cast("long").alias("n_turns"),
        F.array_join(F.transform("all", lambda p: p["piece"]), "").alias("formatted"),
        F.filter(F.transform("all", lambda p: p["span"]), lambda s: s.isNotNull()).alias("loss_spans"),
    )


def format_chats(events: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """Event log to (conv_id, n_turns, formatted, loss_spans)."""
    return render(fold_messages(events), loss_role)


def parts(formatted: Column) -> Column:
    """The turns of a formatted conversation as they are written, without their ends."""
    cut = F.split(formatted, r"<\|end\|>", -1)
    return F.slice(cut, 1, F.size(cut) - 1)


def parse(formatted: Column) -> Column:
    """array<struct<role, text>> read back from a formatted conversation."""
    return F.transform(
        parts(formatted),
        lambda t: F.struct(
            unescape(F.substring_index(F.substring(t, len(TURN) + 1, 2**31 - 1), BODY, 1)).alias("role"),
            unescape(F.split(t, r"<\|body\|>", 2)[1]).alias("text"),
        ),
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of the turns, parsed out of the formatted string, and of the text that the loss spans cut out of it."""
    turns = formatted.select("conv_id", "formatted", "loss_spans", parse(F.col("formatted")).alias("turns"), parts(F.col("formatted")).alias("parts"))
    masked = F.transform("loss_spans", lambda s: unescape(F.substring(F.get("parts", s["turn"]), s["at"] + 1, s["length"].cast("int"))))
    return turns.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), ""), 256).alias("turns_sha256"),
        F.array_join(masked, "").alias("loss"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    ).select("conv_id", "n_turns", "turns_sha256", F.length("loss").cast("long").alias("loss_chars"), F.sha2("loss", 256).alias("loss_sha256"), "formatted_chars")
