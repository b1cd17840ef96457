r"""Event-sourced chat logs: fold into final messages, render with a loss mask, read back.

A log row is an event (conv_id, message, seq, op, role, text). ``message`` orders the messages of
a conversation, ``seq`` the events of a message; a further column ``part``, where a log has one,
tells apart messages that share a number. op: ``post`` starts a message, ``delta`` appends
to it, ``edit`` and ``regenerate`` replace what was there. All on DataFrame functions.

Template: ``<turn>role<text>text</turn>\n``; text under the loss mask is opened by ``<loss>`` in
place of ``<text>``. Inside roles and texts a backslash becomes ``\b`` and ``<`` becomes ``\l``, so
that no text can hold a control string, and the reader gets every character back.

Edge cases: null text or role is empty; null op is ``post``; posts that share a message number
(and part), repeated rows included, are messages of their own, ordered by role and text; when other events
follow, the last post, edit or regeneration is the base that later deltas extend; deltas without a
base begin with an empty text; a null conv_id is a conversation; an empty log gives no rows;
further columns are ignored, also those of names that are used inside.

A conversation may hold a large part of all rows: events are folded by message, messages are
rendered in runs of ``chunk`` numbers, and only one rendered string a run meets in the last group.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

OPEN, TEXT, LOSS, CLOSE = "<turn>", "<text>", "<loss>", "</turn>\n"


def escape(col: Column) -> Column:
    return F.replace(F.replace(col, F.lit("\\"), F.lit("\\b")), F.lit("<"), F.lit("\\l"))


def unescape(col: Column) -> Column:
    return F.replace(F.replace(col, F.lit("\\l"), F.lit("<")), F.lit("\\b"), F.lit("\\"))


def fold_events(log: DataFrame) -> DataFrame:
    """Final messages: conv_id, message, part, role, text; part numbers messages that share a message number."""
    empty = lambda c: F.coalesce(F.col(c), F.lit(""))
    op = F.coalesce(F.col("op"), F.lit("post"))
    own = F.col("part").cast("long") if "part" in log.columns else F.lit(0).cast("long")
    events = log.select("conv_id", "message", own.alias("own"), "seq", op.alias("op"), empty("role").alias("role"), empty("text").alias("text"))
    grouped = events.groupBy("conv_id", "message", "own").agg(
        F.sort_array(F.collect_list(F.struct("seq", "op", "role", "text"))).alias("e"),
        F.count_if(F.col("op") != "post").alias("others"),
    )
    last_base = F.greatest(
        F.array_max(F.transform("e", lambda x, i: F.when(x["op"] != "delta", i).otherwise(F.lit(0)))), F.lit(0)
    )
    live = F.expr("slice(e, base + 1, size(e))")
    one = F.array(F.struct(
        F.expr("e[base].role").alias("role"),
        F.array_join(F.transform(live, lambda x: x["text"]), "").alias("text"),
    ))
    many = F.transform("e", lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text")))
    return (
        grouped.withColumn("base", last_base)
        .select("conv_id", "message", "own", F.posexplode(F.when(F.col("others") > 0, one).otherwise(many)).alias("at", "m"))
        .select("conv_id", "message", F.struct("own", "at").alias("part"), "m.role", "m.text")
    )


def render(messages: DataFrame, trained_role: str = "assistant", chunk: int = 64) -> DataFrame:
    """(conv_id, formatted): the messages in order; those of ``trained_role`` are under the loss mask."""
    mark = F.when(F.col("role") == trained_role, F.lit(LOSS)).otherwise(F.lit(TEXT))
    turn = F.concat(F.lit(OPEN), escape(F.col("role")), mark, escape(F.col("text")), F.lit(CLOSE))
    runs = (
        messages.select("conv_id", F.floor(F.col("message") / chunk).alias("run"), F.struct("message", "part", turn.alias("t")).alias("m"))
        .groupBy("conv_id", "run")
        .agg(F.array_join(F.transform(F.sort_array(F.collect_list("m")), lambda x: x["t"]), "").alias("t"))
    )
    return runs.groupBy("conv_id").agg(
        F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("run", "t"))), lambda x: x["t"]), "").alias("formatted")
    )


def parse(formatted: DataFrame) -> DataFrame:
    """(conv_id, formatted, turns array<struct<role,text,loss>>), from the formatted string alone."""
    pieces = F.filter(F.split("formatted", CLOSE), lambda x: x != "")

    def turn(x: Column) -> Column:
        loss = F.instr(x, F.lit(LOSS)) > 0
        cut = F.when(loss, F.lit(LOSS)).otherwise(F.lit(TEXT))
        head = F.substring_index(x, LOSS, 1)
        role = F.when(loss, head).otherwise(F.substring_index(x, TEXT, 1))
        return F.struct(
            unescape(F.replace(role, F.lit(OPEN), F.lit(""))).alias("role"),
            unescape(F.substring(x, F.instr(x, cut) + F.length(cut), F.length(x))).alias("text"),
            loss.alias("loss"),
        )

    return formatted.select("conv_id", "formatted", F.transform(pieces, turn).alias("turns"))


def log_of_turns(conversations: DataFrame) -> DataFrame:
    """A table of plain turns as the log that could have led to them.

    By a hash of conversation and turn a message is posted whole, streamed in three parts, posted as
    a draft and edited, or begun, regenerated and streamed to its end. Rows that share a turn are
    messages of their own, numbered by role and text.
    """
    same = Window.partitionBy("conv_id", "turn").orderBy("role", "text")
    third = F.ceil(F.length("text") / 3).cast("int")

    def event(op: str, text: Column) -> Column:
        return F.struct(F.lit(op).alias("op"), text.alias("text"))

    def cut(first: int, last: int | None = None) -> Column:
        return F.substring("text", 1 + first * third, F.length("text") if last is None else (last - first) * third)

    whole = F.col("text")
    ways = [
        [event("post", whole)],
        [event("post", cut(0, 1)), event("delta", cut(1, 2)), event("delta", cut(2))],
        [event("post", F.reverse(whole)), event("edit", whole)],
        [event("post", cut(1, 2)), event("delta", cut(0, 1)), event("regenerate", cut(0, 1)), event("delta", cut(1))],
    ]
    way = F.pmod(F.xxhash64("conv_id", "turn"), F.lit(len(ways)))
    events = F.array(*ways[0])
    for i, w in enumerate(ways[1:], 1):
        events = F.when(way == i, F.array(*w)).otherwise(events)
    turns = conversations.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return (
        turns.withColumn("part", F.row_number().over(same))
        .select("conv_id", F.col("turn").alias("message"), "part", "role", F.posexplode(events).alias("seq", "e"))
        .select("conv_id", "message", "part", "seq", "e.op", "role", "e.text")
    )


def digests(parsed: DataFrame) -> DataFrame:
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join(F.transform(F.filter("turns", lambda t: t["loss"]), lambda t: t["text"]), "")
    return (
        parsed.select("conv_id", F.size("turns").cast("long").alias("n_turns"), said.alias("said"), loss.alias("loss"), F.length("formatted").cast("long").alias("formatted_chars"))
        .select(
            "conv_id", "n_turns", F.sha2("said", 256).alias("turns_sha256"),
            F.length("loss").cast("long").alias("loss_chars"), F.sha2("loss", 256).alias("loss_sha256"), "formatted_chars",
        )
    )
