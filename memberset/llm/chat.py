"""Chat formatting from an event log, with DataFrame functions only.

Events (conv_id, turn, seq, kind, role, text) are folded per message in order of seq: ``delta`` appends its text,
``edit`` replaces what there is, ``regenerate`` drops it so that later deltas start anew. Events
before the last edit or regeneration of a message cannot show, so the fold is: find that point by a
partial aggregate's worth of window, then join the texts from there on.

Template: ``<s>``, then per turn a mark (``[SYS]``, ``[INST]``, ``[OUT]``, or ``[ROLE]name[/ROLE]``),
the text and ``</s>``. In texts and names, ``<``, ``[`` and ``\\`` are followed by a ``\\``, so no
control string can arise inside a text and unescaping is exact. Loss spans are code point ranges of
the assistant texts in the formatted string.

Defined results: null text or role = empty; ties of turn go by role and text, null turns come first; repeated rows are
turns of their own; a null conv_id is a conversation of its own; empty tables give no rows; extra
columns are ignored. One conversation is one string, so its messages meet in one task (its event
streams do not: they are folded per message first).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

OPEN, END = "<s>", "</s>"
MARKS = {"system": "[SYS]", "user": "[INST]", "assistant": "[OUT]"}


def escape(c: Column) -> Column:
    return F.regexp_replace(c, r"([<\[\\])", r"$1\\")


def unescape(c: Column) -> Column:
    return F.regexp_replace(c, r"([<\[\\])\\", "$1")


def fold_events(events: DataFrame) -> DataFrame:
    """Event log -> (conv_id, turn, row, role, text): the final messages."""
    of_message = Window.partitionBy("conv_id", "turn", "row")
    resets = F.when(F.col("kind").isin("edit", "regenerate"), F.col("seq"))
    live = events.withColumn("since", F.max(resets).over(of_message)).where("since is null or seq >= since")
    piece = F.struct("seq", F.when(F.col("kind") == "regenerate", F.lit("")).otherwise(F.coalesce("text", F.lit(""))).alias("t"))
    folded = live.groupBy("conv_id", "turn", "row").agg(F.max_by("role", "seq").alias("role"), F.sort_array(F.collect_list(piece)).alias("pieces"))
    return folded.select("conv_id", "turn", "row", "role", F.array_join(F.transform("pieces", lambda p: p["t"]), "").alias("text"))


def as_events(conversations: DataFrame) -> DataFrame:
    """Final messages (conv_id, turn, role, text) as a log that ends in them.

    By a hash of its place a message is streamed in two deltas; or a draft is edited and goes on; or it is begun,
    regenerated and streamed anew. Folding the log gives the messages back.
    """
    same = Window.partitionBy("conv_id", "turn").orderBy("role", "text")
    text = F.coalesce("text", F.lit(""))
    half = F.floor(F.char_length(text) / 2).cast("int")
    left, right = F.substring(text, F.lit(1), half), F.substring(text, half + 1, F.char_length(text))

    def log(*steps):
        return F.array(*[F.struct(F.lit(i).cast("long").alias("seq"), F.lit(kind).alias("kind"), piece.cast("string").alias("text")) for i, (kind, piece) in enumerate(steps)])

    way = F.pmod(F.xxhash64("conv_id", "turn"), F.lit(3))
    streamed = log(("delta", left), ("delta", right))
    edited = log(("delta", right), ("edit", left), ("delta", right))
    anew = log(("delta", left), ("regenerate", F.lit(None)), ("delta", left), ("delta", right))
    event = F.explode(F.when(way == 0, streamed).when(way == 1, edited).otherwise(anew)).alias("event")
    rows = conversations.select("conv_id", "turn", F.row_number().over(same).alias("row"), "role", "text")
    return rows.select("conv_id", "turn", "row", "role", event).select("conv_id", "turn", "row", "event.seq", "event.kind", "role", "event.text")


def render(messages: DataFrame) -> DataFrame:
    """Messages -> (conv_id, n_turns, formatted, loss array<struct<start, stop>>)."""
    role = F.coalesce("role", F.lit(""))
    mark = F.coalesce(*[F.when(role == k, F.lit(m)) for k, m in MARKS.items()], F.concat(F.lit("[ROLE]"), escape(role), F.lit("[/ROLE]")))
    turns = messages.select("conv_id", "turn", "row", mark.alias("mark"), escape(F.coalesce("text", F.lit(""))).alias("body"), (role == "assistant").alias("learn"))
    width = F.char_length("mark") + F.char_length("body") + len(END)
    order = Window.partitionBy("conv_id").orderBy("turn", "row")
    stop = F.sum(width.cast("long")).over(order.rowsBetween(Window.unboundedPreceding, 0)) + len(OPEN) - len(END)
    placed = turns.withColumn("stop", stop).withColumn("start", F.col("stop") - F.char_length("body"))
    item = F.struct("start", "stop", "learn", F.concat("mark", "body", F.lit(END)).alias("out"))
    whole = placed.groupBy("conv_id").agg(F.sort_array(F.collect_list(item)).alias("turns"))
    span = F.transform(F.filter("turns", lambda t: t["learn"]), lambda t: F.struct(t["start"].alias("start"), t["stop"].alias("stop")))
    text = F.concat(F.lit(OPEN), F.array_join(F.transform("turns", lambda t: t["out"]), ""))
    return whole.select("conv_id", text.alias("formatted"), span.alias("loss"))


def read_back(formatted: DataFrame) -> DataFrame:
    """formatted, loss -> the same with turns array<struct<role, text>> and learned (all text under the mask), both parsed."""
    body = F.expr(f"substring(formatted, {len(OPEN) + 1})")
    pieces = F.filter(F.split(body, END), lambda x: x != "")

    def parse(x: Column) -> Column:
        known = F.coalesce(*[F.when(F.startswith(x, F.lit(m)), F.struct(F.lit(k).alias("role"), F.lit(len(m)).alias("skip"))) for k, m in MARKS.items()])
        name = F.regexp_extract(x, r"(?s)^\[ROLE\](.*?)\[/ROLE\]", 1)
        other = F.struct(unescape(name).alias("role"), (F.char_length(name) + len("[ROLE][/ROLE]")).alias("skip"))
        head = F.coalesce(known, other)
        return F.struct(head["role"].alias("role"), unescape(F.substring(x, head["skip"] + 1, F.char_length(x))).alias("text"))

    masked = F.transform("loss", lambda s: unescape(F.substring(F.col("formatted"), (s["start"] + 1).cast("int"), (s["stop"] - s["start"]).cast("int"))))
    return formatted.withColumn("turns", F.transform(pieces, parse)).withColumn("learned", F.array_join(masked, ""))


def format_log(events: DataFrame) -> DataFrame:
    """Event log -> (conv_id, formatted, loss)."""
    return render(fold_events(events))
