"""Conversations rebuilt from event logs and rendered for training.

DataFrame functions only. A log's rows are ``conv_id, seq, event, message_id, role, text``:
``message`` starts a message, ``delta`` adds to its text, ``edit`` replaces
it, ``regenerate`` empties it (deltas follow) and ``delete`` drops it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

START, END = "<|im_start|>", "<|im_end|>"
LOSS_ROLE = "assistant"


def escape(text: Column) -> Column:
    """No control string is left in the result; ``unescape`` gives the text back."""
    return F.replace(F.replace(text, F.lit("&"), F.lit("&amp;")), F.lit("<|"), F.lit("&lt;|"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("&lt;|"), F.lit("<|")), F.lit("&amp;"), F.lit("&"))


def escape_role(role: Column) -> Column:
    return F.replace(escape(role), F.lit("\n"), F.lit("&#10;"))


def unescape_role(role: Column) -> Column:
    return unescape(F.replace(role, F.lit("&#10;"), F.lit("\n")))


def fold(events: DataFrame) -> DataFrame:
    """Final messages: ``conv_id, position, role, text``.

    A message stands where its first event does; its role is that of its last
    ``message`` event, or of its first event. Null text counts as empty and null role as ``""``;
    events without a sequence number come first; events of one
    number go in the order of event, role and text; deltas before any start count as a start.
    Each step groups by message, so a long conversation is folded by many tasks.
    """
    e = events.select("conv_id", F.col("seq").cast("long").alias("seq"), F.coalesce("event", F.lit("message")).alias("event"), "message_id", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    one = F.struct("seq", "event", "role", "text")
    resets = F.col("event").isin("message", "edit", "regenerate", "delete")
    whole = Window.partitionBy("conv_id", "message_id")
    last = e.withColumn("reset", F.max(F.when(resets, one)).over(whole)).withColumn("named", F.max(F.when(F.col("event") == "message", one)).over(whole)).withColumn("first", F.min(one).over(whole))
    live = last.filter(F.col("reset").isNull() | (one >= F.col("reset")))
    text = F.when(F.col("event") == "regenerate", F.lit("")).otherwise(F.col("text"))
    parts = live.groupBy("conv_id", "message_id").agg(F.max("reset").alias("reset"), F.max("named").alias("named"), F.max("first").alias("first"), F.sort_array(F.collect_list(F.struct("seq", "event", "role", text.alias("text")))).alias("parts"))
    kept = parts.filter(F.col("reset").isNull() | (F.col("reset.event") != "delete"))
    return kept.select("conv_id", F.struct(F.col("first.seq"), F.col("message_id")).alias("position"), F.coalesce("named.role", "first.role").alias("role"), F.array_join(F.transform("parts", lambda p: p["text"]), "").alias("text"))


def render(messages: DataFrame) -> DataFrame:
    """``conv_id, segments, formatted``: segments are (text, loss) in order, and
    formatted is their texts together. The loss mask covers exactly the escaped
    texts of assistant messages.

    A conversation's output is one value, so its messages meet in one row; what comes
    before (folding, escaping) is done message by message.
    """
    pieces = messages.select("conv_id", F.struct("position", F.concat(F.lit(START), escape_role(F.col("role")), F.lit("\n")).alias("head"), escape(F.col("text")).alias("body"), (F.col("role") == LOSS_ROLE).alias("loss")).alias("m"))
    grouped = pieces.groupBy("conv_id").agg(F.sort_array(F.collect_list("m")).alias("ms"))
    segments = F.flatten(F.transform("ms", lambda m: F.array(F.struct(m["head"].alias("text"), F.lit(False).alias("loss")), F.struct(m["body"].alias("text"), m["loss"].alias("loss")), F.struct(F.lit(END + "\n").alias("text"), F.lit(False).alias("loss")))))
    return grouped.select("conv_id", segments.alias("segments")).withColumn("formatted", F.array_join(F.transform("segments", lambda s: s["text"]), ""))


def format_log(events: DataFrame) -> DataFrame:
    """Event log -> one rendered row per conversation (see ``fold`` and ``render``)."""
    return render(fold(events))


def turns(formatted: Column) -> Column:
    """Read back (role, text) of each message from a rendered conversation."""
    blocks = F.filter(F.split(formatted, r"<\|im_end\|>\n"), lambda b: b.startswith(START))

    def one(block: Column) -> Column:
        body = F.substring(block, F.lit(len(START) + 1), F.length(block))
        cut = F.instr(body, "\n")
        return F.struct(unescape_role(F.substring(body, F.lit(1), cut - 1)).alias("role"), unescape(F.substring(body, cut + 1, F.length(body))).alias("text"))

    return F.transform(blocks, one)


def loss_text(segments: Column) -> Column:
    """All text under the loss mask, unescaped."""
    return F.array_join(F.transform(F.filter(segments, lambda s: s["loss"]), lambda s: unescape(s["text"])), "")


def log_of_turns(conversations: DataFrame) -> DataFrame:
    """A finished table (conv_id, turn, role, text) as a log of one event a message."""
    nth = F.row_number().over(Window.partitionBy("conv_id").orderBy("turn", "role", "text"))
    return conversations.select("conv_id", nth.alias("seq"), F.lit("message").alias("event"), nth.cast("string").alias("message_id"), "role", "text")


def streamed(log: DataFrame) -> DataFrame:
    """A log of finished messages as a service would have written it: an assistant's message is a draft that is regenerated in
    two deltas, a user's message is a draft that is edited, any other one comes in two parts. Folding gives the finished
    messages back."""
    text = F.coalesce("text", F.lit(""))
    half = F.floor(F.length(text) / 2).cast("int")
    front, back = F.substring(text, F.lit(1), half), F.substring(text, half + 1, F.length(text))

    def event(name: str, part: Column) -> Column:
        return F.struct(F.lit(name).alias("event"), part.alias("text"))

    answer = F.array(event("message", back), event("regenerate", F.lit("")), event("delta", front), event("delta", back))
    question = F.array(event("message", front), event("edit", text))
    other = F.array(event("message", front), event("delta", back))
    events = F.when(F.col("role") == LOSS_ROLE, answer).when(F.col("role") == "user", question).otherwise(other)
    out = log.filter("event = 'message'").select("conv_id", "seq", "message_id", "role", F.posexplode(events).alias("at", "e"))
    return out.select("conv_id", (F.col("seq") * 4 + F.col("at")).alias("seq"), F.col("e.event"), "message_id", "role", F.col("e.text"))


def sha256(text: Column) -> Column:
    return F.sha2(F.encode(text, "UTF-8"), 256)
