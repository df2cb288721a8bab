"""Chat formatting from event logs, with DataFrame functions alone.

A log holds events of conversations: ``message`` sets a turn's text, ``delta`` appends to it, ``edit`` replaces it, and
``regenerate`` starts it anew with the event's own text, which may be empty. Events are folded by turn, turns are ordered within their
conversation, and the conversation is rendered. Control strings inside texts and roles get a backslash after
their first character, and backslashes become ``\\b``, so the rendering can be read back exactly.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

OPEN, BODY, SHUT, STOP = "<s>", "[INST]", "[/INST]", "</s>"


def escape(c: Column) -> Column:
    return F.regexp_replace(F.replace(c, F.lit("\\"), F.lit("\\b")), r"([<\[])(?=s>|/s>|INST\]|/INST\])", r"$1\\")


def unescape(c: Column) -> Column:
    return F.replace(F.regexp_replace(c, r"\\(?=[s/I])", ""), F.lit("\\b"), F.lit("\\"))


def fold(events: DataFrame) -> DataFrame:
    """(conv_id, turn, role, text) from (conv_id, turn, seq, kind, role, text), one row per turn.

    The role is that of the turn's first event. Null text is empty, null kind is a message; equal ``seq`` is settled by
    kind, then text. A turn whose events are deltas only starts empty.
    """
    e = F.struct(F.col("seq"), F.coalesce("kind", F.lit("message")).alias("kind"), F.coalesce("text", F.lit("")).alias("text"), F.coalesce("role", F.lit("")).alias("role"))
    g = events.groupBy("conv_id", "turn").agg(F.sort_array(F.collect_list(e)).alias("log"))
    text = F.aggregate("log", F.lit(""), lambda at, x: F.when(x["kind"] == "delta", F.concat(at, x["text"])).otherwise(x["text"]))
    return g.select("conv_id", "turn", F.element_at("log", 1)["role"].alias("role"), text.alias("text"))


def as_events(messages: DataFrame) -> DataFrame:
    """Rows (conv_id, turn, role, text) as the event log that a chat service would have kept of them; its fold is the rows again.

    Turns are numbered anew by turn, role and text, so that rows that repeat one stay apart. By a fixed rule, turns 3, 6, ... are
    streamed (an empty message, then both halves as deltas), turns 1, 4, ... are edited (a message of the first half, then an
    edit to the whole text), and turns 2, 5, ... are regenerated (a message of the second half, a new start, then a delta).
    """
    text = F.coalesce("text", F.lit(""))
    order = Window.partitionBy("conv_id").orderBy(F.col("turn").asc_nulls_first(), F.coalesce("role", F.lit("")), text)
    rows = messages.select("conv_id", F.row_number().over(order).cast("long").alias("turn"), "role", text.alias("text"))
    half = F.floor(F.length("text") / 2).cast("int")
    head, tail = F.substring("text", F.lit(1), half), F.substring("text", half + 1, F.lit(2**31 - 1))

    def event(kind: str, text: Column) -> Column:
        return F.struct(F.lit(kind).alias("kind"), text.alias("text"))

    kept = F.when(F.col("turn") % 3 == 0, F.array(event("message", F.lit("")), event("delta", head), event("delta", tail)))
    kept = kept.when(F.col("turn") % 3 == 1, F.array(event("message", head), event("edit", F.col("text"))))
    kept = kept.otherwise(F.array(event("message", tail), event("regenerate", F.lit("")), event("delta", F.col("text"))))
    log = rows.select("conv_id", "turn", "role", F.posexplode(kept).alias("at", "event"))
    return log.select("conv_id", "turn", (F.col("turn") * 10 + F.col("at")).alias("seq"), "event.kind", "role", "event.text")


def render(messages: DataFrame, trained_role: str = "assistant") -> DataFrame:
    """(conv_id, formatted, loss_spans) from (conv_id, turn, role, text); loss_spans: (start, length) in code points.

    Null roles and texts count as empty. Rows that repeat a turn are all kept, ordered by role and text. A null
    conv_id is a conversation of its own. Other columns are not read.
    """
    t = messages.select("conv_id", F.struct(F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("m"))
    g = t.groupBy("conv_id").agg(F.sort_array(F.collect_list("m")).alias("turns"))
    shown = F.transform(
        "turns",
        lambda m: F.struct(
            F.concat(F.lit(OPEN), escape(m["role"]), F.lit(BODY)).alias("head"),
            escape(m["text"]).alias("body"),
            F.lit(SHUT + STOP).alias("tail"),
            (m["role"] == trained_role).alias("trained"),
        ),
    )
    g = g.select("conv_id", shown.alias("shown"))
    spans = F.aggregate(
        "shown",
        F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:bigint,length:bigint>>").alias("spans")),
        lambda a, x: F.struct(
            (a["at"] + F.length(x["head"]) + F.length(x["body"]) + F.length(x["tail"])).alias("at"),
            F.when(x["trained"], F.concat(a["spans"], F.array(F.struct((a["at"] + F.length(x["head"])).alias("start"), F.length(x["body"]).cast("long").alias("length"))))).otherwise(a["spans"]).alias("spans"),
        ),
        lambda a: a["spans"],
    )
    return g.select("conv_id", F.array_join(F.transform("shown", lambda x: F.concat(x["head"], x["body"], x["tail"])), "").alias("formatted"), spans.alias("loss_spans"))


def read_back(formatted: DataFrame) -> DataFrame:
    """(conv_id, turns array<struct<role, text>>, loss_text, formatted) from what ``render`` made."""
    part = F.split("formatted", r"\[/INST\]</s>")
    turns = F.transform(
        F.slice(part, 1, F.size(part) - 1),
        lambda p: F.struct(
            unescape(F.substring_index(F.substring(p, len(OPEN) + 1, 2**31 - 1), BODY, 1)).alias("role"),
            unescape(F.substring(p, F.instr(p, BODY) + len(BODY), F.lit(2**31 - 1))).alias("text"),
        ),
    )
    loss = F.array_join(F.transform("loss_spans", lambda s: unescape(F.substring("formatted", (s["start"] + 1).cast("int"), s["length"].cast("int")))), "")
    return formatted.select("conv_id", turns.alias("turns"), loss.alias("loss_text"), "formatted")


def digest(back: DataFrame) -> DataFrame:
    joined = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(joined, 256).alias("turns_sha256"),
        F.length("loss_text").cast("long").alias("loss_chars"),
        F.sha2("loss_text", 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )
