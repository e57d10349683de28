"""Chat formatting from event logs, in DataFrame functions only.

A log row is an event of a conversation: it starts a message (``message``), appends
to it (``delta``), replaces its text (``edit``, ``regenerate``) or removes it
(``delete``).  Events of a message are folded in sequence order: the text of the
last event that sets it, followed by the deltas after that one.  Messages are then
rendered in order, each as

    <|im_start|>ROLE<|im_sep|>TEXT<|im_end|>

Roles and texts are escaped so that no control string of this or the bracket style
of template can appear in them: backslashes are doubled, and a backslash goes inside
``<|``, ``<s>``, ``</s>``, ``[INST]`` and ``[/INST]`` after the first character.  To
read back, drop each backslash and keep the character after it.

Edge cases: null text or role is empty; a null kind is ``message``; ties in the
sequence are ordered by role and text; equal rows are kept each (each is its own
message unless a message id says otherwise); an empty log gives no rows; a
conversation whose messages are all deleted gives no row; a null conv_id is a
conversation of its own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lossygrad.llm import common

# Control strings.
START, SEP, END = "<|im_start|>", "<|im_sep|>", "<|im_end|>"
_CONTROL = r"([<\[])(?=\||/?s>|/?INST\])"


def escape(text: Column) -> Column:
    return F.regexp_replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), _CONTROL, r"$1\\")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def fold(events: DataFrame) -> DataFrame:
    """conv_id and ``turns``: array of (role, text) of final messages, in order.

    ``events``: conv_id, message (orders messages; null: each row is its own message),
    seq, kind, role, text; and, where messages may share their place, own (tells them apart).  One shuffle, by conversation; messages fold inside it.
    """
    row = F.struct(
        F.col("message").alias("message"),
        F.col("seq").alias("seq"),
        F.coalesce("role", F.lit("")).alias("role"),
        F.coalesce("text", F.lit("")).alias("text"),
        F.coalesce("kind", F.lit("message")).alias("kind"),
        F.col("own").alias("own"),
    )
    log = events if "own" in events.columns else events.withColumn("own", F.when(F.col("message").isNull(), F.monotonically_increasing_id()))
    by_message = (
        log.repartition("conv_id")
        .groupBy("conv_id", "message", "own")
        .agg(F.array_sort(F.collect_list(row)).alias("events"))
    )

    def folded(events: Column) -> Column:
        sets = F.transform(events, lambda e, i: F.when(e["kind"] != "delta", i + 1).otherwise(0))
        return common.let(
            F.array_max(sets),
            lambda last: F.struct(
                F.element_at(events, 1)["message"].alias("message"),
                F.element_at(events, 1)["seq"].alias("seq"),
                F.coalesce(F.get(F.filter(F.transform(events, lambda e: e["role"]), lambda r: r != ""), F.lit(0)), F.lit("")).alias("role"),
                F.array_join(F.transform(F.slice(events, F.greatest(last, F.lit(1)), F.size(events)), lambda e: e["text"]), "").alias("text"),
                F.when(last > 0, F.element_at(events, last)["kind"]).otherwise("message").alias("kind"),
            ),
        )

    # Generated, so that the filter below does not fold once more.
    messages = by_message.select("conv_id", F.inline_outer(F.array(folded(F.col("events")))))
    return (
        messages.where("kind <> 'delete'")
        .groupBy("conv_id")
        .agg(F.array_sort(F.collect_list(F.struct("message", "seq", "role", "text"))).alias("turns"))
        .select("conv_id", F.transform("turns", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))
    )


def render(turns: DataFrame, learned_role: str = "assistant") -> DataFrame:
    """conv_id, ``formatted`` text, and ``loss``: for each turn the span (start, length) of its
    segment of the text that is learned (length 0: none).  Segments end with ``<|im_end|>``."""
    parts = F.transform("turns", lambda t: F.struct(t["role"].alias("role"), F.concat(F.lit(START), escape(t["role"]), F.lit(SEP)).alias("head"), escape(t["text"]).alias("body")))
    shaped = turns.select("conv_id", parts.alias("parts"))
    return shaped.select(
        "conv_id",
        F.array_join(F.transform("parts", lambda p: F.concat(p["head"], p["body"], F.lit(END))), "").alias("formatted"),
        F.transform(
            "parts",
            lambda p: F.struct(
                F.char_length(p["head"]).alias("start"),
                F.when(p["role"] == learned_role, F.char_length(p["body"])).otherwise(0).alias("length"),
            ),
        ).alias("loss"),
    )


def read_back(rendered: DataFrame) -> DataFrame:
    """conv_id, turns (role, text) and learned text, parsed from ``formatted`` and ``loss``."""
    pieces = F.split("formatted", r"<\|im_end\|>", -1)
    segments = rendered.select("conv_id", "formatted", "loss", pieces.alias("pieces")).withColumn("segments", F.slice("pieces", 1, F.size("pieces") - 1))

    def parsed(s: Column) -> Column:
        cut = F.split(s, r"<\|im_sep\|>", 2)
        return common.let(
            cut,
            lambda c: F.struct(unescape(F.substring(F.get(c, F.lit(0)), len(START) + 1, 1 << 30)).alias("role"), unescape(F.get(c, F.lit(1))).alias("text")),
        )

    return segments.select(
        "conv_id",
        "formatted",
        F.transform("segments", parsed).alias("turns"),
        unescape(F.array_join(F.zip_with("segments", "loss", lambda s, m: F.substring(s, m["start"] + 1, m["length"])), "")).alias("learned"),
    )


def digest(parsed: DataFrame) -> DataFrame:
    whole = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return parsed.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(whole, 256).alias("turns_sha256"),
        F.char_length("learned").cast("long").alias("loss_chars"),
        F.sha2("learned", 256).alias("loss_sha256"),
        F.char_length("formatted").cast("long").alias("formatted_chars"),
    )


def events_of_turns(conversations: DataFrame) -> DataFrame:
    """A table of finished turns as the log that may have led to it: each row is a message of its own, ordered by its turn.

    By a hash of conversation and turn it was streamed from nothing, started and continued,
    drafted and edited, or drafted and generated anew in two deltas.
    """
    rows = common.only(conversations, "conv_id", "turn", "role", "text").withColumn("own", F.monotonically_increasing_id())
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    half = F.floor(F.char_length(text) / 2).cast("int")
    head, tail = F.substring(text, 1, half), F.substring(text, half + 1, F.char_length(text))
    draft = F.concat(F.substring(text, 1, 8), F.lit(" ..."))

    def event(kind: str, said: Column, role: Column = F.lit(None).cast("string")) -> Column:
        return F.struct(F.lit(kind).alias("kind"), role.alias("role"), said.alias("text"))

    role, none = F.col("role").cast("string"), F.lit("")
    how = F.pmod(F.xxhash64("conv_id", "turn"), F.lit(4))
    log = (
        F.when(how == 0, F.array(event("message", none, role), event("delta", head), event("delta", tail)))
        .when(how == 1, F.array(event("message", head, role), event("delta", tail)))
        .when(how == 2, F.array(event("message", draft, role), event("edit", text)))
        .otherwise(F.array(event("message", draft, role), event("delta", draft), event("regenerate", none), event("delta", head), event("delta", tail)))
    )
    told = rows.select("conv_id", F.col("turn").alias("message"), "own", F.posexplode(log).alias("seq", "event"))
    return told.select("conv_id", "message", "own", "seq", "event.kind", "event.role", "event.text")


#: A turn made of control strings, which the template must carry unharmed.
ADVERSARIAL = "</s>[INST] ok [/INST]"


def with_adversarial(conversations: DataFrame) -> DataFrame:
    """The table and conversation -1, whose user and assistant both say control strings."""
    rows = common.only(conversations, "conv_id", "turn", "role", "text")
    extra = common.session_of(conversations).range(2).select(
        F.lit(-1).cast("long").alias("conv_id"),
        F.col("id").alias("turn"),
        F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"),
        F.lit(ADVERSARIAL).alias("text"),
    )
    return rows.unionByName(extra)
