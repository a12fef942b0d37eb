"""Chat formatting by event-sourced reconstruction (native).

An event log holds, per conversation and in sequence: ``message`` (opens a
message), ``delta`` (appends to it), ``edit`` and ``regenerate`` (replace its
text; deltas that follow append again). Logs are partitioned by conversation,
sorted by sequence, folded into final messages and rendered with a reversible
template and a loss mask over the assistant texts.

Template: ``<turn:role>\\ntext</turn>\\n``. Inside roles and texts ``\\``, ``<``
and ``>`` become ``\\e``, ``\\l`` and ``\\g``, so no marker can occur there, and
unescaping restores every string.

Scale: a conversation is one output string, so it is folded and rendered by one
task; events are partly aggregated per message first. Offsets are code points.

Defined results: null texts count as empty and null roles as the empty role;
conversations of any length up to the engine's limit of 2 GB a string; extra
columns are ignored; events of a null conversation form one conversation of their own; equal
sequence numbers are ordered by kind, role and text, so reruns agree; deltas
before the first ``message`` of their key open it; an empty log renders nothing.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

OPEN, HEAD_END, CLOSE = "<turn:", ">\n", "</turn>\n"
_CODES = (("\\", "\\e"), ("<", "\\l"), (">", "\\g"))


def escape(text: Column) -> Column:
    for raw, code in _CODES:
        text = F.replace(text, F.lit(raw), F.lit(code))
    return text


def unescape(text: Column) -> Column:
    for raw, code in reversed(_CODES):
        text = F.replace(text, F.lit(code), F.lit(raw))
    return text


def fold(events: DataFrame) -> DataFrame:
    """Final messages ``conv_id, seq, role, text`` of ``conv_id, seq, kind, msg, role, text``.

    ``msg`` names the message within its conversation. The message takes the
    role and place of its first event and the text folded over all of them.
    """
    e = events.select("conv_id", "msg", F.struct("seq", "kind", "role", F.coalesce("text", F.lit("")).alias("text")).alias("e"))
    whole = e.repartition("conv_id").groupBy("conv_id", "msg").agg(F.sort_array(F.collect_list("e")).alias("log"))
    text = F.array_join(
        F.transform(
            F.slice(
                "log",
                F.greatest(
                    F.lit(1),
                    F.array_max(F.transform("log", lambda x, i: F.when(x["kind"] != "delta", i + 1).otherwise(1))),
                ),
                F.size("log"),
            ),
            lambda x: x["text"],
        ),
        "",
    )
    first = F.element_at("log", 1)
    return whole.select("conv_id", first["seq"].alias("seq"), "msg", F.coalesce(first["role"], F.lit("")).alias("role"), text.alias("text"))


def render(messages: DataFrame) -> DataFrame:
    """One row per conversation: ``n_turns``, ``formatted`` and ``loss_spans``.

    ``loss_spans`` lists (start, length) in code points of the escaped
    assistant texts inside ``formatted``; offsets come from a running sum.
    """
    m = messages.withColumns(
        {"head": F.concat(F.lit(OPEN), escape(F.col("role")), F.lit(HEAD_END)), "body": escape(F.col("text"))}
    ).withColumn("piece", F.concat("head", "body", F.lit(CLOSE)))
    order = W.partitionBy("conv_id").orderBy("seq", "msg")
    before = F.coalesce(F.sum(F.length("piece").cast("long")).over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    m = m.withColumn("start", before + F.length("head"))
    turns = m.groupBy("conv_id").agg(
        F.sort_array(
            F.collect_list(F.struct("seq", "msg", "piece", "start", F.length("body").cast("long").alias("length"), "role"))
        ).alias("t")
    )
    loss = F.filter("t", lambda x: x["role"] == "assistant")
    return turns.select(
        "conv_id",
        F.size("t").cast("long").alias("n_turns"),
        F.array_join(F.transform("t", lambda x: x["piece"]), "").alias("formatted"),
        F.transform(loss, lambda x: F.struct(x["start"].alias("start"), x["length"].alias("length"))).alias("loss_spans"),
    )


def parse(formatted: Column) -> Column:
    """Turns (role, text) read back from a formatted conversation."""
    pieces = F.filter(F.split(formatted, CLOSE, -1), lambda p: p != "")

    def turn(p: Column) -> Column:
        head = F.substring_index(p, HEAD_END, 1)
        body = F.substr(p, F.length(head) + F.lit(len(HEAD_END) + 1))
        return F.struct(unescape(F.substr(head, F.lit(len(OPEN) + 1))).alias("role"), unescape(body).alias("text"))

    return F.transform(pieces, turn)


def loss_text(formatted: Column, spans: Column) -> Column:
    """The text under the loss mask, unescaped, nothing between: what the spans cut out of a formatted conversation."""
    pieces = F.transform(spans, lambda s: F.substr(formatted, (s["start"] + 1).cast("int"), s["length"].cast("int")))
    return unescape(F.array_join(pieces, ""))


def events_of_rows(rows: DataFrame) -> DataFrame:
    """A log with one ``message`` event per row of ``conv_id, turn, role, text``.

    Rows of a conversation are numbered by turn, then role and text, so two
    rows of one turn stay two messages.
    """
    order = W.partitionBy("conv_id").orderBy("turn", "role", "text")
    numbered = rows.select("conv_id", F.row_number().over(order).cast("long").alias("msg"), "role", "text")
    return numbered.select("conv_id", F.col("msg").alias("seq"), F.lit("message").alias("kind"), "msg", "role", "text")


def drafted_events_of_rows(rows: DataFrame) -> DataFrame:
    """A log as a chat service leaves it, whose fold is that of ``events_of_rows``.

    Every message is opened, streamed on, replaced (assistants regenerate,
    others edit) by the first half of its text, and streamed to its end.
    """
    whole = events_of_rows(rows)
    text = F.coalesce("text", F.lit(""))
    half = F.floor(F.length(text) / 2).cast("int")
    steps = [
        ("message", F.lit("draft ")),
        ("delta", F.concat(F.lit("of "), F.coalesce("role", F.lit("")))),
        (F.when(F.col("role") == "assistant", "regenerate").otherwise("edit"), F.substr(text, F.lit(1), half)),
        ("delta", F.substr(text, half + 1)),
    ]
    log = [
        F.struct((4 * F.col("msg") + i).alias("seq"), (F.lit(kind) if isinstance(kind, str) else kind).alias("kind"), "msg", "role", t.alias("text"))
        for i, (kind, t) in enumerate(steps)
    ]
    return whole.select("conv_id", F.inline(F.array(*log)))


def format_log(events: DataFrame) -> DataFrame:
    """Fold and render an event log."""
    return render(fold(events))
