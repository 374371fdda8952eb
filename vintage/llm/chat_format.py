"""Operator 4: chat formatting by event-sourced reconstruction.

A conversation is a log. Events of one message are folded in the order of their
sequence numbers: ``message``, ``edit`` and ``regenerate`` set its text anew,
``delta`` appends to it, ``delete`` removes the message. What the fold leaves is
rendered with a template that marks turns and escapes control strings inside
roles and texts by a backslash, which parsing takes away again.

A log is grouped by conversation, since one conversation is one output row; no
other key is ever grouped. Defined cases: a null text is empty, a null role is
empty, ties in the sequence are broken by kind, role and text, repeated events
count as often as they stand, events without a conversation id form one
conversation each, an unknown kind sets the text like ``message``, a null turn
comes first, an empty log gives an empty result. Plain rows that share a turn
stay separate messages, ordered by role and a digest of the text.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

OPEN, CLOSE, MARK = "<|turn|>", "<|end|>\n", "\\"
#: Strings that this or other public chat templates read as control.
CONTROL = ["<|", "</s>", "<s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>"]
ESCAPED = re.compile(r"\\(.)", re.S)
TURN = re.compile(r"<\|turn\|>((?:[^\n\\]|\\.)*)\n(.*?)<\|end\|>\n", re.S)


def escape(text: str) -> str:
    text = text.replace(MARK, MARK * 2)
    for c in CONTROL:
        text = text.replace(c, c[0] + MARK + c[1:])
    return text


def escape_role(role: str) -> str:
    return escape(role).replace("\n", MARK + "\n")


def unescape(text: str) -> str:
    return ESCAPED.sub(r"\1", text) if MARK in text else text


def render(turns: list[tuple[str, str]]) -> tuple[str, list[tuple[int, int]]]:
    """The formatted conversation and the spans that a loss is taken on: assistant texts."""
    parts, at, spans = [], 0, []
    for role, text in turns:
        head, body = f"{OPEN}{escape_role(role)}\n", escape(text)
        if role == "assistant":
            spans.append((at + len(head), at + len(head) + len(body)))
        parts += (head, body, CLOSE)
        at += len(head) + len(body) + len(CLOSE)
    return "".join(parts), spans


def parse(formatted: str) -> list[tuple[str, str]]:
    return [(unescape(r), unescape(t)) for r, t in TURN.findall(formatted)]


def fold(events: list[tuple]) -> list[tuple[str, str]]:
    """Final (role, text) of every message from (turn, message, seq, kind, role, text) in order."""
    out: dict = {}
    for turn, message, _, kind, role, text in events:
        key = turn, message
        had = out.pop(key, None) if kind == "delete" else out.get(key)
        if kind == "delete":
            continue
        if kind == "delta" and had:
            had[1].append(text or "")
        else:
            out[key] = (role if role is not None else had[0] if had else "", [text or ""])
    # Events come sorted by turn and message, so messages stand in order of their first event.
    return [(r, "".join(t)) for r, t in out.values()]


def events_of(rows: DataFrame, piece: int = 400) -> DataFrame:
    """A log of plain rows (conv_id, turn, role, text): the first piece opens a message, the others stream in."""
    text = F.coalesce(F.col("text"), F.lit(""))
    # A row without a conversation is one by itself and streams nothing: no other row could be told to belong to it.
    alone = F.col("conv_id").isNull()
    count = F.when(alone, 1).otherwise(F.greatest(F.lit(1), F.ceil(F.char_length(text) / piece).cast("int")))
    cut = F.transform(F.sequence(F.lit(0), count - 1), lambda i: F.struct(i.alias("part"), F.when(alone, text).otherwise(F.substring(text, i * piece + 1, F.lit(piece))).alias("text")))
    # Rows that share a turn are several messages, so each row has a message key of its own. Its number only
    # tells equal rows apart, which may change places freely, so it need not be the same when a task runs again.
    message = F.concat_ws("/", F.coalesce("role", F.lit("")), F.md5(text.cast("binary")), F.lpad(F.monotonically_increasing_id().cast("string"), 19, "0"))
    keyed = rows.select("conv_id", "turn", "role", message.alias("message"), cut.alias("cut"))
    flat = keyed.select("conv_id", "turn", "message", "role", F.inline("cut").alias("part", "text"))
    return flat.select("conv_id", "turn", "message", F.col("part").cast("long").alias("seq"), F.when(F.col("part") == 0, "message").otherwise("delta").alias("kind"), "role", "text")


def format_chats(events: DataFrame) -> DataFrame:
    """(conv_id, formatted, loss_spans) from a log (conv_id, turn, message, seq, kind, role, text)."""
    event = F.struct("turn", "message", "seq", "kind", "role", "text")
    # Events without a conversation need no grouping, and so no id made up for them.
    alone = events.where("conv_id is null").select("conv_id", F.array(event).alias("log"))
    grouped = events.where("conv_id is not null").groupBy("conv_id").agg(F.sort_array(F.collect_list(event)).alias("log")).union(alone)
    kind = dict(events.dtypes)["conv_id"]

    def run(batches):
        for b in batches:
            done = [render(fold([tuple(e.values()) for e in log])) for log in b.column("log").to_pylist()]
            spans = pa.array([[{"start": s, "end": e} for s, e in x] for _, x in done], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
            yield pa.RecordBatch.from_arrays([b.column("conv_id"), pa.array([x for x, _ in done], pa.string()), spans], ["conv_id", "formatted", "loss_spans"])

    return grouped.mapInArrow(run, f"conv_id {kind}, formatted string, loss_spans array<struct<start:bigint,end:bigint>>")
