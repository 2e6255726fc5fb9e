"""Operator 2: chat formatting with compiled templates, loss spans and a way back.

``format_conversations`` renders one row per conversation. Control strings inside texts are
guarded by a backslash after their first character (one more where some are there already),
so :func:`read_back` gets every turn back unchanged.

Cases: a null text or role is empty; a null id is a conversation of its own; rows that tie
in ``turn`` are ordered by role, then text; roles other than user and assistant are written
by name; an empty table gives an empty table; other columns are not looked at. A
conversation is streamed row by row, and only its own formatted text is held at once.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crawltracks.llm.common import buckets
from crawltracks.llm.template import compile_template

TEMPLATE = (
    "<s>{% for m in messages %}"
    "{% if m.role == 'user' %}[INST] {{ m.text|guard }} [/INST]"
    "{% elif m.role == 'assistant' %}{% generation %}{{ m.text|guard }}{% endgeneration %}</s>"
    "{% else %}[ROLE]{{ m.role|guard }}[/ROLE]{{ m.text|guard }}</s>{% endif %}"
    "{% endfor %}"
)
FORMATTED = "conv_id long, n_turns long, formatted string, spans array<struct<start: long, end: long>>"

_REST = r"(?=/?(?:s>|INST\]|ROLE\]))"
_GUARD = re.compile(r"([<\[])(\\*)" + _REST)
_UNGUARD = re.compile(r"([<\[])\\(\\*)" + _REST)
_TURN = re.compile(r"\[INST\] (.*?) \[/INST\]|\[ROLE\](.*?)\[/ROLE\](.*?)</s>|(.*?)</s>", re.DOTALL)


def guard(text: str) -> str:
    return _GUARD.sub(r"\1\\\2", text)


def unguard(text: str) -> str:
    return _UNGUARD.sub(r"\1\2", text)


def read_back(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of every turn of a formatted conversation."""
    turns, at = [], len("<s>")
    while at < len(formatted):
        m = _TURN.match(formatted, at)
        if m is None or m.end() == at:
            raise ValueError(f"not a formatted conversation at {at}")
        if m[1] is not None:
            turns.append(("user", unguard(m[1])))
        elif m[2] is not None:
            turns.append((unguard(m[2]), unguard(m[3])))
        else:
            turns.append(("assistant", unguard(m[4])))
        at = m.end()
    return turns


def loss_texts(formatted: str, spans: list[dict]) -> list[str]:
    """The unguarded texts under the loss mask."""
    return [unguard(formatted[s["start"] : s["end"]]) for s in spans]


def format_conversations(rows: DataFrame, template: str = TEMPLATE) -> DataFrame:
    """One formatted row per conversation of ``rows`` (conv_id, turn, role, text)."""
    empty = F.lit("")
    turns = rows.select(
        F.col("conv_id").cast("long").alias("conv_id"),
        F.col("turn").cast("long").alias("turn"),
        F.coalesce(F.col("role").cast("string"), empty).alias("role"),
        F.coalesce(F.col("text").cast("string"), empty).alias("text"),
    )
    ordered = turns.repartition(buckets(rows.sparkSession), "conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")

    def render_all(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        render = compile_template(template, {"guard": guard})
        schema = pa.schema(
            [("conv_id", pa.int64()), ("n_turns", pa.int64()), ("formatted", pa.string()), ("spans", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))]
        )
        done: list[dict] = []

        def close(conv: int | None, messages: list[dict]) -> None:
            out = render(messages=messages)
            done.append({"conv_id": conv, "n_turns": len(messages), "formatted": "".join(out.pieces), "spans": [{"start": a, "end": b} for a, b in out.spans]})

        current, messages = None, []
        for batch in batches:
            for conv, role, text in zip(*(batch.column(c).to_pylist() for c in ("conv_id", "role", "text"))):
                if messages and conv != current:
                    close(current, messages)
                    messages = []
                current = conv
                messages.append({"role": role, "text": text})
            if len(done) > 500:
                yield pa.RecordBatch.from_pylist(done, schema)
                done.clear()
        if messages:
            close(current, messages)
        yield pa.RecordBatch.from_pylist(done, schema)

    return ordered.mapInArrow(render_all, FORMATTED)
