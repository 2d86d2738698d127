"""Chat formatting: conversations rendered by a compiled template, with the spans that a loss is taken on.

Turns are marked by control strings. A control string inside a role or text is escaped by a backslash behind its first character (one
more if there are some already), which unescaping takes away again, so that texts come back as they were and never look like
markers. Rows become conversations by turn, then role and text where turns tie; repeated rows are turns of their own.

Conversations are records: all turns of one meet in one row, gathered by a grouped aggregate, as its text is one value. Null roles and texts are
empty; a null turn sorts first; rows with a null conv_id are one conversation; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from utilmine.llm.templates import Template

#: The strings that open a turn, part role from text and close a turn, and those of other formats that texts must not smuggle in.
OPEN, MIDDLE, CLOSE = "<|turn|>", "<|text|>", "<|end|>"
CONTROLS = (OPEN, MIDDLE, CLOSE, "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|endoftext|>", "<|im_start|>", "<|im_end|>")

SOURCE = """{% set open = "<|turn|>" %}{% set middle = "<|text|>" %}{% set close = "<|end|>" ~ "\\n" -%}
{% for m in messages -%}
{{ open }}{{ m.role | escape }}{{ middle }}
{%- if m.role == "assistant" -%}
{% generation %}{{ m.text | escape }}{% endgeneration %}
{%- else -%}
{{ m.text | escape }}
{%- endif -%}
{{ close }}
{%- endfor -%}
"""

_UNSAFE = re.compile("|".join(rf"{re.escape(c[0])}\\*{re.escape(c[1:])}" for c in CONTROLS))
_ESCAPED = re.compile("|".join(rf"{re.escape(c[0])}\\+{re.escape(c[1:])}" for c in CONTROLS))
_TURN = re.compile(f"{re.escape(OPEN)}(.*?){re.escape(MIDDLE)}(.*?){re.escape(CLOSE)}\n", re.S)


def escape(s: str | None) -> str:
    return _UNSAFE.sub(lambda m: m[0][0] + "\\" + m[0][1:], s or "")


def unescape(s: str) -> str:
    return _ESCAPED.sub(lambda m: m[0][0] + m[0][2:], s)


def turns_of(formatted: str) -> list[tuple[str, str]]:
    """The roles and texts of a formatted conversation; raises if anything stands between turns."""
    out, at = [], 0
    for m in _TURN.finditer(formatted):
        if m.start() != at:
            raise ValueError(f"unexpected text at {at}")
        out.append((unescape(m[1]), unescape(m[2])))
        at = m.end()
    if at != len(formatted):
        raise ValueError(f"unexpected text at {at}")
    return out


def _formatter(source: str):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        template = Template(source, {"escape": escape})
        for batch in batches:
            conv, turns = batch.column(0), batch.column(1)
            text, spans = [], []
            for i in range(batch.num_rows):
                messages = [{"role": t["role"] or "", "text": t["text"] or ""} for t in turns[i].as_py()]
                s, found = template.render({"messages": messages})
                text.append(s)
                spans.append([{"start": a, "end": b} for a, b in found])
            yield pa.record_batch({"conv_id": conv, "formatted": pa.array(text, pa.string()), "loss_spans": pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))})

    return rows


def format_conversations(rows: DataFrame, source: str = SOURCE) -> DataFrame:
    """rows (conv_id, turn, role, text) -> conv_id, formatted, loss_spans (code points, end exclusive)."""
    kind = rows.schema["conv_id"].dataType.simpleString()
    turns = rows.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    return turns.mapInArrow(_formatter(source), f"conv_id {kind}, formatted string, loss_spans array<struct<start: long, end: long>>")


def _reader(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        turns, loss = [], []
        for formatted, spans in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
            turns.append([{"role": r, "text": t} for r, t in turns_of(formatted)])
            loss.append("".join(unescape(formatted[s["start"] : s["end"]]) for s in spans))
        pair = pa.struct([("role", pa.string()), ("text", pa.string())])
        yield pa.record_batch({"conv_id": batch.column(0), "turns": pa.array(turns, pa.list_(pair)), "loss": pa.array(loss, pa.string()), "formatted_chars": pc.utf8_length(batch.column(1)).cast(pa.int64())})


def read_back(formatted: DataFrame) -> DataFrame:
    """conv_id, turns (role, text), loss (the unescaped text under the loss mask) and formatted_chars, read from formatted text and spans alone."""
    kind = formatted.schema["conv_id"].dataType.simpleString()
    return formatted.select("conv_id", "formatted", "loss_spans").mapInArrow(_reader, f"conv_id {kind}, turns array<struct<role: string, text: string>>, loss string, formatted_chars long")
