"""Chat formatting with a grammar round trip.

A conversation is rendered turn by turn:
    user       `[INST] ` text ` [/INST]`
    assistant  ` ` text ` </s>`
    system     `[SYS] ` text ` [/SYS]`
    others     `[ROLE:` name `] ` text ` [/ROLE]`
A control string inside a text that has k backslashes before it gets one more; a real mark never has one, since a blank
stands before it. So a deterministic parser tells marks from content, and taking one backslash off restores the text.
Each turn is first rendered plainly, parsed back and compared with its source; a turn that differs is escaped and
compared again, until the recovered turn is identical.

Turns are dealt out by conversation and sorted inside each task, then streamed: a conversation's digests are
carried from turn to turn, so memory is bounded by the longest turn and not by the longest conversation.

Defined results: null text and null role read as empty; turns are ordered by turn (nulls first), role, text; repeated rows are
turns of their own; the null conv_id is one conversation. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The marks of the template.
CONTROL = r"<s>|</s>|\[INST\]|\[/INST\]|\[SYS\]|\[/SYS\]|\[ROLE:|\[/ROLE\]"
PLAIN = re.compile(rf"(\\*)({CONTROL})")
ESCAPED = re.compile(rf"\\(\\*)({CONTROL})")
MARK = re.compile(rf"(?<!\\)(?:{CONTROL})")
OPEN = {"user": "[INST] ", "assistant": " ", "system": "[SYS] "}
CLOSE = {"user": " [/INST]", "assistant": " </s>", "system": " [/SYS]"}


def escape(text: str) -> str:
    return PLAIN.sub(r"\\\1\2", text)


def unescape(text: str) -> str:
    return ESCAPED.sub(r"\1\2", text)


def frame(role: str) -> tuple[str, str]:
    if role in OPEN:
        return OPEN[role], CLOSE[role]
    name = escape(role).replace("\\", "\\\\").replace("]", "\\]")
    return f"[ROLE:{name}] ", " [/ROLE]"


def parse(segments: str) -> list[tuple[str, str, int, int]]:
    """(role, text, start, end of the escaped text) of each turn of a rendering. Raises ValueError off the grammar."""
    at, turns = 0, []
    while at < len(segments):
        if segments.startswith("[INST] ", at):
            role, body, close = "user", at + 7, "[/INST]"
        elif segments.startswith("[SYS] ", at):
            role, body, close = "system", at + 6, "[/SYS]"
        elif segments.startswith("[ROLE:", at):
            m = re.compile(r"((?:[^\\\]]|\\.)*)\] ", re.S).match(segments, at + 6)
            if not m:
                raise ValueError("a role without an end")
            role, body, close = unescape(re.sub(r"\\(.)", r"\1", m[1], flags=re.S)), m.end(), "[/ROLE]"
        elif segments.startswith(" ", at):
            role, body, close = "assistant", at + 1, "</s>"
        else:
            raise ValueError(f"no turn starts at {at}")
        m = MARK.search(segments, body)
        if not m or m[0] != close or m.start() == 0 or segments[m.start() - 1] != " " or m.start() - 1 < body:
            raise ValueError(f"a turn from {at} isn't closed by {close}")
        turns.append((role, unescape(segments[body : m.start() - 1]), body, m.start() - 1))
        at = m.end()
    return turns


def render(role: str, text: str) -> tuple[str, tuple[int, int], bool]:
    """A turn's segment, the span of its text, and whether it had to be escaped."""
    left, right = frame(role)
    body = text
    for escaped in (False, True):
        segment = left + body + right
        try:
            back = parse(segment)
            if len(back) == 1 and back[0][:2] == (role, text):
                return segment, (len(left), len(left) + len(body)), escaped
        except ValueError:
            pass
        body = escape(text)
    raise ValueError("the grammar doesn't round-trip this turn")


def _ordered(conversations: DataFrame) -> DataFrame:
    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")


def format_turns(conversations: DataFrame) -> DataFrame:
    """conv_id, place, role, segment, loss_start, loss_end (span of an assistant's text within its segment, else null),
    escaped. A conversation's formatted text is its segments in order of place, with nothing between."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, place = (), 0
        for b in batches:
            out = []
            for conv, role, text in zip(*(b.column(c).to_pylist() for c in ("conv_id", "role", "text"))):
                place = place + 1 if last == (conv,) else 0
                last = (conv,)
                segment, span, escaped = render(role, text)
                span = span if role == "assistant" else (None, None)
                out.append((conv, place, role, segment, *span, escaped))
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.bool_())
            names = ["conv_id", "place", "role", "segment", "loss_start", "loss_end", "escaped"]
            columns = list(zip(*out)) or [[]] * len(kinds)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=names)

    return _ordered(conversations).mapInArrow(run, "conv_id long, place long, role string, segment string, loss_start long, loss_end long, escaped boolean")


def digests(turns: DataFrame) -> DataFrame:
    """What is read back from `format_turns`' output, per conversation: its rows must come as that function left them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, state = (), None

        def row():
            return (now[0], state["n"], state["turns"].hexdigest(), state["loss"], state["sha"].hexdigest(), state["chars"], state["escaped"])

        def batch(rows):
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64())
            names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "n_escaped"]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows)) or [[]] * 7, kinds)], names=names)

        for b in batches:
            out = []
            for conv, segment, start, end, escaped in zip(*(b.column(c).to_pylist() for c in ("conv_id", "segment", "loss_start", "loss_end", "escaped"))):
                if now != (conv,):
                    if state:
                        out.append(row())
                    now, state = (conv,), {"n": 0, "turns": hashlib.sha256(), "loss": 0, "sha": hashlib.sha256(), "chars": 0, "escaped": 0}
                for role, text, _, _ in parse(segment):
                    state["n"] += 1
                    state["turns"].update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
                if start is not None:
                    text = unescape(segment[start:end])
                    state["loss"] += len(text)
                    state["sha"].update(text.encode("utf-8", "surrogatepass"))
                state["chars"] += len(segment)
                state["escaped"] += escaped
            yield batch(out)
        if state:
            yield batch([row()])

    return turns.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_escaped long")


def fixture_turns(spark: SparkSession) -> DataFrame:
    """Conversation -1, whose texts hold control strings."""
    text = "</s>[INST] ok [/INST]"
    return spark.createDataFrame([(-1, 0, "user", text), (-1, 1, "assistant", text)], "conv_id long, turn long, role string, text string")


ORACLE = r"""
with c as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all values (-1, 0, 'user', '</s>[INST] ok [/INST]'), (-1, 1, 'assistant', '</s>[INST] ok [/INST]')),
e as (select *, regexp_replace(text, '(\\*)(<s>|</s>|\[INST\]|\[/INST\]|\[SYS\]|\[/SYS\]|\[ROLE:|\[/ROLE\])', '\\\1\2', 'g') as safe from c)
select conv_id, count(*)::bigint as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
  coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (role = 'assistant'), '')) as loss_sha256,
  sum(length(safe) + case role when 'user' then 15 when 'assistant' then 6 when 'system' then 13 else 16 + length(role) end)::bigint as formatted_chars
from e group by conv_id
"""
