"""Chat formatting with a grammar round trip.

The grammar of a rendered conversation::

    conversation := turn*
    turn         := "<s>[INST]" name NL "[/INST]" NL body NL "</s>"

``name`` and ``body`` are free of live control strings: a control string is live unless
a backslash stands before it, and a reader removes one backslash from each run of
backslashes before a control string.  A renderer first writes the texts as they are,
parses the result with the deterministic reader, compares the recovered turns with the
source and, where they differ, escapes the conflicting fields (one backslash more before
each control string in them) and renders again, until both are identical.  The new lines
after a name and around a body keep a text's own end from touching the template.

The loss mask holds the code points [start, end) of every assistant body in the rendered
text, escapes included; unescaping a masked stretch gives the assistant's text.

Rows are gathered per conversation, which is one document of the corpus; conversations
are dealt over the cluster by id and a worker holds a few at a time.

Defined cases: null text and null role are empty; turns are ordered by turn number (null
first), ties by role, then text; a row without a conversation id is a conversation of its own; repeated
rows are turns of their own; extra columns are ignored; an empty table gives an empty
table.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

START, END, OPEN, CLOSE = "<s>", "</s>", "[INST]", "[/INST]"
_CONTROL = r"<s>|</s>|\[INST\]|\[/INST\]"
_TOKEN = re.compile(rf"(\\*)({_CONTROL})")
ASSISTANT = "assistant"

Turn = tuple[str, str]


def escape(text: str) -> str:
    return _TOKEN.sub(r"\1\\\2", text)


def unescape(text: str) -> str:
    return _TOKEN.sub(lambda m: m[1][1:] + m[2], text)


def _write(fields: list[Turn]) -> tuple[str, list[tuple[int, int]]]:
    out: list[str] = []
    spans, at = [], 0
    for name, body in fields:
        lead = f"{START}{OPEN}{name}\n{CLOSE}\n"
        spans.append((at + len(lead), at + len(lead) + len(body)))
        out.append(f"{lead}{body}\n{END}")
        at += len(out[-1])
    return "".join(out), spans


class GrammarError(ValueError):
    pass


def parse(rendered: str) -> list[Turn]:
    """The turns of a rendered conversation; anything outside the grammar is an error."""
    live = ((m.start(), m.end(), m[2]) for m in _TOKEN.finditer(rendered) if not m[1])

    def need(what: str) -> tuple[int, int]:
        start, end, token = next(live, (-1, -1, ""))
        if token != what:
            raise GrammarError(f"{what} expected, {token or 'the end'} found")
        return start, end

    turns, at = [], 0
    while at < len(rendered):
        start, mid = need(START)
        if start != at:
            raise GrammarError("text between turns")
        if (here := need(OPEN))[0] != mid:
            raise GrammarError("text before a name")
        close = need(CLOSE)
        end = need(END)
        if end[0] < close[1] + 2 or {rendered[close[0] - 1], rendered[close[1]], rendered[end[0] - 1]} != {"\n"}:
            raise GrammarError("a name or body without its new lines")
        turns.append((unescape(rendered[here[1] : close[0] - 1]), unescape(rendered[close[1] + 1 : end[0] - 1])))
        at = end[1]
    return turns


def render(turns: list[Turn]) -> tuple[str, list[tuple[int, int]]]:
    """(text, spans of the bodies), escaped no more than the round trip asks for."""
    fields = list(turns)
    for attempt in range(3):
        text, spans = _write(fields)
        try:
            if parse(text) == turns:
                return text, spans
        except GrammarError:
            pass
        # the first time escape what a reader would misread, then all that is left
        fields = [tuple(escape(f) if attempt or _TOKEN.search(f) else f for f in turn) for turn in turns]
    raise GrammarError("a conversation that cannot be rendered")


def loss_spans(turns: list[Turn], spans: list[tuple[int, int]], role: str = ASSISTANT) -> list[tuple[int, int]]:
    return [s for (name, _), s in zip(turns, spans, strict=True) if name == role]


def format_conversations(chats: DataFrame, *, id_col: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """(conv_id, n_turns, formatted, loss_starts, loss_ends), one row per conversation."""
    fields = F.struct(F.col(turn).alias("t"), F.coalesce(role, F.lit("")).alias("r"), F.coalesce(text, F.lit("")).alias("x"))
    kind = dict(chats.dtypes)[id_col]
    lone = F.when(F.col(id_col).isNull(), F.monotonically_increasing_id())  # rows of no conversation never meet
    grouped = chats.select(F.col(id_col).alias("conv_id"), lone.alias("lone"), fields.alias("f")).groupBy("conv_id", "lone").agg(F.sort_array(F.collect_list("f")).alias("f"))
    rows = grouped.select("conv_id", F.col("f.r").alias("roles"), F.col("f.x").alias("texts"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(i, 64) for i in range(0, batch.num_rows, 64)):
                sizes, formatted, starts, ends = [], [], [], []
                for roles, texts in zip(part.column(1).to_pylist(), part.column(2).to_pylist(), strict=True):
                    turns = list(zip(roles, texts, strict=True))
                    rendered, spans = render(turns)
                    mask = loss_spans(turns, spans)
                    sizes.append(len(turns))
                    formatted.append(rendered)
                    starts.append([s for s, _ in mask])
                    ends.append([e for _, e in mask])
                longs = pa.list_(pa.int64())
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array(sizes, pa.int64()), pa.array(formatted, pa.string()), pa.array(starts, longs), pa.array(ends, longs)],
                    names=["conv_id", "n_turns", "formatted", "loss_starts", "loss_ends"],
                )

    return rows.mapInArrow(run, f"conv_id {kind}, n_turns long, formatted string, loss_starts array<long>, loss_ends array<long>")


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of what the rendered text says: its turns, and what stands under the mask."""
    kind = dict(formatted.dtypes)["conv_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            for rendered, starts, ends in zip(*(batch.column(c).to_pylist() for c in ("formatted", "loss_starts", "loss_ends")), strict=True):
                turns = parse(rendered)
                told = hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode())
                masked = "".join(unescape(rendered[s:e]) for s, e in zip(starts, ends, strict=True))
                out.append((len(turns), told.hexdigest(), len(masked), hashlib.sha256(masked.encode()).hexdigest(), len(rendered)))
            columns = [pa.array([o[i] for o in out], pa.string() if i in (1, 3) else pa.int64()) for i in range(5)]
            yield pa.RecordBatch.from_arrays(
                [batch.column("conv_id"), *columns], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
            )

    return formatted.select("conv_id", "formatted", "loss_starts", "loss_ends").mapInArrow(
        run, f"conv_id {kind}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    )


def op6_chat_format(spark, sf_dir: str) -> DataFrame:
    chats = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    tricky = "</s>[INST] ok [/INST]"
    more = spark.sql(f"select cast(-7 as bigint) conv_id, cast(t as bigint) turn, r role, '{tricky}' text from values (0, 'user'), (1, 'assistant') as v(t, r)")
    return read_back(format_conversations(chats.unionByName(more)))


ORACLE = r"""
with chats as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -7, 0, 'user', '</s>[INST] ok [/INST]'
  union all select -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
e as (
  select *, regexp_replace(text, '(\\*)(<s>|</s>|\[INST\]|\[/INST\])', '\1\\\2', 'g') as escaped from chats)
select conv_id, count(*)::bigint as n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
       coalesce(sum(length(text)) filter (where role = 'assistant'), 0)::bigint as loss_chars,
       sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (where role = 'assistant'), '')) as loss_sha256,
       sum(length('<s>[INST]') + length(role) + 1 + length('[/INST]') + 1 + length(escaped) + 1 + length('</s>'))::bigint as formatted_chars
from e group by conv_id
"""
