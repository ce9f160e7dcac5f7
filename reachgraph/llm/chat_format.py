r"""Chat formatting with a grammar round trip.

A conversation becomes one text of turns, each ``<turn>role<body>text</turn>``
and a line feed. The three marks are control strings. A turn is first rendered
as it stands; a deterministic parser reads the whole text back, and turns that
do not come back identical are escaped and rendered again until all do.

Escaping doubles the backslashes that stand directly before a control string or
at the end of a field and puts one more before the control string. The parser
halves the backslashes before a control string; an odd one makes it plain text.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reachgraph.llm.common import bound_batches, table

#: The control strings of the template.
OPEN, BODY, CLOSE = "<turn>", "<body>", "</turn>"

_MARK = re.compile(r"(\\*)(<turn>|<body>|</turn>)")
_TAIL = re.compile(r"(\\+)$", re.S)


def escape(text: str) -> str:
    """The text with every control string made plain and a safe end."""
    text = _MARK.sub(lambda m: m[1] * 2 + "\\" + m[2], text)
    trail = len(text) - len(text.rstrip("\\"))
    return text + "\\" * trail


def fields(rendered: str) -> Iterator[tuple[str, str, int, int]]:
    """(mark that ends it, text read back, start, end) of each field between control strings."""
    start, out = 0, []
    at = 0
    for m in _MARK.finditer(rendered):
        slashes = len(m[1])
        out.append(rendered[at : m.start()] + "\\" * (slashes // 2))
        if slashes % 2:
            out.append(m[2])
            at = m.end()
            continue
        yield m[2], "".join(out), start, m.start(2)
        start = at = m.end()
        out = []
    yield "", "".join(out) + rendered[at:], start, len(rendered)


def parse(rendered: str) -> list[tuple[str, str, int, int]]:
    """(role, text, start, end) of each turn; start and end frame the text as it is rendered.

    Raises ValueError where the text does not follow the grammar.
    """
    turns, state, role = [], OPEN, ""
    for mark, text, start, end in fields(rendered):
        if mark == "":
            if state != OPEN or text not in ("", "\n"):
                raise ValueError("unfinished turn")
            break
        if mark != state:
            raise ValueError(f"{mark} where {state} was due")
        if mark == OPEN:
            if text not in ("", "\n"):
                raise ValueError("text between turns")
            state = BODY
        elif mark == BODY:
            role, state = text, CLOSE
        else:
            turns.append((role, text, start, end))
            state = OPEN
    return turns


def render(turns: Iterable[tuple[str, str]]) -> str:
    """One text from which ``parse`` gives the same turns back."""
    turns = list(turns)
    made = [f"{OPEN}{role}{BODY}{text}{CLOSE}\n" for role, text in turns]
    for _ in range(2):
        conflict = [i for i, one in enumerate(made) if not _same(one, turns[i])]
        if not conflict:
            break
        for i in conflict:
            made[i] = f"{OPEN}{escape(turns[i][0])}{BODY}{escape(turns[i][1])}{CLOSE}\n"
    rendered = "".join(made)
    if [t[:2] for t in parse(rendered)] != turns:
        raise AssertionError("the rendered conversation does not read back")
    return rendered


def _same(one: str, turn: tuple[str, str]) -> bool:
    try:
        return [t[:2] for t in parse(one)] == [turn]
    except ValueError:
        return False


_FORMATTED = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("formatted", pa.string()), ("loss_start", pa.list_(pa.int64())), ("loss_end", pa.list_(pa.int64()))])
_DIGESTS = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])


def _format(loss_role: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: dict[str, list] = {f.name: [] for f in _FORMATTED}
            for conv, roles, texts in zip(*(batch.column(c).to_pylist() for c in ("conv_id", "roles", "texts")), strict=True):
                rendered = render(zip(roles, texts, strict=True))
                loss = [(s, e) for role, _, s, e in parse(rendered) if role == loss_role]
                for name, value in zip(out, (conv, len(roles), rendered, [s for s, _ in loss], [e for _, e in loss]), strict=True):
                    out[name].append(value)
            yield table(_FORMATTED, out)

    return run


def format_conversations(
    rows: DataFrame,
    *,
    id_col: str = "conv_id",
    turn_col: str = "turn",
    role_col: str = "role",
    text_col: str = "text",
    loss_role: str = "assistant",
) -> DataFrame:
    """conv_id, n_turns, formatted, loss_start, loss_end: one row per conversation.

    ``loss_start[i]`` and ``loss_end[i]`` frame, in code points of ``formatted``,
    the i-th text that the model is trained on. Turns are in order of ``turn``,
    nulls first, ties by role and text; repeated rows are turns of their own.
    Null texts and roles are empty; rows with a null id form one conversation.
    Other columns are not read; an empty table gives an empty result. A
    conversation is one training example and so has to fit in a task.
    """
    bound_batches(rows.sparkSession)
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    role = F.coalesce(F.col(role_col).cast("string"), F.lit(""))
    turns = F.sort_array(F.collect_list("one"))
    grouped = (
        rows.select(F.col(id_col).cast("long").alias("conv_id"), F.struct(F.col(turn_col).cast("long").alias("turn"), role.alias("role"), text.alias("text")).alias("one"))
        .groupBy("conv_id")
        .agg(turns.alias("turns"))
        .select("conv_id", F.col("turns.role").alias("roles"), F.col("turns.text").alias("texts"))
    )
    return grouped.mapInArrow(_format(loss_role), "conv_id long, n_turns long, formatted string, loss_start array<long>, loss_end array<long>")


def _read_back(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out: dict[str, list] = {f.name: [] for f in _DIGESTS}
        for conv, text, starts, ends in zip(*(batch.column(c).to_pylist() for c in ("conv_id", "formatted", "loss_start", "loss_end")), strict=True):
            turns = parse(text)
            all_turns, loss, chars = hashlib.sha256(), hashlib.sha256(), 0
            for role, said, _, _ in turns:
                all_turns.update(f"{role}\n{said}\n".encode())
            for start, end in zip(starts, ends, strict=True):
                said = "".join(t for _, t, _, _ in fields(text[start:end] + OPEN))
                loss.update(said.encode())
                chars += len(said)
            for name, value in zip(out, (conv, len(turns), all_turns.hexdigest(), chars, loss.hexdigest(), len(text)), strict=True):
                out[name].append(value)
        yield table(_DIGESTS, out)


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of what the formatted texts say when they are parsed again."""
    return formatted.select("conv_id", "formatted", "loss_start", "loss_end").mapInArrow(
        _read_back, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    )
