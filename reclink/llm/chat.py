r"""Chat formatting by columnar byte assembly.

Turns become text by a template with control strings:

    user        [INST] text [/INST]          assistant   <s>text</s>
    system      <<SYS>>text<</SYS>>          any other   [INST]<<SYS>>role<</SYS>>text[/INST]

A control string inside a text or role gets a backslash after its first sign, one more if
it has some already, so no text can close a turn and reading takes one away again.

For a step of turns numpy computes the lengths of all segments (opening, text, closing),
their cumulative offsets and scatter indices, and copies openings, texts and closings into
one buffer that becomes the Arrow column.  The loss mask is a list of byte spans, one for
each assistant text.

Turns are ordered by turn, then role and text.  A conversation of any length streams
through its task in parts, so memory does not grow with it; `read_back` follows the parts.
Null texts and roles count as empty; null conv_ids are one conversation; repeated rows are
turns each.  Empty tables give no rows; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reclink.llm._common import steps, tidy, utf8

CONTROL = r"/?INST\]|/?s>|</?SYS>>"
_HIDE = rf"([\[<])(\\*)({CONTROL})"
_SHOW = re.compile(rf"([\[<])\\(\\*)({CONTROL})")
_TURN = re.compile(r"(?s)\[INST\] (.*?) \[/INST\]|<s>(.*?)</s>|<<SYS>>(.*?)<</SYS>>|\[INST\]<<SYS>>(.*?)<</SYS>>(.*?)\[/INST\]")
FRAMES = {"user": ("[INST] ", " [/INST]"), "assistant": ("<s>", "</s>"), "system": ("<<SYS>>", "<</SYS>>")}

PARTS = "conv_id long, formatted string, loss_start array<long>, loss_length array<long>"


def escape(texts: pa.Array) -> pa.Array:
    return pc.replace_substring_regex(texts, pattern=_HIDE, replacement=r"\1\\\2\3")


def unescape(text: str) -> str:
    return _SHOW.sub(r"\1\2\3", text) if "\\" in text else text


def frame(role: str) -> tuple[bytes, bytes]:
    opening, closing = FRAMES.get(role) or (f"[INST]<<SYS>>{escape(pa.array([role]))[0].as_py()}<</SYS>>", "[/INST]")
    return opening.encode(), closing.encode()


def assemble(roles: pa.Array, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(buffer, start of each turn with the end, start and length of each text in it)."""
    names = roles.dictionary_encode()
    code = names.indices.to_numpy(zero_copy_only=False)
    frames = [frame(role) for role in names.dictionary.to_pylist()]
    data, offsets = utf8(escape(texts))
    size = np.diff(offsets)
    opening, closing = (np.array([len(f[k]) for f in frames], np.int64)[code] for k in (0, 1))
    starts = np.concatenate([[0], np.cumsum(opening + size + closing)])
    out = np.empty(int(starts[-1]), np.uint8)
    body = starts[:-1] + opening

    def scatter(source: np.ndarray, begin: np.ndarray, length: np.ndarray, to: np.ndarray) -> None:
        ramp = np.arange(int(length.sum())) - np.repeat(np.cumsum(length) - length, length)
        out[np.repeat(to, length) + ramp] = source[np.repeat(begin, length) + ramp]

    scatter(data, offsets[:-1], size, body)
    for k, length, to in ((0, opening, starts[:-1]), (1, closing, body + size)):
        pieces = [f[k] for f in frames]
        begin = np.cumsum([0, *map(len, pieces)])[:-1]
        scatter(np.frombuffer(b"".join(pieces), np.uint8), begin[code], length, to)
    return out, starts, body, size


def format_turns(turns: DataFrame) -> DataFrame:
    """Parts of conversations in order: conv_id, formatted, loss_start, loss_length (bytes in
    the part).  Parts of a conversation follow each other in one partition."""

    def apply(batches):
        for batch in batches:
            for at, to in steps(utf8(batch.column(2))[1]):
                ids, roles, texts = (batch.column(k).slice(at, to - at) for k in range(3))
                out, starts, body, size = assemble(roles, texts)
                key = ids.fill_null(0).to_numpy(zero_copy_only=False)
                none = ids.is_null().to_numpy(zero_copy_only=False)
                first = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (none[1:] != none[:-1])]))
                cuts = np.append(starts[first], starts[-1])
                formatted = pa.LargeStringArray.from_buffers(len(first), pa.py_buffer(cuts.astype("<i8").tobytes()), pa.py_buffer(out)).cast(pa.string())
                loss = np.flatnonzero(pc.equal(roles, "assistant").to_numpy(zero_copy_only=False))
                part = np.searchsorted(first, loss, "right") - 1
                edges = pa.array(np.searchsorted(part, np.arange(len(first) + 1)).astype(np.int32))
                spans = [pa.ListArray.from_arrays(edges, pa.array(x)) for x in (body[loss] - cuts[part], size[loss])]
                yield pa.RecordBatch.from_arrays([ids.take(pa.array(first)), formatted, *spans], names=["conv_id", "formatted", "loss_start", "loss_length"])

    text = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    rows = turns.select(F.col("conv_id").cast("long").alias("conv_id"), text("role").alias("role"), text("text").alias("text"), F.col("turn").alias("turn"))
    ordered = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return ordered.select("conv_id", "role", "text").mapInArrow(tidy(apply), PARTS)


def turns_of(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of the turns of a formatted text."""
    out, at = [], 0
    for m in _TURN.finditer(formatted):
        if m.start() != at:
            break
        at = m.end()
        k = m.lastindex
        role, text = (unescape(m[4]), m[5]) if k == 5 else (("user", "assistant", "system")[k - 1], m[k])
        out.append((role, unescape(text)))
    if at != len(formatted):
        raise ValueError(f"no turn at {at}: {formatted[at : at + 40]!r}")
    return out


class _Conversation:
    def __init__(self, conv_id):
        self.conv_id, self.turns, self.loss_chars, self.chars = conv_id, 0, 0, 0
        self.all, self.loss = hashlib.sha256(), hashlib.sha256()

    def add(self, formatted: str, starts: list[int], lengths: list[int]) -> None:
        self.chars += len(formatted)
        for role, text in turns_of(formatted):
            self.turns += 1
            self.all.update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
        raw = formatted.encode("utf-8", "surrogatepass")
        for at, n in zip(starts, lengths):
            text = unescape(raw[at : at + n].decode("utf-8", "surrogatepass"))
            self.loss_chars += len(text)
            self.loss.update(text.encode("utf-8", "surrogatepass"))

    def row(self) -> dict:
        return {"conv_id": self.conv_id, "n_turns": self.turns, "turns_sha256": self.all.hexdigest(), "loss_chars": self.loss_chars, "loss_sha256": self.loss.hexdigest(), "formatted_chars": self.chars}


def read_back(parts: DataFrame) -> DataFrame:
    """Per conversation, read from the formatted parts: n_turns, digests and sizes."""
    names = {"conv_id": pa.int64(), "n_turns": pa.int64(), "turns_sha256": pa.string(), "loss_chars": pa.int64(), "loss_sha256": pa.string(), "formatted_chars": pa.int64()}

    def apply(batches):
        open_ = None
        for batch in batches:
            done = []
            for conv_id, formatted, starts, lengths in zip(*(batch.column(k).to_pylist() for k in range(4))):
                if open_ is None or open_.conv_id != conv_id:
                    done += [open_.row()] if open_ else []
                    open_ = _Conversation(conv_id)
                open_.add(formatted, starts, lengths)
            yield pa.RecordBatch.from_pylist(done, schema=pa.schema(names))
        if open_:
            yield pa.RecordBatch.from_pylist([open_.row()], schema=pa.schema(names))

    return parts.mapInArrow(tidy(apply), "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
