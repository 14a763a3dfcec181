"""Chat formatting with a loss mask: turns are rendered, encoded once with offsets, spans meet by binary search."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: The template's marks, and what stands in a text for characters that could begin a control string.
OPEN, MIDDLE, CLOSE = "<|turn|>", "<|text|>", "<|end|>\n"
ESCAPES = (("\\", "\\\\"), ("<", "\\l"), ("[", "\\b"))
_BACK = {"\\": "\\", "l": "<", "b": "["}

SCHEMA = T.StructType([
    T.StructField("conv_id", T.LongType()), T.StructField("formatted", T.StringType()), T.StructField("token_ids", T.ArrayType(T.IntegerType())),
    T.StructField("token_mask", T.ArrayType(T.BooleanType())), T.StructField("loss_spans", T.ArrayType(T.ArrayType(T.LongType()))),
])


def escape(text: str) -> str:
    """No ``<`` and no ``[`` is left, so no control string of any common template can appear."""
    for char, put in ESCAPES:
        text = text.replace(char, put)
    return text


def unescape(text: str) -> str:
    parts = text.split("\\")
    out, i = [parts[0]], 1
    while i < len(parts):
        part = parts[i]
        if part:
            out.append(_BACK[part[0]] + part[1:])
            i += 1
        else:  # an escaped backslash; what follows it is ordinary text
            out.append("\\" + (parts[i + 1] if i + 1 < len(parts) else ""))
            i += 2
    return "".join(out)


def render(turns: list[tuple[str, str]]) -> tuple[str, np.ndarray]:
    """The formatted conversation and the ``[begin, end)`` character spans of the assistant's texts, in order."""
    parts, spans, at = [], [], 0
    for role, text in turns:
        head, body = f"{OPEN}{escape(role)}{MIDDLE}", escape(text)
        if role == "assistant":
            spans.append((at + len(head), at + len(head) + len(body)))
        parts += (head, body, CLOSE)
        at += len(head) + len(body) + len(CLOSE)
    return "".join(parts), np.array(spans, np.int64).reshape(-1, 2)


def parse(formatted: str) -> list[tuple[str, str]]:
    """The turns back from the formatted text."""
    out = []
    for piece in formatted.split(OPEN)[1:]:
        role, _, rest = piece.partition(MIDDLE)
        out.append((unescape(role), unescape(rest.removesuffix(CLOSE))))
    return out


def meet(offsets: np.ndarray, spans: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which tokens touch a span, and the characters of the spans as tokens cover them.

    ``offsets`` and ``spans`` are sorted. Tokens that share a character (its bytes were split) count
    it once. For each span the first and last token are found by binary search.
    """
    mask = np.zeros(len(offsets), bool)
    if not len(offsets) or not len(spans):
        return mask, np.zeros((0, 2), np.int64)
    ends = np.maximum.accumulate(offsets[:, 1])
    begins = np.maximum(offsets[:, 0], np.concatenate(([0], ends[:-1])))
    first = np.searchsorted(ends, spans[:, 0], side="right")
    last = np.searchsorted(offsets[:, 0], spans[:, 1], side="left")
    pieces = []
    for (a, b), i, j in zip(spans, first, last, strict=True):
        if a < b:
            mask[i:j] = True
            cut = np.stack([np.clip(begins[i:j], a, b), np.clip(ends[i:j], a, b)], 1)
            pieces.append(cut[cut[:, 0] < cut[:, 1]])
    found = np.concatenate(pieces) if pieces else np.zeros((0, 2), np.int64)
    if len(found):  # neighbours that touch within one span become one
        new = np.concatenate(([True], (found[1:, 0] != found[:-1, 1]) | np.isin(found[1:, 0], spans[:, 0])))
        at = np.flatnonzero(new)
        found = np.stack([found[at, 0], np.maximum.reduceat(found[:, 1], at)], 1)
    return mask, found


def formatted(conversations: DataFrame, tokenizer_path: str) -> DataFrame:
    """One row per conversation: formatted text, token ids, token mask and masked character spans.

    ``conversations`` has conv_id, turn, role and text; other columns are ignored. Turns are ordered by
    turn (nulls first), equal turns by role and text, and repeated rows stay. A null role or text is
    empty; rows with a null conv_id form one conversation. A conversation is a single output record, so
    its turns are brought together by a keyed aggregate; conversations, not turns, are the unit of work.
    The mask covers exactly the texts of turns whose role is ``assistant``.
    """
    turns = F.array_sort(F.collect_list(F.struct("turn", "role", "text")))
    rows = (
        conversations.select(
            F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"),
            F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"),
        )
        .groupBy("conv_id")
        .agg(turns.alias("turns"))
        .select("conv_id", F.col("turns.role").alias("roles"), F.col("turns.text").alias("texts"))
    )

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_file(tokenizer_path)
        tokenizer.encode_special_tokens = True
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                rendered = [render(list(zip(r, t, strict=True))) for r, t in zip(part.column(1).to_pylist(), part.column(2).to_pylist(), strict=True)]
                out = []
                for conv, (text, spans), code in zip(part.column(0).to_pylist(), rendered, tokenizer.encode_batch([t for t, _ in rendered], add_special_tokens=False), strict=True):
                    mask, loss = meet(np.array(code.offsets, np.int64).reshape(-1, 2), spans)
                    out.append({"conv_id": conv, "formatted": text, "token_ids": code.ids, "token_mask": mask.tolist(), "loss_spans": loss.tolist()})
                yield pa.RecordBatch.from_pylist(out, schema=ARROW)

    return rows.mapInArrow(work, SCHEMA)


ARROW = pa.schema([("conv_id", pa.int64()), ("formatted", pa.string()), ("token_ids", pa.list_(pa.int32())), ("token_mask", pa.list_(pa.bool_())), ("loss_spans", pa.list_(pa.list_(pa.int64())))])

DIGEST = T.StructType([
    T.StructField("conv_id", T.LongType()), T.StructField("n_turns", T.LongType()), T.StructField("turns_sha256", T.StringType()),
    T.StructField("loss_chars", T.LongType()), T.StructField("loss_sha256", T.StringType()), T.StructField("formatted_chars", T.LongType()),
])


def read_back(chats: DataFrame) -> DataFrame:
    """Digests of turns and of unescaped masked text, both taken from the output of ``formatted``."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for row in batch.to_pylist():
                turns, text = parse(row["formatted"]), row["formatted"]
                loss = "".join(unescape(text[a:b]) for a, b in row["loss_spans"])
                whole = "".join(f"{role}\n{said}\n" for role, said in turns)
                out.append((row["conv_id"], len(turns), hashlib.sha256(whole.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest(), len(text)))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()), strict=True)] if out else [pa.array([], f.type) for f in EMPTY], DIGEST.names)

    return chats.select("conv_id", "formatted", "loss_spans").mapInArrow(work, DIGEST)


EMPTY = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])
