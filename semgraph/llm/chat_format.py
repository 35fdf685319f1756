"""Chat formatting by token-level assembly, and its reading back.

Every text is encoded on its own and never joined with its neighbours before encoding. Control
strings of the template stand as reserved ids above the vocabulary, so no text can produce them.
Where a text itself holds a control string, a backslash is put after its first character; one that
already has n backslashes there gets one more, which makes the escape reversible. The loss mask is the
prefix sum of +1 and -1 at the segment bounds, themselves prefix sums of the segments' token counts.
"""

from __future__ import annotations

import functools
import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_of

#: The control strings of the template; reserved ids follow the vocabulary in this order.
CONTROL = ("<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "[ROLE]", "[/ROLE]")
OPENERS = {"user": "[INST]", "assistant": "[/INST]", "system": "<<SYS>>"}
END = "</s>"
#: The same as a pattern: first character, backslashes, rest.
ESCAPE_PATTERN = r"([<\[])(\\*)(/?s>|/?INST\]|</?SYS>>|/?ROLE\])"


@functools.cache
def _pattern() -> tuple[re.Pattern, re.Pattern]:
    heads = {"<": r"(<)(\\*)(/?s>|</?SYS>>)", "[": r"(\[)(\\*)(/?INST\]|/?ROLE\])"}
    return tuple(re.compile(heads[c]) for c in "<[")


def escape(text: str) -> str:
    for p in _pattern():
        text = p.sub(r"\1\\\2\3", text)
    return text


def unescape(text: str) -> str:
    for p in _pattern():
        text = p.sub(lambda m: m[1] + m[2][1:] + m[3] if m[2] else m[0], text)
    return text


@functools.lru_cache(4)
def _tokenizer(path: str):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    t.encode_special_tokens = True  # reserved strings of the vocabulary are ordinary text inside a turn
    return t


def _segments(role: str, text: str) -> list[tuple[str, str | None]]:
    """(kind, text) of a turn: control strings, and texts with or without loss."""
    if role in OPENERS:
        head = [("control", OPENERS[role])]
    else:
        head = [("control", "[ROLE]"), ("text", escape(role)), ("control", "[/ROLE]")]
    return [*head, ("loss" if role == "assistant" else "text", escape(text)), ("control", END)]


def format_conversations(turns: DataFrame, tokenizer_path: str, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """(conv_id, n_turns, formatted, ids array<int>, loss_mask array<boolean>): a row for each conversation.

    Rows go by turn (nulls first), ties by role and text; repeated rows are turns of their own. Null roles and
    texts count as empty; rows with a null conv_id form one conversation. Unknown roles are written out
    between [ROLE] and [/ROLE]. An empty table gives an empty result; other columns play no part.
    One pass over sorted rows: a task holds one conversation at a time, whose output is one row.
    """
    rows = turns.select(
        F.col(conv_col).cast("long").alias("conv_id"), F.col(turn_col).cast("long").alias("turn"),
        text_of(role_col).alias("role"), text_of(text_col).alias("text"),
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = _tokenizer(tokenizer_path)
        reserved = {c: tok.get_vocab_size() + i for i, c in enumerate(CONTROL)}
        open_id, held, seen = None, [], False

        def assemble(conv: int | None, parts: list[tuple[str, str]], n: int) -> tuple:
            plain = [t for kind, t in parts if kind != "control"]
            coded = iter([e.ids for e in tok.encode_batch(plain, add_special_tokens=False)])
            ids = [[reserved[t]] if kind == "control" else next(coded) for kind, t in parts]
            bounds = np.concatenate([[0], np.cumsum([len(x) for x in ids])])
            step = np.zeros(bounds[-1] + 1, np.int32)
            loss = np.array([kind == "loss" for kind, _ in parts], np.int32)
            np.add.at(step, bounds[:-1], loss)
            np.add.at(step, bounds[1:], -loss)
            return conv, n, "".join(t for _, t in parts), np.concatenate([np.asarray(x, np.int32) for x in ids]), np.cumsum(step)[:-1] > 0

        def out(done: list[tuple]) -> pa.RecordBatch:
            conv, n, text, ids, mask = zip(*done)
            return pa.RecordBatch.from_arrays(
                [pa.array(conv, pa.int64()), pa.array(n, pa.int64()), pa.array(text), pa.array(ids, pa.list_(pa.int32())), pa.array(mask, pa.list_(pa.bool_()))],
                ["conv_id", "n_turns", "formatted", "ids", "loss_mask"],
            )

        parts: list[tuple[str, str]] = []
        n = size = 0
        for b in batches:
            for conv, role, text in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist()):
                if seen and conv != open_id:
                    held.append(assemble(open_id, parts, n))
                    size += len(held[-1][2])
                    parts, n = [], 0
                    if size > 4_000_000:
                        yield out(held)
                        held, size = [], 0
                open_id, seen = conv, True
                parts += _segments(role, text)
                n += 1
        if seen:
            held.append(assemble(open_id, parts, n))
        if held:
            yield out(held)

    sorted_rows = rows.repartition("conv_id").sortWithinPartitions(F.asc_nulls_first("conv_id"), F.asc_nulls_first("turn"), "role", "text")
    return sorted_rows.mapInArrow(run, "conv_id long, n_turns long, formatted string, ids array<int>, loss_mask array<boolean>")


def read_turns(tok, ids: np.ndarray, mask: np.ndarray) -> tuple[list[tuple[str, str]], list[str]]:
    """The turns (role, text) and the texts under the loss mask of one formatted conversation, from its ids alone."""
    size = tok.get_vocab_size()
    marks = np.flatnonzero(ids >= size)
    roles = {v: k for k, v in OPENERS.items()}
    begin, role, own, pieces, kinds = 0, None, "", [], []
    for m in marks.tolist():
        pieces.append(ids[begin:m].tolist())
        kinds.append((CONTROL[ids[m] - size], bool(m > begin and mask[begin:m].all()), bool(mask[begin : m + 1].any())))
        begin = m + 1
    texts = [unescape(t) for t in tok.decode_batch(pieces, skip_special_tokens=False)]
    turns, losses = [], []
    for text, (control, all_loss, any_loss) in zip(texts, kinds):
        if control in roles:
            role = roles[control]
        elif control == "[/ROLE]":
            role = text
        elif control == END:
            turns.append((role, text))
            if all_loss:
                losses.append(text)
            elif any_loss:
                raise ValueError("the loss mask cuts a segment")
    return turns, losses


def read_back(formatted: DataFrame, tokenizer_path: str) -> DataFrame:
    """Digests of what formatted conversations hold, decoded from ids and loss_mask.

    (conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars)
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = _tokenizer(tokenizer_path)
        for b in batches:
            cols = [[] for _ in range(6)]
            for i, conv in enumerate(b.column(0).to_pylist()):
                ids = b.column(2)[i].values.to_numpy()
                mask = b.column(3)[i].values.to_numpy(zero_copy_only=False)
                turns, losses = read_turns(tok, ids, mask)
                loss = "".join(losses)
                all_turns = "".join(f"{r}\n{t}\n" for r, t in turns)
                row = (conv, len(turns), hashlib.sha256(all_turns.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest(), len(b.column(1)[i].as_py()))
                for c, v in zip(cols, row):
                    c.append(v)
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    return formatted.select("conv_id", "formatted", "ids", "loss_mask").mapInArrow(
        run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    )
