"""Chat formatting with loss masks aligned to token offsets.

A conversation's turns are rendered with turn markers; control strings inside texts and roles are
escaped reversibly, so a text can't open or close a turn. The rendering is encoded once with
character offsets, and the sorted spans of assistant texts meet the sorted token spans by binary
search. Rows stream in (conversation, turn) order, so a task holds one piece of a conversation at a
time: a conversation over PIECE_CHARS is encoded in pieces cut at turn starts, where the tokenizer's
own pre-tokens always end, and its digests run on.

Defined results: null text or role is empty; turns with equal numbers are ordered by role, then text;
repeated rows are repeated turns; a null conversation id is a conversation; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

PIECE_CHARS = 500_000
# The template's control strings.
TURN_START, TURN_END = "<|im_start|>", "<|im_end|>"
_OPEN = re.compile(r"<(\\*)\|")
_SHUT = re.compile(r"<\\(\\*)\|")
_TURN = re.compile(re.escape(TURN_START) + r"([^\n]*)\n(.*?)" + re.escape(TURN_END) + r"\n", re.S)


def escape(text: str) -> str:
    """No control string is left: every <| gets a backslash between its signs, and so does <\\| and on."""
    return _OPEN.sub(r"<\\\1|", text)


def unescape(text: str) -> str:
    return _SHUT.sub(r"<\1|", text)


def render_turn(role: str, text: str) -> tuple[str, int, int]:
    """The rendered turn, and where its text lies in it."""
    head = TURN_START + escape(role.replace("\\", "\\\\").replace("\n", "\\n")) + "\n"
    body = escape(text)
    return head + body + TURN_END + "\n", len(head), len(head) + len(body)


def read_turns(rendered: str) -> list[tuple[str, str]]:
    """The (role, text) pairs of a rendering."""
    plain = lambda r: re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], r)
    return [(plain(unescape(r)), unescape(t)) for r, t in _TURN.findall(rendered)]


def loss_mask(offsets: np.ndarray, spans: list[tuple[int, int]]) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """Which tokens touch a span, and the characters that tokens and spans share, per span."""
    mask = np.zeros(len(offsets), bool)
    shared = []
    if len(offsets):
        starts, ends = offsets[:, 0], np.maximum.accumulate(offsets[:, 1])
        for a, b in spans:
            i, j = np.searchsorted(ends, a, side="right"), np.searchsorted(starts, b, side="left")
            if i < j and a < b:
                mask[i:j] = True
                shared.append((max(a, int(starts[i])), min(b, int(ends[j - 1]))))
    return mask, shared


_TOKENIZERS: dict = {}


def _tokenizer(path: str):
    if path not in _TOKENIZERS:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        t = Tokenizer.from_file(path)
        t.encode_special_tokens = True
        _TOKENIZERS[path] = t
    return _TOKENIZERS[path]


class _Digest:
    """What is read back of one conversation, piece by piece."""

    def __init__(self, key):
        self.key, self.turns, self.loss_chars, self.chars, self.tokens, self.loss_tokens = key, 0, 0, 0, 0, 0
        self.said, self.loss = hashlib.sha256(), hashlib.sha256()

    def add(self, rendered: str, spans: list[tuple[int, int]], offsets: np.ndarray) -> None:
        for role, text in read_turns(rendered):
            self.turns += 1
            self.said.update(f"{role}\n{text}\n".encode())
        mask, shared = loss_mask(offsets, spans)
        for a, b in shared:
            text = unescape(rendered[a:b])
            self.loss_chars += len(text)
            self.loss.update(text.encode())
        self.chars += len(rendered)
        self.tokens += len(mask)
        self.loss_tokens += int(mask.sum())

    def row(self) -> tuple:
        return self.key, self.turns, self.said.hexdigest(), self.loss_chars, self.loss.hexdigest(), self.chars, self.tokens, self.loss_tokens


def format_conversations(rows: DataFrame, tokenizer_path: str, learn: str = "assistant", texts: bool = False) -> DataFrame:
    """rows: conv_id, turn, role, text. Per conversation: digests and counts read back from the rendering.

    texts=True returns the pieces themselves instead: conv_id, piece, formatted, token ids and mask.
    """
    narrow = rows.select("conv_id", F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    dealt = narrow.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    kind = rows.schema["conv_id"].dataType
    digest_schema = f"conv_id {kind.simpleString()}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_tokens long, n_loss_tokens long"
    text_schema = f"conv_id {kind.simpleString()}, piece long, formatted string, ids array<int>, loss_mask array<boolean>"

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        """(conversation, rendered piece, assistant spans, is it the last) in order."""
        key, parts, spans, size, begun = None, [], [], 0, False
        for b in batches:
            for conv, _, role, text in zip(*(c.to_pylist() for c in b.columns)):
                if begun and (conv != key or size >= PIECE_CHARS):
                    yield key, "".join(parts), spans, conv != key
                    parts, spans, size = [], [], 0
                key, begun = conv, True
                turn, a, z = render_turn(role, text)
                parts.append(turn)
                if role == learn:
                    spans.append((size + a, size + z))
                size += len(turn)
        if begun:
            yield key, "".join(parts), spans, True

    def encoded(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        held, size = [], 0
        for p in pieces(batches):
            held.append(p)
            size += len(p[1])
            if size >= PIECE_CHARS:
                yield from zip(held, _tokenizer(tokenizer_path).encode_batch([h[1] for h in held], add_special_tokens=False))
                held, size = [], 0
        if held:
            yield from zip(held, _tokenizer(tokenizer_path).encode_batch([h[1] for h in held], add_special_tokens=False))

    def offsets_of(e) -> np.ndarray:
        return np.array(e.offsets, np.int64).reshape(-1, 2)

    def digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in digest_schema.split(", ")]
        kinds = [to_arrow_type(kind), *(pa.string() if x.endswith("string") else pa.int64() for x in digest_schema.split(", ")[1:])]
        out, now = [], None
        for (key, rendered, spans, last), e in encoded(batches):
            now = now or _Digest(key)
            now.add(rendered, spans, offsets_of(e))
            if last:
                out.append(now.row())
                now = None
            if len(out) >= 4096:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=names)
                out = []
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=names)

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        piece = 0
        for (key, rendered, spans, last), e in encoded(batches):
            mask, _ = loss_mask(offsets_of(e), spans)
            yield pa.RecordBatch.from_arrays([pa.array([key], to_arrow_type(kind)), pa.array([piece], pa.int64()), pa.array([rendered]), pa.array([e.ids], pa.list_(pa.int32())), pa.array([mask.tolist()], pa.list_(pa.bool_()))], names=["conv_id", "piece", "formatted", "ids", "loss_mask"])
            piece = 0 if last else piece + 1

    return dealt.mapInArrow(whole, text_schema) if texts else dealt.mapInArrow(digests, digest_schema)
