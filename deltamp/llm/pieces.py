"""SentencePiece BPE encoding and decoding by vectorised merge rounds.

A text is cut where no piece of the model crosses: before each run of spaces that follows another
character. Distinct segments go through merge rounds together: flat arrays of
symbols, a segmented minimum of the pair ranks per segment, one merge at the leftmost minimum of every
segment at once, then compaction, until no segment has a pair left. A segment over LONG symbols runs
the same merges through a heap instead, which keeps its cost near-linear. Segments already seen by a
worker come from a bounded table.

Defined results: null text is empty and encodes to begin and end ids alone; repeated rows repeat
their results; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import heapq
import re
from collections.abc import Iterator
from itertools import filterfalse

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltamp.llm.common import as_texts

LONG = 400
CHUNK_CHARS = 2_000_000
TABLE_ENTRIES = 500_000
_SPACE = "▁"
_SEGMENT = re.compile(r" *[^ ]+| +")
_NONE = np.int32(2**31 - 1)


def _text_of(key: str) -> str:
    """The segment a key stands for: a word after one space, or after a further space the segment itself."""
    return key[1:] if key.startswith(" ") else " " + key


def _keys(text: str) -> list[str]:
    """The segments of a text with its dummy prefix, as keys."""
    if not text:
        return []
    text = text.replace(_SPACE, " ")
    parts = text.split(" ")
    if "" not in parts:
        return parts
    return [s[1:] if s[1:] and s[1] != " " else " " + s for s in _SEGMENT.findall(" " + text)]


class PieceModel:
    """The vocabulary of a BPE model with byte fallback, an identity normaliser and a dummy prefix."""

    def __init__(self, path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        self.pieces = [sp.id_to_piece(i) for i in range(n)]
        self.begin, self.end, self.unknown = sp.bos_id(), sp.eos_id(), sp.unk_id()
        self.byte_id = {int(p[3:5], 16): i for i, p in enumerate(self.pieces) if sp.is_byte(i)}
        self.byte_of = {i: b for b, i in self.byte_id.items()}
        self.silent = {i for i in range(n) if sp.is_control(i)}
        text = {p: i for i, p in enumerate(self.pieces) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i))}
        if any(_SPACE in p.lstrip(_SPACE) for p in text):
            raise ValueError("the model has pieces across the cuts this encoder makes")
        self.symbols = dict(text)
        self.strings = dict(zip(text.values(), text))
        for p in text:
            for c in p:
                self._symbol(c, n)
        score = {i: sp.get_score(i) for i in text.values()}
        rank = {s: r for r, s in enumerate(sorted(set(score.values()), reverse=True))}
        pairs = {}
        for p, i in text.items():
            for cut in range(1, len(p)):
                a, b = self.symbols.get(p[:cut]), self.symbols.get(p[cut:])
                if a is not None and b is not None:
                    pairs[a << 32 | b] = (rank[score[i]], i)
        self.keys = np.array(sorted(pairs), np.int64)
        self.ranks = np.array([pairs[k][0] for k in self.keys.tolist()], np.int32)
        self.merged = np.array([pairs[k][1] for k in self.keys.tolist()], np.int64)
        self.pairs = pairs
        self.size = n
        self.symbol_of = np.full(0x110000, -1, np.int64)
        for c, i in self.symbols.items():
            if len(c) == 1:
                self.symbol_of[ord(c)] = i
        for b, i in self.byte_id.items():
            if b < 128 and self.symbol_of[b] < 0:  # one byte, one id, and no pair has it
                self.symbol_of[b] = i
        self.symbol_of[ord(" ")] = self.symbols.get(_SPACE, -1)
        shown = [chr(self.byte_of[i]) if self.byte_of.get(i, 128) < 128 else self.strings.get(i, "").replace(_SPACE, " ") for i in range(n)]
        self.piece_len = np.array([len(x) for x in shown], np.int64)
        self.piece_at = np.concatenate([[0], np.cumsum(self.piece_len)[:-1]])
        self.piece_chars = np.frombuffer("".join(shown).encode("utf-32-le"), np.uint32)
        self.known: dict[str, bytes] = {}
        self.odd: dict[str, str] = {}

    def _symbol(self, c: str, n: int) -> int:
        """The id of a character; characters that are no piece get ids past the vocabulary."""
        if c not in self.symbols:
            self.symbols[c] = max(n, len(self.symbols) + n)
            self.strings[self.symbols[c]] = c
        return self.symbols[c]

    def _look(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = a << np.int64(32) | b
        i = np.searchsorted(self.keys, key)
        i[i == len(self.keys)] = 0
        hit = self.keys[i] == key
        return np.where(hit, self.ranks[i], _NONE), np.where(hit, self.merged[i], 0)

    def _rounds(self, sym: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Merge all segments together.

        sym: their symbols laid end to end (-1: never merges); sizes: how many each has. Returns the
        final symbols in the same order and each segment's count.
        """
        seg = np.repeat(np.arange(len(sizes)), sizes)
        done_sym, done_seg = [], []

        def pair_at(i: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            rank, into = self._look(sym[i], sym[i + 1])
            rank[(seg[i] != seg[i + 1]) | (sym[i] < 0) | (sym[i + 1] < 0)] = _NONE
            return rank, into

        rank, into = np.full(len(sym), _NONE, np.int32), np.zeros(len(sym), np.int64)
        if len(sym) > 1:
            rank[:-1], into[:-1] = pair_at(np.arange(len(sym) - 1))
        while len(sym):
            heads = np.flatnonzero(np.concatenate([[True], seg[1:] != seg[:-1]]))
            lengths = np.diff(np.append(heads, len(sym)))
            least = np.minimum.reduceat(rank, heads)
            over = least == _NONE
            if over.any():
                gone = np.repeat(over, lengths)
                done_sym.append(sym[gone]), done_seg.append(seg[gone])
                sym, seg, rank, into = sym[~gone], seg[~gone], rank[~gone], into[~gone]
                least, lengths = least[~over], lengths[~over]
                if not len(sym):
                    break
            at = np.flatnonzero(rank == np.repeat(least, lengths))
            at = at[np.concatenate([[True], seg[at[1:]] != seg[at[:-1]]])]
            sym[at] = into[at]
            stay = np.ones(len(sym), bool)
            stay[at + 1] = False
            moved = at - np.arange(len(at))
            sym, seg, rank, into = sym[stay], seg[stay], rank[stay], into[stay]
            touched = np.zeros(len(sym) + 1, bool)
            touched[moved] = True
            touched[moved - 1] = True
            redo = np.flatnonzero(touched[: len(sym) - 1])
            rank[-1] = _NONE
            if len(redo):
                rank[redo], into[redo] = pair_at(redo)
        flat, owner = np.concatenate([np.zeros(0, np.int64), *done_sym]), np.concatenate([np.zeros(0, np.int64), *done_seg])
        return flat[np.argsort(owner, kind="stable")], np.bincount(owner, minlength=len(sizes))

    def _heap(self, sym: list[int]) -> list[int]:
        """The same merges for one long word, least (rank, position) first."""
        sym, n = list(sym), len(sym)
        after, before, alive = list(range(1, n + 1)), list(range(-1, n - 1)), [True] * n
        heap: list[tuple] = []

        def push(i: int) -> None:
            j = after[i] if i >= 0 else n
            if i >= 0 and j < n and sym[i] >= 0 and sym[j] >= 0 and (found := self.pairs.get(sym[i] << 32 | sym[j])):
                heapq.heappush(heap, (found[0], i, sym[i], sym[j], j, found[1]))

        for i in range(n - 1):
            push(i)
        while heap:
            _, i, a, b, j, into = heapq.heappop(heap)
            if alive[i] and after[i] == j and j < n and alive[j] and sym[i] == a and sym[j] == b:
                sym[i], alive[j], after[i] = into, False, after[j]
                if after[j] < n:
                    before[after[j]] = i
                push(before[i])
                push(i)
        return [s for s, live in zip(sym, alive) if live]

    def _ids(self, sym: list[int], chars: str) -> list[int]:
        """Final ids; symbols that are no piece fall back to bytes."""
        if all(0 <= s < self.size for s in sym):
            return sym
        out, at = [], 0
        for s in sym:
            if 0 <= s < self.size:
                out.append(s)
                at += len(self.strings[s])
            else:
                raw = chars[at].encode()
                out += [self.byte_id[b] for b in raw] if self.byte_id else [self.unknown]
                at += 1
        return out

    def decode_ids(self, ids: list[int]) -> str:
        """Text of ids without the dummy prefix's removal: bytes join up, pieces read as they are."""
        out: list[bytes] = []
        for i in ids:
            if i in self.byte_of:
                out.append(bytes([self.byte_of[i]]))
            elif i not in self.silent:
                out.append(self.strings[i].replace(_SPACE, " ").encode() if i != self.unknown else " ⁇ ".encode())
        return b"".join(out).decode("utf-8", "replace")

    def learn(self, keys: list[str]) -> None:
        """Encode and decode segments that the table lacks."""
        short = [k for k in keys if len(k) < LONG]
        if short:
            self._learn_short(short)
        for k in keys:
            if len(k) >= LONG:
                chars = _text_of(k).replace(" ", _SPACE)
                self._keep(k, self._ids(self._heap([self.symbols.get(c, -1) for c in chars]), chars))

    def _keep(self, key: str, ids: list[int]) -> None:
        self.known[key] = np.array(ids, "<u4").tobytes()
        if (text := self.decode_ids(ids)) != _text_of(key):
            self.odd[key] = text

    def _learn_short(self, keys: list[str]) -> None:
        segments = [_text_of(k) for k in keys]
        joined = "".join(segments)
        codes = np.frombuffer(joined.encode("utf-32-le"), np.uint32)
        sizes = np.fromiter(map(len, segments), np.int64, len(segments))
        flat, counts = self._rounds(self.symbol_of[codes], sizes)
        at = np.concatenate([[0], np.cumsum(counts)])
        owner = np.repeat(np.arange(len(segments)), counts)
        odd = np.zeros(len(segments), bool)
        odd[owner[(flat < 0) | (flat >= self.size)]] = True
        blob = flat.astype("<u4").tobytes()
        cut = (at * 4).tolist()
        plain = ~odd
        # Decode: the pieces' characters end to end, and only where they differ from the segment, their text.
        ids = np.where(odd[owner], 0, flat)
        wide = self.piece_len[ids]
        chars = self.piece_chars[np.repeat(self.piece_at[ids] - np.concatenate([[0], np.cumsum(wide)[:-1]]), wide) + np.arange(int(wide.sum()))]
        long = np.bincount(owner, weights=wide, minlength=len(segments)).astype(np.int64)
        plain &= long == sizes
        source = codes[np.repeat(plain, sizes)]
        same = np.repeat(np.arange(len(segments)), sizes)[np.repeat(plain, sizes)]
        differs = np.unique(same[source != chars[np.repeat(plain, long)]])
        plain[differs] = False
        known = self.known
        for s, a, b, ok in zip(keys, cut[:-1], cut[1:], plain.tolist()):
            if ok:
                known[s] = blob[a:b]
        for k in np.flatnonzero(~plain).tolist():
            self._keep(keys[k], self._ids(flat[at[k] : at[k + 1]].tolist(), segments[k].replace(" ", _SPACE)))

    def encode_many(self, texts: list[str]) -> list[tuple[bytes, str]]:
        """Per text: ids as little-endian 32-bit integers with begin and end, and the decoded text."""
        edge = [np.array([i], "<u4").tobytes() for i in (self.begin, self.end)]
        cut = [_keys(t) for t in texts]
        known = self.known
        lacking: set[str] = set()
        for parts in cut:
            lacking.update(filterfalse(known.__contains__, parts))
        if len(known) + len(lacking) > TABLE_ENTRIES:
            known.clear(), self.odd.clear()
            lacking = set().union(*cut)
        self.learn(list(lacking))
        out = []
        for parts in cut:
            ids = b"".join(map(known.__getitem__, parts))
            if self.odd.keys().isdisjoint(parts) and " " not in "".join(parts):
                text = " ".join(parts)
            else:
                text = "".join([self.odd.get(k) or _text_of(k) for k in parts])
                text = text[1:] if text.startswith(" ") else text
            out.append((edge[0] + ids + edge[1], text))
        return out


_LOADED: dict[str, PieceModel] = {}


def model(path: str) -> PieceModel:
    """The model at a path that every worker has, loaded once per process."""
    if path not in _LOADED:
        _LOADED[path] = PieceModel(path)
    return _LOADED[path]


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ("n_tokens", "ids_sha256", "decoded_sha256")) -> DataFrame:
    """Per row: id and the chosen of n_tokens, ids (bytes), decoded (text), ids_sha256, decoded_sha256."""
    kinds = {"n_tokens": T.LongType(), "ids": T.BinaryType(), "decoded": T.StringType(), "ids_sha256": T.StringType(), "decoded_sha256": T.StringType()}
    make = {
        "n_tokens": lambda i, t: len(i) // 4, "ids": lambda i, t: i, "decoded": lambda i, t: t,
        "ids_sha256": lambda i, t: hashlib.sha256(i).hexdigest(), "decoded_sha256": lambda i, t: hashlib.sha256(t.encode()).hexdigest(),
    }
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), *(T.StructField(k, kinds[k]) for k in keep)])
    arrow = {"n_tokens": pa.int64(), "ids": pa.binary()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = as_texts(b.column(1))
            rows: list[tuple] = []
            held: list[str] = []
            size = 0
            for t in [*texts, None]:
                if t is None or (held and size + len(t) > CHUNK_CHARS):
                    rows += [tuple(make[k](i, d) for k in keep) for i, d in model(path).encode_many(held)]
                    held, size = [], 0
                if t is not None:
                    held.append(t)
                    size += len(t)
            columns = [pa.array([r[k] for r in rows], arrow.get(name, pa.string())) for k, name in enumerate(keep)]
            yield pa.RecordBatch.from_arrays([b.column(0), *columns], names=schema.names)

    return docs.select(id_col, F.col(text_col).cast("string")).mapInArrow(run, schema)
