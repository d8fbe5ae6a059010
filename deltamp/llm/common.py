"""Helpers shared by the corpus operators: table access, durable cuts, bytes and word hashes."""

from __future__ import annotations

import tempfile

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# Fixed value: the bytes that separate words in every contract of this package.
WORD_BREAKS = b" \t\n\x0b\x0c\r"
WORD_CLASS = r"[^\x20\x09-\x0D]+"

_IS_BREAK = np.zeros(256, bool)
_IS_BREAK[list(WORD_BREAKS)] = True
_BYTE_BASE = 0x9E3779B97F4A7C15
_WORD_BASE = 0xD6E8FEB86659FD93


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, else the context's checkpoint folder.

    Where neither is set, a session on one machine gets a temporary folder; on a cluster that is an error,
    as executors couldn't read what the driver's machine holds.
    """
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir", "") or sc.getCheckpointDir()
    if named:
        return named
    if not sc.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    sc.setCheckpointDir(tempfile.mkdtemp(prefix="deltamp-"))
    return sc.getCheckpointDir()


def settle(df: DataFrame) -> DataFrame:
    """Cut the lineage through the shared checkpoint folder, so lost executors cost no recomputation."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def size_units(df: DataFrame, text_col: str, *unit_bytes: int, least: int = 16) -> list[int]:
    """How many units of so many bytes the texts fill, for each unit; one pass over their lengths.

    The optimiser's estimate isn't used: it multiplies over joins and is unknown for local rows.
    """
    size = df.agg(F.sum(F.octet_length(F.col(text_col).cast("string")))).first()[0] or 0
    return [max(least, min(2**30, size // unit)) for unit in unit_bytes]


def as_bytes(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of a string column; null counts as empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def as_texts(column: pa.Array) -> list[str]:
    return [x or "" for x in column.to_pylist()]


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser, applied to each element."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class _Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 2**64)
        self.up = self.down = np.ones(1, np.uint64)

    def reach(self, n: int) -> None:
        if len(self.up) < n:
            n = max(n, 2 * len(self.up))
            with np.errstate(over="ignore"):
                for name, base in (("up", self.base), ("down", self.inverse)):
                    steps = np.full(n, base, np.uint64)
                    steps[0] = 1
                    setattr(self, name, np.multiply.accumulate(steps))


_BYTES, _WORDS = _Powers(_BYTE_BASE), _Powers(_WORD_BASE)


def word_spans(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Byte starts and ends of the words of one text."""
    solid = np.zeros(len(raw) + 2, np.int8)
    solid[1:-1] = ~_IS_BREAK[np.frombuffer(raw, np.uint8)]
    step = np.diff(solid)
    return np.flatnonzero(step == 1), np.flatnonzero(step == -1)


def span_hashes(raw: bytes, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each byte span, from one running polynomial over the text."""
    _BYTES.reach(len(raw) + 1)
    with np.errstate(over="ignore"):
        run = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum((np.frombuffer(raw, np.uint8).astype(np.uint64) + np.uint64(1)) * _BYTES.up[: len(raw)], out=run[1:])
        flat = (run[ends] - run[starts]) * _BYTES.down[starts]
        return mix64(flat + (ends - starts).astype(np.uint64) * np.uint64(_WORD_BASE))


def run_hashes(hashes: np.ndarray, width: int) -> np.ndarray:
    """A hash for each run of width consecutive elements; empty if there are fewer."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    _WORDS.reach(len(hashes) + 1)
    with np.errstate(over="ignore"):
        run = np.zeros(len(hashes) + 1, np.uint64)
        np.cumsum(hashes * _WORDS.up[: len(hashes)], out=run[1:])
        return mix64((run[width:] - run[:n]) * _WORDS.down[:n])


def lower_ascii(column):
    """Lower-case A-Z only, whatever the locale."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return F.translate(column, upper, upper.lower())


def word_hashes_many(raws: list[bytes], lower: bool = False, piece: int = 1 << 18) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of all texts end to end, and how many words each has; worked in cache-sized pieces."""
    flat, sizes, held, size = [], [], [], 0
    for k, raw in enumerate(raws):
        held.append(raw)
        size += len(raw) + 1
        if size >= piece or k == len(raws) - 1:
            joined = b"\n".join(held)
            joined = joined.lower() if lower else joined  # bytes.lower() changes A-Z only
            starts, ends = word_spans(joined)
            flat.append(span_hashes(joined, starts, ends))
            stops = np.cumsum(np.fromiter(map(len, held), np.int64, len(held)) + 1)
            sizes.append(np.diff(np.searchsorted(starts, stops), prepend=0))
            held, size = [], 0
    empty = np.zeros(0, np.int64)
    return np.concatenate([empty.astype(np.uint64), *flat]), np.concatenate([empty, *sizes])
