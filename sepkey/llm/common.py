"""What the training-data operators share: numpy views of Arrow text batches, and hashes of runs of bytes."""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sepkey.sources.stores import durable, map_arrow, scratch, shared_folder, ship, table

__all__ = ["LOWER", "STEP_BYTES", "STEP_ROWS", "Texts", "Words", "byte_class", "durable", "map_arrow", "mix", "per_process", "run_hashes", "scratch", "shared_folder", "ship", "small", "steps", "table", "texts_of"]

#: Bytes of text that one vectorised step holds at a time; a longer document is a step of its own.
STEP_BYTES = 2 << 20
STEP_ROWS = 4096


#: Most bytes that may be broadcast, by an estimate over all rows; larger tables are joined by a shuffle.
BROADCAST_BYTES = 32 << 20


def small(df: DataFrame, row_bytes: Column) -> DataFrame:
    """``df`` (a written table) marked for broadcast if the bytes of its rows, as ``row_bytes`` estimates each, stay under the limit."""
    total = df.agg(F.sum(row_bytes.cast("long"))).first()[0] or 0
    return F.broadcast(df) if total <= BROADCAST_BYTES else df


def per_process(key: tuple, make):
    """A value made once in each Python worker, such as a loaded tokenizer."""
    kept = sys.__dict__.setdefault("_sepkey_kept", {})
    if key not in kept:
        kept[key] = make()
    return kept[key]


class Texts:
    """UTF-8 bytes of some rows: ``data`` (uint8) and ``at`` (row starts, and the end). Nulls are empty."""

    def __init__(self, data: np.ndarray, at: np.ndarray):
        self.data, self.at = data, at

    def __len__(self) -> int:
        return len(self.at) - 1

    def sizes(self) -> np.ndarray:
        return np.diff(self.at)

    def row(self, i: int) -> bytes:
        return self.data[self.at[i] : self.at[i + 1]].tobytes()


def texts_of(column: pa.Array) -> Texts:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, where, data = column.buffers()
    at = np.frombuffer(where, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64) if where else np.zeros(1, np.int64)
    body = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data else np.zeros(0, np.uint8)
    return Texts(body, at - at[0])


def steps(batch: pa.RecordBatch, column: str = "text", size: int = STEP_BYTES):
    """``(rows of the batch, their Texts)`` in steps of about ``size`` bytes and at most STEP_ROWS."""
    whole = texts_of(batch.column(batch.schema.get_field_index(column)))
    lo, n = 0, len(whole)
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(whole.at, whole.at[lo] + size, "right")) - 1)
        hi = min(hi, n, lo + STEP_ROWS)
        a, b = whole.at[lo], whole.at[hi]
        yield batch.slice(lo, hi - lo), Texts(whole.data[a:b], whole.at[lo : hi + 1] - a)
        lo = hi


def byte_class(keep) -> np.ndarray:
    """A table of 256 booleans from a rule over byte values."""
    return np.array([bool(keep(b)) for b in range(256)])


#: Fixed value: bytes with A-Z turned to a-z.
LOWER = np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)], np.uint8)


class Words:
    """Maximal runs of bytes of a class, never across rows: ``start``, ``end`` (positions in the bytes) and ``first``
    (for each row the index of its first word, and at the end the count)."""

    def __init__(self, texts: Texts, inside: np.ndarray):
        is_in = inside[texts.data]
        n = len(is_in)
        before = np.zeros(n + 1, bool)
        before[1:] = is_in
        before[texts.at[:-1]] = False
        after = np.zeros(n + 1, bool)
        after[:n] = is_in
        after[texts.at[1:]] = False
        self.start = np.flatnonzero(is_in & ~before[:n])
        self.end = np.flatnonzero(is_in & ~after[1:]) + 1
        self.first = np.searchsorted(self.start, texts.at)

    def counts(self) -> np.ndarray:
        return np.diff(self.first)


_FULL = np.uint64(0xFFFFFFFFFFFFFFFF)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_STEP = np.uint64(0x9E3779B97F4A7C15)
#: Runs of more bytes are hashed one by one.
_LONG_RUN = 256


def run_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of ``data[start:end]`` for each run: its eight-byte words are mixed in one after another, so that no two runs collide for
    algebraic reasons, as they would under one polynomial. Long runs go through xxHash."""
    size = end - start
    out = mix(size.astype(np.uint64) + _STEP)
    words = np.ndarray((len(data) + 1,), "<u8", data.tobytes() + bytes(8), strides=(1,))
    live = np.flatnonzero((size > 0) & (size <= _LONG_RUN))
    at, left = start[live], size[live]
    while len(live):
        part = words[at] & (_FULL >> ((8 - np.minimum(left, 8)) * 8).astype(np.uint64))
        out[live] = mix((out[live] ^ part) + _STEP)
        more = left > 8
        live, at, left = live[more], at[more] + 8, left[more] - 8
    for i in np.flatnonzero(size > _LONG_RUN).tolist():
        out[i] = xxhash.xxh3_64_intdigest(data[start[i] : end[i]].tobytes())
    return out
