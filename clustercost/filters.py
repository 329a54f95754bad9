"""Filters of bounded size over 64-bit hashes, and hashes that occur twice found from a few bytes each."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

U = np.uint64
#: Parts that packed hashes are dealt over (a power of two), bits that stay in a part, and hashes packed at once.
PARTS_LOG, REST, PACKED = 10, 32, 1 << 20
PACKED_SCHEMA = "part int, hashes binary"


class HashFilter:
    """A bitmap of 64-bit hashes: it may pass others, and never loses a member."""

    def __init__(self, words: np.ndarray, bits: int):
        self.words, self.bits = words, bits

    def passes(self, hashes: np.ndarray) -> np.ndarray:
        slot = hashes.astype(U) >> U(64 - self.bits)
        return (self.words[(slot >> U(6)).astype(np.int64)] >> (slot & U(63))) & U(1) == U(1)


def hash_filter(hashes: DataFrame, column: str, most_bits: int = 29) -> HashFilter:
    """A filter of a bigint hash column, 64 slots a value, at most ``2**most_bits`` bits (64 MB by default).

    The size bound holds at any input size: a fuller filter passes more, and what it passes
    is decided exactly later.  The bitmap is put together by a distributed bit-or; only
    its words reach the driver.
    """
    bits = min(most_bits, max(10, int(64 * max(1, hashes.count())).bit_length()))
    slot = F.shiftrightunsigned(F.col(column), 64 - bits)
    words = hashes.select(F.shiftright(slot, 6).alias("at"), F.expr(f"shiftleft(1L, CAST(shiftrightunsigned({column}, {64 - bits}) & 63 AS INT))").alias("bit")).groupBy("at").agg(F.bit_or("bit").alias("bits"))
    got = words.toArrow()
    out = np.zeros(1 << (bits - 6), U)
    out[got.column("at").to_numpy()] = got.column("bits").to_numpy().view(U)
    return HashFilter(out, bits)


def _mixed(hashes: np.ndarray) -> np.ndarray:
    """One to one, with even first bits: smallest hashes crowd at low values."""
    return hashes.view(U) * U(0x9E3779B97F4A7C15)


class Repeats:
    """Passes every hash that occurs twice, and few others."""

    def __init__(self, filter: HashFilter):
        self.filter = filter

    def passes(self, hashes: np.ndarray) -> np.ndarray:
        return self.filter.passes(_mixed(hashes))


def packed(hashes: Iterator[np.ndarray]) -> Iterator[pa.RecordBatch]:
    """Rows ``part, hashes``: 42 bits of each hash, ten as the part and four bytes in its row; a hash of one row goes at most twice."""
    held, n = [], 0

    def rows() -> pa.RecordBatch:
        h = np.sort(_mixed(np.concatenate(held)) >> U(64 - PARTS_LOG - REST))
        h = h[np.append([True, True], h[2:] != h[:-2])[: len(h)]]
        part, rest = (h >> U(REST)).astype(np.int32), h.astype(np.uint32)
        first = np.flatnonzero(np.diff(part, prepend=-1))
        data = pa.Array.from_buffers(pa.binary(), len(first), [None, pa.py_buffer((np.append(first, len(h)) * 4).astype(np.int32)), pa.py_buffer(rest)])
        return pa.RecordBatch.from_arrays([pa.array(part[first]), data], names=["part", "hashes"])

    for some in hashes:
        if len(some):
            held.append(some)
            n += len(some)
        if n >= PACKED:
            yield rows()
            held, n = [], 0
    if n:
        yield rows()


def repeats(rows: DataFrame) -> Repeats:
    """The hashes of ``packed`` rows that occur twice; each part is sorted in one group."""

    def twice(table: pa.Table) -> pa.Table:
        h = np.sort(np.concatenate([np.frombuffer(x.as_buffer(), np.uint32) for x in table.column(1)]))
        h = h[:-1][(h[1:] == h[:-1]) & np.append(True, h[1:-1] != h[:-2])[: len(h) - 1]] if len(h) > 1 else h[:0]
        full = ((U(table.column(0)[0].as_py()) << U(REST)) | h.astype(U)) << U(64 - PARTS_LOG - REST)
        return pa.table({"hash": pa.array(full.view(np.int64))})

    found = rows.groupBy("part").applyInArrow(twice, "hash bigint").persist()
    out = Repeats(hash_filter(found, "hash"))
    found.unpersist()
    return out
