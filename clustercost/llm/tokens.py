"""Words, hashes and windows of whole Arrow text columns, as numpy arrays.

All functions work on the bytes of many texts at once: a *block* is a run of rows whose
UTF-8 bytes lie one after another.  Word classes that only exclude ASCII characters can be
decided byte by byte, because every byte of a multi-byte character is 0x80 or more.

Hashes are prefix sums ``sum(value[i] * BASE**i)`` modulo 2**64 with an odd base, so any
span's hash is one subtraction and one multiplication by an inverse power; a finaliser
spreads the bits.  They select; where equality decides a result a second hash of other
values, or a direct comparison, goes with it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_powers: dict[int, np.ndarray] = {}


def powers(n: int, base: int = _BASE) -> np.ndarray:
    """``base**0 .. base**(n-1)`` modulo 2**64 (kept, doubled when too short)."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = max(1 << 16, 1 << int(n).bit_length())
        have = np.empty(size, U)
        have[0] = 1
        done = 1
        while done < size:
            step = U(pow(base, done, 1 << 64))
            have[done : 2 * done] = have[:done] * step
            done *= 2
        _powers[base] = have
    return have[:n]


def inverse_powers(n: int) -> np.ndarray:
    return powers(n, _INVERSE)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (a permutation of the 64-bit integers)."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def byte_values(seed: int) -> np.ndarray:
    """A 64-bit value for each byte, from a seed."""
    return mix(np.arange(1, 257, dtype=U) * U(0xD1342543DE82EF95) + U(seed))


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets (n + 1) of a string column; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    if not wide and not pa.types.is_string(column.type):
        column = column.cast(pa.string())
    n = len(column)
    _, offsets, data = column.buffers()
    if n == 0 or data is None:
        return np.empty(0, np.uint8), np.zeros(n + 1, np.int64)
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]]
    return raw, off - off[0]


def blocks(offsets: np.ndarray, most: int = 1 << 20, most_rows: int = 1 << 16) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``most`` bytes and at most ``most_rows`` rows; a longer row is a block of its own."""
    n, at = len(offsets) - 1, 0
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + most, "right")) - 1
        to = min(n, at + most_rows, max(at + 1, to))
        yield at, to
        at = to


def word_table(ranges: list[tuple[int, int]]) -> np.ndarray:
    """True for bytes of words; ``ranges`` are the byte ranges that separate."""
    table = np.ones(256, bool)
    for low, high in ranges:
        table[low : high + 1] = False
    return table


#: The separators of the two word classes.
ALNUM_WORDS = word_table([(0x00, 0x2F), (0x3A, 0x60), (0x7B, 0x7F)])
SPACE_WORDS = word_table([(0x20, 0x20), (0x09, 0x0D)])
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


class Words:
    """The words of a block of rows: byte spans, row of each word, first word of each row."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, table: np.ndarray):
        self.data, self.offsets, self.rows = data, offsets, len(offsets) - 1
        n = len(data)
        if n == 0:
            self.start = self.end = np.empty(0, np.int64)
        else:
            inside = table[data]
            before = np.empty(n, bool)
            before[0] = False
            before[1:] = inside[:-1]
            before[offsets[:-1][offsets[:-1] < n]] = False
            after = np.empty(n, bool)
            after[-1] = False
            after[:-1] = inside[1:]
            ends = offsets[1:]
            after[ends[ends > 0] - 1] = False
            self.start = np.flatnonzero(inside & ~before)
            self.end = np.flatnonzero(inside & ~after) + 1
        self.first = np.searchsorted(self.start, offsets[:-1], "left")
        self.count = np.diff(np.append(self.first, len(self.start)))
        self.row = np.repeat(np.arange(self.rows), self.count)

    def pieces(self, most: int = 1 << 16) -> Iterator[tuple[int, int]]:
        """Runs of words whose bytes number about ``most``: arrays over a run's bytes stay small and in cache."""
        at = 0
        while at < len(self.start):
            to = max(at + 1, int(np.searchsorted(self.end, self.start[at] + most, "right")))
            yield at, to
            at = to

    def hashes(self, seed: int = 1) -> np.ndarray:
        """A 64-bit hash of each word's bytes and length."""
        table, out = byte_values(seed), np.empty(len(self.start), U)
        for a, b in self.pieces():
            low = self.start[a]
            out[a:b] = Spans(table[self.data[low : self.end[b - 1]]])(self.start[a:b] - low, self.end[a:b] - low)
        return out

    def windows(self, values: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        """First words and hashes of all runs of ``size`` words inside one row."""
        n = len(values)
        if n < size:
            return np.empty(0, np.int64), np.empty(0, U)
        at = np.flatnonzero(self.row[: n - size + 1] == self.row[size - 1 :])
        return at, span_hashes(values, at, at + size)


class Spans:
    """Hashes of any spans of a value array, from one array of prefix sums."""

    def __init__(self, values: np.ndarray):
        n = len(values)
        self.prefix = np.empty(n + 1, U)
        self.prefix[0] = 0
        np.cumsum(values * powers(n), out=self.prefix[1:])
        self.back = inverse_powers(n + 1)

    def __call__(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        raw = (self.prefix[end] - self.prefix[start]) * self.back[start]
        return mix(raw + (end - start).astype(U))


def span_hashes(values: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return Spans(values)(start, end)


def covered(n: int, start: np.ndarray, size: int | np.ndarray) -> np.ndarray:
    """Which of n words lie in a span of ``size`` words that begins at one of ``start``."""
    edge = np.zeros(n + 1, np.int32)
    np.add.at(edge, start, 1)
    np.add.at(edge, np.minimum(start + size, n), -1)
    return np.cumsum(edge[:-1]) > 0


class HashSet:
    """Sorted hashes behind a bitmap: most misses cost one lookup."""

    def __init__(self, values: np.ndarray, bits: int = 20):
        self.values = np.unique(values.astype(U))
        self.shift = U(64 - bits)
        self.map = np.zeros(1 << bits, bool)
        self.map[(self.values >> self.shift).astype(np.int64)] = True

    def find(self, probe: np.ndarray) -> np.ndarray:
        """Places in ``probe`` whose hash is in the set."""
        if not len(self.values):
            return np.empty(0, np.int64)
        maybe = np.flatnonzero(self.map[(probe >> self.shift).astype(np.int64)])
        at = np.searchsorted(self.values, probe[maybe])
        at[at == len(self.values)] = 0
        return maybe[self.values[at] == probe[maybe]]
