"""Document fingerprints from modular prefix arrays.

A text's prefix array holds ``sum(code[i] * BASE**i) mod P`` for two primes near 2**31.  Any
span's hash is a difference times an inverse power, so spans compare in constant time, and
the longest common extension of two places is a binary search over span equality.

A fingerprint is the hash of the whole text and a sketch of its spans: of all
spans of ``span`` code points, the smallest hash in each of 64 classes.  Two fingerprints'
likeness is the share of classes that agree (1 for equal whole hashes), an estimate of the
share of spans that the two texts have in common.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .exchange import arrow_map
from .tokens import U, mix

#: Two primes below 2**31 and the bases.
PRIMES = (2147483647, 2147483629)
BASES = (1000003, 911382323)
SPAN = 16
CLASSES = 64
_tables: dict[tuple[int, int], np.ndarray] = {}


def _powers(base: int, prime: int, n: int) -> np.ndarray:
    have = _tables.get((base, prime))
    if have is None or len(have) < n:
        size = max(1 << 16, 1 << int(n).bit_length())
        have = np.ones(size, np.int64)
        done = 1
        while done < size:
            have[done : 2 * done] = have[:done] * pow(base, done, prime) % prime
            done *= 2
        _tables[(base, prime)] = have
    return have[:n]


class PrefixArrays:
    """Prefix arrays of a code point array (many texts may lie in it one after another)."""

    def __init__(self, codes: np.ndarray):
        self.n = len(codes)
        values = codes.astype(np.int64) + 1
        self.prefix = []
        for base, prime in zip(BASES, PRIMES, strict=True):
            out = np.zeros(self.n + 1, np.int64)
            np.cumsum(values * _powers(base, prime, self.n) % prime, out=out[1:])
            out %= prime
            self.prefix.append(out)

    def spans(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """A 62-bit hash of each span, the same wherever the span lies."""
        parts = []
        for (base, prime), prefix in zip(zip(BASES, PRIMES, strict=True), self.prefix, strict=True):
            back = _powers(pow(base, -1, prime), prime, self.n + 1)
            parts.append((prefix[end] - prefix[start]) % prime * back[start] % prime)
        return (parts[0].astype(U) << U(31)) | parts[1].astype(U)

    def equal(self, i: int, j: int, size: int) -> bool:
        a = self.spans(np.array([i, j]), np.array([i + size, j + size]))
        return bool(a[0] == a[1])

    def common_extensions(self, i: np.ndarray, j: np.ndarray, most: np.ndarray) -> np.ndarray:
        """Lengths of the longest common extensions to the right of pairs of places, up to ``most``, by binary search."""
        low, high = np.zeros(len(i), np.int64), np.array(most, np.int64)
        while (low < high).any():
            half = (low + high + 1) // 2
            same = self.spans(i, i + half) == self.spans(j, j + half)
            low, high = np.where(same, half, low), np.where(same, high, half - 1)
        return low


def sketch(texts: list[str], span: int = SPAN) -> tuple[np.ndarray, np.ndarray, PrefixArrays, np.ndarray]:
    """Whole-text hashes (2 per text), span sketches (texts x classes, 16 bits; -1 where empty), the prefix arrays and the texts' places."""
    size = np.array([len(x) for x in texts], np.int64)
    codes = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), "<u4")
    arrays = PrefixArrays(codes)
    end = np.cumsum(size)
    start = end - size
    whole = arrays.spans(start, end)
    whole = np.stack([mix(whole + size.astype(U)), mix(whole * U(3) + U(7))], 1)
    low = np.full(len(texts) * CLASSES, np.iinfo(np.uint64).max, U)
    width = np.minimum(size, span)
    count = np.where(size > 0, size - width + 1, 0)
    row = np.repeat(np.arange(len(texts)), count)
    if len(row):
        first = np.cumsum(count) - count
        at = np.arange(len(row)) - first[row] + start[row]
        h = mix(arrays.spans(at, at + width[row]))
        np.minimum.at(low, row * CLASSES + (h >> U(58)).astype(np.int64), h << U(6))
    marks = np.where(low == np.iinfo(np.uint64).max, -1, ((mix(low) >> U(48)).astype(np.int64)))
    return whole, marks.reshape(len(texts), CLASSES), arrays, start


def fingerprints(whole: np.ndarray, marks: np.ndarray) -> list[str]:
    shown = (marks & 0xFFFF).astype(">u2")
    return [f"{a:016x}{b:016x}-{m.tobytes().hex()}" for (a, b), m in zip(whole.tolist(), shown, strict=True)]


def likeness(whole: np.ndarray, marks: np.ndarray, other_whole: np.ndarray, other_marks: np.ndarray) -> np.ndarray:
    used = (marks >= 0) | (other_marks >= 0)
    same = ((marks == other_marks) & used).sum(1) / np.maximum(1, used.sum(1))
    return np.where((whole == other_whole).all(1), 1.0, same)


def edited(text: str, other: str) -> str:
    half = len(text) // 2
    return text[: len(text) - half] + other[:half]


def _rows(batches: Iterator[pa.RecordBatch], most_chars: int = 400_000) -> Iterator[pa.RecordBatch]:
    """Rows sorted within buckets, the row after a bucket's last marked ``tail``: each with its next."""
    held: list[tuple] = []
    size = 0

    def flush(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        pairs = [(rows[i], rows[i + 1]) for i in range(len(rows) - 1) if not rows[i][1] and rows[i][0] == rows[i + 1][0]]
        if not pairs:
            return
        texts, after = [a[3] for a, _ in pairs], [b[3] for _, b in pairs]
        new = [edited(a, b) for a, b in zip(texts, after, strict=True)]
        n = len(texts)
        # a pair's next text is mostly the next pair's own; others are sketched beside them
        following = np.array([i + 1 if i + 1 < n and pairs[i + 1][0] is pairs[i][1] else -1 for i in range(n)])
        extra = np.flatnonzero(following < 0)
        following[extra] = 2 * n + np.arange(len(extra))
        whole, marks, arrays, start = sketch([*texts, *new, *(after[i] for i in extra)])
        mine, yours, theirs = np.arange(n), n + np.arange(n), following
        size = np.array([len(x) for x in texts], np.int64)
        near = [likeness(whole[mine], marks[mine], whole[x], marks[x]) for x in (yours, theirs)]
        common = [arrays.common_extensions(start[mine], start[x], np.minimum(size, y)) for x, y in ((yours, [len(x) for x in new]), (theirs, [len(x) for x in after]))]
        yield pa.RecordBatch.from_arrays(
            [
                pa.array([a[2] for a, _ in pairs], pa.int64()),
                pa.array(size),
                pa.array([hashlib.sha256(x.encode("utf-8", "surrogatepass")).hexdigest() for x in new]),
                pa.array(fingerprints(whole[mine], marks[mine])),
                pa.array(fingerprints(whole[yours], marks[yours])),
                *map(pa.array, near),
                *map(pa.array, common),
            ],
            names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "common_edited", "common_next"],
        )

    for batch in batches:
        bucket, tail, ids, texts = (batch.column(i) for i in range(4))
        for b, t, i, x in zip(bucket.to_pylist(), tail.to_pylist(), ids.to_pylist(), texts, strict=True):
            text = x.as_py() or ""
            held.append((b, t, i, text))
            size += len(text)
            if size >= most_chars:
                yield from flush(held)
                held, size = held[-1:], len(text)
    yield from flush(held)


def fingerprint_documents(documents: DataFrame, per_partition: int = 4) -> DataFrame:
    """Per document row: ``doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next, common_edited, common_next``.

    ``near_*`` are likenesses of fingerprints, ``common_*`` the lengths of the longest common
    beginnings with the edited and the next text, by binary search over span equality.

    The edited text is the text whose last half gives way to the beginning of the next
    document's, in descending order of doc_id; after the last comes the first.  A null
    text is empty; null ids come last in that order, and rows with one doc_id are ordered by a
    hash of their text; a single row is its own next; an empty table gives no rows; further
    columns are not read.

    One range shuffle of the texts: bounds are rows of a hash sample whose size follows the
    number of partitions, and each bound row is sent to its own bucket and, as the row after
    the last, to the bucket before it.
    """
    spark = documents.sparkSession
    docs = documents.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    ids = F.coalesce(F.col("doc_id"), F.lit(-(2**63)))
    keys = docs.select(ids.alias("a"), F.xxhash64("text").alias("b"))
    n_partitions = int(spark.conf.get("spark.sql.shuffle.partitions"))
    wanted = n_partitions * per_partition
    n, top = keys.agg(F.count("*"), F.max(F.struct("a", "b"))).first()
    rate = max(1, n // (wanted * 16))
    found = keys.where(F.pmod(F.xxhash64("a", "b"), F.lit(rate)) == 0).distinct().limit(wanted * 256).collect()
    sample = sorted({(r[0], r[1]) for r in found} - {tuple(top) if top else None}, reverse=True)
    step = max(1, len(sample) // wanted)
    bounds = sample[::step]
    highs = np.array([a for a, _ in bounds], np.int64)
    lows = np.array([b for _, b in bounds], np.int64)

    @F.pandas_udf("array<int>")
    def buckets(a: pd.Series, b: pd.Series) -> pd.Series:
        """Bucket of a row, and of the row it follows where it is a bound (as -1 - bucket)."""
        x, y = a.to_numpy(np.int64), b.to_numpy(np.int64)
        # bounds descend: count those that are at or above the row
        left = np.searchsorted(~highs, ~x, "left")
        right = np.searchsorted(~highs, ~x, "right")
        out = []
        for i in range(len(x)):
            k, end = int(left[i]), int(right[i])
            while k < end and lows[k] >= y[i]:
                k += 1
            place, is_bound = k, k > 0 and highs[k - 1] == x[i] and lows[k - 1] == y[i]
            more = [-1 - (place - 1)] if is_bound else []
            if top is not None and (x[i], y[i]) == (top[0], top[1]):
                more.append(-1 - len(highs))
            out.append([place, *more])
        return pd.Series(out)

    dealt = docs.withColumn("to", F.explode(buckets(ids, F.xxhash64("text"))))
    tail = F.col("to") < 0
    dealt = dealt.select(F.when(tail, -1 - F.col("to")).otherwise(F.col("to")).alias("bucket"), tail.alias("tail"), "doc_id", "text")
    order = dealt.repartition(n_partitions, "bucket").sortWithinPartitions("bucket", "tail", F.desc(F.coalesce("doc_id", F.lit(-(2**63)))), F.desc(F.xxhash64("text")))
    return arrow_map(order, _rows, "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, common_edited bigint, common_next bigint")
