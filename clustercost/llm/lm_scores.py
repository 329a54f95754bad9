"""Stupid-backoff scores of whole documents from the n-gram counts of the whole corpus.

Every n-gram of order 1 to ``order`` has its exact count, whatever the corpus size.  A word after
its context is scored with the longest n-gram that occurs ``least`` times or more, as
``backoff**skipped * C(n-gram) / C(its context)``; the last resort is ``C(word) / tokens``.  (An n-gram
that occurs once occurs in the scored text only, so it is no evidence; ``least`` = 2 passes it over.)
Log probabilities are held in fixed point (1/4096), so sums are exact integers in whatever order they are added.

The relations are: exploded n-grams ``(block, order, hash, tf)``, distinct in a block of documents;
count tables ``(order, hash) -> count``, dealt to partitions by ranges of the 64-bit hash; their
join; and sums by document.  One row of the exploded relation would cost a shuffle some 14 bytes
and there are over two for every word of the corpus, so rows with one (block, hash range) travel as one packed
row: sorted hashes as differences, counts as byte planes.

1. ``_asked``: each block explodes to its distinct n-grams, and one packed row goes to each hash range.
2. ``_answered``: a range holds all occurrences of its n-grams; it sums its part of the count
   tables, joins it to the packed rows, and answers each block in the order it asked in.
3. ``_scored``: a block's home meets its word sequence (``_stated``) and its answers, and sums the log
   probabilities of each document.

An n-gram that every document holds is one entry of a block, so no row or partition grows with its
frequency.  A block is known by a hash of its contents: if the table changes between its two
readings the job fails, and never mixes counts.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .exchange import arrow_map, partitions_for
from .tokens import ALNUM_WORDS, LOWER, U, Words, blocks, mix, text_bytes

ORDER = 3
BACKOFF = 0.4
LEAST = 2
UNIT = 4096
#: n-grams of a hash range that one task holds at a time, about.
RANGE_ROWS = 6_000_000
#: Text of a block, in bytes; larger blocks have fewer distinct n-grams, and take some ten times their size in a worker.
BLOCK_BYTES = 12 << 20

_ROWS = "home int, block bigint, place int, data binary"


class Block:
    """A run of whole documents: ids, words, and the distinct n-grams of each order."""

    def __init__(self, ids: np.ndarray, null: np.ndarray, count: np.ndarray, values: np.ndarray):
        self.ids, self.null, self.count, self.values = ids, null, count, values
        self.row = np.repeat(np.arange(len(count), dtype=np.int32), count)

    def runs(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Places of the last words of all runs of ``k`` words inside one document, and the runs' hashes."""
        n = len(self.values)
        if n < k:
            return np.empty(0, np.int64), np.empty(0, U)
        first = np.flatnonzero(self.row[: n - k + 1] == self.row[k - 1 :]) if k > 1 else np.arange(n)
        h = self.values[first]
        for i in range(1, k):
            h = mix(h * U(0x9E3779B97F4A7C15) + self.values[first + i])
        return first + (k - 1), mix(h + U(k))

    def name(self) -> int:
        """A hash of the contents."""
        parts = [mix(self.ids.view(U) + np.arange(len(self.ids), dtype=U)), mix(self.count.astype(U) * U(3) + np.arange(len(self.ids), dtype=U)), mix(self.values + np.arange(len(self.values), dtype=U))]
        return int(np.array([np.bitwise_xor.reduce(mix(p + U(i)), initial=U(0)) for i, p in enumerate(parts)]).sum().view(np.int64))


def _blocks(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[Block]:
    held: list[tuple[np.ndarray, ...]] = []
    size = 0
    for batch in batches:
        data, offsets = text_bytes(batch.column(1))
        ids, null = batch.column(0).fill_null(0).to_numpy(), ~np.asarray(batch.column(0).is_valid())
        for low, high in blocks(offsets):
            words = Words(LOWER[data[offsets[low] : offsets[high]]], offsets[low : high + 1] - offsets[low], ALNUM_WORDS)
            held.append((ids[low:high], null[low:high], words.count, words.hashes(7)))
            size += int(offsets[high] - offsets[low])
            if size >= most:
                yield Block(*map(np.concatenate, zip(*held, strict=True)))
                held, size = [], 0
    if held:
        yield Block(*map(np.concatenate, zip(*held, strict=True)))


def _packed(values: np.ndarray) -> bytes:
    """Numbers as byte planes, as many as the largest needs; planes of uneven bytes are compressed."""
    raw = np.ascontiguousarray(values.astype("<u8")).view(np.uint8).reshape(-1, 8)
    width = (int(values.max()).bit_length() + 7) // 8 if len(values) else 0
    out = [bytes([width]), len(values).to_bytes(4, "little")]
    for i in range(width):
        plane = raw[:, i].tobytes()
        share = np.bincount(raw[:, i], minlength=256) / len(values)
        if -(share[share > 0] * np.log2(share[share > 0])).sum() < 7.5 and len(values) > 64:
            plane = min(plane, zlib.compress(plane, 1), key=len)
        out += [len(plane).to_bytes(4, "little"), plane]
    return b"".join(out)


def _unpacked(data: bytes, at: int) -> tuple[np.ndarray, int]:
    width, n = data[at], int.from_bytes(data[at + 1 : at + 5], "little")
    at += 5
    out = np.zeros((n, 8), np.uint8)
    for i in range(width):
        size = int.from_bytes(data[at : at + 4], "little")
        plane = data[at + 4 : at + 4 + size]
        out[:, i] = np.frombuffer(plane if size == n else zlib.decompress(plane), np.uint8)
        at += 4 + size
    return out.reshape(-1).view("<u8"), at


def _bounds(ranges: int) -> np.ndarray:
    """The first hash of each range."""
    return np.array([-(-(i << 64) // ranges) for i in range(ranges)], U)


def _rows(rows: list[tuple[int, int, int, bytes]]) -> Iterator[pa.RecordBatch]:
    for a in range(0, len(rows), 64):
        home, block, place, data = zip(*rows[a : a + 64], strict=True)
        yield pa.RecordBatch.from_arrays([pa.array(home, pa.int32()), pa.array(block, pa.int64()), pa.array(place, pa.int32()), pa.array(data, pa.binary())], names=["home", "block", "place", "data"])


def _home(block: int, homes: int) -> int:
    return int(mix(np.array([block], np.int64).view(U))[0] % U(homes))


def _asked(batches: Iterator[pa.RecordBatch], order: int, ranges: int, most: int) -> Iterator[pa.RecordBatch]:
    """For each block and hash range, the block's distinct n-grams of each order with their counts in it."""
    bounds = _bounds(ranges)
    for block in _blocks(batches, most):
        name, parts = block.name(), [[] for _ in range(ranges)]
        some = np.zeros(ranges, bool)
        for k in range(1, order + 1):
            h, tf = np.unique(block.runs(k)[1], return_counts=True)
            edges = np.append(np.searchsorted(h, bounds), len(h))
            some |= np.diff(edges) > 0
            for i, (a, b) in enumerate(zip(edges[:-1], edges[1:], strict=True)):
                parts[i].append(_packed(np.diff(h[a:b], prepend=bounds[i])) + _packed(tf[a:b] - 1))
        yield from _rows([(_home(name, ranges), name, i, b"".join(parts[i])) for i in np.flatnonzero(some).tolist()])


def _answered(batches: Iterator[pa.RecordBatch], order: int) -> Iterator[pa.RecordBatch]:
    """A hash range's count tables, joined to what each block asked: counts (less one) in the order asked."""
    ranges: dict[int, list[tuple]] = {}
    for batch in batches:
        for row in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
            ranges.setdefault(row[2], []).append(row)
    for place in sorted(ranges):
        yield from _joined(ranges.pop(place), order)


def _joined(held: list[tuple], order: int) -> Iterator[pa.RecordBatch]:
    at = [0] * len(held)
    answers: list[list[bytes]] = [[] for _ in held]
    for _ in range(order):
        asked, times = [], []
        for i, row in enumerate(held):
            steps, at[i] = _unpacked(row[3], at[i])
            tf, at[i] = _unpacked(row[3], at[i])
            asked.append(np.cumsum(steps, dtype=U))
            times.append(tf)
        kinds, place = np.unique(np.concatenate(asked), return_inverse=True)
        count = np.bincount(place, np.concatenate(times) + U(1), minlength=len(kinds)).astype(np.int64)
        edge = 0
        for i, h in enumerate(asked):
            answers[i].append(_packed(count[place[edge : edge + len(h)]] - 1))
            edge += len(h)
    for i, row in enumerate(held):
        yield from _rows([(row[0], row[1], row[2], b"".join(answers[i]))])


def _stated(batches: Iterator[pa.RecordBatch], homes: int, most: int) -> Iterator[pa.RecordBatch]:
    """Each block's documents and word sequence, for its home: numbers into its distinct words, the commonest first."""
    for block in _blocks(batches, most):
        h, at, n = np.unique(block.values, return_inverse=True, return_counts=True)
        common = np.argsort(-n, kind="stable")
        number = np.empty(len(h), np.int64)
        number[common] = np.arange(len(h))
        data = _packed(block.ids.view(U)) + _packed(block.null) + _packed(block.count) + _packed(h[common]) + _packed(number[at])
        name = block.name()
        yield from _rows([(_home(name, homes), name, -1, data)])


def _log_scores(block: Block, counts: list[np.ndarray], tokens: int, backoff: float, least: int) -> np.ndarray:
    """Fixed-point log probabilities, summed by document."""
    n, order = len(block.values), len(counts)
    at = np.arange(n) - np.repeat(np.cumsum(block.count) - block.count, block.count)
    by_order = []
    for k, answer in enumerate(counts, 1):
        last, h = block.runs(k)
        kinds, place = np.unique(h, return_inverse=True)
        if len(kinds) != len(answer):
            raise RuntimeError("the table of documents changed between two readings of it; checkpoint it first")
        c = np.zeros(n, np.int64)
        c[last] = answer[place]
        by_order.append(c)
    context = np.minimum(at, order - 1)
    p = backoff**context * by_order[0] / tokens
    for k in range(2, order + 1):
        some = np.flatnonzero(by_order[k - 1] >= least)
        p[some] = backoff ** (context[some] + 1 - k) * by_order[k - 1][some] / by_order[k - 2][some - 1]
    fixed = np.rint(np.log(p) * UNIT) if n else p
    return np.bincount(block.row, fixed, minlength=len(block.count)).astype(np.int64)


def _scored(batches: Iterator[pa.RecordBatch], order: int, tokens: int, backoff: float, least: int) -> Iterator[pa.RecordBatch]:
    """Rows sorted by block, then place: a block's statement, and the answers of all hash ranges in order."""
    now, stated, answers = None, [], {}

    def settle() -> Iterator[pa.RecordBatch]:
        counts: list[list[np.ndarray]] = [[] for _ in range(order)]
        for place in sorted(answers):
            at = 0
            for k in range(order):
                part, at = _unpacked(answers[place], at)
                counts[k].append(part.astype(np.int64) + 1)
        whole = [np.concatenate(c) if c else np.empty(0, np.int64) for c in counts]
        for data in stated:
            at, parts = 0, []
            for _ in range(5):
                part, at = _unpacked(data, at)
                parts.append(part)
            ids, null, count, h, number = parts
            block = Block(ids.view(np.int64), null.astype(bool), count.astype(np.int64), h[number.astype(np.int64)])
            total = _log_scores(block, whole, tokens, backoff, least)
            yield pa.RecordBatch.from_arrays([pa.array(block.ids, pa.int64(), mask=block.null), pa.array(total), pa.array(block.count)], names=["doc_id", "score", "n_words"])

    for batch in batches:
        for block, place, data in zip(*(batch.column(i).to_pylist() for i in (1, 2, 3)), strict=True):
            if block != now and now is not None:
                yield from settle()
                stated, answers = [], {}
            now = block
            if place < 0:
                stated.append(data)
            else:
                answers[place] = data
    if now is not None:
        yield from settle()


def token_count(documents: DataFrame) -> int:
    """Words of all texts."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = 0
        for batch in batches:
            data, offsets = text_bytes(batch.column(0))
            n += sum(len(Words(LOWER[data[offsets[a] : offsets[b]]], offsets[a : b + 1] - offsets[a], ALNUM_WORDS).start) for a, b in blocks(offsets))
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])

    return arrow_map(documents.select("text"), count, "n bigint").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]


def score_documents(documents: DataFrame, backoff: float = BACKOFF, least: int = LEAST, order: int = ORDER, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Per document row: ``doc_id, n_words, log_score`` and ``mean_log`` (per word, rounded to 6 places).

    Null and empty texts have no words, log_score 0 and a null mean; null ids stay null.  Repeated rows count as often
    as they occur and score alike; rows of one doc_id and different texts are separate rows; an
    empty table gives no rows; columns other than doc_id and text are not read.  There are no ties.
    """
    docs = documents.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    tokens = max(1, token_count(docs))
    n = partitions_for(docs.sparkSession, order * tokens, RANGE_ROWS)
    asked = arrow_map(docs, lambda it: _asked(it, order, n, block_bytes), _ROWS).repartitionById(n, "place")
    answers = arrow_map(asked, lambda it: _answered(it, order), _ROWS)
    met = answers.unionByName(arrow_map(docs, lambda it: _stated(it, n, block_bytes), _ROWS)).repartitionById(n, "home").sortWithinPartitions("block", "place")
    sums = arrow_map(met, lambda it: _scored(it, order, tokens, backoff, least), "doc_id bigint, score bigint, n_words bigint")
    score = F.col("score") / UNIT
    return sums.select("doc_id", "n_words", F.round(score, 4).alias("log_score"), F.round(score / F.nullif("n_words", F.lit(0)), 6).alias("mean_log"))
