"""Benchmark decontamination by multi-pattern search with block shift tables (Wu and Manber).

Patterns are the runs of 13 consecutive words of each benchmark item (an item of fewer
words is one pattern).  Patterns of one length m are sought together.  A *shift table*, indexed by
the hash of a block of b words, says how far a window may move when that block is its last:
m - b + 1 where no pattern holds the block, else the distance from the block's rightmost place
in any pattern to the pattern's end.  A shift of 0 means that the block ends some pattern: the *suffix
buckets* then name the patterns with this last block, the hash of the whole window leaves few of
them, and a direct comparison of the words confirms.

Many cursors move through a block of texts at once, each over a stretch of one document, so
a step of the search is a few array operations over all cursors.

Patterns travel as broadcast items whose size is checked; a worker builds the tables once.
Beyond ``max_block_mb`` of benchmark text the items are searched in several blocks, each
by a scan of its own that holds one block's tables, and the hits of a document are merged by key.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .exchange import arrow_map, checkpointed, fresh
from .tokens import ALNUM_WORDS, LOWER, Spans, U, Words, blocks, covered, text_bytes

WINDOW = 13
RATIO = 20
BLOCK = 2
STRETCH = 64  # window starts that one cursor covers


class PatternGroup:
    """Shift table and suffix buckets of the patterns of one length."""

    def __init__(self, size: int, found: dict[bytes, set], block: int):
        self.size, self.block = size, min(block, size)
        self.texts = list(found)
        self.items = [sorted(found[x], key=str) for x in self.texts]
        data, offsets = text_bytes(pa.array([x.decode("utf-8", "surrogateescape") for x in self.texts], pa.large_string()))
        words = Words(data, offsets, ALNUM_WORDS)
        spans = Spans(words.hashes())
        starts, reach = words.first, self.size - self.block
        bits = max(12, min(22, int(16 * len(starts) * (reach + 1)).bit_length()))
        self.right = U(64 - bits)
        self.shift = np.full(1 << bits, reach + 1, np.int32)
        for place in range(reach + 1):  # later places have smaller shifts
            at = starts + place
            self.shift[(spans(at, at + self.block) >> self.right).astype(np.int64)] = reach - place
        last = spans(starts + reach, starts + self.size)
        order = np.argsort(last, kind="stable")
        self.suffix, self.pattern = last[order], order
        self.whole = spans(starts, starts + self.size)

    def occurrences(self, words: Words, spans: Spans) -> Iterator[tuple[int, int]]:
        """(first word, pattern) of all occurrences in a block of texts."""
        rows = np.flatnonzero(words.count >= self.size)
        if not len(rows):
            return
        stop = words.first[rows] + words.count[rows] - self.size
        cursors = (stop - words.first[rows]) // STRETCH + 1
        row = np.repeat(np.arange(len(rows)), cursors)
        nth = np.arange(len(row)) - np.repeat(np.cumsum(cursors) - cursors, cursors)
        at = words.first[rows][row] + nth * STRETCH
        end = np.minimum(stop[row], at + STRETCH - 1)
        reach, ended = self.size - self.block, []
        while len(at):
            tail = spans(at + reach, at + self.size)
            step = self.shift[(tail >> self.right).astype(np.int64)]
            if (step == 0).any():
                ended.append((at[step == 0], tail[step == 0]))
            at = at + np.maximum(step, 1)
            some = at <= end
            at, end = at[some], end[some]
        if not ended:
            return
        at, tail = (np.concatenate(x) for x in zip(*ended, strict=True))
        low, high = np.searchsorted(self.suffix, tail, "left"), np.searchsorted(self.suffix, tail, "right")
        some = high > low
        at, low, high = at[some], low[some], high[some]
        whole = spans(at, at + self.size)
        for i in range(len(at)):
            for p in self.pattern[low[i] : high[i]][self.whole[self.pattern[low[i] : high[i]]] == whole[i]].tolist():
                w = int(at[i])
                if b" ".join(words.data[s:e].tobytes() for s, e in zip(words.start[w : w + self.size], words.end[w : w + self.size], strict=True)) == self.texts[p]:
                    yield w, p


class Patterns:
    """Search tables of the items' windows, one group per window length."""

    def __init__(self, items: list[tuple[int, str | None]], window: int = WINDOW, block: int = BLOCK):
        by_length: dict[int, dict[bytes, set]] = {}
        for item, text in items:
            words = split_words(text or "")
            size = min(window, len(words))
            for i in range(len(words) - size + 1 if size else 0):
                by_length.setdefault(size, {}).setdefault(b" ".join(words[i : i + size]), set()).add(item)
        self.groups = [PatternGroup(size, found, block) for size, found in sorted(by_length.items())]

    def search(self, words: Words) -> tuple[np.ndarray, dict[int, set]]:
        """Hit words of a block of texts, and each row's items."""
        spans = Spans(words.hashes())
        hit = np.zeros(len(words.start), bool)
        found: dict[int, set] = {}
        for g in self.groups:
            starts = []
            for w, p in g.occurrences(words, spans):
                starts.append(w)
                found.setdefault(int(words.row[w]), set()).update(g.items[p])
            if starts:
                hit |= covered(len(hit), np.array(starts), g.size)
        return hit, found


def split_words(text: str) -> list[bytes]:
    data = LOWER[np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)]
    words = Words(data, np.array([0, len(data)]), ALNUM_WORDS)
    raw = data.tobytes()
    return [raw[s:e] for s, e in zip(words.start.tolist(), words.end.tolist(), strict=True)]


_built: dict[str, Patterns] = {}


def _patterns(name: str, items: list, window: int) -> Patterns:
    """The tables of a block of items, built once in a worker; another block's tables go."""
    if name not in _built:
        _built.clear()
        _built[name] = Patterns(items, window)
    return _built[name]


def _searcher(documents: DataFrame, items: list, window: int) -> Callable[[pa.Array], Iterator[tuple[int, int, Words, np.ndarray, dict[int, set]]]]:
    """A function of a text column that yields (first row, end, words, hit words, items by row) block by block."""
    shared, name = documents.sparkSession.sparkContext.broadcast(items), uuid.uuid4().hex

    def search(column: pa.Array) -> Iterator[tuple[int, int, Words, np.ndarray, dict[int, set]]]:
        patterns = _patterns(name, shared.value, window)
        data, offsets = text_bytes(column)
        for low, high in blocks(offsets):
            words = Words(LOWER[data[offsets[low] : offsets[high]]], offsets[low : high + 1] - offsets[low], ALNUM_WORDS)
            yield low, high, words, *patterns.search(words)

    return search


def item_blocks(benchmark: DataFrame, max_block_mb: float) -> list[list[tuple[int, str | None]]]:
    """The items in blocks of checked size; each is collected on its own."""
    sized = benchmark.select(F.col("item_id").cast("bigint").alias("item_id"), F.col("text").cast("string").alias("text")).where(F.col("item_id").isNotNull())
    total = sized.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(1, int(-(-total // (max_block_mb * 1e6))))
    if n == 1:
        return [[(r[0], r[1]) for r in sized.collect()]]
    return [[(r[0], r[1]) for r in sized.where(F.pmod(F.xxhash64("item_id"), F.lit(n)) == i).collect()] for i in range(n)]


def _judged(n_hit: Column, n_words: Column, ratio: int) -> Column:
    return (n_hit > 0) & (F.lit(ratio) * n_hit >= n_words)


def contamination(documents: DataFrame, benchmark: DataFrame, window: int = WINDOW, ratio: int = RATIO, max_block_mb: float = 16.0) -> DataFrame:
    """Per document row: ``doc_id, n_words, n_hit, items array<bigint>, contaminated``.

    A document word is hit if it lies in an occurrence of any item window;
    ``contaminated`` is ``n_hit > 0 and ratio * n_hit >= n_words``.
    Null and empty texts have no words and no hits; a null id stays null; repeated rows are judged each for
    itself; items with a null id or without words never match, repeated items match as one; an empty
    benchmark hits nothing; other columns of either table are not read.  There are no ties.
    """
    docs = documents.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    groups = item_blocks(benchmark, max_block_mb)
    if len(groups) == 1:
        search = _searcher(docs, groups[0], window)

        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for low, high, words, hit, found in search(batch.column(1)):
                    n_hit = np.bincount(words.row[hit], minlength=words.rows)
                    items = pa.array([sorted(found.get(i, ()), key=str) for i in range(words.rows)], pa.list_(pa.int64()))
                    yield pa.RecordBatch.from_arrays([batch.column(0).slice(low, high - low), pa.array(words.count, pa.int64()), pa.array(n_hit, pa.int64()), items], names=["doc_id", "n_words", "n_hit", "items"])

        out = arrow_map(docs, scan, "doc_id bigint, n_words bigint, n_hit bigint, items array<bigint>")
    else:
        out = _merged(docs, groups, window)
    return out.withColumn("contaminated", _judged(F.col("n_hit"), F.col("n_words"), ratio))


def _merged(docs: DataFrame, groups: list, window: int) -> DataFrame:
    """Several blocks of items: a scan of the texts for each, whose hits meet by the row's key."""
    keyed = docs.select("doc_id", F.xxhash64("doc_id", "text").alias("key"), "text")

    def hits(items: list) -> DataFrame:
        search = _searcher(docs, items, window)

        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for low, _, words, hit, found in search(batch.column(1)):
                    rows = sorted(found)
                    places = [np.flatnonzero(hit[words.first[i] : words.first[i] + words.count[i]]) for i in rows]
                    yield pa.RecordBatch.from_arrays(
                        [batch.column(0).take(pa.array([low + i for i in rows], pa.int64())), pa.array([list(p) for p in places], pa.list_(pa.int64())), pa.array([sorted(found[i], key=str) for i in rows], pa.list_(pa.int64()))],
                        names=["key", "places", "items"],
                    )

        return arrow_map(keyed.select("key", "text"), scan, "key bigint, places array<bigint>, items array<bigint>")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = text_bytes(batch.column(2))
            sizes = [Words(LOWER[data[offsets[a] : offsets[b]]], offsets[a : b + 1] - offsets[a], ALNUM_WORDS).count for a, b in blocks(offsets)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.concatenate(sizes) if sizes else [], pa.int64())], names=["doc_id", "key", "n_words"])

    found = checkpointed(reduce(DataFrame.unionByName, [hits(g) for g in groups]))
    distinct = lambda c: F.array_sort(F.array_distinct(F.flatten(F.collect_list(c))))
    merged = found.groupBy("key").agg(F.size(distinct("places")).cast("bigint").alias("n_hit"), distinct("items").alias("items"))
    rows = arrow_map(keyed, count, "doc_id bigint, key bigint, n_words bigint").join(merged, "key", "left")
    return rows.select("doc_id", "n_words", F.coalesce("n_hit", F.lit(0).cast("bigint")).alias("n_hit"), F.coalesce("items", F.array().cast("array<bigint>")).alias("items"))


def without_contaminated(documents: DataFrame, benchmark: DataFrame, window: int = WINDOW, ratio: int = RATIO, max_block_mb: float = 16.0) -> DataFrame:
    """The rows of ``documents`` that are not contaminated, with all their columns.

    Null and empty texts stay, repeated rows stay or go together; any further columns pass through.
    """
    groups, names = item_blocks(benchmark, max_block_mb), documents.columns
    if len(groups) > 1:
        key = fresh(names, "key of row")
        text = F.col("text").cast("string")
        ids = documents.select(F.col("doc_id").cast("bigint").alias("doc_id"), text.alias("text"))
        whole = ids.withColumn("doc_id", F.xxhash64("doc_id", "text"))  # rows are known by their keys
        bad = contamination(whole, benchmark, window, ratio, max_block_mb).where("contaminated").select(F.col("doc_id").alias(key)).distinct()
        return documents.withColumn(key, F.xxhash64(F.col("doc_id").cast("bigint"), text)).join(bad, key, "left_anti").select(*names)
    search, at = _searcher(documents, groups[0], window), names.index("text")

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = np.ones(batch.num_rows, bool)
            for low, high, words, hit, _ in search(batch.column(at)):
                n_hit = np.bincount(words.row[hit], minlength=words.rows)
                good[low:high] = ~((n_hit > 0) & (ratio * n_hit >= words.count))
            yield batch.filter(pa.array(good))

    return arrow_map(documents, keep, documents.schema)


def report(documents: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The digest form: item lists as counts and SHA-256 of their sorted strings; rows as in ``contamination``."""
    found = contamination(documents, benchmark)
    ids = F.array_join(F.array_sort(F.transform("items", lambda x: x.cast("string"))), ",")
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("bigint").alias("n_items"), F.sha2(ids, 256).alias("items_sha256"), "contaminated")


def digest(items: list[int]) -> str:
    return hashlib.sha256(",".join(sorted(map(str, items))).encode()).hexdigest()
