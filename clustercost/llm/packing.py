"""Best-fit packing of token pieces, planned on the histogram of their lengths.

Documents are tokenised once, to pieces of at most ``capacity`` ids; only longer documents
are cut, and their first piece takes the remainder.  The plan never sees a document: it
runs best-fit decreasing over *counts* (at most ``capacity`` lengths, at most three bin
groups more for each), on the driver.  Each piece then finds its slot by a join on its rank
within its length.  Ranks come from salted groups and their prefix counts, so a length that
half of the pieces share is ranked by many tasks.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .exchange import arrow_map, checkpointed
from .tokens import text_bytes

CAPACITY = 1024
END = 2

PIECES = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint"


class Encoder:
    """Token ids of a public tokenizer file, through its fast byte-pair form where that is sure to agree.

    Both libraries hold the same vocabulary and pattern; they may differ in what their
    Unicode tables call a letter, so a text with characters beyond U+023F, or with a
    special token's string, goes to the tokenizer file itself.
    """

    def __init__(self, name: str = "byte_bpe_50k"):
        import base64

        import public_tokenizers
        import tiktoken
        from tokenizers import Tokenizer

        self.full = Tokenizer.from_file(public_tokenizers.path(f"{name}.json"))
        with open(public_tokenizers.path(f"{name}.tiktoken"), "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        self.fast = tiktoken.Encoding(name, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def __call__(self, text: str, latin: bool) -> np.ndarray:
        if latin and "<|" not in text:
            try:
                return np.array(self.fast.encode_ordinary(text), "<u4")
            except Exception:  # the pattern engine gives up on some very long runs
                pass
        return np.array(self.full.encode(text, add_special_tokens=False).ids, "<u4")


_encoders: dict[str, Encoder] = {}


def encoder(name: str) -> Encoder:
    """One encoder a worker: its vocabulary takes a second to load."""
    if name not in _encoders:
        _encoders[name] = Encoder(name)
    return _encoders[name]


def first_length(total: int, capacity: int) -> int:
    return total if total <= capacity else (total % capacity or capacity)


def _pieces(batches: Iterator[pa.RecordBatch], capacity: int, end: int, tokenizer: str) -> Iterator[pa.RecordBatch]:
    encode = encoder(tokenizer)
    for batch in batches:
        ids, texts = batch.column(0), batch.column(1)
        data, offsets = text_bytes(texts)
        high = np.zeros(len(ids), np.uint8)
        full = np.flatnonzero(np.diff(offsets))
        if len(full):
            high[full] = np.maximum.reduceat(data, offsets[:-1][full])
        out: list[list] = [[], [], [], [], []]
        for i, text in enumerate(texts):
            tokens = encode(text.as_py() or "", high[i] < 0xC9)
            tokens = np.append(tokens, np.uint32(end)).astype("<u4")
            raw, total, at, piece = tokens.tobytes(), len(tokens), 0, 0
            size = first_length(total, capacity)
            while at < total:
                for column, value in zip(out, (i, piece, at, size, zlib.crc32(raw[4 * at : 4 * (at + size)])), strict=True):
                    column.append(value)
                at, piece, size = at + size, piece + 1, capacity
        yield pa.RecordBatch.from_arrays(
            [ids.take(pa.array(out[0], pa.int64())).cast(pa.int64()), pa.array(out[1], pa.int32()), *(pa.array(x, pa.int64()) for x in out[2:])], names=["doc_id", "piece", "start", "length", "ids_crc32"]
        )


def pieces(documents: DataFrame, capacity: int = CAPACITY, end: int = END, tokenizer: str = "byte_bpe_50k") -> DataFrame:
    docs = documents.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return arrow_map(docs, lambda it: _pieces(it, capacity, end, tokenizer), PIECES)


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int]]:
    """Best-fit decreasing over counts: ``(length, rank_from, rank_to, sequence, per_bin, offset)``.

    Ranks ``rank_from <= r < rank_to`` of a length fill the bins from number ``sequence`` on,
    ``per_bin`` of them one after another in each, from ``offset`` on.
    """
    free: dict[int, list[list[int]]] = {}  # free space -> [first bin, bins]
    out: list[tuple[int, int, int, int, int, int]] = []
    bins = 0
    for length in sorted(counts, reverse=True):
        left, rank = counts[length], 0
        while left:
            space = min((s for s in free if s >= length), default=None)
            if space is None:
                space, per = capacity, capacity // length
                group = [bins, -(-left // per)]
                bins += group[1]
            else:
                group = free[space].pop()
                if not free[space]:
                    del free[space]
                per = space // length
            for first, n, each in ((group[0], min(group[1], left // per), per), (group[0] + min(group[1], left // per), 1, left % per)):
                if n <= 0 or each <= 0 or first >= group[0] + group[1]:
                    continue
                out.append((length, rank, rank + n * each, first, each, capacity - space))
                rank, left = rank + n * each, left - n * each
                group = [first + n, group[0] + group[1] - first - n]
                if rest := space - each * length:
                    free.setdefault(rest, []).append([first, n])
            if group[1]:
                free.setdefault(space, []).append(group)
    return out


def pack(parts: DataFrame, capacity: int = CAPACITY, salts: int | None = None) -> DataFrame:
    """``parts`` with ``sequence_id`` and ``offset``; it is read twice, so it should be a written table."""
    spark: SparkSession = parts.sparkSession
    if salts is None:
        salts = max(64, parts.count() // 1_000_000)
    salted = parts.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)))
    cells = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    totals = {r["length"]: r["n"] for r in cells.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # one row a length
    slots = spark.createDataFrame(plan(totals, capacity) or [(0, 0, 0, 0, 1, 0)], "length bigint, low bigint, high bigint, first bigint, per_bin bigint, place bigint")
    before = F.coalesce(F.sum("n").over(Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = cells.select("length", "salt", before.alias("before"))
    within = F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32")) - 1
    ranked = salted.withColumn("within", within).join(offsets, ["length", "salt"]).withColumn("rank", F.col("before") + F.col("within"))
    inside = F.col("rank") - F.col("low")
    placed = ranked.join(F.broadcast(slots), "length").where("rank >= low AND rank < high")  # at most a few thousand slots, by the plan's bound
    return placed.withColumn("sequence_id", F.expr("first + (rank - low) DIV per_bin")).withColumn("offset", F.col("place") + inside % F.col("per_bin") * F.col("length")).select(*parts.columns, "sequence_id", "offset")


def pack_documents(documents: DataFrame, capacity: int = CAPACITY, end: int = END, tokenizer: str = "byte_bpe_50k") -> DataFrame:
    """Per piece: ``doc_id, piece, start, length, ids_crc32, sequence_id, offset``.

    A document's ids are its text's and then ``end``; a null or empty text has the end id
    alone.  Repeated rows and null ids are packed like any other row; an empty table gives no
    pieces; columns other than doc_id and text are not read.
    """
    return pack(checkpointed(pieces(documents, capacity, end, tokenizer)), capacity)
