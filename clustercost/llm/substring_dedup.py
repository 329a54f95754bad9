"""Removal of long repeated passages by a compacted de Bruijn graph of token k-mers.

A run of ``window`` words is an edge of the graph; its first and last ``window - 1`` words are the
nodes it joins.  Only edges that occur twice matter, and neighbouring edges are handled together
wherever that loses nothing:

1. each edge is represented by its smallest inner seed (a run of ``seed`` words).  Equal
   edges have equal smallest seeds, so an edge repeats only if its smallest seed occurs at
   two places; about one word in ten yields a seed, and those that occur twice are found from four packed bytes each;
2. consecutive edges with one smallest seed are a *piece* of the text with a source coordinate
   ``(doc, start, edges)``.  Pieces of repeated seeds are counted by content; a piece that occurs
   twice has only repeated edges, and is an *arc* of the graph.  Of the other pieces, those cut by the
   border of a repeated passage, each single edge that occurs twice is an arc of its own;
3. arcs compact to paths by Spark joins (``compacted``): coordinates in order tell which
   arcs follow which; an arc with one successor only, which has that one predecessor only (where
   a text that stops repeating counts as a neighbour), continues its path;
4. the arcs of a path always occur together, so each coordinate of a path's first arc is one
   long repeated span.  Spans meet their texts by key, the words at the coordinate are verified to be
   the arc's by their hash, and the span's words go.

Seeds, pieces and marked documents travel as filters of bounded size that never lose a member; what
they pass in error is decided by exact counts.  Counts, candidates and removal cover all
rows; no group is gathered in one task beyond the spans of one document.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Callable, Iterator
from itertools import compress

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..filters import PACKED_SCHEMA, packed, repeats
from .exchange import HashFilter, arrow_map, checkpointed, fresh, hash_filter, row_key
from .tokens import SPACE_WORDS, Spans, U, Words, blocks, covered, span_hashes, text_bytes

WINDOW = 35
SEED = 16


def _smallest(words: Words, window: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Word hashes, seed hashes (0 where none starts), edge starts, and each edge's seed place."""
    values = words.hashes()
    at, h = words.windows(values, seed)
    n = len(values)
    if n < window:
        return values, np.zeros(n, U), np.empty(0, np.int64), np.empty(0, np.int64)
    seeds = np.zeros(n, U)
    seeds[at] = h
    bits = U(max(1, int(n).bit_length()))
    ranked = ((seeds >> bits) << bits) | np.arange(n, dtype=U)
    span, have, low = window - seed + 1, 1, ranked
    while have < span:
        step = min(have, span - have)
        low = np.minimum(low[: len(low) - step], low[step:])
        have += step
    edges = np.flatnonzero(words.row[: n - window + 1] == words.row[window - 1 :])
    place = (low[edges] & ((U(1) << bits) - U(1))).astype(np.int64)
    return values, seeds, edges, place


def _seeds(batches: Iterator[pa.RecordBatch], window: int, seed: int) -> Iterator[np.ndarray]:
    for batch in batches:
        for _, _, seeds, _, place, _ in _parts(batch, window, seed):
            yield seeds[place[np.flatnonzero(np.diff(place, prepend=-1))]]


def _edge_hashes(batches: Iterator[pa.RecordBatch], window: int, seed: int, keep: HashFilter) -> Iterator[np.ndarray]:
    for batch in batches:
        for _, values, seeds, edges, place, _ in _parts(batch, window, seed):
            at = edges[keep.passes(seeds[place])]
            yield span_hashes(values, at, at + window)


def _path_rows(batches: Iterator[pa.RecordBatch], window: int, seed: int, keep: HashFilter) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for words, values, seeds, edges, place, low in _parts(batch, window, seed):
            new = np.flatnonzero(np.diff(place, prepend=-1))
            count = np.diff(np.append(new, len(place)))
            good = keep.passes(seeds[place[new]])
            start, count = edges[new[good]], count[good]
            if len(start):
                yield _coordinates(batch, words, low, start, {"seed": seeds[place[new[good]]].view(np.int64), "content": span_hashes(values, start, start + count + window - 1).view(np.int64)}, count)


def _edge_rows(batches: Iterator[pa.RecordBatch], window: int, seed: int, keep: HashFilter, contents: HashFilter | None, repeated: HashFilter | None = None) -> Iterator[pa.RecordBatch]:
    """Edges of paths whose seed is in ``keep``, and of ``repeated`` where given; with ``contents``, of those paths only, with coordinates."""
    for batch in batches:
        for words, values, seeds, edges, place, low in _parts(batch, window, seed):
            new = np.flatnonzero(np.diff(place, prepend=-1))
            count = np.diff(np.append(new, len(place)))
            good = keep.passes(seeds[place[new]])
            if contents is not None:
                good &= contents.passes(span_hashes(values, edges[new], edges[new] + count + window - 1))
            at = edges[np.repeat(good, count)]
            if not len(at):
                continue
            first = span_hashes(values, at, at + window)
            if repeated is not None:
                again = repeated.passes(first)
                at, first = at[again], first[again]
            second = (span_hashes(words.hashes(2), at, at + window) >> U(33)).astype(np.int32)
            for a in range(0, len(at), 200_000):
                b = slice(a, a + 200_000)
                columns = {"edge": first[b].view(np.int64), "check": second[b]}
                if contents is None:
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in columns.values()], names=list(columns))
                else:
                    yield _coordinates(batch, words, low, at[b], columns, np.ones(len(at[b]), np.int64))


def _parts(batch: pa.RecordBatch, window: int, seed: int) -> Iterator[tuple]:
    data, offsets = text_bytes(batch.column(batch.schema.get_field_index("text")))
    for low, high in blocks(offsets):
        words = Words(data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low], SPACE_WORDS)
        values, seeds, edges, place = _smallest(words, window, seed)
        if len(edges):
            yield words, values, seeds, edges, place, low


def _coordinates(batch: pa.RecordBatch, words: Words, low: int, start: np.ndarray, columns: dict, count: np.ndarray) -> pa.RecordBatch:
    row = words.row[start]
    place = pa.array(low + row)
    columns = columns | {"doc_id": batch.column(0).take(place), "row_key": batch.column(1).take(place), "start": (start - words.first[row]).astype(np.int32), "edges": count.astype(np.int32)}
    return pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x) for x in columns.values()], names=list(columns))


def keyed(documents: DataFrame) -> DataFrame:
    """Columns ``doc_id, row_key, text``; a null id takes the place of -2**63.

    ``row_key`` tells rows of one doc_id and different texts apart; it is 0 throughout where no
    doc_id repeats, which keeps coordinates small.
    """
    ids = F.coalesce(F.col("doc_id").cast("bigint"), F.lit(-(2**63))).alias("doc_id")
    unique = documents.select(ids).groupBy("doc_id").count().where("count > 1").isEmpty()
    key = F.lit(0).cast("bigint") if unique else row_key()
    return documents.select(ids, key.alias("row_key"), F.col("text").cast("string").alias("text"))


def pieces(docs: DataFrame, window: int = WINDOW, seed: int = SEED) -> DataFrame:
    """Candidate pieces ``seed, content, doc_id, row_key, start, edges`` of ``keyed`` rows.

    Holds every piece of every repeated seed, and few others.
    """
    seeds = arrow_map(docs.select("text"), lambda it: packed(_seeds(it, window, seed)), PACKED_SCHEMA)
    keep = docs.sparkSession.sparkContext.broadcast(repeats(seeds))
    return arrow_map(docs, lambda it: _path_rows(it, window, seed, keep.value), "seed bigint, content bigint, doc_id bigint, row_key bigint, start int, edges int")


def arcs(docs: DataFrame, window: int = WINDOW, seed: int = SEED) -> DataFrame:
    """Coordinates ``arc, doc_id, row_key, start, edges`` of all repeated edges: whole pieces, and single edges of other pieces.

    Counts are written before they are joined, so that both sides of a join are plain
    exchanges, whose hot keys Spark can split.  Edges of four packed bytes give a filter of those that occur
    twice; only single edges that pass it are listed, and only edges that pass the filter of these are counted exactly.
    """
    context = docs.sparkSession.sparkContext
    found = pieces(docs, window, seed)
    counts = checkpointed(found.groupBy("seed", "content").agg(F.count("*").alias("n")))
    single = counts.where("n = 1")
    seeds, contents = context.broadcast(hash_filter(single, "seed")), context.broadcast(hash_filter(single, "content"))
    whole = found.join(counts.where("n > 1").select("seed", "content"), ["seed", "content"]).select(F.col("content").alias("arc"), "doc_id", "row_key", "start", "edges")
    hashes = arrow_map(docs.select("text"), lambda it: packed(_edge_hashes(it, window, seed, seeds.value)), PACKED_SCHEMA)
    twice = context.broadcast(repeats(hashes))
    border = checkpointed(arrow_map(docs, lambda it: _edge_rows(it, window, seed, seeds.value, contents.value, twice.value), "edge bigint, check int, doc_id bigint, row_key bigint, start int, edges int"))
    met = context.broadcast(hash_filter(border, "edge"))
    edges = arrow_map(docs, lambda it: _edge_rows(it, window, seed, seeds.value, None, met.value), "edge bigint, check int")
    again = checkpointed(edges.groupBy("edge", "check").agg(F.count("*").alias("n")).where("n > 1").select("edge", "check"))
    return whole.unionByName(border.join(again, ["edge", "check"]).select(F.col("edge").alias("arc"), "doc_id", "row_key", "start", "edges"))


def _side_by_side(occurrences: DataFrame) -> DataFrame:
    """Without single edges that lie in a whole piece: the filters let some pass in error."""
    before = Window.partitionBy("doc_id", "row_key").orderBy("start", F.desc("edges")).rowsBetween(Window.unboundedPreceding, -1)
    reached = F.max(F.col("start") + F.col("edges")).over(before)
    return occurrences.withColumn("reached", reached).where("reached IS NULL OR start >= reached").drop("reached")


def compacted(occurrences: DataFrame) -> DataFrame:
    """``arc, path``: the number of edges of the path that an arc begins, or 0 where it continues one; arcs on their own are not listed.

    ``occurrences`` are rows ``arc, doc_id, row_key, start, edges`` that do not overlap.  An arc continues a path
    if every occurrence of it follows one and the same arc, every occurrence of which it follows.
    The arcs of a path then have their first occurrences side by side, so once the links are
    joined, a path is a run of links over first occurrences.
    """
    along = Window.partitionBy("doc_id", "row_key").orderBy("start")
    end = F.col("start") + F.col("edges")
    after = F.when(F.lead("start").over(along) == end, F.lead("arc").over(along))
    before = F.when(F.lag(end).over(along) == F.col("start"), F.lag("arc").over(along))
    steps = occurrences.select("*", after.alias("next"), before.alias("prev"))
    only = lambda c: F.when((F.min(c) == F.max(c)) & (F.count(c) == F.count("*")), F.min(c))
    place = F.min(F.struct("doc_id", "row_key", "start"))
    facts = checkpointed(steps.groupBy("arc").agg(only("next").alias("next"), only("prev").alias("prev"), F.first("edges").alias("edges"), place.alias("at")).select("arc", "next", "prev", "edges", "at.*"))
    links = facts.where("next IS NOT NULL").select(F.col("arc").alias("prev"), F.col("next").alias("arc"), F.lit(True).alias("linked"))
    marked = facts.where("next IS NOT NULL OR prev IS NOT NULL").join(links, ["arc", "prev"], "left")
    run = F.sum(F.when(F.col("linked"), 0).otherwise(1)).over(along.rowsBetween(Window.unboundedPreceding, 0))
    total = F.sum("edges").over(Window.partitionBy("doc_id", "row_key", "run"))
    paths = marked.select("arc", "edges", "linked", "doc_id", "row_key", run.alias("run")).select("arc", "edges", "linked", total.alias("total"))
    return paths.where("linked OR total > edges").select("arc", F.when(F.col("linked"), 0).otherwise(F.col("total")).cast("bigint").alias("path"))


def repeated_spans(docs: DataFrame, window: int = WINDOW, seed: int = SEED) -> DataFrame:
    """Coordinates ``doc_id, row_key, start, edges, arc, first`` of repeated paths, and their first arcs with their numbers of edges."""
    found = arcs(docs, window, max(1, min(seed, window)))
    found = checkpointed(_side_by_side(found if _ids_are_unique(docs) else found.distinct()))
    fates = checkpointed(compacted(found))
    spans = found.join(fates, "arc", "left").where("path IS NULL OR path > 0")
    return spans.select("doc_id", "row_key", "start", F.coalesce(F.col("path").cast("int"), F.col("edges")).alias("edges"), "arc", F.col("edges").alias("first"))


def _ids_are_unique(docs: DataFrame) -> bool:
    return docs.where("row_key <> 0").isEmpty()


def _marks(docs: DataFrame, window: int, seed: int) -> tuple[DataFrame, Callable[[Column, Column], Column]]:
    """(``doc_id, row_key, spans`` by document, a test of ids and keys that no document with spans fails)."""
    spans = repeated_spans(docs, window, seed)
    marks = checkpointed(spans.groupBy("doc_id", "row_key").agg(F.collect_list(F.struct("start", "edges", "arc", "first")).alias("spans")))
    keep = docs.sparkSession.sparkContext.broadcast(hash_filter(marks.select(F.xxhash64("doc_id", "row_key").alias("h")), "h"))

    @F.pandas_udf("boolean")
    def marked(h: pd.Series) -> pd.Series:
        return pd.Series(keep.value.passes(h.to_numpy(np.int64).view(U)))

    return marks, lambda doc_id, key: marked(F.xxhash64(doc_id, key))


def _squeezed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts compressed row by row: they cross the shuffle at half the size."""
    for batch in batches:
        texts = [zlib.compress(x.as_buffer(), 1) if x.is_valid else None for x in batch.column(2).cast(pa.binary())]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.binary())], names=["doc_id", "row_key", "text"])


def _cut(raw: bytes, spans: pa.StructArray | None, window: int) -> tuple[list[bytes], list[bytes]]:
    """The words of a text, and those that stay.  Every span's first arc is looked for at its coordinate."""
    words = raw.split()
    if spans is None or not len(spans):
        return words, words
    start, edges, arc, first = (spans.field(x).to_numpy(zero_copy_only=False) for x in ("start", "edges", "arc", "first"))
    found = Words(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]), SPACE_WORDS)
    if len(found.start) != len(words) or (start + edges + window - 1 > len(words)).any() or (Spans(found.hashes())(start, start + first + window - 1) != arc.view(U)).any():
        raise RuntimeError("a span's words are not at its coordinate: the table of documents changed between two readings of it")
    return words, list(compress(words, ~covered(len(words), start, edges + (window - 1))))


def _kept(batches: Iterator[pa.RecordBatch], window: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids, keys, texts, spans = (batch.column(i) for i in range(4))
        rows: dict[str, list] = {"n_words": [], "n_removed": [], "kept": []}
        packed = pa.types.is_binary(texts.type)
        for text, at in zip(texts, spans, strict=True):
            raw = b"" if not text.is_valid else zlib.decompress(text.as_py()) if packed else text.as_buffer().to_pybytes()
            words, kept = _cut(raw, at.values if at.is_valid else None, window)
            rows["n_words"].append(len(words))
            rows["n_removed"].append(len(words) - len(kept))
            rows["kept"].append(b" ".join(kept).decode("utf-8", "surrogatepass"))
        yield pa.RecordBatch.from_arrays([ids, keys, pa.array(rows["n_words"], pa.int64()), pa.array(rows["n_removed"], pa.int64()), pa.array(rows["kept"], pa.string())], names=["doc_id", "row_key", "n_words", "n_removed", "kept"])


_SPANS = "array<struct<start:int,edges:int,arc:bigint,first:int>>"


def remove_repeats(documents: DataFrame, window: int = WINDOW, seed: int = SEED) -> DataFrame:
    """Per document row: ``doc_id, row_key, n_words, n_removed, kept``.

    A word goes if it lies in a run of ``window`` words that also starts anywhere else, the same
    document included; runs are judged on the input.  ``kept`` is the remaining words
    joined by single spaces.  Null and empty texts have no words; a null id stays null.  Repeated rows repeat each
    other's runs, so both lose them; rows with one doc_id and different texts are separate rows.
    An empty table gives an empty result; columns other than doc_id and text are not read.
    There are no ties: all occurrences of a run go.

    Texts without spans are settled where they are read; only the others cross a shuffle.
    """
    docs = keyed(documents)
    marks, marked = _marks(docs, window, seed)
    some = marked(F.col("doc_id"), F.col("row_key"))
    schema = "doc_id bigint, row_key bigint, n_words bigint, n_removed bigint, kept string"
    squeezed = arrow_map(docs.where(some), _squeezed, "doc_id bigint, row_key bigint, text binary")
    joined = squeezed.join(marks, ["doc_id", "row_key"], "left").select("doc_id", "row_key", "text", "spans")
    plain = docs.where(~some).withColumn("spans", F.lit(None).cast(_SPANS))
    out = arrow_map(joined, lambda it: _kept(it, window), schema).unionByName(arrow_map(plain, lambda it: _kept(it, window), schema))
    return out.withColumn("doc_id", F.when(F.col("doc_id") != -(2**63), F.col("doc_id")))


def without_repeats(documents: DataFrame, window: int = WINDOW, seed: int = SEED) -> DataFrame:
    """``documents`` with the repeated passages taken out of ``text``, and ``n_chars`` to match where there is one.

    Texts that lose nothing, null ones too, stay as they are, and so do all other columns.
    """
    docs, names = keyed(documents), documents.columns
    marks, marked = _marks(docs, window, seed)
    row_id, key, spans = (fresh(names, x) for x in ("id of row", "key of row", "spans of row"))
    ids = F.coalesce(F.col("doc_id").cast("bigint"), F.lit(-(2**63)))
    rows = documents.withColumns({row_id: ids, key: F.lit(0).cast("bigint") if _ids_are_unique(docs) else F.xxhash64(ids, F.col("text").cast("string"))})
    some = marked(F.col(row_id), F.col(key))
    named = marks.select(F.col("doc_id").alias(row_id), F.col("row_key").alias(key), F.col("spans").alias(spans))
    joined = rows.where(some).join(named, [row_id, key], "left").select(*names, spans)
    at = names.index("text")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(at).to_pylist()
            for i, found in enumerate(batch.column(len(names))):
                if found.is_valid and len(found.values):
                    texts[i] = b" ".join(_cut(texts[i].encode("utf-8", "surrogatepass"), found.values, window)[1]).decode("utf-8", "surrogatepass")
            columns = list(batch.columns[: len(names)])
            columns[at] = pa.array(texts, columns[at].type)
            yield pa.RecordBatch.from_arrays(columns, names=names)

    out = arrow_map(joined, cut, documents.schema)
    if "n_chars" in names:
        out = out.withColumn("n_chars", F.length("text").cast(documents.schema["n_chars"].dataType))
    return rows.where(~some).select(*names).unionByName(out)


def report(documents: DataFrame, window: int = WINDOW) -> DataFrame:
    out = remove_repeats(documents, window)
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept"), 256).alias("kept_sha256"))


def brute_force(texts: list[str | None], window: int = WINDOW) -> list[tuple[int, int, str]]:
    """The same by a dictionary of all runs, for tests."""
    split: Callable[[str | None], list[bytes]] = lambda x: (x or "").encode().split()
    counts: dict[tuple, int] = {}
    docs = [split(x) for x in texts]
    for words in docs:
        for i in range(len(words) - window + 1):
            run = tuple(words[i : i + window])
            counts[run] = counts.get(run, 0) + 1
    out = []
    for words in docs:
        cut = [False] * len(words)
        for i in range(len(words) - window + 1):
            if counts[tuple(words[i : i + window])] > 1:
                cut[i : i + window] = [True] * window
        kept = b" ".join(w for w, c in zip(words, cut, strict=True) if not c)
        out.append((len(words), sum(cut), hashlib.sha256(kept).hexdigest()))
    return out
