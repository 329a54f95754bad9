"""Toxicity by a weighted finite-state pattern grammar with learned weights.

Words are mapped to classes, and five small transducers run together over each clause
(words between punctuation or line breaks):

* *insult* emits a match with the weight of its word or stem;
* *threat* emits a match when a threat verb and a target meet in one clause;
* *target* (a word of address) raises the matches of its clause;
* *negation* marks the matches of its clause that follow within four words;
* *reported speech* (a verb of saying, or quotation marks) marks the matches after it.

A match thus has a context: plain, targeted, negated or reported.  A document's score is a
logistic function of the weights of its distinct matched stems, each scaled by its context.

Stems start from a small lexicon and are learned from labelled rows: a word, or a prefix of
4 to 9 bytes, becomes a stem when it occurs in so many toxic and so few other rows that chance
does not explain it, at the number of features tested.  Context factors are learned in the
same way, from the grammar's own matches.  Only a bounded, documented sample of labelled rows
is read (``most_rows`` rows and ``most_bytes`` of text), chosen by hash.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .exchange import arrow_map, checkpointed
from .tokens import ALNUM_WORDS, HashSet, Spans, U, Words, blocks, byte_values, span_hashes, text_bytes

#: The grammar's lexicon.
INSULTS = "idiot idiots moron morons stupid scum trash loser losers worthless pathetic disgusting clown imbecile dumbass idiota estúpido imbécil basura idiote imbécile crétin ordure abruti dumm dummkopf trottel abschaum versager".split()
THREATS = "kill hurt destroy beat attack burn shoot stab punish töten schlagen vernichten tuer frapper détruire matar golpear destruir".split()
TARGETS = "you your yours yourself they them du dich dir euch ihr tu toi vous te tú usted ustedes vosotros".split()
NEGATIONS = "not no never isn't aren't don't nicht kein keine nie pas jamais aucun nunca jamás".split()
REPORTS = "said says say wrote writes quoted called claims sagte sagt schrieb nannte dit disait écrit dijo dice escribió".split()
PREFIXES = (4, 5, 6, 7, 8, 9)
CONTEXTS = ("plain", "targeted", "negated", "reported")
DEFAULTS = {"plain": 1.0, "targeted": 1.2, "negated": 0.4, "reported": 0.4}
LEXICON_WEIGHT = 4.0
REACH = 4


def texts(documents: DataFrame) -> DataFrame:
    return documents.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))


def _low_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of the texts in lower case."""
    return text_bytes(pc.utf8_lower(column))


def remainder(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string")) % 3


def _features(words: Words) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """(kind, places, hashes): kind 0 is the whole word, else a prefix of so many bytes."""
    size, table = words.end - words.start, byte_values(11)
    kinds = (0, *PREFIXES)
    places = [np.flatnonzero(size > n) for n in kinds]
    hashes = [np.empty(len(at), U) for at in places]
    for a, b in words.pieces():
        low = words.start[a]
        spans = Spans(table[words.data[low : words.end[b - 1]]])
        for n, at, out in zip(kinds, places, hashes, strict=True):
            i, j = np.searchsorted(at, (a, b))
            start = words.start[at[i:j]] - low
            out[i:j] = spans(start, start + n if n else words.end[at[i:j]] - low)
    return list(zip(kinds, places, hashes, strict=True))


def word_hash(word: str, size: int | None = None) -> int:
    raw = np.frombuffer(word.encode(), np.uint8)[:size]
    return int(span_hashes(byte_values(11)[raw], np.array([0]), np.array([len(raw)]))[0])


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Distinct features of each row, as counts over toxic and other rows of a batch."""
    for batch in batches:
        data, offsets = _low_bytes(batch.column(0))
        toxic = batch.column(1).to_numpy(zero_copy_only=False).astype(np.int64)
        for low, high in blocks(offsets):
            words = Words(data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low], ALNUM_WORDS)
            for kind, at, h in _features(words):
                if not len(at):
                    continue
                row = words.row[at]
                order = np.lexsort((row, h))
                h, row = h[order], row[order]
                new = np.append(True, (h[1:] != h[:-1]) | (row[1:] != row[:-1]))
                h, row = h[new], row[new]
                first = np.flatnonzero(np.append(True, h[1:] != h[:-1]))
                bad = np.add.reduceat(toxic[low + row], first)
                rows = np.diff(np.append(first, len(h)))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(first), kind, np.int32)), pa.array(h[first].view(np.int64)), pa.array(bad), pa.array(rows)], names=["kind", "h", "t", "n"])


class Grammar:
    """The stems' weights, context factors and prior; small, and the same size at any input size."""

    def __init__(self, stems: dict[int, dict[int, float]], prior: float):
        self.stems, self.prior, self.factors = stems, prior, dict(DEFAULTS)
        self.ready = False

    def _tables(self) -> None:
        if not self.ready:
            self.sets = {k: HashSet(np.array(list(v), U), 16) for k, v in self.stems.items() if v}
            self.threats, self.targets, self.negations, self.reports = (HashSet(np.array([word_hash(x) for x in w], U), 16) for w in (THREATS, TARGETS, NEGATIONS, REPORTS))
            self.ready = True

    def matches(self, words: Words, breaks: np.ndarray, quotes: np.ndarray) -> list[tuple[int, int, float, str]]:
        """(row, stem, weight, context) of all matches in a block; only clauses with a candidate are walked."""
        self._tables()
        features = _features(words)
        weight: dict[int, tuple[float, int]] = {}
        for kind, at, h in features:
            if kind in self.sets:
                for i in self.sets[kind].find(h).tolist():
                    stem = int(h[i])
                    w = self.stems[kind][stem]
                    place = int(at[i])
                    if place not in weight or w > weight[place][0]:
                        weight[place] = (w, stem)
        whole = features[0][2]
        threat = set(self.threats.find(whole).tolist())
        if not weight and not threat:
            return []
        clause = np.searchsorted(breaks, words.start)
        target, negation, report = (set(x.find(whole).tolist()) for x in (self.targets, self.negations, self.reports))
        out = []
        for key in sorted({(int(words.row[p]), int(clause[p])) for p in [*weight, *threat]}):
            row, c = key
            low = max(int(np.searchsorted(clause, c, "left")), int(words.first[row]))
            high = min(int(np.searchsorted(clause, c, "right")), int(words.first[row] + words.count[row]))
            aimed = any(p in target for p in range(low, high))
            quoted = bool(np.searchsorted(quotes, words.start[low]) < np.searchsorted(quotes, words.end[high - 1]))
            reported, negated = quoted, -REACH - 1
            for p in range(low, high):
                if p in report:
                    reported = True
                if p in negation:
                    negated = p
                hit = weight.get(p) or ((LEXICON_WEIGHT, int(whole[p])) if p in threat and aimed else None)
                if hit:
                    context = "reported" if reported else "negated" if p - negated <= REACH else "targeted" if aimed else "plain"
                    out.append((row, hit[1], hit[0], context))
        return out

    def logit(self, found: list[tuple[int, float, str]]) -> float:
        best: dict[int, float] = {}
        for stem, weight, context in found:
            best[stem] = max(best.get(stem, 0.0), weight * self.factors[context])
        return self.prior + min(20.0, sum(best.values()))


def _blocks_of(batch: pa.RecordBatch, column: int) -> Iterator[tuple[int, int, Words, np.ndarray, np.ndarray]]:
    data, offsets = _low_bytes(batch.column(column))
    stop, quote = np.zeros(256, bool), np.zeros(256, bool)
    stop[[ord(x) for x in ".!?;:,\n()"]] = True
    quote[[ord('"')]] = True
    for low, high in blocks(offsets):
        part = data[offsets[low] : offsets[high]]
        yield low, high, Words(part, offsets[low : high + 1] - offsets[low], ALNUM_WORDS), np.flatnonzero(stop[part]), np.flatnonzero(quote[part])


def _needed(sample: DataFrame, named: dict[tuple[int, int], tuple[float, float]], least: float) -> dict[tuple[int, int], float]:
    """Of the strong features, those that explain enough distinct toxic texts that stronger ones leave unexplained.

    Rare words of a toxic text and its copies look toxic too; the strong stems explain those
    texts, so such words drop out.
    """
    sets = {k: HashSet(np.array([h for kind, h in named if kind == k], U), 16) for k in (0, *PREFIXES)}

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(1)
            for low, _, words, _, _ in _blocks_of(batch, 0):
                for kind, at, h in _features(words):
                    hit = sets[kind].find(h)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(hit), kind, np.int32)), pa.array(h[hit].view(np.int64)), ids.take(pa.array(low + words.row[at[hit]]))], names=["kind", "h", "id"])

    toxic = sample.where("toxic = 1").select("text", F.xxhash64("text").alias("id"))
    held: dict[tuple[int, int], set[int]] = {}
    for r in arrow_map(toxic, found, "kind int, h bigint, id bigint").distinct().collect():  # bounded by the sample's rows and bytes
        held.setdefault((r["kind"], int(np.int64(r["h"]).view(U))), set()).add(r["id"])
    explained: set[int] = set()
    out = {}
    for key in sorted(held, key=lambda k: (-named[k][0], k)):
        if len(held[key] - explained) >= least:
            out[key] = named[key][1]
            explained |= held[key]
    return out


def _contexts(batches: Iterator[pa.RecordBatch], grammar: Grammar) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        toxic = batch.column(1).to_pylist()
        rows: list[tuple[str, int]] = []
        for low, _, words, breaks, quotes in _blocks_of(batch, 0):
            seen = {(row, context) for row, _, _, context in grammar.matches(words, breaks, quotes)}
            rows += [(context, toxic[low + row]) for row, context in seen]
        yield pa.RecordBatch.from_arrays([pa.array([c for c, _ in rows], pa.string()), pa.array([t for _, t in rows], pa.int32())], names=["context", "toxic"])


def fit(documents: DataFrame, labels: DataFrame, most_rows: int = 20_000, most_bytes: int = 128 << 20) -> Grammar:
    """A grammar learned from at most ``most_rows`` labelled rows of remainder 0 or 2, of at most ``most_bytes`` of text, chosen by hash.

    Labels other than 0 and 1 and null ids are passed over; without usable labels the lexicon stands.
    """
    usable = labels.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & (remainder(F.col("doc_id")) != 1))
    chosen = usable.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most_rows)
    found = checkpointed(texts(documents).join(F.broadcast(chosen), "doc_id").select("doc_id", "text", "toxic"))  # at most most_rows labels
    within = found.select("doc_id", "text").groupBy("doc_id").agg(F.sum(F.octet_length("text")).alias("text")).select("doc_id", F.sum("text").over(Window.orderBy(F.xxhash64("doc_id"), "doc_id")).alias("bytes"))  # one row a label
    sample = found.join(F.broadcast(within.where((F.col("bytes") <= most_bytes) | F.col("bytes").isNull()).select("doc_id")), "doc_id").select("text", "toxic")
    total, bad = sample.agg(F.count("*"), F.coalesce(F.sum("toxic"), F.lit(0))).first()
    stems: dict[int, dict[int, float]] = {0: {word_hash(x): LEXICON_WEIGHT for x in INSULTS}, **{k: {} for k in PREFIXES}}
    if not total or not bad or bad == total:
        return Grammar(stems, -2.0)
    rate = bad / total
    counts = checkpointed(arrow_map(sample, _counted, "kind int, h bigint, t bigint, n bigint").groupBy("kind", "h").agg(F.sum("t").alias("t"), F.sum("n").alias("n")).where("t >= 2"))
    tested = max(2, counts.count())
    # chance of t or more toxic rows among n, bounded by the relative entropy of t/n and the base rate
    share = F.least(F.col("t") / F.col("n"), F.lit(1 - 1e-9))
    entropy = F.col("n") * (share * F.log(share / rate) + (1 - share) * F.log((1 - share) / (1 - rate)))
    odds = F.log((F.col("t") + 0.5) / (F.lit(bad) + 1) * (F.lit(total - bad) + 1) / (F.col("n") - F.col("t") + 0.5))
    strong = counts.where((F.col("t") / F.col("n") >= 0.8) & (entropy > math.log(tested)))
    named = {(r["kind"], int(np.int64(r["h"]).view(U))): (float(r["t"]), float(r["w"])) for r in strong.select("kind", "h", entropy.alias("t"), odds.alias("w")).collect()}  # bounded by the sample
    for (kind, h), w in _needed(sample, named, math.log(tested) / -math.log(rate)).items():
        stems[kind][h] = w
    known = {int(np.array(word_hash(x), U).view(np.int64)): x for x in INSULTS}
    for r in counts.where("kind = 0").where(F.col("h").isin(list(known))).where(F.col("n") - F.col("t") >= 5).select("h", odds.alias("w")).collect():
        stems[0][int(np.int64(r["h"]).view(U))] = min(LEXICON_WEIGHT, max(0.0, float(r["w"])))
    grammar = Grammar(stems, math.log(rate / (1 - rate)))
    seen = {(r["context"], r["toxic"]): r["n"] for r in arrow_map(sample, lambda it: _contexts(it, grammar), "context string, toxic int").groupBy("context", "toxic").agg(F.count("*").alias("n")).collect()}
    share_of = {c: (seen.get((c, 1), 0) + 0.0, seen.get((c, 0), 0) + 0.0) for c in CONTEXTS}
    t, f = (sum(x[i] for x in share_of.values()) for i in (0, 1))
    general = math.log((t + 1) / (f + 1)) - grammar.prior
    for c, (t, f) in share_of.items():
        own = max(0.0, math.log((t + 0.5) / (f + 0.5)) - grammar.prior) / max(general, 0.1)
        strength = (t + f) / (t + f + 3)
        grammar.factors[c] = min(1.3, strength * min(1.3, own) + (1 - strength) * DEFAULTS[c])
    return grammar


def _scored(batches: Iterator[pa.RecordBatch], grammar: Grammar) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        score = np.full(batch.num_rows, 1 / (1 + math.exp(-grammar.prior)))
        matched = np.zeros(batch.num_rows, np.int64)
        for low, _, words, breaks, quotes in _blocks_of(batch, 1):
            by_row: dict[int, list] = {}
            for row, stem, weight, context in grammar.matches(words, breaks, quotes):
                by_row.setdefault(row, []).append((stem, weight, context))
            for row, found in by_row.items():
                score[low + row] = 1 / (1 + math.exp(-grammar.logit(found)))
                matched[low + row] = len(found)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score), pa.array(matched)], names=["doc_id", "score", "n_matches"])


def score_documents(documents: DataFrame, grammar: Grammar) -> DataFrame:
    """Per document row: ``doc_id, score double, n_matches bigint``; only the text is an input of the score.

    Null and empty texts match nothing and score the prior; repeated rows score alike; an empty
    table gives no rows.
    """
    return arrow_map(texts(documents), lambda it: _scored(it, grammar), "doc_id bigint, score double, n_matches bigint")


def without_toxic(documents: DataFrame, grammar: Grammar, threshold: float = 0.7) -> DataFrame:
    """The rows of ``documents`` that score below the threshold, with all their columns."""
    at = documents.columns.index("text")

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = pa.RecordBatch.from_arrays([pa.nulls(batch.num_rows), batch.column(at)], names=["doc_id", "text"])
            score = next(_scored(iter([texts]), grammar)).column(1).to_numpy()
            yield batch.filter(pa.array(score < threshold))

    return arrow_map(documents, keep, documents.schema)


def report(documents: DataFrame, labels: DataFrame, threshold: float = 0.7) -> DataFrame:
    scored = score_documents(documents, fit(documents, labels))
    held = F.coalesce(remainder(F.col("doc_id")) == 1, F.lit(False)).alias("held_out")
    return scored.select("doc_id", held, "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "n_matches")
