"""Near-duplicate classes by improved consistent weighted sampling over TF-IDF shingles.

Shingles are runs of five words (a shorter text is one shingle).  A shingle's weight is
``(1 + ln tf) * (1 + idf_share * idf)`` with ``idf = ln(N / df) / ln N``; document frequencies are
counted over all documents in a table of fixed size (hashed, with the mean load of a cell taken
off), so statistics stay bounded at any input size.

Sampling: for each of ``bands * rows`` hash functions a shingle draws ``r, c ~ Gamma(2, 1)`` and
``beta ~ U(0, 1)``, and the shingle with the smallest ``ln c - r * (floor(ln w / r + beta) - beta) - r``
is the sample together with its step.  Draws come from a table of 16,384 triples by hash and
weights from 64 levels, so a sample costs one multiplication and one lookup; ties are
broken by the shingle's own hash.  Two texts agree on a sample with a probability
equal to their weighted Jaccard similarity (to the level's width).

Equal texts are collapsed by digest first.  Bands that occur once are dropped through a filter
of bounded size; members of the others are sorted by band over range partitions, so a hot
band spreads over tasks.  Within a sorted run each member is paired with the
members before it (``back`` of them) and with the run's consensus member, whose samples agree
best with the run's commonest ones; these pairs are linear in members, and most near texts are
joined by them.  Each pair is verified by exact weighted Jaccard.

Runs that still hold several classes are then compared exhaustively: their members' sets are
dealt into cells that meet pairwise, and each meeting compares every pair of two classes by
exact weighted Jaccard in memory, so only links leave it.  The classes are thus the components of
all pairs at or above the threshold that share a band; banding is the only chance of a miss.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import components
from .exchange import arrow_map, checkpointed, fresh, hash_filter, partitions_for
from .tokens import ALNUM_WORDS, LOWER, U, Words, blocks, mix, span_hashes, text_bytes

SIZE = 5
BANDS, ROWS = 12, 3
THRESHOLD = 0.8
CELL_BITS = 18
IDF_SHARE = 0.25
LEVELS = 64
TOP_LN_WEIGHT = 3.0
DRAW_BITS = 14
DRAWS = 1 << DRAW_BITS
LN_A_RANGE = 64.0  # ln a lies within plus and minus half of it


def shingles(words: Words, size: int = SIZE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (row, hash, tf) of a block, sorted by row, then hash."""
    values = words.hashes(5)
    at, h = words.windows(values, size)
    row = words.row[at]
    short = np.flatnonzero((words.count > 0) & (words.count < size))
    if len(short):
        h = np.concatenate([h, span_hashes(values, words.first[short], words.first[short] + words.count[short])])
        row = np.concatenate([row, short])
    order = np.lexsort((h, row))
    h, row = h[order], row[order]
    if not len(h):
        return row, h, np.empty(0, np.int64)
    new = np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (row[1:] != row[:-1])))
    return row[new], h[new], np.diff(np.append(new, len(h)))


def _blocks(batch: pa.RecordBatch, column: int) -> Iterator[tuple[int, Words]]:
    data, offsets = text_bytes(batch.column(column))
    for low, high in blocks(offsets):
        yield low, Words(LOWER[data[offsets[low] : offsets[high]]], offsets[low : high + 1] - offsets[low], ALNUM_WORDS)


class Weights:
    """Shingle weights from the table of document frequencies."""

    def __init__(self, cells: np.ndarray, n: int, idf_share: float = IDF_SHARE):
        load = (cells.sum() - cells) / max(1, len(cells) - 1)
        df = np.clip(cells - load, 1, max(1, n))
        self.of_cell = (1 + idf_share * np.log(max(1, n) / df) / np.log(max(2, n))).astype(np.float32)
        self.shift = 64 - int(len(cells)).bit_length() + 1

    def __call__(self, h: np.ndarray, tf: np.ndarray) -> np.ndarray:
        return self.of_cell[(h >> U(self.shift)).astype(np.int64)] * (1 + np.log(tf)).astype(np.float32)


def document_frequencies(texts: DataFrame, cell_bits: int = CELL_BITS) -> tuple[np.ndarray, int]:
    """Document counts by hash cell over all rows of ``text``, and the number of rows."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells, n = np.zeros(1 << cell_bits, np.int64), 0
        for batch in batches:
            n += batch.num_rows
            for _, words in _blocks(batch, 0):
                _, h, _ = shingles(words)
                cells += np.bincount((h >> U(64 - cell_bits)).astype(np.int64), minlength=len(cells))
        used = np.flatnonzero(cells)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(used, -1).astype(np.int32)), pa.array(np.append(cells[used], n))], names=["cell", "n"])

    got = arrow_map(texts, count, "cell int, n bigint").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    at, n = got.column("cell").to_numpy(), got.column("n").to_numpy()
    cells = np.zeros(1 << cell_bits, np.int64)
    cells[at[at >= 0]] = n[at >= 0]
    return cells, int(n[at < 0].sum())


_sampling: dict[int, np.ndarray] = {}


def _ranks() -> np.ndarray:
    """``ln a`` for each weight level and draw, in steps of a fixed width: the order is kept, near values tie."""
    if 0 not in _sampling:
        draw = np.random.default_rng(20240229)
        r, c, beta = (x.astype(np.float32) for x in (draw.gamma(2, 1, DRAWS), draw.gamma(2, 1, DRAWS), draw.uniform(size=DRAWS)))
        out = np.empty((LEVELS, DRAWS), np.uint32)
        for level in range(LEVELS):
            step = np.floor((level + 0.5) * (TOP_LN_WEIGHT / LEVELS) / r + beta)
            ln_a = np.log(c) - r * (step - beta) - r
            out[level] = np.clip((ln_a + LN_A_RANGE / 2) * ((1 << 24) / LN_A_RANGE), 0, (1 << 24) - 1)
        _sampling[0] = out.reshape(-1)
    return _sampling[0]


def samples(row: np.ndarray, h: np.ndarray, weight: np.ndarray, n_rows: int, k: int) -> np.ndarray:
    """``k`` samples of each row as 64-bit identities; 0 for a row without shingles."""
    out = np.zeros((n_rows, k), U)
    if not len(h):
        return out
    ranks = _ranks()
    level = np.clip(np.log(weight) * (LEVELS / TOP_LN_WEIGHT), 0, LEVELS - 1).astype(np.int64) << DRAW_BITS
    first = np.flatnonzero(np.append(True, row[1:] != row[:-1]))
    for i in range(k):
        x = h * U((0x9E3779B97F4A7C15 * (2 * i + 1) ^ (0xC2B2AE3D27D4EB4F * (i + 1))) & 0xFFFFFFFFFFFFFFFF | 1)
        x ^= x >> U(29)
        x *= U(0xBF58476D1CE4E5B9)
        key = (ranks[level + (x >> U(64 - DRAW_BITS)).astype(np.int64)].astype(U) << U(40)) | ((x >> U(8)) & U((1 << 40) - 1))
        out[row[first], i] = np.minimum.reduceat(key, first)
    return out


def _signed(batches: Iterator[pa.RecordBatch], weights: Weights, bands: int, rows: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for low, words in _blocks(batch, 3):
            row, h, tf = shingles(words)
            sig = samples(row, h, weights(h, tf), words.rows, bands * rows)
            band = np.zeros((words.rows, bands), U)
            for j in range(rows):
                band = mix(band * U(31) + sig[:, j * bands : (j + 1) * bands])
            band = mix(band + np.arange(1, bands + 1, dtype=U))
            some = sig.any(1)
            marks = (mix(sig) >> U(56)).astype(np.uint8)
            whole = [batch.column(i).slice(low, words.rows) for i in range(3)]
            yield pa.RecordBatch.from_arrays(
                [*whole, pa.array([b.view(np.int64) if s else [] for b, s in zip(band, some, strict=True)], pa.list_(pa.int64())), pa.array([m.tobytes() for m in marks], pa.binary())], names=["node", "d1", "d2", "bands", "marks"]
            )


def _members(batches: Iterator[pa.RecordBatch], keep: object) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        lists = batch.column(1)
        count = lists.value_lengths().to_numpy(zero_copy_only=False)
        flat = lists.flatten().to_numpy().view(U)
        row = np.repeat(np.arange(batch.num_rows), count)
        good = np.flatnonzero(keep.passes(flat))
        place = pa.array(row[good])
        yield pa.RecordBatch.from_arrays([pa.array(flat[good].view(np.int64)), batch.column(0).take(place), batch.column(2).take(place)], names=["band", "node", "marks"])


def _pairs(batches: Iterator[pa.RecordBatch], back: int, least: float) -> Iterator[pa.RecordBatch]:
    """Pairs of each run of one band; a run's consensus member also goes out as a head, to meet the same band's runs in other partitions."""
    bands, nodes, marks = [], [], []
    for batch in batches:
        bands.append(batch.column(0).to_numpy())
        nodes.append(batch.column(1).to_numpy())
        marks.append(np.frombuffer(b"".join(batch.column(2).to_pylist()), np.uint8))
    if not bands:
        return
    band, node = np.concatenate(bands), np.concatenate(nodes)
    mark = np.concatenate(marks).reshape(len(band), -1)
    if not len(band):
        return
    first = np.flatnonzero(np.append(True, band[1:] != band[:-1]))
    size = np.diff(np.append(first, len(band)))
    a, b = [], []
    for d in range(1, back + 1):
        i = np.flatnonzero(band[d:] == band[:-d])
        a.append(i)
        b.append(i + d)
    head = first.copy()
    for f in np.flatnonzero(size > back + 1):
        low, n = int(first[f]), int(size[f])
        part = mark[low : low + n]
        common = np.array([np.bincount(part[:, j], minlength=256).argmax() for j in range(part.shape[1])], np.uint8)
        best = low + int((part == common).sum(1).argmax())
        head[f] = best
        a.append(np.full(n, best))
        b.append(np.arange(low, low + n))
    left, right = np.concatenate(a), np.concatenate(b)
    likely = (node[left] != node[right]) & ((mark[left] == mark[right]).mean(1) >= least)
    left, right = left[likely], right[likely]
    x, y = np.minimum(node[left], node[right]), np.maximum(node[left], node[right])
    edge = [0, len(first) - 1] if len(first) > 1 else [0]
    yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(x), np.int64)), pa.array(x), pa.array(y)], names=["band", "a", "b"])
    yield pa.RecordBatch.from_arrays([pa.array(band[first[edge]]), pa.array(node[head[edge]]), pa.array(np.full(len(edge), -1, np.int64))], names=["band", "a", "b"])


def _features(batches: Iterator[pa.RecordBatch], keep: object) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        mine = keep.passes(mix(batch.column(0).to_numpy().view(U)))
        batch = batch.filter(pa.array(mine))
        for low, words in _blocks(batch, 1):
            row, h, tf = shingles(words)
            at = np.searchsorted(row, np.arange(words.rows + 1))
            h32, tf16 = (h >> U(32)).astype("<u4"), np.minimum(tf, 65535).astype("<u2")
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(low, words.rows), pa.array([h32[s:e].tobytes() + tf16[s:e].tobytes() for s, e in zip(at[:-1], at[1:], strict=True)], pa.binary())], names=["node", "set"])


def weighted_jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Of two (sorted hashes, weights)."""
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=False, return_indices=True)
    low = np.minimum(a[1][i], b[1][j]).sum()
    total = a[1].sum() + b[1].sum() - low
    return float(low / total) if total > 0 else 1.0


def _verified(batches: Iterator[pa.RecordBatch], weights: Weights, threshold: float) -> Iterator[pa.RecordBatch]:
    def unpacked(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
        n = len(raw) // 6
        h = np.frombuffer(raw, "<u4", n)
        return h, weights(h.astype(U) << U(32), np.frombuffer(raw, "<u2", n, 4 * n))

    for batch in batches:
        a, b, s, t = (batch.column(i) for i in range(4))
        likeness = [weighted_jaccard(unpacked(x), unpacked(y)) for x, y in zip(s.to_pylist(), t.to_pylist(), strict=True)]
        good = np.array(likeness, float) >= threshold
        yield pa.RecordBatch.from_arrays([a.filter(pa.array(good)), b.filter(pa.array(good)), pa.array(np.array(likeness, float)[good])], names=["a", "b", "similarity"])


def _meetings(members: DataFrame, classes: DataFrame, block: int) -> DataFrame:
    """``node, class, band, x, y``: where members of runs that hold several classes meet.

    A run's largest class is its major side (1), all others the minor side (0); both are dealt
    by hash into cells of about ``block`` members.  Minor cells meet each other and the major
    cells, major cells never meet, as one class has nothing left to link.  Every pair of a run
    in two classes is in some meeting; a run with few strays stays linear in its members.
    """
    marked = checkpointed(members.select("band", "node").join(classes, "node", "left").select("band", "node", F.coalesce("class", "node").alias("class")))
    sizes = marked.groupBy("band", "class").agg(F.count("*").alias("n")).groupBy("band").agg(F.max_by("class", "n").alias("major"), F.sum("n").alias("n"), F.max("n").alias("most"))
    mixed = checkpointed(sizes.where("n > most"))
    long_runs = mixed.where(f"n > {block}").select("band", "major", F.ceil((F.col("n") - F.col("most")) / block).alias("few"), F.ceil(F.col("most") / block).alias("many"))
    kept = members.sparkSession.sparkContext.broadcast(hash_filter(checkpointed(_mixed(mixed.select(F.col("band").alias("node")))), "h"))

    def unsettled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(kept.value.passes(mix(batch.column(0).to_numpy().view(U)))))

    met = arrow_map(marked, unsettled, "band bigint, node bigint, class bigint").join(F.broadcast(long_runs), "band", "left")  # a long run has over ``block`` members, so these are few
    whole = F.col("major").isNull()
    side = F.when(whole | (F.col("class") != F.col("major")), 0).otherwise(1)
    few, many = F.coalesce("few", F.lit(1)), F.coalesce("many", F.lit(0))
    cell = F.pmod(F.xxhash64("node"), F.when(side == 0, few).otherwise(many))
    minor = F.transform(F.sequence(F.lit(0).cast("bigint"), few - 1), lambda g: F.struct(F.least(g, cell).alias("x"), F.greatest(g, cell).alias("y")))
    across = F.when(many > 0, F.transform(F.sequence(F.lit(0).cast("bigint"), F.greatest(many, F.lit(1)) - 1), lambda g: F.struct(cell.alias("x"), (-1 - g).alias("y")))).otherwise(F.array().cast("array<struct<x:bigint,y:bigint>>"))
    major = F.transform(F.sequence(F.lit(0).cast("bigint"), few - 1), lambda g: F.struct(g.alias("x"), (-1 - cell).alias("y")))
    return met.select("node", "class", "band", F.explode(F.when(side == 0, F.concat(minor, across)).otherwise(major)).alias("at")).select("node", "class", "band", "at.x", "at.y")


def _all_links(batches: Iterator[pa.RecordBatch], weights: Weights, threshold: float) -> Iterator[pa.RecordBatch]:
    """Links that join the classes of each meeting: every pair in two classes is compared, unless links found before have joined them."""
    held: list[tuple] = []
    for batch in batches:
        for row in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
            if held and row[:3] != held[0][:3]:
                yield from _linked(held, weights, threshold)
                held = []
            held.append(row)
    yield from _linked(held, weights, threshold)


def _linked(held: list[tuple], weights: Weights, threshold: float) -> Iterator[pa.RecordBatch]:
    """Links of one meeting's rows ``band, x, y, node, class, set``, at most one for each row."""
    group = np.array([r[4] for r in held], np.int64)
    if len(held) < 2 or (group == group[0]).all():
        return
    node = np.array([r[3] for r in held], np.int64)
    sets = [(np.frombuffer(r[5], "<u4", len(r[5]) // 6), np.frombuffer(r[5], "<u2", len(r[5]) // 6, len(r[5]) // 6 * 4)) for r in held]
    count = np.array([len(h) for h, _ in sets])
    end = np.cumsum(count)
    start = end - count
    flat = np.concatenate([h for h, _ in sets])
    w = weights(flat.astype(U) << U(32), np.concatenate([tf for _, tf in sets]))
    total = np.array([w[s:e].sum() for s, e in zip(start, end, strict=True)])
    kinds, term = np.unique(flat, return_inverse=True)
    own = np.zeros(len(kinds), np.float32)
    some = count > 0
    found = []
    for i in np.flatnonzero(some):
        ahead = np.zeros(len(held), bool)
        ahead[i + 1 :] = True
        near = np.flatnonzero(ahead & some & (group != group[i]) & (np.minimum(total, total[i]) >= (threshold - 1e-4) * np.maximum(total, total[i])))
        if not len(near):
            continue
        mine = slice(start[i], end[i])
        own[term[mine]] = w[mine]
        first = np.cumsum(count[near]) - count[near]
        at = np.arange(count[near].sum()) + np.repeat(start[near] - first, count[near])
        low = np.add.reduceat(np.minimum(own[term[at]], w[at]), first)
        own[term[mine]] = 0
        for j in near[low >= (threshold - 1e-4) * (total[i] + total[near] - low)]:
            if group[j] == group[i]:
                continue
            likeness = weighted_jaccard((flat[mine], w[mine]), (flat[start[j] : end[j]], w[start[j] : end[j]]))
            if likeness >= threshold:
                found.append((min(node[i], node[j]), max(node[i], node[j]), likeness))
                group[group == group[j]] = group[i]
    if found:
        a, b, likeness = zip(*found, strict=True)
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(likeness, pa.float64())], names=["a", "b", "similarity"])


def prepared(documents: DataFrame) -> DataFrame:
    """``doc_id, node, d1, d2, text``: digests of the text (null: empty), and the number a row is known by.

    That is its doc_id, or its first digest where ids are null or repeat.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    ids = documents.select(F.col("doc_id").cast("bigint").alias("doc_id"))
    plain = ids.groupBy("doc_id").count().where("count > 1 OR doc_id IS NULL").isEmpty()
    base = documents.select(F.col("doc_id").cast("bigint").alias("doc_id"), text.alias("text")).withColumns({"d1": F.xxhash64("text"), "d2": F.xxhash64(F.lit("second"), "text")})
    return base.select("doc_id", (F.col("doc_id") if plain else F.col("d1")).alias("node"), "d1", "d2", "text")


def near_links(docs: DataFrame, bands: int = BANDS, rows: int = ROWS, threshold: float = THRESHOLD, back: int = 3, block: int = 256) -> tuple[DataFrame, DataFrame]:
    """(representatives ``node, d1, d2``, verified links ``a, b, similarity`` between them) of ``prepared`` rows."""
    context = docs.sparkSession.sparkContext
    cells, n = document_frequencies(docs.select("text"))
    weights = Weights(cells, n)
    signed = arrow_map(docs.select("node", "d1", "d2", "text"), lambda it: _signed(it, weights, bands, rows), "node bigint, d1 bigint, d2 bigint, bands array<bigint>, marks binary")
    found = checkpointed(signed.groupBy("d1", "d2").agg(F.min_by(F.struct("bands", "marks"), "node").alias("s"), F.min("node").alias("node")).select("node", "d1", "d2", "s.bands", "s.marks"))
    repeated = checkpointed(found.select(F.explode("bands").alias("band")).groupBy("band").agg(F.count("*").alias("n")).where("n > 1").select("band"))
    keep = context.broadcast(hash_filter(repeated, "band"))
    members = arrow_map(found.select("node", "bands", "marks"), lambda it: _members(it, keep.value), "band bigint, node bigint, marks binary")
    n_partitions = partitions_for(docs.sparkSession, bands * found.count())
    runs = members.repartitionByRange(n_partitions, "band", "node").sortWithinPartitions("band", "node")
    out = checkpointed(arrow_map(runs, lambda it: _pairs(it, back, 0.5), "band bigint, a bigint, b bigint"))
    heads = out.where("b = -1 AND band <> 0").select("band", "a")  # two at most for each partition
    low = heads.groupBy("band").agg(F.min("a").alias("low"))
    across = heads.join(low, "band").where("a <> low").select(F.least("a", "low").alias("a"), F.greatest("a", "low").alias("b"))
    pairs = checkpointed(out.where("band = 0").select("a", "b").unionByName(across).distinct())
    plain = _node_is_id(docs)
    links = checkpointed(_verified_links(docs, pairs, weights, threshold, plain))
    met = checkpointed(_meetings(members, components(links), block))
    sets = _sets(docs, met.select("node").distinct(), plain)
    dealt = met.join(sets, "node").select("band", "x", "y", "node", "class", "set").repartition(n_partitions, "band", "x", "y").sortWithinPartitions("band", "x", "y", "node")
    rest = checkpointed(arrow_map(dealt, lambda it: _all_links(it, weights, threshold), "a bigint, b bigint, similarity double"))
    links = links.unionByName(rest)
    return found.select("node", "d1", "d2"), links


def _verified_links(docs: DataFrame, pairs: DataFrame, weights: Weights, threshold: float, plain: bool) -> DataFrame:
    """``a, b, similarity`` of the pairs at or above the threshold; only texts of their ends are read again."""
    ends = pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct()
    sets = _sets(docs, ends, plain)
    first = pairs.join(sets.select(F.col("node").alias("a"), F.col("set").alias("s")), "a")
    both = first.join(sets.select(F.col("node").alias("b"), F.col("set").alias("t")), "b").select("a", "b", "s", "t")
    return arrow_map(both, lambda it: _verified(it, weights, threshold), "a bigint, b bigint, similarity double")


def _sets(docs: DataFrame, nodes: DataFrame, plain: bool) -> DataFrame:
    """``node, set`` of the given nodes, and perhaps of some others."""
    chosen = docs.sparkSession.sparkContext.broadcast(hash_filter(checkpointed(_mixed(nodes)), "h"))
    sets = arrow_map(docs.select("node", "text"), lambda it: _features(it, chosen.value), "node bigint, set binary")
    return sets if plain else sets.groupBy("node").agg(F.first("set").alias("set"))


def _node_is_id(docs: DataFrame) -> bool:
    return docs.select("node").groupBy("node").count().where("count > 1").isEmpty()


def _mixed(nodes: DataFrame) -> DataFrame:
    """The numpy finaliser of a bigint, as a column ``h``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(mix(batch.column(0).to_numpy().view(U)).view(np.int64))], names=["h"])

    return arrow_map(nodes.select("node"), run, "h bigint")


def near_classes(documents: DataFrame, bands: int = BANDS, rows: int = ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """Per document row: ``doc_id, class_id, is_first``.

    ``class_id`` is the smallest number (see ``prepared``) of a near-duplicate class; ``is_first``
    marks that row.  Rows with equal texts share a class (null counts as empty); texts
    without words are near to equal texts only.  Repeated rows share a class, and each of the
    first text's rows is marked.  An empty table gives no rows; columns other than doc_id and text are not read.
    """
    docs = prepared(documents)
    reps, links = near_links(docs, bands, rows, threshold)
    classes = components(links)
    joined = reps.join(classes, "node", "left").select("d1", "d2", F.coalesce("class", "node").alias("class_id"))
    rows_ = docs.select("doc_id", "node", "d1", "d2").join(joined, ["d1", "d2"])
    return rows_.select("doc_id", "class_id", (F.col("node") == F.col("class_id")).alias("is_first"))


def first_of_classes(documents: DataFrame, bands: int = BANDS, rows: int = ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """One row of each near-duplicate class, with all columns of ``documents``.

    The row with the class's number stays; where ids are null or repeat, one row of its text.
    """
    docs = prepared(documents)
    reps, links = near_links(docs, bands, rows, threshold)
    stay = reps.join(components(links).where(F.col("node") != F.col("class")).select("node"), "node", "left_anti")
    if _node_is_id(docs):
        return documents.join(stay.select(F.col("node").alias("doc_id")), "doc_id", "left_semi").select(*documents.columns)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    one, two = fresh(documents.columns, "first digest"), fresh(documents.columns, "second digest")
    marked = documents.withColumns({one: F.xxhash64(text), two: F.xxhash64(F.lit("second"), text)})
    named = stay.select(F.col("d1").alias(one), F.col("d2").alias(two))
    return marked.join(named, [one, two], "left_semi").dropDuplicates([one, two]).select(*documents.columns)
