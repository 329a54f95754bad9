"""Language identification by Bayesian evidence fusion.

For each page four pieces of evidence meet as log probabilities over the languages:

* *text*: hashed byte-trigram likelihoods, learned from a bounded sample of labelled documents;
* *markup*: the declared ``lang`` attribute, trusted at a fixed rate;
* *address*: the country suffix of the host, or a language code in the path;
* *host*: a prior by host, smoothed hierarchically: host counts are shrunk towards the
  registered domain's, those towards the suffix's, those towards the whole table's.

Host counts are grouped sums of first-pass posteriors (text, markup and address without the
host), so a host that owns a third of all pages is one partial aggregation.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .exchange import arrow_map, checkpointed
from .tokens import U, blocks, byte_values, mix, text_bytes

LANGS = ("de", "en", "es", "fr")
CELLS_BITS = 16
#: Country suffixes and the language most used under each.
SUFFIXES = {"de": "de", "at": "de", "es": "es", "mx": "es", "ar": "es", "fr": "fr", "uk": "en", "us": "en", "au": "en", "ie": "en"}
TRUST_MARKUP = 0.9
TRUST_PATH = 0.8
TRUST_SUFFIX = 0.7
STRENGTH = 5.0
TEMPER = 0.25  # neighbouring trigrams are not independent

_TAGS = re.compile(r"(?is)<(script|style|nav)\b.*?</\1\s*>|<!--.*?-->|<[^>]*>|&[a-z#0-9]+;")


def visible_text(html: str | None) -> str:
    return _TAGS.sub(" ", html or "")


def _trigrams(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, cell) of all byte trigrams of letters and spaces inside one row."""
    low = data.copy()
    upper = (low >= 65) & (low <= 90)
    low[upper] += 32
    low[(low < 97) & (low != 32) | (low > 122) & (low < 128)] = 32
    n = len(low)
    if n < 3:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    values = byte_values(23)[low]
    h = mix(values[:-2] * U(0x100000001B3) * U(0x100000001B3) + values[1:-1] * U(0x100000001B3) + values[2:]) >> U(64 - CELLS_BITS)
    row = np.searchsorted(offsets, np.arange(n - 2), "right") - 1
    good = (np.searchsorted(offsets, np.arange(2, n), "right") - 1 == row) & ~((low[:-2] == 32) & (low[1:-1] == 32))
    return row[good], h[good].astype(np.int64)


class TextModel:
    """Log likelihoods ``languages x cells`` of a fixed size."""

    def __init__(self, log_p: np.ndarray, langs: tuple[str, ...] = LANGS):
        self.log_p, self.langs = log_p.astype(np.float32), langs

    def score(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Log likelihood of each row under each language, as rows x languages."""
        row, cell = _trigrams(data, offsets)
        n = len(offsets) - 1
        return np.stack([np.bincount(row, self.log_p[k][cell], minlength=n) for k in range(len(self.langs))], 1)


def fit_text(documents: DataFrame, most_rows: int = 20_000, langs: tuple[str, ...] = LANGS) -> TextModel:
    """Trigram likelihoods from at most ``most_rows`` labelled documents, chosen by hash; other languages and nulls are passed over."""
    sample = documents.where(F.col("lang").isin(*langs) & F.col("text").isNotNull()).select(F.col("text").cast("string").alias("text"), "lang", F.xxhash64("doc_id").alias("h"))
    n = sample.count()
    if n > most_rows:
        sample = sample.where(F.col("h") < F.lit(int(-(2**63) + (2**64) * most_rows / n)))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = np.zeros((len(langs), 1 << CELLS_BITS), np.int64)
        for batch in batches:
            data, offsets = text_bytes(batch.column(0))
            lang = np.array([langs.index(x) for x in batch.column(1).to_pylist()], np.int64)
            for low, high in blocks(offsets):
                row, cell = _trigrams(data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low])
                for k in range(len(langs)):
                    cells[k] += np.bincount(cell[lang[low + row] == k], minlength=1 << CELLS_BITS)
        k, c = np.nonzero(cells)
        yield pa.RecordBatch.from_arrays([pa.array(k.astype(np.int32)), pa.array(c.astype(np.int32)), pa.array(cells[k, c])], names=["k", "cell", "n"])

    got = arrow_map(sample.select("text", "lang"), count, "k int, cell int, n bigint").groupBy("k", "cell").agg(F.sum("n").alias("n")).toArrow()  # languages x cells
    counts = np.full((len(langs), 1 << CELLS_BITS), 0.5)
    counts[got.column("k").to_numpy(), got.column("cell").to_numpy()] += got.column("n").to_numpy()
    return TextModel(np.log(counts / counts.sum(1, keepdims=True)), langs)


def host_of(url: Column) -> Column:
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.\-]*://(?:[^/@]*@)?([^/:?#]+)", 1), F.lit("")))


def _evidence(batches: Iterator[pa.RecordBatch], model: TextModel) -> Iterator[pa.RecordBatch]:
    langs = model.langs

    def told(code: str | None, trust: float) -> np.ndarray:
        if code not in langs:
            return np.zeros(len(langs))
        return np.log(np.where(np.array(langs) == code, trust, (1 - trust) / (len(langs) - 1)))

    for batch in batches:
        texts = pa.array([visible_text(x) for x in batch.column(1).to_pylist()], pa.large_string())
        data, offsets = text_bytes(texts)
        score = np.concatenate([model.score(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) for a, b in blocks(offsets)]) * TEMPER if len(texts) else np.zeros((0, len(langs)))
        for i, (declared, path, suffix) in enumerate(zip(*(batch.column(j).to_pylist() for j in (2, 3, 4)), strict=True)):
            score[i] += told((declared or "")[:2].lower(), TRUST_MARKUP)
            score[i] += told(path, TRUST_PATH) if path in langs else told(SUFFIXES.get(suffix or ""), TRUST_SUFFIX)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(5), batch.column(6), batch.column(4), pa.array(list(score), pa.list_(pa.float64()))], names=["page_id", "host", "domain", "suffix", "evidence"])


def evidence(pages: DataFrame, model: TextModel) -> DataFrame:
    """``page_id, host, domain, suffix, evidence``: log evidence by language without the host."""
    host = host_of(F.col("url"))
    rows = pages.select("page_id", F.col("html").cast("string").alias("html"), F.regexp_extract(F.col("html").cast("string"), r"""(?i)<html[^>]*\blang\s*=\s*["']?([A-Za-z]{2})""", 1).alias("declared"), F.regexp_extract("url", r"^[^?#]*?://[^/]+/(?:.*/)?([a-z]{2})(?:/|$)", 1).alias("path"), F.regexp_extract(host, r"([^.]+)$", 1).alias("suffix"), host.alias("host"), F.regexp_extract(host, r"([^.]+\.[^.]+)$", 1).alias("domain"))
    return arrow_map(rows, lambda it: _evidence(it, model), "page_id bigint, host string, domain string, suffix string, evidence array<double>")


def _softmax(scores: Column) -> Column:
    shifted = F.transform(scores, lambda x: F.exp(x - F.array_max(scores)))
    return F.transform(shifted, lambda x: x / F.aggregate(shifted, F.lit(0.0), lambda a, y: a + y))


def identify(pages: DataFrame, model: TextModel, strength: float = STRENGTH) -> DataFrame:
    """Per page row: ``page_id, lang, probability, host``.

    Null or empty html has no text evidence; a null url has the empty host, whose prior is smoothed like
    any other; ties go to the first language in order; repeated rows are judged each for
    itself; an empty table gives no rows; further columns are not read.
    """
    k = len(model.langs)
    first = evidence(pages, model).withColumn("p", _softmax(F.col("evidence")))
    sums = [F.sum(F.col("p")[i]).alias(f"s{i}") for i in range(k)]
    hosts = checkpointed(first.groupBy("suffix", "domain", "host").agg(*sums))  # one row a host: all other levels come from it

    def up(table: DataFrame, *keys: str) -> DataFrame:
        return table.groupBy(*keys).agg(*[F.sum(f"s{i}").alias(f"s{i}") for i in range(k)])

    def smoothed(table: DataFrame, parent: DataFrame, *keys: str) -> DataFrame:
        """Dirichlet smoothing with the parent's distribution ``q``."""
        joined = table.join(parent, list(keys)) if keys else table.crossJoin(F.broadcast(parent))  # one row
        total = sum((F.col(f"s{i}") for i in range(k)), F.lit(0.0))
        return joined.withColumn("q", F.array(*[(F.col(f"s{i}") + strength * F.col("q")[i]) / (total + strength) for i in range(k)]))

    domains = up(hosts, "suffix", "domain")
    suffixes = up(domains, "suffix")
    whole = suffixes.agg(*[F.coalesce(F.sum(f"s{i}"), F.lit(0.0)).alias(f"s{i}") for i in range(k)])
    total = sum((F.col(f"s{i}") for i in range(k)), F.lit(0.0))
    base = whole.select(F.array(*[(F.col(f"s{i}") + 1) / (total + k) for i in range(k)]).alias("q"))
    by_suffix = smoothed(suffixes, base).select("suffix", "q")
    by_domain = smoothed(domains, by_suffix, "suffix").select("suffix", "domain", "q")
    by_host = smoothed(hosts, by_domain, "suffix", "domain").select("suffix", "domain", "host", "q")
    fused = first.join(by_host, ["suffix", "domain", "host"]).withColumn("p", _softmax(F.zip_with("evidence", "q", lambda e, q: e + F.log(q))))
    best = F.array_position("p", F.array_max("p")).cast("int")
    return fused.select("page_id", F.element_at(F.array(*[F.lit(x) for x in model.langs]), best).alias("lang"), F.array_max("p").alias("probability"), "host")
