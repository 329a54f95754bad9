"""The ten operators against brute force, round trips, held-out accuracy, and odd rows."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from clustercost import filters
from clustercost.llm import chat, components, decontaminate, exchange, fingerprint, language, licenses, lm_scores, minhash, packing, substring_dedup, tokens, toxicity

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, label int, kind string, bucket int"
LONG = " ".join(f"word{i % 977}x{i}" for i in range(30_000))
ODD = [None, "", " ", "\n\n", "a", "one two three four five six seven", LONG, "ünïcödé 😀 text", "same words here again and again"]


def documents(spark, rows):
    """Documents with clashing further columns."""
    full = [(i, t, "en", "src", None if t is None else len(t), 1, "x", 7) for i, t in rows]
    return spark.createDataFrame(full, SCHEMA)


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(i, t) for i, t in enumerate(ODD)] + [(5, ODD[5]), (5, "another text for the same id"), (None, "no id"), (None, None), (20, ODD[8]), (21, ODD[8])]
    return documents(spark, rows).persist()


@pytest.fixture(scope="module")
def empty(spark):
    return documents(spark, []).persist()


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def words_of(text):
    low = (text or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)


# tokens


def test_words_and_windows_match_python():
    import pyarrow as pa

    texts = ["Aé b-c  d1", "", None, "x", "😀 ok"]
    data, offsets = tokens.text_bytes(pa.array(texts))
    words = tokens.Words(tokens.LOWER[data], offsets, tokens.ALNUM_WORDS)
    raw = tokens.LOWER[data].tobytes()
    assert [[raw[s:e].decode() for s, e, r in zip(words.start, words.end, words.row, strict=True) if r == i] for i in range(5)] == [words_of(t) for t in texts]
    values = words.hashes()
    at, h = words.windows(values, 2)
    assert list(at) == [0, 1, 2, 5] and len(set(h.tolist())) == 4
    assert [b - a for a, b in tokens.blocks(offsets, 4)] == [1, 3, 1] or sum(b - a for a, b in tokens.blocks(offsets, 4)) == 5


def test_hash_filter_never_loses(spark):
    some = spark.range(0, 100_000, 7).select(F.xxhash64("id").alias("h"))
    keep = exchange.hash_filter(some, "h")
    got = np.array([r["h"] for r in some.collect()], np.int64).view(np.uint64)
    assert keep.passes(got).all()
    other = np.array([r["h"] for r in spark.range(1, 100_000, 7).select(F.xxhash64("id").alias("h")).collect()], np.int64).view(np.uint64)
    assert keep.passes(other).mean() < 0.05


def test_components(spark):
    links = spark.createDataFrame([(1, 2), (2, 3), (5, 4), (9, 9)] + [(i, i + 1) for i in range(100, 160)], "a bigint, b bigint")
    got = {r["node"]: r["class"] for r in components.components(links).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 4: 4, 5: 4, 9: 9, **{i: 100 for i in range(100, 161)}}


# 1 language


def test_language(spark, sf, docs, empty):
    model = language.fit_text(docs)
    texts = docs.select(F.col("doc_id").alias("page_id"), F.col("text").alias("html"), F.lit(None).cast("string").alias("url"))
    got = language.identify(texts, model).join(docs.select(F.col("doc_id").alias("page_id"), F.col("lang").alias("truth")), "page_id")
    assert got.where("lang = truth").count() > 0.97 * docs.count()
    pages = [(1, "http://a.example.de/x", None), (2, None, None), (3, "http://h.example.com/fr/1", "<html lang='fr'></html>"), (3, "http://h.example.com/fr/1", "<html lang='fr'></html>"), (4, "not a url", ""), (None, "http://h.example.com/2", "<p>")]
    found = language.identify(spark.createDataFrame(pages, "page_id bigint, url string, html string").withColumn("lang", F.lit("zz")), model).collect()
    assert len(found) == len(pages) and all(0 < r["probability"] <= 1 for r in found)
    by = {r["page_id"]: r["lang"] for r in found}
    assert by[1] == "de" and by[3] == "fr"
    assert language.identify(spark.createDataFrame([], "page_id bigint, url string, html string"), model).count() == 0
    assert language.fit_text(empty).log_p.shape == (4, 1 << 16)


def test_identification_against_brute_force(spark, sf, docs):
    """Host, domain, suffix and table priors in plain Python, from the same evidence."""
    model = language.fit_text(docs)
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    rows = language.evidence(pages, model).collect()
    soft = lambda x: np.exp(x - np.max(x)) / np.exp(x - np.max(x)).sum()
    sums = collections.defaultdict(lambda: np.zeros(4))
    levels = lambda r: [(), (r["suffix"],), (r["suffix"], r["domain"]), (r["suffix"], r["domain"], r["host"])]
    for r in rows:
        for key in levels(r):
            sums[key] += soft(np.array(r["evidence"]))

    def prior(keys):
        q = (sums[()] + 1) / (sums[()].sum() + 4)
        for key in keys[1:]:
            q = (sums[key] + language.STRENGTH * q) / (sums[key].sum() + language.STRENGTH)
        return q

    got = {r["page_id"]: r for r in language.identify(pages, model).collect()}
    for r in rows:
        p = soft(np.array(r["evidence"]) + np.log(prior(levels(r))))
        assert abs(p.max() - got[r["page_id"]]["probability"]) < 1e-9 and got[r["page_id"]]["lang"] == language.LANGS[int(p.argmax())]


def test_host_prior_decides_where_pages_say_nothing(spark, docs):
    model = language.fit_text(docs)
    rows = [(i, f"http://h.example.com/{i}", "<html lang='es'>") for i in range(20)] + [(99, "http://h.example.com/99", "")]
    got = language.identify(spark.createDataFrame(rows, "page_id bigint, url string, html string"), model)
    assert got.where("page_id = 99").first()["lang"] == "es"


def test_a_declaration_behind_a_long_banner_counts(spark, docs):
    model = language.fit_text(docs)
    banner = "<!--" + "x" * 10_000 + "-->"
    rows = [(1, "http://h.example.com/1", banner + "<html lang='es'></html>"), (2, "http://h.example.com/2", "<html lang='es'></html>")]
    got = {r["page_id"]: r["evidence"] for r in language.evidence(spark.createDataFrame(rows, "page_id bigint, url string, html string"), model).collect()}
    told = [math.log(language.TRUST_MARKUP if x == "es" else (1 - language.TRUST_MARKUP) / 3) for x in language.LANGS]
    assert np.allclose(np.array(got[1]) - np.mean(got[1]), np.array(told) - np.mean(told), atol=1) and int(np.argmax(got[1])) == int(np.argmax(got[2])) == language.LANGS.index("es")


# 2 language model


def brute_scores(rows, backoff=0.4, least=2, order=3):
    docs = [words_of(t) for _, t in rows]
    counts = collections.Counter(tuple(d[j : j + k]) for d in docs for k in range(1, order + 1) for j in range(len(d) - k + 1))
    n = sum(len(d) for d in docs)
    out = []
    for (i, _), d in zip(rows, docs, strict=True):
        total = 0
        for j, w in enumerate(d):
            context = min(j, order - 1)
            p = backoff**context * counts[(w,)] / n
            for k in range(2, context + 2):
                run = tuple(d[j - k + 1 : j + 1])
                if counts[run] >= least:
                    p = backoff ** (context + 1 - k) * counts[run] / counts[run[:-1]]
            total += round(4096 * math.log(p))
        out.append((i, len(d), round(total / 4096, 4)))
    return sorted(out, key=str)


def test_lm_scores(spark, odd, empty):
    for df in (odd, documents(spark, [(i, f"The cat SAT on the mat {i % 3}") for i in range(50)])):
        rows = [(r["doc_id"], r["text"]) for r in df.collect()]
        got = [(r["doc_id"], r["n_words"], r["log_score"]) for r in lm_scores.score_documents(df).collect()]
        assert sorted(got, key=str) == brute_scores(rows)
    assert lm_scores.score_documents(empty).count() == 0
    rows = [(i, " ".join(random.Random(i).choices("abc", k=20))) for i in range(30)]
    for order, least in ((1, 2), (2, 1), (4, 3)):
        got = [(r["doc_id"], r["n_words"], r["log_score"]) for r in lm_scores.score_documents(documents(spark, rows), order=order, least=least, block_bytes=100).collect()]
        assert sorted(got, key=str) == brute_scores(rows, least=least, order=order)


def test_a_table_that_changes_between_readings_fails():
    block = lm_scores.Block(np.array([1]), np.array([False]), np.array([3]), np.array([5, 6, 5], np.uint64))
    with pytest.raises(RuntimeError):
        lm_scores._log_scores(block, [np.array([1]), np.array([1, 1])], 3, 0.4, 2)


def test_rare_words_keep_their_counts_in_a_large_corpus(spark):
    """Over 2**21 tokens: words that occur twice keep their own counts."""
    rows = [(i, "the " * 22_000) for i in range(100)] + [(100, "rare rare"), (101, "seldom seldom")]
    n = 100 * 22_000 + 4
    got = {r["doc_id"]: r["log_score"] for r in lm_scores.score_documents(documents(spark, rows)).where("doc_id >= 100").collect()}
    want = round((round(4096 * math.log(2 / n)) + round(4096 * math.log(0.4 * 2 / n))) / 4096, 4)
    assert got == {100: want, 101: want}


# 3 licences


def test_licenses(spark, odd, empty):
    known = licenses.known_licenses(spark)
    changed = "Copyright (c) 1999 A. Person\nAll rights reserved.\n" + licenses.MIT.upper().replace(",", " ;").replace("SUBLICENSE", "sub-licence".replace("-", " ").replace("licence", "license"))
    rows = [(1, changed), (2, licenses.MIT + " extra"), (3, "LICENCED under the Apache Licence version 2.0!"), (4, None), (5, "--"), (3, licenses.ISC)]
    got = [(r["doc_id"], r["license"]) for r in licenses.scan_licenses(documents(spark, rows), known).collect()]
    assert sorted(got, key=str) == sorted([(1, "MIT"), (2, None), (3, "Apache-2.0"), (4, None), (5, None), (3, "ISC")], key=str)
    assert licenses.scan_licenses(odd, known).count() == odd.count() and licenses.scan_licenses(empty, known).count() == 0
    lines = licenses.scan_lines(documents(spark, [(1, "x\nReleased under the MIT License.\nReleased under the MIT License."), (2, None)]), known)
    assert [tuple(r) for r in lines.collect()] == [(1, "MIT", 2)]
    plan = licenses.scan_licenses(odd, known)._jdf.queryExecution().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


def test_equivalents_next_to_each_other_and_licence_files(spark, tmp_path):
    got = spark.createDataFrame([("favour favour sub license sub license, HOLDERS owners",), ("&",)], "t string").select(licenses.canonical(F.col("t"))).collect()
    assert [r[0] for r in got] == ["favor favor sublicense sublicense holders holders", "and"]
    (tmp_path / "Long-1.0.txt").write_text("Copyright (c) 2001 Somebody\n\nA very long licence of two lines.\nIts second line.")
    both = licenses.known_licenses(spark).unionByName(licenses.licenses_in(spark, str(tmp_path)))
    rows = [(1, "a very LONG license of two lines; its second line"), (2, "Copyright 2020 Me\n" + licenses.BSD_3)]
    assert sorted(tuple(r) for r in licenses.scan_licenses(documents(spark, rows), both).select("doc_id", "license").collect()) == [(1, "Long-1.0"), (2, "BSD-3-Clause")]


# 4 fingerprints


def brute_likeness(a, b):
    """The share of classes in which the smallest span hashes agree, span by span in plain integers."""

    def mixed(x):
        m = 2**64 - 1
        x = ((x ^ (x >> 30)) * 0xBF58476D1CE4E5B9) & m
        x = ((x ^ (x >> 27)) * 0x94D049BB133111EB) & m
        return x ^ (x >> 31)

    def classes(text):
        size, low = min(len(text), fingerprint.SPAN), {}
        for s in range(len(text) - size + 1 if text else 0):
            parts = [sum((ord(c) + 1) * pow(base, k, prime) for k, c in enumerate(text[s : s + size])) % prime for base, prime in zip(fingerprint.BASES, fingerprint.PRIMES, strict=True)]
            h = mixed(parts[0] << 31 | parts[1])
            low[h >> 58] = min(low.get(h >> 58, 2**64), (h << 6) & (2**64 - 1))
        return {k: mixed(x) >> 48 for k, x in low.items()}

    if a == b:
        return 1.0
    x, y = classes(a), classes(b)
    return sum(x.get(k, -1) == y.get(k, -1) for k in x.keys() | y.keys()) / max(1, len(x.keys() | y.keys()))


def test_fingerprints(spark, odd, empty, docs):
    rows = [(r["doc_id"], r["text"] or "") for r in docs.collect()]
    order = sorted(rows, key=lambda r: -r[0])
    want = {}
    for j, (i, t) in enumerate(order):
        other, half = order[(j + 1) % len(order)][1], len(t) // 2
        want[i] = (len(t), hashlib.sha256((t[: len(t) - half] + other[:half]).encode()).hexdigest())
    got = fingerprint.fingerprint_documents(docs).collect()
    assert {r["doc_id"]: (r["n_chars"], r["edited_sha256"]) for r in got} == want
    texts = dict(rows)
    assert len({(texts[r["doc_id"]], r["fingerprint"]) for r in got}) == len(set(texts.values())) == len({r["fingerprint"] for r in got})
    assert all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in got)
    assert np.mean([r["near_edited"] for r in got]) > 10 * np.mean([r["near_next"] for r in got])
    assert fingerprint.fingerprint_documents(odd).count() == odd.count()
    assert fingerprint.fingerprint_documents(empty).count() == 0
    by = {r["doc_id"]: r for r in got}
    for j, (i, t) in list(enumerate(order))[:: max(1, len(order) // 60)]:
        other, half = order[(j + 1) % len(order)][1], len(t) // 2
        edited = t[: len(t) - half] + other[:half]
        for x, near, common in ((edited, "near_edited", "common_edited"), (other, "near_next", "common_next")):
            assert by[i][near] == brute_likeness(t, x)
            assert by[i][common] == next((k for k in range(min(len(t), len(x))) if t[k] != x[k]), min(len(t), len(x)))
    one = fingerprint.fingerprint_documents(documents(spark, [(1, "abcd")])).first()
    assert one["near_next"] == 1 and one["edited_sha256"] == hashlib.sha256(b"abab").hexdigest()


def test_spans_and_extensions():
    rng = random.Random(1)
    text = "".join(rng.choice("ab") for _ in range(300))
    arrays = fingerprint.PrefixArrays(np.frombuffer(text.encode("utf-32-le"), "<u4"))
    for _ in range(100):
        i, j = rng.randrange(300), rng.randrange(300)
        want = next((k for k in range(300 - max(i, j)) if text[i + k] != text[j + k]), 300 - max(i, j))
        assert arrays.common_extensions(np.array([i]), np.array([j]), np.array([300 - max(i, j)])).tolist() == [want]


# 5 near-duplicates


def test_near_duplicates(spark, odd, empty):
    rng = random.Random(5)
    fresh = lambda n: [f"w{rng.randrange(10**6)}" for _ in range(n)]
    rows, truth = [], {}
    for g in range(30):
        base, first = fresh(150), None
        for c in range(4):
            text = list(base)
            for _ in range(c):
                text[rng.randrange(150)] = fresh(1)[0]
            i = len(rows)
            first = i if first is None else first
            truth[i] = first
            rows.append((i, " ".join(text)))
    shared = fresh(30)
    for _ in range(20):
        truth[len(rows)] = len(rows)
        rows.append((len(rows), " ".join(fresh(100) + shared)))
    got = {r["doc_id"]: r["class_id"] for r in minhash.near_classes(documents(spark, rows)).collect()}
    assert got == truth
    assert minhash.near_classes(odd).count() == odd.count()
    by = collections.defaultdict(set)
    for r in minhash.near_classes(odd.where("doc_id >= 8")).collect():
        by[r["class_id"]].add(r["doc_id"])
    assert {8, 20, 21} in by.values()
    assert minhash.near_classes(empty).count() == 0
    kept = minhash.first_of_classes(odd)
    assert kept.columns == odd.columns and kept.count() == len({x or "" for x in ODD} | {"another text for the same id", "no id"})


@pytest.mark.parametrize("edits", [(1, 2), (2, 3, 4)])
def test_a_hot_group_loses_no_class(spark, edits):
    """Hundreds of edited copies: the classes are the components of all pairs at 0.8 or more."""
    rng = random.Random(6)
    base = [f"w{i}" for i in range(160)]
    rows = []
    for i in range(300):
        text = list(base)
        for _ in range(edits[i % len(edits)]):
            text[rng.randrange(160)] = f"x{rng.randrange(10**6)}"
        rows.append((i, " ".join(text)))
    df = documents(spark, rows)
    cells, n = minhash.document_frequencies(df.select("text"))
    weights = minhash.Weights(cells, n)
    sets = []
    for _, text in rows:
        data = np.frombuffer(text.encode(), np.uint8)
        _, h, tf = minhash.shingles(tokens.Words(data, np.array([0, len(data)]), tokens.ALNUM_WORDS))
        sets.append((h, weights(h, tf)))
    parent = list(range(300))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(300):
        for j in range(i):
            if minhash.weighted_jaccard(sets[i], sets[j]) >= 0.8 and root(i) != root(j):
                parent[max(root(i), root(j))] = min(root(i), root(j))
    got = {r["doc_id"]: r["class_id"] for r in minhash.near_classes(df).collect()}
    assert got == {i: root(i) for i in range(300)}
    _, links = minhash.near_links(minhash.prepared(df), block=16)  # many cells of one run meet
    small = {r["node"]: r["class"] for r in components.components(links).collect()}
    assert {i: small.get(i, i) for i in range(300)} == got


def test_sampling_agrees_with_weighted_jaccard():
    rng = np.random.default_rng(3)
    h = rng.integers(0, 2**63, 300, dtype=np.uint64)
    wa, wb = rng.uniform(1, 3, 300).astype(np.float32), rng.uniform(1, 3, 300).astype(np.float32)
    wb[:60] = 0
    a, b = h, h[60:]
    sa = minhash.samples(np.zeros(300, np.int64), a, wa, 1, 600)
    sb = minhash.samples(np.zeros(240, np.int64), b, wb[60:], 1, 600)
    want = np.minimum(wa, wb).sum() / np.maximum(wa, wb).sum()
    assert abs((sa == sb).mean() - want) < 0.08


# 6 decontamination


def brute_hits(rows, items, window=13):
    runs = collections.defaultdict(set)
    for item, t in items:
        w = words_of(t)
        m = min(window, len(w))
        for i in range(len(w) - m + 1 if m else 0):
            runs[tuple(w[i : i + m])].add(item)
    out = []
    for i, t in rows:
        w = words_of(t)
        hit, found = [False] * len(w), set()
        for m in {len(r) for r in runs}:
            for j in range(len(w) - m + 1):
                if (r := tuple(w[j : j + m])) in runs:
                    found |= runs[r]
                    hit[j : j + m] = [True] * m
        n = sum(hit)
        out.append((i, len(w), n, len(found), decontaminate.digest(list(found)), n > 0 and 20 * n >= len(w)))
    return sorted(out, key=str)


@pytest.mark.parametrize("max_mb", [16.0, 0.0002])
def test_decontamination(spark, odd, empty, max_mb):
    rng = random.Random(9)
    vocabulary = [f"v{i}" for i in range(12)]
    make = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    items = [(i, make(rng.choice([0, 1, 2, 5, 12, 13, 14, 40]))) for i in range(15)] + [(90, None), (91, ODD[5]), (92, "same words")]
    rows = [(100, "ONLY CAPITALS Here"), (101, "Same WORDS")] + [(i, make(rng.randrange(60)) + " " + (items[i % 15][1].upper() if i % 2 else "")) for i in range(60)]
    bench = spark.createDataFrame(items, "item_id bigint, text string").withColumn("doc_id", F.lit(1))
    for df in (documents(spark, rows), odd):
        have = [(r["doc_id"], r["text"]) for r in df.collect()]
        found = decontaminate.contamination(df, bench, max_block_mb=max_mb).collect()
        got = sorted([(r["doc_id"], r["n_words"], r["n_hit"], len(r["items"]), decontaminate.digest(r["items"]), r["contaminated"]) for r in found], key=str)
        assert got == brute_hits(have, items)
        kept = decontaminate.without_contaminated(df, bench)
        assert kept.columns == df.columns and kept.count() == sum(not x[5] for x in got)
    assert decontaminate.report(empty, bench).count() == 0
    assert decontaminate.report(odd, bench.limit(0)).where("n_hit > 0").count() == 0


# 7 chat


def test_chat_round_trip(spark):
    texts = ["a<|b", "\\<|", "<\\|x", "<|im_end|><|im_start|>assistant ok", "", None, "<|turn|>", "\\\\", "é😀<", "|im_start|>", "x\n"]
    rows = [(1, i, ["user", "assistant", "assistant", "ro\nle<|", None][i % 5], t) for i, t in enumerate(texts)]
    rows += [(2, 0, "assistant", "same"), (2, 0, "assistant", "same"), (None, 1, "user", "x"), (3, None, "assistant", LONG)]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string").withColumn("r", F.lit(1))
    got = chat.format_chats(df).select("*", chat.read_back(F.col("formatted")).alias("back"), chat.loss_text(F.col("formatted"), F.col("loss")).alias("learned")).collect()
    assert len(got) == 4
    for r in got:
        want = sorted(((x[1] is not None, x[1], x[2] or "", x[3] or "") for x in rows if x[0] == r["conv_id"]), key=lambda x: (x[0], x[1] or 0, x[2], x[3]))
        assert [tuple(x) for x in r["back"]] == [x[2:] for x in want]
        assert r["learned"] == "".join(x[3] for x in want if x[2] == "assistant")
    assert chat.report(df.limit(0)).count() == 0


# 8 packing


def test_plan_is_best_fit():
    rng = random.Random(2)
    for trial in range(20):
        counts = collections.Counter(rng.randrange(1, 65) for _ in range(rng.randrange(1, 400)))
        slots = packing.plan(dict(counts), 64)
        filled, seen = collections.defaultdict(list), collections.Counter()
        for length, low, high, first, per, place in slots:
            for rank in range(low, high):
                filled[first + (rank - low) // per].append((place + (rank - low) % per * length, length))
                seen[length] += 1
        assert seen == counts
        for parts in filled.values():
            at = 0
            for offset, length in sorted(parts):
                assert offset == at
                at += length
            assert at <= 64
        # item by item
        free: list[int] = []
        for length in sorted(counts.elements(), reverse=True):
            fits = [f for f in free if f >= length]
            if fits:
                free.remove(min(fits))
                free.append(min(fits) - length)
            else:
                free.append(64 - length)
        assert len(filled) == len(free), trial


def test_packing(spark, odd, empty, docs):
    import public_tokenizers
    from tokenizers import Tokenizer

    full = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for df in (docs, odd):
        want = []
        for r in df.collect():
            ids = full.encode(r["text"] or "", add_special_tokens=False).ids + [2]
            size, at, piece = packing.first_length(len(ids), 1024), 0, 0
            while at < len(ids):
                want.append((r["doc_id"], piece, at, size, zlib.crc32(np.array(ids[at : at + size], "<u4").tobytes())))
                at, piece, size = at + size, piece + 1, 1024
        got = packing.pack_documents(df).toPandas()
        rows = [(None if i != i else int(i), p, s, n, c) for i, p, s, n, c in zip(got["doc_id"], got["piece"], got["start"], got["length"], got["ids_crc32"], strict=True)]
        assert sorted(rows, key=str) == sorted(want, key=str)
        for _, part in got.sort_values("offset").groupby("sequence_id"):
            assert list(part["offset"]) == [0, *np.cumsum(part["length"])[:-1]] and part["length"].sum() <= 1024
    assert packing.pack_documents(empty).count() == 0


def test_encoder_agrees_on_odd_characters():
    encode = packing.Encoder()
    rng = random.Random(4)
    pool = [chr(c) for c in [*range(0, 0x240), 0x85, 0xA0, 0x2028, 0x3000, 0x1F600]] + ["'s", "  ", "\t\n", "<|endoftext|>"]
    for _ in range(300):
        text = "".join(rng.choice(pool) for _ in range(40))
        latin = max(text.encode(), default=0) < 0xC9
        assert encode(text, latin).tolist() == encode.full.encode(text, add_special_tokens=False).ids


# 9 toxicity


def test_toxicity_held_out(spark, sf):
    big = sf.replace("sf0.001", "sf0.01")
    docs, labels = spark.read.parquet(f"{big}/documents.parquet"), spark.read.parquet(f"{big}/labels.parquet")
    got = toxicity.report(docs, labels).join(labels, "doc_id").toPandas()
    held = got[got["held_out"]]
    clean, toxic = held[held["toxic"] == 0], held[held["toxic"] == 1]
    assert clean["predicted"].mean() < 0.05 and toxic["predicted"].mean() > 0.6
    assert toxic["score"].mean() > clean["score"].mean() + 0.4


def test_toxicity_learns_stems_and_odd_rows(spark, odd, empty):
    rng = random.Random(8)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    rows, labels = [], []
    for i in range(600):
        text = [word() for _ in range(30)]
        if bad := i % 6 == 0:
            text[rng.randrange(30)] = "zorgl" + word()[:3]
        rows.append((i, " ".join(text)))
        labels.append((i, 0, int(bad)))
    lab = spark.createDataFrame([*labels, (None, 0, 1), (5, 1, None), (0, 0, 1)], "doc_id bigint, quality int, toxic int")
    got = toxicity.report(documents(spark, rows), lab).collect()
    truth = {i: t for i, _, t in labels}
    held = [r for r in got if r["held_out"]]
    assert sum(r["predicted"] == truth[r["doc_id"]] for r in held) > 0.97 * len(held)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in got)
    grammar = toxicity.fit(empty, lab)
    scored = toxicity.score_documents(odd, grammar).collect()
    assert len(scored) == odd.count() and all(0 <= r["score"] < 0.7 for r in scored)
    assert toxicity.report(empty, lab.limit(0)).count() == 0
    kept = toxicity.without_toxic(documents(spark, [(1, "you are an idiot and a moron."), (2, "a fine day"), (3, None)]), grammar)
    assert sorted(r["doc_id"] for r in kept.collect()) == [2, 3]


def test_scores_against_brute_force(spark):
    """Clause by clause in plain Python: the best weight of each stem times its context's factor, through the logistic function."""
    grammar = toxicity.Grammar({0: {toxicity.word_hash("idiot"): 4.0, toxicity.word_hash("scum"): 3.0}, **{k: {} for k in toxicity.PREFIXES}, 5: {toxicity.word_hash("vileness", 5): 2.0}}, -3.0)
    weight = lambda w: {"idiot": 4.0, "scum": 3.0}.get(w) or (2.0 if len(w) > 5 and w.startswith("vilen") else None)
    stem = lambda w: w if w in ("idiot", "scum") else "vilen"

    def brute(text):
        best = {}
        for clause in re.split(r"[.!?;:,\n()]", text.lower()):
            words = [(m.group(), m.start()) for m in re.finditer(r"[a-z0-9]+", clause)]
            aimed, reported, negated = any(w in toxicity.TARGETS for w, _ in words), False, -99
            for i, (w, _) in enumerate(words):
                reported |= w in toxicity.REPORTS
                negated = i if w in toxicity.NEGATIONS else negated
                hit = (stem(w), weight(w)) if weight(w) else (w, toxicity.LEXICON_WEIGHT) if w in toxicity.THREATS and aimed else None
                if hit:
                    context = "reported" if reported else "negated" if i - negated <= toxicity.REACH else "targeted" if aimed else "plain"
                    best[hit[0]] = max(best.get(hit[0], 0), hit[1] * grammar.factors[context])
        return 1 / (1 + math.exp(3.0 - min(20.0, sum(best.values()))))

    rng = random.Random(11)
    pool = "idiot scum vileness vilenes you they not never said wrote kill hurt time day is a the . , ; tree".split()
    texts = [" ".join(rng.choices(pool, k=rng.randrange(1, 25))) for _ in range(300)]
    got = {r["doc_id"]: r["score"] for r in toxicity.score_documents(documents(spark, list(enumerate(texts))), grammar).collect()}
    assert all(abs(got[i] - brute(t)) < 1e-12 for i, t in enumerate(texts))


def test_contexts_weigh_matches(spark):
    grammar = toxicity.Grammar({0: {toxicity.word_hash("idiot"): 4.0}, **{k: {} for k in toxicity.PREFIXES}}, -2.0)
    texts = ["idiot", "you idiot", "he is not an idiot", 'he said "idiot"', "i will kill you", "to kill time", "not here. idiot"]
    got = {r["doc_id"]: r["score"] for r in toxicity.score_documents(documents(spark, list(enumerate(texts))), grammar).collect()}
    assert got[1] > got[0] > got[2] and got[3] < got[0] and got[4] > 0.7 > got[5] and got[6] == got[0]


# 10 substrings


def test_substring_dedup(spark, odd, empty):
    rng = random.Random(10)
    for window, seed, size in ((35, 16, 300), (5, 3, 12), (4, 9, 3)):
        vocabulary = [f"v{i}" for i in range(size)]
        make = lambda n: [rng.choice(vocabulary) for _ in range(n)]  # noqa: B023, E731
        passages = [make(rng.randrange(20, 90)) for _ in range(4)]
        rows = [(i, " ".join(make(rng.randrange(80)) + passages[i % 4][i % 7 :] + make(rng.randrange(30)))) for i in range(40)] + [(90, "x " * 80), (91, " ".join(passages[0] * 2))]
        got = sorted((r["doc_id"], r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring_dedup.report(documents(spark, rows), window).collect()) if seed == 16 else sorted((r["doc_id"], r["n_words"], r["n_removed"], hashlib.sha256(r["kept"].encode()).hexdigest()) for r in substring_dedup.remove_repeats(documents(spark, rows), window, seed).collect())
        assert got == sorted((i, *x) for (i, _), x in zip(rows, substring_dedup.brute_force([t for _, t in rows], window), strict=True))
    have = [(r["doc_id"], r["text"]) for r in odd.collect()]
    want = [(i, *x) for (i, _), x in zip(have, substring_dedup.brute_force([t for _, t in have]), strict=True)]
    assert sorted((tuple(r) for r in substring_dedup.report(odd).collect()), key=str) == sorted(want, key=str)
    out = substring_dedup.without_repeats(odd)
    assert out.columns == odd.columns and out.count() == odd.count() and out.where("text IS NULL").count() == odd.where("text IS NULL").count()
    assert substring_dedup.report(empty).count() == 0


def test_full_filters_change_no_result(spark, monkeypatch):
    """Filters that pass everything leave all decisions to the exact counts."""
    monkeypatch.setattr(substring_dedup, "hash_filter", lambda *_: exchange.HashFilter(np.full(16, 2**64 - 1, np.uint64), 10))
    rng = random.Random(3)
    passages = [[rng.choice("abcdefghijk") for _ in range(60)] for _ in range(3)]
    rows = [(i, " ".join([f"u{i}x{j}" for j in range(i % 5)] + passages[i % 3][i % 4 :] + [f"v{i}"] + passages[(i + 1) % 3][: 40 + i % 9])) for i in range(30)]
    got = sorted((r["doc_id"], r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring_dedup.report(documents(spark, rows)).collect())
    assert got == sorted((i, *x) for (i, _), x in zip(rows, substring_dedup.brute_force([t for _, t in rows]), strict=True))


def test_paths_are_the_nonbranching_runs(spark):
    """Against a walk over Python dictionaries: arcs of one edge each, texts over few arcs."""
    rng = random.Random(12)
    texts = [rng.choice(["abcde", "xyz", "pq", "abcxyz", "aab"]) + rng.choice(["", "-", "abcde"]) for _ in range(40)] + ["abababab", "m", "nop"]
    rows = [(ord(c), i, 0, j, 1) for i, t in enumerate(texts) for j, c in enumerate(t) if c != "-"]
    after, before = collections.defaultdict(set), collections.defaultdict(set)
    for i, t in enumerate(texts):
        for part in t.split("-"):
            for a, b in zip([None, *part], [*part, None], strict=True):
                after[a].add(b)
                before[b].add(a)
    follows = {b: next(iter(before[b])) for b in before if b and len(before[b]) == 1 and None not in before[b] and after[next(iter(before[b]))] == {b}}
    want = {}
    for c in {c for t in texts for c in t if c != "-"}:
        head, size = c, 1
        if c in follows:
            want[ord(c)] = 0
            continue
        while nexts := [x for x, y in follows.items() if y == head]:
            head, size = nexts[0], size + 1
        if size > 1:
            want[ord(c)] = size
    found = spark.createDataFrame(rows, "arc bigint, doc_id bigint, row_key bigint, start int, edges int")
    assert {r["arc"]: r["path"] for r in substring_dedup.compacted(found).collect()} == want and any(v > 1 for v in want.values())


def test_columns_with_generated_names(spark):
    rows = [(i, " ".join(f"w{j}" for j in range(60)), 1, 2, 3) for i in range(3)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, spans int, `key of row` int, `first digest` int")
    for out in (substring_dedup.without_repeats(df), minhash.first_of_classes(df.unionByName(df)), decontaminate.without_contaminated(df, spark.createDataFrame([(1, "w1 w2 w99")], "item_id bigint, text string"), max_block_mb=1e-6)):
        assert out.columns == df.columns and out.select("spans").distinct().collect()[0][0] == 1


def test_substring_dedup_filters_single_edges():
    """Of the pieces cut by a border, only edges that occur twice are sent to the join."""
    text = " ".join(f"w{i}" for i in range(60))
    batch = pa.RecordBatch.from_arrays([pa.array([1]), pa.array([0]), pa.array([text])], names=["doc_id", "row_key", "text"])
    everything, nothing = exchange.HashFilter(np.full(16, 2**64 - 1, np.uint64), 10), exchange.HashFilter(np.zeros(16, np.uint64), 10)
    rows = lambda repeated: pa.Table.from_batches(list(substring_dedup._edge_rows(iter([batch]), 35, 16, everything, everything, repeated)))
    edges = rows(everything).column("edge").to_numpy()
    assert len(edges) == 26
    slots = edges.view(np.uint64) >> np.uint64(44)
    few = exchange.HashFilter(np.zeros(1 << 14, np.uint64), 20)
    few.words[(slots[3:5] >> np.uint64(6)).astype(np.int64)] |= np.uint64(1) << (slots[3:5] & np.uint64(63))
    assert set(edges[3:5]) <= set(rows(few).column("edge").to_numpy()) and rows(few).num_rows < 26
    assert sum(b.num_rows for b in substring_dedup._edge_rows(iter([batch]), 35, 16, everything, everything, nothing)) == 0


def test_substring_dedup_counts_packed_hashes(spark):
    """Seeds and edges cross the shuffle as four bytes each; single occurrences are dropped before edges are counted with their checks."""
    rng = np.random.default_rng(3)
    h = rng.integers(0, 2**64, 5000, np.uint64)
    again = np.concatenate([h, h[:700], h[:50], h[:3]])
    rows = spark.createDataFrame(pa.Table.from_batches([*filters.packed(iter(np.array_split(again, 7))), *filters.packed(iter([h[700:900]]))]))
    assert sum(len(r["hashes"]) for r in rows.collect()) <= 4 * 5_900
    found = filters.repeats(rows).passes(h)
    assert found[:900].all() and found[900:].sum() < 200
    assert not filters.repeats(spark.createDataFrame(pa.Table.from_batches(list(filters.packed(iter([h[:3]])))))).passes(h).any()
    words = [f"w{i}" for i in range(400)]
    batch = pa.RecordBatch.from_pydict({"doc_id": [0, 1], "row_key": [0, 0], "text": [" ".join(words), " ".join(words[100:180] + ["x"] * 3 + words[300:])]})
    got = sorted((r["doc_id"], r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring_dedup.report(spark.createDataFrame(pa.Table.from_batches([batch]))).collect())
    assert got == sorted((i, *x) for i, x in enumerate(substring_dedup.brute_force(batch.column(2).to_pylist())))
