import base64
import hashlib
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from spectral_spark.llm import mixing, near_dedup, packing, quality, queries, substring_dedup, tokens, toxicity, url_filter, vp_search, warc
from spectral_spark.llm.components import components
from spectral_spark.llm.words import Block

from . import brute

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, component string, size string, sig string"


def vocabulary(n, seed):
    r = random.Random(seed)
    return ["".join(r.choice("abcdefghij") for _ in range(r.randint(2, 7))) for _ in range(n)]


def passage(seed, n=70):
    r, v = random.Random(seed), vocabulary(500, 1)
    words = [r.choice(v) for _ in range(n)]
    for i in range(8, n, 9):
        words[i] += "."
    return " ".join(words).capitalize() + "."


def odd_texts():
    """Nulls, empty, blank, short, very long, repeated and unusual texts, with clashing extra columns."""
    base = passage(3, 120)
    near = base.split()
    near[60] = "changed"
    texts = [None, "", " \t\n", "One", "one two", base, base, base.upper(), " ".join(near), "x\x1cy z\x85w <|endoftext|> q", "é" * 50 + " naïve Σίσυφος ΣΑΣ", passage(9, 60000), "a\nb\n\na\n", "   lead  and   gaps \r\n  "]
    rows = [(i, t, "en", f"s{i % 3}" if i % 4 else None, None, "c", "z", "s") for i, t in enumerate(texts)]
    return [*rows, (None, base, None, None, 1, None, None, None), (3, "One", "en", "s0", 3, "c", "z", "s")]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(odd_texts(), DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def documents(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def test_components_of_paths_stars_and_loops(spark):
    r = random.Random(4)
    links = [(i, i + 1) for i in range(0, 200)] + [(1000, 1000 + r.randint(1, 400)) for _ in range(300)] + [(7000, 7000)]
    got = {x.id: x.component for x in components(spark, spark.createDataFrame(links, "a long, b long")).collect()}
    assert {got[i] for i in range(201)} == {0}
    assert {c for i, c in got.items() if 1000 <= i < 2000} == {1000}
    assert 7000 not in got


def test_sequential_test_keeps_similar_pairs():
    p = near_dedup.MinHash()
    least = near_dedup.least_matches(p.percent, p.batch, p.batches, p.miss)
    assert list(least) == sorted(least) and all(0 < m < p.batch * (k + 1) for k, m in enumerate(least))
    r = np.random.default_rng(1)
    left = r.integers(0, 1 << 32, (2000, p.size), np.uint32)
    right = np.where(r.random(left.shape) < 0.86, left, 0)
    assert len(near_dedup._sequential(left, right, p)) >= 1998
    right = np.where(r.random(left.shape) < 0.5, left, 0)
    assert len(near_dedup._sequential(left, right, p)) == 0


def test_near_duplicates_against_all_pairs(spark, documents):
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in near_dedup.near_duplicates(spark, documents).collect()}
    assert got == brute.near_components([(x.doc_id, x.text) for x in documents.collect()])


def test_near_duplicates_of_chains(spark):
    """Neighbours in a chain of edits are similar, its ends are not; hubs alone would miss links."""
    words = vocabulary(400, 2)[:150]
    rows = []
    for step in range(40):
        words = list(words)
        words[(step * 7) % 150] = f"edit{step}"
        rows.append((step * 3 + 1, " ".join(words)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute.near_components(rows)
    # blocks of few documents, and of few shingles
    for p in (near_dedup.MinHash(block=8), near_dedup.MinHash(block_shingles=700)):
        assert {x.doc_id: (x.n_shingles, x.component_id) for x in near_dedup.near_duplicates(spark, docs, p).collect()} == want


def test_near_duplicates_of_odd_rows(spark, odd, none):
    rows = near_dedup.near_duplicates(spark, odd).collect()
    assert len(rows) == len(odd_texts())
    by = defaultdict(list)
    for x in rows:
        by[x.doc_id].append(x)
    assert [(by[i][0].n_shingles, by[i][0].component_id, by[i][0].kept) for i in (0, 1, 2)] == [(0, 0, True), (0, 1, True), (0, 2, True)]
    assert {by[i][0].component_id for i in (5, 6, 7, 8)} == {5} and by[None][0].component_id is None and by[None][0].kept
    assert len(by[3]) == 2 and near_dedup.near_duplicates(spark, none).count() == 0


def test_near_duplicates_of_one_id_with_several_texts(spark):
    """Documents 5 and 6 have two texts each; copies of either text belong to them, and 5 and 6 meet through 9."""
    a, b, c, d = (passage(200 + i, 80) for i in range(4))
    near = lambda t, w: " ".join([*t.split()[:40], w, *t.split()[41:]])
    rows = [(5, a), (5, b), (7, near(b, "x")), (6, c), (6, d), (8, near(d, "y")), (10, passage(300, 80)), (5, a), (9, near(a, "z")), (9, near(c, "q"))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = defaultdict(set)
    for x in near_dedup.near_duplicates(spark, docs).collect():
        got[x.doc_id].add((x.component_id, x.kept))
    assert got == {5: {(5, True)}, 7: {(5, False)}, 6: {(5, False)}, 8: {(5, False)}, 9: {(5, False)}, 10: {(10, True)}}
    # one id on many rows of different texts
    rows = [(1, passage(400 + i, 60)) for i in range(60)] + [(2 + i, near(passage(400 + i, 60), "w")) for i in range(0, 60, 7)] + [(900, passage(999, 60))]
    out = near_dedup.near_duplicates(spark, spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert len(out) == len(rows) and {x.component_id for x in out if x.doc_id < 900} == {1} and [x.component_id for x in out if x.doc_id == 900] == [900]


def test_copies_are_dropped_row_by_row(spark, odd, none):
    a, b, c = (passage(500 + i, 80) for i in range(3))
    near = " ".join([*a.split()[:40], "x", *a.split()[41:]])
    rows = [(5, a, "p"), (9, near, "q"), (9, b, "r"), (9, b, "r"), (None, near, "s"), (None, c, "t"), (3, "", "u"), (4, None, "v")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, name string")
    p = near_dedup.MinHash(words=5, percent=80)
    kept = sorted(x.name for x in near_dedup.drop_copies(spark, docs, p).collect())
    assert kept == ["p", "r", "t", "u", "v"]
    assert near_dedup.drop_copies(spark, odd, p).columns == odd.columns and near_dedup.drop_copies(spark, none, p).count() == 0


def test_long_texts_cost_little_memory():
    """Hashing, shingle sets and signatures of a text of 64 MB in a process of its own: its bytes are held once, and a few numbers a word."""
    import subprocess
    import sys

    code = """
import numpy as np
from spectral_spark.llm import near_dedup, words
peak = lambda: int(next(l for l in open('/proc/self/status') if l.startswith('VmHWM')).split()[1]) / 1024
names = [b'w%d ' % i for i in range(100000, 300000)]
raw = np.frombuffer(b''.join(names[i] for i in np.random.default_rng(1).integers(0, 200000, 8_400_000)), np.uint8)
del names
words.release()
open('/proc/self/clear_refs', 'w').write('5')
base = peak()
block = words.Block(raw, np.array([0, len(raw)]))
sets, limits = words.distinct(*words.shingles(block.hashes(), block.first, 5))
near_dedup.signature(sets, limits, 128), near_dedup.set_digests(sets, limits)
print(len(raw) >> 20, peak() - base)
"""
    done = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, check=True)
    size, used = map(float, done.stdout.split())
    assert size >= 64 and used < 300


def test_words_do_not_depend_on_chunks(monkeypatch):
    from spectral_spark.llm import words

    r = random.Random(13)
    for _ in range(40):
        texts = ["".join(r.choice("ab C\n\t é.x") for _ in range(r.randint(0, 60))) for _ in range(r.randint(0, 12))]
        at = np.cumsum([0, *(len(t.encode()) for t in texts)])
        raw = np.frombuffer("".join(texts).encode(), np.uint8)
        seen = []
        for chunk in (1 << 17, 16, 3):
            monkeypatch.setattr(words, "CHUNK", chunk)
            words.powers.cache_clear()
            b = Block(raw, at)
            w = b.hashes()
            seen.append((b.start.tolist(), b.end.tolist(), w.tolist(), b.hashes(prefix=2).tolist(), words.shingles(w, b.first, 3)[0].tolist()))
        words.powers.cache_clear()
        assert seen[0] == seen[1] == seen[2]
        words_of = [m for t in texts for m in __import__("re").findall(rb"[^\x20\x09-\x0d]+", t.encode())]
        assert [raw[a:b].tobytes() for a, b in zip(*seen[0][:2])] == words_of


def test_token_counts_equal_the_library(spark, documents, odd, none):
    lib = tokens.load(tokens.vocabulary("byte_bpe_50k.json"))
    r = random.Random(5)
    alphabet = "ab Z9'é\n\t   \x1c\x1f中🙂.,!?<|endoftext|>sre"
    noise = spark.createDataFrame([(i, "".join(r.choice([*alphabet, "<|endoftext|>", "  ", "'re"]) for _ in range(r.randint(0, 80)))) for i in range(400)], "doc_id long, text string")
    for docs in (documents, odd, noise):
        for x, y in zip(tokens.token_counts(docs).collect(), docs.collect()):
            text = y.text or ""
            assert (x.n_bytes, x.n_tokens) == (len(text.encode()), len(lib.encode(text, add_special_tokens=False).ids)), repr(text[:80])
            assert x.over_limit == (x.n_tokens > 512)
    assert tokens.token_counts(none).count() == 0


def test_packing_round_trip(spark, documents, odd, none):
    lib = tokens.load(tokens.vocabulary("word_bpe_49k.json"))
    for docs in (documents, odd):
        docs = docs.where("doc_id is not null").dropDuplicates(["doc_id"])
        rows = packing.pack(spark, docs).collect()
        want = {}
        for y in docs.collect():
            ids = np.array([*lib.encode(y.text or "", add_special_tokens=False).ids, 1], "<u4")
            for s in range(0, len(ids), 4096):
                part = ids[s : s + 4096]
                want[y.doc_id, s // 4096] = (s, len(part), zlib.crc32(part.tobytes()))
        assert {(x.doc_id, x.piece): (x.start, x.length, x.ids_crc32) for x in rows} == want and len(rows) == len(want)
        bins = defaultdict(list)
        for x in rows:
            bins[x.sequence_id].append((x.offset, x.length))
        for parts in bins.values():
            end = 0
            for offset, length in sorted(parts):
                assert offset == end
                end += length
            assert end <= 4096
        assert len(bins) <= 1.1 * sum(x.length for x in rows) / 4096 + 2
    assert packing.pack(spark, none).count() == 0


def test_best_fit_takes_the_tightest_and_closes_the_fullest():
    b = packing.BestFit(10, 2)
    assert [b.put(n) for n in (6, 7, 3)] == [(0, 0), (1, 0), (1, 7)]
    assert [b.put(n) for n in (5, 5, 9)] == [(2, 0), (2, 5), (3, 0)]
    assert b.put(8) == (4, 0) and b.still_open() == {0, 4}


def test_line_quality_counts(spark, documents, odd, none):
    for docs in (documents, odd):
        for x, y in zip(quality.line_first_cleaning(docs).collect(), docs.collect()):
            text = y.text or ""
            words = brute.WORD.findall(text)
            lines = [s for s in text.split("\n") if brute.WORD.search(s)]
            assert x.n_words == len(words) and x.word_chars == sum(map(len, words))
            assert x.n_symbols == sum(c in "#*$%&|<>" for c in text) and x.n_dup_lines == len(lines) - len(set(lines))
            assert x.n_repeat_words == brute.repeat_words(words)
            assert x.base_failed == (len(words) < 10 or 100 * x.n_repeat_words > 20 * len(words))
            assert not (x.base_failed and x.kept)
    assert quality.line_first_cleaning(none).count() == 0


def test_line_rules():
    assert quality.line_failure("Home | About | Contact | Shop", 7) == "navigation"
    assert quality.line_failure("We use cookies. Accept all cookies.", 6) == "boilerplate"
    assert quality.line_failure("no sentence end here", 4) == "punctuation"
    assert {quality.line_failure(x, 4) for x in ("Alle Rechte vorbehalten.", "© 2020 TOUS DROITS RÉSERVÉS.", "Política de Privacidad.")} == {"boilerplate"}
    assert quality.line_failure('A sentence, "quoted."', 3) is None
    assert quality.clean_lines("Good line.\nmenu\nGood line.")[0] == "Good line.\nGood line."


def test_url_rules(spark):
    urls = [None, "", "no scheme", "http://", "HTTP://A.Example.COM/en/7?x", "http://example.com/en/6", "http://x.net/de/8", "http://example.net/de/8", "http://b.example.net/de/81#y", "http://org/es/?q", "http://xorg/es/", "http://b.org#es/", "http://a.com/EN/1", "http://a.b.c.d.e.f.com/en/"]
    pages = spark.createDataFrame([(i, u, "x", "y") for i, u in enumerate(urls * 2)], "page_id long, url string, rule string, host string").select("page_id", "url", "rule", "host")
    got = {x.page_id: (x.host, x.path, x.rule, x.verdict) for x in url_filter.filter_urls(spark, pages.select("page_id", "url"), queries.RULES).collect()}
    assert [got[i] for i in range(4)] == [("", "", None, "allow")] * 4
    assert got[4] == ("a.example.com", "/en/7", "example.com/en/7", "allow") and got[5] == ("example.com", "/en/6", "com/en/", "block")
    assert got[6][2] == "net/de/" and got[7][2] == got[8][2] == "example.net/de/8" and got[9][2] == "org/es/"
    assert [got[i][2] for i in (10, 11, 12)] == [None] * 3 and got[13][2] == "com/en/" and len(got) == 2 * len(urls)
    assert url_filter.filter_urls(spark, pages, []).where("verdict <> 'allow'").count() == 0
    clash = url_filter.filter_urls(spark, pages, queries.RULES)
    assert clash.count() == 2 * len(urls) and url_filter.filter_urls(spark, pages.limit(0), queries.RULES).count() == 0


def test_url_verdicts_of_the_contract(spark, tmp_path):
    """The verdict of every rule of the query's contract; where a block and an allow rule both fit, the longer one's."""
    wanted = {"http://com/en/x": "block", "http://a.example.com/en/71": "allow", "http://net/de/": "allow", "http://x.net/de/8": "allow", "http://example.net/de/7": "allow", "http://b.example.net/de/8": "block", "http://a.org/es/": "block", "http://a.net/en/": "allow"}
    spark.createDataFrame(list(enumerate(wanted)), "page_id long, url string").write.parquet(str(tmp_path / "pages.parquet"))
    got = {x.page_id: x.verdict for x in queries.op5_url_filter(spark, str(tmp_path)).collect()}
    assert [got[i] for i in range(len(wanted))] == list(wanted.values())


def test_mixing(spark, odd, none):
    docs = spark.createDataFrame([(i, "w " * (5 + i % 50), f"s{i % 7}" if i % 7 else None) for i in range(20000)] + [(i, None, "empty") for i in range(5)], "doc_id long, text string, source string")
    rows = mixing.mix_sources(docs).collect()
    total = sum(x.size for x in rows)
    by = defaultdict(lambda: [0, 0, 0.0])
    for x in rows:
        by[x.source][0] += x.size
        by[x.source][1] += x.copies * x.size
        by[x.source][2] = x.target
        assert 0 <= x.copies <= 2 and x.text is None or x.size == x.text.count("w")
    assert sum(v[2] for v in by.values()) == pytest.approx(1.5 * total)
    for size, taken, target in by.values():
        assert target <= 2 * size + 1e-6 and abs(taken - target) <= 0.05 * target + 1
    again = {(x.doc_id, x.source): x.copies for x in mixing.mix_sources(docs.repartition(7)).collect()}
    assert again == {(x.doc_id, x.source): x.copies for x in rows}
    assert mixing.mix_sources(odd).count() == len(odd_texts()) and mixing.mix_sources(none).count() == 0
    assert mixing.mix_sources(docs.where("source = 'empty'")).where("copies <> 0").count() == 0


def test_mixing_draws_by_row(spark):
    """Null and repeated ids draw apart; a caller's columns may have any name."""
    rows = [(None if i % 2 else 7, f"w{i} b c", "null ids", "x") for i in range(8000)] + [(i, "w " * 40, "big", "y") for i in range(2000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, of string").withColumn("row", F.lit(1)).withColumn("key", F.lit(2)).withColumn("whole", F.lit(3))
    out = mixing.mix_sources(docs)
    assert out.columns == ["doc_id", "text", "source", "of", "row", "key", "whole", "size", "source_size", "target", "copies"]
    got = out.groupBy("source").agg(F.sum(F.col("copies") * F.col("size")).alias("taken"), F.max("target").alias("target")).collect()
    assert len(got) == 2 and all(abs(x.taken - x.target) <= 0.05 * x.target for x in got)


def plain_chain(x, labels, fit, folds):
    """A chain with plain dense features: out-of-fold probabilities of a category are a column for the next one."""
    seen, models, n = np.zeros((len(x), 0)), [], len(x)
    for c in range(labels.shape[1]):
        y, given = labels[:, c], ~np.isnan(labels[:, c])
        models.append(fit(np.hstack([x, seen])[given], y[given]))
        out = np.zeros(n)
        for f in range(folds):
            held = np.arange(n) % folds == f
            w = fit(np.hstack([x, seen])[~held & given], y[~held & given])
            out[held] = 1 / (1 + np.exp(-(np.hstack([x, seen])[held] @ w[:-1] + w[-1])))
        seen = np.column_stack([seen, out])
    return models


def test_chain_equals_a_plain_one():
    """The sparse chain against dense matrices and the same descent, labels of one category partly unknown."""
    r, s = np.random.default_rng(9), toxicity.ChainSettings(buckets=12, chosen=12, steps=150)
    dense = r.random((160, 12)) < 0.3
    dense[:2] = True
    labels = np.column_stack([dense[:, 0] | (r.random(160) < 0.1), dense[:, 0] ^ dense[:, 3]]).astype(float)
    labels[::9, 0] = np.nan
    index, limits = np.nonzero(dense)[1], np.concatenate([[0], np.cumsum(dense.sum(1))])

    def fit(x, y):
        w, rate = np.zeros(x.shape[1] + 1), y.mean()
        w[-1] = np.log((rate + 1e-3) / (1 - rate + 1e-3))
        m, v, one = np.zeros_like(w), np.zeros_like(w), np.hstack([x, np.ones((len(x), 1))])
        for t in range(1, s.steps + 1):
            g = one.T @ (1 / (1 + np.exp(-(one @ w))) - y)
            g[:-1] += s.ridge * w[:-1]
            g /= len(x)
            m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
            w = w - 0.05 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        return w

    chain = toxicity.train_chain(index, limits, labels, ("a", "b"), s)
    assert [(known >= 0).sum() for known, _ in chain.models] == [12, 12]
    for (_, w), want in zip(chain.models, plain_chain(dense.astype(float), labels, fit, s.folds)):
        assert np.allclose(w, want, atol=1e-6)
    p = chain.predict(index, limits)
    first = 1 / (1 + np.exp(-(dense @ chain.models[0][1][:-1] + chain.models[0][1][-1])))
    assert np.allclose(p[:, 0], first) and np.allclose(p[:, 1], 1 / (1 + np.exp(-(np.column_stack([dense, first]) @ chain.models[1][1][:-1] + chain.models[1][1][-1]))))


def test_training_rows_are_bounded(spark):
    """Many rows of one labelled id give one training row; a long text gives at most the bound of features."""
    docs = spark.createDataFrame([(1, f"a{i} b c") for i in range(500)] + [(2, " ".join(f"w{i}" for i in range(3000)))], "doc_id long, text string")
    labels = spark.createDataFrame([(1, None, 1), (2, 1, 0), (2, 0, None)], "doc_id long, quality int, toxic int")
    index, limits, known = toxicity.labelled_features(docs, labels, toxicity.CATEGORIES, toxicity.ChainSettings(sample_features=500))
    assert len(limits) == 3 and np.diff(limits)[1] == 500 and np.isnan(known[0, 0]) and known[0, 1] == 1 and known[1].tolist() == [1, 0]


def test_toxicity_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    held = F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(4)) == 0
    chain = toxicity.fit_toxicity(docs, labels.where(~held))
    out = toxicity.score_toxicity(spark, docs.join(labels.where(held).select("doc_id", "toxic"), "doc_id"), chain).select("toxic", "rejected").collect()
    hit, false = sum(x.toxic and x.rejected for x in out), sum(x.rejected and not x.toxic for x in out)
    assert hit >= 0.85 * sum(x.toxic for x in out) and false <= 0.005 * len(out)


def test_toxicity_of_odd_rows(spark, odd, none):
    labels = spark.createDataFrame([(5, 1, 0), (8, 1, 1), (9, None, 1), (None, 1, 1), (0, 0, 0), (99, 1, 1)], "doc_id long, quality int, toxic int")
    out = toxicity.score_toxicity(spark, odd.withColumn("rejected", F.lit("x")), toxicity.fit_toxicity(odd, labels)).collect()
    assert len(out) == len(odd_texts()) and not any(x.rejected for x in out if not (x.text or "").strip())
    chain = toxicity.fit_toxicity(none, labels.limit(0))
    assert toxicity.score_toxicity(spark, none, chain).count() == 0 and toxicity.score_toxicity(spark, odd, chain).count() == len(odd_texts())


def test_archive_round_trip(spark, tmp_path):
    html = ["<p>a</p>", "<p>a</p>", None, "", "x\r\n\r\nWARC/1.1\r\n\r\n", "é" * 3000, "<p>a</p>", "x\r\n\r\n"]
    pages = spark.createDataFrame([(i, f"http://www.h{i % 3}.org/p?q={i}" if i != 2 else None, h, "extra") for i, h in enumerate(html)], "page_id long, url string, html string, digest string")
    rows = {x.page_id: x for x in warc.archive(spark, pages, str(tmp_path / "a")).collect()}
    last = {h or "": i for i, h in enumerate(html)}
    for i, h in enumerate(html):
        body = (h or "").encode()
        x = rows[i]
        assert (x.payload_bytes, x.payload_digest, x.sound) == (len(body), base64.b32encode(hashlib.sha1(body).digest()).decode(), True)
        assert (x.record_type, x.refers_to) == (("response", None) if last[h or ""] == i else ("revisit", last[h or ""]))
    small = warc.archive(spark, pages, str(tmp_path / "b"), least_bytes=100)
    assert small.where("record_type = 'revisit'").count() == 0
    assert warc.archive(spark, pages.limit(0), str(tmp_path / "c")).count() == 0
    doubled = warc.archive(spark, pages.unionByName(pages), str(tmp_path / "d"))
    assert doubled.count() == 2 * len(html) and doubled.where("not sound").count() == 0


def test_single_records_by_index_entry(spark, tmp_path, monkeypatch):
    """Each record is read by the file, offset and length that the index names; files are bounded, payloads longer than a piece are whole."""
    import gzip

    monkeypatch.setattr(warc, "PIECE", 1000)
    html = [f"<p>{i}</p>" * (1 + 400 * (i % 5)) for i in range(60)] + ["<p>0</p>"]
    pages = spark.createDataFrame([(i, f"http://h.org/{i}\n", h) for i, h in enumerate(html)], "page_id long, url string, html string").repartition(3)
    path = str(tmp_path / "a")
    index = warc.archive(spark, pages, path).collect()
    assert len(index) == len(html)
    for x in index:
        headers, block = warc.fetch(path, x.file, x.offset, x.length)
        assert headers["warc-record-id"] == f"<urn:page:{x.page_id}>" and headers["warc-target-uri"].endswith("%0A")
        assert block == (html[x.page_id].encode() if x.record_type == "response" else b"")
        assert gzip.decompress(open(f"{path}/{x.file}", "rb").read()[x.offset : x.offset + x.length]).startswith(b"WARC/1.1")
    with open(f"{path}/{index[0].file}", "rb") as f:
        whole = f.read()
    with pytest.raises(ValueError):
        list(warc.members(__import__("io").BytesIO(whole[:-5])))


def test_index_is_in_global_order(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    keys = [(x.url_key, x.captured) for x in warc.archive(spark, pages).collect()]
    assert keys == sorted(keys) and len(keys) == pages.count()


def test_loser_tree():
    r = random.Random(8)
    for k in (0, 1, 2, 3, 7, 16, 33):
        runs = [sorted((r.randint(0, 50), i) for i in range(r.randint(0, 40))) for _ in range(k)]
        assert list(warc.LoserTree([iter(x) for x in runs])) == sorted(y for x in runs for y in x)


def test_vantage_point_search(spark):
    r = np.random.default_rng(3)
    m = r.normal(size=(900, 8)).astype("float32").tolist()
    rows = [(i, v) for i, v in enumerate(m)] + [(1000 + i, m[4]) for i in range(40)]
    bad = [(2000, None), (2001, [0.0] * 8), (2002, [float("nan")] * 8), (2003, [None] * 8), (2004, [float("inf")] * 8), (None, m[0])]
    table = spark.createDataFrame(rows + bad, "vec_id long, embedding array<float>")
    asked = table.where("vec_id % 20 = 0")
    want = brute.nearest(rows, [x for x in rows if x[0] % 20 == 0], 10)
    got = defaultdict(list)
    for x in vp_search.nearest(spark, table, asked, factor=1.0).orderBy("query_id", "rank").collect():
        got[x.query_id].append((x.vec_id, x.score))
    assert got.keys() == want.keys()
    for q, found in got.items():
        assert [i for i, _ in found] == [i for i, _ in want[q]] and np.allclose([d for _, d in found], [d for _, d in want[q]], atol=1e-12)
    few = table.where("vec_id < 4")
    assert vp_search.nearest(spark, few, few).count() == 12 and vp_search.nearest(spark, few.limit(0), few.limit(0)).count() == 0


def test_vantage_point_recall(spark):
    for sf in ("sf0.001", "sf0.1"):
        v = spark.read.parquet(f"/root/testdata/{sf}/embeddings.parquet")
        rows = [(x.vec_id, x.embedding) for x in v.collect()]
        want = brute.nearest(rows, [x for x in rows if x[0] % 100 == 0], 10)
        got = defaultdict(set)
        for x in queries.op9_vp_nearest(spark, f"/root/testdata/{sf}").collect():
            got[x.query_id].add(x.vec_id)
        assert np.mean([len(got[q] & {i for i, _ in found}) / len(found) for q, found in want.items()]) >= 0.9


def test_vantage_point_search_prunes(spark):
    """Clustered vectors: the exact search skips most of them, and a smaller factor skips more; many queries walk a tree together."""
    r = np.random.default_rng(4)
    centres = r.normal(size=(40, 16)) * 5
    m = np.repeat(centres, 100, 0) + r.normal(size=(4000, 16)) * 0.3
    tree = vp_search.VPTree(np.arange(4000), m, 11)
    asked, bound = np.arange(0, 4000, 20), np.full(200, np.inf)
    want = brute.nearest(list(enumerate(m)), [(int(i), m[i]) for i in asked], 10)
    compared = []
    for factor in (1.0, 0.5, 0.2):
        score, who, seen = tree.search(asked, m[asked], 10, factor, bound)
        compared.append(seen.mean())
        if factor == 1.0:
            assert all([int(j) for j in who[k]] == [j for j, _ in want[int(i)]] for k, i in enumerate(asked))
    assert compared[0] < 0.3 * 4000 and compared == sorted(compared, reverse=True)


def test_vantage_point_shards(spark, monkeypatch):
    """Several shards: exact at factor one, and leaves are skipped where the vectors part."""
    monkeypatch.setattr(vp_search, "SHARD_ROWS", 150)
    r = np.random.default_rng(6)
    m = np.repeat(r.normal(size=(12, 8)) * 6, 100, 0) + r.normal(size=(1200, 8)) * 0.2
    rows = [(i, v) for i, v in enumerate(m.tolist())] + [(1100, m[1100].tolist())] * 30
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(5)
    asked = table.where("vec_id % 20 = 0")
    got = defaultdict(list)
    compared = {}
    for x in vp_search.nearest(spark, table, asked, factor=1.0).orderBy("query_id", "rank").collect():
        got[x.query_id].append(x.vec_id)
        compared[x.query_id] = x.compared
    want = brute.nearest([(i, v) for i, v in rows], [(i, m[i]) for i in range(0, 1200, 20)], 10)
    assert got == {i: [j for j, _ in found] for i, found in want.items()}
    assert np.mean(list(compared.values())) < 0.5 * len(rows)


def test_repeated_passages(spark, none):
    planted = [passage(100 + i, 55 + 5 * i) for i in range(4)]
    r, v = random.Random(11), vocabulary(3000, 12)
    rows, holders = [], defaultdict(list)
    for i in range(80):
        own = [r.choice(v) + ("." if k % 8 == 7 else "") for k in range(150)]
        at = r.randint(0, 150)
        if i % 4 == 0:
            holders[i // 4 % 4].append(i)
            own = [*own[:at], *planted[i // 4 % 4].split(), *own[at:]]
        rows.append((i, "A common line of few words stands here.\n" + " ".join(own), "src"))
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    out = {x.doc_id: x for x in substring_dedup.dedup_substrings(spark, docs).collect()}
    assert len(out) == 80
    for k, ids in holders.items():
        assert planted[k] in " ".join(out[ids[0]].clean_text.split())
        for i in ids[1:]:
            assert out[i].n_removed >= 25 and planted[k] not in out[i].clean_text
    clean = set(range(80)) - {i for ids in holders.values() for i in ids}
    assert all(out[i].n_removed == 0 and out[i].clean_text == rows[i][1] for i in clean)
    assert substring_dedup.dedup_substrings(spark, none).count() == 0


def test_repeated_passages_of_odd_rows(spark, odd):
    out = substring_dedup.dedup_substrings(spark, odd).collect()
    assert len(out) == len(odd_texts())
    by = {x.doc_id: x for x in out}
    assert by[5].n_removed == 0 and by[6].n_removed >= 60 and by[0].clean_text is None and by[None].n_removed == 0


def hosts(passages, seed, lead=120):
    """Texts of words that stand nowhere else around each passage, with the place of the passage: (text, first word)."""
    r, out = random.Random(seed), []
    for k, words in enumerate(passages):
        own = [f"w{seed}x{k}x{i}" + ("." if r.random() < 0.1 else "") for i in range(lead)]
        at = r.randint(0, lead)
        out.append((" ".join([*own[:at], *words, *own[at:]]), at))
    return out


def removed_runs(spark, texts):
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return {x.doc_id: [(s["first"], s["size"]) for s in x.spans] for x in substring_dedup.repeated_spans(spark, docs).collect()}


def test_all_words_of_a_passage_go(spark):
    """Twelve passages of each length, each in three texts: the later two lose them from the first word to the last."""
    passages = [passage(1000 * n + k, n).split() for n in (25, 51, 55, 60, 80, 300) for k in range(12)]
    placed = hosts(passages * 3, 1)
    got, m = removed_runs(spark, [t for t, _ in placed]), len(passages)
    assert got == {i: [(at, len(passages[i % m]))] for i, (_, at) in enumerate(placed) if i >= m}


def test_repeated_runs_equal_brute_force(spark):
    """Every word of a run of 25 that an earlier document has is removed; what is removed repeats in windows of 16, but for short changes."""
    rows = [(x.doc_id, brute.WORD.findall(brute.lower(x.text))) for x in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    first = {n: {} for n in (16, 25)}
    for n, seen in first.items():
        for i, words in sorted(rows):
            for k in range(len(words) - n + 1):
                seen.setdefault(tuple(words[k : k + n]), i)
    cover = lambda i, words, n: {k + j for k in range(len(words) - n + 1) if first[n][tuple(words[k : k + n])] < i for j in range(n)}
    spans = {x.doc_id: x.spans for x in substring_dedup.repeated_spans(spark, spark.read.parquet(f"{SF}/documents.parquet")).collect()}
    whole = 0
    for i, words in rows:
        must, may = cover(i, words, 25), cover(i, words, 16)
        whole += len(must)
        got = {s["first"] + k for s in spans.get(i, []) for k in range(s["size"])}
        assert must <= got
        for s in spans.get(i, []):
            run = set(range(s["first"], s["first"] + s["size"]))
            assert max(run) < len(words) and 100 * len(run - may) <= 20 * len(run)
    assert whole > 1000


def test_exact_jaccard_of_edited_passages(spark):
    base = passage(77, 120).split()
    edited = [*base]
    edited[60] = "other"
    docs = spark.createDataFrame([(1, " ".join(base)), (2, "Lead. " + " ".join(edited)), (3, passage(78, 120))], "doc_id long, text string")
    out = {x.doc_id: x.n_removed for x in substring_dedup.dedup_substrings(spark, docs).collect()}
    assert out[1] == 0 and out[3] == 0 and out[2] >= 40


def test_passages_with_one_changed_word_go_whole(spark):
    """51, 55 and 60 words, the middle one changed: similar at 80 % by shingles of five."""
    base = [passage(5000 * n + k, n).split() for n in (51, 55, 60) for k in range(12)]
    base.append(passage(77, 60).split())
    edited = [[*w[: len(w) // 2], "other", *w[len(w) // 2 + 1 :]] for w in base]
    placed = hosts([*base, *edited], 2)
    got = removed_runs(spark, [t for t, _ in placed])
    assert got == {i: [(placed[i][1], len(edited[i - len(base)]))] for i in range(len(base), 2 * len(base))}


def test_passages_made_of_common_phrases(spark):
    """Each phrase stands in an earlier text of its own; the two texts that share them all are still compared."""
    phrases = [[passage(9000 + 10 * k + i, 15).split() for i in range(4)] for k in range(10)]
    whole = [sum(x, []) for x in phrases]
    single = [x for y in phrases for x in y]
    placed = hosts([*single, *whole, *whole], 3)
    got = removed_runs(spark, [t for t, _ in placed])
    assert got == {i: [(placed[i][1], 60)] for i in range(len(placed) - len(whole), len(placed))}


def test_seeds_do_not_depend_on_other_texts():
    r, p = random.Random(6), substring_dedup.Paragraphs()
    texts = ["", "one", *(" ".join(str(r.randint(0, 500)) for _ in range(r.randint(1, 200))) for _ in range(200)), "a " * 40, "x. " * 16, ""]

    def found(some):
        raw = "".join(some).encode()
        block = Block(np.frombuffer(raw, np.uint8), np.cumsum([0, *(len(t.encode()) for t in some)]))
        word = block.hashes()
        text, at = substring_dedup.seeds(block, word, p)
        rows = list(zip(text.tolist(), (at - block.first[text]).tolist(), substring_dedup.window_keys(word, at, p.size).tolist()))
        return [[x[1:] for x in rows if x[0] == i] for i in range(len(some))]

    alone = [found([t])[0] for t in texts]
    assert found(texts) == alone and found(texts[::-1]) == alone[::-1]
    for t, places in zip(texts, alone):
        starts = {a for a, _ in places}
        # every run of 25 words holds one, and so does every shorter text of 16 or more
        assert all(starts & set(range(a, a + p.span)) for a in range(len(t.split()) - p.size - p.span + 2))
        assert bool(places) == (len(t.split()) >= p.size)


def test_similar_paragraphs_share_a_band():
    """Every pair of equal paragraphs of 25 words does; of pairs similar at 0.8 or a little more, at least 95 % do."""
    p, r = substring_dedup.Paragraphs(), random.Random(17)

    def keys(words):
        raw = " ".join(words).encode()
        block = Block(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]))
        return set(substring_dedup.band_runs(block, block.hashes(), p)[1].tolist())

    met = 0
    for k in range(400):
        words = [f"v{r.randint(0, 10**6)}" for _ in range(25)]
        assert keys(words) == keys(list(words))
        near = list(words)
        near[r.choice([1, 23])] = "changed"
        a, b = ({tuple(x[i : i + 5]) for i in range(21)} for x in (words, near))
        assert 0.8 <= len(a & b) / len(a | b) < 0.9
        met += bool(keys(words) & keys(near))
    assert met >= 380


def test_shorter_runs_stay(spark):
    """22 common words are 18 of 21 shingles, similar at 18 / 24; 23 are similar at 19 / 23."""
    p = substring_dedup.Paragraphs()
    assert p.least_run == 23 and 19 / (42 - 19) >= 0.8 > 18 / (42 - 18)
    passages = [passage(7000 + 40 * n + k, n).split() for n in (18, 20, 22, 25, 30) for k in range(6)]
    placed = hosts(passages * 2, 12)
    got, m = removed_runs(spark, [t for t, _ in placed]), len(passages)
    assert got == {i: [(at, len(passages[i % m]))] for i, (_, at) in enumerate(placed) if i >= m and len(passages[i % m]) >= 25}


def test_clusters_keep_the_first_document(spark):
    """Document 9 repeats 4, which repeats 2, by different halves of a passage: one component, kept in 2."""
    a, b = passage(610, 40), passage(611, 40)
    (x, _), (y, _), (z, _), (w, _) = hosts([a.split(), [*a.split(), *b.split()], b.split(), passage(612, 40).split()], 7)
    docs = spark.createDataFrame([(2, x), (4, y), (9, z), (11, w)], "doc_id long, text string")
    out = {d.doc_id: [(s["size"], s["home"]) for s in d.spans] for d in substring_dedup.repeated_spans(spark, docs).collect()}
    assert out == {4: [(40, 2)], 9: [(40, 4)]}
    (v, _), = hosts([b.split()], 9)
    docs = spark.createDataFrame([(2, x), (4, y), (9, z), (1, v)], "doc_id long, text string")
    out = {d.doc_id: [(s["size"], s["home"]) for s in d.spans] for d in substring_dedup.repeated_spans(spark, docs).collect()}
    assert out == {4: [(80, 1)], 9: [(40, 1)]}


def test_passages_of_rows_that_share_an_id(spark):
    """Each text loses its own spans; equal names of other columns do not matter."""
    a = passage(620, 60)
    (x, _), (y, at), (z, _) = hosts([a.split(), a.split(), passage(621, 60).split()], 8)
    docs = spark.createDataFrame([(1, x, "q", "s"), (3, y, "q", "s"), (3, z, "q", "s"), (3, y, "q", "s")], "doc_id long, text string, row string, whole string")
    docs = docs.withColumn("span_doc", F.lit(1)).withColumn("spans", F.lit("x")).withColumn("n_removed", F.lit("x")).withColumn("clean_text", F.lit("x"))
    out = substring_dedup.dedup_substrings(spark, docs).collect()
    assert sorted((d.text, d.n_removed) for d in out) == sorted([(x, 0), (y, 60), (z, 0), (y, 60)])
    assert all(d.clean_text == (d.text if not d.n_removed else " ".join([*y.split()[:at], *y.split()[at + 60 :]])) for d in out)


def test_phrases_said_over_and_over_and_long_sentences(spark):
    passages = ["we say this line once more".split() * 20, [f"long{i}" for i in range(90)], ["la"] * 70]
    placed = hosts(passages * 3, 4)
    got = removed_runs(spark, [t for t, _ in placed])
    assert got == {i: [(at, len(passages[i % 3]))] for i, (_, at) in enumerate(placed) if i >= 3}


def removed_by_brute_force(rows, size=25):
    """(words that must go, words that may): those of runs of ``size`` or of 16 words that an earlier document has."""
    out = []
    for n in (size, 16):
        first = {}
        for i, words in sorted(rows):
            for k in range(len(words) - n + 1):
                first.setdefault(tuple(words[k : k + n]), i)
        out.append({i: {k + j for k in range(len(words) - n + 1) if first[tuple(words[k : k + n])] < i for j in range(n)} for i, words in rows})
    return out


def test_pipeline_stages(spark):
    """Every stage on its predecessor's rows, against a plain version of it."""
    import corpus_pipeline as c

    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    seen = {}
    for name, stage in c.STAGES:
        out = stage(spark, docs, sf)
        if name != c.STAGES[-1][0]:
            assert out.columns == c.COLUMNS
        seen[name] = (docs, out := out.cache())
        docs = out
    ids = lambda df: Counter(x.doc_id for x in df.select("doc_id").collect())
    before, after = seen["toxicity"]
    labels = {x.doc_id: x.toxic for x in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    kept = ids(after)
    assert kept <= ids(before)
    # the chain, document by document on plain Python sets of the same features
    chain = toxicity.fit_toxicity(before, spark.read.parquet(f"{sf}/labels.parquet"))
    for x in before.collect():
        raw = (x.text or "").encode()
        index, limits = toxicity.features(Block(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]), toxicity.NOT_WORD), chain.settings.buckets)
        found, given = set(index.tolist()), []
        for known, w in chain.models:
            at = sorted(int(known[f]) for f in found if known[f] >= 0)
            n = len(w) - len(given) - 1
            z = sum(w[k] for k in at) + sum(a * b for a, b in zip(w[n:], given)) + w[-1]
            given.append(1 / (1 + np.exp(-z)))
        assert (x.doc_id in kept) == (not found or given[-1] < chain.settings.threshold)
    known = [x.doc_id for x in before.collect() if x.doc_id in labels]
    assert sum(labels[i] and i not in kept for i in known) >= 0.9 * sum(labels[i] or 0 for i in known)
    assert sum(not labels[i] and i not in kept for i in known) <= 0.01 * len(known)
    before, after = seen["near_dedup"]
    want = brute.near_components([(x.doc_id, x.text) for x in before.collect()], 5, 80)
    assert set(ids(after)) == {i for i, (_, c_) in want.items() if i == c_}
    before, after = seen["substring_dedup"]
    assert ids(before) == ids(after)
    rows = [(x.doc_id, brute.WORD.findall(x.text or "")) for x in before.collect()]
    must, may = removed_by_brute_force([(i, [brute.lower(w) for w in words]) for i, words in rows])
    clean = {x.doc_id: brute.WORD.findall(x.text or "") for x in after.collect()}
    for i, words in rows:
        # what stays is what must not go, but for short changes between removed runs
        rest = [w for k, w in enumerate(words) if k not in must[i]]
        assert len(clean[i]) <= len(rest) and not Counter(clean[i]) - Counter(rest)
        assert len(words) - len(clean[i]) <= 1.25 * len(may[i]) and (may[i] or clean[i] == words)
    before, after = seen["mixing"]
    rate = {x.doc_id: x.copies for x in mixing.mix_sources(before).collect()}
    assert ids(after) == Counter({i: n for i, n in rate.items() if n})
    before, after = seen["packing"]
    assert ids(after.where("piece = 0")) == ids(before)


def test_pipeline_of_odd_rows(spark, odd, none, tmp_path):
    """Nulls, repeats and empty tables through all stages."""
    import corpus_pipeline as c

    labels = spark.createDataFrame([(3, 1, 0), (5, 1, 0), (8, 1, 0), (10, 0, 0), (12, None, 0), (9, None, 1), (None, 1, 1)], "doc_id long, quality int, toxic int")
    for name, docs in (("odd", odd), ("none", none)):
        sf = str(tmp_path / name)
        docs.select(*c.COLUMNS).write.parquet(f"{sf}/documents.parquet")
        labels.write.parquet(f"{sf}/labels.parquet")
        rows = c.run(spark, sf).collect()
        assert bool(rows) == (name == "odd")
        ends = defaultdict(int)
        for x in sorted(rows, key=lambda x: (x.sequence_id, x.offset)):
            assert x.offset == ends[x.sequence_id]
            ends[x.sequence_id] += x.length


def test_cuts_agree_with_the_tokenizers_on_noise():
    """Any mix of characters: ids and counts of the parts are those of the whole text."""
    r = random.Random(21)
    low = [chr(c) for c in range(256)]
    high = [*"ΣσςİıǅﬀÅ①Ⅷ٣中é́̈ 　​­🙂👩‍🚀", "'s", "'RE", "<|endoftext|>", "<|startoftext|>", "  ", "\n\n"]
    ids = packing.WordIds(tokens.vocabulary("word_bpe_49k.json"))
    counts = tokens.PieceCounts(tokens.vocabulary("byte_bpe_50k.json"))
    for alphabet in (low, [*low, *high], [*"abc XYZ'.,19", *high]):
        texts = ["".join(r.choice(alphabet) for _ in range(r.randint(0, 60))) for _ in range(1500)]
        for text, got, n in zip(texts, ids.encode(texts, 1), counts.count(texts)):
            assert got.tolist() == [*ids.tokenizer.encode(text, add_special_tokens=False).ids, 1], repr(text)
            assert n == len(counts.tokenizer.encode(text, add_special_tokens=False).ids), repr(text)
