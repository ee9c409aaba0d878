"""The ten operators against plain versions, on the smallest tables and on awkward rows."""

import itertools
import random
import textwrap
import time
import zlib
from collections import Counter

import brute
import numpy as np
import pyarrow as pa
import pytest
from conftest import SMALL
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from cityweave.llm import decontam, gbt, langid, licenses, packing, pii, quality, queries, simhash, statistics, suffix, urlfilter
from cityweave.llm.kernel import buffers
from cityweave.llm.statistics import DECREASING, FEATURES
from cityweave.scratch import Scratch

DOCS = "doc_id long, text string, lang string, source string, n_chars long, fp long, key string, row int, label string, n int"


def table(spark, name):
    return spark.read.parquet(f"{SMALL}/{name}.parquet")


@pytest.fixture(scope="module")
def docs(spark):
    return {r.doc_id: r.text for r in table(spark, "documents").collect()}


def awkward_texts():
    rng = random.Random(2)
    word = lambda: "".join(rng.choice("abcdeé") for _ in range(rng.randint(1, 7)))
    common = " ".join(word() for _ in range(60))
    other = " ".join(word() for _ in range(400))
    texts = [
        None, "", " ", "\n\n\t", "a", "Hello", "!!! ??? 123", "ab ab", common, common, common + " x", "y " + common, common.upper(),
        other, other.replace(" ", "\n"), other + " " + common + " " + other, "la " * 300, "ab" * 200, "é" * 130, "日本語のテキスト " * 12,
        "x" * 99, "x" * 100, "x" * 101, "mail a.b@c.de, bob@x.y.z.w a@b 1.2.3.4 999.1.1.1 1.2.3.4.5.6.7.8 +49 (30) 123-4567 4111 1111 1111 1111 4111111111111112",
        "é@ü.de é a@b.c.d@e.f ++49 30 1234567- 0300.1.1.1 4929348385146306-", common + "\r\n" + common + "\x0b" + common, "\x1c\x85 \u2028\u00a0 mixed\u3000spaces", "a\x00b " * 40,
        "Released under the MIT License.", "text\nLicensed under the Apache License, Version 2.0.\nmore", "\n".join(["same line here"] * 9), "tail" + " w" * 5000,
    ]
    return texts


@pytest.fixture(scope="module")
def awkward(spark):
    rows = [(k, t, ["en", "de", None][k % 3], "src0", len(t or ""), 1, "k", 2, "l", 3) for k, t in enumerate(awkward_texts())]
    return spark.createDataFrame(rows, DOCS), {r[0]: r[1] for r in rows}


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


# 1: repeated strings
def test_suffix_order():
    rng = np.random.default_rng(1)
    for n in [*range(1, 30), 200]:
        for size in (2, 5):
            s = rng.integers(1, size + 1, n)
            assert suffix.suffix_order(s).tolist() == sorted(range(n), key=lambda i: s[i:].tolist())


def repeats(df, **options):
    return {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix.without_repeats(df, **options).collect()}


def test_repeats(spark, docs):
    assert repeats(table(spark, "documents")) == brute.repeats_row(docs.items())


@pytest.mark.parametrize("hot", [2000, 1])
def test_repeats_awkward(awkward, hot):
    df, texts = awkward
    assert repeats(df, hot=hot) == brute.repeats_row(texts.items())


def test_repeats_common_line(spark):
    """One line in every document, each time among other words: its anchors are hot."""
    rng = random.Random(7)
    line = " ".join(rng.choice(("north", "harbour", "lamp", "seven", "quiet")) for _ in range(30))
    text = lambda: " ".join("".join(rng.choice("abcdefgh") for _ in range(6)) for _ in range(20))
    rows = [(k, f"{text()}\n{line}\n{text()}") for k in range(120)]
    got = repeats(spark.createDataFrame(rows, "doc_id long, text string"), hot=10)
    assert got == brute.repeats_row(rows)


def test_repeats_in_parts_too_large_for_a_task(spark):
    """A line of 93 bytes with few different surroundings: all its strings have the same anchors."""
    rng = random.Random(8)
    line = "".join(rng.choice("abcdefghij ") for _ in range(93))
    text = lambda n: "".join(rng.choice("xy") for _ in range(n))
    rows = [(k, f"{text(40)}{text(6)}{line}{text(6)}{text(40)}") for k in range(300)] + [(300, None), (301, line)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute.repeats_row(rows)
    assert sum(w[1] for w in want.values()) > 0
    assert repeats(df, hot=10, large=500) == want and repeats(df, hot=10) == want


def test_repeats_of_repeated_and_null_ids(spark):
    long_ = "some words that are repeated in each of the texts, and they have more than one hundred bytes, which is why they go "
    rows = [(5, long_ + "b", 1), (5, long_ + "a", 2), (None, long_, 3), (7, long_ + "c", 4), (9, None, 5)]
    got = repeats(spark.createDataFrame(rows, "doc_id long, text string, lo int"))
    assert got == brute.repeats_row([(5, long_ + "a"), (7, long_ + "c"), (9, None)])


def test_long_document_in_parts(spark, monkeypatch):
    monkeypatch.setattr(suffix, "SEGMENT", 300)
    data = np.frombuffer((" ".join(str(k % 37) for k in range(700))).encode(), np.uint8)
    batch = pa.RecordBatch.from_arrays([pa.array([5]), pa.array([data.tobytes().decode()])], ["doc_id", "text"])
    starts = [(first + lo, n) for _, part, offsets, first in suffix.segments([batch]) for _, lo, n, *_ in suffix.runs(part, offsets) for lo, n in zip(lo.tolist(), n.tolist())]
    assert sum(n for _, n in starts) == len(data) - 99 and sorted(starts)[0][0] == 0


# 2: urls
def test_urls(spark):
    urls = [None, "", "no scheme/casino", "http://a.net", "http://a.net/", "https://X.Example.NET/en/1", "http://example.com/de/x", "http://de.example.com/de", "http://m.org/fr/?q=1", "http://casino-win.example.com/", "http://casinos.example.com/", "http://free.example.org/x", "http://free-bets.example.org/x", "http://free-free.example.org/", "x://y://z/casino", "http://u@h:80/p?q#f", "http://cheap.example.com/pills.html", "http://notexample.net/en/"]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r.page_id: (r.host, r.path, r["rule"], r.verdict) for r in urlfilter.judged(df).collect()}
    assert got[0] == got[1] == ("", "", None, "allow") and got[2] == ("", "", None, "block")
    assert got[3] == ("a.net", "", None, "allow") and got[4] == ("a.net", "/", "net/", "block")
    assert got[5] == ("x.example.net", "/en/1", "example.net/en/", "allow") and got[6][2:] == ("example.com/de/", "block")
    assert got[7][2:] == (None, "allow") and got[8] == ("m.org", "/fr/", "org/fr/", "allow") and got[9][3] == "block" and got[10][3] == "allow"
    assert [got[k][3] for k in (11, 12, 13, 14, 16)] == ["allow", "block", "allow", "block", "block"]
    assert got[14][:2] == ("y:", "//z/casino") and got[15][:2] == ("u@h:80", "/p") and got[17][2] == "net/"
    assert urlfilter.judged(df.limit(0)).count() == 0


def test_large_vocabulary_from_a_table(spark):
    """An automaton of thousands of terms equals a search for each of them."""
    rng = random.Random(4)
    words = sorted({"".join(rng.choice("abcde") for _ in range(rng.randint(2, 7))) for _ in range(6000)})
    rows = [(w.upper() if k % 7 == 0 else w, "strict" if k % 5 == 0 else "soft") for k, w in enumerate(words)] + [(words[1], "strict"), (None, "soft"), ("", "strict")]
    vocabulary = urlfilter.Vocabulary.of(spark.createDataFrame(rows, "term string, kind string"))
    strict = {w for k, w in enumerate(words) if k % 5 == 0} | {words[1]}
    assert set(vocabulary.strict) == strict and set(vocabulary.soft) == set(words) - strict and len(words) > 3000
    part = lambda: "".join(rng.choice("abcde") for _ in range(rng.randint(1, 6)))
    urls = [f"http://{part()}.{part()}/{part()}-{part()}{rng.choice('_/.x1')}{part()}" for _ in range(400)]
    got = {r.page_id: (r.n_strict, r.n_soft, r.verdict) for r in urlfilter.judged(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string"), vocabulary, rules=()).collect()}
    for k, url in enumerate(urls):
        own = set(brute.re.findall("[a-z0-9]+", url)) & set(words)
        hard = len(own & strict)
        assert got[k] == (hard, len(own) - hard, "block" if hard or len(own) >= 2 else "allow")
    with pytest.raises(ValueError):
        urlfilter.Vocabulary.of(spark.createDataFrame([("a", "hard")], "term string, kind string"))


# 3: quality rules
def test_statistics(spark, docs, awkward):
    trees = quality.train_rules(table(spark, "documents"), table(spark, "labels"))
    for df, texts in ((table(spark, "documents"), docs), awkward):
        for r in quality.judged_by_rules(df, trees).collect():
            want = brute.base_statistics(texts[r.doc_id])
            assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want
            assert r.base_failed == (want[0] < 10 or 100 * want[4] > 20 * want[0]) and not (r.base_failed and r.kept)


def test_statistics_compare_bytes():
    """Lines and words that sums of powers modulo 2**64 can't tell apart."""
    morse = "".join("ab"[bin(k).count("1") % 2] for k in range(2048))
    other = morse.translate(str.maketrans("ab", "ba"))
    texts = [f"{morse}\n{other}", f"{morse}\n{other}\n{morse}", f"u v {morse} w x u v {other} w x", f"u v {morse} w x u v {morse} w x", "\n".join([""] * 5), "a\n a\na \na"]
    stats = statistics.statistics(*buffers(pa.array(texts)))
    for k, t in enumerate(texts):
        assert tuple(int(stats[c][k]) for c in statistics.BASE) == brute.base_statistics(t)


def test_trees_are_monotonic_and_flat():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(3000, 3))
    y = (rng.random(3000) < 1 / (1 + np.exp(2 * x[:, 0] - np.sin(3 * x[:, 1])))).astype(float)
    trees = gbt.fit(x, y, decreasing=[0])
    line = np.zeros((200, 3))
    line[:, 0] = np.linspace(-3, 3, 200)
    for b in (-1.0, 0.0, 1.0):
        line[:, 1] = b
        assert (np.diff(trees.score(line)) <= 1e-12).all()

    def slow(row):
        total = trees.prior
        for node in trees.roots:
            while trees.left[node] != node:
                node = trees.left[node] if row[trees.feature[node]] <= trees.threshold[node] else trees.right[node]
            total += trees.value[node]
        return 1 / (1 + np.exp(-total))

    assert np.allclose(trees.score(x[:50]), [slow(r) for r in x[:50]])


def held_out(doc_id):
    return zlib.crc32(str(doc_id).encode()) % 5 == 0


MIDDLE = "/root/testdata/sf0.01"


def test_quality_on_held_out(spark):
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{MIDDLE}/labels.parquet").collect()}
    rules = {r.doc_id: r for r in queries.op3_boosted_quality_rules(spark, MIDDLE).collect()}
    votes = {r.doc_id: r for r in queries.op4_neighbour_quality(spark, MIDDLE).collect()}
    own = [d for d in labels if held_out(d)]
    assert all(votes[d].held_out == held_out(d) for d in votes)
    assert np.mean([(votes[d].score >= 0.3) == labels[d] for d in own]) > 0.93
    assert np.mean([rules[d].kept for d in own if labels[d] == 0]) < 0.1
    assert np.mean([rules[d].kept for d in own if labels[d] == 1]) > 0.9


def test_quality_without_data(spark, awkward, empty):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    df, texts = awkward
    for trees in (quality.train_rules(df, labels), quality.train_rules(empty, table(spark, "labels"))):
        assert quality.judged_by_rules(df, trees).count() == len(texts) and quality.judged_by_rules(empty, trees).count() == 0
    model = quality.train_neighbours(df, labels)
    rows = quality.scored_by_neighbours(df, model).collect()
    assert len(rows) == len(texts) and all(r.score == 0.5 for r in rows)
    twice = spark.createDataFrame([(k, k % 2, 0) for k in (8, 9, 13, 16, 18, 23) for _ in range(2)] + [(None, 1, 0)], "doc_id long, quality int, toxic int")
    model = quality.train_neighbours(df, twice)
    assert all(0 <= r.score <= 1 for r in quality.scored_by_neighbours(df, model).collect())


def test_votes_are_exact(spark):
    rng = np.random.default_rng(3)
    unit = lambda a: (a / np.linalg.norm(a, axis=1, keepdims=True)).astype(np.float32)
    labelled, points, y = unit(rng.normal(size=(500, 16))), unit(rng.normal(size=(600, 16))), rng.integers(0, 2, 500).astype(float)
    model = quality.NeighbourModel(1, np.ones(1), np.zeros(len(FEATURES)), np.ones(len(FEATURES)), np.zeros((1, 1)), labelled, y, 0.5, 15)
    got = model.vote(points)
    for k in range(0, 600, 37):
        near = points[k] @ labelled.T
        best = np.argsort(-near)[:15]
        weight = np.maximum(near[best], 0) ** 8 + 1e-12
        assert got[k] == pytest.approx((weight * y[best]).sum() / weight.sum(), rel=1e-4)


# 5: test items
def test_contamination(spark):
    rng = random.Random(11)
    vocabulary = ["".join(rng.choice("abcdefgh") for _ in range(5)) for _ in range(3000)]
    words = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    items = [words(40) for _ in range(30)] + [words(5), words(12)]
    rows, dirty = [], set()
    for k in range(200):
        text = words(100)
        if k % 4 == 0:
            part = list(items[k % len(items)])
            if len(part) > 12 and k % 8 == 0:
                for j in range(3, len(part), 9):  # substitutions
                    part[j] = "xxxx"
            text[40:40] = part
            dirty.add((k, k % len(items)))
        rows.append((k, ", ".join(text).upper() if k % 3 == 0 else " ".join(text)))
    rows += [(500, None), (501, ""), (502, "one")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(items)] + [(90, None), (91, "")], "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontam.contamination(df, bench).collect()}
    assert got == dirty
    clean = decontam.drop_contaminated(df, bench)
    assert clean.columns == df.columns and {r.doc_id for r in clean.collect()} == {r[0] for r in rows} - {d for d, _ in dirty}
    assert decontam.contamination(df, bench.limit(0)).count() == 0 and decontam.contamination(df.limit(0), bench).count() == 0


def test_contamination_is_what_brute_force_finds(spark, docs):
    items = {r.item_id: brute.re.findall(r"[a-z0-9\x80-\U0010ffff]+", r.text.lower()) for r in table(spark, "benchmark").collect()}
    want = set()
    for d, t in docs.items():
        own = " " + " ".join(brute.re.findall(r"[a-z0-9\x80-\U0010ffff]+", brute.lower(t))) + " "
        want |= {(d, i) for i, w in items.items() if " " + " ".join(w) + " " in own}
    got = {(r.doc_id, r.item_id) for r in queries.op5_spaced_seed_decontamination(spark, SMALL).collect()}
    assert want and want <= got


def test_contamination_equals_brute_force(spark, docs):
    """Every overlap of every document with every item, by comparing all windows on all diagonals."""
    tokens = lambda t: brute.re.findall(r"[a-z0-9\x80-\U0010ffff]+", brute.lower(t or ""))
    items = {r.item_id: tokens(r.text) for r in table(spark, "benchmark").collect()}
    number = {w: k for k, w in enumerate({w for t in [*items.values(), *map(tokens, docs.values())] for w in t})}
    want = set()
    for d, t in docs.items():
        own = np.array([number[w] for w in tokens(t)], np.int64)
        for i, item in items.items():
            wanted, covered, agreeing = np.array([number[w] for w in item], np.int64), np.zeros(len(own), bool), np.zeros(len(own), bool)
            size = min(13, len(wanted))
            for start in range(-len(wanted) + size, len(own) - size + 1):
                low, high = max(start, 0), min(start + len(wanted), len(own))
                same = own[low:high] == wanted[low - start : high - start]
                if same.sum() < 0.8 * size:
                    continue
                for k in range(high - low - size + 1):
                    if same[k : k + size].sum() >= 0.8 * size - 1e-9:
                        covered[low + k : low + k + size] = True
                        agreeing[low + k : low + k + size] |= same[k : k + size]
            edge = np.flatnonzero(np.diff(np.concatenate(([0], covered, [0]))))
            want |= {(d, i, int(a), int(b - a), int(agreeing[a:b].sum())) for a, b in zip(edge[::2], edge[1::2])}
    got = [tuple(r[c] for c in ("doc_id", "item_id", "first_word", "n_words", "n_same")) for r in queries.op5_spaced_seed_decontamination(spark, SMALL).collect()]
    assert want and set(got) == want and len(got) == len(want)


def test_contamination_by_repeated_words(spark):
    """Junk of one word against an item of the same: one row, in time that isn't all pairs of places."""
    df = spark.createDataFrame([(1, "la " * 20_000), (2, "la " * 20_000 + "lu " * 500), (3, "other words here"), (3, "la " * 40), (None, "la " * 40)], "doc_id long, text string")
    bench = spark.createDataFrame([(1, "la " * 2000), (1, "la " * 2000), (2, "la la lu " * 300), (None, "other words here")], "item_id long, text string")
    began = time.perf_counter()
    got = sorted(((r.doc_id, r.item_id, r.first_word, r.n_words, r.n_same) for r in decontam.contamination(df, bench).collect()), key=str)
    assert time.perf_counter() - began < 60
    assert [r for r in got if r[1] == 1] == [(1, 1, 0, 20_000, 20_000), (2, 1, 0, 20_002, 20_000), (3, 1, 0, 40, 40), (None, 1, 0, 40, 40)]
    assert len(got) == len({r[:3] for r in got})


def test_short_items_with_substitutions(spark):
    items = {n: [f"item{n}word{k}" for k in range(n)] for n in range(1, 14)}
    rows, want = [], set()
    for n, words in items.items():
        allowed = n - -(-8 * n // 10)
        for wrong in range(allowed + 2):
            for at in itertools.combinations(range(n), wrong):
                text = " ".join(["before", *("other" if k in at else w for k, w in enumerate(words)), "after"])
                if wrong <= allowed:
                    want.add((len(rows), n))
                rows.append((len(rows), text))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame([(n, " ".join(w)) for n, w in items.items()], "item_id long, text string")
    got = decontam.contamination(df, bench).collect()
    assert {(r.doc_id, r.item_id) for r in got} == want and len(got) == len(want)
    assert {r.doc_id for r in decontam.drop_contaminated(df, bench).collect()} == {k for k, _ in rows} - {k for k, _ in want}


# 6: languages
def test_languages(spark, awkward, empty):
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    model = langid.train(docs)
    rows = langid.identify(docs, model).join(docs.select("doc_id", "lang"), "doc_id").collect()
    own = [r for r in rows if held_out(r.doc_id)]
    assert np.mean([r.lang == r.lang_pred for r in own]) > 0.97
    df, texts = awkward
    for r in langid.identify(df, model).collect():
        t = texts[r.doc_id] or ""
        assert (r.lang_pred == "und") == (not any(c.isalpha() for c in t)) and 0 <= r.score <= 1
    kept = langid.keep_identified(df, model)
    assert kept.schema == df.schema and {r.doc_id for r in kept.collect()} == {k for k, t in texts.items() if any(c.isalpha() for c in t or "")}
    nothing = langid.train(empty)
    assert {r.lang_pred for r in langid.identify(df, nothing).collect()} == {"und"} and langid.identify(empty, model).count() == 0
    single = langid.train(docs.where("lang = 'fr'"))
    assert {r.lang_pred for r in langid.identify(docs.limit(20), single).collect()} <= {"fr", "und"}


def test_learning_leaves_held_out_rows_alone(spark):
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    assert langid.training_sample(docs, "lang", 10**6).where(langid.held_out(F.col("doc_id"))).count() == 0


# 7: licences
def test_licenses(spark):
    apache = "Licensed under the Apache License, Version 2.0."
    files = [
        (1, "a/LICENSE", "Released under the MIT License."), (2, "a/x.txt", "words only here"), (3, "a/b/c/y.txt", "more words"), (4, "a/b/LICENSE.txt", "Licensed under CC BY-NC 4.0."),
        (5, "a/b/z.txt", f"intro words go here\n{apache}\nand more words follow after it"), (6, "q/r.txt", "nothing"), (7, None, "nothing"), (8, "q/s.txt", None), (9, "a/b/c/d/e.txt", ""), (2, "a/x.txt", "words only here"),
    ]
    df = spark.createDataFrame(files, "doc_id long, path string, text string")
    got = [(r.doc_id, r.license, r.how, r.source_dir) for r in licenses.license_scan(df, Scratch(spark, "t")).collect()]
    assert set(got) == {
        (1, "MIT", "header", None), (2, "MIT", "inherited", "a"), (3, "CC-BY-NC-4.0", "inherited", "a/b"), (4, "CC-BY-NC-4.0", "header", None), (5, "Apache-2.0", "header", None),
        (6, None, None, None), (7, None, None, None), (8, None, None, None), (9, "CC-BY-NC-4.0", "inherited", "a/b"),
    }
    assert len(got) == 10 and licenses.license_scan(df.limit(0), Scratch(spark, "t")).count() == 0


def test_license_scores_do_not_move_with_the_size_of_the_table(spark):
    project, acme = "This project is released under the MIT License.", "Copyright 2024 Acme Corporation. Licensed under the Apache License, Version 2.0."
    texts = [project, acme] + [f"this project is a text of the year {k % 7}" if k % 3 else "released words under version 2.0 of all" for k in range(58)]
    docs = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string")
    frequency, n, others = licenses.document_frequency(docs)
    at = lambda w: int(licenses._hashes([w]).view(np.int64)[0])
    in_docs = lambda w: sum(w in licenses.terms(t) for t in texts)
    assert n == 60 and {w: others.get(at(w)) for w in ("project", "acme", "corporation")} == {w: in_docs(w) for w in ("project", "acme", "corporation")}
    assert [int(f) for f in frequency] == [in_docs(w) for w in licenses.VOCABULARY] and others[at("year")] == in_docs("year")
    for notice, name in ((project, "MIT"), (acme, "Apache-2.0")):
        found = [licenses.TemplateIndex.of(frequency * k, n * k, {h: f * k for h, f in others.items()}).best(licenses.terms(notice)) for k in (1, 10**3, 10**6)]
        assert {f[0] for f in found} == {name} and found[0][1] > licenses.LEAST and max(f[1] for f in found) - min(f[1] for f in found) < 1e-9
        # words that only the notice has: at the share FLOOR they are as rare as they get
        alone = [licenses.TemplateIndex.of(frequency * k, 60 * k).best(licenses.terms(notice)) for k in (10**3, 10**5, 10**7)]
        assert max(f[1] for f in alone) - min(f[1] for f in alone) < 1e-9


def test_whole_licenses_under_plain_names(spark):
    wrap = lambda name: "\n".join(textwrap.wrap(licenses.FULL[name].replace("(c)", "(c) 2019 Ada Example and others"), 72))
    mit, bsd, free, isc = (wrap(n) for n in ("MIT", "BSD-3-Clause", "Unlicense", "ISC"))
    apache = "Apache License\nVersion 2.0, January 2004\nhttp://www.apache.org/licenses/\n\nTERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION\n" + "\n".join(f"{k}. Grant. Subject to the terms and conditions of this License, each Contributor\nhereby grants to You a perpetual, worldwide, non-exclusive, no-charge\ncopyright license to reproduce the Work." for k in range(30))
    section = "\n".join(f"{k}. Clause. You may convey a covered work\nunder the terms of this License, provided that\nthe conditions of section {k} are met by you and by all who get it." for k in range(40))
    affero = f"GNU AFFERO GENERAL PUBLIC LICENSE\nVersion 3, 19 November 2007\n\n{section}"
    code = "\n".join(f"value_{k} = compute(value_{k - 1}, {k})" for k in range(200))
    files = [
        (1, "a/1.txt", mit), (2, "a/2.txt", "plain words"), (3, "b/3.txt", bsd), (4, "b/c/4.txt", "plain words"), (5, "d/5.txt", free), (6, "d/6.txt", "plain words"), (7, "e/7.txt", affero), (8, "e/8.txt", "plain words"),
        (9, "f/9.txt", f"{mit}\n{code}"), (10, "f/10.txt", "plain words"), (11, "g/11.txt", f"Licensed under the Apache License, Version 2.0.\n{code}"), (12, "g/12.txt", "plain words"),
        (13, "h/13.txt", isc), (14, "h/14.txt", "plain words"), (15, "i/15.txt", apache), (16, "i/16.txt", "plain words"),
    ]
    assert len(mit.splitlines()) > 10
    df = spark.createDataFrame(files, "doc_id long, path string, text string")
    got = {r.doc_id: (r.license, r.how) for r in licenses.license_scan(df, Scratch(spark, "t")).collect()}
    for k, name in ((1, "MIT"), (3, "BSD-3-Clause"), (5, "Unlicense"), (7, "AGPL-3.0"), (13, "ISC"), (15, "Apache-2.0")):
        assert got[k] == (name, "header") and got[k + 1] == (name, "inherited")
    assert got[10] == got[12] == (None, None) and got[11] == ("Apache-2.0", "header")


def test_license_scores_equal_line_by_line_comparison(spark, awkward):
    """Vectorised cosines against one line, block and text at a time."""
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet").select("doc_id", "text").unionByName(awkward[0].select(F.col("doc_id") + 10**6, "text").toDF("doc_id", "text"))
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    index = licenses.TemplateIndex.of(*licenses.document_frequency(docs))
    got = {r.doc_id: r for r in licenses.scanned(docs.withColumn("path", F.lit(None).cast("string")), index).collect()}
    n_found = 0
    for d, t in texts.items():
        cut = [own[k : k + licenses.LINE] for own in map(licenses.terms, t.split("\n")) for k in range(0, len(own), licenses.LINE)]
        scores = [index.best(own)[:2] for own in cut]
        units = list(zip(scores, cut))
        block = []
        for (_, cosine), own in [*zip(scores, cut), ((None, 0.0), [])]:
            if cosine >= licenses.NEAR:
                block.append(own)
            else:
                if len(block) > 1:
                    both = [w for part in block for w in part]
                    units.append((index.best(both)[:2], both))
                block = []
        top = max((u[0][1] for u in units), default=0.0)
        if top >= licenses.LEAST:
            n_found += 1
            assert got[d].own in {u[0][0] for u in units if u[0][1] > top - 1e-9} and got[d].score == pytest.approx(top, rel=1e-9)
        else:
            assert got[d].own is None
    assert n_found > 20


def test_inheritance_on_a_path_table(spark):
    """Licences of a tree with ties, against a walk up each path."""
    rng = random.Random(21)
    notice = {"MIT": "Released under the MIT License.", "Apache-2.0": "Licensed under the Apache License, Version 2.0.", "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0."}
    dirs = [""] + ["/".join(rng.choice("abc") for _ in range(rng.randint(1, 5))) for _ in range(60)]
    rows = []
    for k in range(400):
        d, name = rng.choice(dirs), rng.choice(list(notice))
        kind = rng.choice(("plain", "plain", "plain", "file", "header"))
        file = rng.choice(("LICENSE", "COPYING.txt", f"{k}.txt")) if kind == "file" else f"{k}.txt"
        text = {"plain": "words that say nothing of it", "file": notice[name], "header": notice[name] + "\n" + "other words here " * 30}[kind]
        rows.append((k, f"{d}/{file}" if d else file, text, kind, name))
    df = spark.createDataFrame(rows, "doc_id long, path string, text string, kind string, name string")
    found = licenses.license_scan(df.select("doc_id", "path", "text"), Scratch(spark, "t")).collect()
    score = {r.doc_id: r.score for r in found}
    up = lambda p: p.rsplit("/", 1)[0] if "/" in p else ""
    owners = {}
    for k, path, _, kind, name in rows:
        if kind == "file":
            owners[up(path)] = min(owners.get(up(path), (1, "", "")), (-score[k], path, name))
    for r in found:
        _, path, _, kind, name = rows[r.doc_id]
        at, want = up(path), (None, None, None)
        if kind != "plain":
            want = (name, "header", None)
        else:
            while at not in owners and at:
                at = up(at)
            if at in owners:
                want = (owners[at][2], "inherited", at)
        assert (r.license, r.how, r.source_dir) == want


# 8: personal data
def test_pii_base(spark, docs, awkward):
    for df, texts in ((table(spark, "documents"), docs), awkward):
        for r in _pii_rows(df):
            assert tuple(r[1:6]) == brute.pii_row(texts[r[0]]), texts[r[0]]


def _pii_rows(df):
    base = F.col("base")
    found = pii.personal_data(df)
    return found.select("doc_id", *[queries._count(base, k) for k in pii.KINDS], F.sha2(pii.rendered(base), 256)).collect()


def test_pii_learns_a_context(spark):
    rng = random.Random(5)
    phone = lambda: f"+49 {rng.randint(100, 999)} {rng.randint(1000000, 9999999)}"
    rows = [(k, f"Some words. Please call {phone()} today") for k in range(40)]
    rows += [(100, "Please call 0301234567 today"), (101, "order number 0301234567 today"), (102, "Please call the office"), (103, None)]
    found = {r.doc_id: r for r in pii.personal_data(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [(s.start, s.end, s.kind) for s in found[100].added] == [(12, 22, 3)]
    assert all(not found[k].added for k in (101, 102, 103)) and all(found[k].base for k in range(40))
    clean = {r.doc_id: r.text for r in pii.redact(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert clean[100] == "Please call <PHONE> today" and clean[101] == rows[41][1] and clean[103] is None and clean[0].endswith("call <PHONE> today")


def test_pii_discovered_instances_support_further_patterns(spark):
    """A first pattern finds numbers that a second pattern shares, and that one finds numbers of its own."""
    rng = random.Random(15)
    phone = lambda: f"+49 {rng.randint(100, 999)} {rng.randint(1000000, 9999999)}"
    plain = lambda: f"0{rng.randint(100000000, 999999999)}"
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    shared = [plain() for _ in range(12)]
    texts = [f"{word()} dial {phone()} {word()}" for _ in range(60)] + [f"{word()} dial {n} {word()}" for n in shared]
    second = len(texts)
    texts += [f"{word()} ring {n} {word()}" for n in shared] + [f"{word()} ring {plain()} {word()}" for _ in range(2)]
    texts += [f"{word()} part {plain()} {word()}" for _ in range(20)]
    rows = list(enumerate(texts))
    got = {r.doc_id: r.added for r in pii.personal_data(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(len(got[k]) == (k >= 60) for k in range(second + 14)) and not any(got[k] for k in range(second + 14, len(rows)))
    once = {r.doc_id: r.added for r in pii.personal_data(spark.createDataFrame(rows, "doc_id long, text string"), rounds=1).collect()}
    assert not any(once[k] for k in range(second, len(rows)))


def test_pii_precision_and_recall_on_planted_identifiers(spark):
    rng = random.Random(16)
    words = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7))) for _ in range(400)]
    some = lambda n: " ".join(rng.choice(words) for _ in range(n))
    code = lambda n, letters="0123456789abcdef": "".join(rng.choice(letters) for _ in range(n - 6)) + "12ab34"
    number = lambda n: str(rng.randint(10 ** (n - 1), 10**n - 1))
    rows, want = [], set()
    for k in range(1200):
        kind = k % 12
        before, after, found = some(5), some(5), None
        if kind == 0:
            item, lead = code(40), 'secret_key = "'
        elif kind == 1 and k % 5 == 0:  # other lengths and letters in the same context
            item, lead, found = code(rng.choice((20, 32, 64)), "0123456789ABCDEFXYZ"), 'secret_key = "', 4
        elif kind == 2:  # digests of the same shape
            item, lead = code(40), f"commit {rng.choice(words)} " if k % 2 else "commit "
        elif kind == 3:
            item, lead = f"user{k}@mail.example.org", "write to "
        elif kind == 4 and k % 5 == 0:
            item, lead, found = f"user{k} (at) mail.example.org", "write to ", 0
        elif kind == 5:
            item, lead = f"+49 {number(3)} {number(7)}", "phone: "
        elif kind == 6 and k % 5 == 0:
            item, lead, found = f"{number(3)} {number(3)} {number(4)}", "phone: ", 3
        elif kind == 7:
            item, lead = number(6), "order no. "
        elif kind == 8:
            item, lead = number(4), rng.choice(words) + " "
        else:
            item, lead = rng.choice(words), ""
        found = 4 if kind == 0 else found
        text = f"{before} {lead}{item}{chr(34) if lead.endswith(chr(34)) else ''} {after}"
        if found is not None:
            start = len(before) + 1 + len(lead)
            want.add((k, start, start + len(item), found))
        rows.append((k, text))
    got = {(r.doc_id, s.start, s.end, s.kind) for r in pii.personal_data(spark.createDataFrame(rows, "doc_id long, text string")).collect() for s in r.added}
    assert len(got & want) >= 0.98 * len(want) and len(got & want) >= 0.98 * len(got)


def test_pii_patterns_find_secrets_of_the_tables(spark):
    """All forty-digit codes of the table stand in one context, and no other token is added."""
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    want = {(r.doc_id, m.start(), m.end()) for r in docs.where("text is not null").collect() for m in brute.re.finditer(r"(?i)(?<=token = \")[0-9a-f]{40}", r.text)}
    got = {(r.doc_id, s.start, s.end) for r in pii.personal_data(docs).collect() for s in r.added}
    assert len(want) > 5 and got == want


def test_redaction_goes_by_text(spark):
    rng = random.Random(17)
    phone = lambda: f"+49 {rng.randint(100, 999)} {rng.randint(1000000, 9999999)}"
    schema = "doc_id long, text string, n_chars int, key string, row long, spans string, clean int, Start string"
    more = (1, "k", 2, "s", 3, "t")
    rows = [(k, f"Some words. Please call {phone()} today", *more) for k in range(40)]
    rows += [(7, "short and plain but for another row", *more), (7, "Please call 0301234567 at noon", *more), (None, "Please call 0301234567 at noon", *more), (None, "write to a.b@c.de now", *more), (None, None, *more), (50, "", *more), (51, "y " * 700_000 + "mail a.b@c.de " + "1234 " * 200_000, *more)]
    df = spark.createDataFrame(rows, schema)
    out = pii.redact(df)
    assert out.columns == df.columns
    got = Counter((r.doc_id, r.text) for r in out.collect())
    assert got[7, rows[40][1]] == 1 and got[7, "Please call <PHONE> at noon"] == 1 and got[None, "Please call <PHONE> at noon"] == 1
    assert got[None, "write to <EMAIL> now"] == 1 and got[None, None] == 1 and got[50, ""] == 1 and sum(got.values()) == len(rows)
    long_ = next(t for d, t in got if d == 51)
    assert "a.b@c.de" not in long_ and long_.startswith("y y ") and len(long_) > 1_000_000
    assert Counter(r.text for r in pii.redact(df.unionByName(df)).collect()) == Counter({t: 2 * n for (d, t), n in got.items() if d != 7 and d is not None} | Counter({t: 2 * sum(n for (_, x), n in got.items() if x == t) for _, t in got}))
    assert pii.redact(df.limit(0)).count() == 0 and pii.personal_data(df.limit(0)).count() == 0


def test_pii_is_native(spark):
    for df in (pii.scanned(table(spark, "documents")), pii.personal_data(table(spark, "documents")), pii.redact(table(spark, "documents"))):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "Python" not in plan and "Arrow" not in plan


# 9: near copies
def rows_of(df):
    return {r.doc_id: (f"{r.fp & (2**64 - 1):016x}", r.component_id) for r in simhash.simhash_components(df).collect()}


def test_simhash(spark, docs):
    assert rows_of(table(spark, "documents")) == brute.simhash_rows(docs.items())


def test_simhash_awkward(awkward, empty):
    df, texts = awkward
    assert rows_of(df) == brute.simhash_rows(texts.items())
    assert simhash.simhash_components(empty).count() == 0
    kept = simhash.simhash_representatives(df.unionByName(df))
    firsts = {c for _, c in brute.simhash_rows(texts.items()).values()}
    assert kept.columns == df.columns and sorted(r.doc_id for r in kept.collect()) == sorted(firsts)


def test_representatives_of_repeated_ids(spark):
    text = "one two three four five six"
    rows = [(1, text, "b", 1), (1, text, "a", 2), (1, "zz other words than those", "a", 3), (2, text, "c", 4), (None, text, "d", 5), (None, None, None, 6)]
    df = spark.createDataFrame(rows, "doc_id long, text string, kept string, _kept_id int")
    got = sorted((tuple(r) for r in simhash.simhash_representatives(df).collect()), key=str)
    assert got == sorted([(1, text, "a", 2), (None, text, "d", 5), (None, None, None, 6)], key=str)


@pytest.mark.parametrize("bound,frontier", [(1 << 18, 1 << 19), (3, 1 << 19), (1 << 18, 40)])
def test_trie_finds_all_links(spark, monkeypatch, bound, frontier):
    monkeypatch.setattr(simhash, "FRONTIER", frontier)
    rng = random.Random(8)
    values = {rng.getrandbits(64) for _ in range(150)}
    for v in list(values)[:60]:
        for _ in range(4):
            v ^= 1 << rng.randrange(64)
            values.add(v)
    values = sorted(values)
    signed = [v - (1 << 64) if v >> 63 else v for v in values]
    points = spark.createDataFrame([(s, k) for k, s in enumerate(signed)], "fp long, rep long")
    edges = [(r.u, r.v) for r in simhash.links(points, 2, bound, Scratch(spark, "t")).collect()]
    want = [(i, j) for i in range(len(values)) for j in range(i) if bin(values[i] ^ values[j]).count("1") <= 2]
    assert brute.components(range(len(values)), edges) == brute.components(range(len(values)), want)


# 10: packing
def packed(df, **options):
    return packing.best_fit_packing(df, queries.tokenizer_path(), **options).collect()


def check_packing(rows, capacity=4096):
    by = {}
    for r in rows:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for own in by.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def test_packing(spark, docs, awkward):
    tokenizer = Tokenizer.from_file(queries.tokenizer_path())
    for df, texts in ((table(spark, "documents"), docs), awkward):
        rows = packed(df)
        assert {(r.doc_id, r.piece): (r.start, r.length, r.ids_crc32) for r in rows} == brute.piece_rows(texts.items(), tokenizer)
        lengths = np.array([r.length for r in rows])
        assert check_packing(rows) <= packing.lower_bound(lengths, 4096) + 1


def test_packing_certificate(spark, docs):
    rows = packed(table(spark, "documents"))
    assert {(r.n_sequences, r.lower_bound) for r in rows} == {(check_packing(rows), packing.lower_bound(np.array([r.length for r in rows]), 4096))}


def test_packing_exchanges(spark, docs):
    """Many small groups waste bins that the exchange wins back."""
    df = table(spark, "documents")
    one, many, alone = (check_packing(packed(df, **o)) for o in ({}, {"group_rows": 12}, {"group_rows": 12, "turns": 0}))
    assert one <= many < alone


def test_lower_bounds():
    rng = np.random.default_rng(2)
    for _ in range(200):
        lengths = rng.integers(1, 101, rng.integers(1, 30))
        where, offset = packing.best_fit_decreasing(lengths, 100)
        fill = np.bincount(where, weights=lengths)
        assert fill.max() <= 100 and packing.lower_bound(lengths, 100) <= len(fill)
    assert packing.lower_bound(np.full(10, 51), 100) == 10 and packing.lower_bound(np.array([34] * 9), 100) == 5
    assert packing.lower_bound(np.zeros(0, np.int64), 100) == 0


def test_packing_empty_and_repeated(spark, empty, awkward):
    assert packed(empty) == []
    df, texts = awkward
    assert Counter(r.doc_id for r in packed(df.unionByName(df)) if r.piece == 0) == Counter({k: 2 for k in texts})


def test_tokens_by_chunk():
    path = queries.tokenizer_path()
    plain, ours = Tokenizer.from_file(path), packing.ChunkTokenizer(path)
    rng = random.Random(1)
    letters = list("aAbé É'sß.,!|<>#1 2\n\tçÑñΣ\u0301 日ﬁİ")
    texts = ["it's DON'T we'LL", "a<|startoftext|>b <|endoftext|>", "ΣΑΣ", "foo_bar__ $%^", *("".join(rng.choice(letters) for _ in range(rng.randint(1, 40))) for _ in range(500))]
    for text, ids in zip(texts, ours.ids(texts), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == plain.encode(text, add_special_tokens=False).ids


def test_decreasing_features_exist():
    assert set(DECREASING) <= set(FEATURES)
