"""Each operator against a brute-force version, and on awkward rows."""

import hashlib
import io
import random
import re
import struct
import zlib
from collections import Counter
from itertools import combinations

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from dp_itemsets.llm import catalog, decontamination, language, licenses, lines, lm, media, packing, quality, sharding, simhash

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, fp long, key string, score double, places string, shard int, _fp string"
LONG = " ".join(f"w{k % 977}x{k}" for k in range(30_000))


def awkward(spark, texts=(None, "", "A b", "A b", LONG, "ß ñ 日本   x", "one two three four", " \t\n ", "%%% !!!")):
    rows = [(k, t, "en", "s", None if t is None else len(t), 1, "k", 0.5, "p", 3, "q") for k, t in enumerate(texts)]
    rows += [rows[2], (None, "A b", None, None, None, None, None, None, None, None, None), (None, None, None, None, None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, tiny):
    return spark.read.parquet(f"{tiny}/documents.parquet")


def by_id(df):
    return {r["doc_id"]: r.asDict() for r in df.collect()}


def lower(text):
    return (text or "").translate({c: c + 32 for c in range(65, 91)})


# --- decontamination


def judged(text, items):
    pattern = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    words, hit, found = pattern.findall(lower(text)), set(), set()
    for item, t in items:
        w = pattern.findall(lower(t))
        for k in range(max(len(w) - 13, 0) + 1) if w else ():
            win = w[k : k + 13]
            for p in range(len(words) - len(win) + 1):
                if words[p : p + len(win)] == win:
                    hit.update(range(p, p + len(win)))
                    found.add(str(item))
    names = ",".join(sorted(found))
    return len(words), len(hit), len(found), hashlib.sha256(names.encode()).hexdigest(), len(hit) > 0 and 20 * len(hit) >= len(words)


def test_decontamination_matches_brute_force(spark, docs, tiny):
    benchmark = spark.read.parquet(f"{tiny}/benchmark.parquet")
    some = docs.where("length(text) < 4000")
    items = [(r["item_id"], r["text"]) for r in benchmark.collect()]
    got = decontamination.find_contamination(some, benchmark).collect()
    texts = {r["doc_id"]: r["text"] for r in some.collect()}
    assert len(got) == len(texts)
    for r in got:
        assert tuple(r)[1:6] == judged(texts[r["doc_id"]], items)


def test_decontamination_awkward(spark):
    items = [(1, "a B"), (2, None), (3, ""), (4, LONG[:400]), (5, "one two three four"), (5, "four three")]
    benchmark = spark.createDataFrame(items, "item_id int, text string")
    frame = awkward(spark)
    want = sorted((judged(r["text"], items) for r in frame.collect()), key=repr)
    got = sorted((tuple(r)[1:6] for r in decontamination.find_contamination(frame, benchmark).collect()), key=repr)
    assert got == want
    kept = decontamination.remove_contaminated(frame, benchmark)
    assert kept.columns == frame.columns
    assert kept.count() == sum(not w[4] for w in want)
    assert decontamination.find_contamination(empty(spark), benchmark).count() == 0
    assert not any(r["contaminated"] for r in decontamination.find_contamination(frame, benchmark.limit(0)).collect())


def test_index_blocks_stored_and_proximity(spark, tmp_path):
    frame = spark.createDataFrame([(1, "the quick brown fox jumps"), (2, "brown the lazy dog and a quick fox"), (3, "fox"), (4, "quick")], "doc_id int, text string")
    decontamination.build_index(frame).write.parquet(str(tmp_path / "index"))
    index = spark.read.parquet(str(tmp_path / "index"))
    found = decontamination.proximity(index, {"q": "quick fox"}, 2).collect()
    assert {(r["doc_id"], r["start"], r["end"]) for r in found} == {(1, 1, 4), (2, 6, 8)}
    benchmark = spark.createDataFrame([(k, t) for k, t in enumerate(["quick brown fox", "lazy dog", "fox"])], "item_id int, text string")
    one = decontamination.search(index, decontamination.query_blocks(benchmark))
    many = decontamination.search(index, decontamination.query_blocks(benchmark, limit=1))
    assert sorted(map(tuple, one.drop("item_ids").collect())) == sorted(map(tuple, many.drop("item_ids").collect()))
    for cut in (1, 12):
        passes = decontamination.find_contamination(frame, benchmark, limit=cut)
        assert passes.columns == decontamination.RESULT
        assert sorted(map(tuple, passes.drop("item_ids").collect())) == sorted(map(tuple, one.drop("item_ids").collect()))
    pushed = decontamination.find_contamination(frame, benchmark).drop("item_ids")
    assert sorted(map(tuple, pushed.collect())) == sorted(map(tuple, one.drop("item_ids").collect()))


def test_decontamination_in_passes_matches_brute_force(spark, docs, tiny):
    benchmark = spark.read.parquet(f"{tiny}/benchmark.parquet").unionByName(spark.createDataFrame([(None, "the a of"), (77, None)], "item_id long, text string"))
    rows = docs.where("length(text) < 3000")
    rows = rows.unionByName(rows.limit(3)).unionByName(rows.limit(1).withColumn("text", F.lit(None).cast("string")))
    items = [(r["item_id"], r["text"]) for r in benchmark.collect() if r["item_id"] is not None]
    want = sorted((r["doc_id"], *judged(r["text"], items)) for r in rows.collect())
    assert any(w[2] for w in want)
    got = decontamination.find_contamination(rows, benchmark, limit=3000)
    assert sorted(tuple(r)[:6] for r in got.collect()) == want
    for limit in (3000, 10**9):
        kept = decontamination.remove_contaminated(rows, benchmark, limit=limit)
        assert kept.columns == rows.columns
        assert sorted(r["doc_id"] for r in kept.collect()) == sorted(w[0] for w in want if not w[5])


# --- quality


def test_quality_held_out_accuracy(spark, small):
    docs, labels = spark.read.parquet(f"{small}/documents.parquet"), spark.read.parquet(f"{small}/labels.parquet")
    rows = quality.classify(docs, labels).join(labels, "doc_id").where("held_out").collect()
    assert np.mean([r["predicted"] == r["quality"] for r in rows]) > 0.9
    assert all(0 <= r["score"] <= 1 and r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in rows)


def test_machine_interactions_equal_pairwise_sum():
    model = quality.FactorisationMachine.fresh(50)
    model.weights[:] = np.random.default_rng(0).normal(size=50)
    index, value = np.array([3, 7, 20, 41]), np.array([0.5, 1.0, 0.25, 2.0], np.float32)
    plain = model.bias + (model.weights[index] * value).sum()
    for a in range(4):
        for b in range(a + 1, 4):
            plain += model.factors[index[a]] @ model.factors[index[b]] * value[a] * value[b]
    assert model.raw(index, value, np.array([0]))[0] == pytest.approx(plain, rel=1e-4)


def plain_features(text, metadata):
    """Words by bucket and statistics by step, as the operator's text states them, in plain loops."""
    words = re.findall(r"[^\x20\x09-\x0D]+", lower(text))
    data, rows, n, w = text.encode(), text.encode().split(b"\n"), max(len(text.encode()), 1), max(len(words), 1)
    of = lambda ok: sum(map(ok, data))
    symbol = lambda b: 32 < b < 127 and not chr(b).isalnum() and chr(b) not in ".,"
    mark = lambda c: c.isascii() and c.isprintable() and not c.isalnum() and c != " "
    pieces = [x for x in re.split(r"[\x20\x09-\x0D]+", text) if x]
    stats = [
        np.log1p(len(data)) / 16, np.log1p(len(words)) / 14, min(len(data) / w / 24, 1), len(set(words)) / w, of(lambda b: 65 <= b <= 90) / n, of(lambda b: 48 <= b <= 57) / n * 4,
        min(of(symbol) / n * 3, 1), of(lambda b: b in (9, 10, 11, 12, 13, 32)) / n * 2, of(lambda b: b > 127) / n, np.log1p(len(rows)) / 10, 1 - len(set(rows)) / len(rows),
        sum(len(x) > 1 and mark(x[-1]) and mark(x[-2]) for x in pieces) / w, sum(all(map(mark, x)) for x in pieces) / w,
        max(Counter(words).values(), default=0) / w, sum(a == b for a, b in zip(words, words[1:], strict=False)) / w, *metadata,
    ]
    buckets = sorted(zlib.crc32(x.encode()) % quality.WORDS for x in set(words))
    out = [(b, 1 / max(len(buckets), 1) ** 0.5) for b in buckets]
    return out + [(quality.WORDS + k * 25 + (24 if v is None else min(int(v * 24), 23)), 1 / len(stats) ** 0.5) for k, v in enumerate(stats)]


def test_quality_matches_plain_version(spark, docs):
    """Features and scores of whole texts, pair by pair, for a machine with random parameters."""
    some = docs.where("length(text) < 1200").limit(25).collect()
    model, draw = quality.FactorisationMachine.fresh(quality.size_of(1)), np.random.default_rng(4)
    model.weights[:] = draw.normal(size=model.weights.shape)
    model.bias = 0.3
    odd = [(10**6 + k, t, None) for k, t in enumerate(("", "A a A b", "%%% !!! x?! y..", "x\ty\nz\nz", "Ünï 123 ,,"))]
    frame = spark.createDataFrame([(r["doc_id"], r["text"], r["n_chars"]) for r in some] + odd, "doc_id long, text string, n_chars long")
    got = {r["doc_id"]: r["score"] for r in quality.score(frame, model, ["n_chars"], quality.held_out()).collect()}
    for r in frame.collect():
        x = plain_features(r["text"], [None if r["n_chars"] is None else min(np.log1p(r["n_chars"]) / 16, 1)])
        raw = model.bias + sum(float(model.weights[i]) * v for i, v in x)
        v = np.array([model.factors[i] * np.float64(value) for i, value in x])
        raw += sum(float(v[a] @ v[b]) for a in range(len(x)) for b in range(a))
        assert got[r["doc_id"]] == pytest.approx(1 / (1 + np.exp(-raw)), abs=1e-4)


def test_quality_training_is_bounded_in_features(spark, docs):
    labels = docs.selectExpr("doc_id", "cast(doc_id % 2 AS int) AS quality")
    whole, less = quality.train(docs, labels, ["n_chars"]), quality.train(docs, labels, ["n_chars"], sample_features=3000)
    assert not np.array_equal(whole.weights, less.weights) and less.weights.any()
    assert not quality.train(docs, labels, ["n_chars"], sample_features=1).weights.any()


def test_quality_awkward(spark):
    frame = awkward(spark)
    labels = spark.createDataFrame([(k, k % 2, 0) for k in range(9)] + [(1, 0, 0), (None, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    got = quality.classify(frame, labels).collect()
    assert len(got) == frame.count() and all(0 <= r["score"] <= 1 for r in got)
    same = {round(r["score"], 9) for r in got if r["doc_id"] in (0, 1)}
    assert len(same) == 2 or len(same) == 1  # null and empty differ in their metadata only
    assert quality.classify(empty(spark), labels).count() == 0
    assert {r["score"] for r in quality.classify(frame, labels.limit(0)).collect()}
    kept = quality.keep_good(frame, labels)
    assert kept.columns == frame.columns and kept.count() == sum(r["predicted"] for r in got)


def test_a_repeated_id_counts_once_in_training(spark, docs):
    labels = docs.selectExpr("doc_id", "cast(doc_id % 2 AS int) AS quality")
    repeated = docs.unionByName(docs.where("doc_id % 5 = 0")).unionByName(docs.limit(1).crossJoin(spark.range(500)).drop("id"))
    a, b = (quality.train(x, labels, ["n_chars"]) for x in (docs, repeated))
    assert np.array_equal(a.weights, b.weights) and a.bias == b.bias
    a, b = (lm.train(x, 40) for x in (docs, repeated))
    assert a.head == b.head and all(np.array_equal(a.gru.p[k], b.gru.p[k]) for k in a.gru.p)


def test_quality_never_reads_identity(spark, small):
    docs, labels = spark.read.parquet(f"{small}/documents.parquet"), spark.read.parquet(f"{small}/labels.parquet")
    model = quality.train(docs, labels.where(~quality.held_out()), ["n_chars"])
    a = quality.score(docs, model, ["n_chars"], quality.held_out())
    b = quality.score(docs.withColumn("lang", F.lit("xx")).withColumn("source", F.lit("yy")).withColumn("doc_id", F.col("doc_id") + 10_000), model, ["n_chars"], quality.held_out())
    assert a.agg(F.sum("score")).first()[0] == pytest.approx(b.agg(F.sum("score")).first()[0])


# --- language


@pytest.fixture(scope="module")
def languages():
    counts = {"a": Counter({"the": 50, "of": 30, "nation": 9}), "b": Counter({"der": 50, "und": 40, "nation": 3})}
    return language.LanguageModel.fit(language.Vocabulary.load(catalog.vocabulary_path()), counts, 3)


def every_cut(word, vocabulary, table):
    if not word:
        return np.ones(table.shape[1])
    total = np.zeros(table.shape[1])
    for n in range(1, len(word) + 1):
        piece = vocabulary.pieces.get(word[:n])
        if piece is not None:
            total += table[piece] * every_cut(word[n:], vocabulary, table)
        elif n == 1:
            total += table[vocabulary.spelled(word[0])].prod(axis=0) * every_cut(word[1:], vocabulary, table)
    return total


def test_forward_sums_all_segmentations(languages):
    index = language.PieceIndex(languages.vocabulary)
    words = ["the", "nation", "日x", "derund", "of", "%%ab"]
    got = languages.words(words, index)
    for k, w in enumerate(words):
        want = np.log(every_cut(language.MARK + w, languages.vocabulary, languages.table))
        assert got[k] == pytest.approx(want)
        assert language.long_word(language.MARK + w, languages.vocabulary, np.log(languages.table)) == pytest.approx(want)
    assert np.isfinite(languages.words(["x" * 5000], index)).all()


@pytest.mark.parametrize("n", [20, 30, 40, 47, 48, 60])
def test_words_outside_the_vocabulary_have_no_floor(languages, n):
    """Characters that no piece holds have one segmentation, so the sum is a product; it must come out whole in every language."""
    char = "\U00010330"
    assert not any(char in p for p in languages.vocabulary.pieces)
    logs = np.log(languages.table)
    want = logs[languages.vocabulary.pieces[language.MARK]] + n * logs[languages.vocabulary.spelled(char)].sum(axis=0)
    got = languages.words([char * n, "the"], language.PieceIndex(languages.vocabulary))
    assert got[0] == pytest.approx(want) and abs(got[0, 0] - got[0, 1]) > 1e-3


def test_forward_agrees_across_lengths(languages):
    draw, index = random.Random(1), language.PieceIndex(languages.vocabulary)
    words = ["".join(draw.choice("thenatiofdru日\U00010330") for _ in range(n)) for n in (5, 19, 33, 46, 47, 48, 49, 70)]
    got = languages.words(words, index)
    for k, w in enumerate(words):
        lattice = language.Lattice([language.MARK + w], languages.vocabulary)
        assert got[k] == pytest.approx(lattice.totals(lattice.forward(lattice.weights(np.log(languages.table))))[0])


def test_a_language_without_spaces_learns_from_its_clauses(spark):
    draw = random.Random(3)
    rows = [(k, "".join(draw.choice(letters) for _ in range(300)), lang) for k in range(40) for lang, letters in (("zz", "日本語文章"), ("yy", "한국어글자"))]
    frame = spark.createDataFrame([(k, t, lang) for k, (_, t, lang) in enumerate(rows)], "doc_id long, text string, lang string")
    got = language.identify_languages(frame, catalog.vocabulary_path()).join(frame, "doc_id").where("held_out").collect()
    assert got and all(r["lang_pred"] == r["lang"] for r in got)


def test_training_on_the_cluster_equals_one_machine(spark, docs):
    words = language.sampled_words(docs, 10**9).collect()
    counts = {}
    for r in words:
        counts.setdefault(r["lang"], Counter())[r["word"]] = r["n"]
    vocabulary = language.Vocabulary.load(catalog.vocabulary_path())
    a, b = language.LanguageModel.fit(vocabulary, counts, 2), language.train(docs.repartition(3), catalog.vocabulary_path(), 10**9, 2)
    assert a.languages == b.languages and np.allclose(a.table, b.table)
    plain = Counter()
    for r in docs.collect():
        plain.update((r["lang"], w) for w in r["text"].lower().split())
    assert plain == Counter({(r["lang"], r["word"]): r["n"] for r in words})


def test_expected_counts_add_up(languages):
    lattice = language.Lattice([language.MARK + "the", language.MARK + "nation"], languages.vocabulary)
    got = lattice.expected(lattice.weights(np.log(languages.table[:, :1])), np.array([2.0, 1.0]), len(languages.vocabulary.pieces))
    assert 3 <= got.sum() <= 2 * 4 + 7  # between one and all characters a word


def test_language_held_out_accuracy(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = language.identify_languages(docs, catalog.vocabulary_path()).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r["lang_pred"] == r["lang"] for r in rows]) > 0.95


def test_language_awkward(spark):
    frame = awkward(spark)
    got = language.identify_languages(frame, catalog.vocabulary_path()).collect()
    assert len(got) == frame.count()
    assert all((r["lang_pred"] == "und") == (r["doc_id"] in (0, 1, 7, 8) or r["doc_id"] is None and r["score"] == 0) for r in got)
    assert language.identify_languages(empty(spark), catalog.vocabulary_path()).count() == 0


# --- sharding


def test_sharding_laws(spark, docs):
    got = by_id(sharding.shard_documents(docs))
    assert len(got) == docs.count()
    for r in docs.collect():
        x, data = got[r["doc_id"]], r["text"].encode()
        assert x["size"] == len(data) + 8 and x["text_crc32"] == zlib.crc32(data) and x["law"] == "key"

        def score(s, key=r["doc_id"]):
            h = hashlib.sha256(f"0:{s}:{key}".encode()).hexdigest()[:13]
            return -1 / np.log((int(h, 16) + 0.5) / 2**52)

        assert x["shard"] == max(range(24), key=score) and x["grown_shard"] == max(range(25), key=score)
    for s in range(24):
        assert sorted(x["slot"] for x in got.values() if x["shard"] == s) == list(range(sum(x["shard"] == s for x in got.values())))


def test_sharding_weights_and_skew(spark):
    keys = spark.range(6000).select(F.col("id").alias("doc_id"))
    shares = Counter(r["shard"] for r in sharding.assign(keys, shards=3, weights=[1.0, 2.0, 0.0]).collect())
    assert shares[2] == 0 and 1.8 < shares[1] / shares[0] < 2.2
    hot = spark.range(3000).select(F.lit(7).cast("long").alias("doc_id"), F.when(F.col("id") % 2 == 0, F.lit("a")).alias("text"))
    slots = sorted(r["slot"] for r in sharding.shard_documents(hot).collect())
    assert slots == list(range(3000))


def test_sharding_awkward(spark):
    got = sharding.shard_documents(awkward(spark)).collect()
    assert len(got) == awkward(spark).count() and {r["size"] for r in got if r["doc_id"] in (0, 1)} == {8}
    assert sharding.shard_documents(empty(spark)).count() == 0


# --- licenses


def test_alignment_is_a_common_subsequence():
    draw = random.Random(4)
    for _ in range(200):
        a, b = ([bytes([draw.randrange(97, 104)]) for _ in range(draw.randrange(14))] for _ in range(2))
        pairs = licenses.align(a, b)
        assert all(a[x] == b[y] for x, y in pairs)
        assert all(p[0] < q[0] and p[1] < q[1] for p, q in zip(pairs, pairs[1:], strict=False))


def test_licenses_found_whole_and_changed(spark):
    mit = licenses.TEMPLATES["MIT/text"]
    texts = {1: f"intro words here\n{mit}\nmore text", 2: mit.replace("free of charge", "gratis").replace("merge, ", ""), 3: "the software is fine and the rest is free", 4: "x " * 500 + "Released under the MIT License. " + "y " * 500, 5: mit[:300]}
    got = by_id(licenses.scan_licenses(spark.createDataFrame(list(texts.items()), "doc_id int, text string")))
    assert got[1]["license"] == "MIT/text" and got[1]["coverage"] == 1.0 and got[1]["start"] == 3
    assert got[2]["license"] == "MIT/text" and got[2]["coverage"] > 0.9
    assert got[3]["license"] is None and got[3]["coverage"] == 0
    assert got[4]["license"] == "MIT/statement" and (got[4]["start"], got[4]["end"]) == (500, 505)
    assert got[5]["license"] is None


def plain_alignment(text, template, whole=True):
    """Patience alignment by its definition, recursively: matching ends of a gap, then the longest increasing run of words unique in both."""
    head = 0
    while not whole and head < min(len(text), len(template)) and text[head] == template[head]:
        head += 1
    tail = 0
    while not whole and tail < min(len(text), len(template)) - head and text[-1 - tail] == template[-1 - tail]:
        tail += 1
    a, b = text[head : len(text) - tail], template[head : len(template) - tail]
    both = [(a.index(w), k) for k, w in enumerate(b) if a.count(w) == 1 and b.count(w) == 1]
    runs = [[]] + [list(c) for n in range(1, len(both) + 1) for c in combinations(sorted(both), n) if all(x[1] < y[1] for x, y in zip(c, c[1:], strict=False))]
    size = max(map(len, runs))
    totals = []
    for anchors in (r for r in runs if len(r) == size):
        edges, total = [(-1, -1), *anchors, (len(a), len(b))], 0
        for (e, f), (g, h) in zip(edges, edges[1:], strict=False) if anchors else ():
            total += plain_alignment(a[e + 1 : g], b[f + 1 : h], False)
        totals.append(total + len(anchors))
    return max(totals) + head + tail


def test_alignment_matches_its_definition():
    """Of equally long runs of anchors the definition takes any, so the operator lies between nothing lost at one level and the best of them."""
    draw = random.Random(5)
    same = 0
    for _ in range(300):
        b = [bytes([draw.randrange(97, 107)]) for _ in range(draw.randrange(1, 9))]
        a = [w for w in b if draw.random() > 0.2] + [bytes([draw.randrange(97, 110)]) for _ in range(draw.randrange(3))]
        got, best = len(licenses.align(a, b)), plain_alignment(a, b)
        assert got <= best
        same += got == best
    assert same > 280


@pytest.mark.parametrize(("text", "want"), [
    ("Licensed under CC BY 4.0.", "CC-BY-4.0"), ("Licensed under CC BY-NC 4.0.", "CC-BY-NC-4.0"), ("Licensed under CC BY-SA 4.0.", "CC-BY-SA-4.0"),
    ("This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.", "CC-BY-NC-4.0"),
    ("This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.", "CC-BY-SA-4.0"),
    ("This work is licensed under a Creative Commons Attribution 4.0 International License.", "CC-BY-4.0"),
    ("This work is licensed under a Creative Commons Attribution 3.0 International License.", None),
    ("This work is licensed under the GNU General Public License, version 3.", "GPL-3.0"), ("This work is licensed under the GNU General Public License, version 2.", "GPL-2.0"),
    ("This work is licensed under the GNU Lesser General Public License, version 3.", "LGPL-3.0"), ("This work is licensed under the GNU Affero General Public License, version 3.", "AGPL-3.0"),
    ("This work is licensed under the GNU Library General Public License, version 3.", None), ("Licensed under the Apache License, Version 1.1.", None),
    (licenses.TEMPLATES["GPL-3.0/notice"].replace("General", "Lesser General"), None), (licenses.TEMPLATES["GPL-3.0/notice"].replace("version 3", "version 2"), None),
    ("All rights reserved.", "All-rights-reserved"), ("all of the rights are reserved for the royal family", None),
])
def test_sibling_licenses_are_told_apart(text, want):
    prepared = [(n, w, Counter(w)) for n, w in ((n, licenses.alnum_words(t.encode())) for n, t in licenses.TEMPLATES.items())]
    for around in (text, "some words before " + text + "\nand some words after it " * 3):
        found = licenses.scan(licenses.alnum_words(around.encode()), prepared)
        assert (found[0][0].split("/")[0] if found else None) == want


def test_every_template_names_itself():
    prepared = [(n, w, Counter(w)) for n, w in ((n, licenses.alnum_words(t.encode())) for n, t in licenses.TEMPLATES.items())]
    for name, words, _ in prepared:
        filler = [b"filler%d" % k for k in range(200)]
        assert licenses.scan([*filler, *words, *filler], prepared)[0] == (name, 1.0, 200, 200 + len(words))


def test_licenses_search_is_complete():
    """Windows at every place find nothing that the tiles miss."""
    draw = random.Random(11)
    template = [b"t%d" % k for k in range(10)]
    prepared = [("x", template, Counter(template))]
    for _ in range(300):
        text = [draw.choice(template) if draw.random() < 0.3 else b"w%d" % draw.randrange(50) for _ in range(draw.randrange(80))]
        if draw.random() < 0.7:
            at = draw.randrange(len(text) + 1)
            text[at:at] = [w if draw.random() > 0.1 else b"z" for w in template]
        every = max((len(licenses.align(text[k : k + 10], template)) for k in range(len(text))), default=0)
        found = licenses.scan(text, prepared)
        assert bool(found) or every < 8


def test_licenses_repeated_and_scattered(spark):
    mit, line = licenses.TEMPLATES["MIT/text"], licenses.TEMPLATES["MIT/statement"]
    changed = mit.replace("sublicense", "relicense")
    texts = {1: mit + "\n" + mit, 2: "x y z " + "\n".join([line] * 4), 3: "a sublicense far away " + "filler word " * 900 + changed, 4: ("word " * 90 + mit + "\n") * 6}
    got = by_id(licenses.scan_licenses(spark.createDataFrame(list(texts.items()), "doc_id int, text string")))
    assert [(got[k]["license"], got[k]["coverage"]) for k in (1, 2, 4)] == [("MIT/text", 1.0), ("MIT/statement", 1.0), ("MIT/text", 1.0)]
    assert got[3]["license"] == "MIT/text" and got[3]["coverage"] > 0.98


def test_licenses_match_plain_search(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    got, statements = by_id(licenses.scan_licenses(docs)), [t for n, t in licenses.TEMPLATES.items() if n.endswith("statement")]
    for r in docs.collect():
        if any(s in r["text"] for s in statements):
            assert got[r["doc_id"]]["coverage"] == 1.0
    assert licenses.scan_licenses(awkward(spark)).count() == awkward(spark).count()
    assert licenses.scan_licenses(empty(spark)).count() == 0


# --- language model


def test_word_counts_and_base_score(spark, docs):
    rows = docs.where("length(text) < 3000").unionByName(docs.limit(3)).unionByName(docs.limit(1).withColumn("text", F.lit(None).cast("string")))
    got = lm.score_documents(rows, 50).collect()
    counts = Counter()
    for r in rows.collect():
        if zlib.crc32(str(r["doc_id"]).encode()) % 10:
            counts.update([*re.findall(r"[^\x20\x09-\x0D]+", lower(r["text"])), None])
    total, distinct = sum(counts.values()), len(counts)
    want = []
    for r in rows.collect():
        tokens = [*re.findall(r"[^\x20\x09-\x0D]+", lower(r["text"])), None]
        want.append((r["doc_id"], len(tokens), sum(t in counts for t in tokens), total, round(sum(np.log10((counts[t] + 0.1) / (total + 0.1 * (distinct + 1))) for t in tokens), 4)))
    assert sorted(want) == sorted((r["doc_id"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 4)) for r in got)


def test_network_is_a_distribution_and_carries_state():
    net, draw = lm.Gru.fresh(), np.random.default_rng(1)
    h = draw.normal(size=(1, lm.UNITS)).astype(np.float32)
    every = net.log_probabilities(np.repeat(h, lm.CLASSES * lm.MEMBERS, axis=0), np.arange(lm.CLASSES * lm.MEMBERS))
    assert np.exp(every).sum() == pytest.approx(1, abs=1e-4)
    docs = [draw.integers(0, 1024, n).astype(np.int16) for n in (1, 7, 300, 7)]
    together = net.score(docs, 0, chunk=50)
    for k, d in enumerate(docs):
        h, token, total = np.zeros((1, lm.UNITS), np.float32), np.array([0]), 0.0
        for t in d:
            h, *_ = net.step(h, token)
            token = np.array([t])
            total += net.log_probabilities(h, token)[0]
        assert together[k] == pytest.approx(total / np.log(10), rel=1e-4)


def test_gradient_matches_differences():
    net, draw = lm.Gru.fresh(), np.random.default_rng(2)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    inputs, targets, h0 = draw.integers(1, 1024, (4, 3)), draw.integers(1, 1024, (4, 3)), np.zeros((3, lm.UNITS))
    g, _, _ = net._gradient(h0, inputs, targets, 0)
    for name, at in (("u", (2, 5)), ("u", (1, 40)), ("b", (20,)), ("c", (3, 4)), ("e", (int(inputs[1, 1]), 9))):
        old = net.p[name][at]
        values = []
        for d in (1e-5, -1e-5):
            net.p[name][at] = old + d
            values.append(net._gradient(h0, inputs, targets, 0)[2])
        net.p[name][at] = old
        assert g[name][at] == pytest.approx((values[0] - values[1]) / 2e-5, rel=2e-2, abs=1e-4)


def training_counts(df):
    counts = Counter()
    for r in df.collect():
        if zlib.crc32(str("" if r["doc_id"] is None else r["doc_id"]).encode()) % 10:
            counts.update([*re.findall(rb"[^\x20\x09-\x0D]+", lower(r["text"]).encode()), lm.END])
    return counts


def test_short_list_is_of_all_rows_whatever_the_sample(spark, docs):
    long = "y" * 65
    rows = docs.unionByName(docs.where("doc_id % 5 = 0").withColumn("text", F.concat("text", F.lit(f" {long} {long} late-word"))))
    counts = training_counts(rows)
    want = sorted((n for w, n in counts.items() if len(w) <= lm.HEAD_BYTES), reverse=True)[: lm.OTHER]
    assert counts[long.encode()] > want[-1] and counts[b"late-word"] > want[-1]
    for words in (lm.head_words(lm.sampled(rows, 2)), [lm.END]):
        head, counted = lm.count_all(rows, words)
        head, found = lm.by_count(head, counted.counts)
        assert list(found[: lm.OTHER]) == want == [counts[w] for w in head[: lm.OTHER]]
        assert len(set(head)) == len(head) and b"late-word" in head[: lm.OTHER] and not counted.missed


def test_network_learns_from_every_training_token(spark, docs):
    rows = docs.unionByName(docs.limit(2).withColumn("text", F.lit(None).cast("string")))
    start = lm.train(rows, 2)
    net, seen = lm.refined(rows, start)
    assert seen == sum(training_counts(rows).values())
    assert all(np.isfinite(v).all() for v in net.p.values()) and not np.array_equal(net.p["u"], start.gru.p["u"])


def test_counting_keeps_the_numbers_of_all_tokens(spark, docs):
    rows = docs.limit(40).unionByName(docs.limit(3)).unionByName(docs.limit(2).withColumn("text", F.lit(None).cast("string"))).select("doc_id", "text")
    head, counted = lm.count_all(rows, lm.head_words(rows.limit(5)))
    place, want = {w: k for k, w in enumerate(head)}, []
    for r in rows.collect():
        words = [*re.findall(rb"[^\x20\x09-\x0D]+", lower(r["text"] or "").encode()), lm.END]
        want.append((r["doc_id"], zlib.crc32(str(r["doc_id"]).encode()) % 10 == 0, [place.get(w, -1) for w in words]))
    got = [(r["doc_id"], r["held_out"], np.frombuffer(r["tokens"], np.int32).tolist()) for r in counted.tokens.collect()]
    assert sorted(got) == sorted(want) and any(-1 in x for *_, x in want)
    _, seen = lm.learnt(counted.tokens.where("NOT held_out"), lm.Model(head, lm.Gru.fresh()), np.arange(len(head)))
    assert seen == counted.total == sum(len(x) for _, out, x in want if not out)


def test_texts_are_split_in_one_pass_beside_the_sample(spark, docs):
    read = spark.sparkContext.accumulator(0)
    rows = docs.limit(200).localCheckpoint().select("doc_id", F.udf(lambda t: (read.add(1), t)[1])("text").alias("text"))
    assert lm.score_documents(rows, 200).count() == 200  # all are in the sample, so the words are counted once
    assert 200 <= read.value <= 3 * 200  # the sample is read for the head and for the first network


@pytest.mark.parametrize("size", [1, 2, 15, 17, 1023, 1025, 5003])
def test_learning_leaves_no_token_out(monkeypatch, size):
    seen = []
    monkeypatch.setattr(lm.Adam, "step", lambda self, targets, h, last, end: (seen.extend(targets.reshape(-1)), (h, targets[-1]))[1])
    assert lm.learn(lm.Adam(lm.Gru.fresh()), np.arange(size), 0, 64) == size
    assert sorted(seen) == list(range(size))


def test_model_beats_base_held_out(spark, small):
    rows = lm.score_documents(spark.read.parquet(f"{small}/documents.parquet"), 600).where("held_out").collect()
    assert sum(r["score"] for r in rows) > sum(r["base_score"] for r in rows)


def test_language_model_awkward(spark):
    got = lm.score_documents(awkward(spark), 20).collect()
    assert len(got) == awkward(spark).count() and all(np.isfinite(r["score"]) for r in got)
    assert all(r["n_tokens"] == 1 for r in got if r["doc_id"] in (0, 1, 7))
    assert lm.score_documents(empty(spark), 20).count() == 0


# --- packing


def check_packed(rows, texts, window=1024):
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(catalog.tokenizer_path())
    pieces = sorted((r["doc_id"] is None, r["doc_id"] or 0, r["doc_tokens"], r["ids_crc32"], r["start"], r["length"]) for r in rows)
    want = []
    for doc, text in texts:
        ids = np.array([*slow.encode(text or "", add_special_tokens=False).ids, 0], "<u4")
        want += [(doc is None, doc or 0, ids.size, zlib.crc32(ids[s : s + window].tobytes()), s, min(window, ids.size - s)) for s in range(0, ids.size, window)]
    assert pieces == sorted(want)
    sequences = {}
    for r in rows:
        sequences.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert sorted(sequences) == list(range(len(sequences)))
    for parts in sequences.values():
        end = 0
        for offset, length in sorted(parts):
            assert offset == end
            end += length
        assert end <= window
    return len(sequences)


def test_packing_is_whole_and_tight(spark, docs):
    rows = packing.pack_documents(docs, catalog.tokenizer_path()).collect()
    n = check_packed(rows, [(r["doc_id"], r["text"]) for r in docs.collect()])
    assert n * 1024 < 1.06 * sum(r["length"] for r in rows)


def test_packing_awkward(spark):
    frame = awkward(spark, (None, "", "a", "a", LONG[:30_000], "<|endoftext|>", "a <|endoftext|> b", "日本" * 800, " " * 5000))
    check_packed(packing.pack_documents(frame, catalog.tokenizer_path()).collect(), [(r["doc_id"], r["text"]) for r in frame.collect()])
    assert packing.pack_documents(empty(spark), catalog.tokenizer_path()).count() == 0


def test_added_tokens_keep_their_id():
    assert packing._encoder(catalog.tokenizer_path())("a <|endoftext|> b") == [64, 220, 50256, 275]


def test_fullest_is_optimal():
    draw = random.Random(2)
    for _ in range(200):
        counts = {draw.randrange(1, 30): draw.randrange(1, 4) for _ in range(draw.randrange(1, 6))}
        capacity, sums = draw.randrange(0, 60), {0}
        for n, c in counts.items():
            sums |= {s + n * k for s in sums for k in range(c + 1)}
        got = packing.fullest(counts, capacity)
        assert sum(n * c for n, c in got.items()) == max(s for s in sums if s <= capacity)
        assert all(c <= counts[n] for n, c in got.items())


def test_plan_uses_every_length():
    histogram = {n: 1 + n * 7919 % 100_000 for n in range(1, 1024)}
    used = Counter()
    for filling, times in packing.plan(histogram):
        assert sum(n * c for n, c in filling.items()) <= 1024
        for n, c in filling.items():
            used[n] += c * times
    assert used == Counter(histogram)


# --- simhash


def brute_components(rows):
    prints = []
    for doc, text in rows:
        words = re.findall(r"[^\x20\x09-\x0D]+", lower(text))
        h = [xxhash.xxh64_intdigest(" ".join(words[k : k + 3]).encode(), 42) for k in range(max(1, len(words) - 2))] if words else []
        prints.append((doc, sum(1 << b for b in range(64) if h and 2 * sum(x >> b & 1 for x in h) > len(h))))
    up = list(range(len(prints)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    fps = np.array([f for _, f in prints], np.uint64)
    for i in range(len(prints)):
        for j in np.flatnonzero(np.bitwise_count(fps ^ fps[i]) <= 2):
            a, b = root(i), root(int(j))
            up[max(a, b)] = min(a, b)
    least = {}
    for i, (doc, _) in enumerate(prints):
        if doc is not None:
            least[root(i)] = min(doc, least.get(root(i), doc))
    return [(doc, f"{f:016x}", least.get(root(i))) for i, (doc, f) in enumerate(prints)]


def test_simhash_matches_brute_force(spark, docs):
    rows = [(r["doc_id"], r["text"]) for r in docs.where("length(text) < 5000").collect()]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(map(tuple, simhash.components(frame).collect())) == sorted(brute_components(rows))


def test_simhash_awkward(spark):
    frame = awkward(spark)
    rows = [(r["doc_id"], r["text"]) for r in frame.collect()]
    assert sorted(map(tuple, simhash.components(frame).collect()), key=repr) == sorted(brute_components(rows), key=repr)
    assert simhash.components(empty(spark)).count() == 0
    kept = simhash.keep_first(frame)
    assert kept.columns == frame.columns
    assert kept.count() == len({c for _, _, c in brute_components(rows)})
    assert simhash.keep_first(empty(spark)).count() == 0


def test_every_near_pair_meets_at_an_anchor():
    draw = np.random.default_rng(3)
    fps = draw.integers(0, 1 << 63, 300, dtype=np.uint64)
    near = []
    for f in fps:
        for _ in range(4):
            a, b = draw.integers(0, 64, 2)
            near.append((f, f ^ np.uint64(1 << int(a)) ^ (np.uint64(1 << int(b)) if a != b else np.uint64(0))))
    for a, b in near:
        ka, _, ha = simhash.anchor_rows(np.array([a]))
        kb, _, hb = simhash.anchor_rows(np.array([b]))
        assert set(ka[ha]) & set(kb) and set(kb[hb]) & set(ka)


@pytest.mark.parametrize("limit", [1 << 24, 1])
def test_large_groups_keep_components(monkeypatch, limit):
    monkeypatch.setattr(simhash, "PAIRS", limit)
    draw = np.random.default_rng(5)
    fps = np.unique(draw.integers(0, 1 << 12, 400).astype(np.uint64))
    links = simhash.group_links(fps, np.ones(fps.size, bool))
    assert len(links) < fps.size and all(np.bitwise_count(fps[i] ^ fps[j]) <= 2 for i, j in links)
    parts = simhash.Forest(fps.size)
    for i, j in links:
        parts.join(int(i), int(j))
    for i in range(fps.size):
        for j in np.flatnonzero(np.bitwise_count(fps ^ fps[i]) <= 2):
            assert parts.root(i) == parts.root(int(j))


def test_connected_long_chain(spark):
    links = spark.range(200).selectExpr("id AS a", "id + 1 AS b").union(spark.range(1000, 1003).selectExpr("id AS a", "id + 1 AS b"))
    got = {r["node"]: r["root"] for r in simhash.connected(links.repartition(5)).collect()}
    assert all(got[k] == 0 for k in range(1, 201)) and all(got[k] == 1000 for k in range(1001, 1004))


# --- line dedup


def plain_chunks(ls):
    """All chunks of a text's lines, (start, end), by the rules as the operator's text states them, in plain loops."""
    n, mod = [len(x.split()) for x in ls], 1 << 64
    hashes = [xxhash.xxh64_intdigest(x) for x in ls]
    out, start = set(), 0
    for i, line in enumerate(ls):
        rolling = (hashes[i] + (hashes[i - 1] * 0x9E3779B97F4A7C15 if i else 0)) % mod
        if line.count(b" ") >= 25 and len(line) > 26:
            out |= {(start, i)} if start < i else set()
            out.add((i, i + 1))
            start = i + 1
        elif rolling // 2**32 % 3 == 0 or i + 1 - start == 32:
            out.add((start, i + 1))
            start = i + 1
    out |= {(start, len(ls))} if start < len(ls) else set()
    for a in range(len(ls)):
        if n[a]:
            out |= {next(((a, b) for b in range(a + 1, len(ls) + 1) if sum(n[a:b]) > 50), (0, 0))}
            out |= {next(((c, a + 1) for c in range(a, -1, -1) if sum(n[c : a + 1]) > 50), (0, 0))}
    return sorted((a, b) for a, b in out if b - a > 1 and any(ls[a:b]) or b - a == 1 and n[a] > 50)


def brute_lines(rows):
    """Every chunk but the first of its bytes goes, by plain loops; rows: (doc_id, text)."""
    key = lambda t: int(np.uint64(xxhash.xxh64_intdigest(t)).view(np.int64))
    first, where = {}, []
    for doc, text in sorted(set(rows), key=lambda r: (r[0] is None, r[0] or 0, key((r[1] or "").encode()))):
        ls = (text or "").encode().split(b"\n")
        for a, b in plain_chunks(ls):
            where.append((doc, text, a, b, first.setdefault(tuple(ls[a:b]), (doc, text, a, b))))
    gone = {}
    for doc, text, a, b, least in where:
        if least != (doc, text, a, b):
            gone.setdefault((doc, text), set()).update(range(a, b))
    out = {(doc, text): None if text is None else "\n".join(x for i, x in enumerate(text.split("\n")) if i not in gone.get((doc, text), ())) for doc, text in set(rows)}
    return [(doc, out[doc, text]) for doc, text in rows]


def test_line_dedup_matches_brute_force(spark, docs):
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    got = lines.dedup_lines(docs)
    assert sorted((r["doc_id"], r["text"]) for r in got.collect()) == sorted(brute_lines(rows))


def test_line_dedup_awkward(spark):
    passage = "\n".join(f"line number {k} of a shared passage with words" for k in range(8))
    long = " ".join(f"word{k}" for k in range(60))
    frame = awkward(spark, (None, "", "a\nb", "x\n" + passage + "\ny", "other\n" + passage + "\nend", long, "before\n" + long + "\nafter", "\n\n\n\n", "\n\n\n\n", "same\nsame\nsame\nsame\nsame\nsame"))
    rows = [(r["doc_id"], r["text"]) for r in frame.collect()]
    got = lines.dedup_lines(frame).collect()
    assert sorted(((r["doc_id"], r["text"]) for r in got), key=repr) == sorted(brute_lines(rows), key=repr)
    texts = {r["doc_id"]: r["text"] for r in got}
    assert texts[3] == "x\n" + passage + "\ny" and texts[5] == long and texts[6] == "before\nafter"
    cut = lines.remove_repeats(frame)
    assert cut.columns == frame.columns and cut.count() == len(rows)
    assert all(r["n_chars"] == len(r["text"]) for r in cut.where("text is not null and n_chars is not null").collect())
    assert lines.dedup_lines(empty(spark)).count() == 0


def test_line_dedup_passages_of_two_lines_and_clean_lines(spark):
    def words(name, n):
        return " ".join(f"{name}{k}" for k in range(n))

    passage = words("a", 27) + "\n" + words("b", 24)
    texts = [f"own {k}\n{passage}\nend {k}" for k in range(3)] + [f"{words(f'c{k}x', 30)}\n{words('shared', 45)}\n{words(f'd{k}x', 30)}" for k in range(3)]
    got = {r["doc_id"]: r["text"] for r in lines.dedup_lines(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [got[k] for k in (0, 3, 4, 5)] == [texts[k] for k in (0, 3, 4, 5)]
    assert got[1] == "own 1\nend 1" and got[2] == "own 2\nend 2"


def test_line_dedup_periodic_texts_keep_every_line(spark):
    """Lines that repeat in periods, and copies whose chunks overlap: as the plain version, and no line's content goes."""
    draw, rows = random.Random(12), []
    for k in range(60):
        own = [" ".join(f"t{k}w{draw.randrange(10**6)}" for _ in range(draw.choice((1, 4, 9, 15, 27)))) for _ in range(draw.randrange(2, 9))]
        rows.append((2 * k, "\n".join((own * 4)[: draw.randrange(len(own), 3 * len(own) + 1)])))
        cut = draw.randrange(len(own))
        rows.append((2 * k + 1, "\n".join([*own[cut:], "own line", *own[:cut], *own])))
    got = {r["doc_id"]: r["text"] for r in lines.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == dict(brute_lines(rows))
    assert {x for _, t in rows for x in t.split("\n")} == {x for t in got.values() for x in t.split("\n")} - {""}


def test_line_dedup_text_ids_and_very_long_texts(spark):
    passage = "\n".join(f"line number {k} of a shared passage with words" for k in range(8))
    long = "\n".join(f"row {k} of a very long text" for k in range(40_000))
    rows = [("b", "x\n" + passage), ("a", passage + "\ny"), (None, passage), ("c", long + "\n" + passage), ("d", long)]
    got = {r["doc_id"]: r["text"] for r in lines.dedup_lines(spark.createDataFrame(rows, "doc_id string, text string")).collect()}
    assert got == {"a": passage + "\ny", "b": "x", None: "", "c": long, "d": ""}


def test_a_digest_that_other_bytes_share_removes_nothing():
    text, bad = b"a\nb\nc", {lines._digest(b"b")}
    assert lines._without(text, [(0, 2)], bad)[0] == text and lines._without(text, [(2, 3)], bad)[0] == b"a\nb"
    assert lines._without(text, [(0, 2)], {lines._digest(lines._digest(b"a") + lines._digest(b"b"))})[0] == text


def test_boundaries_shift_with_the_content():
    draw = random.Random(9)
    body = [f"line {draw.randrange(10**9)}".encode() for _ in range(300)]
    cut = lambda ls: {tuple(ls[a:b]) for a, b in lines.chunk_bounds(ls)}
    assert len(cut(body) & cut([b"new first line", *body])) > 0.95 * len(cut(body))


def test_no_line_content_is_lost(spark, docs):
    before = {x for r in docs.collect() for x in r["text"].split("\n")}
    after = {x for r in lines.dedup_lines(docs).collect() for x in r["text"].split("\n")}
    assert before <= after


# --- media


def plain_cells(image, height, width):
    """Area means by weights of every sample: how much of it lies in a cell."""
    def share(n, cells):
        out = np.zeros((cells, n))
        for c in range(cells):
            low, high = c * n / cells, (c + 1) * n / cells
            for k in range(n):
                out[c, k] = max(0.0, min(high, k + 1) - max(low, k)) / (high - low)
        return out

    return share(image.shape[0], height) @ image.astype(float) @ share(image.shape[1], width).T


def plain_hash(image):
    cells = np.round(plain_cells(image, 8, 9), 6)
    bits = "".join("1" if cells[r, c] < cells[r, c + 1] else "0" for r in range(8) for c in range(8))
    return f"{int(bits, 2):016x}"


def plain_stored(payload):
    """PGM or BMP of a payload, byte by byte."""
    rows = len(payload) // 64
    if rows % 2:
        return b"P5\n64 %d\n255\n" % rows + payload
    palette = b"".join(bytes([k, k, k, 0]) for k in range(256))
    head = b"BM" + struct.pack("<IHHI", 54 + 1024 + len(payload), 0, 0, 54 + 1024)
    return head + struct.pack("<IiiHHIIiiII", 40, 64, -rows, 1, 8, 0, len(payload), 2835, 2835, 256, 0) + palette + payload


def test_media_matches_plain_version(spark, docs):
    got = by_id(media.document_media(docs))
    for r in docs.collect():
        x, data = got[r["doc_id"]], r["text"].encode()
        payload = data + b"\0" * (-len(data) % 64 if data else 64)
        assert (x["n_bytes"], x["payload_bytes"], x["payload_sha256"], x["tail_crc32"]) == (len(data), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        stored = plain_stored(payload)
        assert (x["media_bytes"], x["media_sha256"]) == (len(stored), hashlib.sha256(stored).hexdigest())
        if len(payload) < 20_000:
            image = np.frombuffer(payload, np.uint8).reshape(-1, 64)
            out = io.BytesIO()
            tile = np.rint(np.round(plain_cells(image, 32, 32), 6)).astype(np.uint8)
            np.save(out, tile)
            assert x["feature"].split("-")[0] == plain_hash(image)
            assert len(out.getvalue()) == 128 + 1024
            if x["tile_sha256"] == hashlib.sha256(out.getvalue()).hexdigest():
                assert x["feature"].split("-")[1] == plain_hash(tile)
            else:  # a mean on the half between two values may round to either
                own = np.load(io.BytesIO(media.npy_tile(image)))
                assert np.abs(own.astype(int) - tile).max() <= 1 and hashlib.sha256(media.npy_tile(image)).hexdigest() == x["tile_sha256"]


def test_tiles_are_written_and_read(spark, docs, tmp_path):
    some = docs.where("length(text) < 3000")
    media.write_tiles(media.encode_payloads(some, "bmp"), str(tmp_path / "tiles"), 16)
    back, want = by_id(media.read_tiles(spark, str(tmp_path / "tiles"))), by_id(some)
    assert set(back) == set(want)
    for k, r in back.items():
        data = want[k]["text"].encode()
        image = np.frombuffer(data.ljust(max(1, -(-len(data) // 64)) * 64, b"\0"), np.uint8).reshape(-1, 64)
        assert (r["height"], r["width"]) == image.shape
        assert np.abs(np.array(r["samples"]).reshape(16, 16) - plain_cells(image, 16, 16)).max() <= 0.5 + 1e-6


def test_media_awkward(spark):
    got = media.document_media(awkward(spark)).collect()
    assert len(got) == awkward(spark).count() and {r["payload_bytes"] for r in got if r["doc_id"] in (0, 1)} == {64}
    assert media.document_media(empty(spark)).count() == 0
    bad = spark.createDataFrame([(1, 3, b"nonsense"), (2, 0, None), (3, 4, b"P5\n9 9\n255\nxx")], "doc_id int, n_bytes long, media binary")
    assert all(r["feature"] is None for r in media.read_media(bad).collect())


def test_decoders():
    image = np.arange(15, dtype=np.uint8).reshape(3, 5) * 17
    assert (media.decode(media.encode_pgm(image)) == image).all() and (media.decode(media.encode_bmp(image)) == image).all()
    assert (media.decode(b"P2 # c\n5 3\n255\n" + b" ".join(str(int(v)).encode() for v in image.ravel())) == image).all()
    assert media.decode(b"P1\n3 2\n1 0 1\n010").tolist() == [[0, 1, 0], [1, 0, 1]]
    assert media.decode(b"P4\n3 2\n" + bytes([0b10100000, 0b01000000])).tolist() == [[0, 1, 0], [1, 0, 1]]
    rgb = np.arange(24, dtype=np.uint8).reshape(2, 4, 3)
    assert (media.decode(b"P6 4 2 255\n" + rgb.tobytes()) == rgb).all()
    rows = b"".join(r[:, ::-1].tobytes() for r in rgb[::-1])
    bmp = struct.pack("<2sIHHIIiiHHIIiiII", b"BM", 54 + 24, 0, 0, 54, 40, 4, 2, 1, 24, 0, 24, 0, 0, 0, 0) + rows
    assert (media.decode(bmp) == rgb).all()


def test_area_resize_is_exact():
    draw = np.random.default_rng(0)
    image = draw.integers(0, 255, (7, 10)).astype(float)
    fine = np.kron(image, np.ones((4 * 3, 3 * 3)))  # every target edge falls on a fine edge
    want = fine.reshape(4, 21, 9, 10).mean(axis=(1, 3))
    assert np.allclose(media.area_resize(image, 4, 9), want)
    assert np.load(io.BytesIO(media.npy_tile(image, 5))).shape == (5, 5)
    assert len(media.difference_hash(image)) == 16
