"""The near-dedup stage against exact similarities of all pairs."""

import random

import numpy as np

import corpus_pipeline
from dp_itemsets.llm import nearcopies, simhash


def shingles(text):
    words = text.lower().split()
    return {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))} if words else set()


def brute_heads(rows):
    sets, up = [shingles(t) for _, t in rows], list(range(len(rows)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if 5 * len(a & b) >= 4 * len(a | b):
                x, y = sorted((root(i), root(j)))
                up[y] = x
    return sorted(rows[i][0] for i in range(len(rows)) if root(i) == i)


def edited(words, n, draw):
    out = list(words)
    for k in draw.sample(range(len(out)), n):
        out[k] = f"new{draw.randrange(10**9)}"
    return " ".join(out)


def test_stage_finds_copies_from_four_fifths(spark, tiny):
    draw, texts = random.Random(4), ["", " \n", "A b", "a B"]
    for _ in range(30):
        words = [f"w{draw.randrange(5000)}" for _ in range(300)]
        texts += [edited(words, n, draw) for n in (0, 2, 4, 6, 9)]
    words = [f"v{k}" for k in range(300)]
    texts += [edited(words, n, draw) for n in range(40)]
    draw.shuffle(texts)
    rows = list(enumerate(texts))
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(7)
    kept = sorted(r["doc_id"] for r in corpus_pipeline.keep_one_of_near_copies(spark, frame, tiny).collect())
    assert kept == brute_heads(rows)


def test_a_large_group_of_near_and_less_near_copies(spark):
    """Copies of one text at all distances: many share keys without being similar enough, and none of the links is lost."""
    draw, base = random.Random(6), [f"u{k}" for k in range(150)]
    rows = [(k, edited(base if k % 3 else base[::-1], draw.choice((0, 1, 2, 3, 4, 5, 7, 9)), draw)) for k in range(400)]
    kept = nearcopies.keep_first(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    want = brute_heads(rows)
    assert 2 < len(want) < 300
    assert sorted(r["doc_id"] for r in kept) == want
    assert nearcopies.keep_first(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_links_of_a_group_join_all_parts():
    draw = np.random.default_rng(2)
    for _ in range(40):
        base = draw.choice(1000, 60, replace=False)
        sets = [np.unique(np.r_[draw.permutation(base)[: draw.integers(45, 60)], draw.integers(0, 1000, draw.integers(0, 6))]).astype(np.uint32) for _ in range(30)]
        parts = draw.integers(0, 8, 30)
        found = nearcopies.part_links(np.arange(30), parts, sets)
        near = lambda i, j: 5 * np.intersect1d(sets[i], sets[j]).size >= 4 * np.union1d(sets[i], sets[j]).size
        assert all(near(i, j) and parts[i] != parts[j] for i, j in found) and len(found) < 8
        up = {int(p): int(p) for p in parts}
        for i, j in found:
            old, new = up[int(parts[i])], up[int(parts[j])]
            up = {k: new if v == old else v for k, v in up.items()}
        assert all(up[int(parts[i])] == up[int(parts[j])] for i in range(30) for j in range(i) if near(i, j))


def test_similarity_is_of_whole_sets():
    a = np.arange(100, dtype=np.uint64)
    assert nearcopies.are_similar(a, a[:80]) and not nearcopies.are_similar(a, a[:79])


def test_stage_links_fingerprints_too(spark, tiny):
    """Repeats decide a fingerprint, and not a set: these are far apart as sets, and have one fingerprint."""
    often = "a b c d e " * 2000
    one, two = often + " ".join(f"x{k}" for k in range(9)), often + " ".join(f"y{k}" for k in range(9))
    prints = simhash.fingerprints_of([one.encode(), two.encode()])
    assert int(np.bitwise_count(prints[0] ^ prints[1])) <= simhash.THRESHOLD
    assert not nearcopies.are_similar(*(nearcopies.shingle_set(t.encode()) for t in (one, two)))
    docs = spark.createDataFrame([(1, one), (2, two), (3, "something else stands here today")], "doc_id long, text string")
    assert sorted(r["doc_id"] for r in nearcopies.keep_first(docs).collect()) == [1, 2, 3]
    assert sorted(r["doc_id"] for r in corpus_pipeline.keep_one_of_near_copies(spark, docs, tiny).collect()) == [1, 3]
