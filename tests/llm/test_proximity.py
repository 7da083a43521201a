"""Proximity search against plain loops over many short neighbouring documents."""

import random
from collections import Counter

from dp_itemsets.llm import decontamination


def brute(rows, words, slop):
    total = Counter(w for _, t in rows for w in t.split())
    order, out = sorted(dict.fromkeys(words), key=lambda w: total[w]), []
    for doc, text in rows:
        ws = text.split()
        for k in (k for k, w in enumerate(ws) if w == order[0]):
            spots = []
            for w in order[1:]:
                near = sorted((abs(p - k), -p) for p, x in enumerate(ws) if x == w)
                spots.append(near[0] if near else (slop + 1, 0))
            if all(d <= slop for d, _ in spots):
                places = [k, *(-p for _, p in spots)]
                out.append((doc, min(places), max(places) + 1))
    return sorted(out)


def test_matches_lie_in_the_anchors_document(spark):
    rows = [(1, "a b fox"), (2, "quick c d fox")]
    index = decontamination.build_index(spark.createDataFrame(rows, "doc_id int, text string").coalesce(1))
    assert [tuple(r)[1:] for r in decontamination.proximity(index, {"q": "quick fox"}, 3).collect()] == [(2, 0, 4)]


def test_proximity_matches_brute_force(spark):
    draw = random.Random(7)
    rows = [(k, " ".join(draw.choice("abcdefgh") for _ in range(draw.randrange(9)))) for k in range(600)]
    frame = spark.createDataFrame(rows, "doc_id int, text string")
    for parts in (1, 5):
        index = decontamination.build_index(frame.repartition(parts))
        for query, slop in (("a b", 3), ("c a h", 2), ("d", 0), ("e f e", 6), ("a nothing", 4)):
            got = sorted(tuple(r)[1:] for r in decontamination.proximity(index, {"q": query}, slop).collect())
            assert got == brute(rows, query.split(), slop)
