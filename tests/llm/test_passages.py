"""Repeated passages of short lines, in foreign surroundings."""

import random

from dp_itemsets.llm import lines


def sentence(draw, n):
    return " ".join(f"w{draw.randrange(10**6)}" for _ in range(n))


def test_passages_of_short_lines_go_whole(spark):
    draw, rows, own = random.Random(8), [], {}
    for shape in ([18] * 3, [13] * 4, [11] * 5, [10] * 6, [7] * 8, [6] * 10, [12] * 15, [5] * 40, [40, 1, 1, 40, 1], [1, 26, 25, 1], [51]):
        for _ in range(6):
            passage = [sentence(draw, n) for n in shape]
            for _ in range(2):
                head, tail = ([sentence(draw, draw.randrange(1, 20)) for _ in range(3)] for _ in range(2))
                own[len(rows)] = "\n".join(head + tail)
                rows.append((len(rows), "\n".join([*head, *passage, *tail])))
    got = {r["doc_id"]: r["text"] for r in lines.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(got[k] == (own[k] if k % 2 else text) for k, text in rows)


def test_runs_are_the_shortest():
    draw = random.Random(2)
    for _ in range(50):
        ls = [sentence(draw, draw.choice((0, 0, 3, 9, 20, 60))).encode() for _ in range(12)]
        n = [len(x.split()) for x in ls]
        every = [(a, b) for a in range(12) for b in range(a + 1, 13) if sum(n[a:b]) > 50]
        want = {(a, b) for a, b in every if n[a] and n[b - 1] and (sum(n[a : b - 1]) <= 50 or sum(n[a + 1 : b]) <= 50)}
        assert lines.passage_runs(ls) == want
