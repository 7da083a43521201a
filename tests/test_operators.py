"""Mining, bins, bases, baselines and measures on a hand-checkable set, and against each other."""

import math
import time
from itertools import combinations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from dp_itemsets.functions.noise import NoiseSource
from dp_itemsets.operators import bases as B
from dp_itemsets.operators import bins, metrics, mining, truncated
from dp_itemsets.queries import methods
from dp_itemsets.sources.transactions import Transactions
from dp_itemsets.sources.views import VIEWS

TOY = [set(x) for x in ("abc", "abc", "abd", "ab", "acd", "bcd", "ae", "b", "ce", "abcd")]
FIXED = NoiseSource.fixed(42)


@pytest.fixture(scope="module")
def toy(spark):
    return Transactions.from_sets(spark, TOY, "abcdef")


def plain_support(s):
    return sum(set(s) <= t for t in TOY)


def plain_topk(k, max_len=9):
    sets = [c for n in range(1, max_len + 1) for c in combinations("abcde", n) if plain_support(c)]
    return sorted(((plain_support(c), c) for c in sets), key=lambda x: (-x[0], len(x[1]), "|".join(x[1])))[:k]


@pytest.mark.parametrize("k", [1, 3, 4, 7, 12, 50])
@pytest.mark.parametrize("max_len", [None, 1, 2])
def test_topk_on_toy(toy, k, max_len):
    got = [(f.support, tuple(sorted(f.items))) for f in mining.topk(toy, k, max_len)]
    assert got == plain_topk(k, max_len or 9)


def test_apriori_growth_and_thresholds(toy):
    found = mining.apriori(toy, 4)
    assert {mining.key_of(f.items) for f in found} == {"a", "b", "c", "d", "a|b", "a|c", "b|c"}
    assert {(r["itemset"], r["support"]) for r in mining.fp_growth(toy, 4).collect()} == {(mining.key_of(f.items), f.support) for f in found}
    assert {mining.key_of(f.items) for f in mining.maximal(found)} == {"a|b", "a|c", "b|c", "d"}
    assert mining.k_for_threshold(toy, 0.4) == 7 and mining.threshold_for_k(toy, 7) == 0.4 and mining.threshold_for_k(toy, 500) == 0
    assert {r["itemset"]: r["support"] for r in mining.topk_bitmap(toy, list("abcde"), 6).collect()} == {"|".join(c): n for n, c in plain_topk(6)}


def test_miners_agree_on_views(spark, tiny):
    for view, least in (("order_terms", 200), ("line_records", 4300), ("doc_words", 110), ("page_words", 50)):
        tx = VIEWS[view](spark, tiny)
        a = {(mining.key_of(f.items), f.support) for f in mining.apriori(tx, least)}
        top = mining.topk(tx, len(a))
        assert {(mining.key_of(f.items), f.support) for f in top} == a
        assert {(r["itemset"], r["support"]) for r in mining.fp_growth(tx, least).collect()} == a


def test_pools_beyond_one_mask(spark):
    draw = np.random.default_rng(1)
    sets = [{f"i{j:03d}" for j in draw.choice(90, 12, replace=False)} for _ in range(300)]
    tx = Transactions.from_sets(spark, sets)
    for f in mining.topk(tx, 150):
        assert f.support == sum(set(f.items) <= s for s in sets)
    some = [("i000", "i070", "i089"), ("i061", "i062"), ("i088",)]
    assert mining.supports(tx, some) == {s: sum(set(s) <= t for t in sets) for s in some}


def test_items_pairs_neighbours_and_empty(spark, toy):
    assert {r["item"]: r["n"] for r in toy.item_counts().collect()} == {"a": 7, "b": 7, "c": 6, "d": 4, "e": 2, "f": 0}
    assert {(r["a"], r["b"]): r["n"] for r in mining.pair_counts(toy, list("abf")).collect()} == {("a", "b"): 5, ("a", "f"): 0, ("b", "f"): 0}
    assert toy.without(0).size() == 9 and toy.plus("ab").item_counts().where("item = 'a'").first()["n"] == 8
    none = Transactions(toy.rows.limit(0))
    assert mining.topk(none, 5) == [] and mining.apriori(none, 1) == [] and mining.dataset_profile(none, 5)["n"] == 0
    doubled = Transactions.from_long(toy.long().union(toy.long()))
    assert {r["item"]: r["n"] for r in doubled.item_counts().collect()}["a"] == 7


def test_toy_bins_and_fusion(toy):
    abc, both = B.BasisSet.of(["abc"]), B.BasisSet.of(["abc", "cd"])
    full = {r["mask"]: r["n"] for r in bins.complete_bins(bins.bin_counts(toy, abc), abc).collect()}
    assert [full[m] for m in range(8)] == [0, 1, 1, 2, 1, 1, 1, 3] and sum(full.values()) == 10
    got = {r["itemset"]: r for r in bins.basis_estimates(toy, both, math.inf, FIXED).collect()}
    assert got["a|b"]["nc"] == 5 and got["c"]["nc"] == 6 and got[""]["nc"] == 10 and got["c"]["v"] == pytest.approx(4 * 2 / 6)
    top = bins.count_with_bases(toy, both, 3, math.inf, FIXED).collect()
    assert [(r["itemset"], r["noisy_count"], r["noisy_freq"]) for r in top] == [("a", 7, 0.7), ("b", 7, 0.7), ("c", 6, 0.6)]


def test_strategies_and_folds_agree(toy):
    both = B.BasisSet.of(["abc", "bcd", "ab"])
    noisy = bins.noisy_bins(bins.complete_bins(bins.bin_counts(toy, both), both), 3, 0.7, FIXED)
    sums = [sorted((r["basis_id"], r["mask"], round(r["nc"], 8)) for r in bins.superset_sums(noisy, both, s).collect()) for s in ("join", "zeta", "pandas")]
    assert sums[0] == sums[1] == sums[2]
    named = bins.named_estimates(bins.superset_sums(noisy, both), both)
    fold = lambda df: sorted((r["itemset"], round(r["nc"], 8), round(r["v"], 8)) for r in df.collect())
    assert fold(bins.fuse(named)) == fold(bins.fuse_pairwise(named.orderBy(F.desc("nc"))))


def test_error_variance_is_as_predicted(toy):
    b, eps, runs = B.BasisSet.of(["abc"]), 0.5, 400
    full = bins.complete_bins(bins.bin_counts(toy, b), b).crossJoin(toy.spark.range(runs))
    noisy = full.withColumn("noisy", F.col("n") + FIXED.laplace("v", 1 / eps, "id", "mask"))
    for mask, size in ((1, 1), (3, 2), (7, 3)):
        sums = noisy.where(F.col("mask").bitwiseAND(mask) == mask).groupBy("id").agg(F.sum("noisy").alias("s")).agg(F.var_samp("s")).first()[0]
        assert sums == pytest.approx(B.error_variance(3, size, 1, eps), rel=0.3)


def test_bin_sensitivity(toy):
    both = B.BasisSet.of(["abc", "cd", "e"])
    table = lambda tx: {(r["basis_id"], r["mask"]): r["n"] for r in bins.bin_counts(tx, both).collect()}
    whole = table(toy)
    for tid in (0, 4, 8):
        less = table(toy.without(tid))
        assert sum(abs(whole[k] - less.get(k, 0)) for k in whole) == both.width
        assert all(less.get(k, 0) <= whole[k] for k in whole)  # one-directional


def test_privacy_of_a_one_bin_release():
    """Histograms of noisy counts on neighbours differ by a factor of e^eps at most, up to sampling."""
    eps, runs, edges = 1.0, 20_000, np.linspace(5, 15, 8)
    draws = np.array([FIXED.laplace_value("audit", 1 / eps, k) for k in range(runs)])
    a, b = (np.histogram(np.clip(c + draws, 5, 15), edges)[0] for c in (10, 9))
    ratio = np.abs(np.log((a + 1) / (b + 1)))
    assert (ratio <= eps + 4 * np.sqrt(1 / (a + 1) + 1 / (b + 1))).all()


def test_basis_sets():
    pairs = [("1", "2"), ("2", "3"), ("1", "3")]
    assert B.BasisSet.from_cliques("123", pairs).bases == (("1", "2", "3"),)
    assert B.BasisSet.of(["ab", "c"]).merged(0, 1).bases == (("a", "b", "c"),)
    assert {frozenset(c) for c in B.maximal_cliques(B.pair_graph("abcd", [("a", "b"), ("b", "c"), ("a", "c")]), 1)} == {frozenset("abc"), frozenset("d")}
    assert [B.grouping_factor(g) for g in (1, 2, 3, 4, 5, 6)] == pytest.approx([1, 0.5, 4 / 9, 0.5, 0.64, 0.8889], abs=1e-4)
    assert B.worst_error_variance(B.BasisSet.of(["abc", "de"]), 0.5) == 2**3 * 16
    assert B.average_error_variance([frozenset("abc")], ["a"]) == B.error_variance(3, 1, 1, 1.0)
    assert B.average_error_variance([frozenset("ab")], ["c"]) == math.inf
    assert metrics.cost_model(B.BasisSet.of(["abc"]), 50)["superset_sums"] == 27 - 8


@settings(max_examples=60, deadline=None)
@given(st.sets(st.tuples(st.integers(0, 9), st.integers(0, 9)).filter(lambda p: p[0] < p[1]), max_size=20), st.integers(3, 12))
def test_built_bases_always_cover(pairs, longest):
    items, pairs = [f"i{k}" for k in range(10)], [(f"i{a}", f"i{b}") for a, b in pairs]
    wanted = [(i,) for i in items] + pairs
    plain, built = B.build_bases(items, pairs, longest, merge=False, dissolve=False), B.build_bases(items, pairs, longest)
    assert not built.uncovered(wanted) and built.length <= longest
    assert B.average_error_variance(built, wanted) <= B.average_error_variance(plain, wanted) * (1 + 1e-9)
    graph = B.pair_graph(items, pairs)
    cliques = B.maximal_cliques(graph, 1)
    assert all(b in graph[a] for c in cliques for a, b in combinations(sorted(c), 2))
    assert len(cliques) == len({*cliques}) and not any(a < b for a in cliques for b in cliques)


def test_margins_and_spaces():
    golden = {("retail", 100, 1, 88162, 16470): 5767.93, ("mushroom", 100, 2, 8124, 119): 5433.60, ("pumsb", 200, 3, 49046, 2088): 21235.04, ("kosarak", 200, 2, 990002, 41270): 20773.07, ("aol", 200, 1, 647377, 2290685): 16038.43}
    for (_, k, m, n, items), want in golden.items():
        assert truncated.truncation_margin(k, 1.0, n, 0.9, truncated.candidate_space(items, m)) * n == pytest.approx(want, abs=0.01)
    assert truncated.candidate_space(119, 2) == 7140 and truncated.candidate_space(25, 2) == 325 and truncated.candidate_space(25, 2, exact=True) == 300
    assert not truncated.is_effective(5768, 1192) and truncated.is_effective(21235, 28613)


def test_sampled_tail_has_the_law_of_listing(toy):
    """How many unlisted sets get in, and the largest of their scores, against drawing every one."""
    count, value, k, scale, runs = 40, 1.0, 5, 2.0, 1500
    for gumbel in (True, False):
        sampled, listed = [], []
        for seed in range(runs):
            source = NoiseSource.fixed(seed)
            sampled.append(max(truncated.implicit_scores(count, value, k, -1e9, source, "s", gumbel, scale)))
            draw = (lambda j, s=source: s.gumbel_value("all", j)) if gumbel else (lambda j, s=source: s.laplace_value("all", scale, j))
            listed.append(value + max(draw(j) for j in range(count)))
        assert np.mean(sampled) == pytest.approx(np.mean(listed), abs=0.25) and np.std(sampled) == pytest.approx(np.std(listed), rel=0.15)
    huge = truncated.implicit_scores(10**30, 0.0, 3, -1e9, FIXED, "h", True, 1.0)
    assert len(huge) == 3 and huge == sorted(huge, reverse=True) and 60 < huge[0] < 90
    members = truncated.implicit_members(list("abcdef"), 2, {"a", "a|b"}, 10, FIXED, "m")
    assert len({mining.key_of(s) for s in members}) == 10 and not {"a", "a|b"} & {mining.key_of(s) for s in members}
    assert len(truncated.implicit_members([f"i{k}" for k in range(500)], 3, set(), 7, FIXED, "m")) == 7


def test_truncated_release_limits(toy):
    exact = truncated.truncated_release(toy, 4, 2, 1e6, FIXED, rho=1e-12)
    assert {r["itemset"] for r in exact.collect()} == {"a", "b", "c", "a|b"}
    low = truncated.select(toy, 4, 2, 0.01, FIXED, selector="laplace")
    assert len(low) == 4 == len({mining.key_of(s) for s in low})
    pairs = truncated.select(toy, 3, 2, 1e6, FIXED, rho=1e-12, exactly=True)
    assert {mining.key_of(s) for s in pairs} == {"a|b", "a|c", "b|c"}
    direct = truncated.direct_release(toy, [("a",), ("a", "b")], 1e9, FIXED)
    assert {r["itemset"]: round(r["noisy_count"]) for r in direct.collect()} == {"a": 7, "a|b": 5}


def test_measures(spark, toy):
    truth = mining.topk(toy, 4)
    published = [("a", 7.0), ("b", 7.7), ("d", 4.0), ("f", 1.0)]
    m = metrics.measured(toy, published, truth, 4)
    assert m["fnr"] == m["fpr"] == 0.5 and m["infinite_share"] == 0.25 and m["re"] == pytest.approx(0.05)
    assert metrics.measured(toy, [("a|c", 4.0)] * 1, truth, 4, tie_tolerant=True)["fnr"] == 1
    assert metrics.coverage_miss_rate(B.BasisSet.of(["a", "b", "c"]), truth, 4) == 0.25
    rows = spark.createDataFrame([("x", 1.0), ("x", 2.0), ("x", 3.0)], "c string, v double")
    assert metrics.repeats(rows, ["c"], "v").first()["std_error"] == pytest.approx(1 / math.sqrt(3))


def test_levels_are_counted_together(spark):
    """A level costs a pass of bit columns, not one of pairs for every 20,000 sets."""
    items = [f"i{k:02}" for k in range(12)]
    tx = Transactions.from_sets(spark, [items] * 3 + [items[:5]] + [[]])
    found = mining.apriori(tx, 3)
    assert len(found) == 2**12 - 1 and sum(f.support == 4 for f in found) == 31
    projection = mining.Projection(tx, items)
    try:
        assert projection.blocks.columns == ["words", "bits"]
        assert projection.count([(0, 1), (0, 11), (2,), tuple(range(12))]) == {(0, 1): 4, (0, 11): 3, (2,): 4, tuple(range(12)): 3}
    finally:
        projection.close()


def test_maximal_of_many_sets_ends():
    items = [f"i{k:02}" for k in range(16)]
    every = [mining.Found(c, 1) for n in range(1, 17) for c in combinations(items, n)]
    began = time.time()
    assert [f.items for f in mining.maximal(every)] == [tuple(items)]
    assert [f.items for f in mining.maximal([mining.Found(("a",), 2), mining.Found(("a", "b", "c"), 1), mining.Found(("d",), 1)])] == [("a", "b", "c"), ("d",)]
    assert time.time() - began < 60


def test_threshold_counts_level_by_level(toy, monkeypatch):
    grown = mining.fp_growth
    monkeypatch.setattr(mining, "fp_growth", lambda *a: pytest.fail("pattern growth isn't needed for a few sets"))
    assert mining.k_for_threshold(toy, 0.4) == 7
    monkeypatch.setattr(mining, "fp_growth", grown)
    monkeypatch.setattr(mining, "MOST_SETS", 3)  # beyond what may be listed nothing is left out
    assert mining.k_for_threshold(toy, 0.4) == 7


def test_many_bases_are_merged_in_bearable_time():
    draw = np.random.default_rng(5)
    items = [f"k{i}" for i in range(100)]
    pairs = [tuple(draw.choice(items, 2, replace=False)) for _ in range(340)]
    began = time.time()
    built = B.build_bases(items, pairs, 7)
    assert not built.uncovered(pairs) and built.length <= 7
    assert time.time() - began < 15


@pytest.mark.parametrize("selector", ["exponential", "laplace"])
@pytest.mark.parametrize("m", [1, 2])
def test_selection_without_a_list_of_names(spark, monkeypatch, selector, m):
    """Many items stay where they are, and the choice is the one that lists of them give."""
    sets = [[f"i{k}" for k in range(60) if (k * 7 + t * 5) % (3 + k % 11) == 0] for t in range(40)]
    tx = Transactions.from_sets(spark, sets)
    draw = lambda eps: truncated.select(tx, 8, m, eps, FIXED, selector=selector, observed_domain=True)
    budgets = (0.5, 200.0) if m == 1 else (200.0,)
    listed = [draw(eps) for eps in budgets]
    monkeypatch.setattr(truncated, "MOST_NAMES", 10)
    monkeypatch.setattr(truncated, "_universe", lambda tx: pytest.fail("the names were listed"))
    names = truncated.Names(tx)
    assert names.listed is None and list(names.some(range(len(names))).values()).sort() == [x for s in sets for x in s].sort()
    names.close()
    assert [draw(eps) for eps in budgets] == listed


def test_listing_beyond_the_driver(spark, tiny, monkeypatch):
    """More sets than the driver may hold stay in Spark, all of them."""
    tx = VIEWS["order_terms"](spark, tiny)
    want = {(mining.key_of(f.items), len(f.items), f.support) for f in mining.apriori(tx, 40)}
    monkeypatch.setattr(mining, "MOST_SETS", 2000)
    monkeypatch.setattr(methods, "_LEAST", 40)
    with pytest.raises(mining.TooManySets):
        mining.apriori(tx, 40)
    got = list(map(tuple, methods.apriori_order_terms(spark, tiny).select("itemset", "size", "support").collect()))
    assert len(got) == len(want) > 2000 and set(got) == want


def test_listing_in_spark_is_that_of_the_driver(spark):
    draw = np.random.default_rng(2)
    wide = [{f"i{j:03d}" for j in draw.zipf(1.3, 14) % 300} for _ in range(400)]  # places take two bytes
    items = [f"i{k:02}" for k in range(12)]
    for sets, least, most in ((wide, 2, 4), ([items] * 3 + [items[:5]] + [[]], 3, None), ([items] * 3, 3, 2), ([items], 2, None), ([["a"], ["a"]], 2, None)):
        tx = Transactions.from_sets(spark, sets)
        got = [tuple(r) for r in mining.apriori(tx, least, most, listed=False).frame().collect()]
        want = {(mining.key_of(f.items), len(f.items), f.support) for f in mining.apriori(tx, least, most)}
        assert len(got) == len(want) and set(got) == want


def test_sets_grow_the_same_in_small_steps(monkeypatch):
    draw = np.random.default_rng(3)
    held = draw.random((9, 128)) < 0.8
    bits = np.packbits(held, axis=1, bitorder="little").view(np.uint64)
    want = {c: n for k in range(1, 10) for c in combinations(range(9), k) if (n := int(held[list(c)].all(axis=0).sum())) >= 20}
    for most in (1, 100, 1 << 20):
        monkeypatch.setattr(mining, "STEP_BYTES", most)
        start = np.arange(9, dtype=np.uint8).reshape(-1, 1)
        got = [(tuple(s), n) for sets, counts in mining._grown(start, held.sum(axis=1), bits, np.full(9, 9), 20, None) for s, n in zip(sets.tolist(), counts.tolist(), strict=True)]
        assert len(got) == len(want) and dict(got) == want


def test_maximal_beyond_the_driver(spark, tiny, monkeypatch):
    """Sets that stay in Spark are compared there."""
    tx = VIEWS["order_terms"](spark, tiny)
    want = {(mining.key_of(f.items), len(f.items), f.support) for f in mining.maximal(mining.apriori(tx, 40))}
    monkeypatch.setattr(mining, "MOST_SETS", 2000)
    monkeypatch.setattr(methods, "_LEAST", 40)
    got = list(map(tuple, methods.maximal_itemsets_order_terms(spark, tiny).select("itemset", "size", "support").collect()))
    assert len(got) == len(want) > 2000 and set(got) == want


def test_maximal_in_spark_is_that_of_the_driver(spark):
    draw = np.random.default_rng(2)
    wide = [{f"i{j:03d}" for j in draw.zipf(1.3, 14) % 300} for _ in range(400)]
    items = [f"i{k:02}" for k in range(12)]  # sets of over eight items take two words
    for sets, least, most in ((wide, 2, 4), ([items] * 3 + [items[:10]] + [[]], 3, None), ([items[:9]] * 2 + [items[2:11]] * 2, 2, None), ([items] * 3, 3, 2), ([["a"], ["a"]], 2, None), ([["a"]], 2, None)):
        tx = Transactions.from_sets(spark, sets)
        got = [tuple(r) for r in mining.maximal(mining.apriori(tx, least, most, listed=False)).frame().collect()]
        want = {(mining.key_of(f.items), len(f.items), f.support) for f in mining.maximal(mining.apriori(tx, least, most))}
        assert len(got) == len(want) and set(got) == want
