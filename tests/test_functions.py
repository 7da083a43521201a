"""Noise, mechanisms and budgets."""

import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from dp_itemsets.functions import budget, mechanisms, noise

FIXED = noise.NoiseSource.fixed(42)


def test_golden_draws(spark):
    row = spark.range(1).select(FIXED.uniform("bins", F.lit("a")).alias("u"), FIXED.laplace("bins", 2.0, F.lit("a")).alias("l"), FIXED.gumbel("bins", F.lit("a")).alias("g"), FIXED.uniform("bins", F.lit("b")).alias("v"), FIXED.laplace("bins", 2.0, F.lit("b")).alias("m")).first()
    assert row["u"] == pytest.approx(0.6229770783933667, abs=1e-15) and row["l"] == pytest.approx(0.5646042256096643)
    assert row["g"] == pytest.approx(0.7481408852864971) and row["v"] == pytest.approx(0.39628524148276834) and row["m"] == pytest.approx(-0.46494767937892134)
    assert FIXED.uniform_value("bins", "a") == row["u"] and FIXED.laplace_value("bins", 2.0, "b") == pytest.approx(row["m"])
    assert noise.NoiseSource.secret() != noise.NoiseSource.secret()


def test_laplace_and_gumbel_distributions(spark):
    rows = spark.range(20_000).select(FIXED.laplace("d", 3.0, "id").alias("l"), FIXED.gumbel("e", "id").alias("g")).agg(F.avg("l"), F.var_samp("l"), F.avg("g"), F.var_samp("g")).first()
    assert abs(rows[0]) < 0.15 and rows[1] == pytest.approx(18, rel=0.06)
    assert rows[2] == pytest.approx(0.5772, abs=0.05) and rows[3] == pytest.approx(math.pi**2 / 6, rel=0.06)


def test_noise_survives_repartitioning(spark):
    a = spark.range(500).select("id", FIXED.laplace("x", 1.0, "id").alias("n"))
    b = spark.range(500).repartition(7).select("id", FIXED.laplace("x", 1.0, "id").alias("n"))
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))


def test_top_c_of_one_ordering_draws_without_replacement():
    quality, c, eps = np.array([5.0, 3.0, 1.0, 0.0]), 2, 2.0
    draw, runs = np.random.default_rng(0), 4000
    want = Counter(i for _ in range(runs) for i in mechanisms.sequential_sample(quality * eps / c, c, draw))
    got = Counter()
    for seed in range(runs):
        source = noise.NoiseSource.fixed(seed)
        got.update(sorted(range(4), key=lambda i: -(quality[i] * eps / c + source.gumbel_value("p", i)))[:c])
    assert all(abs(got[i] - want[i]) < 5 * math.sqrt(runs / 4 * 2) for i in range(4))


def test_exponential_draw_follows_its_table(spark):
    df = spark.createDataFrame([("a", 3), ("b", 1), ("c", 0)], "k string, q int")
    table = {r["k"]: r["probability"] for r in mechanisms.exponential_probabilities(df, F.col("q"), 1.0).collect()}
    weights = {k: math.exp(q / 2) for k, q in (("a", 3), ("b", 1), ("c", 0))}
    assert table == pytest.approx({k: w / sum(weights.values()) for k, w in weights.items()})
    one = {r["k"]: r["probability"] for r in mechanisms.exponential_probabilities(df, F.col("q"), 1.0, one_sided=True).collect()}
    assert one["a"] > table["a"]
    many = df.crossJoin(spark.range(3000)).withColumn("score", F.col("q") / 2 + noise.NoiseSource.fixed(1).gumbel("t", "k", "id"))
    won = Counter(r["w"] for r in many.groupBy("id").agg(F.max_by("k", "score").alias("w")).collect())
    assert all(abs(won[k] / 3000 - p) < 0.035 for k, p in table.items())


def test_infinite_and_bad_budgets(spark):
    df = spark.createDataFrame([("a", 3), ("b", 9)], "k string, n int")
    assert [r["k"] for r in mechanisms.exponential_sample(df, F.col("n"), math.inf, 1, ["k"], FIXED, "x").collect()] == ["b"]
    assert {r["noisy"] for r in mechanisms.laplace_release(df, "n", 1, math.inf, ["k"], FIXED).collect()} == {3.0, 9.0}
    with pytest.raises(ValueError):
        mechanisms.laplace_release(df, "n", 1, 0, ["k"], FIXED)


def test_ledger_refuses_overspending(spark):
    ledger = budget.BudgetLedger(1.0)
    ledger.spend("a", 0.4)
    ledger.spend("b", 0.6)
    with pytest.raises(ValueError):
        ledger.spend("c", 0.01)
    assert ledger.report(spark).count() == 2


@pytest.mark.parametrize(("k", "eta", "lam", "want"), [(100, 1.2, 20, 44), (100, 1.2, 38, 55), (200, 1.2, 39, 88), (200, 1.1, 171, 49), (200, 1.2, 20, 66), (400, 1.2, 60, 158), (100, 1.2, 130, 0)])
def test_pairs_to_request(k, eta, lam, want):
    assert budget.pairs_to_request(k, eta, lam) == want


def test_split_never_exceeds_budget():
    for lam in (1, 12, 13, 40, 500):
        for pairs in (-5, 0, 7, 100):
            s = budget.split_budget(2.0, lam, pairs)
            assert sum(s.values()) == pytest.approx(2.0) and min(s.values()) >= 0
    assert budget.split_budget(1.0, 12, 30)["pairs"] == 0 and budget.split_budget(1.0, 38, 55)["items"] == pytest.approx(0.4 * 38 / 93)
    with pytest.raises(ValueError):
        budget.split_budget(1.0, 5, 5, (0.5, 0.5, 0.5))
