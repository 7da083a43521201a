"""The whole release, its plans, and the experiment grid."""

import math

import pytest

from dp_itemsets.functions.noise import NoiseSource
from dp_itemsets.operators import bins, metrics, mining
from dp_itemsets.operators.bases import BasisSet
from dp_itemsets.plans import basis_release as R
from dp_itemsets.plans import experiments
from dp_itemsets.sources import files
from dp_itemsets.sources.transactions import Transactions
from dp_itemsets.sources.views import VIEWS

FIXED = NoiseSource.fixed(42)


def test_single_basis_release_is_accurate(spark, small):
    tx = VIEWS["line_records"](spark, small)
    out = R.release_topk_private(tx, 50, 0.5, FIXED)
    truth = mining.topk(tx, 50)
    m = metrics.measured(tx, out.ranked(), truth, 50)
    assert out.bases.width == 1 and out.lam <= 12 and m["fnr"] <= 0.06 and m["re"] < 0.01
    assert out.ledger.spent == pytest.approx(0.5) and out.report(spark).count() == 4


def test_infinite_budget_gives_the_truth(spark, tiny):
    tx = VIEWS["line_records"](spark, tiny)
    out = R.release_topk_private(tx, 50, math.inf, FIXED)
    assert [s for s, _ in out.ranked()] == [mining.key_of(f.items) for f in mining.topk(tx, 50)]
    wide = VIEWS["order_terms"](spark, tiny)
    rel = R.release_topk_private(wide, 50, math.inf, FIXED, R.ReleaseParams(max_basis_len=7))
    truth = mining.topk(wide, 50)
    assert metrics.measured(wide, rel.ranked(), truth, 50)["fnr"] == pytest.approx(metrics.coverage_miss_rate(rel.bases, truth, 50))


def test_boundary_of_one_basis(spark, tiny):
    tx = VIEWS["order_brands"](spark, tiny)
    for limit, width in ((25, 1), (12, None)):
        out = R.release_topk_private(tx, 25, 5.0, FIXED, R.ReleaseParams(single_basis_limit=limit, max_basis_len=6, true_rank=True) if limit < 25 else R.ReleaseParams(single_basis_limit=20, true_rank=False))
        assert width is None or out.bases.width >= width
        assert out.ledger.spent <= 5 * (1 + 1e-9)


def test_bad_parameters(spark, tiny):
    tx = VIEWS["order_brands"](spark, tiny)
    for call in (lambda: R.release_topk_private(tx, 0, 1.0, FIXED), lambda: R.release_topk_private(tx, 5, 0.0, FIXED), lambda: R.ReleaseParams(eta=0.5), lambda: R.ReleaseParams(rank_domain="x"), lambda: bins.bin_counts(tx, BasisSet.of([[f"i{k}" for k in range(30)]]))):
        with pytest.raises(ValueError):
            call()


def test_k_beyond_everything(spark):
    tx = Transactions.from_sets(spark, [{"a"}, {"a", "b"}], "abc")
    out = R.release_topk_private(tx, 30, 100.0, FIXED, R.ReleaseParams(true_rank=True, true_elements=True))
    assert out.itemsets.count() == 3  # all candidates: a, b, ab
    assert R.release_topk_private(tx, 1, 100.0, FIXED).itemsets.count() == 1


def test_all_ranks_variant(spark, tiny):
    tx = VIEWS["order_brands"](spark, tiny)
    ranks = {r["j"]: r["n"] for r in R.item_ranks(tx, None).collect()}
    some = {r["j"]: r["n"] for r in R.item_ranks(tx, 10).collect()}
    assert len(ranks) == 25 and all(ranks[j] == n for j, n in some.items())
    assert 1 <= R.estimate_item_rank(tx, 20, 1.0, 1.2, FIXED, "all_items") <= 25


def test_plans(spark, tiny):
    tx = VIEWS["line_records"](spark, tiny)
    b = BasisSet.of([["q>5", "d<=9", "t<=7"], ["flag=A", "stat=F"]])
    plan = bins.bin_counts(tx, b)._jdf.queryExecution().toString()
    physical = plan[plan.index("== Physical Plan =="):]
    assert "CartesianProduct" not in physical and "Python" not in physical
    assert physical.count("lineitem.parquet") <= 1 or physical.count("FileScan") == 3
    assert "l_comment" not in physical and "c_acctbal" not in physical.split("ReadSchema")[0]
    assert "partial_sum" in physical and "partial_count" in physical


def test_basis_beats_truncated(spark, small):
    rows = experiments.run_grid(spark, small, experiments.WORKLOADS["single_basis_records"], (1.0,), (1,), (50,), (1, 2))
    best = {r["method"]: r["fnr"] for r in experiments.best_m(rows).collect()}
    assert best["basis"] < best["truncated"]


def test_threshold_version_and_ablations(spark, tiny):
    tx = VIEWS["order_terms"](spark, tiny)
    out = R.release_threshold_private(tx, 0.3, 2.0, FIXED)
    assert out.itemsets.count() == mining.k_for_threshold(tx, 0.3)
    assert all("k comes from the data" in r["warning"] for r in out.report(spark).collect())
    variants = R.ablations(R.ReleaseParams(max_basis_len=7))
    plain = R.release_topk_private(tx, 40, 1.0, FIXED, variants["no_merge"])
    merged = R.release_topk_private(tx, 40, 1.0, FIXED, variants["default"])
    assert merged.bases.width <= plain.bases.width
    assert not R.release_topk_private(tx, 40, 1.0, FIXED, variants["maximal_bases"]).bases.uncovered(f.items for f in mining.topk(tx, 40))


def test_file_formats(spark, tiny, tmp_path):
    tx = VIEWS["order_brands"](spark, tiny)
    want = sorted(map(tuple, tx.item_counts().where("n > 0").collect()))
    files.write_lines(tx, str(tmp_path / "lines"))
    files.write_release(tx.rows, str(tmp_path / "json"), "json")
    files.write_release(tx.long(), str(tmp_path / "csv"), "csv")
    for got in (files.read_lines(spark, str(tmp_path / "lines")), files.read_json(spark, str(tmp_path / "json")), files.read_csv(spark, str(tmp_path / "csv"))):
        assert sorted(map(tuple, got.item_counts().collect())) == want
    with pytest.raises(ValueError):
        files.write_lines(Transactions.from_sets(spark, [{"a b"}]), str(tmp_path / "bad"))
