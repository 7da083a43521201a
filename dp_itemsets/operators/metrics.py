"""Measures of a release against the exact result."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.noise import NoiseSource
from ..sources.transactions import Transactions
from .bases import BasisSet
from .mining import Found, key_of, supports


def false_negative_rate(release: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(fnr): the true top-k sets that weren't published, over k."""
    return truth.join(release.select("itemset"), "itemset", "left_anti").agg((F.count("*") / F.lit(float(k))).alias("fnr"))


def false_positive_rate(release: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    return release.join(truth.select("itemset"), "itemset", "left_anti").agg((F.count("*") / F.lit(float(k))).alias("fpr"))


def relative_error_column(noisy: Column, true: Column) -> Column:
    """|noisy - true| / true; infinite where an unsupported set was published."""
    return F.when(true == 0, F.lit(math.inf)).otherwise(F.abs(noisy - true) / true)


def relative_error(release: DataFrame, exact: DataFrame) -> DataFrame:
    """(re, infinite_share): exact median over the published sets; exact: (itemset, freq) of those."""
    e = relative_error_column(F.col("noisy_freq"), F.col("freq"))
    return release.join(exact, "itemset").select(e.alias("e")).agg(F.percentile("e", F.lit(0.5)).alias("re"), F.avg((F.col("e") == math.inf).cast("double")).alias("infinite_share"))


def precision(release: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(precision): the published sets that are in the true top k, over k."""
    return release.join(truth.select("itemset"), "itemset", "left_semi").agg((F.count("*") / F.lit(float(k))).alias("precision"))


def measured(tx: Transactions, published: list[tuple[str, float]], truth: list[Found], k: int, tie_tolerant: bool = False) -> dict[str, float]:
    """``measured_with`` the exact supports of the published sets, counted here."""
    exact = {key_of(s): c for s, c in supports(tx, [tuple(s.split("|")) for s, _ in published]).items()} if published else {}
    return measured_with(exact, published, truth, k, tie_tolerant)


def measured_with(exact: dict[str, int], published: list[tuple[str, float]], truth: list[Found], k: int, tie_tolerant: bool = False) -> dict[str, float]:
    """FNR, FPR, precision, relative error and the share of infinite terms of a release that is already on the driver."""
    top = {key_of(f.items) for f in truth[:k]}
    keys = [s for s, _ in published]
    errors = sorted(math.inf if not (c := exact[s]) else abs(noisy - c) / c for s, noisy in published)
    half = len(errors) // 2
    median = math.nan if not errors else errors[half] if len(errors) % 2 else (errors[half - 1] + errors[half]) / 2
    if tie_tolerant:  # any set as frequent as the k-th is right
        least = truth[min(k, len(truth)) - 1].support if truth else 0
        fnr = 1 - min(sum(exact[s] >= least for s in keys), k) / k
    else:
        fnr = len(top - set(keys)) / k
    return {"fnr": fnr, "fpr": len(set(keys) - top) / k, "precision": len(top & set(keys)) / k, "re": median, "infinite_share": sum(map(math.isinf, errors)) / max(len(errors), 1)}


def coverage_miss_rate(bases: BasisSet, truth: list[Found], k: int) -> float:
    """True top-k sets that no basis covers, over k: the part of the FNR that isn't noise."""
    return len(bases.uncovered(f.items for f in truth[:k])) / k


def repeats(rows: DataFrame, config: list[str], value: str) -> DataFrame:
    """Mean and standard error over repeats."""
    return rows.groupBy(*config).agg(F.avg(value).alias("mean"), (F.stddev_samp(value) / F.sqrt(F.count("*"))).alias("std_error"), F.count("*").alias("runs"))


def cost_model(bases: BasisSet, total_length: int) -> dict[str, float]:
    """Operation counts of the four parts of bin counting."""
    w, l = bases.width, bases.length
    return {
        "init": sum(2 ** len(b) for b in bases), "scan": w * total_length,
        "superset_sums": sum(3 ** len(b) - 2 ** len(b) for b in bases), "halving": sum(len(b) * 2 ** len(b) for b in bases),
        "sort": w * l * math.log2(max(w, 2)) * 2**l,
    }


def empirical_l1_sensitivity(query: Callable[[Transactions], dict], tx: Transactions, tids: Iterable[object]) -> float:
    """Largest L1 change of a table of numbers when one of the given transactions goes; for small data."""
    whole, most = query(tx), 0.0
    for tid in tids:
        less = query(tx.without(tid))
        most = max(most, sum(abs(whole.get(k, 0) - less.get(k, 0)) for k in {*whole, *less}))
    return most


def empirical_variance(full: DataFrame, width: int, length: int, eps: float, runs: int, noise: NoiseSource) -> DataFrame:
    """(basis_id, mask, variance): of the noisy subset counts over ``runs`` draws of the noise of complete bins (basis_id, mask, n)."""
    noisy = full.crossJoin(full.sparkSession.range(runs).withColumnRenamed("id", "run")).withColumn("noisy", F.col("n") + noise.laplace("runs", width / eps, "run", "basis_id", "mask"))
    low = noisy.select(F.col("basis_id").alias("b"), F.col("mask").alias("y"), "run", "noisy")
    own = full.select("basis_id", "mask")
    inside = (F.col("b") == F.col("basis_id")) & (F.col("y").bitwiseAND(F.col("mask")) == F.col("mask"))
    sums = low.join(F.broadcast(own), inside).groupBy("basis_id", "mask", "run").agg(F.sum("noisy").alias("s"))
    return sums.groupBy("basis_id", "mask").agg(F.var_samp("s").alias("variance"))


def privacy_audit(release: Callable[[int, NoiseSource], float], counts: tuple[int, int], eps: float, runs: int, bins: int = 8) -> float:
    """Largest excess, in standard errors, of the log-ratio of two neighbours' output histograms over eps; about 4 or less if private."""
    draws = [[release(c, NoiseSource.fixed(f"audit-{k}")) for k in range(runs)] for c in counts]
    low, high = min(counts) - 5 / eps, max(counts) + 5 / eps
    step, worst = (high - low) / bins, -math.inf
    hist = [[sum(low + step * j <= min(max(x, low), high - 1e-9) < low + step * (j + 1) for x in d) for j in range(bins)] for d in draws]
    for a, b in zip(*hist, strict=True):
        worst = max(worst, (abs(math.log((a + 1) / (b + 1))) - eps) / math.sqrt(1 / (a + 1) + 1 / (b + 1)))
    return worst
