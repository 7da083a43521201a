"""Counts of all subsets of given bases, from noisy disjoint bins.

A basis of l items parts the transactions into 2^l bins.  All bases share one
scan: equal projections on the union of their items are collapsed, each
collapsed row gives its bin in every basis, and partial sums leave at most
w * 2^l rows a task.  Everything after the noise is post-processing of small
tables.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.noise import NoiseSource
from ..sources.transactions import Transactions
from .bases import BasisSet

#: Bins a basis may have, as a power of two.
LONGEST = 20


def bases_frame(tx_or_spark: object, bases: BasisSet) -> DataFrame:
    """(basis_id, pos, item)."""
    spark = tx_or_spark.spark if isinstance(tx_or_spark, Transactions) else tx_or_spark
    return spark.createDataFrame([(b, p, i) for b, items in enumerate(bases) for p, i in enumerate(items)], "basis_id int, pos int, item string")


def _length(basis: Column, bases: BasisSet) -> Column:
    return F.element_at(F.array(*[F.lit(len(b)) for b in bases]), basis + 1)


def bin_counts(tx: Transactions, bases: BasisSet) -> DataFrame:
    """(basis_id, mask, n): transactions by the part of each basis that they hold; empty bins are missing."""
    if bases.length > LONGEST:
        raise ValueError(f"a basis of more than {LONGEST} items has too many bins")
    pool = bases.items
    place = {i: k for k, i in enumerate(pool)}

    def mask(b: int, items: tuple[str, ...]) -> Column:
        bits = [F.when(F.array_contains("items", place[i]), F.lit(1 << p)).otherwise(F.lit(0)) for p, i in enumerate(items)]
        total = bits[0]
        for x in bits[1:]:
            total = total + x
        return F.struct(F.lit(b).alias("basis_id"), total.alias("mask"))

    masks = F.explode(F.array(*[mask(b, items) for b, items in enumerate(bases)])).alias("at")
    return tx.projected(pool).select(masks, "cnt").groupBy("at.basis_id", "at.mask").agg(F.sum("cnt").alias("n"))


def complete_bins(bins: DataFrame, bases: BasisSet) -> DataFrame:
    """All 2^l bins of each basis; noise must reach the empty ones too."""
    spark = bins.sparkSession
    ids = spark.createDataFrame([(b, (1 << len(items)) - 1) for b, items in enumerate(bases)], "basis_id int, top int")
    domain = ids.select("basis_id", F.explode(F.sequence(F.lit(0), "top")).alias("mask"))
    return domain.join(bins, ["basis_id", "mask"], "left").select("basis_id", "mask", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def noisy_bins(bins: DataFrame, width: int, eps: float, noise: NoiseSource, label: str = "bins") -> DataFrame:
    """Adds ``noisy``: one transaction moves one bin of every basis, hence Lap(width / eps)."""
    if not eps > 0:
        raise ValueError("a privacy budget must be above 0")
    if math.isinf(eps):
        return bins.withColumn("noisy", F.col("n").cast("double"))
    return bins.withColumn("noisy", F.col("n") + noise.laplace(label, width / eps, "basis_id", "mask"))


def _superset_join(bins: DataFrame, value: str) -> DataFrame:
    own = bins.select("basis_id", "mask")
    other = bins.select(F.col("basis_id").alias("b"), F.col("mask").alias("y"), F.col(value).alias("v"))
    inside = (F.col("basis_id") == F.col("b")) & (F.col("y").bitwiseAND(F.col("mask")) == F.col("mask"))
    return own.join(other, inside).groupBy("basis_id", "mask").agg(F.sum("v").alias("nc"))


def _superset_halving(bins: DataFrame, value: str, length: int) -> DataFrame:
    """One bit after the other: a bin that has the bit also counts without it."""
    out = bins.select("basis_id", "mask", F.col(value).alias("nc"))
    for p in range(length):
        bit = F.lit(1 << p)
        has = F.col("mask").bitwiseAND(bit) != 0
        targets = F.when(has, F.array("mask", F.col("mask") - bit)).otherwise(F.array("mask"))
        out = out.select("basis_id", F.explode(targets).alias("mask"), "nc").groupBy("basis_id", "mask").agg(F.sum("nc").alias("nc"))
    return out


def _superset_arrays(bins: DataFrame, value: str) -> DataFrame:
    """Each basis in one call: at most 2^l numbers, halved in place."""

    def total(group: pd.DataFrame) -> pd.DataFrame:
        size = 1 << max(int(group["mask"].max()).bit_length(), 0)
        sums = np.zeros(size)
        sums[group["mask"]] = group[value]
        step = 1
        while step < size:
            pairs = sums.reshape(-1, 2, step)
            pairs[:, 0] += pairs[:, 1]
            step *= 2
        return pd.DataFrame({"basis_id": group["basis_id"].iloc[0], "mask": np.arange(size, dtype=np.int32), "nc": sums})

    return bins.select("basis_id", "mask", value).groupBy("basis_id").applyInPandas(total, "basis_id int, mask int, nc double")


def superset_sums(bins: DataFrame, bases: BasisSet, strategy: str = "zeta", value: str = "noisy") -> DataFrame:
    """(basis_id, mask, nc): for each subset the sum of the bins that hold it; bins must be complete.

    ``join`` meets every bin with its subsets (3^l work), ``zeta`` halves bit by
    bit, ``pandas`` halves in numpy, one call a basis.
    """
    if strategy == "join":
        return _superset_join(bins, value)
    if strategy == "zeta":
        return _superset_halving(bins, value, bases.length)
    if strategy == "pandas":
        return _superset_arrays(bins, value)
    raise ValueError("the strategy is join, zeta or pandas")


def named_estimates(sums: DataFrame, bases: BasisSet) -> DataFrame:
    """(itemset, size, nc, v): masks spelled out, with the variance weight 2^(length - size)."""
    table = sums.sparkSession.createDataFrame([(b, list(items)) for b, items in enumerate(bases)], "basis_id int, names array<string>")
    names = F.filter("names", lambda x, p: F.col("mask").bitwiseAND(F.call_function("shiftleft", F.lit(1), p)) != 0)
    size = F.bit_count("mask").cast("int")
    return sums.join(F.broadcast(table), "basis_id").select(F.array_join(F.sort_array(names), "|").alias("itemset"), size.alias("size"), "nc", F.pow(F.lit(2.0), F.size("names") - size).alias("v"))


def fuse(estimates: DataFrame) -> DataFrame:
    """One row per itemset: its estimates weighted by inverse variance, in any order."""
    weight = F.sum(1 / F.col("v"))
    return estimates.groupBy("itemset", "size").agg((F.sum(F.col("nc") / F.col("v")) / weight).alias("nc"), (1 / weight).alias("v"))


def fuse_pairwise(estimates: DataFrame) -> DataFrame:
    """The same by folding pairs of estimates, as a grouped pandas function: the twin that tests compare with."""

    def fold(groups: Iterator[pd.DataFrame] | pd.DataFrame) -> pd.DataFrame:
        nc, v = float(groups["nc"].iloc[0]), float(groups["v"].iloc[0])
        for other, weight in zip(groups["nc"].iloc[1:], groups["v"].iloc[1:], strict=True):
            nc, v = (nc * weight + other * v) / (v + weight), v * weight / (v + weight)
        return pd.DataFrame({"itemset": [groups["itemset"].iloc[0]], "size": [groups["size"].iloc[0]], "nc": [nc], "v": [v]})

    return estimates.groupBy("itemset").applyInPandas(fold, "itemset string, size int, nc double, v double")


def basis_estimates(tx: Transactions, bases: BasisSet, eps: float, noise: NoiseSource, strategy: str = "zeta") -> DataFrame:
    """(itemset, size, nc, v) of all candidates, the empty set among them."""
    noisy = noisy_bins(complete_bins(bin_counts(tx, bases), bases), bases.width, eps, noise)
    return fuse(named_estimates(superset_sums(noisy, bases, strategy), bases))


def count_with_bases(tx: Transactions, bases: BasisSet, k: int, eps: float, noise: NoiseSource, n: int | None = None, strategy: str = "zeta") -> DataFrame:
    """The k largest noisy counts: (itemset, size, noisy_count, noisy_freq, variance).

    Frequencies are over ``n``; without one, over the noisy count of the empty
    set, which is a free private estimate of the number of transactions.  The
    empty set isn't published.
    """
    fused = basis_estimates(tx, bases, eps, noise, strategy)
    scale = 0.0 if math.isinf(eps) else 2 * (bases.width / eps) ** 2
    columns = ["itemset", "size", F.round("nc", 6).alias("noisy_count")]
    if n is not None:
        counted = fused.withColumn("_n", F.lit(float(n)))
    else:
        everyone = fused.where("size = 0").select(F.greatest(F.col("nc"), F.lit(1.0)).alias("_n"))
        counted = fused.crossJoin(F.broadcast(everyone))
    return (
        counted.where("size > 0").orderBy(F.desc(F.round("nc", 6)), "size", "itemset").limit(k)
        .select(*columns, F.round(F.col("nc") / F.col("_n"), 9).alias("noisy_freq"), F.round(F.col("v") * F.lit(scale), 6).alias("variance"))
    )
