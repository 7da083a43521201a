"""Laplace and exponential mechanisms on DataFrames.

An exponential draw is the largest of (scaled quality + Gumbel noise), and c
draws without replacement at equal budget are the c largest of one such
ordering.  Weights are never exponentiated, so no quality is too large.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .noise import NoiseSource


def _positive(eps: float) -> None:
    if not eps > 0:
        raise ValueError("a privacy budget must be above 0")


def laplace_release(df: DataFrame, value: str, sensitivity: float, eps: float, key: list[str], noise: NoiseSource, label: str = "laplace") -> DataFrame:
    """Adds ``noisy``: the value plus Lap(sensitivity / eps).  An infinite budget adds nothing."""
    _positive(eps)
    if math.isinf(eps):
        return df.withColumn("noisy", F.col(value).cast("double"))
    return df.withColumn("noisy", F.col(value) + noise.laplace(label, sensitivity / eps, *key))


def exponential_scores(df: DataFrame, quality: Column, eps: float, key: list[str], noise: NoiseSource, label: str, sensitivity: float = 1.0, one_sided: bool = False) -> DataFrame:
    """Adds ``score``.  one_sided: quality moves in one direction only between neighbours, which saves a factor of two."""
    _positive(eps)
    if math.isinf(eps):
        return df.withColumn("score", quality.cast("double"))
    scale = eps / (sensitivity * (1 if one_sided else 2))
    return df.withColumn("score", F.round(quality * F.lit(scale) + noise.gumbel(label, *key), 9))


def exponential_sample(df: DataFrame, quality: Column, eps: float, c: int, key: list[str], noise: NoiseSource, label: str, sensitivity: float = 1.0, one_sided: bool = False) -> DataFrame:
    """c draws without replacement of eps / c each; ``score`` orders them."""
    scored = exponential_scores(df, quality, eps / max(c, 1), key, noise, label, sensitivity, one_sided)
    return scored.orderBy(F.desc("score"), *key).limit(c)


def exponential_draw(df: DataFrame, quality: Column, eps: float, key: list[str], noise: NoiseSource, label: str, sensitivity: float = 1.0, one_sided: bool = False) -> DataFrame:
    return exponential_sample(df, quality, eps, 1, key, noise, label, sensitivity, one_sided)


def exponential_probabilities(df: DataFrame, quality: Column, eps: float, sensitivity: float = 1.0, one_sided: bool = False) -> DataFrame:
    """Adds ``probability`` of one draw, by log-sum-exp."""
    scaled = df.withColumn("_x", (quality * F.lit(eps / (sensitivity * (1 if one_sided else 2)))).cast("double"))
    top = scaled.agg(F.max("_x").alias("_top"))
    shifted = scaled.crossJoin(F.broadcast(top)).withColumn("_w", F.exp(F.col("_x") - F.col("_top")))
    total = shifted.agg(F.sum("_w").alias("_all"))
    return shifted.crossJoin(F.broadcast(total)).withColumn("probability", F.col("_w") / F.col("_all")).drop("_x", "_top", "_w", "_all")


def sequential_sample(weights: np.ndarray, c: int, draw: np.random.Generator) -> list[int]:
    """The definition: c successive draws, each in proportion to the log-weights left."""
    left, out = list(range(len(weights))), []
    for _ in range(min(c, len(left))):
        w = np.exp(weights[left] - weights[left].max())
        pick = int(draw.choice(len(left), p=w / w.sum()))
        out.append(left.pop(pick))
    return out
