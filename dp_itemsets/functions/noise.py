"""Keyed noise.

A draw is a function of (seed, label, key): a retried or re-planned task makes
the same draw again, so a statistic is never published with two noises.  The
uniform comes from the first 52 bits of a SHA-256, which any SQL engine can
repeat.  Labels differ between the steps of a release, which makes their draws
independent.
"""

from __future__ import annotations

import hashlib
import math
import secrets
from dataclasses import dataclass

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

#: Hex digits of the hash that are used, and the number of values they have.
DIGITS = 13
STEPS = float(1 << 52)


def uniform_of(text: Column) -> Column:
    """Uniform in (0, 1) from a key text."""
    return (F.conv(F.substring(F.sha2(text, 256), 1, DIGITS), 16, 10).cast("double") + F.lit(0.5)) / F.lit(STEPS)


def laplace_from(u: Column, scale: Column | float) -> Column:
    """Inverse distribution function of Lap(scale)."""
    scale = F.lit(float(scale)) if isinstance(scale, int | float) else scale
    return -scale * F.signum(u - 0.5) * F.log(1 - 2 * F.abs(u - 0.5))


def gumbel_from(u: Column) -> Column:
    return -F.log(-F.log(u))


@dataclass(frozen=True)
class NoiseSource:
    """Draws for one release.  A published seed voids the privacy of what was released with it."""

    seed: str

    @classmethod
    def secret(cls) -> NoiseSource:
        return cls(secrets.token_hex(32))

    @classmethod
    def fixed(cls, seed: int | str) -> NoiseSource:
        return cls(str(seed))

    def uniform(self, label: str, *key: Column | str) -> Column:
        cols = [F.col(c) if isinstance(c, str) else c for c in key]
        return uniform_of(F.concat_ws(":", F.lit(self.seed), F.lit(label), *[c.cast("string") for c in cols]))

    def laplace(self, label: str, scale: Column | float, *key: Column | str) -> Column:
        return laplace_from(self.uniform(label, *key), scale)

    def gumbel(self, label: str, *key: Column | str) -> Column:
        return gumbel_from(self.uniform(label, *key))

    def uniform_value(self, label: str, *key: object) -> float:
        """The same draw on the driver."""
        text = ":".join([self.seed, label, *map(str, key)])
        return (int(hashlib.sha256(text.encode()).hexdigest()[:DIGITS], 16) + 0.5) / STEPS

    def laplace_value(self, label: str, scale: float, *key: object) -> float:
        u = self.uniform_value(label, *key)
        return -scale * math.copysign(1.0, u - 0.5) * math.log(1 - 2 * abs(u - 0.5))

    def gumbel_value(self, label: str, *key: object) -> float:
        return -math.log(-math.log(self.uniform_value(label, *key)))


def register_sql(spark: SparkSession) -> None:
    """keyed_uniform, laplace, gumbel and variance_weight as temporary SQL functions."""
    u = f"((CAST(conv(substring(sha2(k, 256), 1, {DIGITS}), 16, 10) AS DOUBLE) + 0.5D) / {STEPS:.1f}D)"
    for head, body in (
        ("keyed_uniform(k STRING) RETURNS DOUBLE", u),
        ("laplace(k STRING, b DOUBLE) RETURNS DOUBLE", f"-b * signum({u} - 0.5D) * ln(1 - 2 * abs({u} - 0.5D))"),
        ("gumbel(k STRING) RETURNS DOUBLE", f"-ln(-ln({u}))"),
        ("variance_weight(len INT, size INT) RETURNS DOUBLE", "pow(2.0D, len - size)"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
