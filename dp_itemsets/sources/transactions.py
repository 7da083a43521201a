"""Transactions: one row each, with the sorted distinct items as an array.

In this form a projection, a mask or a count of items needs no shuffle; only
views whose transactions span many rows of a table group by the transaction
once.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass
class Transactions:
    """rows: (tid, items array<string>); universe: (item), the public domain, or None for what is observed."""

    rows: DataFrame
    universe: DataFrame | None = None
    unit: str = "transaction"
    _kept: dict | None = field(default=None, repr=False)

    @property
    def spark(self) -> SparkSession:
        return self.rows.sparkSession

    @classmethod
    def from_long(cls, df: DataFrame, tid: str = "tid", item: str = "item", universe: DataFrame | None = None, unit: str = "transaction") -> Transactions:
        """From (tid, item) rows; repeated items count once, null items not at all."""
        grouped = df.groupBy(F.col(tid).alias("tid")).agg(F.sort_array(F.collect_set(F.col(item))).alias("items"))
        return cls(grouped, universe, unit)

    @classmethod
    def from_sets(cls, spark: SparkSession, sets: Iterable[Iterable[str]], universe: Iterable[str] | None = None) -> Transactions:
        rows = [(k, sorted(set(s))) for k, s in enumerate(sets)]
        domain = None if universe is None else spark.createDataFrame([(u,) for u in universe], "item string")
        return cls(spark.createDataFrame(rows, "tid long, items array<string>"), domain)

    def need_domain(self, observed_domain: bool) -> None:
        """A private draw is from a public domain; items that merely occur are one only if the caller vouches for that."""
        if self.universe is None and not observed_domain:
            raise ValueError("these transactions have no public domain of items: give a universe, or accept the observed items as public with observed_domain")

    @contextmanager
    def remembering(self) -> Iterator[Transactions]:
        """The same transactions, whose item counts, number and projections are computed once and kept until the end.

        What is kept are counts by item and collapsed projections, never the
        transactions themselves.
        """
        if self._kept is not None:
            yield self
            return
        own = Transactions(self.rows, self.universe, self.unit, {})
        try:
            yield own
        finally:
            for df in own._kept.values():
                if isinstance(df, DataFrame):
                    df.unpersist()
                elif hasattr(df, "close"):
                    df.close()

    def _once(self, key: object, make: Callable[[], DataFrame]) -> DataFrame:
        if self._kept is None:
            return make()
        if key not in self._kept:
            self._kept[key] = make().persist()
        return self._kept[key]

    def kept(self, key: object, make: Callable[[], Any]) -> Any:
        """A small driver value, made once while remembering."""
        if self._kept is None:
            return make()
        if key not in self._kept:
            self._kept[key] = make()
        return self._kept[key]

    def kept_anew(self, key: object, value: Any) -> Any:
        """Replaces a kept value while remembering."""
        if self._kept is not None:
            self._kept[key] = value
        return value

    def size(self) -> int:
        if self._kept is None:
            return self.rows.count()
        return self.kept("n", lambda: (self._tally().where("item is null").first() or {"n": 0})["n"])

    def _tally(self) -> DataFrame:
        """(item, n): supports, and the number of transactions under a null item, in one pass."""
        marked = F.array_append("items", F.lit(None).cast("string"))
        return self._once("tally", lambda: self.rows.select(F.explode(marked).alias("item")).groupBy("item").agg(F.count("*").alias("n")))

    def long(self) -> DataFrame:
        return self.rows.select("tid", F.explode("items").alias("item"))

    def cached(self) -> Transactions:
        """Keeps (tid, items) where it fits; what doesn't is computed again."""
        return Transactions(self.rows.persist(), self.universe, self.unit)

    def without(self, tid: object) -> Transactions:
        """The neighbour that lacks one transaction."""
        return Transactions(self.rows.where(~F.col("tid").eqNullSafe(F.lit(tid))), self.universe, self.unit)

    def plus(self, items: Iterable[str], tid: object = -1) -> Transactions:
        """The neighbour that has one transaction more."""
        kind = self.rows.schema["tid"].dataType.simpleString()
        one = self.spark.createDataFrame([(tid, sorted(set(items)))], f"tid {kind}, items array<string>")
        return Transactions(self.rows.unionByName(one), self.universe, self.unit)

    def item_counts(self) -> DataFrame:
        """(item, n) over the universe where one is given, zero supports included."""
        counts = self._tally().where("item is not null")
        if self.universe is None:
            return counts
        return self.universe.select("item").distinct().join(counts, "item", "left").select("item", F.coalesce("n", F.lit(0)).alias("n"))

    def projected(self, items: list[str]) -> DataFrame:
        """(items array<int> of places in ``items``, cnt): equal projections as one row; empty ones stay.

        Only items of the list get past the scan, and equal projections are
        summed before the shuffle.
        """
        return self._once(tuple(items), lambda: self._projected(items))

    def _projected(self, items: list[str]) -> DataFrame:
        if not items:
            return self.rows.select(F.array().cast("array<int>").alias("items")).groupBy("items").agg(F.count("*").alias("cnt"))
        places = F.create_map(*[x for k, i in enumerate(items) for x in (F.lit(i), F.lit(k))])
        kept = F.array_intersect(F.col("items"), F.array(*[F.lit(i) for i in items]))
        return (
            self.rows.select(kept.alias("kept")).groupBy("kept").agg(F.count("*").alias("cnt"))
            .select(F.sort_array(F.transform("kept", lambda x: places[x])).alias("items"), "cnt")
        )
