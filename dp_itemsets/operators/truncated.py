"""The truncated-frequency baseline, and the direct and exhaustive ones.

Itemsets of at most m items whose frequency exceeds a floor are explicit rows.
All others share the floor's frequency; of them only the largest noises matter,
and those are drawn as order statistics instead of one by one, so a candidate
space of any size costs k draws.
"""

from __future__ import annotations

import math
from bisect import bisect_right
from collections.abc import Collection, Iterable, Iterator, Sequence
from itertools import accumulate, combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.mechanisms import laplace_release
from ..functions.noise import NoiseSource
from ..sources.transactions import Transactions
from . import mining
from .mining import Found, Itemset, key_of

#: Supported sets that may be listed when the floor prunes nothing.
MOST_EXPLICIT = 2_000_000
#: Names of items that the driver lists; of more it asks for those that it needs.
MOST_NAMES = 20_000


def candidate_space(n_items: int, m: int, exact: bool = False) -> int:
    """Itemsets of at most (or exactly) m of n items."""
    return math.comb(n_items, m) if exact else sum(math.comb(n_items, i) for i in range(1, m + 1))


def truncation_margin(k: int, eps: float, n: int, rho: float, space: int) -> float:
    """How far below the k-th frequency an itemset may be before it is lumped with the rest."""
    if not 0 < rho < 1:
        raise ValueError("rho must lie between 0 and 1")
    return 4 * k / (eps * n) * (math.log(k / rho) + math.log(space))


def truncation_margin_lower(k: int, m: int, eps: float, n: int, n_items: int) -> float:
    return 4 * k * m * math.log(n_items) / (eps * n)


def is_effective(margin: float, f_k: float) -> bool:
    """Does the margin leave anything to prune?"""
    return margin < f_k


def _universe(tx: Transactions) -> list[str]:
    """Items that candidates are made of, by name."""
    return [r["item"] for r in _items(tx).select("item").orderBy("item").collect()]


def _items(tx: Transactions) -> DataFrame:
    return tx.item_counts() if tx.universe is not None else tx.item_counts().where("n > 0")


class Names(Sequence):
    """Items that candidates are made of, by name: a list of them, or of many only how many there are and those that are asked for."""

    def __init__(self, tx: Transactions):
        rows = _items(tx).select("item")
        self.rows, self.listed, self.starts = None, None, [0]
        if rows.limit(MOST_NAMES + 1).count() <= MOST_NAMES:
            self.listed = [r["item"] for r in rows.orderBy("item").collect()]
            return
        # the number of a partition, then the place in it
        self.rows = rows.orderBy("item").select("item", F.monotonically_increasing_id().alias("id")).persist()
        sizes = {r["p"]: r["n"] for r in self.rows.groupBy(F.shiftright("id", 33).alias("p")).agg(F.count("*").alias("n")).collect()}
        self.starts = [0, *accumulate(sizes.get(p, 0) for p in range(max(sizes) + 1))]

    def __len__(self) -> int:
        return len(self.listed) if self.rows is None else self.starts[-1]

    def __getitem__(self, k: int) -> str:
        return self.some([k])[k]

    def some(self, places: Iterable[int]) -> dict[int, str]:
        """The items at given places."""
        if self.rows is None:
            return {k: self.listed[k] for k in places}
        at = {}
        for k in places:
            p = bisect_right(self.starts, k) - 1
            at[(p << 33) + k - self.starts[p]] = k
        wanted = self.rows.sparkSession.createDataFrame([(i,) for i in at], "id long")
        return {at[r["id"]]: r["item"] for r in self.rows.join(F.broadcast(wanted), "id").collect()}

    def close(self) -> None:
        if self.rows is not None:
            self.rows.unpersist()


def explicit_itemsets(tx: Transactions, m: int, floor_count: float, exactly: bool = False) -> list[Found]:
    """All sets of at most m items with a support above the floor, and above 0."""
    least = max(1, math.floor(floor_count) + 1)
    if least == 1 and m > 1:
        n_sets = tx.rows.agg(F.sum(sum((_choose(F.size("items"), i) for i in range(2, m + 1)), F.size("items").cast("double")))).first()[0] or 0
        n_sets = min(n_sets, candidate_space(tx.item_counts().where("n > 0").count(), m))
        if n_sets > MOST_EXPLICIT:
            raise mining.TooManySets(f"the floor is at or below 0: up to {n_sets:.3g} supported sets would be listed")
    known, found = tx.kept(("explicit", m), lambda: (least, mining.apriori(tx, least, m)))
    if known > least:  # a lower floor lists what a higher one does
        known, found = tx.kept_anew(("explicit", m), (least, mining.apriori(tx, least, m)))
    return [f for f in found if f.support >= least and (not exactly or len(f.items) == m)]


def _choose(n, i: int):
    out = F.lit(1.0)
    for j in range(i):
        out = out * F.greatest(n - j, F.lit(0)) / (j + 1)
    return out


def implicit_scores(count: int, value: float, k: int, beat: float, noise: NoiseSource, label: str, gumbel: bool, scale: float) -> list[float]:
    """The largest scores of ``count`` candidates that share one value, highest first, while they exceed ``beat``; k at most.

    Descending uniforms follow from powers of independent ones, kept as
    logarithms because count may be astronomically large.
    """
    out: list[float] = []
    log_u = 0.0
    for j in range(min(k, count)):
        log_u += math.log(noise.uniform_value(label, "tail", j)) / (count - j)
        if gumbel:
            draw = -math.log(max(-log_u, 5e-324))
            score = value + draw
        else:
            u = math.exp(log_u)
            rest = -math.expm1(log_u)  # 1 - u, exact near 1
            draw = -scale * math.log(2 * max(rest, 5e-324)) if u > 0.5 else scale * math.log(2 * max(u, 5e-324))
            score = value + draw
        if score <= beat:
            break
        out.append(score)
    return out


def implicit_members(universe: Sequence[str], m: int, listed: Collection[str], how_many: int, noise: NoiseSource, label: str, exactly: bool = False) -> list[Itemset]:
    """Different unlisted sets of at most m items, uniformly."""
    sizes = [m] if exactly else list(range(1, m + 1))
    weights = [math.comb(len(universe), i) for i in sizes]
    if not how_many:
        return []
    if sum(weights) - len(listed) <= max(64, 4 * how_many):  # nearly all are listed: rejection would be slow
        rest = [c for i in sizes for c in combinations(universe, i) if key_of(c) not in listed]
        return sorted(rest, key=lambda c: noise.uniform_value(label, "member", key_of(c)))[:how_many]
    out: dict[str, Itemset] = {}
    trial = 0
    while len(out) < how_many:
        drawn = [_trial(len(universe), sizes, weights, trial + k, noise, label) for k in range(2 * (how_many - len(out)))]
        trial += len(drawn)
        names = universe.some({x for d in drawn for x in d}) if isinstance(universe, Names) else universe
        sets = [tuple(names[x] for x in d) for d in drawn]
        known = listed.among([key_of(s) for s in sets]) if isinstance(listed, Wide) else listed
        for chosen in sets:
            key = key_of(chosen)
            if key not in known and key not in out and len(out) < how_many:
                out[key] = tuple(sorted(chosen))
    return list(out.values())


def _trial(n_items: int, sizes: list[int], weights: list[int], trial: int, noise: NoiseSource, label: str) -> list[int]:
    """The places of one uniformly drawn set."""
    u, i = noise.uniform_value(label, "size", trial) * sum(weights), 0
    while u > weights[i] and i < len(weights) - 1:
        u -= weights[i]
        i += 1
    chosen: list[int] = []
    step = 0
    while len(chosen) < sizes[i]:
        item = int(noise.uniform_value(label, "item", trial, step) * n_items)
        step += 1
        if item not in chosen:
            chosen.append(item)
    return chosen


class Wide(Collection):
    """The items above a floor where they are too many to list: they stay where they are."""

    def __init__(self, tx: Transactions, least: int):
        self.rows, self.items = tx.item_counts().where(F.col("n") >= least), _items(tx).where(F.col("n") < least)
        self.size = self.rows.count()

    def __len__(self) -> int:
        return self.size

    def __iter__(self) -> Iterator[str]:
        return (r["item"] for r in self.rows.select("item").toLocalIterator())

    def __contains__(self, item: object) -> bool:
        return bool(self.among([item]))

    def among(self, keys: list[str]) -> set[str]:
        """Those of the given items that are above the floor."""
        wanted = self.rows.sparkSession.createDataFrame([(k,) for k in dict.fromkeys(keys)], "item string")
        return {r["item"] for r in self.rows.join(F.broadcast(wanted), "item").select("item").collect()}

    def others(self) -> list[Itemset]:
        """The items that aren't above it."""
        return [(r["item"],) for r in self.items.select("item").orderBy("item").collect()]

    def best(self, score: Column, k: int) -> list[tuple[float, str, Itemset]]:
        """(score, key, set) of the k highest scores."""
        rows = self.rows.select(F.round(score, 9).alias("score"), "item").orderBy(F.desc("score"), "item").limit(k).collect()
        return [(r["score"], r["item"], (r["item"],)) for r in rows]


def select(tx: Transactions, k: int, m: int, eps: float, noise: NoiseSource, rho: float = 0.9, selector: str = "exponential", exactly: bool = False, observed_domain: bool = False) -> list[Itemset]:
    """k itemsets at half the budget, by noisy truncated frequencies or by k exponential draws."""
    if selector not in ("exponential", "laplace"):
        raise ValueError("the selector is exponential or laplace")
    tx.need_domain(observed_domain)
    with tx.remembering() as own:
        return _select(own, k, m, eps, noise, rho, selector, exactly)


def _select(tx: Transactions, k: int, m: int, eps: float, noise: NoiseSource, rho: float, selector: str, exactly: bool) -> list[Itemset]:
    n, universe = tx.size(), tx.kept("names", lambda: Names(tx))
    space = candidate_space(len(universe), m, exactly)
    k = min(k, space)
    best = mining.topk_of_size(tx, k, m) if exactly else mining.topk(tx, k, m)
    c_k = best[k - 1].support if len(best) >= k else 0
    floor = c_k - truncation_margin(k, eps, n, rho, space) * n
    value, gumbel, scale = max(floor, 0.0), selector == "exponential", 4 * k / eps
    label = f"select-{selector}"

    def score(f: Found) -> float:
        count = max(float(f.support), value)
        key = key_of(f.items)
        return count / scale + noise.gumbel_value(label, key) if gumbel else count + noise.laplace_value(label, scale, key)

    if m == 1 and universe.rows is not None:
        listed = Wide(tx, max(1, math.floor(floor) + 1))
        count = F.greatest(F.col("n").cast("double"), F.lit(value))
        scored = listed.best(count / F.lit(float(scale)) + noise.gumbel(label, "item") if gumbel else count + noise.laplace(label, float(scale), "item"), k)
    else:
        explicit = explicit_itemsets(tx, m, floor, exactly)
        listed = {key_of(f.items) for f in explicit}
        scored = sorted(((round(score(f), 9), key_of(f.items), f.items) for f in explicit), key=lambda s: (-s[0], s[1]))[:k]
    beat = scored[k - 1][0] if len(scored) >= k else -math.inf
    tail = implicit_scores(space - len(listed), value / scale if gumbel else value, k, beat, noise, label, gumbel, scale)
    if isinstance(listed, Wide) and space - len(listed) <= max(64, 4 * len(tail)):
        members = sorted(listed.others(), key=lambda c: noise.uniform_value(label, "member", key_of(c)))[: len(tail)] if tail else []
    else:
        members = implicit_members(universe, m, listed, len(tail), noise, label, exactly)
    mixed = [(s, 0, items) for s, _, items in scored] + [(s, 1, items) for s, items in zip(tail, members, strict=False)]
    return [items for _, _, items in sorted(mixed, key=lambda x: (-x[0], x[1]))[:k]]


def release_selected(tx: Transactions, sets: list[Itemset], eps: float, noise: NoiseSource, label: str, share: float = 0.5) -> DataFrame:
    """(itemset, size, noisy_count, noisy_freq): one transaction moves each of k counts by 1 at most, hence Lap(k / (share * eps))."""
    n, spark = tx.size(), tx.spark
    counts = mining.supports(tx, sets)
    rows = spark.createDataFrame([(key_of(s), len(s), counts[s]) for s in sets], "itemset string, size int, support long")
    noisy = laplace_release(rows, "support", float(len(sets)), eps * share, ["itemset"], noise, label)
    return noisy.select("itemset", "size", F.round("noisy", 6).alias("noisy_count"), F.round(F.col("noisy") / F.lit(float(max(n, 1))), 9).alias("noisy_freq"))


def truncated_release(tx: Transactions, k: int, m: int, eps: float, noise: NoiseSource, rho: float = 0.9, selector: str = "exponential", exactly: bool = False, observed_domain: bool = False) -> DataFrame:
    """The whole baseline: half the budget to select, half to count."""
    with tx.remembering() as own:
        return release_selected(own, select(own, k, m, eps, noise, rho, selector, exactly, observed_domain), eps, noise, "truncated")


def direct_release(tx: Transactions, sets: list[Itemset], eps: float, noise: NoiseSource) -> DataFrame:
    """Counts of given itemsets, one Laplace draw each at sensitivity k."""
    return release_selected(tx, sets, eps, noise, "direct", 1.0)


def enumerated(tx: Transactions, m: int) -> DataFrame:
    """(itemset, size, support) of every candidate, the unsupported too; for small universes."""
    universe = _universe(tx)
    if candidate_space(len(universe), m) > 100_000:
        raise ValueError("too many candidates to list")
    sets = [c for i in range(1, m + 1) for c in combinations(universe, i)]
    counts = mining.supports(tx, sets)
    return tx.spark.createDataFrame([(key_of(s), len(s), counts[s]) for s in sets], "itemset string, size int, support long")


def truncated_counts(tx: Transactions, k: int, m: int, eps: float, rho: float = 0.9) -> DataFrame:
    """enumerated() with ``truncated``: the larger of a support and the floor."""
    rows, n = enumerated(tx, m), tx.size()
    best = mining.topk(tx, k, m)
    floor = (best[k - 1].support if len(best) >= k else 0) - truncation_margin(k, eps, n, rho, candidate_space(len(_universe(tx)), m)) * n
    return rows.withColumn("truncated", F.greatest(F.col("support").cast("double"), F.lit(floor)))


def exhaustive_select(rows: DataFrame, value: str, k: int, eps: float, noise: NoiseSource, label: str, selector: str = "exponential") -> DataFrame:
    """The same selection with every candidate listed: the reference of the sampled tail."""
    scale = 4 * k / eps
    score = F.col(value) / F.lit(scale) + noise.gumbel(label, "itemset") if selector == "exponential" else F.col(value) + noise.laplace(label, scale, "itemset")
    return rows.withColumn("score", F.round(score, 9)).orderBy(F.desc("score"), "itemset").limit(k)


def guarantee_violations(released: list[Itemset], truth: dict[str, float], f_k: float, margin: float) -> tuple[int, int]:
    """Missed sets of frequency f_k + margin or more, and chosen sets below f_k - margin."""
    chosen = {key_of(s) for s in released}
    missed = sum(f >= f_k + margin and key not in chosen for key, f in truth.items())
    return missed, sum(truth.get(key, 0.0) < f_k - margin for key in chosen)
