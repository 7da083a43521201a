"""The private top-k release: rank, items, pairs, bases, bins.

Stages that touch the data: item counts (one scan), the exact support of the
target rank (one projection on a small pool), pair counts inside the drawn
items, and the bins.  Only private outputs, or the few numbers the mechanisms
need, reach the driver.
"""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.budget import ALPHAS, BudgetLedger, pairs_to_request, split_budget
from ..functions.mechanisms import exponential_draw, exponential_sample
from ..functions.noise import NoiseSource
from ..operators import mining
from ..operators.bases import BasisSet, build_bases
from ..operators.bins import count_with_bases
from ..sources.transactions import Transactions


@dataclass(frozen=True)
class ReleaseParams:
    """Knobs of the release; the defaults are those of the method, the rest are for ablations."""

    alphas: tuple[float, float, float] = ALPHAS
    eta: float = 1.2
    single_basis_limit: int = 12
    max_basis_len: int = 12
    rank_domain: str = "topk"
    pair_rule: str = "root"
    quality_scale: str = "count"
    objective: str = "items_and_pairs"
    merge: bool = True
    dissolve: bool = True
    n_mode: str = "public"
    superset_strategy: str = "zeta"
    true_rank: bool = False
    true_elements: bool = False
    maximal_bases: bool = False
    #: Without a universe a release is refused, unless the items that occur are accepted as public.
    observed_domain: bool = False

    def __post_init__(self) -> None:
        if self.eta < 1 or self.single_basis_limit < 1 or self.max_basis_len < 2:
            raise ValueError("eta must be at least 1, and bases of 2 items or more be allowed")
        if self.rank_domain not in ("topk", "all_items") or self.n_mode not in ("public", "noisy") or self.quality_scale not in ("count", "frequency"):
            raise ValueError("unknown option")


@dataclass
class Release:
    """itemsets: (itemset, size, noisy_count, noisy_freq, variance), and how they came about; seconds: what each step took."""

    itemsets: DataFrame
    ledger: BudgetLedger
    lam: int
    items: list[str]
    pairs: list[tuple[str, str]]
    bases: BasisSet
    params: ReleaseParams
    seconds: dict[str, float] = field(default_factory=dict)

    def ranked(self) -> list[tuple[str, float]]:
        return [(r["itemset"], r["noisy_count"]) for r in self.itemsets.orderBy(F.desc("noisy_count"), "size", "itemset").collect()]

    def report(self, spark: SparkSession) -> DataFrame:
        """What each step spent; outputs that follow from released ones alone spend nothing."""
        return self.ledger.report(spark)

    def timings(self, spark: SparkSession) -> DataFrame:
        """(step, seconds): the rank, the items, the pairs, and bases with bins."""
        return spark.createDataFrame(list(self.seconds.items()), "step string, seconds double")


def item_ranks(tx: Transactions, count: int | None) -> DataFrame:
    """(j, n): supports by rank.  With a count, of the top of them only: small, so ranking them in one task is cheap."""
    counts = tx.item_counts()
    if count is not None:
        rows = counts.orderBy(F.desc("n"), "item").limit(count).collect()
        return tx.spark.createDataFrame([(j, r["n"]) for j, r in enumerate(rows, 1)] or [(1, 0)], "j int, n long")
    # all ranks, without one window over all items: equal supports are summed, then numbered
    sizes = counts.groupBy("n").agg(F.count("*").alias("m")).collect()
    rows, j = [], 1
    for r in sorted(sizes, key=lambda r: -r["n"]):
        rows.append((j, j + r["m"] - 1, r["n"]))
        j += r["m"]
    ranks = tx.spark.createDataFrame(rows or [(1, 1, 0)], "low int, high int, n long")  # a row for each distinct support
    return ranks.select(F.explode(F.sequence("low", "high")).alias("j"), "n")


def rank_scores(tx: Transactions, k: int, eta: float, rank_domain: str = "topk") -> DataFrame:
    """(j, n, quality): minus the distance of the j-th item's support from that of the target itemset.

    Without the constant number of transactions the quality moves by 1 at most.
    """
    target = math.ceil(k * eta - 1e-9)
    found = mining.topk(tx, target)
    theta = found[target - 1].support if len(found) >= target else 0
    ranks = item_ranks(tx, target if rank_domain == "topk" else None)
    return ranks.withColumn("quality", -F.abs(F.col("n") - F.lit(theta)))


def estimate_item_rank(tx: Transactions, k: int, eps: float, eta: float, noise: NoiseSource, rank_domain: str = "topk") -> int:
    """A private draw of how many items the top k has.  Quality may rise for one rank and fall for another: the two-sided factor stays."""
    scored = rank_scores(tx, k, eta, rank_domain)
    return int(exponential_draw(scored, F.col("quality"), eps, ["j"], noise, "rank").first()["j"])


def pick_elements(counts: DataFrame, value: str, c: int, eps: float, key: list[str], noise: NoiseSource, label: str, quality_scale: str = "count", n: int | None = None) -> DataFrame:
    """c private draws without replacement of the most frequent elements.

    Counts move in one direction between neighbours and by 1 at most.
    """
    quality = F.col(value).cast("double") if quality_scale == "count" else F.col(value) / F.lit(float(n or 1))
    return exponential_sample(counts, quality, eps, c, key, noise, label, one_sided=True)


def release_topk_private(tx: Transactions, k: int, eps: float, noise: NoiseSource, params: ReleaseParams | None = None) -> Release:
    """The k itemsets with the highest noisy counts, under eps-differential privacy for one transaction.

    Three passes read the transactions: item counts (and their number), the
    projection that finds the target rank, and the projection on the drawn
    items, which serves both the pairs and the bins.
    """
    if k < 1 or not eps > 0:
        raise ValueError("k and the budget must be above 0")
    params = params or ReleaseParams()
    if not math.isinf(eps):
        tx.need_domain(params.observed_domain)
    with tx.remembering() as own:
        return _release(own, k, eps, noise, params)


def _release(tx: Transactions, k: int, eps: float, noise: NoiseSource, p: ReleaseParams) -> Release:
    spark, ledger = tx.spark, BudgetLedger(eps)
    inf = math.isinf(eps)
    part = (lambda x: math.inf) if inf else (lambda x: x)
    n = tx.size() if p.n_mode == "public" else None
    warning = "" if tx.universe is not None else "items are those observed, accepted as public"
    shares = split_budget(1.0 if inf else eps, 1, 0, p.alphas, p.single_basis_limit)

    seconds, began = {}, [time.time()]

    def book(step: str, share: float, label: str, sensitivity: float, mechanism: str, size: int, note: str = "") -> None:
        now = time.time()
        seconds[step], began[0] = now - began[0], now
        if not inf:
            ledger.spend(step, share, label, sensitivity, mechanism, size, note)

    truth = mining.topk(tx, k) if p.true_rank or p.true_elements or p.maximal_bases else []
    if p.true_rank:
        lam = len({i for f in truth for i in f.items})
    else:
        lam = estimate_item_rank(tx, k, part(shares["rank"]), p.eta, noise, p.rank_domain)
    book("rank", shares["rank"], "rank", 1, "exponential", 1)
    lam2 = 0 if lam <= p.single_basis_limit else pairs_to_request(k, p.eta, lam, p.pair_rule)
    shares = split_budget(1.0 if inf else eps, lam, lam2, p.alphas, p.single_basis_limit)
    if p.true_elements:
        items = sorted({i for f in truth for i in f.items})
    else:
        drawn = pick_elements(tx.item_counts(), "n", lam, part(shares["items"]), ["item"], noise, "items", p.quality_scale, n)
        items = [r["item"] for r in drawn.select("item").collect()]  # a private output of lam rows
    book("items", shares["items"], "items", 1, "exponential, without replacement", len(items), warning)
    pairs: list[tuple[str, str]] = []
    if p.true_elements:
        pairs = [tuple(sorted(f.items)) for f in truth if len(f.items) == 2]
    elif lam2:
        drawn = pick_elements(mining.pair_counts(tx, items), "n", lam2, part(shares["pairs"]), ["a", "b"], noise, "pairs", p.quality_scale, n)
        pairs = [(r["a"], r["b"]) for r in drawn.select("a", "b").collect()]
    book("pairs", shares["pairs"], "pairs", 1, "exponential, without replacement", len(pairs))
    if p.maximal_bases:
        bases = BasisSet.of(f.items for f in mining.maximal(truth))
    elif lam <= p.single_basis_limit:
        bases = BasisSet.single(items)
    else:
        bases = build_bases(items, pairs, p.max_basis_len, objective=p.objective, merge=p.merge, dissolve=p.dissolve)
    counted = count_with_bases(tx, bases, k, part(shares["bins"]), noise, n, p.superset_strategy)
    itemsets = spark.createDataFrame([tuple(r) for r in counted.collect()], counted.schema)  # a private output of k rows, drawn once
    book("bins", shares["bins"], "bins", bases.width, "laplace", sum(1 << len(b) for b in bases), "" if n is None else "the number of transactions is public")
    return Release(itemsets, ledger, lam, items, pairs, bases, p, seconds)


def release_threshold_private(tx: Transactions, theta: float, eps: float, noise: NoiseSource, params: ReleaseParams | None = None) -> Release:
    """All itemsets of a frequency or more, by the k that the data has for it; that k itself isn't private, and the report says so."""
    out = release_topk_private(tx, max(1, mining.k_for_threshold(tx, theta)), eps, noise, params)
    out.ledger.entries = [(*e[:-1], f"{e[-1]}; k comes from the data".lstrip("; ")) for e in out.ledger.entries]
    return out


def ablations(params: ReleaseParams) -> dict[str, ReleaseParams]:
    """One variant for each design choice."""
    return {
        "default": params,
        "true_rank": replace(params, true_rank=True),
        "true_elements": replace(params, true_rank=True, true_elements=True),
        "maximal_bases": replace(params, true_rank=True, true_elements=True, maximal_bases=True),
        "no_merge": replace(params, merge=False),
        "no_dissolve": replace(params, dissolve=False),
        "naive_pairs": replace(params, pair_rule="naive"),
        "eta_1": replace(params, eta=1.0),
        "length_7": replace(params, max_basis_len=7),
        "alphas_even": replace(params, alphas=(0.2, 0.4, 0.4)),
    }
