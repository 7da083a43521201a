"""The experiment grid: views, k, budgets, methods and repeats.

All budgets and repeats of a workload share their passes over the data.  Noise
is keyed, so the draws of every run can be made side by side from the same
exact numbers, and each run publishes what a release of its own would publish:
one pass finds the target rank, one the item counts (all draws of items are one
query), one projection on the items that any run drew serves the pairs and the
bins of all runs, and one pass gives the exact supports of all that was
published, for the measures.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.budget import pairs_to_request, split_budget
from ..functions.noise import NoiseSource, gumbel_from, uniform_of
from ..operators import metrics, mining
from ..operators.bases import BasisSet, build_bases
from ..operators.truncated import candidate_space, is_effective, select, truncation_margin
from ..sources.transactions import Transactions
from ..sources.views import VIEWS
from .basis_release import ReleaseParams, rank_scores

SCHEMA = "view string, method string, k int, eps double, m int, seed int, fnr double, fpr double, precision double, re double, coverage_miss double, width int, length int, seconds double, status string"

BUDGETS = (0.1, 0.25, 0.5, 0.75, 1.0)
SEEDS = (1, 2, 3)


@dataclass(frozen=True)
class Workload:
    """A group of experiments: a view, the ks, and the options of the two methods."""

    view: str
    ks: tuple[int, ...]
    ms: tuple[int, ...]
    max_basis_len: int = 12
    eta: float = 1.2
    budgets: tuple[float, ...] = BUDGETS
    pair_rule: str = "root"


#: Small lambda with one basis; larger lambda with a few bases; lambda near k with many.
WORKLOADS = {
    "single_basis_words": Workload("doc_words", (50, 100), (1, 2)),
    "single_basis_records": Workload("line_records", (50, 150), (1, 2, 3)),
    "few_bases_terms": Workload("order_terms", (50, 100), (1, 2), 7),
    "few_bases_terms_naive_pairs": Workload("order_terms", (50, 100), (1, 2), 7, pair_rule="naive"),
    "few_bases_keywords": Workload("doc_keywords", (50, 100), (1, 2), 7),
    "few_bases_clicks": Workload("user_day_clicks", (100, 200, 300, 400), (1, 2), 7),
    "few_bases_terms_large_k": Workload("order_terms", (200, 300, 400), (1, 2), 7),
    "many_bases": Workload("cust_terms", (100, 200), (1, 2)),
    "many_bases_queries": Workload("conv_keywords", (100, 200), (1,), budgets=(*BUDGETS, 5.0, 10.0)),
    "control_flat_parts": Workload("order_parts", (100,), (1,)),
    "control_signs": Workload("embedding_signs", (50,), (1,)),
}

Run = tuple[float, int]


@dataclass
class GridRelease:
    """What one run publishes: (itemset, noisy count), the largest first, and its bases."""

    published: list[tuple[str, float]]
    bases: BasisSet
    lam: int


def _best(scored: list[tuple], c: int) -> list[tuple]:
    """The c highest scores; scored: (score, key...), ties by key."""
    return [tuple(key) for _, *key in sorted(scored, key=lambda s: (-round(s[0], 9), *s[1:]))[:c]]


def _drawn_items(tx: Transactions, wanted: dict[Run, tuple[float, int]]) -> dict[Run, list[str]]:
    """The items that each run draws, in one query; wanted: (scale of the counts, how many)."""
    runs = list(wanted)
    each = F.explode(F.array(*[F.struct(F.lit(k).alias("run"), F.lit(str(run[1])).alias("seed"), F.lit(wanted[run][0]).alias("scale"), F.lit(wanted[run][1]).alias("c")) for k, run in enumerate(runs)]))
    rows = tx.item_counts().select("item", "n", each.alias("r")).select("item", "n", "r.*")
    score = F.round(F.col("n").cast("double") * F.col("scale") + gumbel_from(uniform_of(F.concat_ws(":", "seed", F.lit("items"), "item"))), 9)
    place = F.row_number().over(Window.partitionBy("run").orderBy(F.desc("score"), "item"))
    most = max(c for _, c in wanted.values())  # a plain number, so that a task ranks no more than this before the shuffle
    best = rows.withColumn("score", score).withColumn("place", place).where(F.col("place") <= most).where("place <= c").select("run", "item").collect()  # the draws
    out: dict[Run, list[str]] = {run: [] for run in runs}
    for k, item in best:
        out[runs[k]].append(item)
    return out


def _many_bins(tx: Transactions, pool: list[str], bases: list[tuple[str, ...]]) -> list[np.ndarray]:
    """Complete exact bins of many bases over a pool, in one pass: a task holds its sums of all bases."""
    place = {i: k for k, i in enumerate(pool)}
    places = [np.array([place[i] for i in b]) for b in bases]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = [np.zeros(1 << p.size, np.int64) for p in places]
        for batch in batches:
            items, cnt = batch.column("items"), batch.column("cnt").to_numpy()
            held = np.zeros((batch.num_rows, len(pool)), np.int64)
            held[np.repeat(np.arange(batch.num_rows), np.diff(items.offsets.to_numpy())), items.flatten().to_numpy()] = 1
            for total, p in zip(sums, places, strict=True):
                total += np.bincount(held[:, p] @ (1 << np.arange(p.size)), cnt, total.size).astype(np.int64)
        for k, total in enumerate(sums):
            at = np.flatnonzero(total)
            if at.size:
                yield pa.RecordBatch.from_arrays([pa.array(np.full(at.size, k, np.int32)), pa.array(at.astype(np.int32)), pa.array(total[at])], ["basis", "mask", "n"])

    out = [np.zeros(1 << p.size) for p in places]
    rows = tx.projected(pool).mapInArrow(count, "basis int, mask int, n long").groupBy("basis", "mask").agg(F.sum("n").alias("n"))
    for k, mask, n in rows.collect():  # the bins of the runs' bases
        out[k][mask] = n
    return out


def _published(bases: BasisSet, counts: list[np.ndarray], eps: float, noise: NoiseSource, k: int) -> list[tuple[str, float]]:
    """The k largest fused noisy counts of the subsets of a run's bases."""
    fused: dict[str, list] = {}
    for b, (items, exact) in enumerate(zip(bases, counts, strict=True)):
        sums = exact + np.array([noise.laplace_value("bins", bases.width / eps, b, mask) for mask in range(exact.size)])
        step = 1
        while step < sums.size:
            halves = sums.reshape(-1, 2, step)
            halves[:, 0] += halves[:, 1]
            step *= 2
        for mask in range(1, sums.size):
            names = [i for p, i in enumerate(items) if mask >> p & 1]
            got, weight = fused.setdefault("|".join(names), [0.0, 0.0, len(names)]), 2.0 ** (len(names) - len(items))
            got[0] += sums[mask] * weight
            got[1] += weight
    best = sorted(((round(float(s / w), 6), size, name) for name, (s, w, size) in fused.items()), key=lambda x: (-x[0], *x[1:]))[:k]
    return [(name, nc) for nc, _, name in best]


def release_grid(tx: Transactions, k: int, runs: Iterable[Run], params: ReleaseParams) -> dict[Run, GridRelease]:
    """``release_topk_private`` of every (eps, seed), from shared passes over the data."""
    tx.need_domain(params.observed_domain)
    runs, p = list(dict.fromkeys(runs)), params
    noises = {run: NoiseSource.fixed(run[1]) for run in runs}
    ranks = [(r["j"], r["quality"]) for r in rank_scores(tx, k, p.eta, p.rank_domain).collect()]
    lams, shares = {}, {}
    for run in runs:
        scale = p.alphas[0] * run[0] / 2
        lams[run] = _best([(q * scale + noises[run].gumbel_value("rank", j), j) for j, q in ranks], 1)[0][0]
        lam2 = 0 if lams[run] <= p.single_basis_limit else pairs_to_request(k, p.eta, lams[run], p.pair_rule)
        shares[run] = (split_budget(run[0], lams[run], lam2, p.alphas, p.single_basis_limit), lam2)
    items = _drawn_items(tx, {run: (shares[run][0]["items"] / lams[run], lams[run]) for run in runs})
    pool = sorted({i for drawn in items.values() for i in drawn})
    pairs = {}
    if any(lam2 for _, lam2 in shares.values()):
        pairs = {(r["a"], r["b"]): r["n"] for r in mining.pair_counts(tx, pool).collect()}  # pairs of drawn items
    bases = {}
    for run in runs:
        share, lam2 = shares[run]
        if lams[run] <= p.single_basis_limit:
            bases[run] = BasisSet.single(items[run])
            continue
        own, noise, scale = set(items[run]), noises[run], share["pairs"] / max(lam2, 1)
        drawn = _best([(n * scale + noise.gumbel_value("pairs", a, b), a, b) for (a, b), n in pairs.items() if a in own and b in own], lam2) if lam2 else []
        bases[run] = build_bases(items[run], drawn, p.max_basis_len, objective=p.objective, merge=p.merge, dissolve=p.dissolve)
    distinct = list(dict.fromkeys(b for run in runs for b in bases[run]))
    exact = dict(zip(distinct, _many_bins(tx, pool, distinct), strict=True))
    return {run: GridRelease(_published(bases[run], [exact[b] for b in bases[run]], shares[run][0]["bins"], noises[run], k), bases[run], lams[run]) for run in runs}


def run_grid(spark: SparkSession, sf_dir: str, workload: Workload, budgets: Iterable[float] | None = None, seeds: Iterable[int] = SEEDS, ks: Iterable[int] | None = None, ms: Iterable[int] | None = None) -> DataFrame:
    """A row for each run of each method; where the baseline can't run, its measures are null and the status says why."""
    out: list[tuple] = []
    kept = VIEWS[workload.view](spark, sf_dir).cached()  # every pool of items is a pass over them
    try:
        with kept.remembering() as tx:
            mining.topk(tx, math.ceil(max(ks or workload.ks) * workload.eta))  # the lists of all ks are parts of this one
            for k in ks or workload.ks:
                out += _run_k(tx, workload, k, [(float(e), s) for e in budgets or workload.budgets for s in seeds], list(ms or workload.ms))
    finally:
        kept.rows.unpersist()
    return spark.createDataFrame(out, SCHEMA)


def _run_k(tx: Transactions, workload: Workload, k: int, runs: list[Run], ms: list[int]) -> list[tuple]:
    n, observed = tx.size(), tx.universe is None
    params = ReleaseParams(max_basis_len=workload.max_basis_len, eta=workload.eta, pair_rule=workload.pair_rule, observed_domain=observed)
    truth = mining.topk(tx, k)
    began = time.time()
    basis = release_grid(tx, k, runs, params)
    seconds = (time.time() - began) / len(runs)
    chosen: dict[tuple, tuple] = {}
    for m in ms:
        for eps, seed in sorted(runs):  # the smallest budget has the lowest floor, whose list serves the others
            began = time.time()
            try:
                got = select(tx, k, m, eps, NoiseSource.fixed(seed), observed_domain=observed)
                chosen[m, eps, seed] = (got, time.time() - began, "run")
            except mining.TooManySets as e:
                chosen[m, eps, seed] = (None, time.time() - began, f"not applicable: {e}")
    wanted = {tuple(s.split("|")) for r in basis.values() for s, _ in r.published} | {s for sets, _, _ in chosen.values() if sets for s in sets}
    exact = {mining.key_of(s): c for s, c in mining.supports(tx, sorted(wanted)).items()}

    def measures(published: list[tuple[str, float]]) -> tuple:
        m = metrics.measured_with(exact, published, truth, k)
        return m["fnr"], m["fpr"], m["precision"], m["re"]

    rows = []
    for (eps, seed), r in basis.items():
        rows.append((workload.view, "basis", k, eps, None, seed, *measures(r.published), metrics.coverage_miss_rate(r.bases, truth, k), r.bases.width, r.bases.length, seconds, "run"))
    for (m, eps, seed), (sets, spent, status) in chosen.items():
        if sets is None:
            rows.append((workload.view, "truncated", k, eps, m, seed, None, None, None, None, None, None, None, spent, status))
            continue
        noise, scale = NoiseSource.fixed(seed), len(sets) / (eps * 0.5)
        published = [(key, exact[key] + noise.laplace_value("truncated", scale, key)) for key in map(mining.key_of, sets)]
        rows.append((workload.view, "truncated", k, eps, m, seed, *measures(published), None, None, None, spent, status))
    return rows


def best_m(rows: DataFrame) -> DataFrame:
    """Runs of the basis method, and of the baseline at the m with the highest mean precision of each (view, k, eps), the smallest of equals."""
    means = rows.where("method = 'truncated' and status = 'run'").groupBy("view", "k", "eps", "m").agg(F.avg("precision").alias("p"))
    chosen = means.groupBy("view", "k", "eps").agg(F.max_by("m", F.struct(F.round("p", 12), -F.col("m"))).alias("m"))
    return rows.where("method = 'basis'").unionByName(rows.where("method = 'truncated'").join(chosen, ["view", "k", "eps", "m"]).select(*rows.columns))


def summary(rows: DataFrame) -> DataFrame:
    """Mean and standard error over repeats of both methods, the baseline at its best m; with the lengths that the baseline couldn't run."""
    mean = lambda c: F.round(F.avg(c), 9).alias(c)
    error = lambda c: F.round(F.stddev_samp(c) / F.sqrt(F.count("*")), 9).alias(f"{c}_error")
    out = best_m(rows).groupBy("view", "method", "k", "eps", "m").agg(mean("fnr"), error("fnr"), mean("precision"), mean("re"), error("re"), mean("coverage_miss"), mean("width"), F.max("length").alias("length"), F.count("*").alias("runs"))
    left_out = rows.where("status <> 'run'").groupBy("view", "k", "eps").agg(F.array_join(F.sort_array(F.collect_set("m")), ",").alias("m_not_run"))
    return out.join(left_out, ["view", "k", "eps"], "left")


def effectiveness(spark: SparkSession, sf_dir: str, views: Iterable[str], k: int, ms: Iterable[int], eps: float = 1.0, rho: float = 0.9) -> DataFrame:
    """For each view and m: the k-th support, the margin in counts, the candidates, and whether truncation prunes anything."""
    out = []
    for name in views:
        with VIEWS[name](spark, sf_dir).remembering() as tx:
            n, n_items = tx.size(), tx.item_counts().count()
            for m in ms:
                found = mining.topk(tx, k, m)
                c_k = found[k - 1].support if len(found) >= k else 0
                space = candidate_space(n_items, m)
                margin = truncation_margin(k, eps, n, rho, space) * n
                out.append((name, k, m, int(c_k), round(margin, 6), float(space), is_effective(margin, c_k)))
    return spark.createDataFrame(out, "view string, k int, m int, c_k long, margin_n double, space double, effective boolean")


def error_table(rows: DataFrame, measure: str = "fnr") -> DataFrame:
    """Mean of a measure by budget, a column for each method."""
    return best_m(rows).groupBy("view", "k", "eps").pivot("method", ["basis", "truncated"]).avg(measure)


def run_all(spark: SparkSession, sf_dir: str, out: str, seeds: Iterable[int] = SEEDS) -> None:
    """Every workload at every budget and repeat, written as Parquet by workload."""
    for name, workload in WORKLOADS.items():
        run_grid(spark, sf_dir, workload, seeds=seeds).write.mode("overwrite").parquet(f"{out}/workload={name}")
