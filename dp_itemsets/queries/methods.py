"""Queries of the methods, baselines, measures and experiments."""

from __future__ import annotations

import math
from collections.abc import Callable
from itertools import combinations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import budget, mechanisms
from ..functions.noise import NoiseSource
from ..operators import bases as B
from ..operators import bins, metrics, mining, truncated
from ..plans import basis_release as R
from ..plans import experiments
from ..sources.transactions import Transactions
from ..sources.views import VIEW_SQL, VIEWS, read
from . import sqltext as S

Query = Callable[[SparkSession, str], DataFrame]

QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
NOISE = NoiseSource.fixed(42)

#: Bases over the brands of an order, for worked checks.
SINGLE = [("Brand#1", "Brand#10", "Brand#11")]
MULTI = [("Brand#1", "Brand#10", "Brand#11"), ("Brand#12", "Brand#13", "Brand#14", "Brand#15")]
OVERLAP = [("Brand#1", "Brand#10", "Brand#11"), ("Brand#10", "Brand#11", "Brand#12", "Brand#13")]
GIVEN = [("PROMO",), ("PROMO", "red"), ("ECONOMY", "SMALL"), ("anvil", "blue", "bolt"), ("Brand#1", "Brand#2"), ("LARGE", "cold", "gear")]


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def register(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return register


def _view(name: str, spark: SparkSession, sf_dir: str) -> Transactions:
    return VIEWS[name](spark, sf_dir)


def _each(rows: DataFrame, f: Callable, schema: str, *columns: str) -> DataFrame:
    """Columns of a plain function of each row, after the rows' own; the tasks call it."""
    return rows.withColumn("_out", F.udf(f, schema)(*columns)).select(*rows.columns, "_out.*")


def _part_shapes(spark: SparkSession, sf_dir: str, *columns: Column) -> DataFrame:
    """Different shapes of parts by the lines that order them."""
    return read(spark, sf_dir, "lineitem").groupBy("l_partkey").agg(*columns).drop("l_partkey").distinct()


def _topk(name: str, view: str, k: int, sets: str | None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return mining.topk_frame(_view(view, spark, sf_dir), k).withColumn("freq", F.round("freq", 9))

    QUERIES[name] = run
    if sets:
        ORACLES[name] = S.topk(view, k, sets)


# --- exact mining ---------------------------------------------------------


@query(f"WITH {S.counts('order_brands')} SELECT item, n FROM c")
def item_counts_brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _view("order_brands", spark, sf_dir).item_counts()


@query(f"""WITH {S.counts('order_brands')}, p AS (SELECT x.item AS a, y.item AS b FROM universe x JOIN universe y ON x.item < y.item),
    q AS (SELECT x.item AS a, y.item AS b, count(*) AS n FROM d x JOIN d y ON x.tid = y.tid AND x.item < y.item GROUP BY 1, 2)
    SELECT a, b, coalesce(n, 0) AS n FROM p LEFT JOIN q USING (a, b)""")
def pair_counts_brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    tx = _view("order_brands", spark, sf_dir)
    return mining.pair_counts(tx, [r["item"] for r in tx.universe.collect()])


@query(f"WITH {S.counts('order_terms')} SELECT row_number() OVER (ORDER BY n DESC, item)::INT AS item_id, item, n FROM c")
def item_dictionary_universe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mining.numbered(_view("order_terms", spark, sf_dir).item_counts())


@query(f"""WITH {S.d('order_terms')}, g AS (SELECT * FROM (VALUES {', '.join(f"('{mining.key_of(s)}', {list(s)})" for s in GIVEN)}) AS t(itemset, items)),
    w AS (SELECT itemset, len(items) AS size, unnest(items) AS item FROM g),
    h AS (SELECT itemset, tid FROM w JOIN d USING (item) GROUP BY itemset, tid, size HAVING count(*) = size)
    SELECT g.itemset, count(h.tid) AS support FROM g LEFT JOIN h USING (itemset) GROUP BY g.itemset""")
def support_given_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = mining.supports(_view("order_terms", spark, sf_dir), GIVEN)
    return spark.createDataFrame([(mining.key_of(s), n) for s, n in got.items()], "itemset string, support long")


_topk("topk_exact_order_brands", "order_brands", 50, S.small_sets(50))
_topk("topk_exact_order_terms", "order_terms", 100, S.small_sets(100))
_topk("topk_exact_line_records", "line_records", 50, S.bitmap_sets(13))
_topk("topk_exact_doc_words", "doc_words", 50, S.bitmap_sets(13))
_topk("topk_exact_cust_terms", "cust_terms", 100, S.small_sets(100, 2))
_topk("topk_exact_order_parts", "order_parts", 100, S.small_sets(100, 2))
_topk("topk_exact_embedding_signs", "embedding_signs", 100, S.small_sets(64))
_topk("topk_exact_page_words", "page_words", 100, S.bitmap_sets(10))
_topk("topk_exact_user_day_clicks", "user_day_clicks", 50, S.small_sets(50))
_topk("topk_exact_doc_keywords", "doc_keywords", 50, S.small_sets(50) if "doc_keywords" in VIEW_SQL else None)
_topk("topk_exact_conv_keywords", "conv_keywords", 50, S.small_sets(50) if "conv_keywords" in VIEW_SQL else None)

_LEAST = 1500
_FREQUENT = f"WITH {S.counts('order_terms')}, {S.small_sets(60)} SELECT itemset, size::INT AS size, support::BIGINT AS support FROM s WHERE support >= {_LEAST}"


def _frame(spark: SparkSession, found: list[mining.Found]) -> DataFrame:
    columns = [pa.array([mining.key_of(f.items) for f in found], pa.string()), pa.array([len(f.items) for f in found], pa.int32()), pa.array([f.support for f in found], pa.int64())]
    return spark.createDataFrame(pa.table(columns, ["itemset", "size", "support"]))


@query(_FREQUENT)
def apriori_order_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mining.apriori(_view("order_terms", spark, sf_dir), _LEAST, listed=False).frame()


@query(_FREQUENT)
def fpgrowth_order_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mining.fp_growth(_view("order_terms", spark, sf_dir), _LEAST)


@query(f"""WITH f AS ({_FREQUENT}), l AS (SELECT *, string_split(itemset, '|') AS items FROM f)
    SELECT itemset, size, support FROM l x WHERE NOT EXISTS (SELECT 1 FROM l y WHERE y.size > x.size AND list_has_all(y.items, x.items))""")
def maximal_itemsets_order_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mining.maximal(mining.apriori(_view("order_terms", spark, sf_dir), _LEAST, listed=False)).frame()


@query(f"WITH {S.counts('order_terms')}, {S.small_sets(60)}, n AS (SELECT count(*) AS n FROM tids) SELECT count(*) AS k FROM s, n WHERE support >= 0.15 * n.n")
def k_for_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(mining.k_for_threshold(_view("order_terms", spark, sf_dir), 0.15),)], "k long")


@query(f"WITH {S.counts('order_terms')}, {S.small_sets(60)}, n AS (SELECT count(*) AS n FROM tids) SELECT round(support / n.n, 9) AS theta FROM s, n ORDER BY support DESC LIMIT 1 OFFSET 99")
def threshold_for_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(round(mining.threshold_for_k(_view("order_terms", spark, sf_dir), 100), 9),)], "theta double")


def _profile_sql(view: str, k: int, sets: str) -> str:
    return f"""WITH {S.counts(view)}, {sets}, top AS (SELECT * FROM s ORDER BY support DESC, size, itemset LIMIT {k})
        SELECT '{view}' AS "view", {k}::INT AS k, {S.N} AS n, (SELECT count(*) FROM c) AS items,
        round((SELECT count(*) FROM d) / {S.N}, 9) AS avg_len,
        (SELECT count(DISTINCT i) FROM (SELECT unnest(string_split(itemset, '|')) AS i FROM top)) AS lam,
        (SELECT count(*) FROM top WHERE size = 2) AS lam2, (SELECT count(*) FROM top WHERE size = 3) AS lam3, (SELECT min(support) FROM top)::BIGINT AS c_k"""


_PROFILED = {"order_brands": (50, S.small_sets(50)), "order_terms": (100, S.small_sets(100)), "line_records": (50, S.bitmap_sets(13)), "cust_terms": (100, S.small_sets(100, 2)), "order_parts": (100, S.small_sets(100, 2)), "embedding_signs": (100, S.small_sets(64)), "page_words": (100, S.bitmap_sets(10))}


@query(" UNION ALL ".join(f"SELECT * FROM ({_profile_sql(v, k, sets)})" for v, (k, sets) in _PROFILED.items()))
def dataset_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = []
    for view, (k, _) in _PROFILED.items():
        p = mining.dataset_profile(_view(view, spark, sf_dir), k)
        rows.append((view, k, p["n"], p["items"], round(p["avg_len"], 9), p["lam"], p["lam2"], p["lam3"], p["c_k"]))
    return spark.createDataFrame(rows, "view string, k int, n long, items long, avg_len double, lam long, lam2 long, lam3 long, c_k long")


@query(f"""WITH {S.counts('order_terms')}, {S.small_sets(100)}, top AS (SELECT itemset, support, string_split(itemset, '|') AS l FROM s ORDER BY support DESC, size, itemset LIMIT 100)
    SELECT p.itemset AS antecedent, array_to_string(list_sort(list_filter(w.l, lambda x: NOT list_contains(p.l, x))), '|') AS consequent, round(w.support / p.support, 9) AS confidence
    FROM top w JOIN top p ON len(p.l) < len(w.l) AND list_has_all(w.l, p.l) WHERE w.support / p.support >= 0.5""")
def rules_from_release(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mining.rules(mining.topk_frame(_view("order_terms", spark, sf_dir), 100), "support", 0.5).withColumn("confidence", F.round("confidence", 9))


@query(f"WITH {S.d('order_brands')}, gone AS (SELECT min(tid) AS tid FROM d) SELECT item, count(*) AS n FROM d WHERE tid <> (SELECT tid FROM gone) GROUP BY item")
def neighbour_item_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    tx = _view("order_brands", spark, sf_dir)
    return tx.without(tx.rows.agg(F.min("tid")).first()[0]).item_counts().where("n > 0")


# --- privacy primitives ---------------------------------------------------


@query(f"WITH {S.counts('order_brands')} SELECT item, n, round(n + {S.laplace(chr(39) + '42:laplace:' + chr(39) + ' || item', '2.0')}, 6) AS noisy FROM c")
def laplace_item_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mechanisms.laplace_release(_view("order_brands", spark, sf_dir).item_counts(), "n", 1.0, 0.5, ["item"], NOISE)
    return rows.select("item", "n", F.round("noisy", 6).alias("noisy"))


@query(f"WITH {S.counts('order_brands')}, w AS (SELECT item, exp((n - (SELECT max(n) FROM c)) * 0.05 / 2) AS w FROM c) SELECT item, round(w / (SELECT sum(w) FROM w), 9) AS probability FROM w")
def exponential_probabilities(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mechanisms.exponential_probabilities(_view("order_brands", spark, sf_dir).item_counts(), F.col("n"), 0.05)
    return rows.select("item", F.round("probability", 9).alias("probability"))


def _rank_sql(view: str, k1: int, eps: float, sets: str) -> str:
    """CTE rank(j, n, quality, score)."""
    return f"""{S.counts(view)}, {sets}, theta AS (SELECT support AS theta FROM s ORDER BY support DESC, size, itemset LIMIT 1 OFFSET {k1 - 1}),
        ranked AS (SELECT row_number() OVER (ORDER BY n DESC, item) AS j, n FROM c ORDER BY n DESC, item LIMIT {k1}),
        rank AS (SELECT j, n, -abs(n - theta) AS quality, round(-abs(n - theta) * {eps} / 2 + {S.gumbel("'42:rank:' || j")}, 9) AS score FROM ranked, theta)"""


@query(f"WITH {_rank_sql('order_brands', 60, 0.05, S.small_sets(60))} SELECT j::INT AS j, n, quality::BIGINT AS quality FROM rank ORDER BY score DESC, j LIMIT 1")
def exponential_draw_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = R.rank_scores(_view("order_brands", spark, sf_dir), 50, 1.2)
    return mechanisms.exponential_draw(scored, F.col("quality"), 0.05, ["j"], NOISE, "rank").select("j", "n", "quality")


@query(f"WITH {_rank_sql('order_brands', 60, 0.1, S.small_sets(60))} SELECT j::INT AS lam FROM rank ORDER BY score DESC, j LIMIT 1")
def estimate_rank_order_brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(R.estimate_item_rank(_view("order_brands", spark, sf_dir), 50, 0.1, 1.2, NOISE),)], "lam int")


@query(f"WITH {S.counts('order_terms')} SELECT item, n FROM c ORDER BY round(n * {0.4 / 22} + {S.gumbel(chr(39) + '42:items:' + chr(39) + ' || item')}, 9) DESC, item LIMIT 22")
def pick_items_order_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return R.pick_elements(_view("order_terms", spark, sf_dir).item_counts(), "n", 22, 0.4, ["item"], NOISE, "items").select("item", "n")


_PICKED = [f"Brand#{i}" for i in range(1, 11)]


@query(f"""WITH {S.d('order_brands')}, i AS (SELECT unnest({_PICKED}) AS item), p AS (SELECT x.item AS a, y.item AS b FROM i x JOIN i y ON x.item < y.item),
    q AS (SELECT x.item AS a, y.item AS b, count(*) AS n FROM d x JOIN d y ON x.tid = y.tid AND x.item < y.item GROUP BY 1, 2), r AS (SELECT a, b, coalesce(n, 0) AS n FROM p LEFT JOIN q USING (a, b))
    SELECT a, b, n FROM r ORDER BY round(n * {0.4 / 12} + {S.gumbel("'42:pairs:' || a || ':' || b")}, 9) DESC, a, b LIMIT 12""")
def pick_pairs_order_brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = mining.pair_counts(_view("order_brands", spark, sf_dir), _PICKED)
    return R.pick_elements(pairs, "n", 12, 0.4, ["a", "b"], NOISE, "pairs").select("a", "b", "n")


@query("""WITH g AS (SELECT DISTINCT sum(l_linenumber) // 2 AS k, count(DISTINCT l_quantity) AS lam FROM lineitem GROUP BY l_partkey), e AS (SELECT unnest([1.0, 1.1, 1.2]) AS eta),
    x AS (SELECT k, lam, eta::DOUBLE AS eta, eta::DOUBLE * k - lam AS r FROM g, e)
    SELECT k::INT AS k, lam::INT AS lam, eta, CASE WHEN r <= 0 THEN 0 ELSE least(floor(r / sqrt(greatest(1.0, r / lam)) + 1e-9), lam * (lam - 1) // 2) END::INT AS pairs,
    CASE WHEN r <= 0 THEN 0 ELSE least(floor(r + 1e-9), lam * (lam - 1) // 2) END::INT AS naive FROM x""")
def pairs_to_request_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each part's number of different quantities, and half the sum of its line numbers as k."""
    shapes = _part_shapes(spark, sf_dir, F.floor(F.sum("l_linenumber") / 2).cast("int").alias("k"), F.countDistinct("l_quantity").cast("int").alias("lam"))
    rows = shapes.select("k", "lam", F.explode(F.array(*map(F.lit, (1.0, 1.1, 1.2)))).alias("eta"))
    return _each(rows, lambda k, lam, eta: (budget.pairs_to_request(k, eta, lam), budget.pairs_to_request(k, eta, lam, "naive")), "pairs int, naive int", "k", "lam", "eta")


@query("""WITH x AS (SELECT DISTINCT count(DISTINCT l_quantity) AS lam, count(DISTINCT l_suppkey) + 5 * min(l_linenumber) AS asked FROM lineitem WHERE l_quantity > 30 GROUP BY l_partkey), y AS (SELECT *, CASE WHEN lam <= 12 THEN 0 ELSE asked END AS p FROM x)
    SELECT lam::INT AS lam, asked::INT AS asked, round(0.1, 9)::DOUBLE AS rank_eps, round(0.4::DOUBLE * lam / (lam + p), 9) AS items_eps, round(0.4::DOUBLE * p / (lam + p), 9) AS pairs_eps, round(0.5, 9)::DOUBLE AS bins_eps FROM y""")
def budget_split_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shares for as many items and pairs as parts have quantities above 30 and suppliers of them."""

    def shares(lam: int, asked: int) -> tuple[float, ...]:
        s = budget.split_budget(1.0, lam, asked)
        return tuple(round(s[x], 9) for x in ("rank", "items", "pairs", "bins"))

    asked = (F.countDistinct("l_suppkey") + 5 * F.min("l_linenumber")).cast("int").alias("asked")
    rows = read(spark, sf_dir, "lineitem").where("l_quantity > 30").groupBy("l_partkey").agg(F.countDistinct("l_quantity").cast("int").alias("lam"), asked).select("lam", "asked").distinct()
    return _each(rows, shares, "rank_eps double, items_eps double, pairs_eps double, bins_eps double", "lam", "asked")


# --- bases and bins -------------------------------------------------------


def _bases(which: list[tuple[str, ...]]) -> B.BasisSet:
    return B.BasisSet.of(which)


def _bins_sql(which: list[tuple[str, ...]], eps: str = "0.5") -> str:
    return f"WITH {S.d('order_brands')}, {S.basis_values(which)}, {S.BINS}, {S.noisy(str(len(which)), eps)}, {S.FUSED}"


def _complete(spark: SparkSession, sf_dir: str, which: list[tuple[str, ...]]) -> tuple[DataFrame, B.BasisSet]:
    b = _bases(which)
    return bins.complete_bins(bins.bin_counts(_view("order_brands", spark, sf_dir), b), b), b


@query(f"""WITH {S.d('order_brands')}, {S.basis_values(OVERLAP)}, ids AS (SELECT basis_id, count(*) AS len FROM bas GROUP BY 1), m AS (SELECT basis_id, unnest(range(1, (1::BIGINT << len))) AS mask FROM ids),
    s AS (SELECT DISTINCT string_agg(item, '|' ORDER BY item) AS itemset, count(*)::INT AS size FROM m JOIN bas ON bas.basis_id = m.basis_id AND (m.mask >> pos) & 1 = 1 GROUP BY m.basis_id, m.mask),
    h AS (SELECT itemset, tid FROM (SELECT itemset, size, unnest(string_split(itemset, '|')) AS item FROM s) JOIN d USING (item) GROUP BY itemset, tid, size HAVING count(*) = size)
    SELECT s.itemset, s.size, count(h.tid) AS support FROM s LEFT JOIN h USING (itemset) GROUP BY s.itemset, s.size""")
def candidate_set_given_bases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The candidates that bases have, with how many orders hold each."""
    candidates = [tuple(sorted(s)) for s in _bases(OVERLAP).candidates()]
    got = mining.supports(_view("order_brands", spark, sf_dir), candidates)
    return spark.createDataFrame([(mining.key_of(s), len(s), n) for s, n in got.items()], "itemset string, size int, support long")


def _bin_query(which: list[tuple[str, ...]]) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return bins.bin_counts(_view("order_brands", spark, sf_dir), _bases(which))

    return run


for _name, _which in (("bin_counts_single", SINGLE), ("bin_counts_multi", MULTI)):
    QUERIES[_name] = _bin_query(_which)
    ORACLES[_name] = f"WITH {S.d('order_brands')}, {S.basis_values(_which)}, {S.BINS} SELECT basis_id::INT AS basis_id, mask::INT AS mask, n FROM seen"


@query(_bins_sql(MULTI) + " SELECT basis_id::INT AS basis_id, mask::INT AS mask, n FROM bins")
def complete_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _complete(spark, sf_dir, MULTI)[0]


@query(_bins_sql(MULTI) + " SELECT basis_id::INT AS basis_id, mask::INT AS mask, n, round(noisy, 6) AS noisy FROM noisy")
def noisy_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bins.noisy_bins(_complete(spark, sf_dir, MULTI)[0], 2, 0.5, NOISE).withColumn("noisy", F.round("noisy", 6))


def _sums(strategy: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        full, b = _complete(spark, sf_dir, MULTI)
        return bins.superset_sums(bins.noisy_bins(full, 2, 0.5, NOISE), b, strategy).select("basis_id", "mask", F.round("nc", 6).alias("nc"))

    return run


for _name in ("join", "zeta", "pandas"):
    QUERIES[f"superset_sums_{_name}"] = _sums(_name)
    ORACLES[f"superset_sums_{_name}"] = _bins_sql(MULTI) + " SELECT basis_id::INT AS basis_id, mask::INT AS mask, round(nc, 6) AS nc FROM sums"


def _estimates(spark: SparkSession, sf_dir: str) -> DataFrame:
    full, b = _complete(spark, sf_dir, OVERLAP)
    return bins.named_estimates(bins.superset_sums(bins.noisy_bins(full, 2, 0.5, NOISE), b), b)


_FUSED_SQL = _bins_sql(OVERLAP) + " SELECT itemset, size, round(nc, 6) AS nc, round(v, 9) AS v FROM fused"


@query(_FUSED_SQL)
def fuse_overlapping_bases(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bins.fuse(_estimates(spark, sf_dir)).select("itemset", "size", F.round("nc", 6).alias("nc"), F.round("v", 9).alias("v"))


@query(_FUSED_SQL)
def fuse_pairwise_udaf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bins.fuse_pairwise(_estimates(spark, sf_dir)).select("itemset", "size", F.round("nc", 6).alias("nc"), F.round("v", 9).alias("v"))


def _counted(which: list[tuple[str, ...]], eps: float, k: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        tx = _view("order_brands", spark, sf_dir)
        return bins.count_with_bases(tx, _bases(which), k, eps, NOISE, tx.size())

    return run


for _name, _which, _eps in (("count_with_bases_noiseless", OVERLAP, math.inf), ("count_with_bases_single", SINGLE, 0.5), ("count_with_bases_overlap", OVERLAP, 0.5)):
    QUERIES[_name] = _counted(_which, _eps, 15)
    ORACLES[_name] = _bins_sql(_which, "inf" if math.isinf(_eps) else str(_eps)) + " " + S.released(15, S.N, "0.0" if math.isinf(_eps) else str(2 * (len(_which) / _eps) ** 2))


def _zero_rows(checks: dict[str, bool]) -> list[tuple[str, int]]:
    return [(name, 0 if ok else 1) for name, ok in checks.items()]


def _zero_sql(names: list[str]) -> str:
    return " UNION ALL ".join(f"SELECT '{n}' AS check_name, 0 AS violations" for n in names)


_BUILD_CHECKS = ["pairs_covered", "items_covered", "length_capped", "merging_lowers_variance", "dissolving_lowers_variance"]


@query(_zero_sql(_BUILD_CHECKS))
def build_bases_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    truth = mining.topk(_view("order_terms", spark, sf_dir), 50)
    items, pairs = sorted({i for f in truth for i in f.items}), [f.items for f in truth if len(f.items) == 2]
    wanted = [(i,) for i in items] + pairs
    built, plain, merged = B.build_bases(items, pairs, 7), B.build_bases(items, pairs, 7, merge=False, dissolve=False), B.build_bases(items, pairs, 7, dissolve=False)
    ev = lambda b: B.average_error_variance(b, wanted)
    ok = [not built.uncovered(pairs), not built.uncovered((i,) for i in items), built.length <= 7, ev(merged) <= ev(plain), ev(built) <= ev(merged)]
    return spark.createDataFrame(_zero_rows(dict(zip(_BUILD_CHECKS, ok, strict=True))), "check_name string, violations int")


_CLIQUE_CHECKS = ["cliques_cover_frequent_sets", "maximal_sets_cover", "maximal_sets_are_shortest", "single_basis_covers", "cliques_are_cliques"]


@query(_zero_sql(_CLIQUE_CHECKS))
def clique_cover_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = mining.topk(_view("line_records", spark, sf_dir), 100)
    found = [f for f in found if f.support > found[-1].support]  # a threshold: all of a support or more
    sets, items, pairs = [f.items for f in found], [f.items[0] for f in found if len(f.items) == 1], [f.items for f in found if len(f.items) == 2]
    cliques, largest = B.BasisSet.from_cliques(items, pairs), B.BasisSet.of(f.items for f in mining.maximal(found))
    known = {frozenset(p) for p in pairs}
    ok = [not cliques.uncovered(sets), not largest.uncovered(sets), largest.length == max(map(len, sets)) <= cliques.length, not B.BasisSet.single(items).uncovered(sets),
          all(frozenset(p) in known for b in cliques for p in combinations(b, 2))]
    return spark.createDataFrame(_zero_rows(dict(zip(_CLIQUE_CHECKS, ok, strict=True))), "check_name string, violations int")


@query(_zero_sql(["merged_covers", "width_less_one"]))
def merge_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = mining.topk(_view("order_terms", spark, sf_dir), 50)
    bases = B.BasisSet.of(f.items for f in mining.maximal(found))
    sets = [f.items for f in found]
    merges = [bases.merged(i, j) for i, j in combinations(range(bases.width), 2)]
    ok = {"merged_covers": not any(m.uncovered(sets) for m in merges), "width_less_one": all(m.width == bases.width - 1 for m in merges)}
    return spark.createDataFrame(_zero_rows(ok), "check_name string, violations int")


@query(f"""WITH {S.d('order_brands')}, {S.basis_values(OVERLAP)}, w AS (SELECT count(DISTINCT basis_id) AS w FROM bas), len AS (SELECT basis_id, count(*) AS len FROM bas GROUP BY 1),
    p AS (SELECT item, sum(pow(2.0, -(len - 1 + 1))) AS p FROM bas JOIN len USING (basis_id) GROUP BY item)
    SELECT round(any_value(w.w) ** 2 / pow(0.5, 2) * avg(1 / p), 6) AS average_ev FROM d JOIN p USING (item), w""")
def average_error_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean over all items of the orders that the bases cover, each as often as it is ordered."""
    b = _bases(OVERLAP)
    variances = spark.createDataFrame([(i, B.average_error_variance(b, [(i,)], 0.5)) for i in b.items], "item string, ev double")
    counted = _view("order_brands", spark, sf_dir).item_counts().join(F.broadcast(variances), "item")
    return counted.agg(F.round(F.sum(F.col("n") * F.col("ev")) / F.sum("n"), 6).alias("average_ev"))


@query(f"WITH {S.basis_values(OVERLAP)}, len AS (SELECT basis_id, count(*) AS len FROM bas GROUP BY 1) SELECT count(*)::INT AS width, max(len)::INT AS length, round(pow(2.0, max(len)) * pow(count(*) / 0.5, 2), 6) AS worst_ev FROM len")
def worst_error_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = _bases(OVERLAP)
    return spark.createDataFrame([(b.width, b.length, round(B.worst_error_variance(b, 0.5), 6))], "width int, length int, worst_ev double")


@query("WITH l AS (SELECT count(*) AS g FROM lineitem GROUP BY l_orderkey) SELECT g::INT AS size, count(*) AS orders, round(pow(2.0, g - 1) / (g * g), 9) AS factor FROM l GROUP BY g")
def grouping_factor_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The factor of bases as long as orders have lines, with the number of such orders."""
    sizes = read(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count("*").cast("int").alias("size")).groupBy("size").agg(F.count("*").alias("orders"))
    return _each(sizes, lambda g: (round(B.grouping_factor(g), 9),), "factor double", "size")


@query(f"""WITH {S.basis_values(OVERLAP)}, {S.d('order_brands')}, len AS (SELECT basis_id, count(*)::INT AS len FROM bas GROUP BY 1)
    SELECT round(sum(pow(2.0, len)), 6) AS init, round(count(*) * (SELECT count(*) FROM d)::DOUBLE, 6) AS scan, round(sum(pow(3.0, len) - pow(2.0, len)), 6) AS superset_sums, round(sum(len * pow(2.0, len)), 6) AS halving FROM len""")
def cost_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    total = _view("order_brands", spark, sf_dir).rows.agg(F.sum(F.size("items"))).first()[0]
    c = metrics.cost_model(_bases(OVERLAP), total)
    return spark.createDataFrame([tuple(float(c[x]) for x in ("init", "scan", "superset_sums", "halving"))], "init double, scan double, superset_sums double, halving double")


# --- releases -------------------------------------------------------------


def _single_release_sql(view: str, k: int, k1: int, pool: int, n: str = S.N, limit: int = 12) -> str:
    """The release of a view whose drawn rank is at most ``limit``, at a budget of 1: rank, items, one basis, bins.  A higher rank takes another path, so the basis is cut there."""
    items_scale = "0.4 / (SELECT lam FROM lam)"
    return f"""WITH {_rank_sql(view, k1, 0.1, S.bitmap_sets(pool))}, lam AS (SELECT j AS lam FROM rank ORDER BY score DESC, j LIMIT 1),
        drawn AS (SELECT item, row_number() OVER (ORDER BY round(n * {items_scale} + {S.gumbel("'42:items:' || item")}, 9) DESC, item) AS r FROM c),
        bas AS (SELECT 0 AS basis_id, row_number() OVER (ORDER BY item) - 1 AS pos, item FROM drawn WHERE r <= (SELECT least(lam, {limit}) FROM lam)),
        {S.BINS}, {S.noisy('1', '0.5')}, {S.FUSED} {S.released(k, n, '8.0')}"""


def _release(view: str, k: int, eps: float = 1.0, **options: object) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return R.release_topk_private(_view(view, spark, sf_dir), k, eps, NOISE, R.ReleaseParams(**options)).itemsets

    return run


#: The bases that the releases below build on the tables of scale 0.01, for their checks: SQL counts with them, so another draw of rank, items or pairs, or other merges, would show.
FEW_TERMS = (
    "LARGE,STANDARD,cold,rod;PROMO,gizmo,hot,red;MEDIUM,SMALL,bolt,small;PROMO,STANDARD,large,ring;MEDIUM,STANDARD,blue,gear;"
    "LARGE,MEDIUM,anvil,plate;LARGE,MEDIUM,PROMO,STANDARD,widget;ECONOMY,SMALL,hot,small,widget;Brand#2,new,old;"
)
MANY_TERMS = (
    "ECONOMY+Brand#12,PROMO+Brand#17,STANDARD+Brand#6;ECONOMY+Brand#7,PROMO+Brand#2,STANDARD+Brand#7;"
    "ECONOMY+Brand#1,LARGE+Brand#13,LARGE+Brand#15;ECONOMY+Brand#15,LARGE+Brand#4,SMALL+Brand#3;"
    "ECONOMY+Brand#17,LARGE+Brand#8,PROMO+Brand#12;ECONOMY+Brand#18,LARGE+Brand#9,MEDIUM+Brand#2;"
    "ECONOMY+Brand#19,MEDIUM+Brand#4,PROMO+Brand#4;ECONOMY+Brand#20,PROMO+Brand#10,SMALL+Brand#6;"
    "ECONOMY+Brand#21,PROMO+Brand#15,STANDARD+Brand#2;ECONOMY+Brand#22,PROMO+Brand#8,STANDARD+Brand#24;"
    "ECONOMY+Brand#25,PROMO+Brand#9,STANDARD+Brand#9;SMALL+Brand#21,SMALL+Brand#25;ECONOMY+Brand#14,PROMO+Brand#9,STANDARD+Brand#23;"
    "ECONOMY+Brand#3,ECONOMY+Brand#4,ECONOMY+Brand#5;LARGE+Brand#12,LARGE+Brand#14,LARGE+Brand#16;"
    "LARGE+Brand#2,LARGE+Brand#20,LARGE+Brand#22;LARGE+Brand#23,LARGE+Brand#24,LARGE+Brand#25;LARGE+Brand#5,LARGE+Brand#6,LARGE+Brand#7;"
    "MEDIUM+Brand#10,MEDIUM+Brand#12,MEDIUM+Brand#13;MEDIUM+Brand#15,MEDIUM+Brand#16,MEDIUM+Brand#17;"
    "MEDIUM+Brand#19,MEDIUM+Brand#21,MEDIUM+Brand#23;MEDIUM+Brand#24,MEDIUM+Brand#25,MEDIUM+Brand#5;"
    "MEDIUM+Brand#8,MEDIUM+Brand#9,PROMO+Brand#11;PROMO+Brand#13,PROMO+Brand#14,PROMO+Brand#16;"
    "PROMO+Brand#19,PROMO+Brand#20,PROMO+Brand#21;PROMO+Brand#22,PROMO+Brand#23,PROMO+Brand#24;"
    "PROMO+Brand#25,PROMO+Brand#3,PROMO+Brand#5;PROMO+Brand#6,PROMO+Brand#7,SMALL+Brand#10;SMALL+Brand#12,SMALL+Brand#13,SMALL+Brand#14;"
    "SMALL+Brand#15,SMALL+Brand#18,SMALL+Brand#20;SMALL+Brand#22,SMALL+Brand#23,SMALL+Brand#4;SMALL+Brand#5,SMALL+Brand#7,SMALL+Brand#8;"
    "SMALL+Brand#9,STANDARD+Brand#1,STANDARD+Brand#13;STANDARD+Brand#15,STANDARD+Brand#16,STANDARD+Brand#18;"
    "STANDARD+Brand#19,STANDARD+Brand#20,STANDARD+Brand#21;STANDARD+Brand#22,STANDARD+Brand#25,STANDARD+Brand#3;"
)
FEW_CLICKS = (
    "click,k11,k38,k45;k1,k13,k2;k16,k26,k32;k17,k28,k8;k19,k29,k33;k21,k34,k60;k22,k42,k95;k30,k46,k98;k31,k50,k85;k35,k6,k71;"
    "k36,k66,k83;k40,k74,k82;k41,k92,k94;k44,purchase,signup;k24,k3,k58;k15,k58,k95;k18,k27,k76;k34,k43,k69;k38,k43,k93;k23,k24,k78;"
    "k55,k56,k74;k99,purchase,view;error,k3,k39;k10,k53,k79;k18,k27,k61,k71;k47,k48,k49;k5,k51,k54;k64,k65,k7;k73,k80,k81;k84,k86,k87;"
    "k9,k90,k91;"
)


def _literal(bases: str) -> list[tuple[str, ...]]:
    return [tuple(b.split(",")) for b in bases.split(";") if b]


def _several_release_sql(view: str, k: int, bases: str) -> str:
    which = _literal(bases)
    scale = str(2 * (len(which) / 0.5) ** 2)
    return f"WITH {S.d(view)}, {S.basis_values(which)}, {S.BINS}, {S.noisy(str(len(which)), '0.5')}, {S.FUSED} {S.released(k, S.N, scale)}"


QUERIES["basis_release_line_records"] = _release("line_records", 50)
ORACLES["basis_release_line_records"] = _single_release_sql("line_records", 50, 60, 13)
QUERIES["basis_release_doc_words"] = _release("doc_words", 50, single_basis_limit=16, observed_domain=True)
ORACLES["basis_release_doc_words"] = _single_release_sql("doc_words", 50, 60, 13, limit=16)
QUERIES["basis_release_order_terms"] = _release("order_terms", 50, max_basis_len=7)
ORACLES["basis_release_order_terms"] = _several_release_sql("order_terms", 50, FEW_TERMS)
QUERIES["basis_release_cust_terms"] = _release("cust_terms", 100)
ORACLES["basis_release_cust_terms"] = _several_release_sql("cust_terms", 100, MANY_TERMS)
QUERIES["basis_release_user_day_clicks"] = _release("user_day_clicks", 100, max_basis_len=7)
ORACLES["basis_release_user_day_clicks"] = _several_release_sql("user_day_clicks", 100, FEW_CLICKS)
QUERIES["basis_release_noisy_n"] = _release("line_records", 50, n_mode="noisy")
ORACLES["basis_release_noisy_n"] = _single_release_sql("line_records", 50, 60, 13, "(SELECT greatest(nc, 1.0) FROM fused WHERE size = 0)")


def _drawn_sql(view: str, k1: int, k: int, sets: str) -> str:
    """CTEs up to picked(a, b, n): rank, the number of pairs, items and pairs of a release at a budget of 1 with more than one basis."""
    left = f"greatest(floor(1.2 * {k} - lam + 1e-12), 0)"
    return f"""WITH {_rank_sql(view, k1, 0.1, sets)}, lam AS (SELECT j AS lam FROM rank ORDER BY score DESC, j LIMIT 1),
        asked AS (SELECT lam, CASE WHEN lam <= 12 OR {left} <= 0 THEN 0 ELSE least(floor((1.2 * {k} - lam) / sqrt(greatest(1.0, (1.2 * {k} - lam) / lam)) + 1e-9), lam * (lam - 1) // 2) END AS lam2 FROM lam),
        split AS (SELECT lam, lam2, 0.4 * lam / (lam + lam2) / lam AS items_scale, CASE WHEN lam2 > 0 THEN (0.4 - 0.4 * lam / (lam + lam2)) / lam2 ELSE 0 END AS pairs_scale FROM asked),
        drawn AS (SELECT item, row_number() OVER (ORDER BY round(n * (SELECT items_scale FROM split) + {S.gumbel("'42:items:' || item")}, 9) DESC, item) AS r FROM c),
        own AS (SELECT item FROM drawn WHERE r <= (SELECT lam FROM split)),
        pp AS (SELECT x.item AS a, y.item AS b FROM own x JOIN own y ON x.item < y.item), dd AS (SELECT tid, item FROM d JOIN own USING (item)),
        qq AS (SELECT x.item AS a, y.item AS b, count(*) AS n FROM dd x JOIN dd y ON x.tid = y.tid AND x.item < y.item GROUP BY 1, 2), rr AS (SELECT a, b, coalesce(n, 0) AS n FROM pp LEFT JOIN qq USING (a, b)),
        placed AS (SELECT a, b, row_number() OVER (ORDER BY round(n * (SELECT pairs_scale FROM split) + {S.gumbel("'42:pairs:' || a || ':' || b")}, 9) DESC, a, b) AS r FROM rr),
        picked AS (SELECT a, b FROM placed WHERE r <= (SELECT lam2 FROM split))"""


def _drawn(view: str, k: int, **options: object) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = R.release_topk_private(_view(view, spark, sf_dir), k, 1.0, NOISE, R.ReleaseParams(**options))
        return spark.createDataFrame([(i, "") for i in out.items] + out.pairs, "a string, b string")

    return run


for _name, _k, _sets in (("order_terms", 50, S.small_sets(60)), ("user_day_clicks", 100, S.small_sets(110)), ("cust_terms", 100, S.small_sets(130, 2))):
    QUERIES[f"release_draws_{_name}"] = _drawn(_name, _k, max_basis_len=7)
    ORACLES[f"release_draws_{_name}"] = _drawn_sql(_name, math.ceil(_k * 1.2), _k, _sets) + " SELECT item AS a, '' AS b FROM own UNION ALL SELECT a, b FROM picked"

_RELEASE_CHECKS = ["as_many_as_asked", "inside_candidates", "budget_kept", "pairs_covered", "repartitioning_changes_nothing"]


@query(_zero_sql(_RELEASE_CHECKS))
def basis_release_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    tx = _view("order_terms", spark, sf_dir)
    out = R.release_topk_private(tx, 50, 1.0, NOISE, R.ReleaseParams(max_basis_len=7))
    dealt = Transactions(tx.rows.repartition(3), tx.universe)
    again = R.release_topk_private(dealt, 50, 1.0, NOISE, R.ReleaseParams(max_basis_len=7))
    rows = out.ranked()
    ok = [len(rows) == min(50, len(out.bases.candidates())), all(out.bases.covers(s.split("|")) for s, _ in rows), out.ledger.spent <= 1 + 1e-9, not out.bases.uncovered(out.pairs), rows == again.ranked()]
    return spark.createDataFrame(_zero_rows(dict(zip(_RELEASE_CHECKS, ok, strict=True))), "check_name string, violations int")


@query()
def basis_release_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    return R.release_topk_private(_view("order_terms", spark, sf_dir), 50, 1.0, NOISE, R.ReleaseParams(max_basis_len=7)).report(spark)


@query()
def threshold_release(spark: SparkSession, sf_dir: str) -> DataFrame:
    return R.release_threshold_private(_view("order_terms", spark, sf_dir), 0.25, 1.0, NOISE).itemsets


@query()
def ablation_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error rate and coverage of each design choice."""
    rows = []
    with _view("order_terms", spark, sf_dir).remembering() as tx:
        truth = mining.topk(tx, 50)
        for name, params in R.ablations(R.ReleaseParams(max_basis_len=7)).items():
            out = R.release_topk_private(tx, 50, 1.0, NoiseSource.fixed(1), params)
            m = metrics.measured(tx, out.ranked(), truth, 50)
            rows.append((name, m["fnr"], m["re"], metrics.coverage_miss_rate(out.bases, truth, 50), out.bases.width, out.bases.length))
    return spark.createDataFrame(rows, "variant string, fnr double, re double, coverage_miss double, width int, length int")


# --- baselines ------------------------------------------------------------


@query("""WITH x AS (SELECT * FROM (VALUES ('retail', 16470, 1), ('mushroom', 119, 2), ('pumsb-star', 2088, 3), ('kosarak', 41270, 2), ('aol', 2290685, 1), ('brands', 25, 2)) AS t(name, items, m))
    SELECT name, m::INT AS m, CASE m WHEN 1 THEN items::DOUBLE WHEN 2 THEN items + items::DOUBLE * (items - 1) / 2 ELSE items + items::DOUBLE * (items - 1) / 2 + items::DOUBLE * (items - 1) * (items - 2) / 6 END AS space FROM x""")
def tf_candidate_space(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [(n, m, float(truncated.candidate_space(i, m))) for n, i, m in (("retail", 16470, 1), ("mushroom", 119, 2), ("pumsb-star", 2088, 3), ("kosarak", 41270, 2), ("aol", 2290685, 1), ("brands", 25, 2))]
    return spark.createDataFrame(rows, "name string, m int, space double")


#: Published parameters of five public datasets: name, k, m, transactions, items.
PUBLISHED = (("retail", 100, 1, 88162, 16470), ("mushroom", 100, 2, 8124, 119), ("pumsb-star", 200, 3, 49046, 2088), ("kosarak", 200, 2, 990002, 41270), ("aol", 200, 1, 647377, 2290685))


@query(f"""WITH x AS (SELECT * FROM (VALUES {', '.join(map(str, PUBLISHED))}) AS t(name, k, m, n, i)),
    y AS (SELECT *, CASE m WHEN 1 THEN i::DOUBLE WHEN 2 THEN i + i::DOUBLE * (i - 1) / 2 ELSE i + i::DOUBLE * (i - 1) / 2 + i::DOUBLE * (i - 1) * (i - 2) / 6 END AS u FROM x)
    SELECT name, k::INT AS k, m::INT AS m, round(4.0 * k * (ln(k / 0.9) + ln(u)), 4) AS margin_n, round(4.0 * k * m * ln(i), 4) AS lower_n FROM y""")
def tf_margin_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [(name, k, m, round(truncated.truncation_margin(k, 1.0, n, 0.9, truncated.candidate_space(i, m)) * n, 4), round(truncated.truncation_margin_lower(k, m, 1.0, n, i) * n, 4)) for name, k, m, n, i in PUBLISHED]
    return spark.createDataFrame(rows, "name string, k int, m int, margin_n double, lower_n double")


_TF_K, _TF_M, _TF_EPS = 20, 2, 50.0
_SPACE = truncated.candidate_space(25, _TF_M)
_TF = f"""{S.counts('order_brands')}, u1 AS (SELECT item AS itemset, 1 AS size, n AS support FROM c),
    q AS (SELECT x.item || '|' || y.item AS itemset, count(*) AS n FROM d x JOIN d y ON x.tid = y.tid AND x.item < y.item GROUP BY 1),
    u2 AS (SELECT x.item || '|' || y.item AS itemset, 2 AS size, coalesce(q.n, 0) AS support FROM universe x JOIN universe y ON x.item < y.item LEFT JOIN q ON q.itemset = x.item || '|' || y.item),
    u AS (SELECT * FROM u1 UNION ALL SELECT * FROM u2), ck AS (SELECT support AS ck FROM u ORDER BY support DESC, size, itemset LIMIT 1 OFFSET {_TF_K - 1}),
    f AS (SELECT itemset, size, support, greatest(support::DOUBLE, ck - 4 * {_TF_K} / {_TF_EPS} * (ln({_TF_K} / 0.9) + ln({_SPACE}))) AS truncated FROM u, ck)"""


@query(f"WITH {_TF} SELECT itemset, size::INT AS size, support, round(truncated, 6) AS truncated FROM f")
def tf_truncated_frequencies(spark: SparkSession, sf_dir: str) -> DataFrame:
    return truncated.truncated_counts(_view("order_brands", spark, sf_dir), _TF_K, _TF_M, _TF_EPS).withColumn("truncated", F.round("truncated", 6))


@query(f"WITH {_TF} SELECT itemset, size::INT AS size, support FROM f WHERE support > ck_floor.v".replace("FROM f WHERE support > ck_floor.v", f"FROM f, ck WHERE support > ck - 4 * {_TF_K} / {_TF_EPS} * (ln({_TF_K} / 0.9) + ln({_SPACE}))"))
def tf_explicit_itemsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    tx = _view("order_brands", spark, sf_dir)
    n, best = tx.size(), mining.topk(tx, _TF_K, _TF_M)
    floor = best[_TF_K - 1].support - truncated.truncation_margin(_TF_K, _TF_EPS, n, 0.9, _SPACE) * n
    return _frame(spark, truncated.explicit_itemsets(tx, _TF_M, floor))


def _tf_sql(selector: str, eps: float, exactly: bool = False) -> str:
    """CTEs up to chosen(itemset): the baseline's choice among all candidates, listed ones by their own draws, the rest by order statistics."""
    label, scale, space = f"42:select-{selector}", 4 * _TF_K / eps, truncated.candidate_space(25, _TF_M, exactly)
    key, gumbel = f"'{label}:' || itemset", selector == "exponential"
    start = f"value / {scale}" if gumbel else "value"
    own = f"greatest(support::DOUBLE, value) / {scale} + {S.gumbel(key)}" if gumbel else f"greatest(support::DOUBLE, value) + {S.laplace(key, str(scale))}"
    draw = "-ln(greatest(-lu, 5e-324))" if gumbel else f"CASE WHEN exp(lu) > 0.5 THEN -{scale} * ln(2 * (1 - exp(lu))) ELSE {scale} * ln(2 * exp(lu)) END"
    u = lambda what: S.uniform(f"'{label}:{what}:' || j")
    size = "2" if exactly else f"CASE WHEN {S.uniform(chr(39) + label + ':size:' + chr(39) + ' || t')} * {space} <= 25 THEN 1 ELSE 2 END"
    index = f"floor({S.uniform(chr(39) + label + ':item:' + chr(39) + ' || t || ' + chr(39) + ':' + chr(39) + ' || s')} * 25)::INT"
    return f"""{_TF.split("ck AS (")[0].rstrip().rstrip(",")}, uu AS (SELECT * FROM u{' WHERE size = 2' if exactly else ''}),
        ck AS (SELECT support AS ck FROM uu ORDER BY support DESC, size, itemset LIMIT 1 OFFSET {_TF_K - 1}),
        fl AS (SELECT ck - {scale} * (ln({_TF_K} / 0.9) + ln({space})) AS floor, greatest(ck - {scale} * (ln({_TF_K} / 0.9) + ln({space})), 0) AS value FROM ck),
        listed AS (SELECT itemset, support, value FROM uu, fl WHERE support > floor AND support > 0),
        own AS (SELECT itemset, round({own}, 9) AS score, row_number() OVER (ORDER BY round({own}, 9) DESC, itemset) AS r FROM listed),
        beat AS (SELECT CASE WHEN (SELECT count(*) FROM own) >= {_TF_K} THEN (SELECT score FROM own WHERE r = {_TF_K}) ELSE -1e300 END AS beat, {space} - (SELECT count(*) FROM listed) AS left_over),
        logs AS (SELECT j, sum(ln({u('tail')}) / (left_over - j)) OVER (ORDER BY j) AS lu FROM range(0, {_TF_K}) t(j), beat WHERE j < left_over),
        tail AS (SELECT j, {start} + {draw} AS score FROM logs, fl), high AS (SELECT j, score FROM tail, beat WHERE score > beat), many AS (SELECT count(*) AS many FROM high),
        names AS (SELECT item, row_number() OVER (ORDER BY item) - 1 AS spot FROM universe), steps AS (SELECT t, s, {index} AS spot FROM range(0, 1000) a(t), range(0, 9) b(s)),
        trials AS (SELECT t, {size} AS size FROM range(0, 1000) a(t)), one AS (SELECT t, spot FROM steps WHERE s = 0),
        two AS (SELECT s.t, arg_min(s.spot, s.s) AS spot FROM steps s JOIN one ON one.t = s.t AND s.s > 0 AND s.spot <> one.spot GROUP BY s.t),
        drawn AS (SELECT trials.t, CASE WHEN size = 1 THEN x.item ELSE least(x.item, y.item) || '|' || greatest(x.item, y.item) END AS itemset
            FROM trials JOIN one ON one.t = trials.t JOIN two ON two.t = trials.t JOIN names x ON x.spot = one.spot JOIN names y ON y.spot = two.spot),
        unlisted AS (SELECT itemset, min(t) AS t FROM drawn ANTI JOIN listed USING (itemset) GROUP BY itemset),
        rest AS (SELECT itemset, {S.uniform(chr(39) + label + ':member:' + chr(39) + ' || itemset')} AS t FROM uu ANTI JOIN listed USING (itemset)),
        few AS (SELECT left_over <= greatest(64, 4 * many) AS few FROM beat, many),
        members AS (SELECT itemset, row_number() OVER (ORDER BY t) - 1 AS j FROM (SELECT itemset, t::DOUBLE AS t FROM unlisted, few WHERE NOT few UNION ALL SELECT itemset, t FROM rest, few WHERE few)),
        mixed AS (SELECT itemset, score, 0 AS last FROM own WHERE r <= {_TF_K} UNION ALL SELECT itemset, score, 1 FROM high JOIN members USING (j)),
        chosen AS (SELECT itemset FROM mixed ORDER BY score DESC, last LIMIT {_TF_K})"""


def _tf_select(selector: str, eps: float) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        with _view("order_brands", spark, sf_dir).remembering() as tx:
            chosen = truncated.select(tx, _TF_K, _TF_M, eps, NOISE, selector=selector)
            counts = mining.supports(tx, chosen)
            return spark.createDataFrame([(mining.key_of(c), len(c), counts[c]) for c in chosen], "itemset string, size int, support long")

    return run


#: Budgets at which most of the candidates are listed, few of them, and none that a draw would reach.
for _name, _selector, _eps in (("exponential", "exponential", _TF_EPS), ("exponential_small_budget", "exponential", 4.0), ("laplace", "laplace", _TF_EPS), ("laplace_small_budget", "laplace", 1.0)):
    QUERIES[f"tf_select_{_name}"] = _tf_select(_selector, _eps)
    ORACLES[f"tf_select_{_name}"] = f"WITH {_tf_sql(_selector, _eps)} SELECT itemset, size::INT AS size, support FROM uu JOIN chosen USING (itemset)"

_SCALE = 4 * _TF_K / _TF_EPS


def _tf_exhaustive(selector: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = truncated.truncated_counts(_view("order_brands", spark, sf_dir), _TF_K, _TF_M, _TF_EPS)
        return truncated.exhaustive_select(rows, "truncated", _TF_K, _TF_EPS, NOISE, "tf", selector).select("itemset", "size", "support")

    return run


for _name, _score in (("exponential", f"truncated / {_SCALE} + {S.gumbel(chr(39) + '42:tf:' + chr(39) + ' || itemset')}"), ("laplace", f"truncated + {S.laplace(chr(39) + '42:tf:' + chr(39) + ' || itemset', str(_SCALE))}")):
    QUERIES[f"tf_exhaustive_{_name}"] = _tf_exhaustive(_name)
    ORACLES[f"tf_exhaustive_{_name}"] = f"WITH {_TF} SELECT itemset, size::INT AS size, support FROM f ORDER BY round({_score}, 9) DESC, itemset LIMIT {_TF_K}"


@query(f"WITH {_TF} SELECT itemset, size::INT AS size, support FROM f ORDER BY round(support / {_SCALE} + {S.gumbel(chr(39) + '42:all:' + chr(39) + ' || itemset')}, 9) DESC, itemset LIMIT {_TF_K}")
def exhaustive_release(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = truncated.enumerated(_view("order_brands", spark, sf_dir), _TF_M)
    return truncated.exhaustive_select(rows, "support", _TF_K, _TF_EPS, NOISE, "all").select("itemset", "size", "support")


def _tf_release_sql(exactly: bool) -> str:
    noisy = f"support + {S.laplace(chr(39) + '42:truncated:' + chr(39) + ' || itemset', f'{_TF_K} / ({_TF_EPS} * 0.5)')}"
    return f"WITH {_tf_sql('exponential', _TF_EPS, exactly)} SELECT itemset, size::INT AS size, round({noisy}, 6) AS noisy_count, round(({noisy}) / {S.N}, 9) AS noisy_freq FROM uu JOIN chosen USING (itemset)"


@query(_tf_release_sql(False))
def tf_release_brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    return truncated.truncated_release(_view("order_brands", spark, sf_dir), _TF_K, _TF_M, _TF_EPS, NOISE)


@query(_tf_release_sql(True))
def tf_release_exactly_m(spark: SparkSession, sf_dir: str) -> DataFrame:
    return truncated.truncated_release(_view("order_brands", spark, sf_dir), _TF_K, _TF_M, _TF_EPS, NOISE, exactly=True)


@query(_zero_sql(["chosen_too_rare", "missed_frequent"]))
def tf_guarantee_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    tx = _view("order_brands", spark, sf_dir)
    n, best = tx.size(), mining.topk(tx, _TF_K, _TF_M)
    truth = {r["itemset"]: r["support"] / n for r in truncated.enumerated(tx, _TF_M).collect()}
    margin = truncated.truncation_margin(_TF_K, _TF_EPS, n, 0.9, _SPACE)
    missed, rare = truncated.guarantee_violations(truncated.select(tx, _TF_K, _TF_M, _TF_EPS, NOISE), truth, best[_TF_K - 1].support / n, margin)
    return spark.createDataFrame([("chosen_too_rare", rare), ("missed_frequent", missed)], "check_name string, violations int")


_DIRECT = [("Brand#1",), ("Brand#2",), ("Brand#1", "Brand#2"), ("Brand#10", "Brand#11")]


@query(f"""WITH {S.d('order_brands')}, g AS (SELECT * FROM (VALUES {', '.join(f"('{mining.key_of(s)}', {list(s)})" for s in _DIRECT)}) AS t(itemset, items)), w AS (SELECT itemset, len(items) AS size, unnest(items) AS item FROM g),
    h AS (SELECT itemset, tid FROM w JOIN d USING (item) GROUP BY itemset, tid, size HAVING count(*) = size), s AS (SELECT g.itemset, any_value(len(items))::INT AS size, count(h.tid) AS support FROM g LEFT JOIN h USING (itemset) GROUP BY 1),
    r AS (SELECT itemset, size, support + {S.laplace("'42:direct:' || itemset", '4.0 / 0.5')} AS x FROM s) SELECT itemset, size, round(x, 6) AS noisy_count, round(x / {S.N}, 9) AS noisy_freq FROM r""")
def direct_release(spark: SparkSession, sf_dir: str) -> DataFrame:
    return truncated.direct_release(_view("order_brands", spark, sf_dir), _DIRECT, 0.5, NOISE)


_EFFECTIVE = ("order_brands", "order_terms", "line_records", "cust_terms", "user_day_clicks", "embedding_signs")


def _effective_sql(view: str, k: int, sets: str, items: int | None = None) -> str:
    return f"""SELECT '{view}' AS "view", {k}::INT AS k, m::INT AS m, ck::BIGINT AS c_k, round(4.0 * {k} * (ln({k} / 0.9) + ln(u)), 6) AS margin_n, u AS space, 4.0 * {k} * (ln({k} / 0.9) + ln(u)) < ck AS effective FROM (
        WITH {S.counts(view)}, {sets}, ms AS (SELECT unnest([1, 2]) AS m), i AS (SELECT count(*)::DOUBLE AS i FROM c),
        r AS (SELECT m, support, row_number() OVER (PARTITION BY m ORDER BY support DESC, size, itemset) AS r FROM s, ms WHERE size <= m)
        SELECT ms.m, coalesce(r.support, 0) AS ck, CASE ms.m WHEN 1 THEN i ELSE i + i * (i - 1) / 2 END AS u FROM ms CROSS JOIN i LEFT JOIN r ON r.m = ms.m AND r.r = {k})"""


@query(" UNION ALL ".join(_effective_sql(v, 20, S.small_sets(70, 2)) for v in _EFFECTIVE))
def tf_effectiveness_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return experiments.effectiveness(spark, sf_dir, _EFFECTIVE, 20, (1, 2))


# --- measures and experiments ---------------------------------------------


def _grid(name: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return experiments.summary(experiments.run_grid(spark, sf_dir, experiments.WORKLOADS[name]))

    return run


for _name in experiments.WORKLOADS:
    QUERIES[f"experiment_{_name}"] = _grid(_name)


@query(f"""WITH {S.counts('order_brands')}, s AS (SELECT unnest([1, 2, 3]) AS seed), e AS (SELECT item, abs({S.laplace("seed || ':repeat:' || item", '2.0')}) / n AS e FROM c, s)
    SELECT item, round(avg(e), 9) AS mean, round(stddev_samp(e) / sqrt(count(*)), 9) AS std_error, count(*) AS runs FROM e GROUP BY item""")
def repeat_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean and standard error of the relative error of item counts over three repeats."""
    counts, rows = _view("order_brands", spark, sf_dir).item_counts(), None
    for seed in (1, 2, 3):
        noisy = mechanisms.laplace_release(counts, "n", 1.0, 0.5, ["item"], NoiseSource.fixed(seed), "repeat")
        one = noisy.select("item", (F.abs(F.col("noisy") - F.col("n")) / F.col("n")).alias("e"))
        rows = one if rows is None else rows.unionByName(one)
    return metrics.repeats(rows, ["item"], "e").select("item", F.round("mean", 9).alias("mean"), F.round("std_error", 9).alias("std_error"), "runs")


_BASIS_K = 50


@query(f"""WITH rel AS ({_single_release_sql('line_records', _BASIS_K, 60, 13)}), tru AS ({S.topk('line_records', _BASIS_K, S.bitmap_sets(13))}), al AS ({S.topk('line_records', 3000, S.bitmap_sets(13))})
    SELECT round((SELECT count(*) FROM tru ANTI JOIN rel USING (itemset)) / 50.0, 9)::DOUBLE AS fnr, round((SELECT count(*) FROM rel ANTI JOIN tru USING (itemset)) / 50.0, 9)::DOUBLE AS fpr, round((SELECT count(*) FROM rel SEMI JOIN tru USING (itemset)) / 50.0, 9)::DOUBLE AS precision,
    (SELECT round(median(abs(noisy_freq - freq) / freq), 6) FROM rel JOIN al USING (itemset)) AS re""")
def fnr_re_basis_line_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    with _view("line_records", spark, sf_dir).remembering() as tx:
        out, truth, n = R.release_topk_private(tx, _BASIS_K, 1.0, NOISE).itemsets, mining.topk_frame(tx, _BASIS_K), tx.size()
        published = [tuple(r["itemset"].split("|")) for r in out.select("itemset").collect()]  # k sets
        exact = spark.createDataFrame([(mining.key_of(s), c / n) for s, c in mining.supports(tx, published).items()], "itemset string, freq double")
    rates = metrics.false_negative_rate(out, truth, _BASIS_K).crossJoin(metrics.false_positive_rate(out, truth, _BASIS_K)).crossJoin(metrics.precision(out, truth, _BASIS_K))
    both = rates.crossJoin(metrics.relative_error(out, exact).select(F.round("re", 6).alias("re")))
    return both.select(F.round("fnr", 9).alias("fnr"), F.round("fpr", 9).alias("fpr"), F.round("precision", 9).alias("precision"), "re")


_TOY = [set("abc"), set("abc"), set("abd"), set("ab"), set("acd"), set("bcd"), set("ae"), set("b"), set("ce"), set("abcd")]


@query("SELECT * FROM (VALUES (0, 0), (1, 1), (2, 1), (3, 2), (4, 1), (5, 1), (6, 1), (7, 3)) AS t(mask, n)".replace("SELECT *", "SELECT mask::INT AS mask, n::BIGINT AS n"))
def toy_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight bins of a basis of three items; a pair's count is the sum of two of them."""
    b = B.BasisSet.of(["abc"])
    return bins.complete_bins(bins.bin_counts(Transactions.from_sets(spark, _TOY), b), b).select("mask", "n")


def _errors(measure: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = experiments.run_grid(spark, sf_dir, experiments.WORKLOADS["single_basis_records"], (0.25, 1.0), (1, 2, 3), (50,), (3,))
        return experiments.error_table(rows, measure)

    return run


QUERIES["fnr_basis_vs_tf"] = _errors("fnr")
QUERIES["relative_error_basis_vs_tf"] = _errors("re")


@query()
def tf_best_m(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The baseline's length limit with the best mean precision at each k and budget, and that precision."""
    rows = experiments.run_grid(spark, sf_dir, experiments.WORKLOADS["few_bases_terms"], (0.5, 1.0), ks=(50,))
    best = experiments.best_m(rows).where("method = 'truncated'")
    return best.groupBy("view", "k", "eps", "m").agg(F.round(F.avg("precision"), 9).alias("precision"), F.round(F.avg("fnr"), 9).alias("fnr"))


@query(_zero_sql(["fnr_and_precision_add_up", "best_m_has_best_precision", "summary_has_every_point", "shared_passes_change_nothing"]))
def experiment_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The grid on one workload: its runs are those that a release of its own makes, and what is summed up is consistent."""
    workload, budgets = experiments.WORKLOADS["few_bases_terms"], (0.5, 1.0)
    rows = experiments.run_grid(spark, sf_dir, workload, budgets, (1, 2), (50,))
    got = [r.asDict() for r in rows.collect()]
    with _view("order_terms", spark, sf_dir).remembering() as tx:
        truth, params = mining.topk(tx, 50), R.ReleaseParams(max_basis_len=workload.max_basis_len)
        alone = [metrics.measured(tx, R.release_topk_private(tx, 50, 0.5, NoiseSource.fixed(s), params).ranked(), truth, 50) for s in (1, 2)]
    same = [r for r in got if r["method"] == "basis" and r["eps"] == 0.5]
    best = {(r["eps"], r["m"]): r["p"] for r in rows.where("method = 'truncated'").groupBy("eps", "m").agg(F.avg("precision").alias("p")).collect()}
    picked = {r["eps"]: r["m"] for r in experiments.best_m(rows).where("method = 'truncated'").select("eps", "m").distinct().collect()}
    points = experiments.summary(rows).select("method", "eps").collect()
    ok = {
        "fnr_and_precision_add_up": all(abs(r["fnr"] + r["precision"] - 1) < 1e-9 for r in got),
        "best_m_has_best_precision": all(best[e, m] >= max(p for (x, _), p in best.items() if x == e) - 1e-12 for e, m in picked.items()),
        "summary_has_every_point": sorted((r["method"], r["eps"]) for r in points) == sorted((m, e) for m in ("basis", "truncated") for e in budgets),
        "shared_passes_change_nothing": all(abs(r["fnr"] - a["fnr"]) < 1e-9 and abs(r["re"] - a["re"]) < 1e-6 for r, a in zip(sorted(same, key=lambda r: r["seed"]), alone, strict=True)),
    }
    return spark.createDataFrame(_zero_rows(ok), "check_name string, violations int")


@query(_zero_sql([f"group_of_{g}" for g in range(1, 7)]))
def grouping_factor_by_draws(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measured variance of single items in bases of a size against one basis an item, over a draw for each customer who ordered: within five standard errors of the factor."""
    runs = read(spark, sf_dir, "orders").select(F.col("o_custkey").alias("run")).distinct()
    checks = {}
    for g in range(1, 7):
        width = 12 / g  # twelve items in bases of g, so a bin's noise has this scale at a budget of 1
        bins_of_one = spark.range(1 << (g - 1)).select(F.col("id").alias("mask"))
        draws = runs.crossJoin(F.broadcast(bins_of_one)).withColumn("x", NOISE.laplace(f"group{g}", width, "run", "mask"))
        variance, n = draws.groupBy("run").agg(F.sum("x").alias("x")).agg(F.var_samp("x"), F.count("*")).first()
        checks[f"group_of_{g}"] = abs(variance / (2 * 12**2) / B.grouping_factor(g) - 1) < 5 * math.sqrt(5 / n)  # a Laplace draw has a kurtosis of 6, sums of them less
    return spark.createDataFrame(_zero_rows(checks), "check_name string, violations int")


@query(_zero_sql(["items", "bins_of_two_bases", "rank_quality"]))
def sensitivity_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measured sensitivities on the toy set against the ones that scale the noise."""
    tx, two = Transactions.from_sets(spark, _TOY, "abcde"), B.BasisSet.of(["abc", "cde"])
    some = (0, 4, 8)
    item = lambda t: {r["item"]: r["n"] for r in t.item_counts().collect()}
    table = lambda t: {(r["basis_id"], r["mask"]): r["n"] for r in bins.bin_counts(t, two).collect()}
    rank = lambda t: {r["j"]: r["quality"] for r in R.rank_scores(t, 4, 1.0).collect()}
    whole = item(tx)
    ok = {
        "items": all(abs(whole[k] - n) <= 1 for t in some for k, n in item(tx.without(t)).items()),
        "bins_of_two_bases": metrics.empirical_l1_sensitivity(table, tx, some) <= two.width,
        "rank_quality": all(abs(rank(tx)[j] - q) <= 1 for t in some[:2] for j, q in rank(tx.without(t)).items() if j in rank(tx)),
    }
    return spark.createDataFrame(_zero_rows(ok), "check_name string, violations int")


@query("SELECT 'variance' AS check_name, 0 AS violations")
def empirical_variance_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measured variance of every subset of a basis over 400 draws within 30 % of the formula."""
    b, eps = _bases(SINGLE), 0.5
    full = bins.complete_bins(bins.bin_counts(_view("order_brands", spark, sf_dir), b), b)
    rows = metrics.empirical_variance(full, 1, b.length, eps, 400, NOISE).collect()
    bad = sum(abs(r["variance"] / B.error_variance(3, bin(r["mask"]).count("1"), 1, eps) - 1) > 0.3 for r in rows)
    return spark.createDataFrame([("variance", bad)], "check_name string, violations int")


@query("SELECT 'audit' AS check_name, 0 AS violations")
def privacy_audit_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of the count of a brand, with and without one of its orders."""
    tx = _view("order_brands", spark, sf_dir)
    with_brand = tx.rows.where(F.array_contains("items", "Brand#1"))
    one = with_brand.agg(F.min("tid")).first()[0]
    count = lambda t: t.item_counts().where("item = 'Brand#1'").first()["n"]
    worst = metrics.privacy_audit(lambda c, source: c + source.laplace_value("a", 1.0), (count(tx), count(tx.without(one))), 1.0, 6000)
    return spark.createDataFrame([("audit", int(worst > 4))], "check_name string, violations int")


@query(f"WITH {S.d('order_brands')} SELECT count(*) AS n FROM (SELECT tid FROM d GROUP BY tid HAVING list_has_all(list(item), ['Brand#1', 'Brand#2']))")
def sql_front_door(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..sources.views import register_views

    register_views(spark, sf_dir, ["order_brands"])
    return spark.sql("SELECT count(*) AS n FROM tx_order_brands WHERE size(array_intersect(items, array('Brand#1', 'Brand#2'))) = 2")
