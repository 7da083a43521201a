"""DuckDB text for the checks: views, noise, top-k, bins."""

from __future__ import annotations

from ..sources.views import TIDS_SQL, UNIVERSE_SQL, VIEW_SQL


def d(view: str) -> str:
    """CTEs d(tid, item) and tids(tid), which also has the transactions without an item."""
    return f"d AS (SELECT tid, item FROM ({VIEW_SQL[view]}) WHERE item IS NOT NULL), tids AS ({TIDS_SQL.get(view, 'SELECT DISTINCT tid FROM d')})"


#: The number of transactions, after d.
N = "(SELECT count(*) FROM tids)"


def universe(view: str) -> str:
    return f"universe AS ({UNIVERSE_SQL[view]})"


def counts(view: str) -> str:
    """CTEs d and c(item, n), zero supports included where the view has a universe."""
    if view not in UNIVERSE_SQL:
        return f"{d(view)}, c AS (SELECT item, count(*) AS n FROM d GROUP BY item)"
    return f"{d(view)}, {universe(view)}, c AS (SELECT u.item, count(d.tid) AS n FROM universe u LEFT JOIN d USING (item) GROUP BY u.item)"


def uniform(key: str) -> str:
    return f"((('0x' || substr(sha256({key}), 1, 13))::BIGINT + 0.5) / 4503599627370496.0)"


def laplace(key: str, scale: str) -> str:
    u = uniform(key)
    return f"(-({scale}) * sign({u} - 0.5) * ln(1 - 2 * abs({u} - 0.5)))"


def gumbel(key: str) -> str:
    return f"(-ln(-ln({uniform(key)})))"


def small_sets(pool: int, largest: int = 3) -> str:
    """CTE s(itemset, size, support): sets of up to ``largest`` of the ``pool`` most frequent items, after c and d."""
    out = f"pool AS (SELECT item FROM c ORDER BY n DESC, item LIMIT {pool}), p AS (SELECT d.tid, d.item FROM d JOIN pool USING (item)), "
    parts = ["SELECT item AS itemset, 1 AS size, count(*) AS support FROM p GROUP BY item"]
    if largest > 1:
        parts.append("SELECT x.item || '|' || y.item, 2, count(*) FROM p x JOIN p y ON x.tid = y.tid AND x.item < y.item GROUP BY 1")
    if largest > 2:
        parts.append("SELECT x.item || '|' || y.item || '|' || z.item, 3, count(*) FROM p x JOIN p y ON x.tid = y.tid AND x.item < y.item JOIN p z ON y.tid = z.tid AND y.item < z.item GROUP BY 1")
    return out + "s AS (" + " UNION ALL ".join(parts) + ")"


def bitmap_sets(pool: int) -> str:
    """CTE s of all sets of the ``pool`` most frequent items (16 at most), by masks, after c and d."""
    return f"""pool AS (SELECT item, row_number() OVER (ORDER BY n DESC, item) - 1 AS pos FROM c ORDER BY n DESC, item LIMIT {pool}),
        hist AS (SELECT m, count(*) AS cnt FROM (SELECT tid, sum(1 << pos)::BIGINT AS m FROM d JOIN pool USING (item) GROUP BY tid) GROUP BY m),
        masks AS (SELECT unnest(range(1, (1 << {pool})::BIGINT)) AS x),
        sup AS (SELECT x, sum(cnt)::BIGINT AS support FROM masks JOIN hist ON (m & x) = x GROUP BY x),
        best AS (SELECT * FROM sup ORDER BY support DESC, bit_count(x) LIMIT 4000),
        s AS (SELECT string_agg(item, '|' ORDER BY item) AS itemset, count(*) AS size, any_value(support) AS support FROM best JOIN pool ON (x >> pos) & 1 = 1 GROUP BY x)"""


def topk(view: str, k: int, sets: str) -> str:
    return f"""WITH {counts(view)}, {sets}, n AS (SELECT count(*) AS n FROM tids)
        SELECT row_number() OVER (ORDER BY support DESC, size, itemset)::INT AS rank, itemset, size::INT AS size, support::BIGINT AS support, round(support / n.n, 9) AS freq
        FROM s, n ORDER BY support DESC, size, itemset LIMIT {k}"""


def basis_values(bases: list[tuple[str, ...]]) -> str:
    rows = ", ".join(f"({b}, {p}, '{i}')" for b, items in enumerate(bases) for p, i in enumerate(sorted(items)))
    return f"bas AS (SELECT * FROM (VALUES {rows}) AS t(basis_id, pos, item))"


#: CTEs after d and bas: bins(basis_id, mask, n), complete.
BINS = """ids AS (SELECT basis_id, count(*) AS len FROM bas GROUP BY basis_id),
    t AS (SELECT tid FROM tids),
    held AS (SELECT basis_id, tid, sum(1 << pos)::BIGINT AS mask FROM d JOIN bas USING (item) GROUP BY basis_id, tid),
    seen AS (SELECT i.basis_id, coalesce(h.mask, 0)::BIGINT AS mask, count(*) AS n FROM t CROSS JOIN ids i LEFT JOIN held h ON h.tid = t.tid AND h.basis_id = i.basis_id GROUP BY 1, 2),
    dom AS (SELECT basis_id, len, unnest(range(0, (1::BIGINT << len))) AS mask FROM ids),
    bins AS (SELECT dom.basis_id, dom.len, dom.mask, coalesce(seen.n, 0) AS n FROM dom LEFT JOIN seen USING (basis_id, mask))"""


def noisy(width: str, eps: str, seed: int = 42) -> str:
    """CTE noisy(basis_id, len, mask, n, noisy) after bins; an eps of 'inf' adds nothing."""
    noise = "0.0" if eps == "inf" else laplace(f"'{seed}:bins:' || basis_id || ':' || mask", f"({width})::DOUBLE / {eps}")
    return f"noisy AS (SELECT *, n + {noise} AS noisy FROM bins)"


#: CTEs after noisy: sums, named, fused(itemset, size, nc, v).
FUSED = """sums AS (SELECT a.basis_id, a.len, a.mask, sum(b.noisy) AS nc FROM noisy a JOIN noisy b ON a.basis_id = b.basis_id AND (b.mask & a.mask) = a.mask GROUP BY 1, 2, 3),
    named AS (SELECT s.basis_id, s.mask, s.nc, coalesce(string_agg(bas.item, '|' ORDER BY bas.item), '') AS itemset, count(bas.item)::INT AS size, pow(2.0, s.len - count(bas.item)) AS v
        FROM sums s LEFT JOIN bas ON bas.basis_id = s.basis_id AND (s.mask >> bas.pos) & 1 = 1 GROUP BY s.basis_id, s.mask, s.nc, s.len),
    fused AS (SELECT itemset, size, sum(nc / v) / sum(1 / v) AS nc, 1 / sum(1 / v) AS v FROM named GROUP BY itemset, size)"""


def released(k: int, n: str, scale: str) -> str:
    return f"""SELECT itemset, size, round(nc, 6) AS noisy_count, round(nc / {n}, 9) AS noisy_freq, round(v * {scale}, 6) AS variance
        FROM fused WHERE size > 0 ORDER BY round(nc, 6) DESC, size, itemset LIMIT {k}"""
