"""Queries of the operators, sources and functions around the methods."""

from __future__ import annotations

import atexit
import contextlib
import re
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.noise import NoiseSource, register_sql
from ..functions.tables import register_tables
from ..operators.mining import itemset_of
from ..sources import files
from ..sources.views import VIEWS, read
from ..streaming import windows
from . import sqltext as S

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def register(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return register


def _shared(spark: SparkSession, name: str) -> str:
    """A fresh path that all executors reach: below the checkpoint folder, or in the warehouse where none is set.

    What earlier queries of this application left there has been read by now,
    or is about to be: it goes when the application ends.
    """
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        base = tempfile.gettempdir() if spark.sparkContext.master.startswith("local") else spark.conf.get("spark.sql.warehouse.dir")
    path = f"{base}/dp-itemsets-{name}-{uuid.uuid4().hex}"
    atexit.register(_remove, spark, path)
    return path


def _remove(spark: SparkSession, path: str) -> None:
    with contextlib.suppress(Exception):  # the session may be gone by then
        target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def _sql(name: str, text: str, duck: str | None = None) -> None:
    """A query in SQL over temporary views of the tables it names."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        tables = ("lineitem", "orders", "customer", "part", "nation", "region", "supplier", "events", "documents", "pages", "conversations", "embeddings")
        return spark.sql(text, **{t: read(spark, sf_dir, t) for t in tables if f"{{{t}}}" in text})

    QUERIES[name] = run
    ORACLES[name] = duck or re.sub(r"\{(\w+)\}", r"\1", text)


# --- scans, projections, predicates ----------------------------------------


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem WHERE l_shipdate < TIMESTAMP '1998-09-02' AND l_quantity > 10 GROUP BY 1, 2")
def scan_lineitem_pushed(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "lineitem").where((F.col("l_shipdate") < F.lit("1998-09-02").cast("timestamp_ntz")) & (F.col("l_quantity") > 10))
    return rows.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


def _round_trip(name: str, write: Callable, load: Callable) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        path = _shared(spark, name)
        write(VIEWS["order_brands"](spark, sf_dir), path)
        return load(spark, path).item_counts()

    QUERIES[name] = run
    ORACLES[name] = f"WITH {S.d('order_brands')} SELECT item, count(*) AS n FROM d GROUP BY item"


_round_trip("scan_transaction_lines", files.write_lines, files.read_lines)
_round_trip("scan_csv", lambda tx, p: files.write_release(tx.long(), p, "csv"), files.read_csv)
_round_trip("scan_json_lines", lambda tx, p: files.write_release(tx.rows, p, "json"), files.read_json)


@query("SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def sink_partitioned_parquet(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "customer").join(F.broadcast(read(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(read(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    path = _shared(spark, "regions")
    files.write_release(rows.select("c_custkey", "r_name"), path, "parquet", ["r_name"])
    return spark.read.parquet(path).groupBy("r_name").agg(F.count("*").alias("n"))


@query(f"WITH {S.d('order_brands')} SELECT item, count(*) AS n FROM d GROUP BY item")
def sink_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Transactions in long form as a table, bucketed by transaction, and their counts from it."""
    name = f"tx_{uuid.uuid4().hex}"
    files.write_table(VIEWS["order_brands"](spark, sf_dir), name)
    atexit.register(_drop, spark, name)
    return files.read_table(spark, name).item_counts()


def _drop(spark: SparkSession, name: str) -> None:
    with contextlib.suppress(Exception):
        spark.sql(f"DROP TABLE IF EXISTS {name}")


_sql("project_coded_items", "SELECT concat_ws('=', 'flag', l_returnflag) AS item, CAST(l_linenumber AS BIGINT) + 1 AS next_line, count(*) AS n FROM {lineitem} GROUP BY 1, 2")
_sql("filter_predicates", "SELECT o_orderstatus, count(*) AS n FROM {orders} WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus LIKE '%O%' OR o_totalprice BETWEEN 1000 AND 50000 GROUP BY o_orderstatus")
_sql("filter_regex_null", "SELECT count(*) AS n, count(nullif(p_size, 1)) AS no_ones FROM {part} WHERE regexp_like(p_name, '^(small|red) ') AND p_brand IS NOT NULL", "SELECT count(*) AS n, count(nullif(p_size, 1)) AS no_ones FROM part WHERE regexp_matches(p_name, '^(small|red) ') AND p_brand IS NOT NULL")
_sql("filter_bit_test", "SELECT p_size & 5 AS bits, count(*) AS n FROM {part} WHERE (p_size & 5) = 5 GROUP BY 1")

# --- joins -----------------------------------------------------------------

_sql("join_inner", "SELECT o_orderpriority, count(*) AS n FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey GROUP BY o_orderpriority", "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority")
_sql("join_broadcast", "SELECT /*+ BROADCAST(n) */ n_name, count(*) AS n FROM {customer} c JOIN {nation} n ON c.c_nationkey = n.n_nationkey GROUP BY n_name", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
_sql("join_left_outer", "SELECT c_mktsegment, count(*) AS n, count(o_orderkey) AS orders FROM {customer} c LEFT JOIN {orders} o ON c.c_custkey = o.o_custkey GROUP BY c_mktsegment", "SELECT c_mktsegment, count(*) AS n, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_mktsegment")
_FULL = "WITH a AS (SELECT p_brand, count(*) AS x FROM {part} WHERE p_size < 5 GROUP BY 1), b AS (SELECT p_brand, count(*) AS y FROM {part} WHERE p_size > 48 GROUP BY 1) SELECT coalesce(a.p_brand, b.p_brand) AS brand, x, y FROM a FULL JOIN b ON a.p_brand = b.p_brand"
_sql("join_full_outer", _FULL)
_sql("join_semi", "SELECT count(*) AS n FROM {customer} c LEFT SEMI JOIN {orders} o ON c.c_custkey = o.o_custkey", "SELECT count(*) AS n FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
_sql("join_anti", "SELECT c_custkey FROM {customer} c LEFT ANTI JOIN {orders} o ON c.c_custkey = o.o_custkey", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")


@query(f"WITH {S.d('order_brands')} SELECT x.item AS a, y.item AS b, count(*) AS n FROM d x JOIN d y ON x.tid = y.tid AND x.item < y.item GROUP BY 1, 2")
def join_self_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    long = VIEWS["order_brands"](spark, sf_dir).long()
    x, y = long.select("tid", F.col("item").alias("a")), long.select("tid", F.col("item").alias("b"))
    return x.join(y, "tid").where("a < b").groupBy("a", "b").agg(F.count("*").alias("n"))


_sql("join_theta_subset", "WITH m AS (SELECT l_linenumber AS m, count(*) AS n FROM {lineitem} GROUP BY 1) SELECT a.m AS lower_mask, count(*) AS supersets, CAST(sum(b.n) AS BIGINT) AS lines FROM m a JOIN m b ON (b.m & a.m) = a.m GROUP BY a.m")
_sql("join_grid", "SELECT k, eps FROM (SELECT DISTINCT l_linenumber AS k FROM {lineitem}) a CROSS JOIN (SELECT DISTINCT l_tax AS eps FROM {lineitem}) b")


@query("""SELECT p.event_id, count(c.event_id) AS clicks FROM events p LEFT JOIN events c ON c.user_id = p.user_id AND c.event_type = 'click' AND c.ts < p.ts AND c.ts >= p.ts - INTERVAL 24 HOUR
    WHERE p.event_type = 'purchase' GROUP BY p.event_id""")
def join_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clicks in the day before a purchase.  Days are equi-join buckets, so the range condition only sees two of them."""
    e = read(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    day = 86_400_000_000
    bought = e.where("event_type = 'purchase'").select("event_id", "user_id", "t", F.explode(F.array(F.floor(F.col("t") / day), F.floor(F.col("t") / day) - 1)).alias("b"))
    clicks = e.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("t").alias("ct"), F.floor(F.col("t") / day).alias("cb"))
    hit = (F.col("user_id") == F.col("u")) & (F.col("b") == F.col("cb")) & (F.col("ct") < F.col("t")) & (F.col("ct") >= F.col("t") - day)
    return bought.join(clicks, hit, "left").groupBy("event_id").agg(F.count("u").alias("clicks"))


@query("""SELECT p.event_id, c.event_id AS before_id FROM events p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') c ON p.user_id = c.user_id AND p.ts > c.ts WHERE p.event_type = 'purchase'""")
def join_as_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The user's last view before a purchase, by one ordered pass over each user."""
    e = read(spark, sf_dir, "events").where("event_type IN ('purchase', 'view')")
    seen = F.when(F.col("event_type") == "view", F.col("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("before_id", F.last(seen, ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "before_id")


# --- aggregation and windows -------------------------------------------------

_sql("agg_basic", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS s, round(avg(l_discount), 6) AS a, min(l_tax) AS lo, max(l_tax) AS hi, round(stddev_samp(l_quantity), 6) AS sd FROM {lineitem} GROUP BY l_returnflag")
_sql("agg_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers FROM {orders} GROUP BY o_orderstatus")
_sql("agg_bits", "SELECT p_type, bit_or(p_size) AS ors, bit_and(p_size) AS ands FROM {part} GROUP BY p_type")
_sql("agg_collect_set", "SELECT p_type, array_join(sort_array(collect_set(p_brand)), '|') AS brands FROM {part} GROUP BY p_type", "SELECT p_type, string_agg(DISTINCT p_brand, '|' ORDER BY p_brand) AS brands FROM part GROUP BY p_type")
_sql("agg_median", "SELECT p_type, round(median(p_retailprice), 6) AS med, round(percentile(p_retailprice, 0.25), 6) AS q1 FROM {part} GROUP BY p_type", "SELECT p_type, round(median(p_retailprice), 6) AS med, round(quantile_cont(p_retailprice, 0.25), 6) AS q1 FROM part GROUP BY p_type")
_CUBE = "SELECT c_mktsegment, o_orderpriority, count(*) AS n FROM {orders} o JOIN {customer} c ON o.o_custkey = c.c_custkey GROUP BY "
_DUCK_CUBE = "SELECT c_mktsegment, o_orderpriority, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY "
for _n, _g in (("rollup", "ROLLUP (c_mktsegment, o_orderpriority)"), ("cube", "CUBE (c_mktsegment, o_orderpriority)"), ("grouping_sets", "GROUPING SETS ((c_mktsegment), (o_orderpriority), ())")):
    _sql(f"agg_{_n}", _CUBE + _g, _DUCK_CUBE + _g)
_sql("agg_max_by_filter", "SELECT p_type, max_by(p_brand, struct(p_retailprice, p_partkey)) AS dearest, count(*) FILTER (WHERE p_size > 25) AS large, count_if(p_size <= 25) AS small FROM {part} GROUP BY p_type HAVING count(*) > 10",
     "SELECT p_type, arg_max(p_brand, (p_retailprice, p_partkey)) AS dearest, count(*) FILTER (WHERE p_size > 25) AS large, count(*) FILTER (WHERE p_size <= 25) AS small FROM part GROUP BY p_type HAVING count(*) > 10")


@query("SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS \"F\", count(*) FILTER (WHERE o_orderstatus = 'O') AS \"O\", count(*) FILTER (WHERE o_orderstatus = 'P') AS \"P\" FROM orders GROUP BY 1")
def agg_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey")).fillna(0)


@query()
def agg_approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median_quantity"))


_RANKS = """WITH c AS (SELECT p_brand, p_type, count(*) AS n FROM {part} GROUP BY 1, 2)
    SELECT p_brand, p_type, n, row_number() OVER (PARTITION BY p_type ORDER BY n DESC, p_brand) AS rn, rank() OVER (PARTITION BY p_type ORDER BY n DESC) AS rk, dense_rank() OVER (PARTITION BY p_type ORDER BY n DESC) AS dr,
    ntile(4) OVER (PARTITION BY p_type ORDER BY n DESC, p_brand) AS q, round(percent_rank() OVER (PARTITION BY p_type ORDER BY n DESC), 6) AS pr FROM c"""
_sql("win_ranks", _RANKS)
_sql("win_support_gaps", """WITH c AS (SELECT p_brand, p_type, count(*) AS n FROM {part} GROUP BY 1, 2)
    SELECT p_brand, p_type, n - lead(n) OVER (PARTITION BY p_type ORDER BY n DESC, p_brand) AS gap, lag(n) OVER (PARTITION BY p_type ORDER BY n DESC, p_brand) AS above,
    sum(n) OVER (PARTITION BY p_type ORDER BY n DESC, p_brand ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS running, first_value(p_brand) OVER (PARTITION BY p_type ORDER BY n DESC, p_brand) AS best FROM c""")
_sql("win_range_frame", "SELECT p_partkey, count(*) OVER (PARTITION BY p_type ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM {part}")


@query("""WITH x AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events)
    SELECT user_id, sum(fresh)::BIGINT AS sessions FROM x GROUP BY user_id""")
def win_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = read(spark, sf_dir, "events").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    fresh = F.when(F.col("t") - F.lag("t").over(w) <= 7_200_000_000, F.lit(0)).otherwise(F.lit(1))
    return e.withColumn("fresh", fresh).groupBy("user_id").agg(F.sum("fresh").alias("sessions"))


# --- order, sets, subqueries ------------------------------------------------

_sql("sort_top_k", "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
_sql("sort_top_k_per_group", "SELECT p_type, p_brand, n FROM (SELECT *, row_number() OVER (PARTITION BY p_type ORDER BY n DESC, p_brand) AS r FROM (SELECT p_type, p_brand, count(*) AS n FROM {part} GROUP BY 1, 2)) WHERE r <= 3")
_A, _B = "SELECT p_brand FROM {part} WHERE p_size = 7", "SELECT p_brand FROM {part} WHERE p_size = 9"
for _n, _op in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("except_all", "EXCEPT ALL")):
    _sql(f"set_{_n}", f"{_A} {_op} {_B}")
_sql("subquery_scalar_exists", "WITH m AS (SELECT avg(o_totalprice) AS a FROM {orders}) SELECT count(*) AS n FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > (SELECT a FROM m)) AND c.c_nationkey IN (SELECT n_nationkey FROM {nation} WHERE n_regionkey < 3)",
     "WITH m AS (SELECT avg(o_totalprice) AS a FROM orders) SELECT count(*) AS n FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > (SELECT a FROM m)) AND c.c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey < 3)")

# --- functions ---------------------------------------------------------------

_sql("fn_string", "SELECT p_partkey, upper(substr(p_name, 1, 3)) AS head, length(p_name) AS len, levenshtein(p_name, 'red widget') AS dist, substr(sha2(p_name, 256), 1, 8) AS sha, regexp_replace(p_name, '[aeiou]', '') AS bare, split(p_name, ' ')[0] AS first FROM {part}",
     "SELECT p_partkey, upper(substr(p_name, 1, 3)) AS head, length(p_name) AS len, levenshtein(p_name, 'red widget') AS dist, substr(sha256(p_name), 1, 8) AS sha, regexp_replace(p_name, '[aeiou]', '', 'g') AS bare, split_part(p_name, ' ', 1) AS first FROM part")
_sql("fn_date", "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n, max(datediff(date_trunc('MONTH', o_orderdate), DATE '1992-01-01')) AS d FROM {orders} GROUP BY 1, 2",
     "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n, max(date_diff('day', DATE '1992-01-01', date_trunc('month', o_orderdate)::DATE)) AS d FROM orders GROUP BY 1, 2")
_sql("fn_math", "SELECT p_size, round(pow(2, p_size % 10) / (p_size * p_size), 9) AS f, round(ln(p_size) + exp(-p_size) + signum(p_size - 25), 9) AS g, greatest(p_size, 10) AS h, bit_count(p_size) AS b, shiftleft(1, p_size % 8) AS s, floor(p_size / 3) AS fl FROM {part} GROUP BY p_size",
     "SELECT p_size, round(pow(2, p_size % 10) / (p_size * p_size), 9) AS f, round(ln(p_size) + exp(-p_size) + sign(p_size - 25), 9) AS g, greatest(p_size, 10) AS h, bit_count(p_size)::INT AS b, 1 << (p_size % 8) AS s, floor(p_size / 3)::BIGINT AS fl FROM part GROUP BY p_size")


@query(f"""WITH {S.d('order_brands')}, a AS (SELECT tid, list_sort(list(item)) AS items FROM d GROUP BY tid)
    SELECT tid, array_to_string(list_sort(list_intersect(items, ['Brand#1', 'Brand#2', 'Brand#3'])), '|') AS kept, len(list_filter(items, lambda x: NOT list_contains(['Brand#1', 'Brand#2', 'Brand#3'], x)))::INT AS others, list_contains(items, 'Brand#4') AS has4 FROM a""")
def fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    three = F.array(*[F.lit(f"Brand#{i}") for i in (1, 2, 3)])
    return VIEWS["order_brands"](spark, sf_dir).rows.select("tid", F.array_join(F.sort_array(F.array_intersect("items", three)), "|").alias("kept"), F.size(F.array_except("items", three)).alias("others"), F.array_contains("items", "Brand#4").alias("has4"))


@query("SELECT l_linenumber % 8 AS mask, array_to_string(list_filter(['a', 'b', 'c'], lambda x, i: ((l_linenumber % 8) >> (i - 1)) & 1 = 1), '|') AS itemset, count(*) AS n FROM lineitem GROUP BY 1, 2")
def fn_masks(spark: SparkSession, sf_dir: str) -> DataFrame:
    masks = read(spark, sf_dir, "lineitem").select((F.col("l_linenumber") % 8).alias("mask"))
    return masks.select("mask", itemset_of(F.col("mask").cast("long"), ["a", "b", "c"]).alias("itemset")).groupBy("mask", "itemset").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag AS item, pos::INT AS pos, count(*) AS n FROM lineitem JOIN (VALUES ('A', 0), ('N', 1), ('R', 2)) AS t(item, pos) ON l_returnflag = item GROUP BY 1, 2")
def fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    places = F.map_from_entries(F.array(*[F.struct(F.lit(i), F.lit(p)) for p, i in enumerate("ANR")]))
    own = F.map_filter(places, lambda item, _: item == F.col("l_returnflag"))
    return read(spark, sf_dir, "lineitem").select(F.explode(own).alias("item", "pos")).groupBy("item", "pos").agg(F.count("*").alias("n"))


_sql("fn_json", "SELECT CAST(get_json_object(props, '$.k') AS INT) AS k, count(*) AS n, max(from_json(props, 'k INT').k) AS same FROM {events} GROUP BY 1", "SELECT json_extract_string(props, '$.k')::INT AS k, count(*) AS n, max(json_extract_string(props, '$.k')::INT) AS same FROM events GROUP BY 1")
_sql("fn_conditional", "SELECT CASE WHEN l_quantity > 20 THEN 'q>20' WHEN l_quantity > 10 THEN 'q>10' ELSE 'q' END AS item, count(*) AS n, sum(coalesce(nullif(l_linenumber, 1), 0)) AS s FROM {lineitem} GROUP BY 1",
     "SELECT CASE WHEN l_quantity > 20 THEN 'q>20' WHEN l_quantity > 10 THEN 'q>10' ELSE 'q' END AS item, count(*) AS n, sum(coalesce(nullif(l_linenumber, 1), 0))::BIGINT AS s FROM lineitem GROUP BY 1")
_sql("gen_explode_stack", "SELECT tag, count(*) AS n FROM (SELECT stack(2, 'type', p_type, 'brand', p_brand) AS (tag, v) FROM {part}) GROUP BY tag", "SELECT tag, count(*) AS n FROM (SELECT unnest(['type', 'brand']) AS tag FROM part) GROUP BY tag")


@query()
def sample_bernoulli(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A quick look, never part of a release."""
    return read(spark, sf_dir, "orders").sample(0.1, seed=7).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query()
def sample_stratified(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "orders").sampleBy("o_orderstatus", {"F": 0.1, "O": 0.1, "P": 0.5}, seed=7).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query("SELECT p_partkey, regexp_replace(split_part(p_name, ' ', 1), '(ing|tion|ed|es|s)$', '') AS stem FROM part")
def udf_stem(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_tables(spark)
    return read(spark, sf_dir, "part").selectExpr("p_partkey", "light_stem(split(p_name, ' ')[0]) AS stem")


@query(f"WITH {S.d('order_brands')} SELECT x.item AS a, y.item AS b, count(*) AS n FROM d x JOIN d y ON x.tid = y.tid AND x.item < y.item GROUP BY 1, 2")
def udtf_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_tables(spark)
    return spark.sql("SELECT a, b, count(*) AS n FROM {tx}, LATERAL pairs_of(items) GROUP BY a, b", tx=VIEWS["order_brands"](spark, sf_dir).rows)


@query(f"WITH {S.d('order_brands')}, c AS (SELECT item, count(*) AS n FROM d GROUP BY item), {S.small_sets(25, 2)} SELECT itemset, size::INT AS size, support AS n FROM s WHERE support > 0")
def udtf_subsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_tables(spark)
    return spark.sql("SELECT itemset, size, count(*) AS n FROM {tx}, LATERAL subsets_of(items, 2) GROUP BY itemset, size", tx=VIEWS["order_brands"](spark, sf_dir).rows)


@query(f"SELECT k, round({S.uniform(chr(39) + '42:bins:' + chr(39) + ' || k')}, 12) AS u, round({S.laplace(chr(39) + '42:bins:' + chr(39) + ' || k', '2.0')}, 9) AS lap, round({S.gumbel(chr(39) + '42:bins:' + chr(39) + ' || k')}, 9) AS gum FROM (VALUES ('a'), ('b'), ('c')) AS t(k)")
def sql_noise_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_sql(spark)
    return spark.sql("SELECT k, round(keyed_uniform('42:bins:' || k), 12) AS u, round(laplace('42:bins:' || k, 2.0D), 9) AS lap, round(gumbel('42:bins:' || k), 9) AS gum FROM VALUES ('a'), ('b'), ('c') AS t(k)")


# --- streams -------------------------------------------------------------------


def _drained(stream: DataFrame) -> DataFrame:
    return windows.drain(stream, _shared(stream.sparkSession, "stream"))


@query("SELECT date_trunc('day', ts) AS opened, user_id, count(DISTINCT event_type) AS kinds FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY 1, 2")
def stream_tumbling_transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Final windows only: those that the watermark has passed."""
    rows = _drained(windows.transactions(windows.event_stream(spark, sf_dir), windows.tumbling("1 day")))
    return rows.select(F.col("opened").cast("timestamp_ntz").alias("opened"), "user_id", F.size("items").cast("long").alias("kinds"))


@query("""WITH x AS (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
    y AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM x), z AS (SELECT user_id, s, max(ts) + INTERVAL 2 HOUR AS closed, count(*) AS n FROM y GROUP BY 1, 2)
    SELECT user_id, count(*) AS sessions FROM z WHERE closed <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY user_id""")
def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _drained(windows.transactions(windows.event_stream(spark, sf_dir), windows.sessions("2 hours")))
    return rows.groupBy("user_id").agg(F.count("*").alias("sessions"))


@query("""SELECT opened, sum(n)::BIGINT AS n FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR * o AS opened, count(*) AS n FROM events, (VALUES (0), (1)) AS t(o) GROUP BY 1)
    WHERE opened + INTERVAL 12 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY opened""")
def stream_sliding_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = windows.event_stream(spark, sf_dir).withWatermark("ts", "1 day").groupBy(windows.sliding("12 hours", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return _drained(e.select(F.col("w.start").cast("timestamp_ntz").alias("opened"), "n"))


_BASIS = ("click", "purchase", "view")


@query("""SELECT date_trunc('day', ts) AS opened, (CASE event_type WHEN 'click' THEN 1 WHEN 'purchase' THEN 2 WHEN 'view' THEN 4 ELSE 0 END)::INT AS mask, count(*) AS n FROM events
    WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY 1, 2""")
def stream_window_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _drained(windows.window_bins(windows.event_stream(spark, sf_dir), "1 day", _BASIS))
    return rows.select(F.col("opened").cast("timestamp_ntz").alias("opened"), "mask", "n")


_FINAL = "date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY"
_RELEASED = f"""WITH e AS (SELECT date_trunc('day', ts) AS opened, (CASE event_type WHEN 'click' THEN 1 WHEN 'purchase' THEN 2 WHEN 'view' THEN 4 ELSE 0 END) AS mask, count(*) AS n FROM events WHERE {_FINAL} GROUP BY 1, 2),
    bins AS (SELECT o.opened, t.m AS mask, coalesce(e.n, 0) AS n FROM (SELECT DISTINCT opened FROM e) o CROSS JOIN range(0, 8) t(m) LEFT JOIN e ON e.opened = o.opened AND e.mask = t.m),
    noisy AS (SELECT opened, mask, n + {S.laplace("'42:window:' || strftime(opened, '%Y-%m-%d %H:%M:%S') || ':' || mask", '1.0')} AS noisy FROM bins),
    sums AS (SELECT a.opened, t.m AS mask, sum(a.noisy) AS nc FROM noisy a JOIN range(1, 8) t(m) ON (a.mask & t.m) = t.m GROUP BY 1, 2)
    SELECT opened, array_to_string(list_filter(['click', 'purchase', 'view'], lambda x, i: (mask >> (i - 1)) & 1 = 1), '|') AS itemset, round(nc, 6) AS noisy_count FROM sums"""


@query(_RELEASED)
def stream_window_release(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows published as they close, batch by batch."""
    bins = windows.window_bins(windows.event_stream(spark, sf_dir), "1 day", _BASIS)
    rows = windows.release_stream(bins, _BASIS, 1.0, NoiseSource.fixed(42), _shared(spark, "release"))
    return rows.select(F.col("opened").cast("timestamp_ntz").alias("opened"), "itemset", "noisy_count")


@query("SELECT user_id, count(*) AS n_events, count(DISTINCT event_type) AS n_kinds FROM events GROUP BY user_id")
def stream_own_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last running total of each user."""
    rows = windows.drain_updates(windows.running_item_counts(windows.event_stream(spark, sf_dir)), _shared(spark, "state"))
    last = F.struct("n_events", "n_kinds")
    return rows.groupBy("user_id").agg(F.max(last).alias("last")).select("user_id", "last.n_events", "last.n_kinds")


@query("SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type")
def stream_deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = windows.event_stream(spark, sf_dir)
    return _drained(windows.deduplicated(e.union(e), "40 days")).groupBy("event_type").agg(F.count("*").alias("n"))


@query("SELECT item_id, count(*) AS n FROM events JOIN (VALUES ('click', 1), ('view', 2)) AS t(event_type, item_id) USING (event_type) GROUP BY item_id")
def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    words = spark.createDataFrame([("click", 1), ("view", 2)], "event_type string, item_id int")
    rows = _drained(windows.enriched(windows.event_stream(spark, sf_dir), words).where("item_id is not null").select("item_id"))
    return rows.groupBy("item_id").agg(F.count("*").alias("n"))
