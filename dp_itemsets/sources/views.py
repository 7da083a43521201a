"""Transaction views of the given tables, and the SQL that defines each in long form."""

from __future__ import annotations

import zipfile
from collections.abc import Callable
from pathlib import Path

import pyspark
from pyspark.ml.feature import StopWordsRemover
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .transactions import Transactions

# Thresholds of the thermometer codes of a lineitem record.
QUANTITY_STEPS = (5, 10, 20)
DISCOUNT_STEPS = (9, 8)
TAX_STEPS = (7, 6)
PRICE_STEPS = ((10_000, "10k"), (20_000, "20k"))

#: The codes of a lineitem record that its columns can take, by tag; with the thermometer codes they are the public domain.
RECORD_CODES = {
    "flag": ("A", "N", "R"), "stat": ("F", "O"), "line": tuple(range(1, 8)), "yr": tuple(range(1995, 2002)), "ost": ("F", "O", "P"), "nat": tuple(range(25)),
    "prio": ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"), "seg": ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"),
}
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
#: Event pages are numbered below this, and vectors have so many dimensions.
PAGES, DIMENSIONS = 100, 64


def record_items() -> list[str]:
    steps = [f"q>{q}" for q in QUANTITY_STEPS] + [f"d<={d}" for d in DISCOUNT_STEPS] + [f"t<={t}" for t in TAX_STEPS] + [f"p>{name}" for _, name in PRICE_STEPS]
    return steps + [f"{tag}={code}" for tag, codes in RECORD_CODES.items() for code in codes]


def click_items() -> list[str]:
    return [*EVENT_TYPES, *(f"k{k}" for k in range(PAGES))]


def sign_items() -> list[str]:
    return [f"e{k}" for k in range(DIMENSIONS)]


def _domain(spark: SparkSession, items: list[str]) -> DataFrame:
    return spark.createDataFrame([(i,) for i in items], "item string")


WORD = r"\p{L}+"
SUFFIX = "(ing|tion|ed|es|s)$"
LANGUAGES = ("english", "french", "german", "spanish")


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def line_records(spark: SparkSession, sf_dir: str) -> Transactions:
    """A lineitem row as a record of coded attributes, with those of its order and customer."""
    line = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority", "o_orderstatus")
    customer = read(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment", "c_nationkey")
    joined = line.join(orders, line["l_orderkey"] == orders["o_orderkey"]).join(customer, F.col("o_custkey") == customer["c_custkey"])
    percent = lambda c: F.round(F.col(c) * 100).cast("int")
    coded = [F.when(F.col("l_quantity") > q, F.lit(f"q>{q}")) for q in QUANTITY_STEPS]
    coded += [F.when(percent("l_discount") <= d, F.lit(f"d<={d}")) for d in DISCOUNT_STEPS]
    coded += [F.when(percent("l_tax") <= t, F.lit(f"t<={t}")) for t in TAX_STEPS]
    coded += [F.when(F.col("l_extendedprice") > p, F.lit(f"p>{name}")) for p, name in PRICE_STEPS]
    tags = {"flag": "l_returnflag", "stat": "l_linestatus", "line": "l_linenumber", "prio": "o_orderpriority", "ost": "o_orderstatus", "seg": "c_mktsegment", "nat": "c_nationkey"}
    coded += [F.concat(F.lit(f"{tag}="), F.col(c).cast("string")) for tag, c in tags.items()]
    coded.append(F.concat(F.lit("yr="), F.year("l_shipdate").cast("string")))
    tid = F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
    return Transactions(joined.select(tid.alias("tid"), F.sort_array(_present(*coded)).alias("items")), _domain(spark, record_items()), unit="record")


def _present(*items: Column) -> Column:
    """Array of the distinct items that aren't null, in generated code: array_compact would run a lambda a value."""
    return F.array_except(F.array(*items), F.array(F.lit(None).cast("string")))


def _words(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(f"({WORD})"))


def doc_words(spark: SparkSession, sf_dir: str) -> Transactions:
    """Lower-cased letter runs of a document."""
    rows = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("tid"), F.sort_array(F.array_distinct(_words(F.col("text")))).alias("items"))
    return Transactions(rows.withColumn("items", F.coalesce("items", F.array().cast("array<string>"))), unit="document")


def stop_words() -> list[str]:
    return sorted({w for lang in LANGUAGES for w in StopWordsRemover.loadDefaultStopWords(lang)})


def stop_words_file() -> list[str] | None:
    """The same lists, read from the engine's library without a session; None where it isn't beside this Python package."""
    jars = sorted((Path(pyspark.__file__).parent / "jars").glob("spark-mllib_*.jar"))
    if not jars:
        return None
    with zipfile.ZipFile(jars[0]) as jar:
        return sorted({w for lang in LANGUAGES for w in jar.read(f"org/apache/spark/ml/feature/stopwords/{lang}.txt").decode().split("\n") if w})


def keywords(text: Column, stop: list[str]) -> Column:
    """Letter runs of three letters or more that are no stop words, less a common suffix."""
    # a set difference hashes the stop words once a text
    kept = F.array_except(F.filter(_words(text), lambda w: F.length(w) >= 3), F.array(*[F.lit(w) for w in stop]))
    return F.sort_array(F.array_distinct(F.filter(F.transform(kept, lambda w: F.regexp_replace(w, SUFFIX, "")), lambda w: F.length(w) > 0)))


def doc_keywords(spark: SparkSession, sf_dir: str) -> Transactions:
    rows = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("tid"), keywords(F.col("text"), stop_words()).alias("items"))
    return Transactions(rows.withColumn("items", F.coalesce("items", F.array().cast("array<string>"))), unit="document")


def conv_keywords(spark: SparkSession, sf_dir: str) -> Transactions:
    """Keywords of what the user says in a conversation: queries grouped by their author."""
    said = read(spark, sf_dir, "conversations").where("role = 'user'").select("conv_id", F.explode_outer(keywords(F.col("text"), stop_words())).alias("item"))
    return Transactions.from_long(said, "conv_id", unit="conversation")


def _order_lines(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    line = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    part = read(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type", "p_name")
    return line.join(part, line["l_partkey"] == part["p_partkey"]), part


def order_terms(spark: SparkSession, sf_dir: str) -> Transactions:
    """Type, brand and name words of an order's parts."""
    lines, part = _order_lines(spark, sf_dir)
    terms = F.concat(F.array("p_type", "p_brand"), F.split("p_name", " "))
    universe = part.select(F.explode(terms).alias("item")).distinct()
    return Transactions.from_long(lines.select("l_orderkey", F.explode(terms).alias("item")), "l_orderkey", universe=universe, unit="order")


def order_brands(spark: SparkSession, sf_dir: str) -> Transactions:
    lines, part = _order_lines(spark, sf_dir)
    return Transactions.from_long(lines.select("l_orderkey", "p_brand"), "l_orderkey", "p_brand", part.select(F.col("p_brand").alias("item")).distinct(), "order")


def order_parts(spark: SparkSession, sf_dir: str) -> Transactions:
    """Parts of an order: flat supports, nothing to be learned."""
    line = read(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").cast("string").alias("item"))
    universe = read(spark, sf_dir, "part").select(F.col("p_partkey").cast("string").alias("item"))
    return Transactions.from_long(line, "l_orderkey", universe=universe, unit="order")


def cust_terms(spark: SparkSession, sf_dir: str) -> Transactions:
    """Type and brand pairs of all that a customer ordered."""
    lines, part = _order_lines(spark, sf_dir)
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    term = F.concat_ws("+", "p_type", "p_brand")
    universe = part.select(term.alias("item")).distinct()
    rows = lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"]).select("o_custkey", term.alias("item"))
    return Transactions.from_long(rows, "o_custkey", universe=universe, unit="customer")


def user_day_clicks(spark: SparkSession, sf_dir: str) -> Transactions:
    """Event types and page numbers of a user's day."""
    events = read(spark, sf_dir, "events").select("user_id", F.date_format("ts", "yyyy-MM-dd").alias("day"), "event_type", F.get_json_object("props", "$.k").alias("k"))
    items = _present(F.col("event_type"), F.when(F.col("k").isNotNull(), F.concat(F.lit("k"), F.col("k"))))
    rows = events.select(F.concat_ws("/", "user_id", "day").alias("tid"), F.explode_outer(items).alias("item"))
    return Transactions.from_long(rows, universe=_domain(spark, click_items()), unit="user and day")


def page_words(spark: SparkSession, sf_dir: str) -> Transactions:
    """Letter runs of a page without its tags: many words on every page."""
    rows = read(spark, sf_dir, "pages").select(F.col("page_id").alias("tid"), F.sort_array(F.array_distinct(_words(F.regexp_replace("html", "<[^>]*>", " ")))).alias("items"))
    return Transactions(rows.withColumn("items", F.coalesce("items", F.array().cast("array<string>"))), unit="page")


def embedding_signs(spark: SparkSession, sf_dir: str) -> Transactions:
    """Dimensions with a positive value: nearly independent items."""
    signs = F.filter(F.transform("embedding", lambda x, i: F.when(x > 0, F.concat(F.lit("e"), i.cast("string")))), lambda s: s.isNotNull())
    return Transactions(read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("tid"), F.sort_array(signs).alias("items")), _domain(spark, sign_items()), unit="vector")


VIEWS: dict[str, Callable[[SparkSession, str], Transactions]] = {
    f.__name__: f for f in (line_records, doc_words, doc_keywords, conv_keywords, order_terms, order_brands, order_parts, cust_terms, user_day_clicks, page_words, embedding_signs)
}


def register_views(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> None:
    """Each view as a temporary SQL view tx_<name>(tid, items)."""
    for name in names or list(VIEWS):
        VIEWS[name](spark, sf_dir).rows.createOrReplaceTempView(f"tx_{name}")


_LINES = "lineitem JOIN part ON l_partkey = p_partkey"

#: DuckDB: (tid, item), distinct, of the views that SQL checks.
VIEW_SQL = {
    "order_brands": f"SELECT DISTINCT l_orderkey AS tid, p_brand AS item FROM {_LINES}",
    "order_terms": f"SELECT DISTINCT l_orderkey AS tid, unnest([p_type, p_brand, split_part(p_name, ' ', 1), split_part(p_name, ' ', 2)]) AS item FROM {_LINES}",
    "order_parts": "SELECT DISTINCT l_orderkey AS tid, l_partkey::VARCHAR AS item FROM lineitem",
    "cust_terms": f"SELECT DISTINCT o_custkey AS tid, p_type || '+' || p_brand AS item FROM {_LINES} JOIN orders ON l_orderkey = o_orderkey",
    "doc_words": r"SELECT DISTINCT doc_id AS tid, unnest(regexp_extract_all(lower(text), '\p{L}+')) AS item FROM documents",
    "page_words": r"SELECT DISTINCT page_id AS tid, unnest(regexp_extract_all(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '\p{L}+')) AS item FROM pages",
    "user_day_clicks": "SELECT DISTINCT user_id || '/' || strftime(ts, '%Y-%m-%d') AS tid, unnest([event_type, 'k' || json_extract_string(props, '$.k')]) AS item FROM events",
    "embedding_signs": "SELECT vec_id AS tid, 'e' || (i - 1)::VARCHAR AS item FROM (SELECT vec_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE x > 0",
    "line_records": """SELECT tid, item FROM (SELECT concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice) AS tid, unnest([
        CASE WHEN l_quantity > 5 THEN 'q>5' END, CASE WHEN l_quantity > 10 THEN 'q>10' END, CASE WHEN l_quantity > 20 THEN 'q>20' END,
        CASE WHEN round(l_discount * 100) <= 9 THEN 'd<=9' END, CASE WHEN round(l_discount * 100) <= 8 THEN 'd<=8' END,
        CASE WHEN round(l_tax * 100) <= 7 THEN 't<=7' END, CASE WHEN round(l_tax * 100) <= 6 THEN 't<=6' END,
        CASE WHEN l_extendedprice > 10000 THEN 'p>10k' END, CASE WHEN l_extendedprice > 20000 THEN 'p>20k' END,
        'flag=' || l_returnflag, 'stat=' || l_linestatus, 'line=' || l_linenumber, 'yr=' || year(l_shipdate),
        'prio=' || o_orderpriority, 'ost=' || o_orderstatus, 'seg=' || c_mktsegment, 'nat=' || c_nationkey]) AS item
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey) WHERE item IS NOT NULL""",
}

def _keyword_sql(tid: str, table: str, stop: list[str]) -> str:
    """(tid, item) of keywords: words of three letters or more but stop words, without a suffix."""
    words = ", ".join("'" + w.replace("'", "''") + "'" for w in stop)
    return rf"""SELECT DISTINCT tid, regexp_replace(w, '{SUFFIX}', '') AS item FROM (SELECT {tid} AS tid, unnest(regexp_extract_all(lower(text), '\p{{L}}+')) AS w FROM {table})
        WHERE len(w) >= 3 AND w NOT IN ({words}) AND regexp_replace(w, '{SUFFIX}', '') <> ''"""


if (_STOP := stop_words_file()) is not None:
    VIEW_SQL["doc_keywords"] = _keyword_sql("doc_id", "documents", _STOP)
    VIEW_SQL["conv_keywords"] = _keyword_sql("conv_id", "(SELECT * FROM conversations WHERE role = 'user')", _STOP)

#: DuckDB: (tid) of all transactions, those without an item among them, of views that may have such.
TIDS_SQL = {
    "doc_words": "SELECT doc_id AS tid FROM documents",
    "doc_keywords": "SELECT doc_id AS tid FROM documents",
    "page_words": "SELECT page_id AS tid FROM pages",
    "conv_keywords": "SELECT DISTINCT conv_id AS tid FROM conversations WHERE role = 'user'",
    "embedding_signs": "SELECT vec_id AS tid FROM embeddings",
}

#: DuckDB: (item), the public universe of a view that has one.
UNIVERSE_SQL = {
    "order_brands": "SELECT DISTINCT p_brand AS item FROM part",
    "order_terms": "SELECT DISTINCT unnest([p_type, p_brand, split_part(p_name, ' ', 1), split_part(p_name, ' ', 2)]) AS item FROM part",
    "order_parts": "SELECT p_partkey::VARCHAR AS item FROM part",
    "cust_terms": "SELECT DISTINCT p_type || '+' || p_brand AS item FROM part",
    "line_records": f"SELECT unnest({record_items()}) AS item",
    "user_day_clicks": f"SELECT unnest({click_items()}) AS item",
    "embedding_signs": f"SELECT unnest({sign_items()}) AS item",
}
