"""Collections of sets on the given tables. Each is (set_id, element), distinct, with the SQL that gives the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.encoders import json_key, links, shingles, string_id, string_id_sql, top_dims, words, words_sql
from .tables import read


def _members(df: DataFrame, set_id, element) -> DataFrame:
    rows = df.select(set_id.cast("bigint").alias("set_id"), element.cast("bigint").alias("element"))
    return rows.where("set_id is not null and element is not null").distinct()


def customer_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return _members(lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"]), F.col("o_custkey"), F.col("l_partkey"))


def supplier_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _members(read(spark, sf_dir, "lineitem"), F.col("l_suppkey"), F.col("l_partkey"))


def part_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _members(read(spark, sf_dir, "lineitem"), F.col("l_partkey"), F.col("l_suppkey"))


def event_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The update stream of ``events``: users are sets, keys are elements, errors delete. Not legal."""
    op = F.when(F.col("event_type") == "error", -1).otherwise(1)
    return read(spark, sf_dir, "events").select(F.col("event_id").alias("seq"), F.col("user_id").alias("set_id"), json_key(F.col("props")).alias("element"), op.alias("op"), "ts")


def order_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Inserts at the order date, deletes of returned lines at the ship date; sets are customers. Not legal."""
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber", "l_returnflag", "l_shipdate")
    both = lines.join(read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    who = [F.col("o_custkey").alias("set_id"), F.col("l_partkey").alias("element")]
    tie = F.xxhash64("l_orderkey", "l_linenumber", "l_partkey").alias("tie")
    put = both.select(*who, F.lit(1).alias("op"), F.col("o_orderdate").alias("ts"), tie)
    out = both.where("l_returnflag = 'R'").select(*who, F.lit(-1).alias("op"), F.col("l_shipdate").alias("ts"), tie)
    seq = (F.unix_micros(F.col("ts").cast("timestamp")) * 4).cast("bigint") + F.pmod("tie", F.lit(4))
    return put.unionByName(out).select(seq.alias("seq"), "set_id", "element", "op", "ts")


def user_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _members(event_updates(spark, sf_dir), F.col("set_id"), F.col("element"))


def user_keys_live(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..operators.streams import members_at

    return members_at(event_updates(spark, sf_dir))


def doc_shingles(spark: SparkSession, sf_dir: str, width: int = 3) -> DataFrame:
    rows = read(spark, sf_dir, "documents").select("doc_id", F.explode(shingles(F.col("text"), width)).alias("s"))
    return _members(rows, F.col("doc_id"), string_id(F.col("s")))


def doc_shingle_sets(spark: SparkSession, sf_dir: str, width: int = 3) -> DataFrame:
    """(set_id, e): the sets of ``doc_shingles``, each in one row, its elements in order; a document's elements are shuffled once, as one array."""
    e = F.filter(F.transform(shingles(F.col("text"), width), lambda s: string_id(s).cast("bigint")), lambda x: x.isNotNull())
    rows = read(spark, sf_dir, "documents").select(F.col("doc_id").cast("bigint").alias("set_id"), F.array_distinct(e).alias("e")).where("set_id is not null")
    # Empty ones are left out last: a filter here would make all shingles twice.
    return rows.groupBy("set_id").agg(F.sort_array(F.array_distinct(F.flatten(F.collect_list("e")))).alias("e")).where("size(e) > 0")


def doc_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "documents").select("doc_id", F.explode(words(F.col("text"))).alias("s"))
    return _members(rows, F.col("doc_id"), string_id(F.col("s")))


def benchmark_shingles(spark: SparkSession, sf_dir: str, width: int = 3) -> DataFrame:
    rows = read(spark, sf_dir, "benchmark").select("item_id", F.explode(shingles(F.col("text"), width)).alias("s"))
    return _members(rows, F.col("item_id"), string_id(F.col("s")))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "pages").select("page_id", F.explode(links(F.col("html"))).alias("s"))
    return _members(rows, F.col("page_id"), string_id(F.col("s")))


def vector_topdims(spark: SparkSession, sf_dir: str, t: int = 8) -> DataFrame:
    rows = read(spark, sf_dir, "embeddings").select("vec_id", F.explode(top_dims(F.col("embedding"), t)).alias("i"))
    return _members(rows, F.col("vec_id"), F.col("i"))


def conversation_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "conversations").select("conv_id", F.explode(words(F.col("text"))).alias("s"))
    return _members(rows, F.col("conv_id"), string_id(F.col("s")))


def conversation_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Growing sets: each turn inserts its words, in turn order."""
    rows = read(spark, sf_dir, "conversations").select("conv_id", "turn", F.explode(words(F.col("text"))).alias("s"))
    return rows.select(F.col("turn").cast("bigint").alias("seq"), F.col("conv_id").cast("bigint").alias("set_id"), string_id(F.col("s")).alias("element"), F.lit(1).alias("op"))


def thin_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer–part edges of large returned lines; parts are numbered after customers."""
    lines = read(spark, sf_dir, "lineitem").where("l_returnflag = 'R' and l_quantity >= 46").select("l_orderkey", "l_partkey")
    both = lines.join(read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return both.select(F.col("o_custkey").cast("bigint").alias("u"), (F.col("l_partkey") + 1_000_000_000).cast("bigint").alias("v")).distinct()


def edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer–part edges of all order lines; parts are numbered after customers."""
    return customer_parts(spark, sf_dir).select(F.col("set_id").alias("u"), (F.col("element") + 1_000_000_000).alias("v"))


def nation_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _members(read(spark, sf_dir, "customer"), F.col("c_nationkey"), F.col("c_custkey"))


def region_nations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _members(read(spark, sf_dir, "nation"), F.col("n_regionkey"), F.col("n_nationkey"))


COLLECTIONS = {
    f.__name__: f
    for f in (customer_parts, supplier_parts, part_suppliers, user_keys, user_keys_live, doc_shingles, doc_words, benchmark_shingles, page_links, vector_topdims, conversation_words, nation_customers, region_nations)
}

_EVENTS_SQL = """SELECT event_id AS seq, user_id AS set_id, regexp_extract(props, '"k": *([0-9]+)', 1)::BIGINT AS element,
  CASE WHEN event_type = 'error' THEN -1 ELSE 1 END AS op, ts FROM events"""
_LIVE_SQL = f"""SELECT set_id, element FROM (SELECT set_id, element, arg_max(op, seq) AS op FROM ({_EVENTS_SQL}) GROUP BY 1, 2) WHERE op = 1"""


def _grams_sql(table: str, key: str, width: int) -> str:
    return f"""SELECT DISTINCT {key} AS set_id, {string_id_sql("g")} AS element FROM (
  SELECT {key}, array_to_string(w[i:i + {width - 1}], ' ') AS g FROM (
    SELECT {key}, w, unnest(range(1, len(w) - {width - 2})) AS i FROM (SELECT {key}, {words_sql("text")} AS w FROM {table}) WHERE len(w) >= {width}))"""


def _words_sql(table: str, key: str) -> str:
    return f"SELECT DISTINCT {key} AS set_id, {string_id_sql('w')} AS element FROM (SELECT {key}, unnest({words_sql('text')}) AS w FROM {table})"


#: SQL of the update stream and of each collection.
EVENT_UPDATES_SQL = _EVENTS_SQL
COLLECTIONS_SQL = {
    "customer_parts": "SELECT DISTINCT o_custkey AS set_id, l_partkey AS element FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "supplier_parts": "SELECT DISTINCT l_suppkey AS set_id, l_partkey AS element FROM lineitem",
    "part_suppliers": "SELECT DISTINCT l_partkey AS set_id, l_suppkey AS element FROM lineitem",
    "user_keys": f"SELECT DISTINCT set_id, element FROM ({_EVENTS_SQL})",
    "user_keys_live": _LIVE_SQL,
    "doc_shingles": _grams_sql("documents", "doc_id", 3),
    "doc_words": _words_sql("documents", "doc_id"),
    "benchmark_shingles": _grams_sql("benchmark", "item_id", 3),
    "page_links": f"""SELECT DISTINCT page_id AS set_id, {string_id_sql("s")} AS element FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS s FROM pages)""",
    "vector_topdims": """SELECT vec_id AS set_id, i AS element FROM (SELECT vec_id, i, row_number() OVER (PARTITION BY vec_id ORDER BY x DESC, i) AS r
  FROM (SELECT vec_id, unnest(embedding) AS x, (unnest(range(len(embedding))))::BIGINT AS i FROM embeddings)) WHERE r <= 8""",
    "conversation_words": _words_sql("conversations", "conv_id"),
    "nation_customers": "SELECT DISTINCT c_nationkey::BIGINT AS set_id, c_custkey AS element FROM customer",
    "region_nations": "SELECT DISTINCT n_regionkey::BIGINT AS set_id, n_nationkey::BIGINT AS element FROM nation",
}
