"""Ratings views on the given tables: unique (user_id, item_id, rating) relations, and the same in SQL for oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TOKEN = "[a-z]{3,}"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def five_steps(total: Column) -> Column:
    """A sum of quantities as a rating from 1 to 5."""
    return F.least(F.lit(5.0), F.greatest(F.lit(1.0), F.ceil(total / 10).cast("double")))


def order_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey)


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = order_lines(spark, sf_dir)
    return lines.groupBy(F.col("o_custkey").alias("user_id"), F.col("l_partkey").alias("item_id")).agg(five_steps(F.sum("l_quantity")).alias("rating"))


def supplier_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = order_lines(spark, sf_dir)
    return lines.groupBy(F.col("o_custkey").alias("user_id"), F.col("l_suppkey").alias("item_id")).agg(five_steps(F.sum("l_quantity")).alias("rating"))


def branded(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = load(spark, sf_dir, "part").select("p_partkey", "p_brand")
    lines = order_lines(spark, sf_dir)
    return lines.join(parts, lines.l_partkey == parts.p_partkey)


def brand_affinity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return branded(spark, sf_dir).groupBy(F.col("o_custkey").alias("user_id"), F.col("p_brand").alias("item_id")).agg(five_steps(F.sum("l_quantity")).alias("rating"))


def nation_brand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of the small graph: a nation and a brand with some line of 50 pieces or more."""
    customers = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    lines = branded(spark, sf_dir).join(F.broadcast(customers), F.col("o_custkey") == F.col("c_custkey"))
    sums = lines.groupBy(F.col("c_nationkey").alias("user_id"), F.col("p_brand").alias("item_id")).agg(F.sum("l_quantity").alias("rating"), F.max("l_quantity").alias("most"))
    return sums.where("most >= 50").select("user_id", "item_id", "rating")


def terms(rows: DataFrame, user: str, text: Column) -> DataFrame:
    words = rows.select(F.col(user).alias("user_id"), F.explode(F.regexp_extract_all(F.lower(text), F.lit(TOKEN), F.lit(0))).alias("item_id"))
    return words.groupBy("user_id", "item_id").agg(F.least(F.lit(5), F.count("*")).cast("double").alias("rating"))


def frequent_items(ratings: DataFrame, least_users: int) -> DataFrame:
    """Ratings of the items that at least so many users have rated."""
    kept = ratings.groupBy("item_id").agg(F.count("*").alias("n")).where(F.col("n") >= least_users).select("item_id")
    return ratings.join(kept, "item_id", "left_semi")


def doc_terms(spark: SparkSession, sf_dir: str, least_users: int = 10) -> DataFrame:
    return frequent_items(terms(load(spark, sf_dir, "documents"), "doc_id", F.col("text")), least_users)


def terms60(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sixty terms of most documents, ties by term."""
    all_terms = terms(load(spark, sf_dir, "documents"), "doc_id", F.col("text"))
    top = all_terms.groupBy("item_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "item_id").limit(60)
    return all_terms.join(F.broadcast(top.select("item_id")), "item_id", "left_semi")


def chat_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return terms(load(spark, sf_dir, "conversations").where("role = 'user'"), "conv_id", F.col("text"))


def page_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return terms(load(spark, sf_dir, "pages"), "page_id", F.regexp_replace("html", "<[^>]*>", " "))


def bench_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return terms(load(spark, sf_dir, "benchmark").withColumnRenamed("item_id", "bench_id"), "bench_id", F.col("text"))


def event_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = load(spark, sf_dir, "events").select("user_id", F.get_json_object("props", "$.k").cast("int").alias("item_id"))
    return events.groupBy("user_id", "item_id").agg(F.least(F.lit(5), F.count("*")).cast("double").alias("rating"))


def event_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").groupBy("user_id", F.col("event_type").alias("item_id")).agg(F.count("*").cast("double").alias("rating"))


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "purchases": purchases,
    "supplier_mix": supplier_mix,
    "brand_affinity": brand_affinity,
    "nation_brand": nation_brand,
    "doc_terms": doc_terms,
    "terms60": terms60,
    "chat_terms": chat_terms,
    "page_terms": page_terms,
    "bench_terms": bench_terms,
    "event_keys": event_keys,
    "event_types": event_types,
}

_STEP = "CAST(least(5, greatest(1, ceil(sum(l_quantity) / 10))) AS DOUBLE)"
_LINES = "lineitem JOIN orders ON l_orderkey = o_orderkey"


def _terms(table: str, user: str, text: str) -> str:
    return f"SELECT user_id, item_id, CAST(least(5, count(*)) AS DOUBLE) AS rating FROM (SELECT {user} AS user_id, unnest(regexp_extract_all(lower({text}), '{TOKEN}')) AS item_id FROM {table}) GROUP BY 1, 2"


_ALL_TERMS = _terms("documents", "doc_id", "text")
#: DuckDB SQL of the views.
VIEW_SQL: dict[str, str] = {
    "purchases": f"SELECT o_custkey AS user_id, l_partkey AS item_id, {_STEP} AS rating FROM {_LINES} GROUP BY 1, 2",
    "supplier_mix": f"SELECT o_custkey AS user_id, l_suppkey AS item_id, {_STEP} AS rating FROM {_LINES} GROUP BY 1, 2",
    "brand_affinity": f"SELECT o_custkey AS user_id, p_brand AS item_id, {_STEP} AS rating FROM {_LINES} JOIN part ON l_partkey = p_partkey GROUP BY 1, 2",
    "nation_brand": f"SELECT c_nationkey AS user_id, p_brand AS item_id, sum(l_quantity) AS rating FROM {_LINES} JOIN part ON l_partkey = p_partkey JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2 HAVING max(l_quantity) >= 50",
    "doc_terms": f"WITH t AS ({_ALL_TERMS}) SELECT * FROM t WHERE item_id IN (SELECT item_id FROM t GROUP BY 1 HAVING count(*) >= 10)",
    "terms60": f"WITH t AS ({_ALL_TERMS}) SELECT * FROM t WHERE item_id IN (SELECT item_id FROM t GROUP BY 1 ORDER BY count(*) DESC, item_id LIMIT 60)",
    "chat_terms": _terms("(SELECT * FROM conversations WHERE role = 'user')", "conv_id", "text"),
    "page_terms": _terms("pages", "page_id", "regexp_replace(html, '<[^>]*>', ' ', 'g')"),
    "bench_terms": _terms("(SELECT item_id AS bench_id, text FROM benchmark)", "bench_id", "text"),
    "event_keys": "SELECT user_id, CAST(json_extract_string(props, '$.k') AS INT) AS item_id, CAST(least(5, count(*)) AS DOUBLE) AS rating FROM events GROUP BY 1, 2",
    "event_types": "SELECT user_id, event_type AS item_id, CAST(count(*) AS DOUBLE) AS rating FROM events GROUP BY 1, 2",
}
