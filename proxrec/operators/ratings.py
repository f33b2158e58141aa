"""The ratings relation and the statistics of its items."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def canonical(rows: DataFrame, user: str, item: str, value: str, agg: str = "sum", cap: float | None = None) -> DataFrame:
    """Unique (user_id, item_id, rating >= 0). Null keys and negative values are rejected with an error, repeated pairs combined."""
    checked = rows.select(F.col(user).alias("user_id"), F.col(item).alias("item_id"), F.col(value).cast("double").alias("rating"))
    wrong = F.col("user_id").isNull() | F.col("item_id").isNull() | F.col("rating").isNull() | (F.col("rating") < 0)
    checked = checked.withColumn("rating", F.when(wrong, F.raise_error(F.lit("null key or negative rating"))).otherwise(F.col("rating")).cast("double"))
    out = checked.groupBy("user_id", "item_id").agg(F.expr(f"{agg}(rating)").alias("rating"))
    return out if cap is None else out.withColumn("rating", F.least(F.lit(float(cap)), "rating"))


def item_stats(ratings: DataFrame, n_users: int | None = None) -> DataFrame:
    """item_id, norm, n_raters, mean and sd over all users (absent ratings count as 0). One shuffle with partial sums."""
    sums = ratings.groupBy("item_id").agg(F.count("*").alias("n_raters"), F.sum("rating").alias("s1"), F.sum(F.col("rating") * F.col("rating")).alias("s2"))
    users = F.lit(n_users) if n_users is not None else None
    if users is None:
        sums, users = sums.crossJoin(ratings.agg(F.count_distinct("user_id").alias("n_users"))), F.col("n_users")  # one row
    mean = F.col("s1") / users
    return sums.select("item_id", F.sqrt("s2").alias("norm"), "n_raters", mean.alias("mean"), F.sqrt(F.greatest(F.lit(0.0), F.col("s2") / users - mean * mean)).alias("sd"))


def core(ratings: DataFrame, least_users: int, least_items: int) -> DataFrame:
    """Ratings left when items with few users and users with few items are taken away in turn until none is, however many rounds that takes.

    Each round's result is checkpointed, so plans stay short and rounds survive lost executors.
    """
    from proxrec.plans.planner import cut

    ratings = cut(ratings)
    now = ratings.count()
    while True:
        before = now
        items = ratings.groupBy("item_id").agg(F.count("*").alias("n")).where(F.col("n") >= least_users).select("item_id")
        ratings = ratings.join(items, "item_id", "left_semi")
        users = ratings.groupBy("user_id").agg(F.count("*").alias("n")).where(F.col("n") >= least_items).select("user_id")
        ratings = cut(ratings.join(users, "user_id", "left_semi"))
        now = ratings.count()
        if now == before:
            return ratings


def density_report(ratings: DataFrame) -> DataFrame:
    """n_users, n_items, nnz, nnz_per_item, density in one pass over distinct keys."""
    one = ratings.agg(F.count_distinct("user_id").alias("n_users"), F.count_distinct("item_id").alias("n_items"), F.count("*").alias("nnz"))
    return one.select("n_users", "n_items", "nnz", (F.col("nnz") / F.col("n_items")).alias("nnz_per_item"), (F.col("nnz") / (F.col("n_users") * F.col("n_items"))).alias("density"))
