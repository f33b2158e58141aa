"""The SQL surface of a fitted model."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from proxrec.functions import vectors

from . import model as models
from .gram import pack_rows
from .ratings import item_stats


def register(spark: SparkSession, fitted: models.LatentModel, ratings: DataFrame, n: int = 10) -> None:
    """Views ratings, items, latent, user_factors and recs, and the functions.

    latent_scores is a view of the rated pairs' scores; latent_score(user, item) scores any pair of a known user and item (null otherwise);
    recommend_user(items, ratings, n) lists place, item_id and score for the row of any user, known or not.
    """
    vectors.register(spark)
    ratings.createOrReplaceTempView("ratings")
    item_stats(ratings).createOrReplaceTempView("items")
    fitted.latent(spark).createOrReplaceTempView("latent")
    models.factors(fitted, pack_rows(ratings, fitted.index(spark)), models.item_blocks(fitted)).select("user_id", "p").createOrReplaceTempView("user_factors")
    models.recommend(fitted, ratings, n).createOrReplaceTempView("recs")
    models.score_pairs(fitted, ratings, ratings.select("user_id", "item_id")).createOrReplaceTempView("latent_scores")
    user, item = ratings.schema["user_id"].dataType.simpleString(), ratings.schema["item_id"].dataType.simpleString()
    dot = "aggregate(zip_with(f.p, l.v, (a, b) -> a * b), 0D, (s, x) -> s + x)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION latent_score(u {user}, i {item}) RETURNS DOUBLE RETURN (SELECT max({dot}) FROM user_factors f JOIN latent l ON l.item_id = i WHERE f.user_id = u)")
    spark.udtf.register("recommend_user", recommender(spark, fitted))


def recommender(spark: SparkSession, fitted: models.LatentModel):
    """The table function: a user's row of items and ratings against the broadcast vectors."""
    if 8 * fitted.vectors.size > models.BROADCAST_BYTES:
        raise MemoryError("the vectors exceed a broadcast: use operators.model.recommend, which goes by blocks of items")
    shared = spark.sparkContext.broadcast((fitted.vectors, fitted.items, fitted.norms > 0))
    kind = "string" if fitted.items and isinstance(fitted.items[0], str) else "bigint"

    @udtf(returnType=f"place int, item_id {kind}, score double")
    class RecommendUser:
        def __init__(self):
            self.v, self.items, self.alive = shared.value
            self.place = {k: i for i, k in enumerate(self.items)}

        def eval(self, items: list, marks: list, n: int):
            own = [(self.place[k], x) for k, x in zip(items or [], marks or [], strict=True) if k in self.place]
            at = np.array([i for i, _ in own], np.int64)
            scores = self.v @ (np.array([x for _, x in own]) @ self.v[at]) if own else np.zeros(len(self.v))
            scores[~self.alive] = np.nan
            scores[at] = np.nan
            for place, j in enumerate(models.best_n(scores, n)):
                yield place + 1, self.items[j], float(scores[j])

    return RecommendUser
