"""Splits, candidate lists, rankings, measures and the scenarios of the experiments."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from proxrec.functions.hashing import fraction

NEGATIVES = 1000


def probe_split(ratings: DataFrame, share: float = 0.014, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """(train, probe): complementary filters on one hash, so neither is shuffled."""
    h = ratings.withColumn("h", fraction(seed, "user_id", "item_id"))
    return h.where(F.col("h") >= share).drop("h"), h.where(F.col("h") < share)


def test_cases(probe: DataFrame, best: float = 5.0) -> DataFrame:
    """Entries of the probe with the best rating, each a case of its own."""
    hits = probe.where(F.col("rating") >= best)
    return hits.select(F.concat_ws("|", F.col("user_id").cast("string"), F.col("item_id").cast("string")).alias("case_id"), "user_id", "item_id")


def negatives_of(users: DataFrame, ratings: DataFrame, negatives: int = NEGATIVES, seed: int = 7) -> DataFrame:
    """(user_id, item_id): the given users' unrated items with the smallest hashes.

    Only test users meet the items, which are broadcast if their table is small; the window keeps so many rows a user before it is shuffled.
    """
    free = users.crossJoin(ratings.select("item_id").distinct()).join(ratings.select("user_id", "item_id"), ["user_id", "item_id"], "left_anti")
    order = Window.partitionBy("user_id").orderBy(fraction(seed, "user_id", "item_id"), "item_id")
    return free.withColumn("r", F.row_number().over(order)).where(F.col("r") <= negatives).select("user_id", "item_id")


def candidates(cases: DataFrame, ratings: DataFrame, negatives: int = NEGATIVES, seed: int = 7) -> DataFrame:
    """(case_id, user_id, item_id, is_target): the held-out item and the user's unrated items with the smallest hashes."""
    drawn = negatives_of(cases.select("user_id").distinct(), ratings, negatives, seed)
    lists = cases.select("case_id", "user_id").join(drawn, "user_id").select("case_id", "user_id", "item_id", F.lit(False).alias("is_target"))
    return lists.unionByName(cases.select("case_id", "user_id", "item_id", F.lit(True).alias("is_target")))


def ranked(scored: DataFrame) -> DataFrame:
    """rank within each case: larger score first (rounded to 1e-9), then smaller item key."""
    order = Window.partitionBy("case_id").orderBy(F.desc(F.round("score", 9)), "item_id")
    return scored.withColumn("rank", F.row_number().over(order)).withColumn("rel", F.when(F.col("is_target"), 1.0).otherwise(0.0))


def first_hits(lists: DataFrame) -> DataFrame:
    """case_id and the rank of its first relevant item (null if none)."""
    return lists.groupBy("case_id").agg(F.min(F.when(F.col("rel") > 0, F.col("rank"))).alias("hit"))


def recall_at(lists: DataFrame, most: int = 20) -> DataFrame:
    """k, recall, precision for k = 1..most; a list has one relevant item, so precision is recall / k."""
    ks = lists.sparkSession.range(1, most + 1).select(F.col("id").cast("int").alias("k"))
    hits = first_hits(lists)
    return hits.crossJoin(F.broadcast(ks)).groupBy("k").agg(F.avg(F.when(F.col("hit") <= F.col("k"), 1.0).otherwise(0.0)).alias("recall")).withColumn("precision", F.col("recall") / F.col("k"))


def mrr(lists: DataFrame) -> DataFrame:
    return first_hits(lists).agg(F.avg(F.coalesce(1 / F.col("hit"), F.lit(0.0))).alias("mrr"), F.count("*").alias("n_cases"))


def _gain(rel: Column, place: Column, offset: int) -> Column:
    return (F.pow(F.lit(2.0), rel) - 1) / F.log2(place + offset)


def ndcg_at(lists: DataFrame, most: int = 20, offset: int = 2) -> DataFrame:
    """k, ndcg: discounted gains by log2(offset + rank), as a share of the best order of the same grades; averaged over cases."""
    ideal = Window.partitionBy("case_id").orderBy(F.desc("rel"), "item_id")
    both = lists.where(F.col("rank") <= F.lit(1_000_000_000)).withColumn("best", F.row_number().over(ideal))
    ks = lists.sparkSession.range(1, most + 1).select(F.col("id").cast("int").alias("k"))
    some = both.where((F.col("rel") > 0) | (F.col("rank") <= most)).crossJoin(F.broadcast(ks))
    sums = some.groupBy("case_id", "k").agg(
        F.sum(F.when(F.col("rank") <= F.col("k"), _gain(F.col("rel"), F.col("rank"), offset)).otherwise(0.0)).alias("dcg"),
        F.sum(F.when(F.col("best") <= F.col("k"), _gain(F.col("rel"), F.col("best"), offset)).otherwise(0.0)).alias("idcg"),
    )
    return sums.groupBy("k").agg(F.avg(F.when(F.col("idcg") > 0, F.col("dcg") / F.col("idcg")).otherwise(0.0)).alias("ndcg"))


def rscore(lists: DataFrame, half_lives: list[float], neutral: float = 0.0) -> DataFrame:
    """half_life, rscore: utilities above neutral, halved every half_life - 1 ranks; averaged over cases."""
    if min(half_lives) <= 1:
        raise ValueError("a half-life must exceed 1")
    h = F.explode(F.array(*[F.lit(float(x)) for x in half_lives])).alias("half_life")
    terms = lists.where(F.col("rel") > neutral).select("case_id", "rank", "rel", h)
    value = (F.col("rel") - neutral) / F.pow(F.lit(2.0), (F.col("rank") - 1) / (F.col("half_life") - 1))
    cases = lists.select("case_id").distinct().count()
    return terms.groupBy("half_life").agg((F.sum(value) / max(1, cases)).alias("rscore"))


def best_of(results: DataFrame) -> DataFrame:
    """Each method's best value and the setting that gave it. results: method, setting, value."""
    return results.groupBy("method").agg(F.max("value").alias("value"), F.max_by("setting", "value").alias("setting"))


def head_items(ratings: DataFrame, share: float = 1 / 3) -> DataFrame:
    """The most rated items that together hold the share of the ratings: item_id, n, before (ratings of the items above).

    The running sum is over the distinct numbers of ratings (at most the root of twice their total), then over the items of one number,
    and only of numbers that reach the head: no window runs over all items.
    """
    counts = ratings.groupBy("item_id").agg(F.count("*").alias("n"))
    by_number = counts.groupBy("n").agg(F.sum("n").alias("held"))
    above = Window.orderBy(F.desc("n")).rowsBetween(Window.unboundedPreceding, -1)
    total = by_number.agg(F.sum("held").alias("total"))  # one row
    numbers = by_number.withColumn("above", F.coalesce(F.sum("held").over(above), F.lit(0))).crossJoin(F.broadcast(total)).where(F.col("above") < F.col("total") * share)
    order = Window.partitionBy("n").orderBy("item_id")
    placed = counts.join(F.broadcast(numbers), "n").withColumn("before", F.col("above") + F.col("n") * (F.row_number().over(order) - 1))
    return placed.where(F.col("before") < F.col("total") * share).select("item_id", "n", "before")


def tail_cases(cases: DataFrame, ratings: DataFrame, share: float = 1 / 3) -> DataFrame:
    return cases.join(F.broadcast(head_items(ratings, share).select("item_id")), "item_id", "left_anti")


def community(ratings: DataFrame, share: float, seed: int = 42) -> DataFrame:
    """A share of the ratings; smaller shares are nested in larger ones."""
    return ratings.where(fraction(seed, "user_id", "item_id") < share)


def new_users(ratings: DataFrame, users: int = 50, least: int = 100, drop: float = 0.95, seed: int = 11) -> tuple[DataFrame, DataFrame]:
    """(ratings with the chosen users' rows thinned out, the chosen users): so many users with at least ``least`` ratings lose a share."""
    eligible = ratings.groupBy("user_id").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    chosen = eligible.orderBy(fraction(seed, "user_id"), "user_id").limit(users).select("user_id")
    marked = ratings.join(F.broadcast(chosen.withColumn("fresh", F.lit(True))), "user_id", "left")
    left = marked.where(F.col("fresh").isNull() | (fraction(seed, "user_id", "item_id") >= drop)).drop("fresh")
    return left, chosen


@dataclass(frozen=True)
class Standard:
    probe: float = 0.014
    seed: int = 42

    def split(self, ratings: DataFrame) -> tuple[DataFrame, DataFrame]:
        train, probe = probe_split(ratings, self.probe, self.seed)
        return train, test_cases(probe)


@dataclass(frozen=True)
class LongTail:
    probe: float = 0.014
    head_share: float = 1 / 3
    seed: int = 42

    def split(self, ratings: DataFrame) -> tuple[DataFrame, DataFrame]:
        train, cases = Standard(self.probe, self.seed).split(ratings)
        return train, tail_cases(cases, ratings, self.head_share)


@dataclass(frozen=True)
class NewCommunity:
    share: float
    probe: float = 0.014
    seed: int = 42

    def split(self, ratings: DataFrame) -> tuple[DataFrame, DataFrame]:
        return Standard(self.probe, self.seed + 1).split(community(ratings, self.share, self.seed))


@dataclass(frozen=True)
class NewUsers:
    k: int = 50
    least: int = 100
    drop: float = 0.95
    probe: float = 0.10
    seed: int = 42

    def split(self, ratings: DataFrame) -> tuple[DataFrame, DataFrame]:
        thin, chosen = new_users(ratings, self.k, self.least, self.drop, self.seed)
        own = thin.join(F.broadcast(chosen), "user_id", "left_semi")
        _, probe = probe_split(own, self.probe, self.seed + 2)
        cases = test_cases(probe, best=1.0)
        return thin.join(probe.select("user_id", "item_id"), ["user_id", "item_id"], "left_anti"), cases


def evaluate(scenario, ratings: DataFrame, scorer, negatives: int = NEGATIVES) -> DataFrame:
    """Ranked lists of a scenario under a scorer: scorer(train, pairs with case_id, user_id, item_id, is_target) adds score."""
    from proxrec.plans.planner import cut

    train, cases = scenario.split(ratings)
    train, cases = cut(train), cut(cases)
    lists = candidates(cases, ratings, negatives)
    return ranked(scorer(train, lists))
