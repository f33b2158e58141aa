"""Scalings, similarities and the proximity A = S K S as relations (pairs) in DataFrame operations."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .ratings import item_stats

#: Items of which a similarity that is dense by definition is written out in full.
FULL_ITEMS = 20_000


@dataclass(frozen=True)
class NormScaling:
    """Item norm to the power d; 0 where the norm is 0."""

    d: float

    def column(self) -> Column:
        return F.when(F.col("norm") > 0, F.pow(F.col("norm"), F.lit(float(self.d)))).otherwise(0.0)


@dataclass(frozen=True)
class CountScaling:
    """Number of raters to the power d."""

    d: float

    def column(self) -> Column:
        return F.when(F.col("n_raters") > 0, F.pow(F.col("n_raters").cast("double"), F.lit(float(self.d)))).otherwise(0.0)


@dataclass(frozen=True)
class PropensityScaling:
    """A column of the item statistics, joined by the caller, to the power d."""

    weight: str
    d: float = 1.0

    def column(self) -> Column:
        return F.when(F.col(self.weight) > 0, F.pow(F.col(self.weight).cast("double"), F.lit(float(self.d)))).otherwise(0.0)


def co_ratings(ratings: DataFrame) -> DataFrame:
    """(i, j, dot, both) for all ordered pairs of items with a user in common, i = j included.

    Pairs are summed on the map side; heavy users are the cost (the square of their degree), which skew joins split.
    """
    a = ratings.select("user_id", F.col("item_id").alias("i"), F.col("rating").alias("x"))
    b = ratings.select("user_id", F.col("item_id").alias("j"), F.col("rating").alias("y"))
    return a.join(b, "user_id").groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("dot"), F.count("*").alias("both"))


def _with_both(pairs: DataFrame, items: DataFrame) -> DataFrame:
    one = lambda side: items.select(*[F.col(c).alias(f"{c}_{side}" if c != "item_id" else side) for c in items.columns])
    return pairs.join(one("i"), "i").join(one("j"), "j")


def small_enough(items: DataFrame) -> None:
    """Full matrices are written out for so many items only; the model's product form and ``vector_top`` serve larger sets."""
    n = items.count()
    if n > FULL_ITEMS:
        raise MemoryError(f"{n} items: a matrix of all pairs is written out for {FULL_ITEMS} items at most")


def cosine_pairs(ratings: DataFrame) -> DataFrame:
    p = _with_both(co_ratings(ratings), item_stats(ratings).where("norm > 0"))
    return p.select("i", "j", (F.col("dot") / (F.col("norm_i") * F.col("norm_j"))).alias("v"))


def pearson_pairs(ratings: DataFrame, corated: bool = False) -> DataFrame:
    """Correlation over all users, absent ratings being 0; pairs without a common user included. ``corated``: over common users only."""
    if corated:
        a = ratings.select("user_id", F.col("item_id").alias("i"), F.col("rating").alias("x"))
        b = ratings.select("user_id", F.col("item_id").alias("j"), F.col("rating").alias("y"))
        sums = a.join(b, "user_id").groupBy("i", "j").agg(F.covar_pop("x", "y").alias("c"), F.var_pop("x").alias("p"), F.var_pop("y").alias("q"))
        return sums.where("p > 1e-12 AND q > 1e-12").select("i", "j", (F.col("c") / F.sqrt(F.col("p") * F.col("q"))).alias("v"))
    n = ratings.select("user_id").distinct().count()
    items = item_stats(ratings, n).where("sd > 0")
    # every pair of items: the matrix is dense by definition, so this form is for small item sets only
    small_enough(items)
    every = items.select(F.col("item_id").alias("i")).crossJoin(items.select(F.col("item_id").alias("j")))
    p = _with_both(every.join(co_ratings(ratings), ["i", "j"], "left"), items)
    return p.select("i", "j", ((F.coalesce("dot", F.lit(0.0)) / n - F.col("mean_i") * F.col("mean_j")) / (F.col("sd_i") * F.col("sd_j"))).alias("v"))


def pearson_rated_pairs(ratings: DataFrame) -> DataFrame:
    """The correlation over all users for pairs of items with a user in common; others are below 0. No pair is written that has none."""
    n = ratings.select("user_id").distinct().count()
    p = _with_both(co_ratings(ratings), item_stats(ratings, n).where("sd > 0"))
    return p.select("i", "j", ((F.col("dot") / n - F.col("mean_i") * F.col("mean_j")) / (F.col("sd_i") * F.col("sd_j"))).alias("v"))


def jaccard_pairs(ratings: DataFrame) -> DataFrame:
    p = _with_both(co_ratings(ratings), item_stats(ratings))
    return p.select("i", "j", (F.col("both") / (F.col("n_raters_i") + F.col("n_raters_j") - F.col("both"))).alias("v"))


def minhash_signatures(ratings: DataFrame, hashes: int = 64) -> DataFrame:
    """item_id, mins: for each of so many hash functions the least hash of the item's users. One shuffle of partial minima."""
    mins = [F.min(F.xxhash64(F.lit(k), "user_id")).alias(f"h{k}") for k in range(hashes)]
    return ratings.groupBy("item_id").agg(*mins).select("item_id", F.array(*[f"h{k}" for k in range(hashes)]).alias("mins"))


def minhash_jaccard_pairs(ratings: DataFrame, hashes: int = 64) -> DataFrame:
    """Estimates of the Jaccard similarity: the share of equal minima, for pairs with one at least."""
    s = minhash_signatures(ratings, hashes).select("item_id", F.posexplode("mins").alias("k", "h"))
    a, b = s.select(F.col("item_id").alias("i"), "k", "h"), s.select(F.col("item_id").alias("j"), "k", "h")
    return a.join(b, ["k", "h"]).groupBy("i", "j").agg((F.count("*") / hashes).alias("v"))


def vector_pairs(items: DataFrame, item: str, vector: str) -> DataFrame:
    """Cosine of given item vectors for every pair (a custom similarity); the item set must be small, as in pearson_pairs."""
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    small_enough(items)
    a = items.select(F.col(item).alias("i"), F.col(vector).alias("a"))
    b = items.select(F.col(item).alias("j"), F.col(vector).alias("b"))
    return a.crossJoin(b).select("i", "j", (dot("a", "b") / F.sqrt(dot("a", "a") * dot("b", "b"))).alias("v"))


def vector_top(items: DataFrame, item: str, vector: str, k: int = 20, block: int = 8192) -> DataFrame:
    """i, rank, j, v: the k most similar others of every item by the cosine of given vectors, over all rows.

    Items are dealt to blocks and each task compares two of them, strip by strip, so that no row meets another outside a matrix product. Null and zero
    vectors, those with null or non-finite components or of another length than the longest, and null ids take no part; an id given several
    times counts once, with its best value; equal values rank by smaller id.
    """
    fine = F.expr(f"`{item}` IS NOT NULL AND forall(`{vector}`, x -> x IS NOT NULL AND abs(x) < double('infinity')) AND exists(`{vector}`, x -> x <> 0)")
    rows = items.where(fine).select(F.col(item).cast("long").alias("i"), F.col(vector).cast("array<double>").alias("x"))
    n, dim = rows.agg(F.count("*"), F.max(F.size("x"))).first()
    blocks = max(1, -(-n // block))
    dealt = rows.where(F.size("x") == (dim or 0)).withColumn("own", F.pmod(F.xxhash64("i"), F.lit(blocks)).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    dealt = dealt.select("i", "x", "own", F.least("own", "other").alias("a"), F.greatest("own", "other").alias("b"))

    def best(left, right):
        ids, y = right
        names, first = np.unique(ids, return_index=True)
        mine, begin = np.unique(left[0], return_index=True)
        for at in range(0, len(mine), 256):  # ids, whose rows stand together
            begins = begin[at : at + 256]
            end = begin[at + 256] if at + 256 < len(mine) else len(left[0])
            v = np.maximum.reduceat(np.maximum.reduceat(left[1][begins[0] : end] @ y.T, first, axis=1), begins - begins[0], axis=0)
            v[mine[at : at + 256, None] == names[None, :]] = -np.inf
            top = min(k, len(names))
            least = np.partition(v, len(names) - top, axis=1)[:, len(names) - top] - 1e-9
            for i, row, low in zip(mine[at : at + 256], v, least, strict=True):
                near = np.flatnonzero((row >= low) & (row > -np.inf))
                near = near[np.lexsort((names[near], -np.round(row[near], 9)))[:k]]
                yield pd.DataFrame({"i": np.full(len(near), i), "j": names[near], "v": np.clip(row[near], -1, 1)})

    def compared(pdf: pd.DataFrame) -> pd.DataFrame:
        a, b = int(pdf["a"].iloc[0]), int(pdf["b"].iloc[0])
        sides = []
        for own in (a, b):
            part = pdf[pdf["own"] == own].sort_values("i")
            x = np.array(part["x"].tolist(), np.float64).reshape(len(part), dim)
            sides.append((part["i"].to_numpy(), x / np.linalg.norm(x, axis=1, keepdims=True)))
        found = [*best(*sides), *(best(*sides[::-1]) if a < b else ())] if all(len(s[0]) for s in sides) else []
        return pd.concat(found) if found else pd.DataFrame({"i": np.zeros(0, np.int64), "j": np.zeros(0, np.int64), "v": np.zeros(0)})

    order = Window.partitionBy("i").orderBy(F.desc(F.round("v", 9)), "j")
    found = dealt.groupBy("a", "b").applyInPandas(compared, "i long, j long, v double")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("i", "rank", "j", "v")


def neighbour_pairs(items: DataFrame, item: str, vector: str, k: int = 20) -> DataFrame:
    """(i, j, v): a sparse symmetric similarity from given vectors, for models over content: each item with itself (1) and with those
    where one is among the other's k most similar. Item keys must be integers, as in vector_top."""
    near = vector_top(items, item, vector, k).select("i", "j", "v")
    both = near.unionByName(near.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"))
    own = items.where(F.col(item).isNotNull()).select(F.col(item).cast("long").alias("i")).distinct().select("i", F.col("i").alias("j"), F.lit(1.0).alias("v"))
    return both.groupBy("i", "j").agg(F.max("v").alias("v")).unionByName(own)


SIMILARITIES = {"cosine": cosine_pairs, "pearson": pearson_pairs, "jaccard": jaccard_pairs}


def scaled_pairs(pairs: DataFrame, items: DataFrame, scaling) -> DataFrame:
    """S K S as pairs."""
    s = items.select("item_id", scaling.column().alias("s"))
    return _with_both(pairs, s).select("i", "j", (F.col("s_i") * F.col("v") * F.col("s_j")).alias("v"))


def proximity(ratings: DataFrame, similarity: str = "cosine", d: float = 0.4) -> DataFrame:
    return scaled_pairs(SIMILARITIES[similarity](ratings), item_stats(ratings), NormScaling(d))
