"""Experiments: one scenario, many methods with whole parameter grids, all measures.

A scenario is prepared once: training rows, cases and drawn items are packed by test user. Every method then scores a block of users for all its
settings and hands back only the rank of each case's held-out item, from which all measures follow, for a list has one relevant item.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxrec.plans.planner import cut

from . import evaluation, kernels, linalg, model
from .gram import batch_csr, pack_rows, row_sums

HALF_LIVES = (2.0, 5.0, 10.0, 20.0)
HITS = "method string, setting string, case_id string, tail boolean, hit int"
SIMILARITIES = ("cosine", "pearson", "jaccard")


@dataclass
class Prepared:
    """train (user_id, item_id, rating); users (user_id, ix, x, cases, others) by place in ``items``, the sorted keys of all items."""

    train: DataFrame
    users: DataFrame
    items: list


def prepare(scenario, ratings: DataFrame, negatives: int = evaluation.NEGATIVES, head_share: float = 1 / 3) -> Prepared:
    """Splits once and packs what the test users need. Cases of items outside the head are marked as tail."""
    spark = ratings.sparkSession
    train, cases = scenario.split(ratings)
    train, cases = cut(train), cut(cases)
    items = [r[0] for r in ratings.select("item_id").distinct().orderBy("item_id").collect()]
    index = model.item_index(spark, items)
    tail = evaluation.tail_cases(cases, ratings, head_share).select("case_id").withColumn("tail", F.lit(True))
    marked = cases.join(tail, "case_id", "left").join(index, "item_id")
    per_user = marked.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("case_id", "item_ix", F.coalesce("tail", F.lit(False)).alias("tail")))).alias("cases"))
    who = cut(per_user)
    drawn = evaluation.negatives_of(who.select("user_id"), ratings, negatives).join(index, "item_id").groupBy("user_id").agg(F.array_sort(F.collect_list("item_ix")).alias("others"))
    rows = pack_rows(train.join(who.select("user_id"), "user_id", "left_semi"), index)
    none = lambda c, t: F.coalesce(F.col(c), F.array().cast(t)).alias(c)
    users = who.join(rows, "user_id", "left").join(drawn, "user_id", "left").select("user_id", none("ix", "array<int>"), none("x", "array<double>"), "cases", none("others", "array<int>"))
    return Prepared(train, cut(users), items)


def hit_rank(scores: np.ndarray, target: int, others: np.ndarray) -> int:
    """Place of the target among the others: larger score first (rounded to 1e-9), then smaller item."""
    mine, theirs = np.round(scores[target], 9), np.round(scores[others], 9)
    return 1 + int((theirs > mine).sum() + ((theirs == mine) & (others < target)).sum())


def block_hits(method: str, setting: str, scores: np.ndarray, users: list[dict]) -> list[tuple]:
    out = []
    for row, user in zip(scores, users, strict=True):
        others = np.asarray(user["others"], np.int64)
        out += [(method, setting, c["case_id"], c["tail"], hit_rank(row, c["item_ix"], others)) for c in user["cases"]]
    return out


def latent_hits(prepared: Prepared, method: str, fitted: list[tuple[str, model.LatentModel]], fs: list[int]) -> DataFrame:
    """Ranks under several models at several numbers of factors: one job, models broadcast (their size is checked by the planner's limit)."""
    place = {k: i for i, k in enumerate(prepared.items)}
    settings = []
    for label, m in fitted:
        v = np.zeros((len(prepared.items), m.vectors.shape[1]))
        v[[place[k] for k in m.items]] = m.vectors
        settings.append((label, v))
    if sum(v.nbytes for _, v in settings) > model.BROADCAST_BYTES:
        half = len(fitted) // 2
        if not half:
            raise MemoryError("one model exceeds a broadcast")
        return latent_hits(prepared, method, fitted[:half], fs).unionByName(latent_hits(prepared, method, fitted[half:], fs))
    shared = prepared.users.sparkSession.sparkContext.broadcast(settings)

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 64):
                batch = whole.slice(at, 64)
                ends, ix, x = batch_csr(batch)
                users = batch.select(["cases", "others"]).to_pylist()
                found = []
                for label, v in shared.value:
                    p = row_sums(ends, x[:, None] * v[ix])
                    scores, before = np.zeros((len(users), len(v))), 0
                    for f in fs:
                        scores = scores + p[:, before:f] @ v[:, before:f].T
                        before = f
                        found += block_hits(method, f"{label} f={f}", scores, users)
                yield pa.RecordBatch.from_pandas(pd.DataFrame(found, columns=["method", "setting", "case_id", "tail", "hit"]).astype({"hit": np.int32}), preserve_index=False)

    return prepared.users.mapInArrow(run, HITS)


class Proximities:
    """The leading factors of one similarity for many scalings: what does not depend on the scaling is made once."""

    def __init__(self, train: DataFrame, similarity: str):
        self.users, self.items, self.row, self.column, self.value = model.triplets(train)
        self.n, self.m, self.similarity, self.train = len(self.users), len(self.items), similarity, train
        self.dense = None
        if similarity == "jaccard" and self.m <= model.PAIR_ITEMS:
            op, self.norms = model.local_operator(self.row, self.column, self.value, self.n, self.m, "jaccard", 0.0)
            self.dense = op.a
        elif similarity != "jaccard" and kernels.DenseGraph.fits(self.n, self.m):
            r = np.zeros((self.n, self.m))
            r[self.row, self.column] = self.value
            self.norms = np.linalg.norm(r, axis=0)
            self.dense = r / self.norms if similarity == "cosine" else (r - r.mean(0)) / np.where(r.std(0) > 1e-12, r.std(0), np.inf) / np.sqrt(self.n)

    def fit(self, d: float, f: int, tol: float = 1e-8) -> model.LatentModel:
        spec = model.ModelSpec(self.similarity, d, f, tol=tol)
        if self.dense is None:
            return model.fit(self.train, spec)
        s = np.where(self.norms > 0, np.power(np.maximum(self.norms, 1e-300), d), 0)
        if self.similarity == "jaccard":
            found = linalg.lanczos(linalg.DenseOperator(s[:, None] * self.dense * s), f, tol)
        else:
            found = linalg.factor_eigh(self.dense * s, f)
        return model.LatentModel(spec, self.items, self.norms, found.vectors, found.values, found.trace)


def latent_methods(prepared: Prepared, ds: list[float], fs: list[int], similarities=SIMILARITIES) -> DataFrame:
    """Every similarity at every scaling and number of factors; one solve serves all numbers of factors."""
    out = None
    for kind in similarities:
        own = Proximities(prepared.train, kind)
        fitted = [(f"d={d:g}", own.fit(d, max(fs))) for d in ds]
        one = latent_hits(prepared, f"latent {kind}", fitted, fs)
        out = one if out is None else out.unionByName(one)
    return out


def svd_method(prepared: Prepared, fs: list[int]) -> DataFrame:
    return latent_hits(prepared, "truncated svd", [("d=1", Proximities(prepared.train, "cosine").fit(1.0, max(fs)))], fs)


def setting_name(how: dict) -> str:
    return " ".join(f"{k}={v:g}" for k, v in how.items()) or "none"


def kernel_methods(prepared: Prepared, grid: dict[str, list[dict]] | None = None) -> DataFrame:
    """The graph kernels over their whole parameter ranges, for the test users; a graph beyond the dense form goes setting by setting through kernel_scores."""
    spark, grid = prepared.users.sparkSession, grid or kernels.GRID
    user_keys, item_keys, row, column, value = model.triplets(prepared.train)
    if not kernels.DenseGraph.fits(len(user_keys), len(item_keys)):
        return _kernel_lists(prepared, grid)
    dense = kernels.DenseGraph(kernels.Graph(row, column, np.ones(len(value)), len(user_keys), len(item_keys)))
    place = {k: i for i, k in enumerate(user_keys)}
    at = np.searchsorted(np.array(prepared.items), np.array(item_keys))
    users = [r.asDict(recursive=True) for r in prepared.users.orderBy("user_id").collect()]  # users of a dense graph: a few thousand
    known = np.array([place.get(u["user_id"], -1) for u in users])
    found = []
    for kind, settings in grid.items():
        for how in settings:
            scores = np.full((len(users), len(prepared.items)), -1e300)
            scores[np.ix_(np.flatnonzero(known >= 0), at)] = dense.rows(kind, known[known >= 0], **how)
            found += block_hits(f"kernel {kind}", setting_name(how), scores, users)
    return spark.createDataFrame(pd.DataFrame(found, columns=["method", "setting", "case_id", "tail", "hit"]), HITS)


def lists_of(prepared: Prepared) -> DataFrame:
    """(case_id, user_id, item_id, is_target, tail), unpacked."""
    index = model.item_index(prepared.users.sparkSession, prepared.items)
    case = prepared.users.select("user_id", F.explode("cases").alias("c"), "others").select("user_id", "c.case_id", "c.tail", F.col("c.item_ix").alias("target"), "others")
    both = case.select("user_id", "case_id", "tail", F.explode(F.concat(F.array(F.struct(F.col("target").alias("item_ix"), F.lit(True).alias("is_target"))), F.transform("others", lambda x: F.struct(x.alias("item_ix"), F.lit(False).alias("is_target"))))).alias("e"))
    return both.select("case_id", "user_id", "tail", "e.item_ix", "e.is_target").join(index, "item_ix").drop("item_ix")


def scored_hits(lists: DataFrame, method: str, setting: str) -> DataFrame:
    """Ranks from lists with a score column."""
    placed = evaluation.ranked(lists)
    return placed.where("is_target").select(F.lit(method).alias("method"), F.lit(setting).alias("setting"), "case_id", "tail", F.col("rank").alias("hit"))


def _kernel_lists(prepared: Prepared, grid: dict[str, list[dict]]) -> DataFrame:
    lists, out = cut(lists_of(prepared)), None
    for kind, settings in grid.items():
        for how in settings:
            own = kernels.kernel_scores(prepared.train, kind, lists.select("user_id").distinct(), **how)
            one = scored_hits(lists.join(own, ["user_id", "item_id"], "left").withColumn("score", F.coalesce("score", F.lit(-1e300))), f"kernel {kind}", setting_name(how))
            out = one if out is None else out.unionByName(one)
    return out


def plain_methods(prepared: Prepared) -> DataFrame:
    """Popularity and random order."""
    lists = cut(lists_of(prepared))
    return scored_hits(kernels.popularity(prepared.train, lists), "popularity", "none").unionByName(scored_hits(kernels.random_rank(lists), "random", "none"))


def measures(hits: DataFrame, by: tuple[str, ...] = ("method", "setting")) -> DataFrame:
    """by.., measure, k, value, n_cases: mrr, recall and precision at 1..20, NDCG (offset 2 and 1) at 1..20, and RScore by half-life.

    A list has one relevant item, at rank hit: its ideal gain is that of rank 1.
    """
    k = F.explode(F.sequence(F.lit(1), F.lit(20))).alias("k")
    grouped = hits.withColumn("hit", F.col("hit").cast("double"))
    whole = grouped.groupBy(*by).agg(F.avg(1 / F.col("hit")).alias("mrr"), F.count("*").alias("n_cases"))
    at = grouped.select(*by, "hit", k).groupBy(*by, "k").agg(
        F.avg((F.col("hit") <= F.col("k")).cast("double")).alias("recall"),
        *[F.avg(F.when(F.col("hit") <= F.col("k"), float(np.log2(1 + o)) / F.log2(F.col("hit") + o)).otherwise(0.0)).alias(f"ndcg_{o}") for o in (2, 1)],
        F.count("*").alias("n_cases"),
    )
    lives = F.explode(F.array(*[F.lit(h) for h in HALF_LIVES])).alias("h")
    score = grouped.select(*by, "hit", lives).groupBy(*by, "h").agg(F.avg(1 / F.pow(F.lit(2.0), (F.col("hit") - 1) / (F.col("h") - 1))).alias("rscore"), F.count("*").alias("n_cases"))
    one = lambda df, name, column, k: df.select(*by, F.lit(name).alias("measure"), k.cast("int").alias("k"), (F.round(column, 6) + 0.0).alias("value"), "n_cases")
    out = one(whole, "mrr", F.col("mrr"), F.lit(0))
    for name, column in (("recall", F.col("recall")), ("precision", F.col("recall") / F.col("k")), ("ndcg", F.col("ndcg_2")), ("ndcg_offset1", F.col("ndcg_1"))):
        out = out.unionByName(one(at, name, column, F.col("k")))
    return out.unionByName(one(score, "rscore", F.col("rscore"), F.col("h")))


def tuned(hits: DataFrame, groups: tuple[str, ...] = ()) -> DataFrame:
    """The measures of every method at its best setting, chosen by MRR on the test cases (as the comparison does); ties to the first name."""
    by = (*groups, "method")
    rows = hits.groupBy(*by, "setting").agg(F.avg(1 / F.col("hit")).alias("value"))
    best = rows.groupBy(*by).agg(F.min(F.struct((-F.round("value", 9)).alias("v"), "setting")).alias("b")).select(*by, F.col("b.setting").alias("setting"))
    return measures(hits.join(F.broadcast(best), [*by, "setting"]), (*by, "setting"))
