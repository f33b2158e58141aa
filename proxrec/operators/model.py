"""The scaled-proximity latent model: fit, recommend, explain, fold in, save and load.

The similarity is cosine, Pearson or Jaccard, or given as pairs (i, j, v); the scaling any of operators.proximity. Solves that do not
reach the tolerance are errors unless the spec allows them. Vectors that exceed a broadcast are worked through in blocks of items.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.storagelevel import StorageLevel

from proxrec.plans.planner import BROADCAST_BYTES, DENSE_ITEMS, LOCAL_NNZ, PAIR_ITEMS, choose_operator

from . import linalg
from .gram import GramOperator, RowOperator, batch_csr, pack_pairs, pack_rows, pair_sums, relational_subspace, row_sums
from .linalg import Csr, Eigen
from .proximity import NormScaling, jaccard_pairs
from .ratings import item_stats

#: Scores held at once by a task, and cells of ratings that the driver spreads out densely.
CELLS, DENSE_CELLS = 4_000_000, 50_000_000


@dataclass(frozen=True)
class ModelSpec:
    similarity: str = "cosine"  # cosine, pearson, jaccard, or pairs (given to fit)
    d: float = 0.4
    f: int = 10
    solver: str = "auto"  # auto, dense, lanczos, thick, block, filtered
    form: str = "auto"  # auto, dense, local, blocks, relational (cosine only)
    project_with: str = "original"  # original rows, or rows scaled as in the rescaled-matrix identity
    seed: int = 1
    tol: float = 1e-10
    allow_partial: bool = False  # keep factors that did not reach tol; their residuals stand in the trace
    least: float | None = None  # the factors are those whose value exceeds this, however many; f is where the search begins


@dataclass
class LatentModel:
    spec: ModelSpec
    items: list  # keys by item_ix, in sorted order
    norms: np.ndarray
    vectors: np.ndarray  # items x f
    values: np.ndarray
    trace: linalg.Trace

    def phi(self) -> np.ndarray:
        return self.vectors @ self.vectors.T

    def truncated(self, f: int) -> LatentModel:
        """One solve serves every smaller number of factors."""
        return LatentModel(self.spec, self.items, self.norms, self.vectors[:, :f], self.values[:f], self.trace)

    def index(self, spark: SparkSession) -> DataFrame:
        return item_index(spark, self.items)

    def latent(self, spark: SparkSession) -> DataFrame:
        """(item_id, item_ix, v array<double>, norm)."""
        m, f = self.vectors.shape
        v = pa.ListArray.from_arrays(pa.array(np.arange(0, m * f + 1, f) if f else np.zeros(m + 1, int), pa.int32()), pa.array(np.ascontiguousarray(self.vectors).reshape(-1), pa.float64()))
        table = pa.table({"item_id": pa.array(self.items, pa.string() if isinstance(_key_type(self.items), T.StringType) else pa.int64()), "item_ix": pa.array(range(m), pa.int32()), "v": v, "norm": pa.array(self.norms, pa.float64())})
        return spark.createDataFrame(table)

    def save(self, spark: SparkSession, path: str) -> None:
        self.latent(spark).write.mode("overwrite").parquet(f"{path}/latent")
        spec = json.dumps(self.spec.__dict__)
        spark.createDataFrame([(spec, self.values.tolist())], "spec string, theta array<double>").write.mode("overwrite").parquet(f"{path}/spec")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> LatentModel:
        spec, theta = spark.read.parquet(f"{path}/spec").first()
        rows = spark.read.parquet(f"{path}/latent").orderBy("item_ix").collect()
        return cls(ModelSpec(**json.loads(spec)), [r["item_id"] for r in rows], np.array([r["norm"] for r in rows], float), np.array([r["v"] for r in rows]), np.array(theta), linalg.Trace(path="loaded"))


def _key_type(keys: list) -> T.DataType:
    return T.StringType() if keys and isinstance(keys[0], str) else T.LongType()


def item_index(spark: SparkSession, items: list) -> DataFrame:
    return spark.createDataFrame(pa.table({"item_id": pa.array(items, pa.string() if isinstance(_key_type(items), T.StringType) else pa.int64()), "item_ix": pa.array(np.arange(len(items), dtype=np.int32))}))


def weights_of(norms: np.ndarray, d: float, divide: np.ndarray | None = None) -> np.ndarray:
    """norm**d, divided; items whose norm or divisor is 0 get 0 and so leave the model."""
    divide = norms if divide is None else divide
    ok = (norms > 0) & (divide > 1e-12)
    out = np.zeros(len(norms))
    out[ok] = norms[ok] ** d / divide[ok]
    return out


def triplets(ratings: DataFrame) -> tuple[list, list, np.ndarray, np.ndarray, np.ndarray]:
    """Sorted keys of users and items, and the ratings by index; for the forms that the planner lets the driver hold."""
    t = ratings.select("user_id", "item_id", F.col("rating").cast("double")).toArrow()
    users, items = t.column(0).to_pandas(), t.column(1).to_pandas()
    user_keys, row = np.unique(users.to_numpy(), return_inverse=True)
    item_keys, column = np.unique(items.to_numpy(), return_inverse=True)
    return user_keys.tolist(), item_keys.tolist(), row, column, t.column(2).to_numpy()


def scaled_by(s: np.ndarray, divide: np.ndarray) -> np.ndarray:
    """s / divide, and 0 for items without a scale or a divisor, which so leave the model."""
    ok = (s > 0) & (divide > 1e-12)
    out = np.zeros(len(s))
    out[ok] = s[ok] / divide[ok]
    return out


def both_counts(ones: Csr, m: int) -> np.ndarray:
    """The users that each pair of items has in common: one dense product where the ratings fit it, else by blocks of columns."""
    n = ones.shape[0]
    if n * m <= DENSE_CELLS:
        dense = np.zeros((n, m), np.float32)
        dense[ones.row, ones.column] = 1
        return (dense.T @ dense).astype(np.float64)  # counts below 2**24 are exact
    both = np.zeros((m, m))
    for a in range(0, m, 512):
        unit = np.zeros((m, min(512, m - a)))
        unit[np.arange(a, a + unit.shape[1]), np.arange(unit.shape[1])] = 1
        both[:, a : a + unit.shape[1]] = ones.tdot(ones.dot(unit))
    return both


def local_operator(row, column, value, n: int, m: int, similarity: str, d: float, scale: np.ndarray | None = None):
    """The proximity operator over ratings on the driver, and the items' norms; ``scale`` stands for the norms to the power d."""
    r = Csr(row, column, value, (n, m))
    s1, s2 = np.bincount(column, weights=value, minlength=m), np.bincount(column, weights=value * value, minlength=m)
    norms = np.sqrt(s2)
    s = weights_of(norms, d, np.ones(m)) if scale is None else np.where(norms > 0, scale, 0)
    if similarity == "cosine":
        return linalg.LocalOperator(r, scaled_by(s, norms)), norms
    if similarity == "pearson":
        mean = s1 / n
        return linalg.LocalOperator(r, scaled_by(s, np.sqrt(np.maximum(0, s2 / n - mean * mean))), float(n), mean), norms
    if similarity == "jaccard":
        if m > PAIR_ITEMS:
            raise MemoryError(f"the driver forms Jaccard pairs of {PAIR_ITEMS} items at most; fit with form auto or blocks keeps them on Spark")
        k = np.bincount(column, minlength=m).astype(np.float64)
        both = both_counts(Csr(row, column, np.ones(len(value)), (n, m)), m)
        sim = np.where(both > 0, both / np.maximum(k[:, None] + k[None, :] - both, 1), 0)
        return linalg.DenseOperator(s[:, None] * sim * s[None, :]), norms
    raise ValueError(similarity)


def dense_matrix(op) -> np.ndarray:
    return op.a if isinstance(op, linalg.DenseOperator) else op.apply(np.eye(op.m))


def summed_operator(rows: DataFrame, similarity: str, norms: np.ndarray, mean: np.ndarray, sd: np.ndarray, s: np.ndarray) -> linalg.DenseOperator:
    """The proximity matrix of few items whose ratings stay on Spark as packed rows: the driver holds items squared."""
    sums = pair_sums(rows, len(norms), similarity == "jaccard")
    if similarity == "jaccard":
        k = np.diag(sums)
        return linalg.DenseOperator(s[:, None] * np.where(sums > 0, sums / np.maximum(k[:, None] + k[None, :] - sums, 1), 0) * s[None, :])
    if similarity == "pearson":
        sums = sums / float(rows.count()) - np.outer(mean, mean)
    g = scaled_by(s, norms if similarity == "cosine" else sd)
    return linalg.DenseOperator(g[:, None] * sums * g[None, :])


def solve(op, spec: ModelSpec) -> Eigen:
    """The spec's factors of an operator; an error if they do not reach its tolerance, unless it allows that."""
    if spec.least is None:
        return leading(op, spec, spec.f)
    f = spec.f + 1
    while True:
        found = leading(op, spec, min(f, op.m))
        above = int((found.values > spec.least).sum())
        if above < len(found.values) or len(found.values) == op.m:
            return Eigen(found.values[:above], found.vectors[:, :above], found.trace)
        f *= 2


def leading(op, spec: ModelSpec, f: int) -> Eigen:
    how = spec.solver
    far = getattr(op, "distributed", False)
    if how == "auto":
        how = "block" if far else "dense" if op.m <= 3000 else "lanczos"
    more = {"tol": spec.tol, "seed": spec.seed, "allow_partial": spec.allow_partial}
    if how == "dense":
        return linalg.dense_eigh(dense_matrix(op), f)
    if how in SOLVERS:
        return SOLVERS[how](op, f, **more)
    raise ValueError(how)


SOLVERS = {"lanczos": linalg.lanczos, "thick": linalg.thick_restart_lanczos, "block": linalg.block_subspace, "filtered": linalg.filtered_lanczos}


def fit(ratings: DataFrame, spec: ModelSpec, pairs: DataFrame | None = None, scaling=None, weights: DataFrame | None = None) -> LatentModel:
    """Fits the model. Small relations are solved on the driver; larger ones by block products over packed rows on Spark.

    ``pairs`` (i, j, v), symmetric, is the similarity of a spec whose similarity is "pairs"; absent pairs count as 0. ``scaling`` replaces the norms
    to the power d; a column that it reads beside the item statistics comes from ``weights`` (item_id and that column; absent items leave the model).
    """
    if (spec.similarity == "pairs") != (pairs is not None):
        raise ValueError("pairs are given with the similarity pairs, and only with it")
    level = ratings.storageLevel
    if level.useMemory or level.useDisk:
        return fitted(ratings, spec, pairs, scaling, weights)
    # counted, summed and packed in turn: a view is worked out once
    ratings = ratings.persist(StorageLevel.DISK_ONLY)
    try:
        return fitted(ratings, spec, pairs, scaling, weights)
    finally:
        ratings.unpersist()


def fitted(ratings: DataFrame, spec: ModelSpec, pairs: DataFrame | None, scaling, weights: DataFrame | None) -> LatentModel:
    """The model of ratings that are read several times."""
    form = chosen_form(ratings, spec, pairs, scaling)
    if form == "relational":
        stats = item_stats(ratings)
        known = stats.orderBy("item_id").select("item_id", "norm").toArrow()
        items = known.column("item_id").to_pylist()
        values, vectors = relational_subspace(ratings, stats.select("item_id", F.pow("norm", F.lit(spec.d - 1)).alias("g")), spec.f, tol=max(spec.tol, 1e-6), allow_partial=spec.allow_partial, least=spec.least)
        rows = vectors.join(item_index(ratings.sparkSession, items), "item_id").drop("item_id").toArrow()
        v = np.zeros((len(items), len(values)))
        v[np.array(rows.column("item_ix"))] = np.stack([np.array(rows.column(f"q{k}")) for k in range(len(values))], 1)
        return LatentModel(spec, items, np.array(known.column("norm")), v, values, linalg.Trace(path="relational"))
    op, items, norms, rows = item_operator(ratings, spec.similarity, spec.d, form, pairs, scaling, weights)
    try:
        found = solve(op, spec)
    finally:
        if rows is not None:
            rows.unpersist()
    return LatentModel(spec, items, norms, found.vectors, found.values, found.trace)


def chosen_form(ratings: DataFrame, spec: ModelSpec, pairs: DataFrame | None = None, scaling=None) -> str:
    form = spec.form
    if form == "auto":
        n, m, nnz = ratings.agg(F.count_distinct("user_id"), F.count_distinct("item_id"), F.count("*")).first()
        form = choose_operator(n, m, nnz, spec.f, spec.similarity).form
    return "blocks" if form == "relational" and (spec.similarity != "cosine" or scaling is not None) else form


def item_operator(ratings: DataFrame, similarity: str, d: float, form: str, pairs: DataFrame | None = None, scaling=None, weights: DataFrame | None = None):
    """The operator in the given form, the items and their norms, and the rows to unpersist afterwards (or None).

    The forms dense and local hold ratings on the driver only up to LOCAL_NNZ of them; beyond, few items have their matrix summed up on Spark and
    many go by blocks.
    """
    spark, small = ratings.sparkSession, form in ("dense", "local")
    stats = item_stats(ratings)
    if weights is not None:
        stats = stats.join(weights, "item_id", "left")
    if small and pairs is None and ratings.count() <= LOCAL_NNZ:
        users, items, row, column, value = triplets(ratings)
        scale = None if scaling is None else scales(stats, scaling, items)
        op, norms = local_operator(row, column, value, len(users), len(items), similarity, d, scale)
        return op, items, norms, None
    known = stats.select("item_id", "norm", "mean", "sd", (scaling or NormScaling(d)).column().alias("s")).orderBy("item_id").toArrow()
    items = known.column("item_id").to_pylist()
    norms, mean, sd, s = (np.array(known.column(c).fill_null(0.0)) for c in ("norm", "mean", "sd", "s"))
    s = np.where(norms > 0, s, 0)
    index = item_index(spark, items)
    if pairs is not None and small and pairs.count() <= LOCAL_NNZ:
        one, two = index.select(F.col("item_id").alias("i"), F.col("item_ix").alias("a")), index.select(F.col("item_id").alias("j"), F.col("item_ix").alias("b"))
        t = pairs.join(one, "i").join(two, "j").select("a", "b", F.col("v").cast("double")).toArrow()
        return linalg.PairsOperator(Csr(*(np.array(t.column(k)) for k in range(3)), (len(items), len(items))), s), items, norms, None
    if pairs is None and small and len(items) <= DENSE_ITEMS:
        rows = pack_rows(ratings, index).persist()
        op = summed_operator(rows, similarity, norms, mean, sd, s)
    elif similarity in ("jaccard", "pairs"):
        rows = pack_pairs(jaccard_pairs(ratings) if pairs is None else pairs, index).persist()
        op = RowOperator(rows, len(items), s)
    else:
        rows = pack_rows(ratings, index).persist()
        op = GramOperator(rows, len(items), scaled_by(s, norms)) if similarity == "cosine" else GramOperator(rows, len(items), scaled_by(s, sd), float(rows.count()), mean)
    return op, items, norms, rows


def scales(stats: DataFrame, scaling, items: list) -> np.ndarray:
    """The scaling's values in item order."""
    found = dict(map(tuple, stats.select("item_id", scaling.column()).collect()))
    return np.array([found.get(k) or 0.0 for k in items])


def best_n(scores: np.ndarray, n: int) -> np.ndarray:
    """Columns of the n largest of a row, by score rounded to 1e-9, then by column; NaN never ranks."""
    s = np.round(scores, 9)
    ok = np.flatnonzero(~np.isnan(s))
    if len(ok) > n:
        least = np.partition(s[ok], len(ok) - n)[len(ok) - n]
        ok = ok[s[ok] >= least]
    return ok[np.lexsort((ok, -s[ok]))][:n]


def item_blocks(model: LatentModel, bytes_: int | None = None) -> list[tuple[int, int]]:
    """Ranges of items whose vectors fit a broadcast each."""
    m, f = model.vectors.shape
    step = max(1, (bytes_ or BROADCAST_BYTES) // (8 * max(1, f)))
    return [(a, min(m, a + step)) for a in range(0, m, step)] or [(0, 0)]


def factors(model: LatentModel, rows: DataFrame, blocks: list[tuple[int, int]]) -> DataFrame:
    """Packed rows (user_id, ix, x) with p, the user's factors: one narrow step a block of items, whose vectors are broadcast."""
    sc = rows.sparkSession.sparkContext
    scale = np.ones(len(model.norms)) if model.spec.project_with == "original" else weights_of(model.norms, model.spec.d)
    f = model.vectors.shape[1]
    schema = T.StructType([*rows.schema.fields, T.StructField("p", T.ArrayType(T.DoubleType()))])
    for k, (a, b) in enumerate(blocks):
        shared = sc.broadcast(model.vectors[a:b] * scale[a:b, None])

        def run(batches, a=a, b=b, first=not k, shared=shared):
            from pyspark.sql.pandas.types import to_arrow_schema

            out = to_arrow_schema(schema)
            for whole in batches:
                for at in range(0, whole.num_rows, 1000):
                    batch = whole.slice(at, 1000)
                    ends, ix, x = batch_csr(batch)
                    inside = (ix >= a) & (ix < b)
                    p = row_sums(ends, np.where(inside, x, 0)[:, None] * shared.value[np.where(inside, ix - a, 0)]) if b > a else np.zeros((batch.num_rows, f))
                    if not first:
                        p = p + batch.column("p").flatten().to_numpy().reshape(-1, f)
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(p) + 1) * f, pa.int32()), pa.array(p.reshape(-1)))
                    yield pa.RecordBatch.from_arrays([batch.column(c).cast(out.field(c).type) for c in out.names[:-1]] + [lists], schema=out)

        rows = rows.mapInArrow(run, schema)
    return rows


def recommend(model: LatentModel, ratings: DataFrame, n: int = 10, exclude_seen: bool = True, block_bytes: int | None = None) -> DataFrame:
    """(user_id, rank, item_id, score): each user's n best items. Users stay where they are; V is broadcast by blocks of items that fit."""
    from pyspark.sql import Window

    spark = ratings.sparkSession
    blocks = item_blocks(model, block_bytes)
    rows = factors(model, pack_rows(ratings, model.index(spark)), blocks)
    schema = T.StructType([ratings.schema["user_id"], T.StructField("rank", T.IntegerType()), T.StructField("item_id", _key_type(model.items)), T.StructField("score", T.DoubleType())])
    alive = model.norms > 0

    def best(shared):
        def run(batches):
            from pyspark.sql.pandas.types import to_arrow_schema

            first, v, items, alive = shared.value
            out, f = to_arrow_schema(schema), v.shape[1]
            step = max(1, CELLS // max(1, len(items)))
            for whole in batches:
                for a in range(0, whole.num_rows, step):
                    batch = whole.slice(a, step)
                    ends, ix, _ = batch_csr(batch)
                    ix = ix - first
                    scores = batch.column("p").flatten().to_numpy().reshape(-1, f) @ v.T
                    scores[:, ~alive] = np.nan
                    users, ranks, keys, values = [], [], [], []
                    start = 0
                    for i, (user, end) in enumerate(zip(batch.column("user_id").to_pylist(), ends.tolist(), strict=True)):
                        if exclude_seen:
                            own = ix[start:end]
                            scores[i, own[(own >= 0) & (own < len(items))]] = np.nan
                        start = end
                        top = best_n(scores[i], n)
                        users += [user] * len(top)
                        ranks += range(1, len(top) + 1)
                        keys += [items[j] for j in top]
                        values += scores[i, top].tolist()
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip((users, ranks, keys, values), out, strict=True)], schema=out)

        return run

    parts = [rows.mapInArrow(best(spark.sparkContext.broadcast((a, model.vectors[a:b], model.items[a:b], alive[a:b]))), schema) for a, b in blocks]
    if len(parts) == 1:
        return parts[0]
    every = parts[0]
    for part in parts[1:]:
        every = every.unionByName(part)
    order = Window.partitionBy("user_id").orderBy(F.desc(F.round("score", 9)), "item_id")
    return every.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= n)


def dot(a: str, b: str):
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def _small(model: LatentModel, latent: DataFrame) -> DataFrame:
    """The items' vectors, broadcast if they fit."""
    return F.broadcast(latent) if 8 * model.vectors.size <= BROADCAST_BYTES else latent


def score_pairs(model: LatentModel, ratings: DataFrame, pairs: DataFrame) -> DataFrame:
    """score for the given (user_id, item_id) pairs only: factors of their users from packed rows, then a join to the items' vectors; 0 for users or items the model lacks."""
    spark = ratings.sparkSession
    users = ratings.join(pairs.select("user_id").distinct(), "user_id", "left_semi")
    own = factors(model, pack_rows(users, model.index(spark)), item_blocks(model)).select("user_id", "p")
    found = pairs.join(own, "user_id", "left").join(_small(model, model.latent(spark).select("item_id", "v")), "item_id", "left")
    return found.withColumn("score", F.coalesce(dot("p", "v"), F.lit(0.0))).drop("p", "v")


def explain(model: LatentModel, ratings: DataFrame, pairs: DataFrame, k: int = 5) -> DataFrame:
    """The k rated items that add most to each pair's score: contribution = rating * phi."""
    from pyspark.sql import Window

    latent = model.latent(ratings.sparkSession)
    one = _small(model, latent.select(F.col("item_id"), F.col("v").alias("target")))
    own = _small(model, latent.select(F.col("item_id").alias("rated_item"), F.col("v").alias("source")))
    rated = ratings.select("user_id", F.col("item_id").alias("rated_item"), "rating")
    parts = pairs.join(one, "item_id").join(rated, "user_id").join(own, "rated_item").withColumn("contribution", F.col("rating") * dot("target", "source"))
    order = Window.partitionBy("user_id", "item_id").orderBy(F.desc(F.round("contribution", 9)), "rated_item")
    return parts.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).select("user_id", "item_id", "rated_item", "place", "contribution")


def fold_in(model: LatentModel, fresh: DataFrame, n: int = 10) -> DataFrame:
    """Recommendations for users the model has never seen, without a new solve."""
    return recommend(model, fresh, n)


def tsvd(ratings: DataFrame, f: int, **how) -> LatentModel:
    """Truncated-SVD reconstruction in item space: the case of cosine and d = 1."""
    return fit(ratings, ModelSpec("cosine", 1.0, f, **how))


def rescaled(ratings: DataFrame, d: float) -> DataFrame:
    """Ratings with each item's column multiplied by its norm to the power d - 1."""
    norms = ratings.groupBy("item_id").agg(F.sqrt(F.sum(F.col("rating") * F.col("rating"))).alias("norm"))
    return ratings.join(norms, "item_id").select("user_id", "item_id", (F.col("rating") * F.pow("norm", F.lit(d - 1.0))).alias("rating"))


def tune(ratings: DataFrame, kinds: list[str], ds: list[float], fs: list[int], measure) -> list[dict]:
    """measure(model) for every setting; one solve at the largest f serves the smaller ones."""
    out = []
    for kind in kinds:
        for d in ds:
            model = fit(ratings, ModelSpec(kind, d, max(fs)))
            out += [{"similarity": kind, "d": d, "f": f, "value": measure(model.truncated(f))} for f in fs]
    return out
