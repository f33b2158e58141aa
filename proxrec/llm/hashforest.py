"""Nearest neighbours by inner product through a forest of hash-string prefix trees.

Each tree gives every vector a string of BITS hyperplane signs (after the usual lift that turns inner products into angles: vectors
are scaled by the largest norm and get one more component). Rows are dealt to parts of PART_ROWS once, by a hash of id and vector, and every part holds the
sorted arrays of its strings, an array a tree. A query descends to its longest matches and ascends in all trees at once, tree after tree
within a level, until the trees together hold SHARE of all rows with its prefixes. Counts by prefix of DEPTH bits, a table of fixed size, give
each query's level in every tree before a vector moves. Its matches are then contiguous runs of the sorted arrays, scored exactly on the
original vectors. A vector moves once, a query once for each part.

SHARE is a share, not a number: on directions without structure a fixed number of candidates loses recall as rows are added.

Defined results: vectors that are null, zero, of another length than the most common one (the longer of two as common), or with null or non-finite
components, and null ids take no part; ``left_out`` counts them. Equal scores rank by smaller id; an id given several times counts once, with
its best score, and never as its own neighbour; fewer candidates than k give fewer rows; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, load

TREES, BITS, DEPTH = 24, 48, 12
SHARE = 0.9
#: Candidates (repeats in several trees included) that a query gets at least.
LEAST = 1_000
PART_ROWS = 200_000
#: Scores held at once.
CELLS = 4_000_000


def usable(vector: str) -> Column:
    return F.expr(f"`{vector}` IS NOT NULL AND forall(`{vector}`, x -> x IS NOT NULL AND NOT isnan(x) AND abs(x) < double('infinity')) AND exists(`{vector}`, x -> x <> 0)")


def planes(dim: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal((dim + 1, TREES * BITS))


def strings(x: np.ndarray, normals: np.ndarray, largest: float, is_query: bool) -> np.ndarray:
    """Hash strings as integers: rows x TREES, first bit highest."""
    x = x / np.linalg.norm(x, axis=1, keepdims=True) if is_query else x / largest
    extra = np.zeros((len(x), 1)) if is_query else np.sqrt(np.maximum(0, 1 - (x * x).sum(1, keepdims=True)))
    signs = (np.hstack([x, extra]) @ normals > 0).reshape(len(x), TREES, BITS)
    return signs @ (np.int64(1) << np.arange(BITS - 1, -1, -1, dtype=np.int64))


def matrix(column: pa.Array, dtype) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(dtype)
    return flat.reshape(len(column), -1)


def prefix_counts(rows: DataFrame, normals, largest: float) -> np.ndarray:
    """TREES x 2**DEPTH counts over all rows; every task sends one table of that size."""

    def run(batches):
        total = np.zeros((TREES, 1 << DEPTH), np.int64)
        for batch in batches:
            if batch.num_rows:
                h = strings(matrix(batch.column("vector"), np.float64), normals.value, largest, False) >> (BITS - DEPTH)
                for t in range(TREES):
                    total[t] += np.bincount(h[:, t], minlength=1 << DEPTH)
        if total.any():
            yield pa.RecordBatch.from_arrays([pa.array(range(TREES), pa.int32()), pa.array([x.tobytes() for x in total], pa.binary())], names=["tree", "counts"])

    def added(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"tree": [pdf["tree"].iloc[0]], "counts": [sum(np.frombuffer(x, np.int64) for x in pdf["counts"]).tobytes()]})

    out = np.zeros((TREES, 1 << DEPTH), np.int64)
    for r in rows.select("vector").mapInArrow(run, "tree int, counts binary").groupBy("tree").applyInPandas(added, "tree int, counts binary").collect():
        out[r["tree"]] = np.frombuffer(r["counts"], np.int64)
    return out


def levels(h: np.ndarray, sums: list[np.ndarray], budget: float) -> np.ndarray:
    """Levels (queries x trees) at which the trees together reach the budget: all ascend level by level, and within the last one tree after tree.

    A row of zeros but one -1 a tree stands for the whole first tree, where the budget takes all rows.
    """
    q = len(h)
    level = np.full((q, TREES), -1, np.int8)
    level[:, 0] = 0
    open_ = np.ones(q, bool)
    below = np.zeros((q, TREES), np.int64)
    for x in range(DEPTH, 0, -1):
        held = np.stack([sums[x][t][h[:, t] >> (BITS - x)] for t in range(TREES)], 1)
        reach = np.cumsum(held - below, axis=1) + below.sum(1, keepdims=True)  # the first trees at x, the others still below
        done = np.flatnonzero(open_ & (reach[:, -1] >= budget))
        last = (reach[done] >= budget).argmax(1)
        deeper = -1 if x == DEPTH else x + 1
        level[done] = np.where(np.arange(TREES)[None, :] <= last[:, None], x, deeper)
        open_[done] = False
        below = held
    return level


def search(base_id: np.ndarray, base: np.ndarray, h: np.ndarray, query_id: np.ndarray, queries: np.ndarray, hq: np.ndarray, level: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best of each query within its prefix run of one sorted array: query ids, ids, scores. A level below 0 asks nothing."""
    asked = level >= 0
    query_id, queries, hq, level = query_id[asked], queries[asked], hq[asked], level[asked].astype(np.int64)
    order = np.argsort(h, kind="stable")
    base_id, base, h = base_id[order], base[order], h[order]
    shift = BITS - level
    low = (hq >> shift) << shift
    start, stop = np.searchsorted(h, low), np.searchsorted(h, low + (np.int64(1) << shift))
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    runs, of = np.unique(np.stack([start, stop], 1), axis=0, return_inverse=True)
    for i, (a, b) in enumerate(runs.tolist()):
        if a == b:
            continue
        ids, vectors = base_id[a:b], base[a:b].astype(np.float64)
        by = np.argsort(ids, kind="stable")
        first = np.flatnonzero(np.append(True, ids[by][1:] != ids[by][:-1]))
        mine = np.flatnonzero(of.reshape(-1) == i)
        for c in range(0, len(mine), max(1, CELLS // (b - a))):
            part = mine[c : c + max(1, CELLS // (b - a))]
            q = queries[part].astype(np.float64)
            scores = q @ vectors.T
            by_id = scores if len(first) == b - a else np.maximum.reduceat(scores[:, by], first, axis=1)
            top = min(k + 1, len(first))  # ids, one more, since the query may find its own
            least = np.partition(by_id, len(first) - top, axis=1)[:, len(first) - top] - 1e-9
            for j, row in enumerate(scores):
                near = np.flatnonzero(row >= least[j])
                near = near[ids[near] != query_id[part[j]]]
                exact = (vectors[near] * q[j]).sum(1)
                best = np.lexsort((ids[near], -exact))
                best = best[np.sort(np.unique(ids[near][best], return_index=True)[1])[:k]]  # an id's best row only
                out.append((np.full(len(best), query_id[part[j]]), ids[near][best], exact[best]))
    if not out:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def best_of(query: np.ndarray, found: np.ndarray, score: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best distinct ids of each query, of what several trees found."""
    order = np.lexsort((found, -score, query))
    query, found, score = query[order], found[order], score[order]
    pair = np.lexsort((np.arange(len(query)), found, query))
    first = np.ones(len(query), bool)
    first[1:] = (query[pair][1:] != query[pair][:-1]) | (found[pair][1:] != found[pair][:-1])
    keep = np.sort(pair[first])
    query, found, score = query[keep], found[keep], score[keep]
    start = np.flatnonzero(np.append(True, query[1:] != query[:-1])) if len(query) else np.zeros(0, np.int64)
    place = np.arange(len(query)) - np.repeat(start, np.diff(np.append(start, len(query))))
    return query[place < k], found[place < k], score[place < k]


def left_out(rows: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """size, usable, n: how many rows have vectors of each length, and whether such rows may take part (one length only does)."""
    fine = F.coalesce(usable(vector_col) & F.col(id_col).isNotNull(), F.lit(False))
    return rows.groupBy(F.size(F.col(f"`{vector_col}`")).alias("size"), fine.alias("usable")).agg(F.count("*").alias("n"))


def nearest(rows: DataFrame, is_query: Column, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", share: float = SHARE, seed: int = 7) -> DataFrame:
    """query_id, rank (from 1), the neighbour's id under its own name, and score, for the k nearest rows found of each query row."""
    spark = rows.sparkSession
    rows = rows.where(usable(vector_col) & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.col(f"`{vector_col}`").alias("vector"), F.coalesce(is_query, F.lit(False)).alias("asks"))
    sizes = rows.groupBy(F.size("vector").alias("dim")).agg(F.count("*").alias("n")).agg(F.max(F.struct("n", "dim")).alias("most")).first()["most"]
    if sizes is None:
        return spark.createDataFrame([], f"query_id long, rank int, `{id_col}` long, score double")
    dim = sizes["dim"]
    # equal rows would fill runs and candidates with copies
    rows = cut(rows.where(F.size("vector") == dim).groupBy("id", "vector").agg(F.max("asks").alias("asks")))
    n, largest = rows.agg(F.count("*"), F.max(F.sqrt(F.aggregate("vector", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))))).first()
    single = isinstance(rows.schema["vector"].dataType.elementType, T.FloatType)
    kind = np.float32 if single else np.float64
    normals = spark.sparkContext.broadcast(planes(dim, seed))  # size set by the dimension
    shared = spark.sparkContext.broadcast(prefix_counts(rows, normals, largest))  # TREES x 2**DEPTH, whatever the number of rows
    parts = max(1, -(-n // PART_ROWS))
    budget = max(share * n, LEAST)

    def deal(batches):
        table = shared.value
        sums = [table.reshape(TREES, 1 << x, -1).sum(2) for x in range(DEPTH + 1)]
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                x = matrix(part.column("vector"), kind)
                ids, home = part.column("id").to_numpy(), part.column("home").to_numpy()
                raw = [v.tobytes() for v in x]
                rows_of = [np.arange(len(x))]
                where, level = [home], [None] * len(x)
                ask = np.flatnonzero(part.column("asks").to_numpy(zero_copy_only=False))
                if len(ask):
                    lv = levels(strings(x[ask].astype(np.float64), normals.value, largest, True), sums, min(budget, 2 * TREES * n))
                    for p in range(parts):
                        rows_of.append(ask)
                        where.append(np.full(len(ask), p, np.int64))
                        level += [v.tobytes() for v in lv]
                which = np.concatenate(rows_of)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(where)), pa.array(ids[which]), pa.array(level, pa.binary()), pa.array([raw[i] for i in which.tolist()], pa.binary())], names=["part", "id", "level", "vector"])

    def find(pdf: pd.DataFrame) -> pd.DataFrame:
        asks = pdf["level"].notna().to_numpy()
        x = np.frombuffer(b"".join(pdf["vector"]), kind).reshape(len(pdf), dim)
        ids = pdf["id"].to_numpy()
        empty = pd.DataFrame({"query_id": np.zeros(0, np.int64), "id": np.zeros(0, np.int64), "score": np.zeros(0)})
        if not asks.any() or asks.all():
            return empty
        lv = np.frombuffer(b"".join(pdf["level"][asks]), np.int8).reshape(-1, TREES)
        base, queries = x[~asks], x[asks]
        h = np.concatenate([strings(base[a : a + 5000].astype(np.float64), normals.value, largest, False) for a in range(0, len(base), 5000)])
        hq = np.concatenate([strings(queries[a : a + 5000].astype(np.float64), normals.value, largest, True) for a in range(0, len(queries), 5000)])
        held = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        for t in range(TREES):
            if (lv[:, t] >= 0).any():
                more = search(ids[~asks], base, h[:, t], ids[asks], queries, hq[:, t], lv[:, t], k)
                held = best_of(*(np.concatenate(c) for c in zip(held, more, strict=True)), k)
        return pd.DataFrame(dict(zip(("query_id", "id", "score"), held, strict=True)))

    placed = rows.withColumn("home", F.pmod(F.xxhash64("id", "vector"), F.lit(parts)).cast("long"))
    found = placed.mapInArrow(deal, "part long, id long, level binary, vector binary").groupBy("part").applyInPandas(find, "query_id long, id long, score double")
    best = found.groupBy("query_id", "id").agg(F.max("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", F.col("id").alias(id_col), "score")


def op3_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(load(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)
