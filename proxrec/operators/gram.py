"""Products with the proximity operator on Spark: packed rows with partial sums, rows of a similarity, and a purely relational form."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes of partial sums that travel as one value, and how many of them meet in one task.
CHUNK_BYTES, FAN_IN = 4_000_000, 32
#: Rows of a similarity that are multiplied at once.
ROWS_AT_ONCE = 64
#: Partial sums of all tasks together that the driver may add by itself, without a shuffle.
DRIVER_SUMS = 64_000_000
#: Cells of ratings that a task spreads out densely, and rows of ratings that it multiplies at once.
SPREAD_CELLS, PRODUCT_ROWS = 2_000_000, 1000
#: Rounds of the relational form after which its columns double.
WIDEN = 6


def pack_rows(ratings: DataFrame, index: DataFrame) -> DataFrame:
    """(user_id, ix array<int>, x array<double>): one row a user, in item order. One shuffle by user; the index is joined first."""
    placed = ratings.join(index, "item_id").select("user_id", F.struct("item_ix", "rating").alias("e"))
    rows = placed.groupBy("user_id").agg(F.array_sort(F.collect_list("e")).alias("e"))
    return rows.select("user_id", F.col("e.item_ix").alias("ix"), F.col("e.rating").alias("x"))


def batch_csr(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row ends, item indexes and values of a batch of packed rows, without Python objects."""
    ix, x = batch.column("ix"), batch.column("x")
    lengths = ix.value_lengths().to_numpy(zero_copy_only=False)
    return np.cumsum(lengths), ix.flatten().to_numpy(zero_copy_only=False).astype(np.int64), x.flatten().to_numpy(zero_copy_only=False)


def row_sums(ends: np.ndarray, terms: np.ndarray) -> np.ndarray:
    starts = np.concatenate([[0], ends[:-1]])
    return np.add.reduceat(terms, np.minimum(starts, max(len(terms) - 1, 0)), axis=0) * (ends > starts)[:, None] if len(terms) else np.zeros((len(ends), terms.shape[1]))


def added(pdf: pd.DataFrame) -> pd.DataFrame:
    """One row of summed vectors for a group of partial ones; at most FAN_IN values of CHUNK_BYTES."""
    total = np.frombuffer(pdf["sums"].iloc[0]).copy()
    for b in pdf["sums"].iloc[1:]:
        total += np.frombuffer(b)
    return pd.DataFrame({"chunk": [pdf["chunk"].iloc[0]], "part": [pdf["part"].iloc[0] // FAN_IN], "sums": [total.tobytes()]})


def summed(partial: DataFrame, tasks: int) -> DataFrame:
    """chunk, part, sums of the partial sums of so many tasks, FAN_IN of them at a time: no group grows with the number of tasks."""
    schema = "chunk int, part int, sums binary"
    while tasks > 1:
        tasks = -(-tasks // FAN_IN)
        partial = partial.groupBy("chunk", F.floor(F.col("part") / FAN_IN).alias("at")).applyInPandas(lambda key, pdf: added(pdf), schema)
    return partial


def gathered(partial: DataFrame, tasks: int, chunk: int, out: np.ndarray) -> np.ndarray:
    """The partial sums of so many tasks added to ``out``, whose rows stand in chunks of so many: by the driver where they are small, else in a tree."""
    sums = partial if out.nbytes * tasks <= DRIVER_SUMS else summed(partial, tasks)
    for r in sums.toLocalIterator() if sums is not partial else sums.collect():
        out[r["chunk"] * chunk : (r["chunk"] + 1) * chunk] += np.frombuffer(r["sums"]).reshape(-1, out.shape[1])
    return out


def pair_sums(rows: DataFrame, m: int, marks: bool = False) -> np.ndarray:
    """R'R of packed rows, or with ``marks`` the number of users that each pair of items has in common, in one pass over rows that stay where they are.

    For item sets whose matrix a task and the driver can hold, whatever the number of ratings.
    """
    chunk = max(1, CHUNK_BYTES // (8 * m))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        total, step = np.zeros((m, m)), max(1, SPREAD_CELLS // m)
        for whole in batches:
            for a in range(0, whole.num_rows, step):
                batch = whole.slice(a, step)
                ends, ix, v = batch_csr(batch)
                flat = np.repeat(np.arange(len(ends)), np.diff(ends, prepend=0)) * m + ix
                x = np.bincount(flat, weights=None if marks else v, minlength=len(ends) * m).reshape(-1, m)
                x = (x > 0).astype(float) if marks else x
                total += x.T @ x
        own = TaskContext.get().partitionId()
        for k, a in enumerate(range(0, m, chunk)):
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([own], pa.int32()), pa.array([total[a : a + chunk].tobytes()], pa.binary())], names=["chunk", "part", "sums"])

    partial = rows.select("ix", "x").mapInArrow(run, "chunk int, part int, sums binary")
    return gathered(partial, rows.rdd.getNumPartitions(), chunk, np.zeros((m, m)))


class GramOperator:
    """g (R'R / scale - shift shift') g over packed rows on Spark.

    A product broadcasts the block X, lets every task multiply its rows both ways (R X, then R' of it), and adds the
    partial sums by chunk of items in a tree: rows of the user side never move. X and the sums have m rows; the planner checks their size.
    """

    distributed = True

    def __init__(self, rows: DataFrame, m: int, g: np.ndarray, scale: float = 1.0, shift: np.ndarray | None = None):
        self.rows, self.m, self.g, self.scale, self.shift = rows.select("ix", "x"), m, g[:, None], scale, shift
        self.passes, self.seconds = 0, 0.0
        self._tasks: int | None = None

    @property
    def tasks(self) -> int:
        if self._tasks is None:
            self._tasks = self.rows.rdd.getNumPartitions()
        return self._tasks

    def partial(self, x: np.ndarray) -> tuple[DataFrame, object, int]:
        """(chunk, part, sums) a task, the broadcast block, and the items of a chunk."""
        m, width = x.shape
        chunk = max(1, CHUNK_BYTES // (8 * width))
        shared = self.rows.sparkSession.sparkContext.broadcast(x)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            from pyspark import TaskContext

            total, block = np.zeros((width, m)), shared.value
            for whole in batches:
                for a in range(0, whole.num_rows, PRODUCT_ROWS):
                    ends, ix, v = batch_csr(whole.slice(a, PRODUCT_ROWS))
                    y = row_sums(ends, v[:, None] * block[ix])
                    user = np.repeat(np.arange(len(ends)), np.diff(ends, prepend=0))
                    # only the items that occur: a slice has few of them
                    at, ix = np.unique(ix, return_inverse=True)
                    for c in range(width):
                        total[c][at] += np.bincount(ix, weights=v * y[user, c], minlength=len(at))
            own = TaskContext.get().partitionId()
            for k, a in enumerate(range(0, m, chunk)):
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([own], pa.int32()), pa.array([total[:, a : a + chunk].T.tobytes()], pa.binary())], names=["chunk", "part", "sums"])

        return self.rows.mapInArrow(run, "chunk int, part int, sums binary"), shared, chunk

    def gram(self, x: np.ndarray) -> np.ndarray:
        partial, shared, chunk = self.partial(x)
        out = gathered(partial, self.tasks, chunk, np.zeros(x.shape))
        shared.unpersist()
        return out

    def apply(self, x: np.ndarray) -> np.ndarray:
        t = time.perf_counter()
        z = self.g * x
        y = self.gram(z) / self.scale
        if self.shift is not None:
            y = y - self.shift[:, None] * (self.shift @ z)
        self.passes += 1
        self.seconds += time.perf_counter() - t
        return self.g * y


class RowOperator:
    """S K S with the rows of a sparse symmetric K packed on Spark (i, ix, x): every task multiplies its rows with the broadcast block; nothing is added up."""

    distributed = True

    def __init__(self, rows: DataFrame, m: int, s: np.ndarray):
        self.rows, self.m, self.s, self.passes = rows, m, s[:, None], 0

    def apply(self, x: np.ndarray) -> np.ndarray:
        width = x.shape[1]
        shared = self.rows.sparkSession.sparkContext.broadcast(self.s * x)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for whole in batches:
                for a in range(0, whole.num_rows, ROWS_AT_ONCE):
                    batch = whole.slice(a, ROWS_AT_ONCE)
                    ends, ix, v = batch_csr(batch)
                    y = row_sums(ends, v[:, None] * shared.value[ix])
                    at = batch.column("i").to_numpy().astype(np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array([at.tobytes()], pa.binary()), pa.array([y.tobytes()], pa.binary())], names=["at", "y"])

        out = np.zeros((self.m, width))
        for r in self.rows.mapInArrow(run, "at binary, y binary").toLocalIterator():
            out[np.frombuffer(r["at"], np.int64)] = np.frombuffer(r["y"]).reshape(-1, width)
        shared.unpersist()
        self.passes += 1
        return self.s * out


def pack_pairs(pairs: DataFrame, index: DataFrame) -> DataFrame:
    """(i, ix, x): the rows of a symmetric similarity given as pairs (i, j, v), by item index; pairs of unknown items are left out."""
    one = index.select(F.col("item_id").alias("i"), F.col("item_ix").alias("at"))
    two = index.select(F.col("item_id").alias("j"), F.col("item_ix").alias("other"))
    rows = pairs.join(one, "i").join(two, "j").groupBy("at").agg(F.array_sort(F.collect_list(F.struct("other", "v"))).alias("e"))
    return rows.select(F.col("at").alias("i"), F.col("e.other").alias("ix"), F.col("e.v").alias("x"))


def relational_product(ratings: DataFrame, q: DataFrame, weights: DataFrame) -> DataFrame:
    """One product y = g R'R g q with vectors as relations q(item_id, q, ...) and weights(item_id, g): two joins and two aggregations.

    For item sets beyond a broadcast; nothing is collected. Items absent from q count as 0. All columns of q but item_id are vectors.
    """
    names = [c for c in q.columns if c != "item_id"]
    scaled = q.join(weights.select("item_id", "g"), "item_id").select("item_id", *[(F.col(c) * F.col("g")).alias(c) for c in names])
    users = ratings.join(scaled, "item_id").groupBy("user_id").agg(*[F.sum(F.col("rating") * F.col(c)).alias(c) for c in names])
    items = ratings.join(users, "user_id").groupBy("item_id").agg(*[F.sum(F.col("rating") * F.col(c)).alias(c) for c in names])
    return items.join(weights.select("item_id", "g"), "item_id").select("item_id", *[(F.col(c) * F.col("g")).alias(c) for c in names])


def relational_power(ratings: DataFrame, weights: DataFrame, rounds: int = 30, every: int = 3) -> DataFrame:
    """Leading eigenvector (item_id, q) of g R'R g by power iteration on relations; every few rounds lineage is cut and the vector normalised."""
    from proxrec.plans.planner import cut

    ratings, weights = cut(ratings), cut(weights)
    q = weights.where("g > 0").select("item_id", F.lit(1.0).alias("q"))
    for k in range(rounds):
        q = relational_product(ratings, q, weights)
        if (k + 1) % every == 0 or k + 1 == rounds:
            q = cut(q)
            norm = q.agg(F.sqrt(F.sum(F.col("q") * F.col("q")))).first()[0] or 1.0
            q = q.withColumn("q", F.col("q") / norm)
    return q


def _matrix(batch: pa.RecordBatch, names: list[str]) -> np.ndarray:
    return np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in names], 1)


def _sums(q: DataFrame, of: Callable[[pa.RecordBatch], np.ndarray], shape: tuple[int, ...]) -> np.ndarray:
    """A small matrix summed over all items: by every task for its own, then by the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(shape)
        for batch in batches:
            total += of(batch)
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["sums"])

    total = np.zeros(shape)
    for r in q.mapInArrow(run, "sums binary").toLocalIterator():
        total += np.frombuffer(r["sums"]).reshape(shape)
    return total


def _turned(q: DataFrame, names: list[str], by: np.ndarray) -> DataFrame:
    kept = [f"q{k}" for k in range(by.shape[1])]
    schema = T.StructType([q.schema["item_id"], *[T.StructField(c, T.DoubleType()) for c in kept]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("item_id"), *map(pa.array, (_matrix(batch, names) @ by).T)], names=["item_id", *kept])

    return q.mapInArrow(run, schema)


def _unit(q: DataFrame, names: list[str]) -> tuple[DataFrame, list[str]]:
    """Orthonormal columns by the small matrix of their products; dependent ones go. The second turn takes away what rounding left."""
    from proxrec.plans.planner import cut

    for _ in range(2):
        at, xi = np.linalg.eigh(_sums(q, lambda b, names=names: _matrix(b, names).T @ _matrix(b, names), (len(names), len(names))))
        keep = at > 1e-14 * max(at[-1], 1e-300)
        q, names = cut(_turned(q, names, xi[:, keep] / np.sqrt(at[keep]))), names[: int(keep.sum())]
    return q, names


def relational_subspace(ratings: DataFrame, weights: DataFrame, f: int, rounds: int = 60, tol: float = 1e-6, extra: int = 4, allow_partial: bool = False, least: float | None = None) -> tuple[np.ndarray, DataFrame]:
    """(values, vectors(item_id, q0, ..)): the f leading eigenpairs of g R'R g by orthogonal iteration with every vector kept as a relation.

    Only matrices of the columns squared reach the driver, whatever the number of items. Start values are hashes of the item keys; each round's
    vectors are checkpointed. Ends when the residuals, as a share of the largest value, are below tol; else an error unless allowed. It begins with
    f + extra columns, which double every WIDEN rounds, so that close values part.
    With ``least`` it finds every pair whose value exceeds that, as many as there are, and f is where the search begins; the residuals above the cut must also
    be below a thousandth of tol as a share of the gap there, for they turn the space that the pairs span by as much.
    """
    from proxrec.plans.planner import cut

    ratings, weights = cut(ratings), cut(weights.where("g > 0"))
    start = lambda k: (F.xxhash64(F.lit(k), F.col("item_id").cast("string")) / float(1 << 63)).alias(f"q{k}")
    names = [f"q{k}" for k in range(f + extra)]
    q = weights.select("item_id", *[start(k) for k in range(len(names))])
    value, residual = np.zeros(f), np.inf
    for done in range(1, rounds + 1):
        asked = len(names)
        q, names = _unit(q, names)
        full, images = len(names) < asked, [f"y{k}" for k in range(len(names))]
        both = cut(q.join(relational_product(ratings, q, weights).toDF("item_id", *images), "item_id"))
        small = _sums(both, lambda b, n=names, y=images: _matrix(b, n).T @ _matrix(b, y), (len(names), len(names)))
        at, xi = np.linalg.eigh((small + small.T) / 2)
        value, xi = at[::-1], xi[:, ::-1]
        rest = np.sqrt(_sums(both, lambda b, n=names, y=images, v=value, x=xi: ((_matrix(b, y) @ x - _matrix(b, n) @ x * v) ** 2).sum(0), (len(names),)))
        above = f if least is None else int((value > least).sum())
        # one pair below the cut settles too, so that none above it is missed
        pairs = min(f if least is None else max(f, above + 1), len(value))
        residual = float(rest[:pairs].max() / max(value[0], 1e-300))
        if least is not None and 0 < above < len(value):
            residual = max(residual, 1e3 * float(rest[:above].max()) / (value[above - 1] - value[above]))
        more = 0 if full else above + extra - len(names)
        # without a column that is independent of the others, these span all that there is
        if more <= 0 and (residual <= tol or full and residual <= 1e3 * tol or len(names) < f):
            break
        q = _turned(both, images, xi)
        more = more if full else max(more, len(names) if done % WIDEN == 0 else 0)
        if more > 0:
            fresh = range(len(names), len(names) + more)
            q, names = q.select("*", *[start(k) for k in fresh]), [*names, *[f"q{k}" for k in fresh]]
    else:
        if not allow_partial:
            raise ArithmeticError(f"relational form: not converged in {rounds} rounds; residual {residual:.3g}")
    return value[:above], _turned(both, names, xi[:, :above])
