"""Quality classifier: random-indexing word vectors pooled per document, then a two-layer numpy network with calibrated probabilities.

Every token (letter case kept; runs of word characters or of punctuation) falls into one of BUCKETS hashed words. A word's vector sums the sparse
ternary index vectors of its neighbours within WINDOW over the whole corpus. A document is the mean of its words' vectors, rare words
weighing more. The network is fitted on at most SAMPLE_ROWS labelled rows; a temperature fitted on a part held back calibrates it.

Defined results: null and empty texts pool to the zero vector and are scored like any other; documents without labels, and labels
without documents, take no part in the fit; with no labelled rows or one class only the score is the smoothed share of label 1;
repeated rows are scored alike; an input column named like a result column is replaced.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import crc_bucket, field, load, map_text, slices, small_batches

BUCKETS, DIM, NONZERO, WINDOW = 1 << 14, 64, 4, 2
BLOCK = 64  # words whose sums travel together
SAMPLE_ROWS = 20_000
HIDDEN = 32
RARE = 1e-4  # a word of this share of the tokens weighs a half
TOKEN = re.compile(r"\w+|[^\w\s]+")
GOOD_AT = 0.7


def index_vectors() -> tuple[np.ndarray, np.ndarray]:
    """Places and signs of the few non-zero components of every bucket's index vector."""
    rng = np.random.default_rng(20240)
    return rng.permuted(np.tile(np.arange(DIM), (BUCKETS, 1)), axis=1)[:, :NONZERO], rng.choice([-1.0, 1.0], (BUCKETS, NONZERO))


class Buckets(dict):
    """Hashed words, remembered up to a bound."""

    def __missing__(self, token: str) -> int:
        if len(self) > 400_000:
            self.clear()
        self[token] = b = zlib.crc32(token.encode()) & (BUCKETS - 1)
        return b

    def of(self, text: str | None) -> np.ndarray:
        tokens = TOKEN.findall(text) if text else []
        return np.fromiter(map(self.__getitem__, tokens), np.int64, len(tokens))


def add_contexts(sums: np.ndarray, ids: np.ndarray, doc: np.ndarray, places: np.ndarray, signs: np.ndarray) -> None:
    """Adds each token's neighbours within WINDOW in its own document to the sums (BUCKETS x (DIM + 1); the last column counts)."""
    flat = np.zeros(BUCKETS * DIM)
    for d in range(1, WINDOW + 1):
        same = doc[d:] == doc[:-d]
        for a, b in ((ids[d:][same], ids[:-d][same]), (ids[:-d][same], ids[d:][same])):
            for j in range(NONZERO):
                flat += np.bincount(a * DIM + places[b, j], weights=signs[b, j], minlength=BUCKETS * DIM)
    sums[:, :DIM] += flat.reshape(BUCKETS, DIM)
    sums[:, DIM] += np.bincount(ids, minlength=BUCKETS)


def context_sums(docs: DataFrame, text_col: str = "text") -> np.ndarray:
    """The sums over all documents. Every task sends a table of fixed size in blocks; they are added in two levels."""

    def run(batches):
        from pyspark import TaskContext

        places, signs = index_vectors()
        buckets, sums = Buckets(), np.zeros((BUCKETS, DIM + 1))
        for batch in batches:
            for part in slices(batch, "_llm_text"):
                ids = [buckets.of(t) for t in part.column("_llm_text").to_pylist()]
                if total := sum(map(len, ids)):
                    add_contexts(sums, np.concatenate(ids), np.repeat(np.arange(len(ids)), [len(x) for x in ids]), places, signs)
                del total
        if sums[:, DIM].any():
            blocks = [zlib.compress(sums[i : i + BLOCK].astype(np.int64).tobytes(), 1) for i in range(0, BUCKETS, BLOCK)]
            group = TaskContext.get().partitionId() % 16
            yield pa.RecordBatch.from_pydict({"block": pa.array(range(len(blocks)), pa.int32()), "part": pa.array([group] * len(blocks), pa.int32()), "sums": pa.array(blocks, pa.binary())})

    def added(pdf: pd.DataFrame) -> pd.DataFrame:
        total = sum(np.frombuffer(zlib.decompress(x), np.int64) for x in pdf["sums"])
        return pd.DataFrame({"block": [pdf["block"].iloc[0]], "sums": [zlib.compress(total.tobytes(), 1)]})

    schema = "block int, sums binary"
    small_batches(docs.sparkSession)
    tables = docs.select(F.col(text_col).cast("string").alias("_llm_text")).mapInArrow(run, "block int, part int, sums binary")
    rows = tables.groupBy("block", "part").applyInPandas(added, schema).groupBy("block").applyInPandas(added, schema).collect()
    out = np.zeros((BUCKETS, DIM + 1))
    for r in rows:
        out[r["block"] * BLOCK : (r["block"] + 1) * BLOCK] = np.frombuffer(zlib.decompress(r["sums"]), np.int64).reshape(-1, DIM + 1)
    return out


def word_vectors(sums: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Unit vectors around the corpus mean, and the words' weights."""
    n = sums[:, DIM]
    mean = sums[:, :DIM].sum(0) / max(1.0, n.sum())
    v = np.where(n[:, None] > 0, sums[:, :DIM] / np.maximum(n, 1)[:, None] - mean, 0)
    v /= np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-9)
    return v.astype(np.float32), RARE / (RARE + n / max(1.0, n.sum()))


def pooled(ids: np.ndarray, vectors: np.ndarray, weights: np.ndarray) -> np.ndarray:
    if not len(ids):
        return np.zeros(DIM, np.float32)
    words, n = np.unique(ids, return_counts=True)
    w = weights[words] * n
    return (w @ vectors[words] / max(w.sum(), 1e-12)).astype(np.float32)


class Network:
    """Two layers (tanh, then a logit) with standardised inputs and a temperature."""

    def __init__(self, prior: float = 0.5):
        self.prior, self.layers, self.temperature = prior, None, 1.0

    def logits(self, x: np.ndarray) -> np.ndarray:
        if self.layers is None:
            return np.full(len(x), np.log(self.prior / (1 - self.prior)))
        mean, scale, w1, b1, w2, b2 = self.layers
        return np.tanh((x - mean) / scale @ w1 + b1) @ w2 + b2

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(np.asarray(x, np.float64)) / self.temperature, -500, 500)))

    def fit(self, x: np.ndarray, y: np.ndarray, rounds: int = 60, batch: int = 256, l2: float = 1e-4, seed: int = 11) -> Network:
        x, y = np.asarray(x, np.float64), np.asarray(y, np.float64)
        self.prior = (y.sum() + 0.5) / (len(y) + 1)
        if len(y) < 10 or len(set(y.tolist())) < 2:
            return self
        rng = np.random.default_rng(seed)
        order = rng.permutation(len(y))
        held, own = order[: len(y) // 5], order[len(y) // 5 :]
        mean, scale = x[own].mean(0), x[own].std(0) + 1e-6
        p = [rng.normal(0, 1 / np.sqrt(x.shape[1]), (x.shape[1], HIDDEN)), np.zeros(HIDDEN), rng.normal(0, 1 / np.sqrt(HIDDEN), HIDDEN), np.zeros(())]
        m, v = [np.zeros_like(q) for q in p], [np.zeros_like(q) for q in p]
        best, best_loss, t = None, np.inf, 0
        z_held = (x[held] - mean) / scale
        for _ in range(rounds):
            for at in np.array_split(rng.permutation(own), max(1, len(own) // batch)):
                t += 1
                z = (x[at] - mean) / scale
                h = np.tanh(z @ p[0] + p[1])
                e = (1 / (1 + np.exp(-np.clip(h @ p[2] + p[3], -500, 500))) - y[at]) / len(at)
                back = e[:, None] * p[2] * (1 - h * h)
                for i, g in enumerate((z.T @ back + l2 * p[0], back.sum(0), h.T @ e + l2 * p[2], e.sum())):
                    m[i], v[i] = 0.9 * m[i] + 0.1 * g, 0.999 * v[i] + 0.001 * g * g
                    p[i] = p[i] - 0.003 * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
            loss = cross_entropy(np.tanh(z_held @ p[0] + p[1]) @ p[2] + p[3], y[held])
            if loss < best_loss:
                best, best_loss = [q.copy() for q in p], loss
        self.layers = (mean, scale, *best)
        logits = self.logits(x[held])
        grid = np.exp(np.linspace(np.log(0.25), np.log(8), 141))
        self.temperature = float(min(grid, key=lambda c: cross_entropy(logits / c, y[held])))
        return self


def cross_entropy(logits: np.ndarray, y: np.ndarray) -> float:
    return float(np.mean(np.logaddexp(0, logits) - y * logits))


def with_vectors(docs: DataFrame, shared, text_col: str, keep: list[str]) -> DataFrame:
    def make():
        vectors, weights = shared.value
        buckets = Buckets()

        def work(texts):
            x = np.array([pooled(buckets.of(t), vectors, weights) for t in texts], np.float32).reshape(len(texts), DIM)
            return [pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, DIM), pa.int32()), pa.array(x.reshape(-1)))]

        return work

    return map_text(docs, make, [field("pooled", T.ArrayType(T.FloatType()))], text_col, keep)


def train(docs: DataFrame, labels: DataFrame, label_col: str = "quality", id_col: str = "doc_id", text_col: str = "text", rows: int = SAMPLE_ROWS):
    """(broadcast word vectors of fixed size, fitted network). ``labels`` holds only rows that may be learnt from."""
    shared = docs.sparkSession.sparkContext.broadcast(word_vectors(context_sums(docs, text_col)))
    chosen = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).select(id_col, F.col(label_col).cast("int").alias("_llm_label"))
    chosen = chosen.orderBy(F.xxhash64(id_col), id_col, "_llm_label").limit(rows)  # the bound of the broadcast
    found = with_vectors(docs.select(id_col, text_col).join(F.broadcast(chosen), id_col), shared, text_col, [id_col, "_llm_label"]).collect()
    found.sort(key=lambda r: (r[0], r["_llm_label"], r["pooled"]))
    x = np.array([r["pooled"] for r in found], np.float64).reshape(len(found), DIM)
    return shared, Network().fit(x, np.array([r["_llm_label"] for r in found]))


def score(docs: DataFrame, shared, network: Network, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Adds score, the calibrated probability of label 1."""

    def make():
        vectors, weights = shared.value
        buckets = Buckets()

        def work(texts):
            x = np.array([pooled(buckets.of(t), vectors, weights) for t in texts], np.float64).reshape(len(texts), DIM)
            return [pa.array(network.probabilities(x), pa.float64())]

        return work

    return map_text(docs, make, [field("score", T.DoubleType())], text_col, keep)


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    learnt = load(spark, sf_dir, "labels").where(crc_bucket("doc_id", 4) != 2)
    shared, network = train(docs, learnt)
    scored = score(docs, shared, network, keep=["doc_id"])
    return scored.select("doc_id", (crc_bucket("doc_id", 4) == 2).alias("held_out"), "score", (F.col("score") >= GOOD_AT).cast("int").alias("predicted"))
