"""Toxicity by cumulative-link ordinal regression over sparse word features.

P(grade <= k) = sigmoid(threshold_k - w.x) with ordered thresholds and one weight vector for all of them; x holds 1 + ln(tf) of the
words that a likelihood-ratio test ties to the grades. The fit runs on a bounded sample of labelled rows; scores cover whole texts.
A quarter of that sample is held back from the fit and sets the cut at which a document counts as toxic: the one with the best mean of the
shares of toxic and of other rows judged rightly. The cut belongs to the model.

Defined results: null and empty texts have no features and get the base rate; documents without a label, or labels without a
document, are left out of the fit; repeated documents are scored row by row; null grades are ignored; an input column named like
a result column is replaced; with no labelled rows, or one grade only, every probability is the smoothed share of the grades. Where the held-back
rows are fewer than LEAST_HELD of either kind, the cut is DEFAULT_CUT; a model without a word calls nothing toxic.
"""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import field, load, map_text
from .decontaminate import words_of

#: Most labelled rows that the fit uses (those with the smallest keyed hashes).
SAMPLE_ROWS = 10_000
MIN_DF = 5
#: Likelihood-ratio statistic that a word needs to become a feature (chi-squared, one degree of freedom: p < 1e-6).
MIN_G2 = 24.0
L2 = 1e-4
#: Every fourth row of the sample is held back; fewer rows of a kind than LEAST_HELD set no cut.
HELD_BACK, LEAST_HELD, DEFAULT_CUT = 4, 5, 0.5
#: Above every probability.
NEVER = 2.0


@dataclass(frozen=True)
class OrdinalModel:
    """Weights by word hash, ordered thresholds, and the P(grade >= 1) from which a document counts as toxic."""

    weights: dict[int, float]
    thresholds: list[float]
    cut: float = DEFAULT_CUT

    def probabilities(self, s: float) -> list[float]:
        """P(grade = 0), P(grade = 1), ... at the linear score s."""
        below = [0.0] + [1 / (1 + math.exp(-max(-500.0, min(500.0, t - s)))) for t in self.thresholds] + [1.0]
        return [b - a for a, b in zip(below, below[1:], strict=False)]

    def packed_score(self, packed: bytes) -> float:
        """The linear score of packed features."""
        n = len(packed) // 12
        pairs = zip(np.frombuffer(packed, np.uint64, n).tolist(), np.frombuffer(packed, np.float32, n, 8 * n).tolist(), strict=True)
        return sum(w * (1 + math.log(c)) for k, c in pairs if (w := self.weights.get(k)) is not None)


def features(docs: DataFrame, text_col: str, keep: list[str]) -> DataFrame:
    """Sorted 64-bit word hashes and their counts, packed."""

    def make():
        def work(texts):
            out = []
            for t in texts:
                c = Counter(words_of(t))
                h = np.array([xxhash.xxh64_intdigest(w) for w in c], np.uint64)
                n = np.fromiter(c.values(), np.float32, len(c))
                out.append(h.tobytes() + n.tobytes())
            return [pa.array(out, pa.binary())]

        return work

    return map_text(docs, make, [field("packed", T.BinaryType())], text_col, keep)


def fit(rows: list[tuple[int, bytes]], l2: float = L2, rounds: int = 600) -> tuple[dict[int, float], list[float]]:
    """Weights by word hash and ordered thresholds, from (grade, packed features); Adam over the whole sample."""
    grades = np.array([g for g, _ in rows], np.int64)
    top = int(grades.max()) if len(rows) else 1
    share = np.bincount(grades, minlength=max(top, 1) + 1) + 0.5
    cumulative = np.cumsum(share)[:-1] / share.sum()
    theta = np.log(cumulative / (1 - cumulative))
    if not len(rows) or len(set(grades.tolist())) < 2:
        return {}, theta.tolist()
    sizes = [len(p) // 12 for _, p in rows]
    hashes = np.concatenate([np.frombuffer(p, np.uint64, n) for (_, p), n in zip(rows, sizes, strict=True)])
    values = 1 + np.log(np.concatenate([np.frombuffer(p, np.float32, n, 8 * n) for (_, p), n in zip(rows, sizes, strict=True)]).astype(np.float64))
    row = np.repeat(np.arange(len(rows)), sizes)
    words, column = np.unique(hashes, return_inverse=True)
    high = grades[row] >= 1  # association with the lowest threshold
    df, df1 = np.bincount(column, minlength=len(words)), np.bincount(column, weights=high, minlength=len(words))
    n, n1 = len(rows), int((grades >= 1).sum())
    g2 = np.zeros(len(words))
    for seen, expected in ((df1, df * n1 / n), (df - df1, df * (n - n1) / n), (n1 - df1, (n - df) * n1 / n), (n - df - n1 + df1, (n - df) * (n - n1) / n)):
        g2 += 2 * np.where(seen > 0, seen * np.log(np.maximum(seen, 1e-12) / np.maximum(expected, 1e-12)), 0)
    chosen = np.flatnonzero((df >= MIN_DF) & (g2 >= MIN_G2))
    place = np.full(len(words), -1)
    place[chosen] = np.arange(len(chosen))
    used = place[column] >= 0
    row, column, values = row[used], place[column[used]], values[used]
    d = len(chosen)
    # thresholds as a first one and positive steps, so that they stay ordered
    steps = np.log(np.expm1(np.maximum(np.diff(theta), 1e-3)))
    x = np.concatenate([np.zeros(d), theta[:1], steps])
    m, v = np.zeros_like(x), np.zeros_like(x)
    sigmoid = lambda z: 1 / (1 + np.exp(-np.clip(z, -500, 500)))
    for t in range(1, rounds + 1):
        th = x[d] + np.concatenate([[0.0], np.cumsum(np.log1p(np.exp(x[d + 1 :])))])
        s = np.bincount(row, weights=values * x[column], minlength=n)
        edge = np.concatenate([[-np.inf], th, [np.inf]])
        up, lo = edge[grades + 1] - s, edge[grades] - s
        fu, fl = np.where(np.isinf(up), 1.0, sigmoid(up)), np.where(np.isinf(lo), 0.0, sigmoid(lo))
        p = np.maximum(fu - fl, 1e-12)
        du, dl = fu * (1 - fu) / p, fl * (1 - fl) / p  # of ln p by the upper and the lower edge
        gw = np.bincount(column, weights=values * (du - dl)[row], minlength=d) / n + l2 * x[:d]
        ge = np.array([-(du[grades == k].sum() - dl[grades == k + 1].sum()) / n for k in range(len(th))])
        tail = np.cumsum(ge[::-1])[::-1]
        g = np.concatenate([gw, tail[:1], tail[1:] * sigmoid(x[d + 1 :])])
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        x -= 0.1 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    th = x[d] + np.concatenate([[0.0], np.cumsum(np.log1p(np.exp(x[d + 1 :])))])
    return dict(zip(words[chosen].tolist(), x[:d].tolist(), strict=True)), th.tolist()


def graded(rows: list[tuple[int, bytes]]) -> list[tuple[int, bytes]]:
    """Severity grades from a 0/1 label: toxic rows above the toxic median of a two-grade fit's score get 2, other toxic rows 1.

    A stand-in for human grades, used only where the label has two values. Grades that follow the score suit shared weights; any
    other split of the toxic rows would pull the lower threshold's probabilities towards the middle.
    """
    plain = OrdinalModel(*fit([(int(g > 0), p) for g, p in rows]))
    scores = [plain.packed_score(p) if g else 0.0 for g, p in rows]
    middle = float(np.median([x for (g, _), x in zip(rows, scores, strict=True) if g] or [0.0]))
    return [(2 if g and x > middle else int(g > 0), p) for (g, p), x in zip(rows, scores, strict=True)]


def best_cut(p_toxic: np.ndarray, toxic: np.ndarray) -> float:
    """The cut with the best mean of both kinds' shares judged rightly; the middle, in log-odds, of the first gap that reaches it."""
    if min(toxic.sum(), (~toxic).sum()) < LEAST_HELD:
        return DEFAULT_CUT
    order = np.argsort(-p_toxic, kind="stable")
    p, hit = np.clip(p_toxic[order], 1e-12, 1 - 1e-12), toxic[order]
    right = np.cumsum(hit) / hit.sum() + 1 - np.cumsum(~hit) / (~hit).sum()
    right[:-1][p[:-1] == p[1:]] = -1  # equal scores stay together
    k = int(np.argmax(right))
    odds = np.log(p / (1 - p))
    return float(1 / (1 + np.exp(-(odds[k] + odds[min(k + 1, len(p) - 1)]) / 2))) if k + 1 < len(p) else float(p[k])


def sample(docs: DataFrame, labels: DataFrame, label_col: str, id_col: str, text_col: str, rows: int) -> list[tuple[int, bytes]]:
    """(label, packed features) of at most ``rows`` labelled documents; the broadcast side has that bound."""
    chosen = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).select(F.col(id_col), F.col(label_col).cast("int").alias("_llm_label"))
    chosen = chosen.orderBy(F.xxhash64(id_col), id_col, "_llm_label").limit(rows)
    joined = docs.select(id_col, text_col).join(F.broadcast(chosen), id_col)
    found = features(joined, text_col, [id_col, "_llm_label"]).collect()
    found.sort(key=lambda r: (r[0], r["_llm_label"], bytes(r["packed"])))
    return [(r["_llm_label"], bytes(r["packed"])) for r in found[:rows]]


def score(docs: DataFrame, model: OrdinalModel, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Adds grade_probabilities (array), p_toxic, expected_severity, severity (the likeliest grade) and toxic (p_toxic reaches the model's cut)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # at most one weight for each screened word of the sample

    def make():
        held = shared.value
        remembered: dict[bytes, float | None] = {}

        def work(texts):
            columns = [[], [], [], [], []]
            if len(remembered) > 500_000:
                remembered.clear()
            for t in texts:
                counts = Counter(words_of(t))
                s = 0.0
                for w, n in counts.items():
                    if w not in remembered:
                        remembered[w] = held.weights.get(xxhash.xxh64_intdigest(w))
                    if remembered[w] is not None:
                        s += remembered[w] * (1 + math.log(n))
                p = held.probabilities(s)
                for column, x in zip(columns, (p, 1 - p[0], sum(k * x for k, x in enumerate(p)), max(range(len(p)), key=p.__getitem__), 1 - p[0] >= held.cut), strict=True):
                    column.append(x)
            return columns

        return work

    fields = [field("grade_probabilities", T.ArrayType(T.DoubleType())), field("p_toxic", T.DoubleType()), field("expected_severity", T.DoubleType()), field("severity", T.IntegerType()), field("toxic", T.BooleanType())]
    return map_text(docs, make, fields, text_col, keep)


def train(docs: DataFrame, labels: DataFrame, label_col: str = "toxic", id_col: str = "doc_id", text_col: str = "text", rows: int = SAMPLE_ROWS) -> OrdinalModel:
    """Fits on three quarters of a bounded sample; the last quarter sets the cut."""
    found = sample(docs, labels, label_col, id_col, text_col, rows)
    own, held = [r for i, r in enumerate(found) if i % HELD_BACK], found[::HELD_BACK]
    plain = OrdinalModel(*fit(graded(own) if max([g for g, _ in own], default=0) <= 1 else own))
    p_toxic = np.array([1 - plain.probabilities(plain.packed_score(p))[0] for _, p in held])
    return OrdinalModel(plain.weights, plain.thresholds, best_cut(p_toxic, np.array([g > 0 for g, _ in held], bool)) if plain.weights else NEVER)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return score(docs, train(docs, load(spark, sf_dir, "labels")), keep=["doc_id"])
