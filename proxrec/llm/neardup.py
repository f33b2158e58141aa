"""Near-duplicate documents: fast similarity sketches of word shingles, banding, verification on the full sets, components.

A text's set holds the 64-bit hashes of its distinct 5-word shingles (words: runs of characters other than ASCII white space, A-Z
lower-cased; a shorter text is one shingle). A sketch has BINS coordinates; in round i < BINS every element falls into a
hashed bin with value i + fraction, in round BINS + j bin j takes every element, so that all coordinates fill. Texts
with equal sets form one class by their set's digest; only one sketch a class goes on.

Candidates come from equal bands and all pairs of a bucket are never written out: first each bucket's smallest class meets the others, on the
full sets, and components are joined; the leader has then met everyone and goes, as does every bucket that lies within one component. The rest of
each bucket is compared inside tasks, block by block, and only links that join components leave a task. So no link between
components is lost, whatever a bucket's size. Joins on band keys, leaders, labels and set digests split hot keys (common.spread_join), so a
group of copies that holds a third of all rows is dealt to many tasks; the bytes that blocks move grow with the square of an open bucket's size.

Defined results: a null or empty text has an empty set, is linked with nothing and is kept; a class id is the smallest doc_id that
is not null; rows that repeat a doc_id with an equal set share the class and its decision; a null doc_id is kept only if its
component has no other id; extra columns pass through ``deduplicate`` and those named like a result column are replaced.
Two different sets count as equal if their 64-bit digests are (chance below 1e-7 for a million sets).
"""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, field, load, lower_ascii, map_text, spread_join

SHINGLE = 5
BINS = 128
ROWS = 4  # coordinates a band: at a similarity of 0.85 all 32 bands miss with a chance of 6e-11, at 0.8 of 5e-8
#: Ids sent to every executor at most; beyond, the texts are found by a shuffled join.
BROADCAST_IDS = 500_000
#: Shingles of a bucket's members that meet in one task as a block.
BLOCK_SHINGLES = 400_000
M1, M2, GOLD = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)
_SPACE = {c: " " for c in range(9, 14)}
#: str.split() also splits at these; they belong to words here, so they are replaced by private stand-ins first.
_ODD = [c for c in range(0x3001) if chr(c).isspace() and c not in (*range(9, 14), 32)]
_ODD_TABLE = {c: 0xF0000 + c for c in _ODD}
_ODD_FIND = "[" + "".join(map(chr, _ODD)) + "]"


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (splitmix)."""
    x = (x ^ (x >> np.uint64(30))) * M1
    x = (x ^ (x >> np.uint64(27))) * M2
    return x ^ (x >> np.uint64(31))


def words_of(text: str) -> list[str]:
    low = lower_ascii(text)
    return (low.translate(_ODD_TABLE) if re.search(_ODD_FIND, low) else low).split()


class ShingleHasher:
    """Sorted distinct shingle hashes of a text; remembers word hashes up to a bound."""

    def __init__(self, size: int = SHINGLE, remembered: int = 200_000):
        self.size, self.remembered, self.known = size, remembered, {}

    def __call__(self, text: str | None) -> np.ndarray:
        words = words_of(text) if text else []
        if not words:
            return np.zeros(0, np.uint64)
        if len(self.known) > self.remembered:
            self.known.clear()
        known = self.known
        for w in set(words).difference(known):
            known[w] = xxhash.xxh64_intdigest(w)
        h = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
        k = min(self.size, len(words))
        n = len(words) - k + 1
        out = np.full(n, k, np.uint64)
        for i in range(k):
            out = mix(out * GOLD + h[i : i + n])
        return np.unique(out)


def sketch(sets: list[np.ndarray], bins: int = BINS) -> np.ndarray:
    """Fast similarity sketches of many non-empty sets at once: len(sets) x bins coordinates (the element hashes that won)."""
    out = np.full((len(sets), bins), np.uint64(0xFFFFFFFFFFFFFFFF))
    filled = np.zeros((len(sets), bins), bool)
    live = np.arange(len(sets))
    for i in range(2 * bins):
        own = np.repeat(live, [len(sets[j]) for j in live])
        x = np.concatenate([sets[j] for j in live])
        h = mix(x ^ mix(np.full(1, i + 1, np.uint64) * GOLD))
        value = h >> np.uint64(7)  # the fraction, independent of the bin's low bits
        b = (h & np.uint64(bins - 1)).astype(np.int64) if i < bins else np.full(len(x), i - bins)
        place = own * bins + b
        open_ = ~filled.reshape(-1)[place]
        place, value = place[open_], value[open_]
        best = np.full(out.size, np.uint64(0xFFFFFFFFFFFFFFFF)) if len(place) * 4 > out.size else None
        if best is not None:
            np.minimum.at(best, place, value)
            hit = np.flatnonzero(best != np.uint64(0xFFFFFFFFFFFFFFFF))
            low = best[hit]
        else:
            order = np.lexsort((value, place))
            place, value = place[order], value[order]
            first = np.concatenate([[True], place[1:] != place[:-1]]) if len(place) else np.zeros(0, bool)
            hit, low = place[first], value[first]
        out.reshape(-1)[hit] = mix(low ^ mix(np.full(1, i + 1, np.uint64) * M1))  # the round is part of the coordinate
        filled.reshape(-1)[hit] = True
        live = live[~filled[live].all(axis=1)]
        if not len(live):
            break
    return out


def band_keys(sketches: np.ndarray, rows: int = ROWS) -> np.ndarray:
    n, bins = sketches.shape
    keys = np.broadcast_to(np.arange(bins // rows, dtype=np.uint64) * M2, (n, bins // rows)).copy()
    for i in range(rows):
        keys = mix(keys * GOLD + sketches[:, i::rows])
    return keys


def sketched(docs: DataFrame, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Adds n_shingles, node (digest of the set; null if empty) and bands (array of keys; null if empty)."""

    def make():
        hasher = ShingleHasher()

        def work(texts):
            sets = [hasher(t) for t in texts]
            full = [i for i, s in enumerate(sets) if len(s)]
            keys: list = [None] * len(sets)
            node: list = [None] * len(sets)
            for a in range(0, len(full), 256):
                part = full[a : a + 256]
                for i, k in zip(part, band_keys(sketch([sets[i] for i in part])).view(np.int64), strict=True):
                    keys[i] = k
                    node[i] = xxhash.xxh3_64_intdigest(sets[i].tobytes()) - (1 << 63)
            return [pa.array([len(s) for s in sets], pa.int64()), pa.array(node, pa.int64()), pa.array(keys, pa.list_(pa.int64()))]

        return work

    return map_text(docs, make, [field("n_shingles", T.LongType()), field("node", T.LongType()), field("bands", T.ArrayType(T.LongType()))], text_col, keep)


def counted(rows: DataFrame, key: str) -> DataFrame:
    return rows.groupBy(key).agg(F.count("*").alias("n"))


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, label): the smallest node reachable, for every node of a link. Least label of the neighbours, then pointer jumping, a job a round."""
    both = cut(links.select(F.col(a).alias("src"), F.col(b).alias("dst")).unionAll(links.select(F.col(b), F.col(a))).distinct())
    labels = both.groupBy(F.col("src").alias("node")).agg(F.min("dst").alias("m")).select("node", F.least("node", "m").alias("label"))
    degree = cut(counted(both, "dst"))
    while True:
        near = spread_join(both, labels.select(F.col("node").alias("dst"), "label"), "dst", degree).groupBy(F.col("src").alias("node")).agg(F.min("label").alias("m"))
        better = cut(labels.join(near, "node").select("node", F.col("label").alias("old"), F.least("label", "m").alias("label")))
        point = better.select(F.col("node").alias("label"), F.col("label").alias("further"))
        fresh = cut(spread_join(better, point, "label", counted(better, "label")).select("node", "old", F.least("label", "further").alias("label")))
        labels = fresh.select("node", "label")
        if fresh.where("label <> old").isEmpty():
            return labels


def full_sets(docs: DataFrame, ids: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(node, set) for the classes in ids(node, id): the packed sorted set of the row with that id. Texts are only shuffled beyond BROADCAST_IDS."""
    wanted = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    texts = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text")).join(wanted, F.col("_id") == F.col("id"))

    def make():
        hasher = ShingleHasher()

        def work(texts):
            sets = [hasher(t) for t in texts]
            return [pa.array([s.tobytes() for s in sets], pa.binary()), pa.array([xxhash.xxh3_64_intdigest(s.tobytes()) - (1 << 63) for s in sets], pa.int64())]

        return work

    found = map_text(texts, make, [field("set", T.BinaryType()), field("own", T.LongType())], "_text", ["node"])
    return cut(found.where("own = node").select("node", "set").groupBy("node").agg(F.first("set").alias("set")))


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets reach the similarity; a may be the leader of many."""
    one = pairs.join(sets.select(F.col("node").alias("b"), F.col("set").alias("set_b")), "b")
    two = spread_join(one, sets.select(F.col("node").alias("a"), F.col("set").alias("set_a")), "a", counted(pairs, "a")).select("a", "b", "set_a", "set_b")

    def run(batches):
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("set_a"), batch.column("set_b"), strict=True):
                p, q = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                both = len(np.intersect1d(p, q, assume_unique=True))
                keep.append(100 * both >= percent * (len(p) + len(q) - both))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return two.mapInArrow(run, "a long, b long")


def block_links(rows: list[tuple[int, int, bytes]], percent: int) -> list[tuple[int, int]]:
    """Links that join different components of (node, component, packed set); at most one fewer than there are components."""
    sets = [np.frombuffer(r[2], np.uint64) for r in rows]
    sizes = np.array([len(s) for s in sets])
    if len(rows) <= 6:
        both = np.array([[len(np.intersect1d(x, y, assume_unique=True)) if j > i else 0 for j, y in enumerate(sets)] for i, x in enumerate(sets)], np.float64)
    else:
        row = np.repeat(np.arange(len(rows)), sizes)
        _, column, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        shared = count > 1
        place = np.cumsum(shared) - 1
        used = shared[column]
        row, column = row[used], place[column[used]]
        order = np.argsort(column, kind="stable")
        row, column = row[order], column[order]
        both = np.zeros((len(rows), len(rows)))
        for c in range(0, int(shared.sum()), 2048):
            a, b = np.searchsorted(column, [c, c + 2048])
            dense = np.zeros((len(rows), 2048), np.float32)
            dense[row[a:b], column[a:b] - c] = 1
            both += dense @ dense.T
    component = np.unique([r[1] for r in rows], return_inverse=True)[1]
    linked = (100 * both >= percent * (sizes[:, None] + sizes[None, :] - both)) & (component[:, None] != component[None, :]) & np.triu(np.ones_like(both, bool), 1)
    top = list(range(len(rows)))

    def root(x: int) -> int:
        while top[x] != x:
            top[x] = top[top[x]]
            x = top[x]
        return x

    out = []
    for i, j in zip(*np.nonzero(linked), strict=True):
        x, y = root(int(component[i])), root(int(component[j]))
        if x != y:
            top[y] = x
            out.append((rows[i][0], rows[j][0]))
    return out


def compared(members: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) between different components of the same bucket. members: key, node, c, blocks.

    A bucket's members are dealt to its blocks of some BLOCK_SHINGLES shingles; each task compares two blocks (small buckets share tasks), so
    every pair of a bucket meets in one task of bounded size and none is written out.
    """
    dealt = members.withColumn("own", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("key", "node", "c", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), (F.col("blocks") > 1).alias("large"))
    with_sets = dealt.join(sets, "node")
    groups = max(64, 2 * int(members.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    home = F.when(F.col("large"), F.xxhash64("key", "i", "j")).otherwise(F.pmod(F.xxhash64("key"), F.lit(groups)))

    def run(pdf):
        found = []
        for _, part in pdf.groupby(["key", "i", "j"], sort=False):
            found += block_links(list(zip(part["node"], part["c"], part["set"], strict=True)), percent)
        return pd.DataFrame(found, columns=["a", "b"], dtype="int64")

    return with_sets.groupBy(home.alias("home")).applyInPandas(run, "a long, b long")


def link_classes(docs: DataFrame, classes: DataFrame, percent: int, id_col: str, text_col: str) -> DataFrame:
    """(node, label) for the classes in links. classes: node, id, n_shingles, bands."""
    bands = classes.select("node", F.col("n_shingles").alias("n"), F.explode("bands").alias("key"))
    buckets = bands.groupBy("key").agg(F.min(F.struct("node", "n")).alias("leader"), F.count("*").alias("size")).where("size > 1")
    buckets = cut(buckets.select("key", F.col("leader.node").alias("leader"), F.col("leader.n").alias("n_leader"), "size"))
    members = cut(spread_join(bands, buckets, "key", buckets.select("key", F.col("size").alias("n"))))
    if members.isEmpty():
        return docs.sparkSession.createDataFrame([], "node long, label long")
    sets = full_sets(docs, cut(members.select("node").distinct().join(classes.select("node", "id"), "node")), id_col, text_col)
    # the smaller set of a link has at least percent % of the larger one's size
    pairs = members.where(f"node <> leader AND 100 * least(n, n_leader) >= {percent} * greatest(n, n_leader)").select(F.col("leader").alias("a"), F.col("node").alias("b")).distinct()
    labels = components(cut(verified(cut(pairs), sets, percent)))
    left = members.where("node <> leader AND size > 2").join(labels, "node", "left").select("key", "node", "n", F.coalesce("label", "node").alias("c"))
    left = cut(left)
    open_ = left.groupBy("key").agg(F.min("c").alias("x"), F.max("c").alias("y"), F.ceil(F.sum("n") / BLOCK_SHINGLES).cast("int").alias("blocks"), F.count("*").alias("n")).where("x <> y")
    open_ = cut(open_.select("key", "blocks", "n"))
    more = cut(compared(spread_join(left.drop("n"), open_.drop("n"), "key", open_.select("key", "n")), sets, percent))
    if more.isEmpty():
        return labels
    name = lambda c: labels.select(F.col("node").alias(c), F.col("label").alias(f"{c}_label"))
    joined = spread_join(spread_join(more, name("a"), "a", counted(more, "a"), "left"), name("b"), "b", counted(more, "b"), "left")
    joined = joined.select(F.coalesce("a_label", "a").alias("a"), F.coalesce("b_label", "b").alias("b")).where("a <> b")
    final = components(joined).select(F.col("node").alias("label"), F.col("label").alias("now"))
    known = cut(labels.unionByName(more.select(F.explode(F.array("a", "b")).alias("node")).distinct().join(labels, "node", "left_anti").withColumn("label", F.col("node"))))
    return spread_join(known, final, "label", counted(known, "label"), "left").select("node", F.coalesce("now", "label").alias("label"))


def decisions(docs: DataFrame, percent: int = 85, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_shingles, component_id (smallest id linked, directly or not) and kept (one document of each component), a row a document."""
    base = cut(sketched(docs, text_col, [id_col]))
    filled = base.where("node IS NOT NULL")
    classes = filled.groupBy("node").agg(F.min(id_col).alias("id"), F.first("n_shingles").alias("n_shingles"), F.first("bands").alias("bands"), F.count("*").alias("copies"))
    classes = cut(classes)
    labels = link_classes(docs, classes, percent, id_col, text_col)
    named = cut(classes.select("node", "id").join(labels, "node", "left").select("node", "id", F.coalesce("label", "node").alias("label")))
    least = named.groupBy("label").agg(F.min("id").alias("component_id"))
    by_node = spread_join(named, least, "label", counted(named, "label")).select("node", "component_id")
    out = spread_join(filled.select(id_col, "n_shingles", "node"), by_node, "node", classes.select("node", F.col("copies").alias("n"))).select(id_col, "n_shingles", "component_id")
    out = out.unionByName(base.where("node IS NULL").select(id_col, "n_shingles", F.col(id_col).alias("component_id")))
    return out.withColumn("kept", F.col(id_col).eqNullSafe(F.col("component_id")))


def deduplicate(docs: DataFrame, percent: int = 85, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents with n_shingles, component_id and kept added. Rows that share an id share its least component and its best decision."""
    new = ("n_shingles", "component_id", "kept")
    by_id = decisions(docs, percent, id_col, text_col).groupBy(F.col(id_col).alias("_id")).agg(F.min(new[0]).alias(new[0]), F.min(new[1]).alias(new[1]), F.max(new[2]).alias(new[2]))
    passed = [F.col(f"`{c}`") for c in docs.columns if c.lower() not in new]
    return docs.select(*passed).join(by_id, F.col(id_col).eqNullSafe(F.col("_id"))).drop("_id")


def survivors(docs: DataFrame, percent: int = 85, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents that are kept, with their own columns. Texts are not shuffled while the ids that go fit a checked broadcast."""
    gone = decisions(docs, percent, id_col, text_col).groupBy(F.col(id_col).alias("_id")).agg(F.max("kept").alias("kept")).where("NOT kept").select("_id")
    gone = cut(gone)
    gone = F.broadcast(gone) if gone.count() <= BROADCAST_IDS else gone
    return docs.join(gone, F.col(id_col).eqNullSafe(F.col("_id")), "left_anti")


def op9_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decisions(load(spark, sf_dir, "documents"))


OP9_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
sh AS (SELECT DISTINCT doc_id, array_to_string(ws[i:i + least(len(ws), 5) - 1], ' ') AS s
       FROM (SELECT doc_id, ws, unnest(generate_series(1, greatest(1, len(ws) - 4))) AS i FROM w WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS k FROM sh x JOIN sh y ON x.s = y.s AND x.doc_id < y.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * k >= 85 * (na.n + nb.n - k)),
e AS (SELECT a, b FROM l UNION SELECT b, a FROM l),
r(doc_id, reached) AS (SELECT a, a FROM e UNION SELECT r.doc_id, e.b FROM r JOIN e ON e.a = r.reached),
c AS (SELECT doc_id, min(reached) AS m FROM r GROUP BY doc_id)
SELECT w.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(c.m, w.doc_id) AS component_id, coalesce(c.m, w.doc_id) = w.doc_id AS kept
FROM w LEFT JOIN n USING (doc_id) LEFT JOIN c USING (doc_id)
"""
