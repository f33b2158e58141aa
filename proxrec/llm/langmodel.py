"""Scores of texts under an n-gram model kept in Elias-Fano tries, trained on part of the same corpus.

Tokens are runs of characters other than ASCII white space with A-Z lower-cased, then one end. With counts c over the training rows the model
is a trigram whose lower orders enter by their counts: P(w | t u) = (c(t u w) + PAIR * c(u w) + SINGLE * P1(w)) / (c(t u) + PAIR * c(u) + SINGLE),
P1(w) = (c(w) + 0.5) / (N + 0.5 * (V + 1)). Summed over w the numerators give the denominator, and all words that training lacks share one
unknown class, so both are distributions. A numerator needs the counts of what stands before w, a denominator those of u and of what stands before it: all
that concerns a word - its counts, its trie of preceding words and of the words before those, its terms - lives in one shard, and texts are
scored by sending each token to its word's shard once. Frequent words (more than SPREAD of them) are dealt to all shards by the preceding
word, with their counts known from the first pass; how many there are is bounded by the tokens over SPREAD. No table of the vocabulary is broadcast; shards have a
bounded number of tokens, and their tries lie in anonymous memory mappings.

Words are known by 62-bit hashes, preceding words by 32 bits and those before them by 24 bits of theirs (within one word's list).

Defined results: null and empty texts have the end token only; repeated rows are scored (and, in training, counted) one by one; null ids hash as the
empty string and come back null; with no training rows every P1 is 1 (V = 0: only the unknown class is left) and scores are 0; an empty
table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_bucket, give_back, load, slices
from .eliasfano import NgramTrie
from .neardup import mix, words_of

#: Weights of pairs and of single words against one triple; chosen by the probability of held-out texts.
PAIR, SINGLE = 0.01, 10.0
SHARDS, SHARD_TOKENS = 64, 1_200_000
#: A word with more tokens than this, in training, is dealt to all shards.
SPREAD = SHARD_TOKENS // 4
#: Documents, and characters of text, that are dealt as one batch.
BATCH_ROWS, BATCH_CHARS = 16_000, 6_000_000
HELD = 1 << 15  # bit of a document's number within its batch
MASK = np.uint64((1 << 62) - 1)
END, BEGIN = np.uint64(1), np.uint64(2)


class Words:
    """62-bit hashes of tokens, remembered up to a bound; 0 to 2 are left free for the marks."""

    def __init__(self, remembered: int = 200_000):
        self.known: dict[str, int] = {}
        self.remembered = remembered

    def __call__(self, text: str | None) -> np.ndarray:
        words = words_of(text) if text else []
        known = self.known
        if len(known) > self.remembered:
            known.clear()
        for w in set(words).difference(known):
            known[w] = max(3, xxhash.xxh64_intdigest(w) & int(MASK))
        out = np.empty(len(words) + 1, np.uint64)
        out[:-1] = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
        out[-1] = END
        return out


def corpus_counts(docs: DataFrame, groups: int) -> dict:
    """N, V, all tokens and the frequent words with their counts. docs: _id, _held, _llm_text."""

    def run(batches):
        words, total = Words(), 0
        kept: list[tuple[np.ndarray, np.ndarray]] = []

        def settle():
            v = np.concatenate([x for x, _ in kept])
            n = np.concatenate([x for _, x in kept])
            u, inverse = np.unique(v, return_inverse=True)
            return u, np.bincount(inverse, weights=n).astype(np.uint32)

        for batch in batches:
            for part in slices(batch, "_llm_text"):
                ids = []
                for t, held in zip(part.column("_llm_text").to_pylist(), part.column("_held").to_pylist(), strict=True):
                    x = words(t)
                    total += len(x)
                    if not held:
                        ids.append(x)
                if ids:
                    u, n = np.unique(np.concatenate(ids), return_counts=True)
                    kept.append((u, n.astype(np.uint32)))
                    if len(kept) == 12:
                        kept[:] = [settle()]
        u, n = settle() if kept else (np.zeros(0, np.uint64), np.zeros(0, np.uint32))
        g = (mix(u) % np.uint64(groups)).astype(np.int64)
        order = np.argsort(g, kind="stable")
        cuts = np.searchsorted(g[order], np.arange(groups + 1))
        rows = [(i, u[order[a:b]].tobytes(), n[order[a:b]].tobytes(), total if i == 0 else 0) for i, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)) if b > a or (i == 0 and total)]
        if rows:
            k, w, c, t = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(k, pa.int32()), pa.array(w, pa.binary()), pa.array(c, pa.binary()), pa.array(t, pa.int64())], names=["g", "w", "c", "total"])

    def summed(pdf: pd.DataFrame) -> pd.DataFrame:
        v = np.frombuffer(b"".join(pdf["w"]), np.uint64)
        n = np.frombuffer(b"".join(pdf["c"]), np.uint32)
        u, inverse = np.unique(v, return_inverse=True)
        c = np.bincount(inverse, weights=n, minlength=len(u)).astype(np.int64)
        top = np.flatnonzero(c > SPREAD)
        return pd.DataFrame({"n": [int(c.sum())], "v": [len(u)], "total": [int(pdf["total"].sum())], "top": [u[top].astype(np.int64).tolist()], "count": [c[top].tolist()]})

    rows = docs.mapInArrow(run, "g int, w binary, c binary, total long").groupBy("g").applyInPandas(summed, "n long, v long, total long, top array<long>, count array<long>")
    # at most one frequent word for every SPREAD tokens
    whole = rows.agg(F.sum("n").alias("n"), F.sum("v").alias("v"), F.sum("total").alias("total"), F.flatten(F.collect_list(F.arrays_zip("count", "top"))).alias("top")).first()
    return {"n": whole["n"] or 0, "v": whole["v"] or 0, "total": whole["total"] or 0, "frequent": {r["top"]: r["count"] for r in whole["top"] or []}}


def gathered_parts(batches):
    """Record batches of at most BATCH_ROWS rows and about BATCH_CHARS of text, so that words repeat within them."""
    held, rows, size = [], 0, 0
    for whole in batches:
        for wide in slices(whole, "_llm_text"):
            for at in range(0, wide.num_rows, BATCH_ROWS):
                part = wide.slice(at, BATCH_ROWS)
                if held and (rows + part.num_rows > BATCH_ROWS or size + part.nbytes > BATCH_CHARS):
                    yield pa.Table.from_batches(held).combine_chunks()
                    held, rows, size = [], 0, 0
                held.append(part)
                rows, size = rows + part.num_rows, size + part.nbytes
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def dealt(docs: DataFrame, shards: int, frequent: list[int]) -> DataFrame:
    """For each batch of documents and each shard the tokens that belong there: shard, batch, payload, meta (ids, once a batch)."""
    often = np.array(sorted(frequent), np.uint64)

    def run(batches):
        from pyspark import TaskContext

        words, number = Words(), TaskContext.get().partitionId() << 32
        for part in gathered_parts(batches):
            if not part.num_rows:
                continue
            held = np.array(part.column("_held").to_pylist(), bool)
            ids = [words(t) for t in part.column("_llm_text").to_pylist()]
            w = np.concatenate(ids)
            sizes = np.array([len(x) for x in ids])
            first_of = np.cumsum(sizes) - sizes
            del ids
            before = np.empty_like(w)
            before[1:] = w[:-1]
            before[first_of] = BEGIN
            low = (mix(before) & np.uint64(0xFFFFFFFF)).astype(np.uint32)
            third = np.empty(len(w), np.uint32)
            third[1:] = low[:-1] & np.uint32(0xFFFFFF)
            third[first_of] = 0
            doc = np.repeat(np.arange(part.num_rows) | np.where(held, HELD, 0), sizes).astype(np.uint16)
            route = mix(w)
            if len(often):
                spread = np.isin(w, often)
                route[spread] = mix(route[spread] + low[spread])
            shard = (route % np.uint64(shards)).astype(np.int64)
            del before, route
            order = np.lexsort((w, shard))
            w, low, third, doc, shard = w[order], low[order], third[order], doc[order], shard[order]
            cuts = np.searchsorted(shard, np.arange(shards + 1))
            rows = []
            home = number % shards
            for s in range(shards):
                a, b = cuts[s], cuts[s + 1]
                if a == b and s != home:
                    continue
                own = w[a:b]
                first = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]])) if b > a else np.zeros(0, np.int64)
                count = np.diff(np.append(first, b - a)).astype(np.uint32)
                far = third[a:b].astype("<u4").view(np.uint8).reshape(-1, 4)[:, :3]  # 24 bits travel
                payload = np.array([part.num_rows, len(first), b - a], np.int64).tobytes() + own[first].tobytes() + count.tobytes() + low[a:b].tobytes() + doc[a:b].tobytes() + far.tobytes()
                meta = None
                if s == home:
                    meta = pa.RecordBatch.from_arrays([part.column("_id").combine_chunks(), pa.array(held), pa.array(sizes, pa.int64())], names=["id", "held", "n"]).serialize().to_pybytes()
                rows.append((s, number, payload, meta))
            for at in range(0, len(rows), 16):
                k, n, p, m = zip(*rows[at : at + 16], strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(k, pa.int32()), pa.array(n, pa.int64()), pa.array(p, pa.binary()), pa.array(m, pa.binary())], names=["shard", "batch", "payload", "meta"])
            number += 1
        del words
        give_back()

    return docs.mapInArrow(run, "shard int, batch long, payload binary, meta binary")


def shard_scores(payloads: list[bytes], n: int, v: int, frequent: dict[int, int], pair: float = PAIR, single: float = SINGLE) -> list[bytes]:
    """For each batch of a shard the sums of its documents: numbers (uint16), known tokens (uint32), base and score (double).

    Builds the shard's trie (words, the words before them, the words before those), maps it and looks every distinct triple up.
    """
    heads, words, counts, lows, docs, thirds = [], [], [], [], [], []
    for p in payloads:
        size, k, t = (int(x) for x in np.frombuffer(p, np.int64, 3))
        heads.append((size, t))
        words.append(np.frombuffer(p, np.uint64, k, 24))
        counts.append(np.frombuffer(p, np.uint32, k, 24 + 8 * k))
        lows.append(np.frombuffer(p, np.uint32, t, 24 + 12 * k))
        docs.append(np.frombuffer(p, np.uint16, t, 24 + 12 * k + 4 * t))
        far = np.zeros((t, 4), np.uint8)
        far[:, :3] = np.frombuffer(p, np.uint8, 3 * t, 24 + 12 * k + 6 * t).reshape(t, 3)
        thirds.append(far.view("<u4")[:, 0])
    distinct, inverse = np.unique(np.concatenate(words), return_inverse=True)
    word = np.repeat(inverse.astype(np.int32), np.concatenate(counts))
    del words, counts, inverse, payloads
    doc = np.concatenate(docs)
    learnt = (doc & HELD) == 0
    c = np.bincount(word[learnt], minlength=len(distinct)).astype(np.float64)
    if frequent:
        often = np.array(sorted(frequent), np.uint64)
        at = np.searchsorted(distinct, often)
        ok = (at < len(distinct)) & (distinct[np.minimum(at, max(len(distinct) - 1, 0))] == often) if len(distinct) else np.zeros(len(often), bool)
        c[at[ok]] = [frequent[int(x)] for x in often[ok]]
    p1 = (c + 0.5) / (n + 0.5 * (v + 1))
    pairs, pair_of = np.unique((word.astype(np.uint64) << np.uint64(32)) | np.concatenate(lows), return_inverse=True)
    pair_of = pair_of.astype(np.int32)
    triples, triple_of = np.unique((pair_of.astype(np.uint64) << np.uint64(24)) | np.concatenate(thirds), return_inverse=True)
    triple_of = triple_of.astype(np.int32)
    del lows, thirds, docs
    c2, c3 = np.bincount(pair_of[learnt], minlength=len(pairs)), np.bincount(triple_of[learnt], minlength=len(triples))
    parent, parent3 = (pairs >> np.uint64(32)).astype(np.int64), (triples >> np.uint64(24)).astype(np.int64)
    # the trie of what training has seen
    seen1, seen2, seen3 = np.flatnonzero(c > 0), np.flatnonzero(c2 > 0), np.flatnonzero(c3 > 0)
    rank1, rank2 = np.full(len(distinct), -1, np.int64), np.full(len(pairs), -1, np.int64)
    rank1[seen1], rank2[seen2] = np.arange(len(seen1)), np.arange(len(seen2))
    keys2 = (rank1[parent[seen2]].astype(np.uint64) << np.uint64(32)) | (pairs[seen2] & np.uint64(0xFFFFFFFF))
    keys3 = (rank2[parent3[seen3]].astype(np.uint64) << np.uint64(32)) | (triples[seen3] & np.uint64(0xFFFFFF))
    over2 = pair * c2[seen2] + single * p1[parent[seen2]]
    under1, under2 = pair * c[seen1] + single, c2[seen2] + pair * c[parent[seen2]] + single
    over3 = c3[seen3] + pair * c2[parent3[seen3]] + single * p1[parent[parent3[seen3]]]
    trie = NgramTrie.build([distinct[seen1], keys2, keys3], [[-np.log10(under1)], [np.log10(over2), -np.log10(under2)], [np.log10(over3)]]).mapped()
    del keys2, keys3, over2, over3, under1, under2, seen1, seen2, seen3, rank1, rank2
    at1, known = trie.roots(distinct)
    # what stands below: the denominator where the token is the context of the next one; an end stands for the context of a text's first token
    single_under = np.full(len(distinct), -np.log10(single))
    single_under[known] = trie.value(0, at1[known])
    under = single_under[parent]
    over2 = np.log10(single * p1)[parent]
    ask = np.flatnonzero(known[parent])
    at2, hit = trie.children(1, at1[parent[ask]], pairs[ask] & np.uint64(0xFFFFFFFF))
    over2[ask[hit]], under[ask[hit]] = trie.value(1, at2[hit], 0), trie.value(1, at2[hit], 1)
    node2 = np.full(len(pairs), -1, np.int64)
    node2[ask[hit]] = at2[hit]
    ends = distinct[parent] == END
    under[ends] = -np.log10((1 + pair) * c[parent[ends]] + single)
    over = over2[parent3]
    ask = np.flatnonzero(node2[parent3] >= 0)
    at3, hit = trie.children(2, node2[parent3[ask]], triples[ask] & np.uint64(0xFFFFFF))
    over[ask[hit]] = trie.value(2, at3[hit])
    del trie
    total = (over + under[parent3])[triple_of]
    base, is_known = np.log10(p1)[word], (c > 0)[word]
    out, a = [], 0
    for size, t in heads:
        d = (doc[a : a + t] & (HELD - 1)).astype(np.int64)
        present = np.flatnonzero(np.bincount(d, minlength=size))
        sums = [np.bincount(d, weights=x[a : a + t], minlength=size)[present] for x in (is_known, base, total)]
        out.append(np.array([len(present)], np.int64).tobytes() + sums[1].tobytes() + sums[2].tobytes() + sums[0].astype(np.uint32).tobytes() + present.astype(np.uint16).tobytes())
        a += t
    return out


def score(docs: DataFrame, held, id_col: str = "doc_id", text_col: str = "text", pair: float = PAIR, single: float = SINGLE) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for each document; ``held`` is true where a row must not be learnt from."""
    source = docs.select(F.col(id_col).alias("_id"), F.coalesce(held, F.lit(False)).alias("_held"), F.col(text_col).cast("string").alias("_llm_text"))
    stats = corpus_counts(source, max(64, source.rdd.getNumPartitions()))
    n, v, frequent = stats["n"], stats["v"], stats["frequent"]
    shards = SHARDS * max(1, -(-stats["total"] // (SHARDS * SHARD_TOKENS)))

    def scored(pdf: pd.DataFrame) -> pd.DataFrame:
        out = pd.DataFrame({"batch": pdf["batch"], "sums": shard_scores(list(pdf["payload"]), n, v, frequent, pair, single), "meta": pdf["meta"]})
        give_back()
        return out

    id_type = docs.schema[id_col].dataType.simpleString()

    def gathered(pdf: pd.DataFrame) -> pd.DataFrame:
        meta = next(m for m in pdf["meta"] if m is not None)
        rows = pa.ipc.read_record_batch(meta, pa.schema([("id", id_arrow), ("held", pa.bool_()), ("n", pa.int64())]))
        size = rows.num_rows
        base, total, known = np.zeros(size), np.zeros(size), np.zeros(size, np.int64)
        for s in pdf["sums"]:
            k = int(np.frombuffer(s, np.int64, 1)[0])
            at = np.frombuffer(s, np.uint16, k, 8 + 20 * k).astype(np.int64)
            base[at] += np.frombuffer(s, np.float64, k, 8)
            total[at] += np.frombuffer(s, np.float64, k, 8 + 8 * k)
            known[at] += np.frombuffer(s, np.uint32, k, 8 + 16 * k)
        return pd.DataFrame({id_col: pd.Series(rows.column(0).to_pylist(), dtype=object), "held_out": rows.column(1).to_pandas(), "n_tokens": rows.column(2).to_pandas(), "n_known": known, "train_tokens": n, "base_score": base, "score": total})

    from pyspark.sql.pandas.types import to_arrow_type

    id_arrow = to_arrow_type(docs.schema[id_col].dataType)
    sums = dealt(source, shards, list(frequent)).groupBy("shard").applyInPandas(scored, "batch long, sums binary, meta binary")
    return sums.groupBy("batch").applyInPandas(gathered, f"`{id_col}` {id_type}, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def op6_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(load(spark, sf_dir, "documents"), crc_bucket("doc_id", 5) == 1)
