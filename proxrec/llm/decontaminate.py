"""Benchmark decontamination: one Aho-Corasick automaton over anchors of all normalised test items.

A text is normalised to its words (A-Z lower-cased; every run of characters outside 0-9, a-z and non-ASCII separates) joined by
single spaces, scanned once, and each occurrence is mapped back to word positions and to code-point offsets of the original.

An item's anchors are its consecutive pieces of half a window, so every window holds one whole: the automaton stores a text once, not once a
word. Where an anchor occurs, the match is extended word by word to both sides; runs that reach a window are hits.

Defined results: a null or empty text has no words and no hits; null or empty items match nothing and a null item id counts as
the empty string; repeated items count once by id, repeated documents are judged row by row; an input column named like a
result column is replaced; an empty benchmark leaves every document clean.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, field, load, resident, slices, small_batches

WINDOW = 10
#: Bytes of item text in one automaton; a larger benchmark is scanned in several such blocks, one after the other.
BLOCK_BYTES = 4_000_000
#: Blocks that are scanned in one pass over the documents, each in a Python process of its own; then the result is checkpointed.
CHAINED = 3
#: Byte by byte: separators become spaces, A-Z become a-z; bytes of non-ASCII characters are word bytes.
WORD_BYTES = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def words_of(text: str | None) -> list[bytes]:
    return text.encode().translate(WORD_BYTES).split() if text else []


class Anchors:
    """The automaton of all items' anchors; each knows the items and the places where it stands."""

    def __init__(self, items: list[tuple[str, str]], window: int):
        self.names: list[str] = []
        self.words: list[list[bytes]] = []
        found: dict[bytes, list[tuple[int, int]]] = {}
        for name, words in dict.fromkeys((item, tuple(words_of(text))) for item, text in items):
            if not words:
                continue
            size = (min(window, len(words)) + 1) // 2
            for at in range(0, len(words) - size + 1, size):
                found.setdefault(b" ".join(words[at : at + size]), []).append((len(self.names), at))
            self.names.append(name)
            self.words.append(list(words))
        self.window, self.automaton = window, None
        if found:
            self.automaton = ahocorasick.Automaton(ahocorasick.STORE_ANY)
            for text, places in found.items():
                self.automaton.add_word(f" {text.decode('latin-1')} ", (text.count(b" ") + 1, places))
            self.automaton.make_automaton()

    def scan(self, words: list[bytes]) -> tuple[list[int], list[int], set[str]]:
        """First and one-past-last words of the runs that reach a window, and the items they belong to."""
        starts: list[int] = []
        ends: list[int] = []
        items: set[str] = set()
        if self.automaton is None or not words:
            return starts, ends, items
        hits = list(self.automaton.iter(" ".join(["", b" ".join(words).decode("latin-1"), ""])))
        if not hits:
            return starts, ends, items
        space = np.cumsum([len(w) + 1 for w in words])  # where the space after each word stands
        reached: dict[tuple[int, int], int] = {}  # by item and shift, where its last run ended
        for e, (_, (n, places)) in zip(np.searchsorted(space, [h[0] for h in hits]).tolist(), hits, strict=True):
            first = e + 1 - n
            for item, at in places:
                shift = first - at
                if reached.get((item, shift), 0) > first:
                    continue
                own = self.words[item]
                a, b = at, at + n
                while a and a + shift and own[a - 1] == words[a - 1 + shift]:
                    a -= 1
                while b < len(own) and b + shift < len(words) and own[b] == words[b + shift]:
                    b += 1
                reached[item, shift] = b + shift
                if b - a >= min(self.window, len(own)):
                    starts.append(a + shift)
                    ends.append(b + shift)
                    items.add(self.names[item])
        return starts, ends, items


def merged(starts: list[int], ends: list[int]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(zip(starts, ends, strict=True)):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def original_offsets(text: str, ranges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Code-point offsets, end exclusive, of ranges of words."""
    raw = np.frombuffer(text.encode(), np.uint8)
    inside = np.frombuffer(WORD_BYTES, np.uint8)[raw] != 32
    edge = np.flatnonzero(np.diff(np.concatenate([[False], inside, [False]]).astype(np.int8)))
    point = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])
    return [(int(point[edge[2 * a]]), int(point[edge[2 * b - 1]])) for a, b in ranges]


def blocks(items: DataFrame, id_col: str, text_col: str) -> Iterator[list[tuple[str, str]]]:
    """The items in blocks of bounded size, one on the driver at a time."""
    block, held = [], 0
    for item, text in items.select(F.coalesce(F.col(id_col).cast("string"), F.lit("")), F.coalesce(F.col(text_col), F.lit(""))).toLocalIterator():
        if block and held + len(text) > BLOCK_BYTES:
            yield block
            block, held = [], 0
        block.append((item, text))
        held += len(text)
    if block:
        yield block


def decontaminate(docs: DataFrame, items: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = WINDOW, keep: list[str] | None = None) -> DataFrame:
    """Adds n_words, n_hit, hit_spans (start, end in code points of the original text) and hit_items (sorted strings).

    Documents are never shuffled. Each block of items is broadcast behind its size bound (BLOCK_BYTES); later blocks continue
    from what the earlier ones found, CHAINED of them in a pass.
    """
    own = [field("n_words", T.LongType()), field("n_hit", T.LongType()), field("hit_spans", T.ArrayType(T.StructType([field("start", T.IntegerType()), field("end", T.IntegerType())]))), field("hit_items", T.ArrayType(T.StringType()))]
    temp = [field("_llm_starts", T.ArrayType(T.IntegerType())), field("_llm_ends", T.ArrayType(T.IntegerType())), field("_llm_items", T.ArrayType(T.StringType()))]
    names = {f.name.lower() for f in own}
    kept = [c for c in (docs.columns if keep is None else keep) if c.lower() not in names]
    small_batches(docs.sparkSession)
    out = docs.select(*[F.col(f"`{c}`") for c in kept], F.col(f"`{text_col}`").cast("string").alias("_llm_text"))
    base = T.StructType([out.schema[c] for c in kept])
    def stage(held, first: bool, last: bool, schema: T.StructType):
        key = ("items", uuid.uuid4().hex)

        def run(batches):
            from pyspark.sql.pandas.types import to_arrow_schema

            anchors, made = resident(key, lambda: Anchors(held.value, window)), to_arrow_schema(schema)
            for batch in batches:
                for part in slices(batch, "_llm_text"):
                    texts = part.column("_llm_text").to_pylist()
                    before = [[None] * len(texts)] * 3 if first else [part.column(f.name).to_pylist() for f in temp]
                    rows = []
                    for text, s0, e0, i0 in zip(texts, *before, strict=True):
                        words = words_of(text) if text else []
                        starts, ends, ids = anchors.scan(words)
                        starts, ends, ids = (s0 or []) + starts, (e0 or []) + ends, ids | set(i0 or [])
                        if last:
                            ranges = merged(starts, ends)
                            spans = [{"start": a, "end": b} for a, b in original_offsets(text, ranges)] if ranges else []
                            rows.append((len(words), sum(b - a for a, b in ranges), spans, sorted(ids)))
                        else:
                            rows.append((starts, ends, sorted(ids)))
                    fresh = [list(c) for c in zip(*rows, strict=True)]
                    columns = [part.column(c).cast(made.field(c).type) for c in kept] + ([] if last else [part.column("_llm_text")])
                    columns += [pa.array(c, type=made.field(len(columns) + i).type) for i, c in enumerate(fresh)]
                    yield pa.RecordBatch.from_arrays(columns, schema=made)

        return run

    own_blocks, k = blocks(items, item_col, item_text_col), 0
    block, following = next(own_blocks, []), None
    while block is not None:
        following = next(own_blocks, None)
        if k and k % CHAINED == 0:
            out = cut(out)
        schema = T.StructType(base.fields + (own if following is None else [field("_llm_text", T.StringType()), *temp]))
        out = out.mapInArrow(stage(docs.sparkSession.sparkContext.broadcast(block), k == 0, following is None, schema), schema)
        block, k = following, k + 1
    return out


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"), keep=["doc_id"])
    return found.select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("hit_items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "hit_items").cast("binary"), 256).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
    )


OP8_SQL = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(len(ws), 10) AS k, array_to_string(ws[i:i + least(len(ws), 10) - 1], ' ') AS win
       FROM (SELECT item_id, ws, unnest(generate_series(1, greatest(1, len(ws) - 9))) AS i FROM b WHERE len(ws) > 0)),
ks AS (SELECT DISTINCT k FROM bw),
dw AS (SELECT doc_id, k, i, array_to_string(ws[i:i + k - 1], ' ') AS win
       FROM (SELECT doc_id, ws, k, unnest(generate_series(1, len(ws) - k + 1)) AS i FROM w, ks WHERE len(ws) >= k)),
hit AS (SELECT doc_id, dw.k, i, item_id FROM dw JOIN bw ON dw.win = bw.win AND dw.k = bw.k),
pos AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(generate_series(i, i + k - 1)) AS p FROM hit) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM hit) GROUP BY doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM w LEFT JOIN pos USING (doc_id) LEFT JOIN its USING (doc_id)
"""
