"""Byte-level BPE by a public rank file: encoding in two tiers, and decoding.

Tier one resolves a whole pre-token that is itself in the vocabulary through a minimal perfect hash (hash and displace; the
slot's bytes are compared, so strangers are told apart). Tier two merges the others by a heap of adjacent pairs over linked bytes.
Which characters are letters, numbers and spaces is asked of the tokenizer library itself, over all code points, when a vocabulary is
read; the pattern is spelt out with them, so texts split alike whatever Unicode tables the workers' Python has.

Defined results: a null text counts as empty (no ids, empty decoded bytes); repeated rows give repeated results; an input
column named like a result column is replaced; empty tables give empty results with the same schema. Ids outside the
vocabulary raise ValueError in ``decode``.
"""

from __future__ import annotations

import base64
import re
from array import array
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import field, load, map_text, resident

RANK_FILE = "byte_bpe_multi_50k.tiktoken"
#: Entries in each of the two generations of resolved pre-tokens that a worker remembers.
REMEMBERED = 200_000


class PerfectHash:
    """Minimal perfect hash from byte strings to 0..n-1: each bucket has a displacement that sends its keys to free slots.

    Buckets of one key come last and name their slot outright (stored as -1 - slot).
    """

    def __init__(self, keys: list[bytes], load_factor: int = 3):
        n = self.n = len(keys)
        self.buckets = max(1, n // load_factor)
        groups: dict[int, list[int]] = {}
        hashes = [xxhash.xxh64_intdigest(k) for k in keys]
        for i, h in enumerate(hashes):
            groups.setdefault(h % self.buckets, []).append(i)
        self.displacement = [0] * self.buckets
        self.order = np.full(n, -1, np.int64)
        free: list[int] | None = None
        for bucket, members in sorted(groups.items(), key=lambda x: -len(x[1])):
            if len(members) == 1:
                free = np.flatnonzero(self.order < 0)[::-1].tolist() if free is None else free
                self.displacement[bucket] = -1 - (s := free.pop())
                self.order[s] = members[0]
                continue
            d = 0
            while True:
                slots = [self._slot(hashes[i], d) for i in members]
                if len(set(slots)) == len(slots) and all(self.order[s] < 0 for s in slots):
                    break
                d += 1
            self.displacement[bucket] = d
            for i, s in zip(members, slots, strict=True):
                self.order[s] = i

    def _slot(self, h: int, d: int) -> int:
        return (((h ^ d) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF) >> 20) % self.n

    def slot(self, key: bytes) -> int:
        h = xxhash.xxh64_intdigest(key)
        d = self.displacement[h % self.buckets]
        return self._slot(h, d) if d >= 0 else -1 - d


class Vocabulary:
    """Ranks of a byte-level BPE with its perfect hash. Built once on the driver; its size is the rank file's."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        tokens = list(ranks)
        self.pattern, self.hash, self.classes = pattern, PerfectHash(tokens), character_classes()
        self.slot_key = [tokens[i] for i in self.hash.order]
        self.slot_rank = [ranks[k] for k in self.slot_key]
        self.decoder = {r: k for k, r in ranks.items()}
        self.byte_rank = [ranks[bytes([b])] for b in range(256)]

    @classmethod
    def read(cls, path: str, pattern: str) -> Vocabulary:
        with open(path, "rb") as f:
            return cls({base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}, pattern)

    def digest(self) -> int:
        return xxhash.xxh64_intdigest(b"".join(b"%d %d " % (len(k), r) + k for k, r in zip(self.slot_key, self.slot_rank, strict=True)) + self.pattern.encode() + repr(self.classes).encode())

    def whole(self, token: bytes) -> int | None:
        """Tier one: the rank of a byte string that is a vocabulary entry, else None."""
        s = self.hash.slot(token)
        return self.slot_rank[s] if self.slot_key[s] == token else None


CLASSES = (r"\p{L}", r"\p{N}", r"\s")


def character_classes() -> dict[str, list[tuple[int, int]]]:
    """Ranges of the code points in each class of a pattern, as the tokenizer library sees them: it encodes only what matches."""
    import tiktoken

    every = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    found = {}
    for name in CLASSES:
        probe = tiktoken.Encoding("probe", pat_str=name, mergeable_ranks={bytes([b]): b for b in range(256)}, special_tokens={})
        points = np.array([ord(c) for c in bytes(probe.encode_ordinary(every)).decode()])
        cuts = np.flatnonzero(np.diff(points) != 1) + 1
        found[name] = [(int(x[0]), int(x[-1])) for x in np.split(points, cuts)]
    return found


def spelt(ranges: list[tuple[int, int]], top: int) -> str:
    """The part of a class below a code point, as the inside of a set."""
    return "".join(f"\\U{a:08x}-\\U{min(b, top - 1):08x}" for a, b in ranges if a < top)


def spelt_pattern(pattern: str, classes: dict[str, list[tuple[int, int]]], top: int) -> str:
    """The pattern with its Unicode classes spelt out for texts whose characters all lie below ``top``."""
    inner = {name: spelt(ranges, top) for name, ranges in classes.items()} | {r"\S": "^" + spelt(classes[r"\s"], top)}
    out, inside, i = [], False, 0
    while i < len(pattern):
        name = next((k for k in inner if pattern.startswith(k, i)), None)
        if name and inside and name == r"\S":
            raise ValueError("a negated space class inside a set")
        if name:
            out.append(inner[name] if inside else f"[{inner[name]}]")
            i += len(name)
            continue
        if pattern[i] == "\\":
            out.append(pattern[i : i + 2])
            i += 2
            continue
        inside = pattern[i] == "[" or (inside and pattern[i] != "]")
        out.append(pattern[i])
        i += 1
    return "".join(out)


class Encoder:
    """One worker's encoder: the merges by pair of ranks, and resolved pre-tokens in two generations.

    Three spellings of the pattern serve texts within Latin-1, within the basic plane, and all others: shorter sets match faster.
    """

    def __init__(self, vocabulary: Vocabulary):
        self.vocabulary = vocabulary
        self.find_latin, self.find_basic, self.find = (re.compile(spelt_pattern(vocabulary.pattern, vocabulary.classes, top)).findall for top in (0x100, 0x10000, 0x110000))
        self.beyond = re.compile("[\U00010000-\U0010ffff]").search
        ranks = {k: r for r, k in vocabulary.decoder.items()}
        self.joined: dict[int, int] = {}
        for token, rank in ranks.items():
            for i in range(1, len(token)):
                a, b = ranks.get(token[:i]), ranks.get(token[i:])
                if a is not None and b is not None:
                    self.joined[a << 32 | b] = rank
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def merged(self, token: bytes) -> list[int]:
        """Tier two: lowest rank first, leftmost on ties, over bytes linked to their neighbours."""
        ids: list[int] = [self.vocabulary.byte_rank[b] for b in token]
        n, joined = len(ids), self.joined
        after = list(range(1, n + 1))
        before = list(range(-1, n - 1))
        heap = [(r, i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := joined.get(ids[i] << 32 | ids[i + 1])) is not None]
        heapify(heap)
        while heap:
            rank, i, a, b = heappop(heap)
            j = after[i]
            if ids[i] != a or j >= n or ids[j] != b:
                continue  # one side has been merged meanwhile
            k = after[j]
            ids[i], ids[j], after[i] = rank, -1, k
            if k < n:
                before[k] = i
                if (r := joined.get(rank << 32 | ids[k])) is not None:
                    heappush(heap, (r, i, rank, ids[k]))
            p = before[i]
            if p >= 0 and (r := joined.get(ids[p] << 32 | rank)) is not None:
                heappush(heap, (r, p, ids[p], rank))
        return [x for x in ids if x >= 0]

    def resolve(self, token: str) -> bytes:
        """The ids of a pre-token, as packed 32-bit integers."""
        packed = self.old.get(token)
        if packed is None:
            raw = token.encode()
            rank = self.vocabulary.whole(raw)
            packed = array("i", (rank,) if rank is not None else self.merged(raw)).tobytes()
        if len(token) <= 64:  # long runs are rare and would fill the memory
            if len(self.young) >= REMEMBERED:
                self.old, self.young = self.young, {}
            self.young[token] = packed
        return packed

    def encode(self, text: str) -> bytes:
        get, resolve = self.young.get, self.resolve
        parts = []
        try:
            text.encode("latin-1")
            tokens = self.find_latin(text)
        except UnicodeEncodeError:
            tokens = self.find(text) if self.beyond(text) else self.find_basic(text)
        for token in tokens:
            packed = get(token)
            if packed is None:
                packed = resolve(token)
                get = self.young.get
            parts.append(packed)
        return b"".join(parts)


def encode(df: DataFrame, vocabulary: Vocabulary, text_col: str = "text", ids_col: str = "ids", keep: list[str] | None = None) -> DataFrame:
    """Adds the ids of each whole text as array<int>. The vocabulary is broadcast: its size is fixed by the rank file."""
    shared, key = df.sparkSession.sparkContext.broadcast(vocabulary), ("bpe", vocabulary.digest())

    def make():
        encoder = resident(key, lambda: Encoder(shared.value))

        def work(texts):
            packed = [encoder.encode(t) if t else b"" for t in texts]
            ends = np.cumsum([0] + [len(p) // 4 for p in packed])
            return [pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.frombuffer(b"".join(packed), "<i4")))]

        return work

    make.stays = True
    return map_text(df, make, [field(ids_col, T.ArrayType(T.IntegerType()))], text_col, keep)


def spelled(lists: pa.ListArray, table: dict[int, bytes]) -> list[bytes]:
    """The bytes of each list of ids (null: none). Ids go by NumPy: Arrow would make an object of its own for each."""
    made = []
    for ids in lists:
        try:
            made.append(b"".join(map(table.__getitem__, ids.values.to_numpy(zero_copy_only=False).tolist())) if ids.is_valid else b"")
        except KeyError as e:
            raise ValueError(f"id {e} is not in the vocabulary") from None
    return made


def decode(df: DataFrame, vocabulary: Vocabulary, ids_col: str = "ids", bytes_col: str = "decoded") -> DataFrame:
    """Adds the bytes that the ids stand for (null ids: empty)."""
    shared = df.sparkSession.sparkContext.broadcast(vocabulary.decoder)
    kept = [c for c in df.columns if c.lower() != bytes_col.lower()]
    schema = T.StructType([df.schema[c] for c in kept] + [field(bytes_col, T.BinaryType())])

    def run(batches):
        from pyspark.sql.pandas.types import to_arrow_schema

        out, table = to_arrow_schema(schema), shared.value
        for batch in batches:
            column, made = batch.column(ids_col), []
            for start in range(0, batch.num_rows, 256):
                made += spelled(column.slice(start, 256), table)
            columns = [batch.column(batch.schema.get_field_index(c)).cast(out.field(i).type) for i, c in enumerate(kept)]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(made, pa.binary())], schema=out)

    return df.mapInArrow(run, schema)


def public_vocabulary(path: str | None = None, pattern: str | None = None) -> Vocabulary:
    import public_tokenizers

    return Vocabulary.read(path or public_tokenizers.path(RANK_FILE), pattern or public_tokenizers.PATTERN)


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    vocabulary = public_vocabulary()
    coded = decode(encode(load(spark, sf_dir, "documents"), vocabulary, keep=["doc_id"]), vocabulary)
    return coded.select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.concat_ws(",", F.col("ids").cast("array<string>")).cast("binary"), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )
