"""Elias-Fano sequences and n-gram tries over them, as numpy arrays that can be memory-mapped."""

from __future__ import annotations

import mmap
import os

import numpy as np

_POP = np.array([bin(b).count("1") for b in range(256)], np.uint8)
#: Place of the k-th set bit of a byte.
_SELECT = np.array([[([i for i in range(8) if b >> i & 1] + [8] * 8)[k] for k in range(8)] for b in range(256)], np.uint8)
CHUNK = 1 << 17


class EliasFano:
    """A non-decreasing sequence of integers below 2**62: low bits packed, high bits in unary with counts a 64-bit word.

    Supports access by index and the search for a key within a range of indexes; both take arrays.
    """

    def __init__(self, low: np.ndarray, high: np.ndarray, ones: np.ndarray, n: int, bits: int):
        self.low, self.high, self.ones, self.n, self.bits = low, high, ones, int(n), int(bits)
        self.zeros = np.arange(len(ones), dtype=np.int64) * 64 - ones.astype(np.int64)

    @classmethod
    def build(cls, values: np.ndarray) -> EliasFano:
        v = np.ascontiguousarray(values, np.uint64)
        n = len(v)
        top = int(v[-1]) if n else 0
        bits = min(56, max(0, (max(1, top // max(1, n))).bit_length() - 1))
        parts = []
        for a in range(0, n, CHUNK):  # a multiple of 8 elements, so that parts end on bytes
            x = v[a : a + CHUNK]
            parts.append(np.packbits(((x[:, None] >> np.arange(bits, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8).reshape(-1), bitorder="little"))
        low = np.concatenate([*parts, np.zeros(8, np.uint8)])
        size = n + (top >> bits) + 1
        high = np.zeros((size + 63) // 64 * 64 + 64, np.uint8)
        high[(v >> np.uint64(bits)).astype(np.int64) + np.arange(n)] = 1
        high = np.packbits(high, bitorder="little")
        per_word = _POP[high].reshape(-1, 8).sum(1, dtype=np.int64)
        return cls(low, high, np.concatenate([[0], np.cumsum(per_word)]).astype(np.uint32), n, bits)

    def _select(self, k: np.ndarray, directory: np.ndarray, flip: int) -> np.ndarray:
        """Position of the k-th one (flip 0) or zero (flip 255)."""
        word = np.searchsorted(directory, k, side="right") - 1
        left = (k - directory[word]).astype(np.int64)
        raw = self.high.reshape(-1, 8)[word] ^ np.uint8(flip)
        ends = np.cumsum(_POP[raw], axis=1, dtype=np.int64)
        byte = (ends <= left[:, None]).sum(1)
        row = np.arange(len(k))
        left = left - np.where(byte > 0, ends[row, np.maximum(byte - 1, 0)], 0)
        return word * 64 + byte * 8 + _SELECT[raw[row, byte], left]

    def lows(self, i: np.ndarray) -> np.ndarray:
        if not self.bits:
            return np.zeros(len(i), np.uint64)
        at = i.astype(np.int64) * self.bits
        window = self.low[(at >> 3)[:, None] + np.arange(8)].copy().view("<u8")[:, 0]
        return (window >> (at & 7).astype(np.uint64)) & np.uint64((1 << self.bits) - 1)

    def __getitem__(self, i: np.ndarray) -> np.ndarray:
        i = np.asarray(i, np.int64)
        return ((self._select(i, self.ones, 0) - i).astype(np.uint64) << np.uint64(self.bits)) | self.lows(i)

    def find(self, keys: np.ndarray, start: np.ndarray | None = None, end: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """For each key the index of its successor within [start, end), and whether that is the key itself."""
        keys = np.asarray(keys, np.uint64)
        if not self.n:
            return np.zeros(len(keys), np.int64), np.zeros(len(keys), bool)
        where, found = np.empty(len(keys), np.int64), np.empty(len(keys), bool)
        most = int(self.zeros[-1]) - 1
        for a in range(0, len(keys), CHUNK):
            k = keys[a : a + CHUNK]
            h = np.minimum((k >> np.uint64(self.bits)).astype(np.int64), most)
            lo = np.where(h > 0, self._select(np.maximum(h - 1, 0), self.zeros, 255) - (h - 1), 0)
            hi = self._select(h, self.zeros, 255) - h
            if start is not None:
                lo, hi = np.maximum(lo, start[a : a + CHUNK]), np.minimum(hi, end[a : a + CHUNK])
            lo, hi = np.minimum(lo, self.n), np.minimum(hi, self.n)
            target, stop = k & np.uint64((1 << self.bits) - 1), hi.copy()
            live = np.flatnonzero(lo < hi)
            while len(live):
                mid = (lo[live] + hi[live]) >> 1
                below = self.lows(mid) < target[live]
                lo[live] = np.where(below, mid + 1, lo[live])
                hi[live] = np.where(below, hi[live], mid)
                live = live[lo[live] < hi[live]]
            where[a : a + CHUNK] = lo
            ok = lo < stop
            ok[ok] = (self[lo[ok]] == k[ok])
            found[a : a + CHUNK] = ok
        return where, found

    def arrays(self) -> dict[str, np.ndarray]:
        return {"low": self.low, "high": self.high, "ones": self.ones, "shape": np.array([self.n, self.bits])}

    def save(self, path: str) -> None:
        for k, x in self.arrays().items():
            np.save(f"{path}.{k}.npy", x)

    @classmethod
    def open(cls, path: str) -> EliasFano:
        low, high, ones = (np.load(f"{path}.{k}.npy", mmap_mode="r") for k in ("low", "high", "ones"))
        return cls(low, high, ones, *np.load(f"{path}.shape.npy"))


class Quantiser:
    """Evenly spaced 16-bit codes over the range of the values."""

    def __init__(self, values: np.ndarray):
        self.base, top = (float(values.min()), float(values.max())) if len(values) else (0.0, 0.0)
        self.step = (top - self.base) / 65535 or 1.0

    def codes(self, values: np.ndarray) -> np.ndarray:
        return np.rint((values - self.base) / self.step).astype(np.uint16)

    def values(self, codes: np.ndarray) -> np.ndarray:
        return self.base + np.asarray(codes, np.float64) * self.step


class NgramTrie:
    """Levels of (parent's rank, child id) with monotone pointers to the children and quantised values at each node.

    First words lie below 2**62, ids of children below 2**32. A child is found by successor search for (parent's rank, id) within the range that
    the parent's pointers give. The levels are plain arrays: kept in files that are mapped, or in one anonymous mapping.
    """

    def __init__(self, levels: list[tuple[EliasFano, EliasFano | None, list[tuple[np.ndarray, Quantiser]]]]):
        self.levels = levels

    @classmethod
    def build(cls, keys: list[np.ndarray], values: list[list[np.ndarray]]) -> NgramTrie:
        """keys[0]: sorted distinct first words; keys[k]: sorted distinct parent's rank << 32 | id. values[k]: the level's value columns."""
        levels = []
        for k, (own, columns) in enumerate(zip(keys, values, strict=True)):
            pointers = None
            if k + 1 < len(keys):
                parents = (keys[k + 1] >> np.uint64(32)).astype(np.int64)
                pointers = EliasFano.build(np.concatenate([[0], np.cumsum(np.bincount(parents, minlength=len(own)))]).astype(np.uint64))
            coded = []
            for column in columns:
                q = Quantiser(column)
                coded.append((q.codes(column), q))
            levels.append((EliasFano.build(own), pointers, coded))
        return cls(levels)

    def roots(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return self.levels[0][0].find(words)

    def children(self, level: int, parents: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ranks at ``level`` of the children ``ids`` of nodes of the level above."""
        pointers = self.levels[level - 1][1]
        key = (np.asarray(parents, np.uint64) << np.uint64(32)) | np.asarray(ids, np.uint64)
        return self.levels[level][0].find(key, pointers[parents].astype(np.int64), pointers[np.asarray(parents) + 1].astype(np.int64))

    def value(self, level: int, ranks: np.ndarray, column: int = 0) -> np.ndarray:
        codes, q = self.levels[level][2][column]
        return q.values(codes[ranks])

    def arrays(self) -> dict[str, np.ndarray]:
        out = {}
        for k, (own, pointers, coded) in enumerate(self.levels):
            for name, e in (("keys", own), ("pointers", pointers)):
                if e is not None:
                    out |= {f"{k}.{name}.{part}": x for part, x in e.arrays().items()}
            for j, (codes, q) in enumerate(coded):
                out |= {f"{k}.codes{j}": codes, f"{k}.range{j}": np.array([q.base, q.step])}
        return out

    @classmethod
    def of_arrays(cls, arrays: dict[str, np.ndarray]) -> NgramTrie:
        def sequence(name: str) -> EliasFano | None:
            return EliasFano(*(arrays[f"{name}.{part}"] for part in ("low", "high", "ones")), *arrays[f"{name}.shape"]) if f"{name}.low" in arrays else None

        levels: list = []
        while f"{len(levels)}.keys.low" in arrays:
            k, coded = len(levels), []
            while f"{k}.codes{len(coded)}" in arrays:
                q = Quantiser(np.zeros(0))
                q.base, q.step = arrays[f"{k}.range{len(coded)}"].tolist()
                coded.append((arrays[f"{k}.codes{len(coded)}"], q))
            levels.append((sequence(f"{k}.keys"), sequence(f"{k}.pointers"), coded))
        return cls(levels)

    def save(self, folder: str) -> None:
        for name, x in self.arrays().items():
            np.save(os.path.join(folder, f"{name}.npy"), x)

    @classmethod
    def open(cls, folder: str) -> NgramTrie:
        return cls.of_arrays({name[:-4]: np.load(os.path.join(folder, name), mmap_mode="r") for name in os.listdir(folder) if name.endswith(".npy")})

    def mapped(self) -> NgramTrie:
        """The same trie in one anonymous memory mapping, which needs no folder."""
        arrays, at, places = self.arrays(), 0, {}
        for name, x in arrays.items():
            places[name] = at
            at += -(-x.nbytes // 64) * 64
        memory = mmap.mmap(-1, max(at, 1))
        view = {}
        for name, x in arrays.items():
            held = np.frombuffer(memory, x.dtype, x.size, places[name]) if x.size else x
            if x.size:
                held[:] = x.reshape(-1)
            view[name] = held
        return NgramTrie.of_arrays(view)
