"""Byte-level BPE encoding and decoding with a two-tier lookup.

Tier one: a minimal perfect hash over the vocabulary (hash, displace) resolves a pre-token that
is itself a token: one probe, one comparison.  Tier two: other pre-tokens are merged by rank with
a heap over a doubly linked list of their bytes, O(n log n) also for a pre-token of a megabyte.
Results of distinct pre-tokens are remembered per worker, up to a bound, after which the memory
starts anew; that affects speed only.

Defined cases: null and empty texts have no ids; special strings are ordinary text; equal rows
get equal ids; ill-formed ranks (a missing single byte) raise KeyError.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .kernel import KEPT, Memory, slices, tidy


def hash_bytes(data: bytes) -> int:
    return int.from_bytes(hashlib.blake2b(data, digest_size=8).digest(), "little")


class MinimalPerfectHash:
    """Hash-and-displace: n keys to 0..n-1 without collision; a stranger is told by comparison.

    Buckets of one size, the largest first, look for their seeds together, so a table of 50,000 keys takes
    less than a second."""

    def __init__(self, keys: list[bytes]):
        n = len(keys)
        self.n, self.buckets = n, max(1, n // 4)
        base = np.array([hash_bytes(k) for k in keys], np.uint64)
        bucket = (base % np.uint64(self.buckets)).astype(np.int64)
        by = np.argsort(bucket, kind="stable")
        size = np.bincount(bucket, minlength=self.buckets)
        first = np.cumsum(size) - size
        shift, slot = np.zeros(self.buckets, np.int64), np.full(n, -1, np.int64)
        for m in range(int(size.max(initial=0)), 1, -1):
            todo = np.flatnonzero(size == m)
            members = by[first[todo][:, None] + np.arange(m)]
            seed = 0
            while len(todo):
                seed += 1
                places = self._places(base[members], seed)
                ordered = np.sort(places, axis=1)
                fits = (slot[places] < 0).all(axis=1) & (ordered[:, 1:] != ordered[:, :-1]).all(axis=1)
                # of those that fit, each place goes to the first bucket that asks for it; a bucket takes all its places or none
                asked = np.flatnonzero(fits)
                flat = places[asked].ravel()
                owner = np.full(n, len(todo), np.int64)
                np.minimum.at(owner, flat, np.repeat(asked, m))
                won = asked[(owner[places[asked]] == asked[:, None]).all(axis=1)]
                slot[places[won].ravel()] = members[won].ravel()
                shift[todo[won]] = seed
                left = np.setdiff1d(np.arange(len(todo)), won)
                todo, members = todo[left], members[left]
        free = np.flatnonzero(slot < 0)
        alone = np.flatnonzero(size == 1)
        shift[alone] = -1 - free[: len(alone)]  # a bucket of one key names its place itself
        slot[free[: len(alone)]] = by[first[alone]]
        self.shift, self.slot = shift.tolist(), slot.tolist()
        self.keys = [keys[i] for i in self.slot]

    def _places(self, h: np.ndarray, seed: int) -> np.ndarray:
        h = h ^ np.uint64(seed * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0xD1342543DE82EF95)
        return ((h ^ (h >> np.uint64(29))) % np.uint64(self.n)).astype(np.int64)

    def _place(self, h: int, seed: int) -> int:
        h = (h ^ (seed * 0x9E3779B97F4A7C15)) & 0xFFFFFFFFFFFFFFFF
        h = (h ^ (h >> 31)) * 0xD1342543DE82EF95 & 0xFFFFFFFFFFFFFFFF
        return (h ^ (h >> 29)) % self.n

    def find(self, key: bytes) -> int:
        """The place of ``key`` among the keys given, or -1."""
        if not self.n:
            return -1
        h = hash_bytes(key)
        shift = self.shift[h % self.buckets]
        place = -1 - shift if shift < 0 else self._place(h, shift)
        return self.slot[place] if self.keys[place] == key else -1


class Codec:
    """Encoder and decoder over a file of ranks (base64 token, rank) and a splitting pattern."""

    def __init__(self, path: str, pattern: str):
        with open(path, "rb") as f:
            pairs = [line.split() for line in f if line.strip()]
        self.ranks = {base64.b64decode(a): int(b) for a, b in pairs}
        tokens = list(self.ranks)
        self.index = MinimalPerfectHash(tokens)
        self.ids = [self.ranks[t] for t in tokens]
        self.bytes_of = {r: t for t, r in self.ranks.items()}
        self.byte_ids = [self.ranks[bytes([b])] for b in range(256)]
        #: the rank of two tokens' bytes together, where that is a token
        self.pairs = {}
        for t, r in self.ranks.items():
            for cut in range(1, len(t)):
                a, b = self.ranks.get(t[:cut]), self.ranks.get(t[cut:])
                if a is not None and b is not None:
                    self.pairs[a << 32 | b] = r
        self.split = regex.compile(pattern).findall
        self.memory = Memory(self.pre_token)

    def merge(self, piece: bytes) -> list[int]:
        """Ids of one pre-token: the pair of least rank, leftmost among equals, is merged first."""
        n = len(piece)
        pair, one = self.pairs.get, self.byte_ids
        ids = [one[b] for b in piece]
        left, right = list(range(-1, n - 1)), list(range(1, n + 1))
        heap = [r << 32 | i for i in range(n - 1) if (r := pair(ids[i] << 32 | ids[i + 1])) is not None]
        heapq.heapify(heap)
        pop, push = heapq.heappop, heapq.heappush
        while heap:
            entry = pop(heap)
            r, i = entry >> 32, entry & 0xFFFFFFFF
            j = right[i]
            if ids[i] < 0 or j >= n or pair(ids[i] << 32 | ids[j]) != r:
                continue  # one of the two has been merged since
            ids[i], ids[j] = r, -1
            k = right[i] = right[j]
            if k < n:
                left[k] = i
                if (r2 := pair(r << 32 | ids[k])) is not None:
                    push(heap, r2 << 32 | i)
            h = left[i]
            if h >= 0 and (r2 := pair(ids[h] << 32 | r)) is not None:
                push(heap, r2 << 32 | h)
        return [i for i in ids if i >= 0]

    def pre_token(self, piece: str) -> bytes:
        """Ids of one pre-token as little-endian unsigned 32-bit integers."""
        raw = piece.encode()
        at = self.index.find(raw)
        ids = [self.ids[at]] if at >= 0 else self.merge(raw)
        return np.array(ids, "<u4").tobytes()

    def encode(self, text: str) -> bytes:
        memory = self.memory
        return b"".join([memory[p] for p in self.split(text)])

    def decode(self, ids: bytes) -> bytes:
        table = self.bytes_of
        return b"".join([table[i] for i in np.frombuffer(ids, "<u4").tolist()])


@lru_cache(maxsize=2)
def codec(path: str, pattern: str) -> Codec:
    return Codec(path, pattern)


KEPT[__name__] = codec.cache_clear


def encode_documents(docs: DataFrame, path: str, pattern: str, with_ids: bool = True) -> DataFrame:
    """Every row of ``docs`` with ``token_ids`` (binary, little-endian u32; if ``with_ids``), ``n_tokens``,
    ``ids_sha256`` and ``decoded_sha256`` added; columns of these names are replaced."""
    own = [*(["token_ids"] if with_ids else []), "n_tokens", "ids_sha256", "decoded_sha256"]
    docs = docs.drop(*own)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path, pattern)
        for batch in batches:
            for part in slices(batch):
                ids = [c.encode(t) if t else b"" for t in part.column("text").to_pylist()]
                arrays = [pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in ids], pa.string()), pa.array([hashlib.sha256(c.decode(x)).hexdigest() for x in ids], pa.string())]
                if with_ids:
                    arrays.insert(0, pa.array(ids, pa.binary()))
                yield pa.RecordBatch.from_arrays([*part.columns, *arrays], [*part.schema.names, *own])
        c.memory.forget()  # a waiting worker holds the tables alone

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return docs.mapInArrow(tidy(encode), f"{kinds}, {'token_ids binary, ' if with_ids else ''}n_tokens bigint, ids_sha256 string, decoded_sha256 string")
