"""Exact token counts of every prefix by dynamic programming.

Inside a pre-token the encoding of a prefix ends in exactly one token t that is compatible with
the last token of the prefix before t (merging never joins across their border).  So one pass
over the ends gives ``count[end] = count[end - len(t)] + 1`` for all prefixes at once, and a
document's counts are sums over its pre-tokens.  Truncation and budget questions are looked up
in the stored counts; nothing is encoded again.

Defined cases: null and empty texts have 0 tokens; added special strings of the tokenizer file
that occur in a text are one token each, as its library has it by default; equal rows get equal
counts.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .kernel import KEPT, Memory, slices, tidy

PAIRS_REMEMBERED = 1_000_000
#: Fixed value: the splitting pattern of the byte-level pre-tokenizer.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


def _byte_letters() -> dict[str, int]:
    """The letters that stand for bytes in the vocabulary file: printable bytes stand for themselves, the rest follow from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class PrefixCounter:
    """Counts by the merges of a byte-level BPE tokenizer file (JSON)."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = _byte_letters()
        raw = lambda s: bytes(letters[c] for c in s)
        self.id_of = {raw(t): i for t, i in spec["model"]["vocab"].items() if all(c in letters for c in t)}
        self.longest = max(map(len, self.id_of))
        size = max(self.id_of.values()) + 1
        #: priority of a token: the place of its merge; single bytes come first
        self.order = [-1] * size
        self.first, self.second, self.joined = list(range(size)), list(range(size)), {}
        for k, m in enumerate(spec["model"]["merges"]):
            a, b = (raw(x) for x in (m.split(" ") if isinstance(m, str) else m))
            a, b, t = self.id_of[a], self.id_of[b], self.id_of[a + b]
            self.joined.setdefault(a << 32 | b, k)
            if self.order[t] < 0:
                self.order[t], self.first[t], self.second[t] = k, a, b
        added = [x["content"] for x in spec.get("added_tokens", [])]
        self.special = regex.compile("|".join(map(regex.escape, sorted(added, key=len, reverse=True)))) if added else None
        self.added = tuple(added)
        self.split = regex.compile(PATTERN).findall
        self.totals = Memory(lambda piece: self.piece_counts(piece.encode())[-1])
        self.compatible: dict[int, bool] = {}

    def _stays_apart(self, a: int, b: int) -> bool:
        """Whether merging leaves tokens ``a`` and ``b`` side by side: their merges are taken back
        from the last to the first, and no pair across the border may come before one taken back."""
        order, joined = self.order, self.joined
        bound = 1 << 60
        while True:
            k = joined.get(a << 32 | b)
            if k is not None and k < bound:
                return False
            if order[a] < 0 and order[b] < 0:
                return True
            # equal merges are made from the left, so those at the right are taken back first
            if order[a] > order[b]:
                bound, a = order[a], self.second[a]
            else:
                bound, b = order[b] + 1, self.first[b]

    def fits(self, a: int, b: int) -> bool:
        key = a << 32 | b
        known = self.compatible.get(key)
        if known is None:
            if len(self.compatible) > PAIRS_REMEMBERED:
                self.compatible.clear()
            known = self.compatible[key] = self._stays_apart(a, b)
        return known

    def piece_counts(self, piece: bytes) -> list[int]:
        """Token counts of all byte prefixes of one pre-token."""
        n, id_of, fits = len(piece), self.id_of.get, self.fits
        count, last = [0] * (n + 1), [0] * (n + 1)
        for end in range(1, n + 1):
            for start in range(max(0, end - self.longest), end):
                t = id_of(piece[start:end])
                if t is not None and (not start or fits(last[start], t)):
                    count[end], last[end] = count[start] + 1, t
                    break
        return count

    def _parts(self, text: str) -> Iterator[tuple[str, bool]]:
        if self.special is None or not any(a in text for a in self.added):
            yield text, False
            return
        at = 0
        for m in self.special.finditer(text):
            if m.start() > at:
                yield text[at : m.start()], False
            yield m.group(), True
            at = m.end()
        if at < len(text):
            yield text[at:], False

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        out = 0
        for part, special in self._parts(text):
            if special:
                out += 1
                continue
            known = self.totals
            out += sum([known[p] for p in self.split(part)])
        return out

    def _plain_prefixes(self, text: str) -> list[int]:
        """Counts at all character prefixes of a text without special strings."""
        out, done, at = [0], 0, 0
        before, before_start, before_done = "", 0, 0
        for piece in self.split(text):
            counts = self.piece_counts(piece.encode())
            if piece.lstrip(" ").isalpha() or piece.isspace() and not before.isspace():
                byte = 0
                for c in piece:
                    byte += len(c.encode())
                    out.append(done + counts[byte])
                if before.isspace() and not piece.isspace() and piece[0] == " ":
                    out[at + 1] = before_done + sum(self.totals[p] for p in self.split(before + " "))
            else:  # a shorter end may be split otherwise
                start, base = (before_start, before_done) if before.isspace() else (at, done)
                for end in range(at + 1, at + len(piece) + 1):
                    out.append(base + sum(self.totals[p] for p in self.split(text[start:end])))
            before, before_start, before_done = piece, at, done
            at += len(piece)
            done += counts[-1]
        return out

    def prefix_counts(self, text: str | None) -> np.ndarray:
        """Token counts of text[:0], text[:1], ... text (characters)."""
        out, before, base = [0], "", 0
        for part, special in self._parts(text or ""):
            if special:  # until it is whole it is ordinary text, together with what stands before
                out += [base + self.count(before + part[:k]) for k in range(1, len(part))] + [out[-1] + 1]
                before, base = "", out[-1]
            else:
                before, base = part, out[-1]
                out += [base + c for c in self._plain_prefixes(part)[1:]]
        return np.array(out, np.int32)


def longest_within(counts: np.ndarray, budget: int) -> int:
    """Characters of the longest prefix that needs ``budget`` tokens at most."""
    return int(np.flatnonzero(counts <= budget)[-1]) if budget >= 0 else 0


@lru_cache(maxsize=2)
def counter(path: str) -> PrefixCounter:
    return PrefixCounter(path)


KEPT[__name__] = counter.cache_clear


def count_documents(docs: DataFrame, path: str, limit: int = 512, with_prefixes: bool = False) -> DataFrame:
    """Every row of ``docs`` with ``n_bytes``, ``n_tokens`` and ``over_limit`` (and, if asked,
    ``prefix_tokens``: the counts of all character prefixes) added; such columns are replaced."""
    own = ["n_bytes", "n_tokens", "over_limit", *(["prefix_tokens"] if with_prefixes else [])]
    docs = docs.drop(*own)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = counter(path)
        for batch in batches:
            for part in slices(batch):
                texts = part.column("text").to_pylist()
                if with_prefixes:
                    prefixes = [c.prefix_counts(t) for t in texts]
                    n = np.array([p[-1] for p in prefixes], np.int64)
                else:
                    n = np.array([c.count(t) for t in texts], np.int64)
                arrays = [pa.array([len(t.encode()) if t else 0 for t in texts], pa.int64()), pa.array(n), pa.array(n > limit)]
                if with_prefixes:
                    arrays.append(pa.array([p.tolist() for p in prefixes], pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays([*part.columns, *arrays], [*part.schema.names, *own])
        c.totals.forget()  # a waiting worker holds the tables alone

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return docs.mapInArrow(tidy(run), f"{kinds}, n_bytes bigint, n_tokens bigint, over_limit boolean{', prefix_tokens array<int>' if with_prefixes else ''}")
