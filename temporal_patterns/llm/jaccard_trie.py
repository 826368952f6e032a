"""N-gram Jaccard join with prefix trees, and the classes it links documents into.

A document's set holds the 64-bit hashes of its distinct word shingles in one global order (by
hash).  Two documents link when intersection / union reaches ``threshold`` (a ratio of integers,
tested in integers).  The join is exact.

*Who can link.*  Sets are cut by hash range into ``k`` parts, where ``k`` exceeds the largest symmetric
difference that two linked sets of that size band can have; so two linked sets agree on a whole part,
and a signature (band, part, content) is held by both.  A set goes by its own band and the next
one.  More parts than needed leave room for empty ones: only a set with more empty parts than that
also sends those.  Only sets that share signatures enough are built again; equal ones become one; then those with too
many shingles that are in no other set are out, too.

*Joining.*  The sets left are put in a global order, the rarest shingle first.  Two sets that link have a first
common shingle, and from there on each has as many shingles as their intersection takes at least: so only a
set's prefix is posted, with its place, and only sets with one posting in common and enough after it are
candidates.  Inside a posting the set whose shingles are the most common ones is the hub (a star; no pairs are
listed); each set is linked to the hub it meets most if they are similar, and components are formed; then once more
with other hubs.  Of what is left, pairs of different components in one posting are tested, as far as the places
allow a link.  Similarity is decided in a prefix
tree over a block's ordered sets: the probe walks it once, shares the overlap of common prefixes, and
leaves a subtree as soon as the overlap so far plus the most that can follow falls short.

Joins of texts and sets are sort-merge joins by hint: no side has a size bound, so the plan is one at every
size.

Defined cases: null and blank texts have an empty set, link with nothing and are their own component;
equal sets link (a task's equal sets are one); repeated rows get equal answers; a null id takes part in
no link; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .components import components
from .kernel import mix, packed, PACKED, signed, slices, tidy, U, unsigned, Words
from .workspace import buckets, forget, forget_dealt, keep, keep_dealt

BLOCK = 128
GROUP = 4096
HELD = 400_000
STRIDE = 64


@dataclass(frozen=True)
class Likeness:
    """Shingles of ``size`` words, similar from ``num / den`` on."""

    size: int = 5
    num: int = 80
    den: int = 100

    def overlap(self, a: int, b: int) -> int:
        """The least intersection of linked sets of these sizes."""
        return -(-self.num * (a + b) // (self.num + self.den))


@lru_cache(maxsize=8)
def _bands(num: int, den: int) -> tuple[np.ndarray, list[int], list[int]]:
    """First sizes of the bands, and of each band the parts and how many of them may be empty."""
    first, parts, spare = [1], [], []
    while first[-1] < 1 << 40:
        top = first[-1] * den // num
        differ = 2 * top * (den - num) // (den + num)
        room = 1 + differ // 8 if differ else 0
        parts.append(differ + 1 + room)
        spare.append(room)
        first.append(top + 1)
    return np.array(first, np.int64), parts, spare


def _least_shared(shingles: np.ndarray, further: int, like: Likeness) -> int:
    """Signatures, for one band, that an ordered set shares at least with any it links with: all parts but
    the largest difference agree, and of these only parts that are empty in both may go without signature."""
    first, parts, spare = _bands(like.num, like.den)
    b = int(np.searchsorted(first, len(shingles), "right")) - 1 + further
    part = ((shingles >> U(32)) * U(parts[b])) >> U(32)
    empty = parts[b] - 1 - int(np.count_nonzero(part[1:] != part[:-1]))
    return max(1, 1 + spare[b] - empty)


def signatures(shingles: np.ndarray, like: Likeness) -> list[np.ndarray]:
    """Signatures of an ordered, non-empty set, for its band and the next."""
    first, parts, spare = _bands(like.num, like.den)
    band = int(np.searchsorted(first, len(shingles), "right")) - 1
    top = shingles >> U(32)
    mixed = np.concatenate([[U(0)], np.cumsum(mix(shingles + U(0x51ED27))).astype(np.uint64)])
    out = []
    for b in (band, band + 1):
        k = parts[b]
        part = (top * U(k)) >> U(32)
        edge = np.searchsorted(part, np.arange(k + 1, dtype=np.uint64))
        filled = edge[1:] > edge[:-1]
        use = filled if k - int(filled.sum()) <= spare[b] else np.ones(k, bool)
        which = np.flatnonzero(use)
        content = mixed[edge[1:][which]] - mixed[edge[:-1][which]]
        out.append(mix(content ^ mix((which + (b << 40)).astype(np.uint64))))
    return out


def shingle_sets(texts: pa.Array, size: int) -> list[np.ndarray]:
    """Ordered distinct shingle hashes of each text."""
    h, at = Words(texts, lower=True).shingles(size)
    return [np.unique(h[a:b]) for a, b in zip(at[:-1], at[1:])]


def set_sizes(docs: DataFrame, size: int) -> DataFrame:
    """Every row of ``docs`` (doc_id, text) as doc_id, n_shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch):
                n = [len(s) for s in shingle_sets(part.column("text"), size)]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(n, pa.int64())], ["doc_id", "n_shingles"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(tidy(run), "doc_id bigint, n_shingles bigint")


ENTRY, COUNT, SAME = 0, 1, 2


def _enough_shared(rows: DataFrame, entries: Callable[[pa.RecordBatch], Iterator[tuple]]) -> DataFrame:
    """kind, a, b: ids that share as many of their keys as they need (COUNT, id, 0), and equal sets (SAME, id, id).

    ``entries`` gives of each slice of rows: keys, their ids, what each id needs at least (as an array beside the
    keys), and pairs of equal ones.  A task first settles its own repeats - a key that it has twice is shared for
    certain and goes on as one row - so a key that a third of all rows hold sends one row per task.  Rows travel
    packed by range of the key, counts by range of the id."""
    parts = 4 * buckets(rows.sparkSession)

    def counted(ids: np.ndarray, needs: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
        """What is known of each id, packed."""
        key, ids, needs, n = summed(mix(ids.view(U)), ids, needs, n)
        return packed(COUNT, parts // 4, key, np.stack([ids, needs], axis=1), n)

    def summed(key: np.ndarray, ids: np.ndarray, needs: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, ...]:
        order = np.argsort(key, kind="stable")
        key = key[order]
        at = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        return key[at], ids[order][at], np.minimum.reduceat(needs[order], at), np.add.reduceat(n[order], at)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        n = 0

        def settle() -> Iterator[pa.RecordBatch]:
            key, ids, needs = (np.concatenate(x) for x in zip(*held))
            order = np.argsort(key, kind="stable")
            key, ids, needs = key[order], ids[order], needs[order]
            new = np.concatenate([[True], key[1:] != key[:-1]])
            shared = ~new | np.append(~new[1:], False)
            if shared.any():
                yield counted(ids[shared], needs[shared], np.ones(int(shared.sum()), np.int64))
            yield packed(ENTRY, parts, key[new], ids[new], np.where(shared[new], -1, needs[new]))

        for batch in batches:
            for key, ids, needs, same in entries(batch):
                if same:
                    u, v = np.array(same, np.int64).T
                    order = np.argsort(u.view(U))
                    yield packed(SAME, parts, u.view(U)[order], v[order], v[order])
                free = needs <= 0
                if free.any():  # these need no partner
                    none = np.zeros(int(free.sum()), np.int64)
                    yield counted(ids[free], none, none)
                if len(key):
                    held.append((key, ids, np.maximum(needs, 0)))
                    n += len(key)
                if n >= HELD:
                    yield from settle()
                    held, n = [], 0
        if n:
            yield from settle()

    def entries_of(batches: Iterator[pa.RecordBatch], kind: int, passed: list[pa.RecordBatch]) -> Iterator[list[bytes]]:
        """Columns of what lies in each block, of that kind; other rows go to ``passed``."""
        now, held = None, []
        for batch in batches:
            kinds, blocks = (np.asarray(batch.column(c)) for c in ("kind", "block"))
            columns = [batch.column(f"c{j}") for j in range(3)]
            if (kinds != kind).any():
                passed.append(batch.filter(pa.array(kinds != kind)))
            for i in np.flatnonzero(kinds == kind).tolist():
                if blocks[i] != now:
                    if held:
                        yield [b"".join(c) for c in zip(*held)]
                    now, held = blocks[i], []
                held.append([c[i].as_py() for c in columns])
        if held:
            yield [b"".join(c) for c in zip(*held)]

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        passed: list[pa.RecordBatch] = []
        found, size = [], 0

        def give() -> pa.RecordBatch:
            ids, needs = (np.concatenate(x) for x in zip(*found))
            return counted(ids, needs, np.ones(len(ids), np.int64))

        for block in entries_of(batches, ENTRY, passed):
            key, ids, needs = (np.frombuffer(c, kind) for c, kind in zip(block, (U, np.int64, np.int64)))
            order = np.argsort(key, kind="stable")
            key, ids, needs = key[order], ids[order], needs[order]
            new = np.concatenate([[True], key[1:] != key[:-1]])
            shared = (~new | np.append(~new[1:], False)) & (needs >= 0)
            if shared.any():
                found.append((ids[shared], needs[shared]))
                size += len(found[-1][0])
            if size > HELD:
                yield give()
                found, size = [], 0
            while passed:
                yield passed.pop()
        if found:
            yield give()
        yield from passed

    def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        passed: list[pa.RecordBatch] = []

        def pairs() -> Iterator[pa.RecordBatch]:
            while passed:
                for u, v in zip(*(passed[-1].column(c).to_pylist() for c in ("c0", "c1"))):
                    u, v = np.frombuffer(u, np.int64), np.frombuffer(v, np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(u), SAME, np.int32)), pa.array(u), pa.array(v)], ["kind", "a", "b"])
                passed.pop()

        for block in entries_of(batches, COUNT, passed):
            key, what, n = (np.frombuffer(c, kind) for c, kind in zip(block, (U, np.int64, np.int64)))
            _, ids, needs, n = summed(key, *np.ascontiguousarray(what.reshape(-1, 2).T), n)
            ids = ids[n >= needs]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), COUNT, np.int32)), pa.array(np.ascontiguousarray(ids)), pa.array(np.zeros(len(ids), np.int64))], ["kind", "a", "b"])
            yield from pairs()
        yield from pairs()

    dealt = rows.mapInArrow(tidy(deal), PACKED).repartition("block").sortWithinPartitions("block").mapInArrow(tidy(gather), PACKED)
    return dealt.repartition("block").sortWithinPartitions("block").mapInArrow(tidy(decide), "kind int, a bigint, b bigint")


def _ids(found: DataFrame, name: str) -> DataFrame:
    """Of ``_enough_shared``: the ids that share enough, as a column of that name."""
    return found.where(F.col("kind") == COUNT).select(F.col("a").alias(name))


def _signed_documents(docs: DataFrame, like: Likeness) -> DataFrame:
    """Documents by the signatures of their sets; a task's equal sets are one."""

    def entries(batch: pa.RecordBatch) -> Iterator[tuple]:
        known: dict[tuple, int] = {}
        for part in slices(batch):
            same, keys, ids, needs = [], [], [], []
            for i, s in zip(part.column("doc_id").to_pylist(), shingle_sets(part.column("text"), like.size)):
                if i is None or not len(s):
                    continue
                hub = known.setdefault(digest(s), i)
                if hub != i:
                    same.append((i, hub))
                    continue
                keys.append(np.concatenate(signatures(s, like)))
                ids.append(i)
                needs.append(min(_least_shared(s, b, like) for b in (0, 1)))
            size = [len(k) for k in keys]
            none = np.zeros(0, U)
            yield np.concatenate(keys) if keys else none, np.repeat(np.array(ids, np.int64), size), np.repeat(np.array(needs, np.int64), size), same

    return _enough_shared(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), entries)


def digest(s: np.ndarray) -> tuple[int, int, int]:
    """Size and two hashes of a set."""
    return len(s), int(np.bitwise_xor.reduce(mix(s)).view(np.int64)), int(np.sum(mix(s ^ U(0xA5A5)), dtype=U).view(np.int64))


def _sets_of(docs: DataFrame, wanted: DataFrame, like: Likeness) -> DataFrame:
    """uid, id, n, d1, d2 (digests), s (the ordered set) of the wanted documents; uid stands for id and set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, seen = None, set()
        for batch in batches:
            for part in slices(batch):
                rows, sets = [], []
                for i, s in zip(part.column("doc_id").to_pylist(), shingle_sets(part.column("text"), like.size)):
                    if not len(s):
                        continue
                    if i != last:
                        last, seen = i, set()
                    key = digest(s)
                    if key not in seen:  # a repeated row
                        seen.add(key)
                        rows.append((i, *key))
                        sets.append(s)
                if rows:
                    i, n, d1, d2 = np.array(rows, np.int64).T
                    uid = signed(mix(unsigned(i) * U(0x9E3779B97F4A7C15) + mix(unsigned(d1))))
                    at = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
                    arrays = [pa.array(np.ascontiguousarray(x)) for x in (uid, i, n, d1, d2)]
                    yield pa.RecordBatch.from_arrays([*arrays, pa.ListArray.from_arrays(pa.array(at), pa.array(signed(np.concatenate(sets))))], ["uid", "id", "n", "d1", "d2", "s"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    rows = rows.join(wanted.hint("merge"), "doc_id", "left_semi")
    return rows.mapInArrow(tidy(run), "uid bigint, id bigint, n bigint, d1 bigint, d2 bigint, s array<bigint>")


def _sets_in(column: pa.Array) -> list[np.ndarray]:
    at = np.asarray(column.offsets)
    flat = unsigned(np.asarray(column.values))
    return [flat[a:b] for a, b in zip(at[:-1].tolist(), at[1:].tolist())]


def _by_shingles(sets: DataFrame, like: Likeness) -> DataFrame:
    """Of sets (uid, n, s): those of whose shingles so few are in no other set that a link is possible.

    Every other shingle (by its lowest bit) is asked about: what of them stands alone counts against the set."""

    def entries(batch: pa.RecordBatch) -> Iterator[tuple]:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            asked = [s[(s & U(1)) == 1] for s in _sets_in(part.column("s"))]
            n = np.asarray(part.column("n"))
            size = np.array([len(a) for a in asked])
            needs = size - (n - -(-like.num * n // like.den))
            ids = np.asarray(part.column("uid"))
            # a set none of whose shingles are asked about has no key, but needs none
            lone = np.flatnonzero(size == 0)
            yield np.concatenate([*asked, np.zeros(0, U)]), np.repeat(ids, size), np.repeat(needs, size), []
            if len(lone):
                yield np.zeros(0, U), ids[lone], np.zeros(len(lone), np.int64), []

    return _ids(_enough_shared(sets.select("uid", "n", "s"), entries), "uid")


def _prefixes(sets: DataFrame, like: Likeness) -> DataFrame:
    """h, uid, id, n, rest, score of the shingles in each set's prefix that are in other sets too.

    The global order is by number of sets, the rarest first (ties by hash), so those of one set alone, which lead
    to nobody, come first.  ``rest`` counts a set's shingles from this one on: two sets that link have in their
    first common shingle a rest each of at least their least intersection.  ``score`` is how common a set's
    shingles are on average: high in the middle of a group of near copies."""
    rows = sets.select("uid", F.explode("s").alias("h"))
    common = rows.groupBy("h").agg(F.count("*").alias("df")).where("df > 1")
    per = rows.join(common.hint("merge"), "h").groupBy("uid").agg(F.sort_array(F.collect_list(F.struct("df", "h"))).alias("e"), F.sum("df").alias("score"))
    per = per.join(sets.select("uid", "id", "n").hint("merge"), "uid")
    least = F.ceil(F.col("n") * like.num / F.lit(like.den))
    per = per.withColumn("size", F.size("e")).where(F.col("size") >= least)
    per = per.withColumn("e", F.slice("e", F.lit(1), F.greatest(F.col("size") - least + 1, F.lit(0)).cast("int")))
    per = per.select("uid", "id", "n", "size", (F.col("score") / F.col("n")).alias("score"), F.posexplode("e").alias("at", "x"))
    return per.select(F.col("x.h").alias("h"), "uid", "id", "n", (F.col("size") - F.col("at")).cast("long").alias("rest"), "score")


def _can_link(like: Likeness, n: Column, rest: Column, n2: Column, rest2: Column) -> Column:
    return F.least(rest, rest2) >= F.ceil((n + n2) * like.num / F.lit(like.num + like.den))


class PrefixTree:
    """Ordered sets in a trie whose edges are runs of shingles.

    ``sets`` come in lexicographic order; a node is a run of sets that agree up to ``depth``.
    """

    def __init__(self, sets: list[np.ndarray]):
        self.order = sorted(range(len(sets)), key=lambda i: sets[i].byteswap().tobytes())
        self.sets = [sets[i] for i in self.order]
        self.common = [0]
        for a, b in zip(self.sets, self.sets[1:]):
            n = min(len(a), len(b))
            differ = a[:n] != b[:n]
            self.common.append(int(differ.argmax()) if differ.any() else n)

    def similar(self, probe: np.ndarray, like: Likeness, skip: np.ndarray | None = None) -> list[int]:
        """Numbers (as given) of the sets that link with ``probe``; ``skip`` marks sets not wanted."""
        out = []
        n = len(probe)
        saved: list[tuple[int, int]] = [(0, 0)]  # (depth, overlap) along the path to the set before
        dead = 1 << 62  # depth at which the branch was left
        for k, s in enumerate(self.sets):
            depth = self.common[k]
            if depth >= dead:
                continue  # still under the branch that was left
            dead = 1 << 62
            while saved[-1][0] > depth:
                saved.pop()
            if skip is not None and skip[self.order[k]]:
                continue
            m = len(s)
            need = like.overlap(m, n)
            if need > min(m, n):
                continue
            at, have = saved[-1]
            step = STRIDE
            failed = False
            while at < m:
                stop = min(m, at + step)
                run = s[at:stop]
                place = np.searchsorted(probe, run)
                place_ok = place < n
                have += int(np.count_nonzero(probe[np.minimum(place, n - 1)] == run) if place_ok.all() else np.count_nonzero(probe[place[place_ok]] == run[place_ok]))
                at = stop
                ahead = n - int(np.searchsorted(probe, run[-1], "right"))
                if have + min(m - at, ahead) < need:
                    failed = True
                    # any set below has this prefix, and a linked one shares its part of the larger set
                    if have + ahead < max(like.overlap(at, n), -(-like.num * n // like.den)):
                        dead = at
                    break
                saved.append((at, have))
                step *= 2
            if not failed and have >= need:
                out.append(self.order[k])
        return out


def _linked_stars(pairs: DataFrame, sets: DataFrame, like: Likeness) -> DataFrame:
    """Ids (u, v) of the pairs of sets (u, hub v) that are similar: a hub probes the tree of its candidates, block by block."""
    salts = 64
    members = pairs.join(sets.select(F.col("uid").alias("u"), "id", "s").hint("merge"), "u").select("v", F.pmod(F.xxhash64("u"), F.lit(salts)).alias("salt"), F.lit(1).alias("kind"), "id", "s")
    hubs = members.select("v", "salt").distinct().join(sets.select(F.col("uid").alias("v"), "id", "s").hint("merge"), "v").select("v", "salt", F.lit(0).alias("kind"), "id", "s")
    rows = members.unionByName(hubs).repartition("v", "salt").sortWithinPartitions("v", "salt", "kind")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, probe, hub, ids, sets_, found = None, None, None, [], [], []

        def answer() -> None:
            if ids:
                tree = PrefixTree(sets_)
                found.extend((ids[k], hub) for k in tree.similar(probe, like))
                ids.clear()
                sets_.clear()

        for batch in batches:
            for v, salt, kind, i, s in zip(*(batch.column(c).to_pylist() for c in ("v", "salt", "kind", "id")), _sets_in(batch.column("s"))):
                if (v, salt) != key:
                    answer()
                    key = v, salt
                if kind == 0:
                    probe, hub = s.copy(), i
                else:
                    ids.append(i)
                    sets_.append(s.copy())
                    if len(ids) >= BLOCK:
                        answer()
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*found)], ["u", "v"])
                found.clear()
        answer()
        if found:
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*found)], ["u", "v"])

    return rows.mapInArrow(tidy(run), "u bigint, v bigint")


def _open_rows(prefixes: DataFrame, labels: DataFrame, score: Column) -> DataFrame:
    """``prefixes`` with their component, of the shingles that sets of several components have; with the hub of
    each (uid, n, rest, component), the one of the highest score, and the number of rows."""
    named = prefixes.join(labels.withColumnRenamed("node", "id").hint("merge"), "id", "left")
    named = named.withColumn("component", F.coalesce("component", "id"))
    groups = named.groupBy("h").agg(
        F.min("component").alias("low"), F.max("component").alias("high"), F.count("*").alias("holders"),
        F.max(F.struct(score.alias("score"), "uid", "component", "n", "rest")).alias("hub"),
    )
    return named.join(groups.where("low < high").drop("low", "high").hint("merge"), "h")


def _nearest_hubs(rows: DataFrame, like: Likeness) -> DataFrame:
    """u, v: for each set the hub of another component that it meets most often, if they can link."""
    hub = lambda c: F.col(f"hub.{c}")
    met = rows.where((F.col("component") != hub("component")) & _can_link(like, F.col("n"), F.col("rest"), hub("n"), hub("rest")))
    met = met.groupBy(F.col("uid").alias("u"), hub("uid").alias("v")).agg(F.count("*").alias("met"), F.max("hub.score").alias("score"))
    return met.groupBy("u").agg(F.max(F.struct("met", "score", "v")).alias("m")).select("u", F.col("m.v").alias("v"))


def _left_over(rows: DataFrame, like: Likeness) -> DataFrame:
    """u, v: all pairs of sets of different components that can link by a shingle they have in common.

    A shingle's sets meet in blocks of ``GROUP``, and pairs of blocks where they are more."""
    blocks = F.ceil(F.col("holders") / GROUP).cast("int")
    rows = rows.select("h", "uid", "component", "n", "rest", blocks.alias("blocks"), F.pmod(F.xxhash64("uid"), blocks).cast("int").alias("block"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.select("h", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block", "uid", "component", "n", "rest")
    rows = rows.repartition("h", "low", "high").sortWithinPartitions("h", "low", "high")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        now = None
        out: set[tuple[int, int]] = set()

        def answer() -> None:
            uid, comp, n, rest, block, low, high = np.concatenate(held, axis=1)
            names, which, size = np.unique(comp, return_inverse=True, return_counts=True)
            if len(names) < 2:
                return
            order = np.argsort(size[which] * -1, kind="stable")  # those of the largest component first
            uid, comp, n, rest, block = (x[order] for x in (uid, comp, n, rest, block))
            apart = low[0] != high[0]  # pairs inside a block are met where it stands alone
            for k in range(int(size.max()), len(uid)):
                need = -(-like.num * (n[:k] + n[k]) // (like.num + like.den))
                fits = (np.minimum(rest[:k], rest[k]) >= need) & (comp[:k] != comp[k])
                if apart:
                    fits &= block[:k] != block[k]
                out.update((max(x, y), min(x, y)) for x in uid[:k][fits].tolist() for y in [int(uid[k])])

        def give() -> Iterator[pa.RecordBatch]:
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*out)], ["u", "v"])
                out.clear()

        for batch in batches:
            columns = np.array([np.asarray(batch.column(c)).astype(np.int64) for c in ("h", "uid", "component", "n", "rest", "block", "low", "high")])
            keys = columns[[0, 6, 7]]
            cuts = np.flatnonzero((keys[:, 1:] != keys[:, :-1]).any(axis=0)) + 1
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), columns.shape[1]]):
                if a == b:
                    continue
                key = tuple(keys[:, a].tolist())
                if key != now:
                    if held:
                        answer()
                    now, held = key, []
                held.append(columns[1:, a:b])
            if len(out) > HELD:
                yield from give()
        if held:
            answer()
        yield from give()

    return rows.mapInArrow(tidy(run), "u bigint, v bigint").distinct()


def link_classes(docs: DataFrame, like: Likeness = Likeness()) -> DataFrame:
    """node, component of every document that links with another one."""
    dealt = keep(_signed_documents(docs, like), "shared-signatures")
    sets = keep(_sets_of(docs, _ids(dealt, "doc_id"), like), "wanted-sets")
    # equal sets are linked to the one of least id, which alone goes on
    first = sets.groupBy("d1", "d2", "n").agg(F.min(F.struct("id", "uid")).alias("first"))
    equal = sets.select("id", "d1", "d2", "n").join(first.hint("merge"), ["d1", "d2", "n"]).select(F.col("id").alias("u"), F.col("first.id").alias("v"))
    equal = equal.unionByName(dealt.where(F.col("kind") == SAME).select(F.col("a").alias("u"), F.col("b").alias("v")))
    single = sets.select("uid", "id", "n", "s").join(first.select("first.uid").hint("merge"), "uid", "left_semi")
    likely, table = keep_dealt(single.join(_by_shingles(single, like).hint("merge"), "uid", "left_semi"), "sets", "uid")
    prefixes = keep(_prefixes(likely, like), "prefixes")
    links = keep(equal.where("u <> v"), "links")
    forget(dealt, sets)
    labels = components(links)
    for score in (F.col("score"), F.xxhash64("uid").cast("double"), None):
        rows = keep(_open_rows(prefixes, labels, F.col("score") if score is None else score), "open-prefixes")
        candidates = _left_over(rows, like) if score is None else _nearest_hubs(rows, like)
        found = keep(_linked_stars(candidates, likely, like), "found")
        more = not found.isEmpty()
        if more:
            links = keep(labels.select(F.col("node").alias("u"), F.col("component").alias("v")).unionByName(found).where("u <> v"), "links")
            labels = components(links)
        forget(rows, found)
    forget(prefixes)
    forget_dealt(likely, table)
    return labels


def document_classes(docs: DataFrame, like: Likeness = Likeness()) -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    linked = link_classes(docs, like).select(F.col("node").alias("doc_id"), "component")
    sized = set_sizes(docs, like.size)
    return sized.join(linked, "doc_id", "left").select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))


def keep_one(docs: DataFrame, like: Likeness = Likeness()) -> DataFrame:
    """``docs`` with one document of each class, the one with the least id; documents that link with
    nothing (also those without text or id) stay.  Repeated rows of one id stay together."""
    others = link_classes(docs, like).where("component < node").select(F.col("node").alias("doc_id"))
    return docs.join(others, "doc_id", "left_anti")
