"""Repeated byte strings by distributed prefix doubling.

A byte is removed if a string of ``length`` bytes that covers it also starts anywhere else.  Positions
get names (hashes standing for ranks) of the strings that start there, of growing length: ``first``
bytes, twice that, and so on to ``length``; a position whose name is unique drops out, for then any
longer string from it is unique too.  Spark only groups runs by their first name; the offsets grow inside
the task that holds a gram's runs, until every position is unique or past the threshold.

The first names are taken at sampled positions only: each window of ``length`` bytes chooses the least
of its ``first``-byte grams (a minimizer), so equal windows choose the same gram at the same offset.
Successive windows with one choice form a run, of about forty; a run whose gram is unique in the corpus
holds no repeat, and of two runs with equal bytes every window repeats.  Only runs between these - the
gram repeats, the run doesn't - are fetched again and doubled position by position, together with one
representative of each repeated run of that gram; runs that repeat whole need no doubling.  A task settles its own equal runs beforehand, so a
passage that a third of all documents hold sends a row or two per task.

A gram with over ``crowd`` such runs isn't gathered in one task: its windows are named one by one, by
two hashes of all ``length`` bytes, and grouped by those names, without doubling.

Defined cases: null and empty texts, and those under ``length`` bytes, lose nothing; matches never
cross rows; repeated rows repeat each other, so all their windows do; a null id is an id of its own; an
empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .kernel import buffer, mix, RollingHash, signed, slices, sliding_argmin, tidy, U
from .spans import cut, doc_key, gathered, text_key
from .workspace import keep

HELD = 200_000
PIECE = 1 << 19


@dataclass(frozen=True)
class Doubling:
    length: int = 200
    first: int = 50
    crowd: int = 2_000


def _runs(data: np.ndarray, offsets: np.ndarray, d: Doubling) -> tuple[np.ndarray, ...]:
    """Row, first start (in the row), starts, gram name and content name of each run of windows."""
    if len(data) < d.length:
        z = np.zeros(0, np.int64)
        return z, z, z, z.view(np.uint64), z.view(np.uint64)
    one, two = RollingHash(data), RollingHash(data, 1)
    grams = one.grams(d.first)
    chosen = sliding_argmin(grams, d.length - d.first + 1)
    inside = np.zeros(len(data) + 1, np.int32)
    low = offsets[:-1]
    high = np.maximum(offsets[1:] - d.length + 1, low)
    np.add.at(inside, low, 1)
    np.add.at(inside, high, -1)
    start = np.flatnonzero(np.cumsum(inside[: len(chosen)]) > 0)
    if not len(start):
        z = np.zeros(0, np.int64)
        return z, z, z, z.view(np.uint64), z.view(np.uint64)
    pick = chosen[start]
    new = np.flatnonzero(np.concatenate([[True], pick[1:] != pick[:-1]]))
    first, last = start[new], start[np.append(new[1:], len(start)) - 1]
    row = np.searchsorted(offsets, first, "right") - 1
    # the content's name holds where the gram lies in it, so equal names mean equal runs of windows
    content = mix(two.spans(first, last + d.length) ^ mix((pick[new] - first).astype(np.uint64)))
    return row, first - offsets[row], last - first + 1, grams[pick[new]], content


def _pieces(data: np.ndarray, offsets: np.ndarray, length: int) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
    """The buffer, or a single long text in overlapping pieces: bytes, offsets, place of the first."""
    if len(data) <= 2 * PIECE or len(offsets) > 2:
        yield data, offsets, 0
        return
    for at in range(0, len(data), PIECE):
        part = data[at : at + PIECE + length - 1]
        yield part, np.array([0, len(part)]), at


def _settle(parts: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
    """Rows gram, content, n, k, th, start, starts: of a task's equal runs the first one stands for all
    (n counts them), and all of them go on as repeats (n is 0); adjacent repeats of a text are joined."""
    gram, content, k, th, start, starts = (np.concatenate([p[i] for p in parts]) for i in range(6))
    order = np.lexsort((content, gram))
    new = np.concatenate([[True], (gram[order][1:] != gram[order][:-1]) | (content[order][1:] != content[order][:-1])])
    lead = np.flatnonzero(new)
    count = np.diff(np.append(lead, len(order)))
    n = np.empty(len(order), np.int64)
    n[order] = np.repeat(count, count)
    stands = np.zeros(len(order), bool)
    stands[order[lead]] = True
    sure = n >= 2
    # repeats as spans of starts, joined where one ends at the next
    a = np.flatnonzero(sure)
    k2, th2, s2, e2 = k[a], th[a], start[a], start[a] + starts[a]
    by = np.lexsort((s2, th2, k2))
    k2, th2, s2, e2 = k2[by], th2[by], s2[by], e2[by]
    fresh = np.concatenate([[True], (k2[1:] != k2[:-1]) | (th2[1:] != th2[:-1]) | (s2[1:] > e2[:-1])]) if len(a) else np.zeros(0, bool)
    heads = np.flatnonzero(fresh)
    tails = np.append(heads[1:], len(by)) - 1 if len(a) else heads
    stand = np.flatnonzero(stands)
    cat = lambda x, y: pa.array(np.concatenate([x, y]))
    m = len(heads)
    apart = signed(mix(k2[heads].astype(np.uint64) ^ mix(s2[heads].astype(np.uint64))))  # deals them out evenly
    return pa.RecordBatch.from_arrays(
        [
            cat(signed(gram[stand]), apart), cat(signed(content[stand]), np.zeros(m, np.int64)), cat(n[stand], np.zeros(m, np.int64)), cat(k[stand], k2[heads]), cat(th[stand], th2[heads]),
            cat(start[stand], s2[heads]), cat(starts[stand], e2[tails] - s2[heads] if m else np.zeros(0, np.int64)),
        ],
        ["gram", "content", "n", "k", "th", "start", "starts"],
    )


def named_runs(docs: DataFrame, d: Doubling) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        n = 0
        for batch in batches:
            for part in slices(batch):
                k, th = (np.asarray(part.column(c), np.int64) for c in ("k", "th"))
                for data, offsets, at in _pieces(*buffer(part.column("text")), d.length):
                    row, start, starts, gram, content = _runs(data, offsets, d)
                    held.append((gram, content, k[row], th[row], start + at, starts))
                    n += len(row)
                if n >= HELD:
                    yield _settle(held)
                    held, n = [], 0
        if n:
            yield _settle(held)

    return docs.select(doc_key().alias("k"), text_key().alias("th"), "text").mapInArrow(tidy(run), "gram bigint, content bigint, n bigint, k bigint, th bigint, start bigint, starts bigint")


def _double(names: np.ndarray, group: np.ndarray, at: np.ndarray, have: int, length: int, mine: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Which positions' strings of ``length`` occur twice or more in their group.

    ``names`` are those of the strings of ``have`` bytes at every byte of the laid-out runs; ``at`` the
    positions asked about, ``group`` their gram's number, ``weight`` how often their run occurs."""
    alive = np.ones(len(at), bool)
    while True:
        # a name for (name here, name further on): the offset grows to twice the length, or to what is missing
        key = mix(names[at] ^ mix(group.astype(np.uint64)))
        order = np.argsort(key, kind="stable")
        key = key[order]
        new = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        total = np.add.reduceat(weight[order], new) if len(new) else np.zeros(0, np.int64)
        often = np.empty(len(at), bool)
        often[order] = np.repeat(total >= 2, np.diff(np.append(new, len(order))))
        keep_ = np.flatnonzero(alive)[often]
        alive[:] = False
        alive[keep_] = True
        at, group, weight = at[often], group[often], weight[often]
        if have >= length or not len(at):
            return alive
        step = min(have, length - have)
        far = names[step:] if step else names
        names = np.concatenate([mix(names[: len(far)] * U(0x9E3779B97F4A7C15) + mix(far + U(step))), np.zeros(len(names) - len(far), np.uint64)])
        have += step


def _found(context: list[bytes], gram: np.ndarray, starts: np.ndarray, n: np.ndarray, d: Doubling) -> np.ndarray:
    """For every window of every run, one after the other: does it occur twice in its gram's runs?"""
    size = np.array([len(c) for c in context])
    base = np.cumsum(size) - size
    names = np.zeros(int(size.sum()), np.uint64)
    for i in range(0, len(context), 1000):
        data = np.frombuffer(b"".join(context[i : i + 1000]), np.uint8)
        hashes = RollingHash(data).grams(d.first) ^ mix(RollingHash(data, 1).grams(d.first))
        names[base[i] : base[i] + len(hashes)] = hashes
    total = int(starts.sum())
    within = np.arange(total) - np.repeat(np.cumsum(starts) - starts, starts)
    at = np.repeat(base, starts) + within
    return _double(names, np.repeat(gram, starts), at, d.first, d.length, within, np.repeat(n, starts))


def repeated_starts(docs: DataFrame, d: Doubling = Doubling()) -> DataFrame:
    """k, th, start, starts: runs of positions whose strings of ``length`` bytes also start elsewhere."""
    runs = named_runs(docs, d).repartition("gram")
    same, all_ = Window.partitionBy("gram", "content").orderBy("k", "th", "start"), Window.partitionBy("gram")
    whole = same.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    marked = runs.withColumns({"rn": F.row_number().over(same), "copies": F.sum("n").over(whole)})
    marked = marked.withColumns({"total": F.sum("n").over(all_), "kinds": F.sum(F.when(F.col("rn") == 1, 1).otherwise(0)).over(all_)})
    marked = keep(marked.where("n = 0 or total > 1").drop("content", "total"), "runs")
    sure = marked.where("n = 0 or copies > 1 and n = 1").select("k", "th", "start", "starts")
    # single runs of a repeated gram, and one representative of each repeated run beside them
    asked = marked.where("n > 0 and kinds > 1 and rn = 1")
    asked = asked.groupBy("k", "th").agg(F.collect_list(F.struct("gram", F.least("copies", F.lit(2)).alias("copies"), "kinds", "start", "starts")).alias("asked"))
    texts = docs.select(doc_key().alias("k"), text_key().alias("th"), "text").join(asked, ["k", "th"])

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole_ in batches:
            for i in range(0, whole_.num_rows, 256):
                batch, rows = whole_.slice(i, 256), []
                for k, th, text, want in zip(*(batch.column(c).to_pylist() for c in ("k", "th", "text", "asked"))):
                    raw = (text or "").encode()
                    rows += [(w["gram"], w["kinds"], w["copies"], k, th, w["start"], w["starts"], raw[w["start"] : w["start"] + w["starts"] + d.length - 1]) for w in want]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(x, pa.binary() if j == 7 else pa.int64()) for j, x in enumerate(zip(*rows))], ["gram", "kinds", "copies", "k", "th", "start", "starts", "context"])

    contexts = keep(texts.mapInArrow(tidy(fetch), "gram bigint, kinds bigint, copies bigint, k bigint, th bigint, start bigint, starts bigint, context binary"), "contexts")

    def spans(flags: np.ndarray, rows: list[tuple]) -> Iterator[tuple]:
        at = 0
        for _, copies, k, th, start, starts, _ in rows:
            own = flags[at : at + starts]
            at += starts
            if copies > 1 or not own.any():
                continue
            edge = np.flatnonzero(np.diff(np.concatenate([[0], own.astype(np.int8), [0]])))
            for a, b in zip(edge[::2].tolist(), edge[1::2].tolist()):
                yield k, th, start + a, b - a

    def double(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def answer(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
            _, number = np.unique([r[0] for r in rows], return_inverse=True)
            flags = _found([r[6] for r in rows], number, np.array([r[5] for r in rows]), np.array([r[1] for r in rows]), d)
            out = list(spans(flags, rows))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*out)], ["k", "th", "start", "starts"])

        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in ("gram", "copies", "k", "th", "start", "starts", "context"))):
                if len(held) >= 2000 and row[0] != held[-1][0]:
                    yield from answer(held)
                    held = []
                held.append(row)
        if held:
            yield from answer(held)

    small = contexts.where(F.col("kinds") <= d.crowd).repartition("gram").sortWithinPartitions("gram")
    found = small.mapInArrow(tidy(double), "k bigint, th bigint, start bigint, starts bigint")

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for copies, k, th, start, starts, raw in zip(*(batch.column(c).to_pylist() for c in ("copies", "k", "th", "start", "starts", "context"))):
                data = np.frombuffer(raw, np.uint8)
                one, two = (signed(RollingHash(data, which).grams(d.length)) for which in (0, 1))
                columns = [one, two, *(np.full(starts, x, np.int64) for x in (copies, k, th)), start + np.arange(starts)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["a", "b", "copies", "k", "th", "start"])

    crowded = contexts.where(F.col("kinds") > d.crowd).mapInArrow(tidy(windows), "a bigint, b bigint, copies bigint, k bigint, th bigint, start bigint")
    twice = crowded.groupBy("a", "b").agg(F.sum("copies").alias("n")).where("n > 1").drop("n")
    late = crowded.where("copies = 1").join(twice, ["a", "b"]).select("k", "th", "start", F.lit(1).cast("bigint").alias("starts"))
    return sure.unionByName(found).unionByName(late)


def drop_repeated_bytes(docs: DataFrame, d: Doubling = Doubling(), with_text: bool = True) -> DataFrame:
    """Every row of ``docs`` without its repeated bytes (see ``spans.cut`` for the columns)."""
    spans = repeated_starts(docs, d).select("k", "th", "start", (F.col("starts") + (d.length - 1)).alias("length"))
    return cut(docs, gathered(spans), with_text)

