"""Substring deduplication by lines.

Units are the lines of a text; a longer line is cut into pieces at places that its words choose: a gap
between two words is a cut if a hash of the two is the least among the gaps up to ``REACH`` before and after, in the same
line.  So a passage that stands in the middle of different lines has the same pieces in all of them, but
for the first and the last, and no piece of a line has fewer than ``REACH`` + 1 words.

A unit is normalised (A-Z to lower case, blanks between words to one, trimmed), its 128-bit digest is grouped
over the whole corpus, the occurrence of least rank (doc_id, then byte offset) stays, and others are repeats.
Repeats that follow one another in a text, with ``min_words`` words together (25) or more, are removed with the blanks after them;
the removed spans are returned as offsets in the original bytes.  Shorter ones are left alone: such lines
(licences, notices, captions) repeat in documents that have nothing else in common.

A task first settles its own repeats, so a line that a third of all documents hold sends one row per task.

Defined cases: null, empty and blank texts have no units; repeated rows (same id, same text) are
one document and keep the same lines; a null id ranks first; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernel import _BASES, mix, signed, slices, tidy, U, Words
from .spans import cut, doc_key, text_key
from .workspace import buckets

MIN_WORDS = 25
REACH = 3
HELD = 400_000


def _power_sums(h: np.ndarray, base: int) -> tuple[np.ndarray, np.ndarray]:
    bits = max(1, int(len(h)).bit_length())
    power, inverse = np.ones(1 << bits, np.uint64), np.ones(1 << bits, np.uint64)
    for b in range(bits):
        power[1 << b : 2 << b] = power[: 1 << b] * U(pow(base, 1 << b, 1 << 64))
        inverse[1 << b : 2 << b] = inverse[: 1 << b] * U(pow(base, -(1 << b), 1 << 64))
    return np.concatenate([[U(0)], np.cumsum(h * power[: len(h)], dtype=np.uint64)]), inverse


def _cuts(w: Words, h: np.ndarray) -> np.ndarray:
    """Whether a unit ends after each word."""
    breaks = np.cumsum(w.data == 10)
    line_end = np.append((breaks[w.start[1:]] != breaks[w.start[:-1]]) | (w.row[1:] != w.row[:-1]), True)
    gap = mix(h * U(_BASES[0]) + mix(np.append(h[1:], U(0)))) | U(1)
    gap[line_end] = 0
    least = ~line_end
    for far in range(1, REACH + 1):
        least[far:] &= gap[far:] < gap[:-far]
        least[:far] &= False
        least[:-far] &= gap[:-far] <= gap[far:]
    return line_end | least


def line_units(texts: pa.Array) -> tuple[np.ndarray, ...]:
    """Two digests, row, first byte in the row, bytes (up to the next unit), and words of each unit."""
    w = Words(texts, lower=True)
    none = np.zeros(0, np.int64)
    if not len(w.start):
        return none.view(U), none.view(U), none, none, none, none
    h = w.hashes()
    last = np.flatnonzero(_cuts(w, h))
    first = np.append(0, last[:-1] + 1)
    row = w.row[first]
    starts = w.start[first]
    ends = np.append(starts[1:], len(w.data))
    final = np.append(row[1:] != row[:-1], True)
    ends[final] = w.offsets[row[final] + 1]
    digests = []
    for base in _BASES:
        sums, inverse = _power_sums(mix(h ^ U(base)), base)
        digests.append(mix((sums[last + 1] - sums[first]) * inverse[first] + (last + 1 - first).astype(U)))
    return digests[0], digests[1], row, starts - w.offsets[row], ends - starts, last + 1 - first


def _in_order(parts: list[tuple[np.ndarray, ...]]) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Columns (d1, d2, k, th, start, ...) in order, each row once; whether a row is the first of its unit, and whether others are."""
    columns = [np.concatenate(x) for x in zip(*parts)]
    order = np.lexsort(tuple(reversed(columns[:5])))
    columns = [x[order] for x in columns]
    same = np.concatenate([[False], (columns[0][1:] == columns[0][:-1]) & (columns[1][1:] == columns[1][:-1])])
    again = same.copy()  # repeated rows
    for x in columns[2:5]:
        again[1:] &= x[1:] == x[:-1]
    columns, same = [x[~again] for x in columns], same[~again]
    return columns, ~same, same | np.append(same[1:], False)


def _to_documents(blocks: int, parts: list[tuple[np.ndarray, ...]]) -> tuple[pa.Array, pa.Array]:
    """Rows k, th, start, length, words, first (1: this occurrence stays), packed by block of the document."""
    table = np.stack([np.concatenate(x).astype(np.int64) for x in zip(*parts)], axis=1)
    return _by_block((mix(mix(table[:, 0].view(U).copy()) ^ table[:, 1].view(U)) % U(blocks)).astype(np.int32), table)


def _by_block(block: np.ndarray, table: np.ndarray) -> tuple[pa.Array, pa.Array]:
    order = np.argsort(block, kind="stable")
    block, table = block[order], np.ascontiguousarray(table[order])
    at = np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]]))
    ends = pa.array((np.append(at, len(block)) * table.shape[1] * 8).astype(np.int32))
    return pa.array(block[at]), pa.Array.from_buffers(pa.binary(), len(at), [None, ends.buffers()[1], pa.py_buffer(table)])


def _tables(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[np.ndarray]:
    """What lies in each block, of rows (block, units) in order of block."""
    now, held = None, []
    for batch in batches:
        for block, units in zip(batch.column("block").to_pylist(), batch.column("units")):
            if block != now:
                if held:
                    yield np.concatenate(held)
                now, held = block, []
            held.append(np.frombuffer(units.as_buffer(), np.int64).reshape(-1, width).copy())
    if held:
        yield np.concatenate(held)


def repeated_runs(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """k, th, starts, lengths of the runs to be removed, and n_repeated: bytes of all runs of units that stand
    elsewhere too, those that stay included; of documents that have any."""
    blocks = 4 * buckets(docs.sparkSession)
    names = ["kind", "block", "units"]

    def rows_of(kind: int, packed: tuple[pa.Array, pa.Array]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(packed[0]), kind, np.int32)), *packed], names)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        n = 0

        def settle() -> Iterator[pa.RecordBatch]:
            columns, first, shared = _in_order(held)
            # what is not the first here is a repeat for certain; the first goes on and may have others elsewhere
            gone = ~first
            if gone.any():
                yield rows_of(1, _to_documents(blocks, [(*(x[gone] for x in columns[2:]), np.zeros(int(gone.sum()), np.int64))]))
            block = ((columns[0] >> U(32)) * U(blocks) >> U(32)).astype(np.int32)
            yield rows_of(0, _by_block(block[first], np.stack([signed(columns[0]), signed(columns[1]), *columns[2:], shared.astype(np.int64)], axis=1)[first]))

        for batch in batches:
            for part in slices(batch):
                d1, d2, row, start, length, words = line_units(part.column("text"))
                k, th = (np.asarray(part.column(c), np.int64)[row] for c in ("k", "th"))
                held.append((d1, d2, k, th, start, length, words))
                n += len(row)
                if n >= HELD:
                    yield from settle()
                    held, n = [], 0
        if n:
            yield from settle()

    def both(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Open units (kind 0, which come first) meet; repeats that a task knew of (kind 1) pass."""
        rest: list[pa.RecordBatch] = []

        def open_ones() -> Iterator[pa.RecordBatch]:
            for batch in batches:
                last = int(np.count_nonzero(np.asarray(batch.column("kind")) == 0))
                yield batch.slice(0, last)
                if last < batch.num_rows:
                    rest.append(batch.slice(last))
                    return

        for batch in meet(open_ones()):
            yield batch.select(["block", "units"])
        for batch in (*rest, *batches):
            yield batch.select(["block", "units"])

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, n = [], 0
        for t in _tables(batches, 8):
            t = np.asfortranarray(t)
            # the earliest of all stays; whether a task had others of it is known by its mark
            columns = [t[:, 0].view(U), t[:, 1].view(U), *t.T[2:]]
            (*columns, elsewhere), first, shared = _in_order([tuple(columns)])
            shared |= elsewhere > 0
            found.append((*(x[shared] for x in columns[2:]), first[shared].astype(np.int64)))
            n += len(found[-1][0])
            if n >= HELD:
                yield rows_of(1, _to_documents(blocks, found))
                found, n = [], 0
        if n:
            yield rows_of(1, _to_documents(blocks, found))

    def runs(start: np.ndarray, length: np.ndarray, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        new = np.flatnonzero(np.concatenate([[True], start[1:] != (start + length)[:-1]]))
        fits = np.add.reduceat(words, new) >= min_words
        return start[new][fits], np.add.reduceat(length, new)[fits]

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.int64()]
        for t in _tables(batches, 6):
            t = t[np.lexsort((t[:, 2], t[:, 1], t[:, 0]))]
            at = np.flatnonzero(np.concatenate([[True], (t[1:, :2] != t[:-1, :2]).any(axis=1)]))
            rows = []
            for a, b in zip(at.tolist(), np.append(at[1:], len(t)).tolist()):
                start, length, words, first = t[a:b, 2:].T
                whole = runs(start, length, words)[1]
                if len(whole):
                    gone = first == 0
                    starts, lengths = runs(start[gone], length[gone], words[gone]) if gone.any() else (start[:0], length[:0])
                    rows.append((int(t[a, 0]), int(t[a, 1]), starts.tolist(), lengths.tolist(), int(whole.sum())))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*rows), kinds)], ["k", "th", "starts", "lengths", "n_repeated"])

    units = docs.select(doc_key().alias("k"), text_key().alias("th"), "text").mapInArrow(tidy(deal), "kind int, block int, units binary")
    met = units.repartition("kind", "block").sortWithinPartitions("kind", "block").mapInArrow(tidy(both), "block int, units binary")
    repeats = met.repartition("block").sortWithinPartitions("block")
    return repeats.mapInArrow(tidy(judge), "k bigint, th bigint, starts array<bigint>, lengths array<bigint>, n_repeated bigint")


def drop_repeated_lines(docs: DataFrame, min_words: int = MIN_WORDS, with_text: bool = True) -> DataFrame:
    """Every row of ``docs`` without its repeated runs of units (see ``spans.cut`` for the columns), and n_repeated."""
    return cut(docs, repeated_runs(docs, min_words), with_text, ("n_repeated",))
