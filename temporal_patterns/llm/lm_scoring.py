"""Language-model scoring by cross-entropy difference.

Two interpolated bigram models over one shared vocabulary: the background is counted on all
documents, the target on all trusted ones.  A document's score is the mean over its tokens of
log p_background - log p_target (the difference of the two cross-entropies, in nats): the lower,
the more the document is like the target.

Tokens are words with A-Z in lower case, known by 64-bit hashes.  Every word and every pair of
neighbours is modelled, whatever the size of the corpus: nothing is cut by count or share.

Documents lie in chunks of about ``CHUNK`` bytes, by hash of their id, written once.  A chunk counts its own words
and pairs and sends each of them once; where the counts of all chunks meet, those that several chunks have get the
totals sent back, while what only one chunk has needs no answer.  So no task and no driver holds a model, a document's tokens
never travel, and a word that all documents hold sends one entry for each chunk.  A chunk with its answers then
scores its documents.

Defined cases: null and blank texts have no tokens and score 0; without trusted rows the target
is the background and every score is 0; an empty table gives no rows; repeated rows (same id, same
text) each count and get the same scores; rows of one id lie in one chunk.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .kernel import mix, PACKED, slices, tidy, U, Words
from .spans import text_key
from .workspace import buckets, collect_garbage, keep, keep_dealt

PAIR_WEIGHT = 0.6
CHUNK = 1 << 23
#: Stands for the word before a text's first one.
START = U(0x5DEECE66D)
_TURN = U(0x9E3779B97F4A7C15)
_PAIR, _WORD, _TRUSTED, _SUMS = range(4)
#: ``id`` is the document of a trusted one, else the block.
_ANSWER = "chunk bigint, kind int, id bigint, c0 binary, c1 binary, c2 binary"


def _pairs(w: Words, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A key of each word and the word before it in its text, and both; keys have ``bits`` + 48 bits."""
    cut = ~U((1 << (16 - bits)) - 1)
    word = w.hashes() & cut
    before = np.concatenate([[START], word[:-1]])[: len(word)]
    before[w.of[:-1][w.count > 0]] = START
    return mix(before * _TURN + mix(word)) & cut, before, word


def trusted_ids(labels: DataFrame) -> DataFrame:
    """doc_id of all trusted documents."""
    return labels.where((F.col("quality") == 1) & (F.coalesce(F.col("toxic"), F.lit(0)) == 0) & F.col("doc_id").isNotNull()).select("doc_id").distinct()


@dataclass(frozen=True)
class Model:
    """Chunks of documents (chunk, id, row), what they are told (``_ANSWER``), and the number of different words, of all words and of trusted ones."""

    chunks: DataFrame
    answers: DataFrame
    columns: tuple[str, ...]
    words: int
    total: int
    target: int
    bits: int


class _Counts:
    """Tokens and counts of a chunk: of its ``kind`` of keys (ascending) all occurrences and those of trusted documents."""

    def __init__(self, rows: pa.Table, told: pa.Table, bits: int):
        kinds = np.asarray(told.column("kind"))
        trusted = np.asarray(told.column("id").fill_null(0))[kinds == _TRUSTED]
        ids = rows.column("id")
        known = np.isin(np.asarray(ids.fill_null(0)), trusted) & ~np.asarray(ids.is_null())
        parts, self.n = [], []
        at = 0
        for batch in pa.table({"text": rows.column("text")}).combine_chunks().to_batches():
            for part in slices(batch):
                w = Words(part.column("text"), lower=True)
                parts.append((*_pairs(w, bits), w.row + at))
                self.n.append(w.count)
                at += part.num_rows
        none = np.zeros(0, U)
        key, before, word, self.row = (np.concatenate(x) for x in zip(*parts)) if parts else (none, none, none, none.view(np.int64))
        self.n = np.concatenate(self.n) if self.n else np.zeros(0, np.int64)
        weight = known[self.row].astype(float)

        def counted(x: np.ndarray) -> tuple[np.ndarray, ...]:
            one, first, which = np.unique(x, return_index=True, return_inverse=True)
            b, t = np.bincount(which, minlength=len(one)), np.bincount(which, weights=weight, minlength=len(one))
            return one, b.astype(np.int64), t.astype(np.int64), first, which

        self.keys = {}
        self.keys[_PAIR] = counted(key)
        self.keys[_WORD] = counted(word)
        first, self.which = self.keys[_PAIR][3:]
        self.before, self.word = before[first], word[first]
        # the totals of what other chunks have as well
        for i in np.flatnonzero(kinds < _TRUSTED).tolist():
            k, b, t = _received(bits, told.column("id")[i].as_py(), *(told.column(f"c{j}")[i].as_py() for j in range(3)))
            one, all_b, all_t = self.keys[int(kinds[i])][:3]
            place = np.searchsorted(one, k)
            all_b[place], all_t[place] = b, t

    def of(self, kind: int, keys: np.ndarray, target: bool) -> np.ndarray:
        """Totals of keys; of those that the chunk hasn't, 0."""
        one, b, t = self.keys[kind][:3]
        if not len(one):
            return np.zeros(len(keys), np.int64)
        place = np.minimum(np.searchsorted(one, keys), len(one) - 1)
        return np.where(one[place] == keys, (t if target else b)[place], 0)


def _slim(bits: int, edge: np.ndarray, keys: np.ndarray, b: np.ndarray, t: np.ndarray) -> list[pa.Array]:
    """Counts of keys of one block each, cut at ``edge``: the 48 bits of each key that follow the block, b and t in a byte
    each, and (place, b, t) of those that need more."""
    short = (keys << U(bits)) >> U(16)
    low = np.ascontiguousarray(short.view(np.uint8).reshape(-1, 8)[:, :6])
    counts = np.minimum(np.stack([b, t], axis=1), 255).astype(np.uint8)
    ends = np.append(edge, len(keys))
    far = np.flatnonzero(np.maximum(b, t) >= 255)
    start = ends[np.searchsorted(ends, far, "right") - 1]
    large = np.stack([far - start, b[far], t[far]], axis=1).astype(np.int64)
    cut = lambda x, at: pa.Array.from_buffers(pa.binary(), len(edge), [None, pa.array(at.astype(np.int32)).buffers()[1], pa.py_buffer(np.ascontiguousarray(x).tobytes())])
    return [cut(low, ends * 6), cut(counts, ends * 2), cut(large, np.searchsorted(far, ends) * 24)]


def _sent(kind: int, bits: int, keys: np.ndarray, b: np.ndarray, t: np.ndarray) -> pa.RecordBatch:
    """A chunk's counts (keys ascending) by block, the upper bits of the key."""
    block = keys >> U(64 - bits) if bits else np.zeros(len(keys), U)
    edge = np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]]))
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(edge), kind, np.int32)), pa.array(block[edge].astype(np.int32)), *_slim(bits, edge, keys, b, t)], ["kind", "block", "c0", "c1", "c2"])


def _received(bits: int, block: int, c0: bytes, c1: bytes, c2: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    low = np.zeros((len(c0) // 6, 8), np.uint8)
    low[:, :6] = np.frombuffer(c0, np.uint8).reshape(-1, 6)
    keys = (low.view(U)[:, 0] << U(16 - bits)) | U(block << (64 - bits) if bits else 0)
    b, t = np.frombuffer(c1, np.uint8).reshape(-1, 2).astype(np.int64).T.copy()
    large = np.frombuffer(c2, np.int64).reshape(-1, 3)
    b[large[:, 0]], t[large[:, 0]] = large[:, 1], large[:, 2]
    return keys, b, t


def _chunk(id_: Column, n: int) -> Column:
    return F.pmod(F.xxhash64(id_), F.lit(n))


def fit(docs: DataFrame, labels: DataFrame) -> Model:
    """Counts of all words and pairs of all documents, for those of ``labels`` apart."""
    spark = docs.sparkSession
    bytes_ = docs.select(F.sum(F.octet_length("text")).alias("n")).first().n or 0
    n = max(1, -(-bytes_ // CHUNK))
    id_ = F.col("doc_id").cast("long")
    rows = docs.select(_chunk(F.coalesce(id_, text_key()), n).alias("chunk"), id_.alias("id"), "text", F.struct(*(F.col(f"`{c}`") for c in docs.columns if c != "text")).alias("row"))
    chunks, _ = keep_dealt(rows.repartition(buckets(spark), "chunk"), "chunks", "chunk")
    collect_garbage(spark)
    nothing = [F.lit(None).cast("binary").alias(f"c{j}") for j in range(3)]
    trusted = keep(trusted_ids(labels).select(_chunk(F.col("doc_id").cast("long"), n).alias("chunk"), F.lit(_TRUSTED).alias("kind"), F.col("doc_id").cast("long").alias("id"), *nothing), "trusted")
    bits = min(16, (4 * buckets(spark) - 1).bit_length())

    def count(left: pa.Table, right: pa.Table) -> pa.Table:
        c = _Counts(left, right, bits)
        out = []
        for kind, (keys, b, t, *_) in c.keys.items():
            if len(keys):
                batch = _sent(kind, bits, keys, b, t)
                out.append(pa.Table.from_batches([batch.append_column("chunk", pa.array(np.full(batch.num_rows, left.column("chunk")[0].as_py(), np.int64)))]))
        return pa.concat_tables(out) if out else pa.table({})

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        sums = np.zeros(3, np.int64)

        def answer() -> Iterator[pa.RecordBatch]:
            key, b, t = (np.concatenate(x) for x in zip(*(_received(bits, now[1], *h[:3]) for h in held)))
            chunk = np.repeat(np.array([h[3] for h in held], np.int64), [len(h[0]) // 6 for h in held])
            order = np.argsort(key, kind="stable")
            key, b, t, chunk = key[order], b[order], t[order], chunk[order]
            new = np.concatenate([[True], key[1:] != key[:-1]])
            at = np.flatnonzero(new)
            all_b, all_t = np.add.reduceat(b, at), np.add.reduceat(t, at)
            if now[0] == _WORD:
                sums[:] += np.array([len(at), all_b.sum(), all_t.sum()])
            group = np.cumsum(new) - 1
            shared = np.flatnonzero(~new | np.append(~new[1:], False))
            if not len(shared):
                return
            by = shared[np.argsort(chunk[shared], kind="stable")]
            edge = np.flatnonzero(np.concatenate([[True], chunk[by][1:] != chunk[by][:-1]]))
            columns = _slim(bits, edge, key[by], all_b[group[by]], all_t[group[by]])
            yield pa.RecordBatch.from_arrays([pa.array(chunk[by][edge]), pa.array(np.full(len(edge), now[0], np.int32)), pa.array(np.full(len(edge), now[1], np.int64)), *columns], names)

        names = ["chunk", "kind", "id", "c0", "c1", "c2"]
        for batch in batches:
            binaries = [batch.column(f"c{j}") for j in range(3)]
            for i, (kind, block, chunk) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("kind", "block", "chunk")))):
                if (kind, block) != now:
                    if held:
                        yield from answer()
                    now, held = (kind, block), []
                held.append((*(c[i].as_py() for c in binaries), chunk))
        if held:
            yield from answer()
        yield pa.RecordBatch.from_arrays([pa.array([-1], pa.int64()), pa.array([_SUMS], pa.int32()), pa.nulls(1, pa.int64()), pa.array([sums.tobytes()], pa.binary()), *[pa.nulls(1, pa.binary())] * 2], names)

    sent = chunks.groupBy("chunk").cogroup(trusted.groupBy("chunk")).applyInArrow(_with_rows(count), PACKED + ", chunk bigint")
    dealt = sent.repartition("kind", "block").sortWithinPartitions("kind", "block")
    answers = keep(dealt.mapInArrow(tidy(meet), _ANSWER), "answers")
    collect_garbage(spark)
    sums = np.zeros(3, np.int64)
    for r in answers.where(F.col("kind") == _SUMS).select("c0").toLocalIterator():  # a row for each task
        sums += np.frombuffer(bytes(r.c0), np.int64)
    return Model(chunks, answers.where(F.col("kind") < _SUMS).unionByName(trusted), tuple(docs.columns), *map(int, sums), bits)


def _with_rows(fn: Callable) -> Callable:
    """``fn`` for chunks that have documents; labels may name ids that no document has."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        return fn(left, right) if left.num_rows else pa.table({})

    return run


def score(model: Model) -> DataFrame:
    """Every row of the documents that the model was fitted on, with n_tokens, target_entropy, background_entropy and
    score added (nats a token; such columns are replaced)."""
    own = ["n_tokens", "target_entropy", "background_entropy", "score"]
    fields = {f.name: f.dataType for f in model.chunks.schema["row"].dataType}
    fields["text"] = model.chunks.schema["text"].dataType
    kept = [c for c in model.columns if c not in own]
    kinds = ", ".join(f"`{c}` {fields[c].simpleString()}" for c in kept)
    schema = f"{kinds}, n_tokens bigint, target_entropy double, background_entropy double, score double"
    size, total, target, bits = model.words, model.total, model.target, model.bits

    def give(left: pa.Table, right: pa.Table) -> pa.Table:
        c = _Counts(left, right, bits)
        first = c.before == START
        weights = []
        for trusted in (False, bool(target)):
            p = (c.of(_WORD, c.word, trusted) + 1) / ((target if trusted else total) + size + 1)
            heads = np.maximum(c.of(_WORD, c.before, trusted), 1)
            weights.append(-np.log(np.where(first, p, (1 - PAIR_WEIGHT) * p + PAIR_WEIGHT * c.of(_PAIR, c.keys[_PAIR][0], trusted) / heads)))
        n = np.maximum(c.n, 1)
        b, t = (np.bincount(c.row, weights=w[c.which], minlength=left.num_rows) / n for w in weights)
        row = left.column("row").combine_chunks()
        row = row.chunk(0) if isinstance(row, pa.ChunkedArray) else row
        columns = dict(zip([f.name for f in row.type], row.flatten()))
        columns["text"] = left.column("text")
        return pa.table([*(columns[x] for x in kept), pa.array(c.n.astype(np.int64)), pa.array(t), pa.array(b), pa.array(t - b)], [*kept, *own])

    return model.chunks.groupBy("chunk").cogroup(model.answers.groupBy("chunk")).applyInArrow(_with_rows(give), schema)
