"""Quality rules: counting rules, then a hashed n-gram log-likelihood ratio.

Two multinomials over hashed byte n-grams are fitted: the trusted target and the raw corpus.
A document's score is the sum of log(target / raw) over its n-grams divided by their number;
one threshold decides every document.

Parameters: ``gram`` bytes per n-gram (3), ``BUCKETS`` hash buckets (2**16, so the model is two
arrays of half a megabyte, whatever the corpus), ``target_limit`` trusted documents at most
(20,000, those with the least hash of their id), ``threshold`` of the score (-0.5 nats).

Defined cases: a null or blank text has no words, fails the base rule and is rejected with
score 0; equal rows get equal verdicts; an empty table gives no rows; without trusted rows the
target equals the raw corpus and every score is 0.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernel import buffer, mix, slices, tidy, Words

BUCKETS = 1 << 16
GRAM = 3
WINDOW = 8
MIN_WORDS = 20
REPEAT_PERCENT = 30
THRESHOLD = -0.5
TARGET_LIMIT = 20_000
SYMBOLS = np.zeros(256, bool)
SYMBOLS[list(b"#*$%&|<>")] = True
_BLANKS = " \t\n\x0b\x0c\r"

BASE = "n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint"


def hashed_grams(data: np.ndarray, offsets: np.ndarray, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """The bucket of every n-gram inside a row, and where each row's begin."""
    n = len(data) - gram + 1
    if n <= 0:
        return np.zeros(0, np.uint32), np.zeros(len(offsets), np.int64)
    v = np.zeros(n, np.uint32)
    for j in range(gram):
        v *= np.uint32(257)
        v += data[j : j + n]
    v = (v * np.uint32(2654435761)) >> np.uint32(16)
    per_row = np.maximum(np.diff(offsets) - gram + 1, 0)
    at = np.concatenate([[0], np.cumsum(per_row)])
    keep = np.zeros(n + 1, np.int32)
    starts = offsets[:-1][per_row > 0]
    np.add.at(keep, starts, 1)
    np.add.at(keep, starts + per_row[per_row > 0], -1)
    return v[np.cumsum(keep[:n]) > 0], at


def repeated_words(words: Words, window: int = WINDOW) -> np.ndarray:
    """Per row: words that lie in a window of ``window`` words found twice or more in the row."""
    grams, _ = words.shingles(window)
    full = np.maximum(words.count - window + 1, 0)
    # rows shorter than a window have one short shingle, which can't repeat
    has = np.where(words.count >= window, full, (words.count > 0).astype(np.int64))
    row = np.repeat(np.arange(len(has)), has)
    first = np.repeat(words.of[:-1], has) + np.arange(len(row)) - np.repeat(np.cumsum(has) - has, has)
    key = mix(grams ^ mix(row.astype(np.uint64)))
    order = np.argsort(key, kind="stable")
    same = key[order][1:] == key[order][:-1]
    hit = np.zeros(len(key), bool)
    hit[order[1:][same]] = True
    hit[order[:-1][same]] = True
    mark = np.zeros(len(words.start) + 1, np.int32)
    at = first[hit]
    np.add.at(mark, at, 1)
    np.add.at(mark, np.minimum(at + window, words.of[row[hit] + 1]), -1)
    covered = np.concatenate([[0], np.cumsum(np.cumsum(mark[:-1]) > 0)])
    return np.diff(covered[words.of])


def _dup_lines(text: str | None) -> int:
    if not text or "\n" not in text:
        return 0
    lines = [x for x in text.split("\n") if x.strip(_BLANKS)]
    return len(lines) - len(set(lines))


def base_columns(texts: pa.Array) -> list[np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of each text."""
    w = Words(texts)
    chars = w.ink & ((w.data & 0xC0) != 0x80)
    return [
        w.count.astype(np.int64),
        w.per_row(chars),
        w.per_row(SYMBOLS[w.data]),
        np.array([_dup_lines(t) for t in texts.to_pylist()], np.int64),
        repeated_words(w).astype(np.int64),
    ]


def bucket_counts(docs: DataFrame, gram: int = GRAM, ids: np.ndarray | None = None) -> np.ndarray:
    """Counts of all n-grams of all texts (or of those with one of a bounded list of ids): each task sums its own,
    the driver gets BUCKETS rows."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(BUCKETS, np.int64)
        for batch in batches:
            if ids is not None:
                batch = batch.filter(pa.array(np.isin(np.asarray(batch.column("doc_id").fill_null(-(1 << 62))), ids)))
            for part in slices(batch):
                total += np.bincount(hashed_grams(*buffer(part.column("text")), gram)[0], minlength=BUCKETS)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], ["bucket", "n"])

    rows = docs.select("text") if ids is None else docs.select("doc_id", "text")
    rows = rows.mapInArrow(tidy(count), "bucket int, n bigint").groupBy("bucket").agg(F.sum("n").alias("n"))
    out = np.zeros(BUCKETS, np.int64)
    table = rows.toArrow()
    out[np.asarray(table.column("bucket"))] = np.asarray(table.column("n"))
    return out


def target_ids(labels: DataFrame, limit: int = TARGET_LIMIT) -> np.ndarray:
    """Ids of the trusted documents: quality 1 and not toxic, ``limit`` at most, by hash of the id."""
    good = labels.where((F.col("quality") == 1) & (F.coalesce("toxic", F.lit(0)) == 0) & F.col("doc_id").isNotNull())
    picked = good.select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(limit)
    return np.sort(np.array([r[0] for r in picked.collect()], np.int64))


def log_ratios(target: np.ndarray, raw: np.ndarray) -> np.ndarray:
    """log(target / raw) per bucket, both with one added to every count."""
    if not target.sum():
        return np.zeros(BUCKETS)
    return np.log((target + 1) / (target.sum() + BUCKETS)) - np.log((raw + 1) / (raw.sum() + BUCKETS))


def score_documents(docs: DataFrame, ratios: np.ndarray, gram: int = GRAM, threshold: float = THRESHOLD) -> DataFrame:
    """Every row of ``docs`` with the rule columns, ``score``, ``base_failed`` and ``kept`` added.

    Columns of ``docs`` with these names are replaced."""
    own = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "score", "base_failed", "kept"]
    docs = docs.drop(*own)
    shared = docs.sparkSession.sparkContext.broadcast(ratios)  # BUCKETS doubles

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights = shared.value
        for batch in batches:
            for part in slices(batch):
                texts = part.column("text")
                base = base_columns(texts)
                grams, at = hashed_grams(*buffer(texts), gram)
                sums = np.concatenate([[0.0], np.cumsum(weights[grams])])
                n = np.diff(at)
                value = (sums[at[1:]] - sums[at[:-1]]) / np.maximum(n, 1)
                failed = (base[0] < MIN_WORDS) | (100 * base[4] > REPEAT_PERCENT * base[0])
                arrays = [*base, value, failed, ~failed & (np.round(value, 9) >= threshold)]
                yield pa.RecordBatch.from_arrays([*part.columns, *map(pa.array, arrays)], [*part.schema.names, *own])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return docs.mapInArrow(tidy(score), f"{kinds}, {BASE}, score double, base_failed boolean, kept boolean")


def assess(docs: DataFrame, labels: DataFrame, gram: int = GRAM, threshold: float = THRESHOLD, target_limit: int = TARGET_LIMIT) -> DataFrame:
    """Fit both multinomials (the raw one on all of ``docs``) and judge every document."""
    raw = bucket_counts(docs, gram)
    target = bucket_counts(docs, gram, target_ids(labels, target_limit))
    return score_documents(docs, log_ratios(target, raw), gram, threshold)

