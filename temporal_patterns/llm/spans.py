"""Byte spans of documents: keys of rows, and cutting spans out of whole texts.

A document is known by its id (null: the least long) and a hash of its text, so that rows with
one id and different texts stay apart and repeated rows (same id, same text) are one document.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .kernel import tidy

NULL_ID = -(1 << 63)


def doc_key() -> Column:
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_ID).cast("long"))


def text_key() -> Column:
    return F.xxhash64(F.coalesce("text", F.lit("")))


def cover(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of the union of [start, end)."""
    if not len(start):
        return start, end
    order = np.argsort(start, kind="stable")
    start, end = start[order], np.maximum.accumulate(end[order])
    new = np.concatenate([[True], start[1:] > end[:-1]])
    last = np.concatenate([np.flatnonzero(new)[1:] - 1, [len(start) - 1]])
    return start[new], end[last]


def gathered(spans: DataFrame) -> DataFrame:
    """One row for each document of spans (k, th, start, length): k, th, and arrays of starts and lengths."""
    return spans.groupBy("k", "th").agg(F.collect_list("start").alias("starts"), F.collect_list("length").alias("lengths"))


def cut(docs: DataFrame, per_doc: DataFrame, with_text: bool = True, also: tuple[str, ...] = ()) -> DataFrame:
    """Every row of ``docs`` without the bytes of its spans.

    ``per_doc`` has a row for each document with spans: k, th (of ``doc_key``, ``text_key``), starts, lengths
    (arrays, in bytes; as many as the text's length allows), and numbers named in ``also`` (0 for other documents).  Added: these, n_bytes, n_removed, n_spans (long), kept_sha256, spans
    (array of start, length in the original bytes); ``text`` is what remains, and n_chars its length
    where ``docs`` has that column.  Spans that end inside a character lose the character's rest in
    ``text`` alone.
    """
    own = ["n_bytes", "n_removed", "n_spans", "kept_sha256", "spans"]
    docs = docs.drop(*own, *also)
    names = docs.columns
    # the caller's columns travel as one struct, so their names can't clash
    keyed = docs.select(F.struct(*(F.col(f"`{c}`") for c in names)).alias("row"), doc_key().alias("k"), text_key().alias("th"))
    joined = keyed.join(per_doc, ["k", "th"], "left").select("row", "starts", "lengths", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in also))
    kept_names = names if with_text else [c for c in names if c != "text"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                part = whole.slice(at, 512)
                batch = dict(zip(names, part.column("row").flatten()))
                texts = batch["text"].to_pylist()
                starts, lengths = part.column("starts").to_pylist(), part.column("lengths").to_pylist()
                rows: list[list] = [[] for _ in own]
                out = []
                for text, s, n in zip(texts, starts, lengths):
                    raw = (text or "").encode()
                    a, b = cover(np.array(s or [], np.int64), np.array(s or [], np.int64) + np.array(n or [], np.int64))
                    kept, last = [], 0
                    for x, y in zip(a.tolist(), b.tolist()):
                        kept.append(raw[last:x])
                        last = y
                    rest = b"".join([*kept, raw[last:]])
                    for column, value in zip(rows, (len(raw), len(raw) - len(rest), len(a), hashlib.sha256(rest).hexdigest(), [{"start": x, "length": y - x} for x, y in zip(a.tolist(), b.tolist())])):
                        column.append(value)
                    out.append(None if text is None else rest.decode("utf-8", "ignore") if len(a) else text)
                columns = []
                for c in kept_names:
                    if c == "text":
                        columns.append(pa.array(out, pa.string()))
                    elif c == "n_chars":
                        columns.append(pa.array([len(t) if s else m for t, s, m in zip(out, starts, batch[c].to_pylist())], pa.int64()))
                    else:
                        columns.append(batch[c])
                kinds = [pa.int64()] * 3 + [pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("length", pa.int64())]))]
                yield pa.RecordBatch.from_arrays([*columns, *(pa.array(v, k) for v, k in zip(rows, kinds)), *(part.column(c) for c in also)], [*kept_names, *own, *also])

    kinds = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in docs.schema if f.name in kept_names)
    return joined.mapInArrow(tidy(run), f"{kinds}n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string, spans array<struct<start: bigint, length: bigint>>{''.join(f', `{c}` bigint' for c in also)}")
