"""Approximate nearest neighbours by a permutation index.

``pivots`` are a bounded sample of the rows (the valid vectors with the least hash of their id: the
square root of the number of rows, from 64 to 4,096, equal ones once).  A row lies in the inverted
file of its nearest pivot; a query has a permutation, all pivots from the nearest on, and visits the
files of its first ``visit`` pivots.  How many that must be depends on the table: it is measured on
``sample`` queries, whose true neighbours are found by one pass over all rows, as the least number
whose files hold a share ``recall`` of those neighbours.  At most it is every file, and then the
result is exact.  Whatever is visited is compared by exact cosine: nothing is cut before it.

Files are dealt to groups of about equal size (a file above that size in several pieces), so that a
query is copied to each group once, and a visited group is compared whole.  All rows are indexed and
all queries answered; no task holds more than one group.

Defined cases: vectors that are null, zero, or hold null or non-finite components take no part, nor
do rows without id nor vectors of another length than most; ties go to the smaller id; a repeated id is taken once for each of its rows;
tables with fewer rows give what there is.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .kernel import mix, tidy, unsigned

BLOCK = 32768
GROUPS = 48
QUERIES = 64


@dataclass(frozen=True)
class IndexSettings:
    recall: float = 0.95
    sample: int = 200
    least: int = 64
    most: int = 4096


def _narrow(rows: DataFrame, vec: str) -> bool:
    return dict(rows.dtypes)[vec] == "array<float>"


def valid_vectors(rows: DataFrame, vec: str = "embedding") -> DataFrame:
    """vec_id, v (array of floats if they are, else of doubles) of the rows that take part."""
    v = F.col(vec).cast("array<double>")
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    return rows.where(F.col("vec_id").isNotNull() & F.col(vec).isNotNull()).where(fine).select(F.col("vec_id").cast("long").alias("vec_id"), (F.col(vec) if _narrow(rows, vec) else v).alias("v"))


def _matrix(column: pa.Array) -> np.ndarray:
    n = len(column)
    return np.asarray(column.flatten(), np.float64).reshape(n, -1)


def _unit(x: np.ndarray) -> np.ndarray:
    scale = np.abs(x).max(axis=1, keepdims=True)
    y = x / scale
    return y / np.sqrt((y * y).sum(axis=1, keepdims=True))


def _least_hash(vectors: DataFrame, seed: int, count: int) -> pa.Table:
    return vectors.orderBy(F.xxhash64(F.lit(seed), "vec_id"), "vec_id").limit(count).toArrow()


def choose_pivots(vectors: DataFrame, n: int, settings: IndexSettings) -> np.ndarray:
    count = min(settings.most, max(settings.least, math.isqrt(n)))
    picked = _least_hash(vectors, 17, count)
    return np.unique(_unit(_matrix(picked.column("v").combine_chunks())), axis=0) if picked.num_rows else np.zeros((0, 1))


def permutations(x: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    """Numbers of all pivots by row, the nearest first."""
    return np.argsort(-(_unit(x) @ pivots.T), axis=1, kind="stable")


def files(x: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    """The nearest pivot of each row, whose file it lies in."""
    return np.argmax(_unit(x) @ pivots.T, axis=1)


def _norms(x: np.ndarray) -> np.ndarray:
    scale = np.abs(x).max(axis=1)
    return scale * np.sqrt(((x / scale[:, None]) ** 2).sum(axis=1))


def _needed(vec_ids: np.ndarray, x: np.ndarray, k: int) -> np.ndarray:
    """Rows that can be among the k best of some query: of equal vectors those of the k + 1 least ids."""
    _, same = np.unique(np.ascontiguousarray(x).view(np.dtype((np.void, x.shape[1] * 8))).ravel(), return_inverse=True)
    order = np.lexsort((vec_ids, same))
    g, v = same[order], vec_ids[order]
    again = np.concatenate([[False], (g[1:] == g[:-1]) & (v[1:] == v[:-1])])
    order, g = order[~again], g[~again]
    first = np.maximum.accumulate(np.where(np.concatenate([[True], g[1:] != g[:-1]]), np.arange(len(g)), 0))
    return np.sort(order[np.arange(len(g)) - first <= k])


def _search(vec_ids: np.ndarray, x: np.ndarray, q_ids: np.ndarray, q: np.ndarray, k: int) -> Iterator[tuple]:
    """The k best of all rows for each query: its place, ids and scores; of ``_needed`` rows."""
    norms, q_norms = _norms(x), _norms(q)
    unit, q_unit = _unit(x), _unit(q)
    for at in range(0, len(q), QUERIES):
        near = q_unit[at : at + QUERIES] @ unit.T
        for j in range(len(near)):
            i = at + j
            score = near[j]
            score[vec_ids == q_ids[i]] = -np.inf
            if len(score) > k:
                # products of matrices round equal vectors apart: all that may be among the best are compared again
                best = np.flatnonzero(score >= np.partition(score, len(score) - k)[-k] - 1e-9)
            else:
                best = np.arange(len(score))
            best = best[score[best] > -np.inf]
            exact = (x[best] * q[i]).sum(axis=1) / (norms[best] * q_norms[i])
            top = np.lexsort((vec_ids[best], -exact))[:k]
            yield i, best[top], exact[top]


def visits_for(vectors: DataFrame, sampled: pa.Table, pivots: np.ndarray, k: int, recall: float) -> int:
    """How many files a query must visit to meet a share ``recall`` of the true neighbours of ``sampled``."""
    if not sampled.num_rows:
        return 1
    q_ids, q = np.asarray(sampled.column("vec_id")), _matrix(sampled.column("v").combine_chunks())
    order = permutations(q, pivots)
    place = np.empty_like(order)
    np.put_along_axis(place, order, np.arange(len(pivots))[None, :], axis=1)
    shared = vectors.sparkSession.sparkContext.broadcast((q_ids, q, place, pivots))  # of bounded size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q_ids, q, place, pivots = shared.value
        held: tuple[np.ndarray, ...] | None = None  # the best so far: query, id, place of its file, score
        for whole in batches:
            for at in range(0, whole.num_rows, 4096):
                batch = whole.slice(at, 4096)
                ids, x = np.asarray(batch.column("vec_id")), _matrix(batch.column("v"))
                need = _needed(ids, x, k)
                ids, x = ids[need], x[need]
                near = files(x, pivots)
                new = [(np.full(len(best), i), ids[best], place[i, near[best]], score) for i, best, score in _search(ids, x, q_ids, q, k)]
                held = tuple(np.concatenate(c) for c in zip(*([held] if held else []), *new))
                by = np.lexsort((held[1], -held[3], held[0]))
                held = tuple(c[by] for c in held)
                first = np.searchsorted(held[0], held[0])
                held = tuple(c[np.arange(len(first)) - first < k] for c in held)
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(c.astype(np.float64 if j == 3 else np.int64)) for j, c in enumerate(held)], ["q", "vec_id", "place", "score"])

    best = Window.partitionBy("q").orderBy(F.desc("score"), "vec_id", "place")
    rows = vectors.mapInArrow(tidy(run), "q bigint, vec_id bigint, place bigint, score double").groupBy("q", "vec_id").agg(F.max("score").alias("score"), F.min("place").alias("place"))
    rows = rows.withColumn("r", F.row_number().over(best)).where(F.col("r") <= k)
    places = np.sort([r[0] for r in rows.select("place").collect()])  # k for each sampled query
    return int(places[min(len(places) - 1, math.ceil(recall * len(places)) - 1)]) + 1 if len(places) else 1


def deal(counts: dict[int, int], n_pivots: int, block: int = BLOCK, least: int = GROUPS) -> list[list[int]]:
    """The group of each piece of each pivot's file: pieces of about the same size, the largest dealt first."""
    n = sum(counts.values())
    groups = max(least, -(-n // block))
    size = max(1, -(-n // groups))
    pieces = sorted(((c / parts, p) for p, c in counts.items() for parts in [max(1, -(-c // size))] for _ in range(parts)), key=lambda x: (-x[0], x[1]))
    loads = [(0.0, g) for g in range(groups)]
    out: list[list[int]] = [[] for _ in range(n_pivots)]
    for c, p in pieces:
        load, g = heapq.heappop(loads)
        out[p].append(g)
        heapq.heappush(loads, (load + c, g))
    return out


def nearest(rows: DataFrame, is_query, k: int = 5, settings: IndexSettings = IndexSettings(), vec: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the ``k`` nearest found for the rows of ``is_query`` (a condition on vec_id)."""
    spark = rows.sparkSession
    vectors = valid_vectors(rows, vec)
    sizes = vectors.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    if sizes is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    dimensions, n = sizes
    vectors = vectors.where(F.size("v") == dimensions)
    queries = vectors.where(is_query(F.col("vec_id")))
    pivots = choose_pivots(vectors, n, settings)
    visit = visits_for(vectors, _least_hash(queries, 19, settings.sample), pivots, k, settings.recall)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(shared.value[0]), np.int64)
        for whole in batches:
            for at in range(0, whole.num_rows, 2048):
                total += np.bincount(files(_matrix(whole.slice(at, 2048).column("v")), shared.value[0]), minlength=len(total))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], ["pivot", "n"])

    shared = spark.sparkContext.broadcast((pivots, None))
    counts = vectors.mapInArrow(tidy(count), "pivot bigint, n bigint").groupBy("pivot").agg(F.sum("n").alias("n")).where("n > 0")
    dealt = deal({r[0]: r[1] for r in counts.collect()}, len(pivots))  # a row for each pivot
    shared = spark.sparkContext.broadcast((pivots, dealt))  # 4,096 vectors at most, and the groups of their files

    def post(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pivots, dealt = shared.value
        parts = np.array([max(1, len(g)) for g in dealt])
        first = np.concatenate([[0], np.cumsum(parts)])
        flat = np.array([g for groups in dealt for g in groups or [0]])
        for whole in batches:
            for at in range(0, whole.num_rows, 2048):
                batch = whole.slice(at, 2048)
                file = files(_matrix(batch.column("v")), pivots)
                piece = (mix(unsigned(np.asarray(batch.column("vec_id")))) % parts[file].astype(np.uint64)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(flat[first[file] + piece].astype(np.int32)), pa.array(np.zeros(len(file), np.int32)), *batch.columns], ["group", "kind", *batch.schema.names])

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pivots, dealt = shared.value
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                batch = whole.slice(at, 256)
                order = permutations(_matrix(batch.column("v")), pivots)[:, :visit]
                groups = [sorted({g for p in o for g in dealt[p]}) for o in order.tolist()]
                row = np.repeat(np.arange(len(groups)), [len(g) for g in groups])
                flat = np.array([g for x in groups for g in x], np.int32)
                for a in range(0, len(row), 4096):
                    part = batch.take(pa.array(row[a : a + 4096]))
                    yield pa.RecordBatch.from_arrays([pa.array(flat[a : a + 4096]), pa.array(np.ones(part.num_rows, np.int32)), *part.columns], ["group", "kind", *part.schema.names])

    kinds = f"group int, kind int, vec_id bigint, v {dict(vectors.dtypes)['v']}"
    together = vectors.mapInArrow(tidy(post), kinds).unionByName(queries.mapInArrow(tidy(ask), kinds))
    together = together.repartition("group").sortWithinPartitions("group", "kind")

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held, ready = None, [], None
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                batch = whole.slice(at, 1024)
                group, kind = (np.asarray(batch.column(c)) for c in ("group", "kind"))
                cuts = np.flatnonzero((group[1:] != group[:-1]) | (kind[1:] != kind[:-1])) + 1
                for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(group)]):
                    if group[a] != key:
                        key, held, ready = group[a], [], None
                    ids, x = np.asarray(batch.column("vec_id"))[a:b], _matrix(batch.column("v").slice(a, b - a))
                    if kind[a] == 0:
                        held.append((ids, x))
                    elif held:
                        if ready is None:
                            all_ids, all_x = (np.concatenate(c) for c in zip(*held))
                            need = _needed(all_ids, all_x, k)
                            ready = all_ids[need], all_x[need]
                        found = [(np.full(len(best), ids[i]), ready[0][best], score) for i, best, score in _search(*ready, ids, x, k)]
                        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*found)], ["query_id", "vec_id", "score"])

    found = together.mapInArrow(tidy(search), "query_id bigint, vec_id bigint, score double")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    found = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
