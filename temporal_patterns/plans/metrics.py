"""Measures of a run: times, counts, selectivity, live partial matches, exactness."""

from __future__ import annotations

import time
from collections.abc import Callable
from statistics import mean, pstdev

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.automaton import TimedRule
from ..functions.pattern import Pattern
from ..operators.matching import match
from ..operators.strategies import verdicts
from ..sources.graphs import TemporalGraph, packed


def timed(run: Callable[[], DataFrame], runs: int = 3) -> dict[str, float]:
    """Mean seconds and coefficient of variation; results are counted, not collected."""
    took = []
    for _ in range(runs):
        began = time.perf_counter()
        run().agg(F.count("*")).first()
        took.append(time.perf_counter() - began)
    return {"seconds": mean(took), "variation": pstdev(took) / mean(took)}


def match_seconds(g: TemporalGraph, pattern: Pattern, runs: int = 3) -> dict[str, float]:
    return timed(lambda: match(packed(g), pattern, g.nodes), runs)


def counts(g: TemporalGraph, pattern: Pattern, rule: TimedRule) -> DataFrame:
    """matches, accepted, selectivity, letters read, and the automaton's moves offered (letters times states)."""
    v = verdicts(g, pattern, rule)
    return v.agg(F.count("*").alias("matches"), F.count_if("accepted").alias("accepted"), F.sum(F.size("word")).cast("long").alias("letters")).withColumns(
        {"selectivity": F.col("accepted") / F.col("matches"), "moves_tried": F.col("letters") * rule.states}
    )


def difference(a: DataFrame, b: DataFrame) -> int:
    """Rows that one has and the other hasn't (0: the methods agree)."""
    return a.exceptAll(b).count() + b.exceptAll(a).count()
