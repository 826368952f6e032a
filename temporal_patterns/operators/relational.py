"""Rules as relational queries: the nine of two edges (comparisons of activity, windows, islands), and round robin and
orders of first activity for any number of edges.

These are the baselines: no automaton runs.  ``solve`` works on matches with packed activity; the rules of
``SIMPLE`` need one expression a match.  Which form a rule has, and its arguments, follow from its moves, never from
its name: a rule that equals none of the library's has no form.
"""

from __future__ import annotations

import re
from collections.abc import Callable
from functools import partial, reduce
from operator import and_

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import library
from ..functions.automaton import TimedRule
from ..functions.pattern import Pattern
from ..sources.graphs import TemporalGraph, packed
from .matching import match

_JOINT = lambda: F.array_intersect("ts1", "ts2")

#: Rules that are comparisons of first, last or the arrays, with their condition.
SIMPLE: list[tuple[TimedRule, Callable[[], Column]]] = [
    (library.exists_before(), lambda: F.col("f1") < F.col("l2")),
    (library.exists_not_after(), lambda: F.col("f1") <= F.col("l2")),
    (library.first_strictly_before(2), lambda: F.col("f1") < F.col("f2")),
    (library.first_in_order(2), lambda: F.col("f1") <= F.col("f2")),
    (library.always_together(), lambda: F.col("ts1") == F.col("ts2")),
    (library.never_together(), lambda: ~F.arrays_overlap("ts1", "ts2")),
    (library.contained(1, 2), lambda: F.size(F.array_except("ts1", "ts2")) == 0),
    (library.contained(2, 1), lambda: F.size(F.array_except("ts2", "ts1")) == 0),
    (library.all_before(), lambda: F.col("l1") < F.col("f2")),
]


def comparison(rule: TimedRule) -> Callable[[], Column] | None:
    """The condition that says the same as the rule, if it is one of ``SIMPLE``."""
    return next((condition for known, condition in SIMPLE if known == rule), None)


def _alternation(rows: DataFrame, names: list[str], bound: float | None, m: int = 2) -> DataFrame:
    """By windows: times of all edges in one line, tagged; tags go round from y1, and a reply (of two) is in time."""

    def tagged(i: int) -> Column:
        return F.transform(f"ts{i}", lambda x: F.struct(x["t"].alias("t"), F.lit(i).alias("tag")))

    tags = F.explode(F.concat(*map(tagged, range(1, m + 1))))
    along = Window.partitionBy(*names).orderBy("t", "tag")
    line = rows.select(*names, tags.alias("x")).select(*names, "x.t", "x.tag").withColumns({"before": F.lag("tag").over(along), "t0": F.lag("t").over(along)})
    wrong = F.when(F.col("before").isNull(), F.col("tag") != 1).otherwise((F.col("tag") != F.col("before") % m + 1) | (F.col("t") == F.col("t0")))
    if bound is not None:
        wrong = wrong | ((F.col("tag") == 2) & F.col("before").isNotNull() & (F.col("t") - F.col("t0") >= bound))
    return line.groupBy(*names).agg(F.max(wrong.cast("int")).alias("wrong")).where("wrong = 0").select(names)


def _islands(rows: DataFrame, names: list[str], points: int) -> DataFrame:
    """Joint times whose rank rises by one are an island; one has ``points`` times or more."""
    joint = rows.select(*names, F.explode(_JOINT()).alias("x"))
    at = F.row_number().over(Window.partitionBy(*names).orderBy("x.t"))
    islands = joint.select(*names, (F.col("x.r") - at).alias("island"))
    return islands.groupBy(*names, "island").agg(F.count("*").alias("n")).where(F.col("n") >= points).select(names).distinct()


def form(rule: TimedRule) -> Callable[[DataFrame, list[str]], DataFrame] | None:
    """What turns matches with packed activity into the accepted ones; None if the rule has no relational form."""
    condition = comparison(rule)
    if condition is not None:
        return lambda rows, names: rows.where(condition()).select(names)
    if rule == library.round_robin(rule.m):
        return partial(_alternation, bound=None, m=rule.m)
    for known, strict in ((library.first_strictly_before, True), (library.first_in_order, False)):
        if rule == known(rule.m):
            rises = [F.col(f"f{i}") < F.col(f"f{i + 1}") if strict else F.col(f"f{i}") <= F.col(f"f{i + 1}") for i in range(1, rule.m)]
            return lambda rows, names: rows.where(reduce(and_, rises)).select(names)
    for text in {x for mv in rule.moves for x in re.findall(r"\d+(?:\.\d+)?", str(mv.guard))}:
        bound = float(text) if "." in text else int(text)
        if any(rule == library.timed_alternation(bound, "reply", restart) for restart in ("first", "every")):
            return partial(_alternation, bound=bound)
    if rule.m == 2 and rule.states > 1 and rule == library.together_for(rule.states - 1, "points"):
        return partial(_islands, points=rule.states - 1)
    return None


def solve(g: TemporalGraph, pattern: Pattern, rule: TimedRule) -> DataFrame:
    """Accepted matches (x.., e..)."""
    if pattern.m != rule.m:
        raise ValueError("the rule is for another number of edges")
    found = form(rule)
    if found is None:
        raise ValueError(f"no relational form of {rule.name}")
    ranks = getattr(found, "func", None) is _islands
    return found(match(packed(g, ranked=ranks), pattern, g.nodes), [*pattern.nodes, *(f"e{i}" for i in range(1, pattern.m + 1))])


def conciseness(rule: TimedRule, sql: str) -> dict[str, int]:
    """Moves of the rule against words of a query that does the same."""
    return {"moves": len(rule.moves), "sql_tokens": len(sql.split())}
