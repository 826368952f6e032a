"""Choice of a strategy from the graph's statistics, the pattern and the rule."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..functions import library, pattern as pt
from ..functions.automaton import TimedRule
from ..functions.pattern import Pattern
from ..operators import relational, strategies
from ..sources.graphs import TemporalGraph

DENSE = 0.3


@dataclass(frozen=True)
class Choice:
    strategy: str
    reason: str


def choose(pattern: Pattern, rule: TimedRule, structural_density: float | None = None) -> Choice:
    """Staged for what has a usable order and isn't a short cycle on a sparse graph; a plain relational query
    for rules that are one; on-demand otherwise."""
    if pattern.m == 2 and relational.comparison(rule) is not None:
        return Choice("relational", "the rule is a comparison of activity arrays")
    if rule.empty_letter() == "general":
        return Choice("full", "empty letters move the rule")
    if strategies.staged_orders(pattern, rule) is None:
        return Choice("ondemand", "no order of first activity keeps prefixes connected")
    if pattern.is_cyclic and pattern.m < 4 and (structural_density is None or structural_density < DENSE):
        return Choice("ondemand", "short cycles on sparse graphs have few matches and many partial ones")
    return Choice("staged", "partial matches die early and share their runs")


def find(g: TemporalGraph, pattern: Pattern, rule: TimedRule, strategy: str = "auto", structural_density: float | None = None) -> DataFrame:
    if strategy == "auto":
        strategy = choose(pattern, rule, structural_density).strategy
    if strategy == "relational":
        return relational.solve(g, pattern, rule)
    return {"full": strategies.solve_full, "ondemand": strategies.solve_ondemand, "staged": strategies.solve_staged}[strategy](g, pattern, rule)


_QUERY = re.compile(r"\s*match\s+(?P<pattern>.+?)\s+obeying\s+(?P<rule>\w+)\s*(?:\((?P<args>[^)]*)\))?\s*(?:using\s+(?P<strategy>\w+))?\s*$", re.I | re.S)


def find_sql(g: TemporalGraph, text: str) -> DataFrame:
    """``MATCH (a)-[y1]->(b), (b)-[y2]->(a) OBEYING round_robin(2) [USING staged]``"""
    q = _QUERY.match(text)
    if not q:
        raise ValueError(f"can't read {text!r}")
    shape = re.fullmatch(r"(path|cycle|in_star|out_star)\((\d+)\)", q["pattern"].strip())
    pattern = getattr(pt, shape[1])(int(shape[2])) if shape else Pattern.of(q["pattern"])
    args = [float(a) if "." in a else int(a) for a in (q["args"] or "").replace(" ", "").split(",") if a]
    return find(g, pattern, getattr(library, q["rule"])(*args), (q["strategy"] or "auto").lower())
