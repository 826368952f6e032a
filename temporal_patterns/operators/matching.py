"""Matches of a pattern, by joins of the packed edge table with itself.

Rows: e1..em (edge ids), f1..fm and l1..lm (first, last activity), ts1..tsm (activity), x.. (nodes).
"""

from __future__ import annotations

import functools
import operator
from collections.abc import Iterable
from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.pattern import Pattern


def edge_columns(i: int) -> list[str]:
    return [f"e{i}", f"f{i}", f"l{i}", f"ts{i}"]


def side(edges: DataFrame, pattern: Pattern, i: int, nodes: DataFrame | None = None) -> DataFrame:
    """The edges that y_i can be, with its column names; labels and constants are filtered here."""
    a, b = pattern.edges[i - 1]
    df = edges
    if i <= len(pattern.edge_labels) and pattern.edge_labels[i - 1]:
        df = df.where(F.col("label") == pattern.edge_labels[i - 1])
    bound = dict(pattern.bound)
    for v, c in ((a, "src"), (b, "dst")):
        if v in bound:
            df = df.where(F.col(c) == bound[v])
    if a == b:
        df = df.where("src = dst")
    out = [F.col("eid").alias(f"e{i}"), F.col("first").alias(f"f{i}"), F.col("last").alias(f"l{i}"), F.col("ts").alias(f"ts{i}"), F.col("src").alias(a)]
    if a != b:
        out.append(F.col("dst").alias(b))
    df = df.select(out)
    for v, label in pattern.node_labels:
        if v in (a, b) and nodes is not None:
            df = df.join(nodes.where(F.col("label") == label).select(F.col("vid").alias(v)), v, "left_semi")
    return df


def extras(pattern: Pattern, have: Iterable[int], i: int) -> list[Column]:
    out = []
    for j in have:
        if pattern.break_symmetry:
            out.append(F.col(f"e{min(i, j)}") < F.col(f"e{max(i, j)}"))
        elif pattern.distinct_edges:
            out.append(F.col(f"e{i}") != F.col(f"e{j}"))
    return out


def _kept(rows: DataFrame, conditions: list[Column]) -> DataFrame:
    return rows.where(functools.reduce(operator.and_, conditions)) if conditions else rows


def extend(partial: DataFrame, right: DataFrame, pattern: Pattern, have: list[int], i: int, conditions: Iterable[Column] = ()) -> DataFrame:
    """Partial matches on ``have`` extended by y_i: an equi-join on the shared nodes; the rest are residual conditions, in a
    filter, since a later filter that Spark moves into the join would be tested before the join's own conditions."""
    shared = [v for v in dict.fromkeys(pattern.edges[i - 1]) if any(v in pattern.edges[j - 1] for j in have)]
    if not shared:
        raise ValueError("an edge without a shared node would make a Cartesian product")
    renamed = right.withColumnsRenamed({v: f"__{v}" for v in shared})
    if pattern.m == 2:  # a few edges make all matches at once: with a given number of tasks Spark doesn't merge them by the edges' size
        n = int(partial.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        partial, renamed = partial.repartition(n, *shared), renamed.repartition(n, *(f"__{v}" for v in shared))
    return _kept(partial.join(renamed, functools.reduce(operator.and_, [F.col(v) == F.col(f"__{v}") for v in shared])), extras(pattern, have, i) + list(conditions)).drop(*(f"__{v}" for v in shared))


def loose(pattern: Pattern) -> Pattern | None:
    """A pattern of two edges, each with a node of its own, without its tests on edges; None for other patterns."""
    if pattern.m != 2 or any(not set(pattern.edges[k]) - set(pattern.edges[1 - k]) for k in (0, 1)):
        return None
    return replace(pattern, distinct_edges=False, break_symmetry=False)


def alike(one: DataFrame, pattern: Pattern, i: int, bounds: bool = False) -> DataFrame:
    """One row for all of y_i's edges that have the same activity at the same shared node: what a rule says of one of
    them, it says of all.  The edges and their own nodes are in ``same{i}``.  ``bounds``: with the least e1 or the greatest e2."""
    here, there = set(pattern.edges[i - 1]), set(pattern.edges[2 - i])
    own = F.struct(F.col(f"e{i}"), *(F.col(v) for v in sorted(here - there)))
    bound = [(F.min("e1") if i == 1 else F.max("e2")).alias(f"e{i}")] if bounds else []
    return one.groupBy(*sorted(here & there), f"ts{i}", f"f{i}", f"l{i}").agg(F.collect_list(own).alias(f"same{i}"), *bound)


def each(rows: DataFrame, pattern: Pattern) -> DataFrame:
    """Matches of edges from matches of rows made by ``alike``, with the pattern's tests on edges."""
    for i in (1, 2):
        rows = rows.withColumn(f"one{i}", F.explode(f"same{i}")).drop(f"same{i}")
        rows = rows.withColumns({v: F.col(f"one{i}")[v] for v in [f"e{i}", *sorted(set(pattern.edges[i - 1]) - set(pattern.edges[2 - i]))]}).drop(f"one{i}")
    return _kept(rows, extras(pattern, [1], 2))


def halves(pattern: Pattern, order: tuple[int, ...]) -> tuple[tuple[int, ...], tuple[int, ...]] | None:
    """The order's two halves, if both hang together and share two nodes: then each is matched alone, and the open
    paths of a long cycle never exist."""
    a, b = order[: pattern.m // 2], order[pattern.m // 2 :]
    nodes = lambda part: {v for j in part for v in pattern.edges[j - 1]}
    return (a, b) if pattern.m >= 4 and len(nodes(a) & nodes(b)) >= 2 and pattern.is_connected_order(b) else None


def meet(left: DataFrame, right: DataFrame, pattern: Pattern, a: tuple[int, ...], b: tuple[int, ...], conditions: Iterable[Column] = ()) -> DataFrame:
    """Partial matches on ``a`` and on ``b`` joined on the nodes that they share."""
    bound = {v for j in a for v in pattern.edges[j - 1]}
    shared = [v for v in dict.fromkeys(v for j in b for v in pattern.edges[j - 1]) if v in bound]
    renamed = right.withColumnsRenamed({v: f"__{v}" for v in shared})
    rest = [c for j in b for c in extras(pattern, a, j)] + list(conditions)
    return _kept(left.join(renamed, functools.reduce(operator.and_, [F.col(v) == F.col(f"__{v}") for v in shared])), rest).drop(*(f"__{v}" for v in shared))


def _matched(tables: dict[int, DataFrame], pattern: Pattern, nodes: DataFrame | None, order: tuple[int, ...], predicates: Iterable[tuple[int, int, bool]], group: bool = False) -> DataFrame:
    """Matches whose y_i is in ``tables[i]``.  ``group``: for a ``loose`` pattern pairs of ``alike`` rows, for ``each`` after
    the rule; pairs that can't hold a match by their bounds are left out."""
    tests = lambda i, now: [F.col(f"f{a}") < F.col(f"f{b}") if strict else F.col(f"f{a}") <= F.col(f"f{b}") for a, b, strict in predicates if i in (a, b) and {a, b} <= now]

    if group:
        one, two = (alike(side(tables[i], pattern, i, nodes), pattern, i, pattern.break_symmetry) for i in (1, 2))
        ids = [F.col("e1") < F.col("e2")] if pattern.break_symmetry else []
        return extend(one, two, loose(pattern), [1], 2, ids + tests(2, {1, 2}))

    def grown(part: tuple[int, ...]) -> DataFrame:
        out, have = side(tables[part[0]], pattern, part[0], nodes), [part[0]]
        for i in part[1:]:
            out = extend(out, side(tables[i], pattern, i, nodes), pattern, have, i, tests(i, {*have, i}))
            have.append(i)
        return out

    parts = halves(pattern, order)
    if parts is None:
        return grown(order)
    a, b = parts
    across = [c for i in b for c in tests(i, {*a, i})]
    return meet(grown(a), grown(b), pattern, a, b, across)


def match(edges: DataFrame, pattern: Pattern, nodes: DataFrame | None = None, order: Iterable[int] | None = None, predicates: Iterable[tuple[int, int, bool]] = ()) -> DataFrame:
    """All matches.  ``predicates`` (i, j, strict): first(y_i) <= (or <) first(y_j), tested inside the joins."""
    order = tuple(order or pattern.join_order())
    return _matched(dict.fromkeys(range(1, pattern.m + 1), edges), pattern, nodes, order, list(predicates))


def match_alike(edges: DataFrame, pattern: Pattern, nodes: DataFrame | None = None, predicates: Iterable[tuple[int, int, bool]] = ()) -> DataFrame:
    """All matches of a ``loose`` pattern as pairs of ``alike`` rows.  ``predicates``: as for ``match``."""
    return _matched({1: edges, 2: edges}, pattern, nodes, (1, 2), list(predicates), True)


def _subsets(pattern: Pattern) -> list[tuple[int, ...]]:
    """Sets of edge variables that hang together, each in an order with connected prefixes."""
    found: dict[frozenset, tuple[int, ...]] = {frozenset([i]): (i,) for i in range(1, pattern.m + 1)}
    grown = list(found.values())
    for order in grown:  # the list grows
        nodes = {v for j in order for v in pattern.edges[j - 1]}
        for i in range(1, pattern.m + 1):
            have = frozenset([*order, i])
            if i not in order and nodes & set(pattern.edges[i - 1]) and have not in found:
                found[have] = (*order, i)
                grown.append(found[have])
    return grown


def partials(edges: DataFrame, pattern: Pattern, nodes: DataFrame | None = None, maximal: bool = False) -> DataFrame:
    """Connected partial matches: x.., e.. (null: unset) and ``have``, the edge variables that are set.
    ``maximal``: only those that no further edge extends; for reports, not for solving, as a partial match that
    stops being maximal can still be extended by a later edge."""
    out = None
    for order in _subsets(pattern):
        df, have = side(edges, pattern, order[0], nodes), [order[0]]
        for i in order[1:]:
            df = extend(df, side(edges, pattern, i, nodes), pattern, have, i)
            have.append(i)
        bound = {v for j in order for v in pattern.edges[j - 1]}
        if maximal:
            for i in range(1, pattern.m + 1):
                shared = [v for v in dict.fromkeys(pattern.edges[i - 1]) if v in bound]
                if i not in order and shared:
                    right = side(edges, pattern, i, nodes).select(F.col(f"e{i}"), *(F.col(v).alias(f"__{v}") for v in shared))
                    on = [F.col(v) == F.col(f"__{v}") for v in shared] + extras(pattern, have, i)
                    df = df.join(right, functools.reduce(operator.and_, on), "left_anti")
        unset = F.lit(None).cast("long")
        shown = [(F.col(v) if v in bound else unset).alias(v) for v in pattern.nodes] + [(F.col(f"e{i}") if i in order else unset).alias(f"e{i}") for i in range(1, pattern.m + 1)]
        df = df.select(F.lit(",".join(map(str, sorted(order)))).alias("have"), *shown)
        out = df if out is None else out.unionByName(df)
    return out


def grow_cycle(edges: DataFrame, m: int) -> DataFrame:
    """Cycles of m >= 3 nodes by growing nodes: the last one is drawn from the intersection of two neighbour
    lists, so open paths of m edges never exist.  Rows: x1..xm."""
    out = edges.groupBy("src").agg(F.collect_set("dst").alias("to"))
    into = edges.groupBy("dst").agg(F.collect_set("src").alias("from"))
    rows = edges.select(F.col("src").alias("x1"), F.col("dst").alias("x2"))
    for k in range(3, m):
        rows = rows.join(edges.select(F.col("src").alias(f"x{k - 1}"), F.col("dst").alias(f"x{k}")), f"x{k - 1}")
    rows = rows.join(out.withColumnRenamed("src", f"x{m - 1}"), f"x{m - 1}").join(into.withColumnRenamed("dst", "x1"), "x1")
    return rows.withColumn(f"x{m}", F.explode(F.array_intersect("to", "from"))).select(*(f"x{i}" for i in range(1, m + 1)))


def latest(pattern: Pattern, skip: Iterable[tuple[int, int]]) -> list[int]:
    """The variables that by ``skip`` (as for ``match_delta``) no other can come after: a match is complete when they are there."""
    skip, variables = set(skip), range(1, pattern.m + 1)
    return [j for j in variables if all((j, i) in skip for i in variables if i != j)]


def match_delta(old: DataFrame, new: DataFrame, both: DataFrame, pattern: Pattern, nodes: DataFrame | None = None, skip: Iterable[tuple[int, int]] = (), predicates: Iterable[tuple[int, int, bool]] = (), group: bool = False) -> DataFrame:
    """Matches with an edge of ``new``: for each i, y_i is new, the variables before it old, those after
    it any.  ``skip`` has pairs (i, j) where y_i can't come strictly before y_j: a term is dropped if it would
    need that (y_i new, so after all old ones, is no use if every such match fails the rule), and y_j is new if it
    can't come before y_i.  If some y_j is always latest, one term has it all: y_j new, the others any.  ``predicates``: as for ``match``;
    ``group``: pairs of ``alike`` rows, as by ``match_alike``."""
    out = None
    skip, predicates = set(skip), list(predicates)
    if end := latest(pattern, skip):
        return _matched({j: new if j in end else both for j in range(1, pattern.m + 1)}, pattern, nodes, _order_from(pattern, end[0]), predicates, group)
    for i in range(1, pattern.m + 1):
        # in this term y_j (j < i) is first active strictly before y_i
        if any((j, i) in skip for j in range(1, i)):
            continue
        tables = {j: new if j == i or (j, i) in skip else old if j < i else both for j in range(1, pattern.m + 1)}
        df = _matched(tables, pattern, nodes, _order_from(pattern, i), predicates, group)
        out = df if out is None else out.unionByName(df)
    if out is None:
        raise ValueError("the rule excludes every term")
    return out


def match_lasting(edges: DataFrame, low: int, high: int, pattern: Pattern, nodes: DataFrame | None = None, skip: Iterable[tuple[int, int]] = (), predicates: Iterable[tuple[int, int, bool]] = (), group: bool = False) -> DataFrame:
    """Matches complete after ``low`` and by ``high`` that are active after ``high``: for each i, y_i is, the variables
    before it aren't, and those after it may be, so that no other match is made.  Where halves meet, a term saves nothing in the
    half without y_i, so both are made once for all terms.  ``skip``, ``predicates`` and ``group``: as for ``match_delta``."""
    predicates, variables = list(predicates), range(1, pattern.m + 1)
    both, end = edges.where(F.col("first") <= high), latest(pattern, skip)
    if end and halves(pattern, order := _order_from(pattern, end[0])):
        tables = {j: both.where(F.col("first") > low) if j in end else both for j in variables}
        return _matched(tables, pattern, nodes, order, predicates).where(functools.reduce(operator.or_, [F.col(f"l{j}") > high for j in variables]))
    out = None
    for i in variables:
        tables = {j: both.where(F.col("last") > high) if j == i else both.where(F.col("last") <= high) if j < i else both for j in variables}
        tables |= {j: tables[j].where(F.col("first") > low) for j in end}
        df = _matched(tables, pattern, nodes, _order_from(pattern, i), predicates, group)
        df = df.where(F.array_max(F.array(*(F.col(f"f{j}") for j in variables))) > low)
        out = df if out is None else out.unionByName(df)
    return out


def _order_from(pattern: Pattern, i: int) -> tuple[int, ...]:
    order, seen = [i], set(pattern.edges[i - 1])
    while len(order) < pattern.m:
        j = next((j for j in range(1, pattern.m + 1) if j not in order and seen & set(pattern.edges[j - 1])), None)
        if j is None:
            raise ValueError("the pattern isn't connected")
        order.append(j)
        seen |= set(pattern.edges[j - 1])
    return tuple(order)


def count_paths(edges: DataFrame, m: int) -> DataFrame:
    """Number of paths of 2 or 3 edges from the nodes' degrees, without listing one."""
    into = edges.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("i"))
    out = edges.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("o"))
    if m == 2:
        return into.join(out, "v").agg(F.sum(F.col("i") * F.col("o")).alias("n"))
    if m == 3:
        mid = edges.select(F.col("src").alias("v"), F.col("dst").alias("w"))
        return mid.join(into, "v").join(out.withColumnRenamed("v", "w"), "w").agg(F.sum(F.col("i") * F.col("o")).alias("n"))
    raise ValueError("degrees tell paths of 2 or 3 edges")
