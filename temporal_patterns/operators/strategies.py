"""Three exact ways from a graph, a pattern and a rule to accepted matches.

``solve_full`` matches, then runs the rule.  ``solve_ondemand`` takes time in slabs: a match appears in the
slab of its latest first activity, catches up, and is dropped as soon as no run lives.  ``solve_staged``
adds one edge variable at a time in an order of first activity that the rule allows: partial matches carry
their runs, so that prefixes share work, and one whose runs have died before an edge's first activity isn't
joined with it.

All return the pattern's nodes x.. and edges e.. of accepted matches.
"""

from __future__ import annotations

import functools
import itertools
import operator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.analysis import feasible_orders, find_order, must_not_precede, only_firsts, safe_states
from ..functions.automaton import TimedRule
from ..functions.pattern import Pattern
from ..sources.graphs import TemporalGraph, domain, fresh, packed
from ..sources.storage import settle
from .matching import alike, each, extend, extras, halves, loose, match, match_alike, match_delta, match_lasting, meet, side
from .runners import Fold, decided, dense_word, latest_letter, once, word


def result_columns(pattern: Pattern) -> list[str]:
    return [*pattern.nodes, *(f"e{i}" for i in range(1, pattern.m + 1))]


def _prepared(g: TemporalGraph, rule: TimedRule, early: bool = False) -> tuple[DataFrame, Fold, Column | None]:
    """Packed edges, the compiled rule, and the domain's size where the rule needs it."""
    fold = Fold(rule, early=early)
    edges = packed(g, ranked=fold.kind == "filter")
    n = F.lit(domain(g).count()).cast("long") if fold.kind == "filter" else None
    return edges, fold, n


def verdicts(g: TemporalGraph, pattern: Pattern, rule: TimedRule, early: bool = False) -> DataFrame:
    """All matches with ``word`` and ``accepted``."""
    edges, fold, n = _prepared(g, rule, early)
    rows = match(edges, pattern, g.nodes)
    if fold.kind == "general":
        all_ = domain(g).agg(F.array_sort(F.collect_list(F.struct("t", "r"))).alias("__domain"))  # one row
        rows = rows.join(F.broadcast(all_)).withColumn("word", dense_word(word(pattern.m), F.col("__domain"))).drop("__domain")
    else:
        rows = rows.withColumn("word", word(pattern.m))
    return rows.withColumn("accepted", fold.accepted(fold.run(F.col("word")), n))


def first_order(rule: TimedRule) -> list[tuple[int, int, bool]]:
    """Orders of first activity that every accepted match has, as tests inside the joins."""
    return [(j, i, False) for i, j in sorted(must_not_precede(rule))]


def _grouped(pattern: Pattern, fold: Fold) -> bool:
    """Whether the rule runs, and can once for all edges of equal activity."""
    return loose(pattern) is not None and not (fold.kind == "neutral" and only_firsts(fold.rule))


def solve_full(g: TemporalGraph, pattern: Pattern, rule: TimedRule, early: bool = False) -> DataFrame:
    if rule.empty_letter() == "general":
        return verdicts(g, pattern, rule, early).where("accepted").select(result_columns(pattern))
    edges, fold, n = _prepared(g, rule, early)
    if _grouped(pattern, fold):
        return each(match_alike(edges, pattern, g.nodes, first_order(rule)).where(decided(fold, n)), pattern).select(result_columns(pattern))
    return match(edges, pattern, g.nodes, predicates=first_order(rule)).where(decided(fold, n)).select(result_columns(pattern))


def slim(edges: DataFrame) -> DataFrame:
    """Edges whose activity is left out if it is one time, which ``first`` says; for activity without ranks."""
    return edges.withColumn("ts", F.when(F.col("first") < F.col("last"), F.col("ts")))


def filled(rows: DataFrame, m: int) -> DataFrame:
    """Matches of ``slim`` edges with all their activity."""
    time = lambda i: F.array(F.struct(F.col(f"f{i}").alias("t"), F.lit(0).cast("long").alias("r")))
    return rows.withColumns({f"ts{i}": F.coalesce(f"ts{i}", time(i)) for i in range(1, m + 1)})


def slab_plan(edges: DataFrame, slabs: int) -> list[int]:
    """Upper ends of time slabs with about equal numbers of new edges."""
    ends = edges.agg(F.percentile_approx("first", [k / slabs for k in range(1, slabs)] or [1.0]), F.max("last")).first()
    return sorted({*(ends[0] or []), ends[1]} - {None}) if ends[1] is not None else []


def solve_ondemand(g: TemporalGraph, pattern: Pattern, rule: TimedRule, slabs: int = 4, early: bool = True, prune_terms: bool = True) -> DataFrame:
    """The live matches and their configurations are a written table between slabs."""
    edges, fold, n = _prepared(g, rule)
    if fold.kind == "general":
        return solve_full(g, pattern, rule)
    m, names, group = pattern.m, result_columns(pattern), _grouped(pattern, fold)
    shared = [v for v in pattern.nodes if all(v in e for e in pattern.edges)]
    keep = [*((*shared, "same1", "same2") if group else names), *(f"ts{i}" for i in range(1, m + 1))]
    listed = lambda rows: (each(rows, pattern) if group else rows).select(names)
    bare = fold.kind == "neutral"  # partial matches of edges active once travel without activity
    whole = lambda rows: filled(rows, m) if bare else rows
    edges = settle(slim(edges) if bare else edges, "packed")  # each slab joins it anew
    skip, tests = (must_not_precede(rule), first_order(rule)) if prune_terms else (set(), [])
    safe = safe_states(rule) if early else frozenset()
    live, done, low = None, [], 0
    for high in slab_plan(edges, slabs):
        old, new, both = (edges.where(F.col("first") <= low), edges.where((F.col("first") > low) & (F.col("first") <= high)), edges.where(F.col("first") <= high))
        if early and fold.kind == "neutral":  # matches without activity after the slab are decided at the end and never stored
            ended = [df.where(F.col("last") <= high) for df in (old, new, both)]
            done.append(listed(whole(match_delta(*ended, pattern, g.nodes, skip, tests, group)).where(decided(fold))))
            added = whole(match_lasting(edges, low, high, pattern, g.nodes, skip, tests, group)).where(fold.balanced())
        else:
            added = whole(match_delta(old, new, both, pattern, g.nodes, skip, tests, group))
        added = added.select(*keep)
        # letters before the slab are read from the history: that is the catch-up
        rows = added.withColumn("acc", fold.run(word(m, high=F.lit(high + 1))))
        if live is not None:
            rows = live.withColumn("acc", fold.run(word(m, low=F.lit(low + 1), high=F.lit(high + 1)), F.col("acc"))).unionByName(rows)
        if early:
            rows = rows.where(fold.alive(F.col("acc")))
        rows = settle(rows, "slab")
        if safe and fold.kind == "neutral":
            done.append(listed(rows.where(fold.within(F.col("acc"), safe))))
            rows = rows.where(~fold.within(F.col("acc"), safe))
        live, low = rows, high
    if live is None:
        return solve_full(g, pattern, rule)
    out = listed(live.where(fold.accepted(F.col("acc"), n)))
    for d in done:
        out = out.unionByName(d)
    return out


def _pass(edges: DataFrame, g: TemporalGraph, pattern: Pattern, fold: Fold, n: Column | None, order: tuple[int, ...], ties_by_number: bool, share: bool) -> DataFrame:
    """Accepted matches whose first activities come in this order."""
    m, free = pattern.m, loose(pattern)
    table = lambda i: alike(side(edges, pattern, i, g.nodes), pattern, i) if free else side(edges, pattern, i, g.nodes)
    rows, have = table(order[0]), [order[0]]
    rows = rows.withColumn("acc", fold.start())
    parts = halves(pattern, order)
    plain = share and fold.kind == "neutral" and only_firsts(fold.rule)  # the order of first activities says what the runs would
    for i in order[1:]:
        last = have[-1]
        f, here = F.col(f"f{i}"), F.col(f"f{last}")
        tie = here <= f if not ties_by_number or i > last else here < f
        conditions = [tie]
        if not plain:
            # the partial's runs at each of its letters from its latest edge on, once for all extensions
            letters = word(m, low=here, variables=tuple(have))
            at = lambda t, acc: F.struct(t.alias("t"), acc.alias("acc"))
            begin = F.array(at(F.lit(0).cast("long"), F.col("acc")))
            history = F.aggregate(letters, begin, lambda h, x: F.concat(h, F.array(at(x["t"], fold.step(F.element_at(h, -1)["acc"], x)))))
            ends = F.filter("history", lambda h: ~fold.alive(h["acc"]))
            death = F.when(F.size(ends) > 0, F.element_at(ends, 1)["t"]).otherwise(F.lit((1 << 62)))
            if fold.kind == "neutral":  # edges active once each have one letter from there on: no word is sorted, no array searched
                single, after = once(have), fold.step(F.col("acc"), latest_letter(tuple(have)))
                history = F.when(single, F.array(at(F.lit(0).cast("long"), F.col("acc")), at(here, after))).otherwise(history)
                death = F.when(single, F.when(fold.alive(after), F.lit(1 << 62)).otherwise(here)).otherwise(death)
            rows = rows.withColumn("history", history).withColumn("death", death)
            conditions += [f <= F.col("death")] if share else []
        if parts and tuple(have) == parts[0]:
            # the edges left close a cycle: they meet it at once, and the runs go on from the first of them
            rest = side(edges, pattern, i, g.nodes)
            for k, j in zip(parts[1], parts[1][1:]):
                after = F.col(f"f{k}") <= F.col(f"f{j}") if not ties_by_number or j > k else F.col(f"f{k}") < F.col(f"f{j}")
                rest = extend(rest, side(edges, pattern, j, g.nodes), pattern, list(parts[1][: parts[1].index(j)]), j, [after])
            rows = meet(rows, rest, pattern, *parts, conditions)
        else:
            rows = extend(rows, table(i), free or pattern, have, i, conditions)
        if not plain:  # the configurations just before the new edge is first active
            rows = rows.withColumn("acc", F.element_at(F.filter("history", lambda h: h["t"] < f), -1)["acc"]).drop("history", "death")
        have.append(i)
        if parts and i == parts[1][0]:
            break
    rows = rows.where(decided(fold, n, F.col(f"f{have[-1]}"), F.col("acc")))
    return (each(rows, pattern) if free else rows).select(result_columns(pattern))


def staged_orders(pattern: Pattern, rule: TimedRule) -> tuple[list[tuple[int, ...]], bool] | None:
    """One compatible order, or all feasible permutations (disjoint by their ties); None if some prefix would
    have to be disconnected."""
    order = find_order(pattern, rule)
    if order is not None:
        return [order], False
    orders = feasible_orders(rule)
    if all(pattern.is_connected_order(p) for p in orders):
        return orders, True
    return None


def solve_staged(g: TemporalGraph, pattern: Pattern, rule: TimedRule, order: tuple[int, ...] | None = None, share: bool = True) -> DataFrame:
    """``order``: of first activity, if known; ``share=False`` leaves the liveness test out of the joins."""
    edges, fold, n = _prepared(g, rule)
    plan = ([order], False) if order else staged_orders(pattern, rule)
    if plan is None or fold.kind == "general":
        raise ValueError("no order of first activity keeps the prefixes connected; use solve_ondemand")
    out = None
    for p in plan[0]:
        one = _pass(edges, g, pattern, fold, n, p, plan[1], share)
        out = one if out is None else out.unionByName(one)
    if out is None:  # the rule accepts no match
        return match(edges, pattern, g.nodes).where(F.lit(False)).select(result_columns(pattern))
    return out


def _joined(base: DataFrame, right: DataFrame, pattern: Pattern, have: list[int], i: int, most: int) -> DataFrame:
    """``extend``, or a product where y_i shares no node with the partial match: only while it has ``most`` rows or fewer."""
    nodes = {v for j in have for v in pattern.edges[j - 1]}
    conditions = [(F.col(f"f{j}") <= F.col(f"f{i}")) if j < i else (F.col(f"f{j}") < F.col(f"f{i}")) for j in have]
    if nodes & set(pattern.edges[i - 1]):
        return extend(base, right, pattern, have, i, conditions)
    size = base.count() * right.count()
    if size > most:
        raise ValueError(f"partial matches without a shared node would make {size} rows; use solve_staged or solve_ondemand")
    return base.join(right, functools.reduce(operator.and_, conditions + extras(pattern, have, i)))


def solve_partial(g: TemporalGraph, pattern: Pattern, rule: TimedRule, slabs: int = 2, most: int = 1_000_000) -> DataFrame:
    """All live partial matches, of every set of edge variables, connected or not, through slabs of time.

    A match is built once, by its edges in order of (first activity, number); its partial match must have a run
    that lives just before each further edge comes.  Partial matches that aren't connected grow with products, so this
    is for graphs small enough for ``most``; the planner never chooses it."""
    edges, fold, n = _prepared(g, rule)
    if fold.kind == "general":
        raise ValueError("empty letters move the rule; use solve_full")
    m = pattern.m
    sets = [s for k in range(1, m + 1) for s in itertools.combinations(range(1, m + 1), k)]
    live: dict[tuple[int, ...], DataFrame] = {}
    low = 0
    for high in slab_plan(edges, slabs):
        new = fresh(edges, low, high)
        made: dict[tuple[int, ...], DataFrame] = {}
        for have in sets:
            ways = []
            for i in have:  # the latest edge
                right, rest = side(new, pattern, i, g.nodes), tuple(j for j in have if j != i)
                if not rest:
                    ways.append(right.withColumn("acc", fold.start()))
                for base in (live.get(rest), made.get(rest)):
                    if base is not None:
                        rows = _joined(base, right, pattern, list(rest), i, most)
                        ways.append(rows.where(fold.alive(fold.run(word(m, low=F.lit(low + 1), high=F.col(f"f{i}"), variables=rest), F.col("acc")))))
            made[have] = functools.reduce(DataFrame.unionByName, ways)
        for have in sets:
            rows = made[have] if have not in live else live[have].unionByName(made[have])
            rows = rows.withColumn("acc", fold.run(word(m, low=F.lit(low + 1), high=F.lit(high + 1), variables=have), F.col("acc")))
            made[have] = settle(rows.where(fold.alive(F.col("acc"))), "partial")
        live, low = made, high
    if not live:
        return solve_full(g, pattern, rule)
    return live[sets[-1]].where(fold.accepted(F.col("acc"), n)).select(result_columns(pattern))


def run_dataflow(g: TemporalGraph, pattern: Pattern, rule: TimedRule, every: int = 8) -> DataFrame:
    """The rule as a join per timepoint: states and clocks as rows, joined with the moves of their letter.
    The number of jobs grows with the domain; kept as the reference form for small ones."""
    from ..functions import formula as fm

    spark = g.edges.sparkSession
    m, names = pattern.m, result_columns(pattern)
    clocks = [f"c_{x}" for x in rule.clocks]
    moves = spark.createDataFrame([(v.source, a, k, v.target) for k, v in enumerate(rule.moves) for a in v.letters], "s int, a int, move int, s2 int")
    rows = match(packed(g), pattern, g.nodes).select(names).withColumns({"s": F.lit(rule.start), **{c: F.lit(0).cast("long") for c in clocks}})
    for step, (t,) in enumerate(domain(g).orderBy("t").select("t").collect(), 1):
        now = g.active.where(F.col("t") == t).select("eid")
        bit = F.lit(0)
        for i in range(1, m + 1):
            rows = rows.join(now.withColumnRenamed("eid", f"__n{i}"), F.col(f"e{i}") == F.col(f"__n{i}"), "left")
            bit = bit + F.when(F.col(f"__n{i}").isNotNull(), 1 << (i - 1)).otherwise(0)
        rows = rows.withColumn("a", bit).drop(*(f"__n{i}" for i in range(1, m + 1))).join(F.broadcast(moves), ["s", "a"])
        ok, reset = F.lit(True), {c: F.col(c) for c in clocks}
        for k, v in enumerate(rule.moves):
            if v.guard:
                ok = F.when(F.col("move") == k, fm.guard_column(fm.guard(v.guard), {x: F.lit(t) - F.col(f"c_{x}") for x in rule.clocks})).otherwise(ok)
            for x in v.resets:
                reset[f"c_{x}"] = F.when(F.col("move") == k, F.lit(t).cast("long")).otherwise(reset[f"c_{x}"])
        rows = rows.where(ok).select(*names, F.col("s2").alias("s"), *(c.alias(k) for k, c in reset.items())).distinct()
        if step % every == 0:
            rows = settle(rows, "states")
    return rows.where(F.col("s").isin(sorted(rule.accepting))).select(names).distinct()
