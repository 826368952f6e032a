"""Timed rules: automata over sets of edge variables, with clocks.

A rule reads the word of a match: at each timepoint of the graph's domain the set of the match's edges
that are active then (a bit mask).  Clocks run with time; a clock that was never reset reads the time
since the origin.  An automaton without clocks is a plain NFA.
"""

from __future__ import annotations

import json
from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from . import formula as fm


@dataclass(frozen=True)
class Move:
    source: int
    letters: frozenset[int]
    target: int
    guard: str = ""
    resets: tuple[str, ...] = ()


@dataclass(frozen=True)
class TimedRule:
    m: int
    states: int
    accepting: frozenset[int]
    moves: tuple[Move, ...]
    start: int = 0
    clocks: tuple[str, ...] = ()
    name: str = field(default="rule", compare=False)

    @classmethod
    def of(cls, m: int, states: int, accepting: Iterable[int], moves: Iterable[tuple], clocks: Iterable[str] = (), name: str = "rule") -> TimedRule:
        """Moves are (source, letter formula or masks, target[, guard[, resets]])."""
        made = [Move(s, fm.letters(a, m) if isinstance(a, str) else frozenset(a), t, *more) for s, a, t, *more in moves]
        return cls(m, states, frozenset(accepting), tuple(made), 0, tuple(clocks), name)

    @property
    def is_clockless(self) -> bool:
        return not self.clocks

    def by_letter(self) -> dict[tuple[int, int], list[Move]]:
        out: dict[tuple[int, int], list[Move]] = {}
        for mv in self.moves:
            for a in mv.letters:
                out.setdefault((mv.source, a), []).append(mv)
        return out

    def step(self, configs: set[tuple], t: float, a: int) -> set[tuple]:
        out = set()
        for s, c in configs:
            for mv in self.moves:
                if mv.source == s and a in mv.letters and fm.guard_holds(fm.guard(mv.guard), {x: t - v for x, v in zip(self.clocks, c)}):
                    out.add((mv.target, tuple(t if x in mv.resets else v for x, v in zip(self.clocks, c))))
        return out

    def accepts(self, word: Iterable[tuple[float, int]]) -> bool:
        """Reference interpreter: ``word`` has (time, mask) at every timepoint of the domain."""
        configs = {(self.start, (0,) * len(self.clocks))}
        for t, a in word:
            configs = self.step(configs, t, a)
        return any(s in self.accepting for s, _ in configs)

    def empty_letter(self) -> str:
        """How the empty letter acts: ``neutral`` (nothing changes), ``filter`` (states without a loop on it
        die) or ``general``."""
        loops, other = set(), False
        for mv in self.moves:
            if 0 in mv.letters:
                if mv.target == mv.source and not mv.guard and not mv.resets:
                    loops.add(mv.source)
                else:
                    other = True
        if other:
            return "general"
        return "neutral" if len(loops) == self.states else "filter"

    def idle_states(self) -> frozenset[int]:
        return frozenset(mv.source for mv in self.moves if 0 in mv.letters and mv.target == mv.source)

    def to_relation(self, spark: SparkSession) -> DataFrame:
        """One row per state, letter and move: s, a, guard, resets, s2."""
        rows = [(mv.source, a, mv.guard, [self.clocks.index(x) for x in mv.resets], mv.target) for mv in self.moves for a in sorted(mv.letters)]
        return spark.createDataFrame(rows, "s int, a int, guard string, resets array<int>, s2 int")

    def to_json(self) -> str:
        return json.dumps({"m": self.m, "states": self.states, "accepting": sorted(self.accepting), "clocks": self.clocks, "name": self.name, "moves": [[v.source, sorted(v.letters), v.target, v.guard, v.resets] for v in self.moves]})

    @classmethod
    def from_json(cls, text: str) -> TimedRule:
        d = json.loads(text)
        return cls.of(d["m"], d["states"], d["accepting"], [(s, a, t, g, tuple(r)) for s, a, t, g, r in d["moves"]], d["clocks"], d["name"])

    def dot(self) -> str:
        lines = [f'  {s} [shape={"doublecircle" if s in self.accepting else "circle"}];' for s in range(self.states)]
        lines += [f'  {v.source} -> {v.target} [label="{sorted(v.letters)} {v.guard} {",".join(v.resets)}"];' for v in self.moves]
        return "digraph {\n" + "\n".join(lines) + "\n}"


def unfold(rule: TimedRule, times: int) -> TimedRule:
    """The same language with the states doubled ``times`` times: each move goes to the other copy."""
    for _ in range(times):
        n = rule.states
        moves = [Move(v.source + k * n, v.letters, v.target + (1 - k) * n, v.guard, v.resets) for v in rule.moves for k in (0, 1)]
        # the empty letter's loops stay loops, so that it remains neutral
        moves = [Move(v.source, frozenset([0]), v.source, v.guard, v.resets) if w.target == w.source and a == 0 else Move(v.source, frozenset([a]), v.target, v.guard, v.resets) for v, w in zip(moves, [x for x in rule.moves for _ in (0, 1)]) for a in v.letters]
        rule = TimedRule(rule.m, 2 * n, rule.accepting | {s + n for s in rule.accepting}, tuple(moves), rule.start, rule.clocks, rule.name)
    return rule


def with_idle_clocks(rule: TimedRule, n: int) -> TimedRule:
    """The same language with ``n`` clocks more, reset on every move with a letter and never read."""
    own = tuple(f"idle{i}" for i in range(n))
    moves = []
    for v in rule.moves:
        busy = v.letters - {0} if v.source == v.target else v.letters
        moves += [Move(v.source, busy, v.target, v.guard, v.resets + own)] if busy else []
        moves += [Move(v.source, frozenset([0]), v.target, v.guard, v.resets)] if 0 in v.letters and v.source == v.target else []
    return TimedRule(rule.m, rule.states, rule.accepting, tuple(moves), rule.start, rule.clocks + own, rule.name)


def intersect(rule: TimedRule, other: TimedRule) -> TimedRule:
    """Words that both accept; clocks of the second are renamed apart."""
    fix = lambda x: f"o_{x}"
    number = lambda s, t: s * other.states + t
    moves = []
    for v in rule.moves:
        for w in other.moves:
            common = v.letters & w.letters
            if common:
                renamed = w.guard
                for x in sorted(other.clocks, key=len, reverse=True):
                    renamed = renamed.replace(x, fix(x))
                text = f"({v.guard}) & ({renamed})" if v.guard and renamed else v.guard or renamed
                moves.append(Move(number(v.source, w.source), common, number(v.target, w.target), text, v.resets + tuple(map(fix, w.resets))))
    accepting = frozenset(number(s, t) for s in rule.accepting for t in other.accepting)
    return TimedRule(rule.m, rule.states * other.states, accepting, tuple(moves), number(rule.start, other.start), rule.clocks + tuple(map(fix, other.clocks)), rule.name)
