"""Running a rule over the words of matches, inside their rows.

A word is an array of (t, r, a): time, rank in the domain, mask of the active edges.  Timepoints without
an active edge are left out ("sparse") whenever the rule allows: if the empty letter changes nothing, or if
it only ends runs in some states, which shows as a jump of the rank.  Clocks are kept as the time of
their last reset, so nothing is rewritten as time goes by.

``fold`` keeps a set of states as the bits of a long (no clocks) or an array of configurations, and is a
single ``aggregate`` expression; ``table`` looks moves up in an array literal, for rules of many states.
"""

from __future__ import annotations

import functools
import operator
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import formula as fm
from ..functions.analysis import balance, dead_states, only_firsts, safe_states, weak_orders
from ..functions.automaton import TimedRule


def _merged(line: Column, m: int) -> Column:
    """Letters from a sorted array of (t, r, bit): at most ``m`` neighbours share a time, and the last of them
    gets the sum of their bits."""
    letter = lambda x, i: F.struct(x["t"].alias("t"), x["r"].alias("r"), functools.reduce(operator.add, [x["bit"], *(F.when(F.get(line, i - k)["t"] == x["t"], F.get(line, i - k)["bit"]).otherwise(0) for k in range(1, m))]).alias("a"))
    last = lambda i: F.coalesce(F.get(line, i + 1)["t"] != F.get(line, i)["t"], F.lit(True))
    return F.filter(F.transform(line, lambda x, i: F.when(last(i), letter(x, i))), lambda y: y.isNotNull())


def word(m: int, low: Column | None = None, high: Column | None = None, variables: tuple[int, ...] | None = None) -> Column:
    """The sparse word of columns ts1..tsm, at times from ``low`` and before ``high``.  With ``variables``
    only these edges exist yet."""
    use = variables or tuple(range(1, m + 1))

    def times(i: int) -> Column:
        ts = F.col(f"ts{i}")
        if low is not None:
            ts = F.filter(ts, lambda x: x["t"] >= low)
        if high is not None:
            ts = F.filter(ts, lambda x: x["t"] < high)
        return F.transform(ts, lambda x: F.struct(x["t"].alias("t"), x["r"].alias("r"), F.lit(1 << (i - 1)).alias("bit")))

    line = F.array_sort(F.concat(*map(times, use)))
    # the array is bound to a name, or it would be sorted anew for every element
    return F.element_at(F.transform(F.array(line), lambda bound: _merged(bound, len(use))), 1)


def configurations_at(letters: Column, fold: Fold, t: Column) -> Column:
    """The runs after all letters up to time ``t``."""
    return fold.run(F.filter(letters, lambda x: x["t"] <= t))


def exploded_word(matches: DataFrame, active: DataFrame, m: int) -> DataFrame:
    """Words by a shuffle of the activity of all matches, for edges whose activity is too long for a row:
    ``matches`` has e1..em; the result has e1..em and word (without ranks)."""
    keys = [f"e{i}" for i in range(1, m + 1)]
    ids = F.explode(F.array(*(F.struct(F.col(k).alias("eid"), F.lit(1 << i).alias("bit")) for i, k in enumerate(keys))))
    rows = matches.select(*keys, ids.alias("x")).select(*keys, "x.eid", "x.bit").join(active, "eid")
    rows = rows.groupBy(*keys, "t").agg(F.bit_or("bit").alias("a"))
    return rows.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("t", F.lit(0).cast("long").alias("r"), "a"))).alias("word"))


def dense_word(sparse: Column, domain: Column) -> Column:
    """The word at every timepoint of the domain (an array of (t, r)), for rules that the empty letter moves."""
    at = lambda x: F.aggregate(F.filter(sparse, lambda y: y["t"] == x["t"]), F.lit(0), lambda s, y: y["a"])
    return F.transform(domain, lambda x: F.struct(x["t"].alias("t"), x["r"].alias("r"), at(x).alias("a")))


class Fold:
    """A rule compiled to expressions over an accumulator struct (r: last rank, q: configurations)."""

    def __init__(self, rule: TimedRule, encoding: str = "case", early: bool = False):
        """``early``: letters after the one that decides the rule change nothing and are passed over."""
        self.rule = rule
        self.early = early
        self.safe = safe_states(rule) if early else frozenset()
        self.kind = rule.empty_letter()
        self.bits = rule.is_clockless and rule.states <= 62
        self.encoding = "table" if encoding == "case" and self.bits and len(rule.by_letter()) > 40 else encoding
        self.live = [s for s in range(rule.states) if s not in dead_states(rule)]

    def start(self) -> Column:
        q = F.lit(1 << self.rule.start).cast("long") if self.bits else F.array(self._config(F.lit(self.rule.start), [F.lit(0).cast("long")] * len(self.rule.clocks)))
        return self._acc(F.lit(0).cast("long"), q)

    @staticmethod
    def _acc(r: Column, q: Column) -> Column:
        return F.struct(r.alias("r"), q.alias("q"))

    def _config(self, s: Column, clocks: list[Column]) -> Column:
        c = F.array(*clocks) if clocks else F.array().cast("array<bigint>")
        return F.struct(s.cast("int").alias("s"), c.alias("c"))

    def _idle(self, q: Column) -> Column:
        """What is left of the configurations after empty letters."""
        keep = sorted(self.rule.idle_states())
        if self.bits:
            return q.bitwiseAND(F.lit(sum(1 << s for s in keep)).cast("long"))
        return F.filter(q, lambda x: x["s"].isin(keep) if keep else F.lit(False))

    def step(self, acc: Column, x: Column) -> Column:
        q = acc["q"]
        if self.kind == "filter":
            q = F.when(x["r"] > acc["r"] + 1, self._idle(q)).otherwise(q)
        moved = self._move_bits(q, x["a"]) if self.bits else self._move(q, x)
        if self.early:
            now = self._acc(x["r"], q)
            stays = ~self.alive(now) | self.within(now, self.safe) if self.safe else ~self.alive(now)
            moved = F.when(stays, q).otherwise(moved)
        return self._acc(x["r"], moved)

    def _move_bits(self, q: Column, a: Column) -> Column:
        targets: dict[tuple[int, int], int] = {}
        for (s, letter), moves in self.rule.by_letter().items():
            targets[s, letter] = sum(1 << t for t in {v.target for v in moves})
        n = self.rule.states
        if self.encoding == "table":
            size = 1 << self.rule.m
            table = F.array(*(F.lit(targets.get((s, letter), 0)).cast("long") for s in range(n) for letter in range(size)))
            return F.aggregate(F.sequence(F.lit(0), F.lit(n - 1)), F.lit(0).cast("long"), lambda out, s: F.when(F.getbit(q, s) == 1, out.bitwiseOR(F.element_at(table, s * size + a + 1))).otherwise(out))
        by_letter = None
        for letter in range(1 << self.rule.m):
            bits = [F.when(q.bitwiseAND(F.lit(1 << s)) != 0, F.lit(targets[s, letter])).otherwise(F.lit(0)).cast("long") for s in range(n) if targets.get((s, letter))]
            value = functools.reduce(lambda p, r: p.bitwiseOR(r), bits) if bits else F.lit(0).cast("long")
            by_letter = F.when(a == letter, value) if by_letter is None else by_letter.when(a == letter, value)
        return by_letter

    def _move(self, q: Column, x: Column) -> Column:
        rule = self.rule

        def follow(c: Column) -> Column:
            made = []
            for v in rule.moves:
                elapsed = {name: x["t"] - c["c"][i] for i, name in enumerate(rule.clocks)}
                ok = (c["s"] == v.source) & x["a"].isin(sorted(v.letters)) & fm.guard_column(fm.guard(v.guard), elapsed)
                clocks = [x["t"] if name in v.resets else c["c"][i] for i, name in enumerate(rule.clocks)]
                made.append(F.when(ok, self._config(F.lit(v.target), clocks)))
            return F.filter(F.array(*made), lambda y: y.isNotNull())

        return F.array_distinct(F.flatten(F.transform(q, follow)))

    def run(self, letters: Column, acc: Column | None = None) -> Column:
        return F.aggregate(letters, self.start() if acc is None else acc, self.step)

    def alive(self, acc: Column) -> Column:
        """Some run can still be accepted."""
        if self.bits:
            return acc["q"].bitwiseAND(F.lit(sum(1 << s for s in self.live)).cast("long")) != 0
        return F.exists(acc["q"], lambda x: x["s"].isin(self.live) if self.live else F.lit(False))

    def within(self, acc: Column, states) -> Column:
        """Some run is in one of the states."""
        states = sorted(states)
        if self.bits:
            return acc["q"].bitwiseAND(F.lit(sum(1 << s for s in states)).cast("long")) != 0
        return F.exists(acc["q"], lambda x: x["s"].isin(states) if states else F.lit(False))

    def accepted(self, acc: Column, domain_size: Column | None = None) -> Column:
        if self.kind == "filter":
            acc = self._acc(acc["r"], F.when(acc["r"] < domain_size, self._idle(acc["q"])).otherwise(acc["q"]))
        return self.within(acc, self.rule.accepting)

    def _once(self, blocks: list[tuple[int, ...]]) -> dict[int, Column | None]:
        """States after y_1..y_m were active once each in this order, with their condition on clocks (None: none)."""
        rule = self.rule
        moves = rule.by_letter()
        configs: dict[tuple[int, tuple[int, ...]], Column | None] = {(rule.start, (0,) * len(rule.clocks)): None}
        at = lambda i: F.col(f"f{i}") if i else F.lit(0).cast("long")
        for block in blocks:
            made: dict[tuple[int, tuple[int, ...]], Column | None] = {}
            for (s, resets), condition in configs.items():
                for v in moves.get((s, sum(1 << (i - 1) for i in block)), ()):
                    ok = condition
                    if v.guard:
                        holds = fm.guard_column(fm.guard(v.guard), {x: at(block[0]) - at(i) for x, i in zip(rule.clocks, resets)})
                        ok = holds if ok is None else ok & holds
                    key = (v.target, tuple(block[0] if x in v.resets else i for x, i in zip(rule.clocks, resets)))
                    made[key] = ok if key not in made else None if ok is None or made[key] is None else made[key] | ok
            configs = made
        out: dict[int, Column | None] = {}
        for (s, _), ok in configs.items():
            out[s] = ok if s not in out else None if ok is None or out[s] is None else out[s] | ok
        return out

    @staticmethod
    def _ordered(blocks: list[tuple[int, ...]]) -> Column:
        f = lambda i: F.col(f"f{i}")
        ties = [f(b[0]) == f(i) for b in blocks for i in b[1:]]
        return functools.reduce(operator.and_, ties + [f(a[0]) < f(b[0]) for a, b in zip(blocks, blocks[1:])], F.lit(True))

    def accepted_once(self) -> Column:
        """``accepted`` for a match whose edges are active once each, at f1..fm: comparisons, without a word.
        For rules that ignore empty letters."""
        ways = []
        for blocks in weak_orders(self.rule.m):
            states = {s: ok for s, ok in self._once(blocks).items() if s in self.rule.accepting}
            if states:
                conditions = list(states.values())
                here = self._ordered(blocks)
                ways.append(here if any(c is None for c in conditions) else here & functools.reduce(operator.or_, conditions))
        return functools.reduce(operator.or_, ways) if ways else F.lit(False)

    def run_once(self) -> Column:
        """``run`` for such a match, for rules without clocks whose states are bits."""
        q = None
        for blocks in weak_orders(self.rule.m):
            bits = F.lit(sum(1 << s for s in self._once(blocks))).cast("long")
            q = F.when(self._ordered(blocks), bits) if q is None else q.when(self._ordered(blocks), bits)
        return self._acc(F.lit(0).cast("long"), q.otherwise(F.lit(0).cast("long")))

    def balanced(self) -> Column:
        """Whether the edges' numbers of activities allow acceptance at all."""
        out = F.lit(True)
        for (i, j), (low, high) in balance(self.rule).items():
            more = F.size(f"ts{i}") - F.size(f"ts{j}")
            out = out if low is None else out & (more >= low)
            out = out if high is None else out & (more <= high)
        return out


def once(variables: Iterable[int]) -> Column:
    """Each of these edges is active once."""
    return functools.reduce(operator.and_, [F.col(f"f{i}") == F.col(f"l{i}") for i in variables])


def latest_letter(order: tuple[int, ...]) -> Column:
    """What the word of edges active once each, first active in this order, has from the last one's first activity on."""
    here = F.col(f"f{order[-1]}")
    mask = functools.reduce(operator.add, [F.when(F.col(f"f{i}") == here, 1 << (i - 1)).otherwise(0) for i in order])
    return F.struct(here.alias("t"), F.lit(0).cast("long").alias("r"), mask.alias("a"))


def decided(fold: Fold, domain_size: Column | None = None, low: Column | None = None, acc: Column | None = None) -> Column:
    """Acceptance of whole matches, those from runs ``acc`` before ``low``.  Where the rule ignores empty letters, edges
    active once each are compared, and what the numbers of activities exclude isn't run: a word is made for the others only."""
    m = fold.rule.m
    slow = fold.accepted(fold.run(word(m, low=low), acc), domain_size)
    if fold.kind != "neutral":
        return slow
    if only_firsts(fold.rule):
        return fold.accepted_once()
    return F.when(once(range(1, m + 1)), fold.accepted_once()).otherwise(fold.balanced() & slow)


def letters_text(letters: Column) -> Column:
    """The word as text: letter k as the k-th character from 'A'."""
    return F.array_join(F.transform(letters, lambda x: F.char(F.lit(65) + x["a"])), "")


def to_regex(rule: TimedRule) -> str:
    """The language of a clockless rule over non-empty letters, by elimination of states."""
    if not rule.is_clockless or rule.empty_letter() != "neutral":
        raise ValueError("only rules without clocks that ignore empty letters are regular expressions of sparse words")
    n = rule.states
    edge: dict[tuple[int, int], str] = {}
    for v in rule.moves:
        chars = "".join(chr(65 + a) for a in sorted(v.letters) if a)
        if chars:
            old = edge.get((v.source, v.target))
            edge[v.source, v.target] = f"[{chars}]" if old is None else f"(?:{old}|[{chars}])"
    edge[n, rule.start] = ""
    for s in rule.accepting:
        edge[s, n + 1] = ""
    for k in range(n):
        loop = f"(?:{edge[k, k]})*" if (k, k) in edge else ""
        for i in [i for i, j in edge if j == k and i != k]:
            for j in [j for i2, j in edge if i2 == k and j != k]:
                way = edge[i, k] + loop + edge[k, j]
                edge[i, j] = f"(?:{edge[i, j]}|{way})" if (i, j) in edge else way
        edge = {e: r for e, r in edge.items() if k not in e}
    return f"^(?:{edge[n, n + 1]})$" if (n, n + 1) in edge else "$.^"


def run_regex(letters: Column, rule: TimedRule) -> Column:
    return letters_text(letters).rlike(to_regex(rule))


def run_monoid(letters: Column, rule: TimedRule, chunk: int = 64) -> Column:
    """Acceptance by state maps of chunks of the word, composed in order; chunks are independent, so those
    of one long activity can be made by different tasks."""
    fold = Fold(rule)
    if not fold.bits or fold.kind != "neutral":
        raise ValueError("for rules without clocks that ignore empty letters")
    n = rule.states
    unit = F.array(*(F.lit(1 << s).cast("long") for s in range(n)))
    starts = F.sequence(F.lit(1), F.greatest(F.size(letters), F.lit(1)), F.lit(chunk))
    maps = F.transform(starts, lambda k: F.aggregate(F.slice(letters, k, chunk), unit, lambda mp, x: F.transform(mp, lambda q: fold._move_bits(q, x["a"]))))
    spread = lambda q, mp: F.aggregate(F.sequence(F.lit(0), F.lit(n - 1)), F.lit(0).cast("long"), lambda out, s: F.when(F.getbit(q, s) == 1, out.bitwiseOR(F.element_at(mp, s + 1))).otherwise(out))
    last = F.aggregate(maps, F.lit(1 << rule.start).cast("long"), spread)
    return last.bitwiseAND(F.lit(sum(1 << s for s in rule.accepting)).cast("long")) != 0


def run_arrow(words: DataFrame, rule: TimedRule, column: str = "word") -> DataFrame:
    """Rows with ``accepted`` added by the interpreter, batch by batch; for neutral rules or dense words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [rule.accepts((x["t"], x["a"]) for x in w) for w in b.column(column).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(got)], [*b.schema.names, "accepted"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in words.schema)
    return words.mapInArrow(run, f"{kinds}, accepted boolean")


def trace(words: DataFrame, rule: TimedRule, keys: list[str], column: str = "word") -> DataFrame:
    """keys, t, a, s, c: the configurations after each letter, one row each."""
    fold = Fold(TimedRule(rule.m, rule.states, rule.accepting, rule.moves, rule.start, rule.clocks or ("none",), rule.name))
    steps = F.sequence(F.lit(1), F.size(column))
    rows = words.where(F.size(column) > 0).select(*keys, F.explode(F.transform(steps, lambda k: F.struct(F.element_at(column, k)["t"].alias("t"), F.element_at(column, k)["a"].alias("a"), fold.run(F.slice(column, F.lit(1), k))["q"].alias("q")))).alias("x"))
    return rows.select(*keys, "x.t", "x.a", F.explode("x.q").alias("q")).select(*keys, "t", "a", "q.s", "q.c")
