"""What a rule implies: dead and safe states, and orders of first activity it is compatible with.

All inputs are a few states and moves; everything runs on the driver.  Clock rules are analysed over a
grid of clock values that separates all guard constants; where that isn't exact (reachability with
several clocks) the answer errs to "possible", which only prunes less.
"""

from __future__ import annotations

import functools
import itertools

from . import formula as fm
from .automaton import Move, TimedRule, intersect


def reachable(rule: TimedRule, start: int | None = None) -> set[int]:
    seen, todo = set(), [rule.start if start is None else start]
    while todo:
        s = todo.pop()
        if s not in seen:
            seen.add(s)
            todo += [v.target for v in rule.moves if v.source == s and v.letters and possible(v.guard)]
    return seen


def _grid(trees: list[tuple]) -> list[float]:
    c = fm.constants(trees)
    return sorted({0.0, *c, *((a + b) / 2 for a, b in zip(c, c[1:])), *((c[0] / 2, c[-1] + 1) if c else ())})


@functools.cache
def possible(guard: str) -> bool:
    """Whether some clock values satisfy the guard."""
    tree = fm.guard(guard)
    names = sorted(fm.guard_clocks(tree))
    return any(fm.guard_holds(tree, dict(zip(names, v))) for v in itertools.product(_grid([tree]), repeat=len(names)))


def dead_states(rule: TimedRule) -> frozenset[int]:
    """States from which no accepting state can be reached."""
    back: dict[int, set[int]] = {}
    for v in rule.moves:
        if v.letters and possible(v.guard):
            back.setdefault(v.target, set()).add(v.source)
    live, todo = set(), list(rule.accepting)
    while todo:
        s = todo.pop()
        if s not in live:
            live.add(s)
            todo += back.get(s, ())
    return frozenset(range(rule.states)) - live


def safe_states(rule: TimedRule) -> frozenset[int]:
    """States from which every continuation is accepted: accepting, and for each letter and all clock
    values some move stays among them (greatest such set)."""
    safe = set(rule.accepting)
    while True:
        bad = set()
        for s in safe:
            for a in range(1 << rule.m):
                trees = [fm.guard(v.guard) for v in rule.moves if v.source == s and a in v.letters and v.target in safe]
                names = sorted(set().union(*map(fm.guard_clocks, trees))) if trees else []
                if not trees or not all(any(fm.guard_holds(t, dict(zip(names, v))) for t in trees) for v in itertools.product(_grid(trees), repeat=len(names))):
                    bad.add(s)
        if not bad:
            return frozenset(safe)
        safe -= bad


def runs_can_die(rule: TimedRule) -> bool:
    """Whether a run can come to where no continuation is accepted: early rejection is of use only then."""
    live = reachable(rule) - dead_states(rule)
    for s in live:
        for a in range(1 << rule.m):
            trees = [fm.guard(v.guard) for v in rule.moves if v.source == s and a in v.letters and v.target in live]
            names = sorted(set().union(*map(fm.guard_clocks, trees))) if trees else []
            if not all(any(fm.guard_holds(t, dict(zip(names, v))) for t in trees) for v in itertools.product(_grid(trees), repeat=len(names))):
                return True
    return not live


def precedes(m: int, i: int, j: int) -> TimedRule:
    """Words in which y_i is first active strictly before y_j (or y_j never is)."""
    bi, bj = 1 << (i - 1), 1 << (j - 1)
    moves = [Move(0, frozenset(a for a in range(1 << m) if not a & (bi | bj)), 0), Move(0, frozenset(a for a in range(1 << m) if a & bi and not a & bj), 1), Move(1, frozenset(range(1 << m)), 1)]
    return TimedRule(m, 2, frozenset([1]), tuple(moves))


def all_seen(m: int) -> TimedRule:
    """Words in which every edge variable is active at some time, as it is for every match."""
    n = 1 << m
    return TimedRule(m, n, frozenset([n - 1]), tuple(Move(s, frozenset([a]), s | a) for s in range(n) for a in range(n)))


def is_empty(rule: TimedRule) -> bool:
    """No word is accepted.  Exact without clocks; with clocks "not empty" may be wrong."""
    return not reachable(rule) & rule.accepting


def must_not_precede(rule: TimedRule) -> set[tuple[int, int]]:
    """Pairs (i, j): no accepted word of a match has y_i first active strictly before y_j."""
    moves: dict[int, list[tuple[int, int]]] = {}
    for v in rule.moves:
        if possible(v.guard):
            moves.setdefault(v.source, []).extend((a, v.target) for a in v.letters)
    full = (1 << rule.m) - 1

    def happens(bi: int, bj: int) -> bool:
        """Some word leads to acceptance, with all edges seen and y_i before y_j."""
        reached, todo = {(rule.start, 0)}, [(rule.start, 0)]
        while todo:
            s, seen = todo.pop()
            if seen == full and s in rule.accepting:
                return True
            for a, target in moves.get(s, ()):
                if a & bj and not seen & bi:
                    continue
                if (at := (target, seen | a)) not in reached:
                    reached.add(at)
                    todo.append(at)
        return False

    return {(i, j) for i in range(1, rule.m + 1) for j in range(1, rule.m + 1) if i != j and not happens(1 << (i - 1), 1 << (j - 1))}


def balance(rule: TimedRule, most: int = 512) -> dict[tuple[int, int], tuple[int | None, int | None]]:
    """(i, j): least and greatest number of times that y_i is active more often than y_j in an accepted word
    (None: no limit); pairs without either, and rules of over ``most`` states, have no entry."""
    if rule.states > most:
        return {}
    live = reachable(rule) - dead_states(rule)
    moves = [(v.source, a, v.target) for v in rule.moves if v.source in live and v.target in live and possible(v.guard) for a in v.letters]

    def greatest(bi: int, bj: int) -> int | None:
        far = {rule.start: 0}
        for _ in range(rule.states + 1):
            changed = False
            for s, a, target in moves:
                if s in far and (d := far[s] + bool(a & bi) - bool(a & bj)) > far.get(target, -(1 << 30)):
                    far[target], changed = d, True
            if not changed:
                return max((far[s] for s in rule.accepting if s in far), default=None)
        return None  # a cycle gains

    out = {}
    for i, j in itertools.combinations(range(1, rule.m + 1), 2):
        high, low = greatest(1 << (i - 1), 1 << (j - 1)), greatest(1 << (j - 1), 1 << (i - 1))
        if high is not None or low is not None:
            out[i, j] = (None if low is None else -low, high)
    return out


def only_firsts(rule: TimedRule) -> bool:
    """Whether acceptance follows from the order of first activities: letters count only for edges not seen before."""
    if rule.clocks:
        return False
    to = {key: {v.target for v in moves} for key, moves in rule.by_letter().items()}
    dead = dead_states(rule)
    reached, todo = {(rule.start, 0)}, [(rule.start, 0)]
    while todo:
        s, seen = todo.pop()
        for a in range(1, 1 << rule.m):
            new = a & ~seen
            after = to.get((s, a), set()) - dead
            if after != (to.get((s, new), set()) - dead if new else {s}):
                return False
            for at in {(x, seen | a) for x in after} - reached:
                reached.add(at)
                todo.append(at)
    return True


def weak_orders(m: int) -> list[list[tuple[int, ...]]]:
    """Ways in which y_1..y_m can come one after the other, ties allowed: lists of tied variables."""
    out: list[list[tuple[int, ...]]] = [[]]
    for i in range(1, m + 1):
        out = [w for o in out for w in [*(o[:k] + [(*o[k], i)] + o[k + 1 :] for k in range(len(o))), *(o[:k] + [(i,)] + o[k:] for k in range(len(o) + 1))]]
    return out


def is_compatible(rule: TimedRule, order: tuple[int, ...]) -> bool:
    """Accepted matches have first activities in this order (ties allowed)."""
    never = must_not_precede(rule)
    return all((b, a) in never for a, b in itertools.combinations(order, 2))


def feasible_orders(rule: TimedRule) -> list[tuple[int, ...]]:
    """Orders of first activity that accepted matches may have."""
    never = must_not_precede(rule)
    out = []
    for p in itertools.permutations(range(1, rule.m + 1)):
        # in order p an earlier variable is strictly before a later one, or tied with it and of smaller number
        if not any((a, b) in never and a > b for a, b in itertools.combinations(p, 2)):
            if not any((a, b) in never and a < b and _no_tie(rule, a, b) for a, b in itertools.combinations(p, 2)):
                out.append(p)
    return out


def _no_tie(rule: TimedRule, a: int, b: int) -> bool:
    ba, bb = 1 << (a - 1), 1 << (b - 1)
    m = rule.m
    tie = TimedRule(m, 2, frozenset([1]), (Move(0, frozenset(x for x in range(1 << m) if not x & (ba | bb)), 0), Move(0, frozenset(x for x in range(1 << m) if x & ba and x & bb), 1), Move(1, frozenset(range(1 << m)), 1)))
    return is_empty(intersect(intersect(rule, all_seen(m)), tie))


def find_order(pattern, rule: TimedRule) -> tuple[int, ...] | None:
    """A compatible order with connected prefixes, if there is one."""
    for p in itertools.permutations(range(1, rule.m + 1)):
        if pattern.is_connected_order(p) and is_compatible(rule, p):
            return p
    return None
