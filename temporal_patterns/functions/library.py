"""The rules of the experiments, and relatives.  Each docstring says what a match must do."""

from __future__ import annotations

from .automaton import TimedRule
from .formula import only


def _has(v: int, m: int) -> frozenset[int]:
    return frozenset(a for a in range(1 << m) if a >> (v - 1) & 1)


def exists_before(m: int = 2) -> TimedRule:
    """Some time of y1 strictly before some time of y2."""
    return TimedRule.of(m, 3, [2], [(0, "true", 0), (0, "y1", 1), (1, "true", 1), (1, "y2", 2), (2, "true", 2)], name="exists_before")


def exists_not_after(m: int = 2) -> TimedRule:
    """Some time of y1 at or before some time of y2."""
    return TimedRule.of(m, 3, [2], [(0, "true", 0), (0, "y1", 1), (0, "y1 & y2", 2), (1, "true", 1), (1, "y2", 2), (2, "true", 2)], name="exists_not_after")


def exists_gap_over(gap: float) -> TimedRule:
    """Some time of y2 more than ``gap`` after some time of y1."""
    return TimedRule.of(2, 3, [2], [(0, "true", 0), (0, "y1", 1, "", ("x",)), (1, "true", 1), (1, "y2", 2, f"x>{gap}"), (2, "true", 2)], ["x"], "exists_gap_over")


def round_robin(m: int = 2) -> TimedRule:
    """One edge at a time, in cyclic order from y1; any prefix will do."""
    moves = [(i, only(i + 1), (i + 1) % m) for i in range(m)] + [(i, [0], i) for i in range(m)]
    return TimedRule.of(m, m, range(m), moves, name="round_robin")


def timed_alternation(bound: float, guard: str = "reply", restart: str = "first") -> TimedRule:
    """y1 and y2 in turns, y2 under ``bound`` after the y1 before it (``guard='both'``: y1 also after y2)."""
    both = guard == "both"
    moves = [(0, only(1), 1, "", ("x",)), (1, only(2), 2 if both else 0, f"x<{bound}", ("x",) if both or restart == "every" else ())]
    moves += [(2, only(1), 1, f"x<{bound}", ("x",))] if both else []
    n = 3 if both else 2
    return TimedRule.of(2, n, range(n), moves + [(i, [0], i) for i in range(n)], ["x"], "timed_alternation")


def _in_order(m: int, strict: bool) -> TimedRule:
    moves = []
    for i in range(m):
        seen = (1 << i) - 1
        rest = ((1 << m) - 1) & ~seen
        moves.append((i, frozenset(a for a in range(1 << m) if not a & rest), i))
        for j in range(i + 1, (i + 1 if strict else m) + 1):  # variables i+1 .. j are seen for the first time
            new = sum(1 << k for k in range(i, j))
            moves.append((i, frozenset(a for a in range(1 << m) if a & rest == new), j))
    return TimedRule.of(m, m + 1, [m], [*moves, (m, "true", m)], name="first_strictly_before" if strict else "first_in_order")


def first_strictly_before(m: int = 2) -> TimedRule:
    """First activities in strictly rising order."""
    return _in_order(m, True)


def first_in_order(m: int = 2) -> TimedRule:
    """First activities in order, ties allowed."""
    return _in_order(m, False)


def always_together() -> TimedRule:
    """Equal activity sets (a stand-in: the text doesn't say what its fifth rule is)."""
    return TimedRule.of(2, 1, [0], [(0, [0, 3], 0)], name="always_together")


def never_together() -> TimedRule:
    """No joint timepoint."""
    return TimedRule.of(2, 1, [0], [(0, [0, 1, 2], 0)], name="never_together")


def together_for(d: float, measure: str = "span") -> TimedRule:
    """A contiguous stretch of joint activity that spans ``d`` (or, by ``points``, has ``d`` timepoints)."""
    if measure == "points":
        n = int(d)
        moves = [(0, "true", 0), (n, "true", n)] + [(i, only(1, 2), i + 1) for i in range(n)]
        return TimedRule.of(2, n + 1, [n], moves, name="together_for")
    moves = [(0, "true", 0), (0, only(1, 2), 1, "", ("x",)), (1, only(1, 2), 1), (1, only(1, 2), 2, f"x>={d}"), (2, "true", 2)]
    if d <= 0:
        moves.append((0, only(1, 2), 2))
    return TimedRule.of(2, 3, [2], moves, ["x"], "together_for")


def contained(i: int = 1, j: int = 2) -> TimedRule:
    """Whenever yi is active, yj is."""
    return TimedRule.of(2, 1, [0], [(0, f"!y{i} | y{j}", 0)], name="contained")


def answered_within(gap: float) -> TimedRule:
    """Every y1 is followed by y2 within ``gap`` (measured from the oldest unanswered y1)."""
    moves = [(0, "!y1", 0), (0, "y1 & !y2", 1, "", ("x",)), (0, "y1 & y2", 0), (1, "!y2", 1, f"x<={gap}"), (1, "y2", 0, f"x<={gap}")]
    return TimedRule.of(2, 2, [0], moves, ["x"], "answered_within")


def all_before() -> TimedRule:
    """All of y1 strictly before all of y2."""
    return TimedRule.of(2, 2, [0, 1], [(0, [0, 1], 0), (0, [2], 1), (1, [0, 2], 1)], name="all_before")


def motif_within(m: int, delta: float) -> TimedRule:
    """Times t1 < t2 < ... of y1, y2, ... that lie within ``delta``."""
    moves = [(0, "true", 0), (0, _has(1, m), 1, "", ("x",)), (m, "true", m)]
    for i in range(1, m):
        moves += [(i, "true", i), (i, _has(i + 1, m), i + 1, f"x<={delta}")]
    return TimedRule.of(m, m + 1, [m], moves, ["x"], "motif_within")


def gaps_between(low: float, high: float, m: int = 2) -> TimedRule:
    """Times of y1, y2, ... with successive gaps from ``low`` to ``high``."""
    moves = [(0, "true", 0), (0, _has(1, m), 1, "", ("x",)), (m, "true", m)]
    for i in range(1, m):
        moves += [(i, "true", i), (i, _has(i + 1, m), i + 1, f"x>={low} & x<={high}", ("x",))]
    return TimedRule.of(m, m + 1, [m], moves, ["x"], "gaps_between")


def within_common_window(low: float, high: float) -> TimedRule:
    """Both edges active at some times in [low, high]."""
    inside = f"x>={low} & x<={high}"
    moves = [(s, "true", s) for s in range(4)]
    moves += [(s, _has(v, 2), s | 1 << (v - 1), inside) for s in range(4) for v in (1, 2)] + [(0, only(1, 2), 3, inside)]
    return TimedRule.of(2, 4, [3], moves, ["x"], "within_common_window")


def journey(m: int) -> TimedRule:
    """Times of y1, y2, ... that don't decrease."""
    moves = [(m, "true", m)]
    for i in range(m):
        moves.append((i, "true", i))
        for j in range(i + 1, m + 1):
            need = sum(1 << k for k in range(i, j))
            moves.append((i, frozenset(a for a in range(1 << m) if a & need == need), j))
    return TimedRule.of(m, m + 1, [m], moves, name="journey")


#: The nine two-edge rules of the comparison with relational engines, by the experiments' labels.
NINE = {
    "TA_e": exists_before(), "TA_1": round_robin(2), "TA_2": timed_alternation(3), "TA_3": first_strictly_before(2), "TA_4": first_in_order(2),
    "TA_5": always_together(), "TA_6": never_together(), "TA_7": together_for(3, "points"), "TA_8": contained(1, 2),
}
