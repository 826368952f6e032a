"""Rules against plain definitions, on all short words; analysis against the same words."""

import itertools
import re

import pytest

from temporal_patterns.functions import analysis, library as lib, pattern as pt
from temporal_patterns.functions.automaton import TimedRule, unfold, with_idle_clocks
from temporal_patterns.operators.runners import to_regex

WORDS = [[(t + 1, a) for t, a in enumerate(w)] for n in range(6) for w in itertools.product(range(4), repeat=n)]


def times(word, v):
    return [t for t, a in word if a >> (v - 1) & 1]


MEANING = {
    "exists_before": lambda a, b: any(x < y for x in a for y in b),
    "exists_not_after": lambda a, b: any(x <= y for x in a for y in b),
    "first_strictly_before": lambda a, b: bool(a and b) and a[0] < b[0],
    "first_in_order": lambda a, b: bool(a and b) and a[0] <= b[0],
    "always_together": lambda a, b: a == b,
    "never_together": lambda a, b: not set(a) & set(b),
    "contained": lambda a, b: set(a) <= set(b),
    "all_before": lambda a, b: not a or not b or a[-1] < b[0],
}


@pytest.mark.parametrize("name", MEANING)
def test_two_edge_rules(name):
    rule = getattr(lib, name)()
    for w in WORDS:
        assert rule.accepts(w) == MEANING[name](times(w, 1), times(w, 2)), w


def test_rules_with_clocks():
    for w in WORDS:
        a, b = times(w, 1), times(w, 2)
        line = sorted([(t, 1) for t in a] + [(t, 2) for t in b])
        alternates = not set(a) & set(b) and [v for _, v in line] == [1 + k % 2 for k in range(len(line))]
        assert lib.round_robin(2).accepts(w) == alternates
        in_time = all(t - s < 2 for (s, _), (t, v) in zip(line, line[1:]) if v == 2)
        assert lib.timed_alternation(2).accepts(w) == (alternates and in_time)
        assert lib.exists_gap_over(2).accepts(w) == any(y - x > 2 for x in a for y in b)
        joint = "".join("x" if t in a and t in b else "." for t, _ in w)
        assert lib.together_for(3, "points").accepts(w) == ("xxx" in joint)
        assert lib.together_for(2).accepts(w) == ("xxx" in joint)
        assert lib.motif_within(2, 2).accepts(w) == any(0 < y - x <= 2 for x in a for y in b)
        assert lib.journey(2).accepts(w) == any(x <= y for x in a for y in b)
        assert lib.gaps_between(2, 3).accepts(w) == any(2 <= y - x <= 3 for x in a for y in b)
        assert lib.within_common_window(2, 4).accepts(w) == (any(2 <= x <= 4 for x in a) and any(2 <= y <= 4 for y in b))
    assert not lib.timed_alternation(0).accepts([(1, 1), (2, 2)])


def test_equal_languages():
    for rule in (lib.round_robin(2), lib.first_in_order(2), lib.timed_alternation(3)):
        for other in (unfold(rule, 2), with_idle_clocks(rule, 2), TimedRule.from_json(rule.to_json())):
            assert all(rule.accepts(w) == other.accepts(w) for w in WORDS)
    assert unfold(lib.round_robin(4), 6).states == 256


def test_regular_expressions():
    for rule in (lib.round_robin(2), lib.first_in_order(2), lib.exists_before(), lib.contained()):
        expression = re.compile(to_regex(rule))
        for w in WORDS:
            text = "".join(chr(65 + a) for _, a in w if a)
            assert bool(expression.match(text)) == rule.accepts(w)


def test_analysis():
    both = [w for w in WORDS if times(w, 1) and times(w, 2)]
    for rule in lib.NINE.values():
        accepted = [w for w in both if rule.accepts(w)]
        firsts = {(times(w, 1)[0] > times(w, 2)[0]) - (times(w, 1)[0] < times(w, 2)[0]) for w in accepted}
        never = analysis.must_not_precede(rule)
        assert not ((1, 2) in never and -1 in firsts) and not ((2, 1) in never and 1 in firsts)
    assert analysis.must_not_precede(lib.round_robin(2)) == {(2, 1)}
    assert analysis.must_not_precede(lib.always_together()) == {(1, 2), (2, 1)}
    assert analysis.must_not_precede(lib.contained(1, 2)) == {(1, 2)}
    assert analysis.must_not_precede(lib.never_together()) == set()
    assert analysis.safe_states(lib.exists_before()) == {2} and analysis.safe_states(lib.round_robin(2)) == set()
    assert analysis.find_order(pt.path(3), lib.round_robin(3)) == (1, 2, 3)
    assert analysis.runs_can_die(lib.round_robin(2)) and analysis.runs_can_die(lib.contained()) and not analysis.runs_can_die(lib.exists_before())
    assert analysis.dead_states(unfold(lib.round_robin(4), 6)) == set()
    assert analysis.find_order(pt.path(2), lib.exists_before()) is None


def test_patterns():
    p = pt.Pattern.of("(a:cust)-[y1:msg]->(b), (b)-[]->(a)")
    assert p.edges == (("a", "b"), ("b", "a")) and p.edge_labels == ("msg", None) and p.node_labels == (("a", "cust"),) and p.is_cyclic
    assert not pt.path(3).is_connected_order((1, 3, 2)) and pt.path(3).is_connected_order((2, 1, 3))
    with pytest.raises(ValueError):
        pt.Pattern.of("(a)-[]->(b), (c)-[]->(d)").join_order()
