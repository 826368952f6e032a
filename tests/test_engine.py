"""Strategies against each other and against brute force; worked examples; stores; registered queries."""

import dataclasses
import itertools
import random

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from temporal_patterns.functions import library as lib, pattern as pt
from temporal_patterns.operators import matching, relational, runners, strategies
from temporal_patterns.plans import metrics, planner, workloads
from temporal_patterns.sources import graphs as gr, storage
from temporal_patterns.streaming.online import OnlineMatcher


def rows(df):
    return sorted(map(tuple, df.collect()))


def brute(edges, pattern, rule):
    """edges: (src, dst) -> times; accepted matches as node tuples."""
    domain = sorted({t for ts in edges.values() for t in ts})
    out = []
    for chosen in itertools.product(edges, repeat=pattern.m):
        at = {}
        if all(at.setdefault(v, n) == n for (a, b), e in zip(pattern.edges, chosen) for v, n in ((a, e[0]), (b, e[1]))):
            if pattern.break_symmetry and list(chosen) != sorted(set(chosen)):
                continue
            word = [(t, sum(1 << i for i, e in enumerate(chosen) if t in edges[e])) for t in domain]
            if rule.accepts(word):
                out.append(tuple(at[v] for v in pattern.nodes))
    return sorted(out)


CASES = [
    (pt.path(2), lib.round_robin(2)), (pt.path(2), lib.together_for(1)), (pt.path(2), lib.timed_alternation(2)), (pt.cycle(3), lib.first_in_order(3)),
    (pt.out_star(2), lib.never_together()), (pt.path(3), lib.first_in_order(3)), (pt.cycle(2), lib.exists_before()), (pt.cycle(3), lib.journey(3)), (pt.path(3), lib.round_robin(3)),
]


@pytest.mark.parametrize("case", range(len(CASES)))
def test_strategies_agree_with_brute_force(spark, case):
    pattern, rule = CASES[case]
    rng = random.Random(case)
    edges = {(a, b): sorted(rng.sample(range(1, 9), rng.randrange(1, 4))) for a in range(1, 6) for b in range(1, 6) if rng.random() < 0.5}
    g = gr.from_activity(spark.createDataFrame([(*e, t) for e, ts in edges.items() for t in ts], "src long, dst long, t long"))
    want = brute(edges, pattern, rule)
    names = list(pattern.nodes)
    assert rows(strategies.solve_full(g, pattern, rule).select(names)) == want
    assert rows(strategies.solve_ondemand(g, pattern, rule, slabs=3).select(names)) == want
    if strategies.staged_orders(pattern, rule):
        assert rows(strategies.solve_staged(g, pattern, rule).select(names)) == want
        assert rows(strategies.solve_staged(g, pattern, rule, share=False).select(names)) == want
    assert rows(planner.find(g, pattern, rule).select(names)) == want
    assert rows(strategies.solve_full(g, pattern, rule, early=True).select(names)) == want
    assert rows(strategies.solve_partial(g, pattern, rule).select(names)) == want
    if relational.form(rule) is not None:
        assert rows(relational.solve(g, pattern, rule).select(names)) == want
    if case < 2:
        assert rows(strategies.run_dataflow(g, pattern, rule).select(names)) == want


def test_a_partial_match_that_stops_being_maximal_is_kept(spark):
    g = gr.from_activity(spark.createDataFrame([(1, 2, 1), (2, 3, 2), (2, 4, 3)], "src long, dst long, t long"))
    assert strategies.solve_staged(g, pt.path(2), lib.first_in_order(2)).count() == 2


def test_products_of_partial_matches_are_bounded(spark):
    g = gr.from_activity(spark.createDataFrame([(a, a + 1, a) for a in range(1, 7)], "src long, dst long, t long"))
    assert strategies.solve_partial(g, pt.path(3), lib.first_in_order(3), slabs=1).count() == 4
    with pytest.raises(ValueError, match="partial matches"):
        strategies.solve_partial(g, pt.path(3), lib.first_in_order(3), slabs=1, most=3)
    sets = {r.have: r["count"] for r in matching.partials(gr.packed(g), pt.path(3)).groupBy("have").count().collect()}
    assert sets == {"1": 6, "2": 6, "3": 6, "1,2": 5, "2,3": 5, "1,2,3": 4}
    word = [(1, 0, 1), (2, 0, 2), (3, 0, 2)]
    fold = runners.Fold(lib.round_robin(2))
    df = spark.createDataFrame([(word,)], "w array<struct<t:bigint,r:bigint,a:int>>")
    got = df.select(*(runners.configurations_at(F.col("w"), fold, F.lit(t))["q"] for t in (0, 1, 2, 3))).first()
    assert tuple(got) == (1, 2, 1, 0)


def test_running_example(spark):
    g = gr.office_example(spark)
    assert gr.validate(g).count() == 0
    assert [r.t for r in gr.domain(g).orderBy("t").collect()] == [10, 11, 19, 20, 30, 40, 50, 60, 90]
    both = rows(matching.match(gr.packed(g), pt.exchange(), g.nodes).select("e1", "e2"))
    assert both == [(5, 6), (8, 9)]
    for solve in (strategies.solve_full, strategies.solve_ondemand, strategies.solve_staged):
        assert rows(solve(g, pt.exchange(), lib.round_robin(2)).select("e1", "e2")) == [(5, 6)]
        assert rows(solve(g, pt.exchange(), lib.timed_alternation(20)).select("e1", "e2")) == [(5, 6)]
    assert rows(strategies.solve_full(g, pt.leak().bind(a=1, b=4), lib.exists_not_after()).select("x")) == [(2,)]
    office = strategies.solve_full(g, pt.shared_office(), lib.never_together())
    assert rows(office.select("e1", "e2")) == [(11, 12)]
    assert strategies.solve_full(g, pt.shared_office(), lib.together_for(1)).count() == 0
    words = matching.match(gr.packed(g), pt.exchange(), g.nodes).withColumn("word", runners.word(2))
    steps = rows(runners.trace(words, lib.round_robin(2), ["e1", "e2"]).where("e1 = 8").select("t", "s"))
    assert steps == [(20, 1)]  # the second message in a row ends its run at 30
    assert rows(planner.find_sql(g, "MATCH (x1:customer)-[y1:message]->(x2:employee), (x2)-[y2:message]->(x1) OBEYING round_robin(2) USING full").select("e1", "e2")) == [(5, 6)]


def test_general_empty_letters(spark):
    """A rule that counts timepoints: y2 two timepoints of the domain after y1."""
    from temporal_patterns.functions.automaton import TimedRule

    rule = TimedRule.of(2, 4, [3], [(0, "!y1", 0), (0, "y1 & !y2", 1), (1, "true", 2), (2, "y2", 3), (3, "true", 3)])
    assert rule.empty_letter() == "general"
    g = gr.from_activity(spark.createDataFrame([(1, 2, 1), (2, 3, 4), (5, 6, 3), (7, 8, 1), (8, 9, 3)], "src long, dst long, t long"))
    assert rows(strategies.solve_full(g, pt.path(2), rule).select("x1", "x2", "x3")) == [(1, 2, 3)]


def test_online_batches_replays_and_late_rows(spark):
    make = lambda x: spark.createDataFrame(x, "src long, dst long, t long")
    m = OnlineMatcher(spark, pt.path(2), lib.round_robin(2))
    m.batch(make([(1, 2, 1), (5, 6, 2)]), 0)
    for _ in range(2):
        m.batch(make([(2, 3, 3), (1, 2, 4), (6, 7, 3), (5, 6, 1)]), 1)
    m.batch(make([(5, 6, 5), (5, 6, 6)]), 2)
    assert rows(m.results().select("x1", "x2", "x3")) == [(1, 2, 3)]
    assert rows(m.late()) == [(5, 6, 1)]


@pytest.mark.parametrize("fmt", ["parquet", "csv", "json", "orc"])
def test_stores(spark, tmp_path, fmt):
    g = gr.office_example(spark)
    storage.write_graph(g, str(tmp_path), fmt)
    back = storage.read_graph(spark, str(tmp_path), fmt)
    assert all(metrics.difference(getattr(g, n), getattr(back, n)) == 0 for n in ("nodes", "edges", "active"))


def test_plans_have_no_product_and_no_python(spark, sf):
    for name in ("handoff_path2_TA_1_staged", "handoff_cohort_path3_TA_0_staged", "handoff_path2_TA_3_full"):
        plan = workloads.QUERIES[name](spark, sf("0.001"))._jdf.queryExecution().toString()
        assert "CartesianProduct" not in plan and "NestedLoop" not in plan and "Python" not in plan and "InArrow" not in plan


def test_measures(spark, sf):
    got = metrics.counts(gr.dialogue(spark, sf("0.01")), pt.cycle(2), lib.round_robin(2)).first()
    assert (got.matches, got.accepted) == (174, 87)


def test_relational_forms_and_choice(spark, sf):
    g = gr.handoff_cohort(spark, sf("0.01"))
    for rule in lib.NINE.values():
        assert metrics.difference(relational.solve(g, pt.path(2), rule), strategies.solve_full(g, pt.path(2), rule)) == 0
    assert planner.choose(pt.path(3), lib.round_robin(3)).strategy == "staged"
    assert planner.choose(pt.cycle(3), lib.round_robin(3), 0.01).strategy == "ondemand"
    assert planner.choose(pt.path(2), lib.never_together()).strategy == "relational"


def test_relational_forms_take_their_arguments_from_the_rule(spark, sf):
    g = gr.handoff_cohort(spark, sf("0.001"))
    rules = [lib.contained(2, 1), lib.timed_alternation(5), lib.timed_alternation(2.5), lib.timed_alternation(4, restart="every"), lib.together_for(2, "points")]
    for rule in rules:
        want = strategies.solve_full(g, pt.path(2), rule)
        assert metrics.difference(planner.find(g, pt.path(2), rule, "relational"), want) == 0
        assert metrics.difference(planner.find(g, pt.path(2), rule), want) == 0
    impostor = dataclasses.replace(lib.answered_within(3), name="contained")
    assert planner.choose(pt.path(2), impostor).strategy != "relational"
    for rule in (impostor, lib.timed_alternation(3, guard="both"), lib.together_for(2)):
        with pytest.raises(ValueError):
            planner.find(g, pt.path(2), rule, "relational")


def test_a_new_online_matcher_goes_on(spark, tmp_path):
    slabs = [[(1, 2, 1), (2, 3, 2)], [(2, 3, 4), (4, 5, 4)], [(3, 4, 5), (1, 2, 7)]]
    frames = [spark.createDataFrame(s, "src long, dst long, t long") for s in slabs]
    whole = OnlineMatcher(spark, pt.path(2), lib.first_in_order(2), f"{tmp_path}/whole")
    for i, f in enumerate(frames):
        whole.batch(f, i)
        OnlineMatcher(spark, pt.path(2), lib.first_in_order(2), f"{tmp_path}/parts").batch(f, i)
    last = OnlineMatcher(spark, pt.path(2), lib.first_in_order(2), f"{tmp_path}/parts")
    assert last.ends == whole.ends
    assert last.results().count() > 0 and metrics.difference(last.results(), whole.results()) == 0


@pytest.mark.parametrize("name", sorted(workloads.ORACLES)[::4])
def test_queries_equal_their_sql(spark, sf, name):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from '{sf('0.001')}/{t}.parquet'")
    df = workloads.QUERIES[name](spark, sf("0.001"))
    want = con.execute(workloads.ORACLES[name])
    columns = [c[0] for c in want.description]
    assert sorted(columns) == sorted(df.columns)
    assert sorted(map(tuple, df.select(columns).collect()), key=str) == sorted(want.fetchall(), key=str)


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() == 13
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
