"""What large graphs need: matches decided without words, long cycles in halves, graphs that are made once."""

import itertools
import random
import re

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from temporal_patterns.functions import analysis, library as lib, pattern as pt
from temporal_patterns.functions.automaton import unfold
from temporal_patterns.operators import matching, runners, strategies
from temporal_patterns.plans import oracles, workloads
from temporal_patterns.sources import graphs as gr
from temporal_patterns.streaming.online import OnlineMatcher


def plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("rule", [lib.round_robin(3), lib.first_in_order(3), unfold(lib.round_robin(3), 1), lib.journey(3), lib.timed_alternation(2)], ids=str)
def test_edges_active_once_are_decided_by_comparisons(spark, rule):
    times = list(itertools.product(range(1, 5), repeat=rule.m))
    df = spark.createDataFrame(times, ", ".join(f"f{i} long" for i in range(1, rule.m + 1)))
    got = {tuple(r)[: rule.m]: tuple(r)[rule.m] for r in df.withColumn("a", runners.Fold(rule).accepted_once()).collect()}
    for ts in times:
        word = [(t, sum(1 << i for i, x in enumerate(ts) if x == t)) for t in sorted(set(ts))]
        assert got[ts] == rule.accepts(word), ts


def test_what_a_rule_implies():
    assert analysis.balance(lib.round_robin(2)) == {(1, 2): (0, 1)}
    assert analysis.only_firsts(lib.first_in_order(4)) and not analysis.only_firsts(lib.round_robin(3))
    assert [len(analysis.weak_orders(m)) for m in (1, 2, 3, 4)] == [1, 3, 13, 75]


def test_long_cycles_meet_in_halves(spark):
    g = gr.from_activity(spark.createDataFrame([(1, 2, 1), (2, 3, 2), (3, 4, 3), (4, 1, 4)], "src long, dst long, t long"))
    assert matching.halves(pt.cycle(4), (1, 2, 3, 4)) == ((1, 2), (3, 4)) and matching.halves(pt.path(4), (1, 2, 3, 4)) is None
    for rule in (lib.round_robin(4), lib.first_in_order(4)):
        for solve in (strategies.solve_full, strategies.solve_ondemand, strategies.solve_staged):
            assert [tuple(r)[:4] for r in solve(g, pt.cycle(4), rule).collect()] == [(1, 2, 3, 4)]


def test_the_order_of_first_activity_is_tested_in_the_joins(spark):
    g = gr.from_activity(spark.createDataFrame([(1, 2, 1), (2, 3, 2), (3, 4, 3)], "src long, dst long, t long"))
    text = plan(strategies.solve_full(g, pt.path(3), lib.round_robin(3)))
    assert "f1#" in text and any("Join" in line and "f1#" in line and "<=" in line for line in text.splitlines())


def test_ondemand_stores_only_what_goes_on(spark, monkeypatch):
    kept = []
    monkeypatch.setattr(strategies, "settle", lambda df, label, f=strategies.settle: (out := f(df, label), kept.append((label, out.count())))[0])
    g = gr.from_activity(spark.createDataFrame([(1, 2, 1), (2, 3, 2), (3, 4, 3), (4, 5, 4)], "src long, dst long, t long"))
    assert strategies.solve_ondemand(g, pt.path(2), lib.round_robin(2), slabs=2).count() == 3
    assert kept[0] == ("packed", 4) and all(n == 0 for label, n in kept if label == "slab")


@pytest.mark.parametrize("name", ["sweep_bound_handoff", "sweep_domain"])
def test_a_sweep_makes_its_graph_once(spark, sf, name):
    assert "Window" not in plan(__spark_entry__.queries()[name](spark, sf("0.001")))


def test_the_stream_makes_its_graph_once(spark, sf, monkeypatch):
    made = []
    monkeypatch.setattr(workloads, "settle", lambda df, label, f=workloads.settle: (made.append(label), f(df, label))[1])
    assert workloads.streamed(spark, sf("0.001")).count() > 0 and made == ["activity"]


@pytest.mark.parametrize("name", ["sweep_clocks_cycle4", "sweep_density_cycle3", "sweep_density_cycle4", "sweep_density_path3", "sweep_density_path4", "sweep_states_cycle4"])
def test_sweeps_are_on_given_tables(spark, sf, name, monkeypatch):
    monkeypatch.setattr(gr, "complete_sample", None)
    rows = __spark_entry__.queries()[name](spark, sf("0.001"))
    assert "Range" not in plan(rows) and rows.agg(F.sum("accepted")).first()[0] > 0


@pytest.mark.parametrize("name", ["sweep_density_cycle3", "sweep_density_cycle4", "sweep_density_path3", "sweep_density_path4"])
def test_density_sweeps_read_the_tables_themselves(spark, sf, name, monkeypatch):
    monkeypatch.setattr(workloads, "stored", None)
    text = plan(__spark_entry__.queries()[name](spark, sf("0.001")))
    assert "l_extendedprice" in text and "o_orderdate" in text


def test_the_trade_graph_joins_the_lines_once(spark, tmp_path):
    con = duckdb.connect()
    con.execute("create table nations as select i as k, i % 3 as n from range(6) r(i)")
    day = "case o when 4 then null else timestamp '1995-01-01' + interval (o // 2 * 100) day end"
    for name, q in {
        "customer": "select k as c_custkey, cast(case k when 5 then null else n end as int) as c_nationkey from nations",
        "supplier": "select k as s_suppkey, cast(n as int) as s_nationkey from nations",
        "orders": f"select o as o_orderkey, o % 6 as o_custkey, {day} as o_orderdate from range(8) r(o)",
        "lineitem": "select o as l_orderkey, s as l_suppkey, case when o + s = 7 then null else (o * s % 5 - 1) * 1.25 end as l_extendedprice from range(9) r(o), range(6) p(s)",
    }.items():
        con.execute(f"copy ({q}) to '{tmp_path}/{name}.parquet' (format parquet)")
        con.execute(f"create view {name} as select * from '{tmp_path}/{name}.parquet'")
    for tick in ("rivalry", "rivalry_year"):
        want = con.execute(f"select distinct * from ({oracles.ACTIVITY[tick]})").fetchall()
        g = gr.GRAPHS[tick](spark, str(tmp_path))
        got = g.active.join(g.edges, "eid").select("src", "dst", "t").collect()
        assert sorted(map(tuple, got), key=str) == sorted(want, key=str) and want
        assert plan(g.active).count("Relation [l_orderkey") == 1


def test_ondemand_finds_lasting_matches_from_their_lasting_edges(spark, monkeypatch):
    rng = random.Random(5)
    edges = {(a, b): sorted(rng.sample(range(1, 9), rng.randrange(1, 3))) for a in range(1, 7) for b in range(1, 7) if rng.random() < 0.6}
    g = gr.from_activity(spark.createDataFrame([(*e, t) for e, ts in edges.items() for t in ts], "src long, dst long, t long"))
    e, low, high = gr.packed(g), 2, 5
    old, both = e.where(F.col("first") <= low), e.where(F.col("first") <= high)
    for pattern in (pt.path(3), pt.cycle(4), pt.in_star(2)):
        names = strategies.result_columns(pattern)
        last = F.greatest(*(f"l{i}" for i in range(1, pattern.m + 1)))
        want = matching.match_delta(old, both.where(F.col("first") > low), both, pattern).where(last > high).select(names)
        got = matching.match_lasting(e, low, high, pattern).select(names)
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and want.count()
    plans = []
    monkeypatch.setattr(strategies, "settle", lambda df, label, f=strategies.settle: (plans.append((label, plan(df))), f(df, label))[1])
    strategies.solve_ondemand(g, pt.path(3), lib.round_robin(3), slabs=2)
    slab = next(text for label, text in plans if label == "slab")
    assert any("Filter" in line and "last#" in line and ">" in line for line in slab.splitlines())


def test_packed_edges_are_made_in_one_pass(spark, sf):
    for name, table in (("purchase", "l_orderkey"), ("handoff", "event_id"), ("visit", "event_id")):
        g = gr.GRAPHS[name](spark, sf("0.001"))
        assert len([x for x in plan(gr.packed(g)).splitlines() if "Relation [" in x and table in x]) == 1
        apart = gr.packed(gr.TemporalGraph(g.nodes, g.edges, g.active)).select(gr.packed(g).columns)
        assert sorted(gr.packed(g).collect(), key=str) == sorted(apart.collect(), key=str)
        assert [(f.name, f.dataType) for f in gr.packed(g).schema] == [(f.name, f.dataType) for f in apart.schema]


def test_edges_with_two_labels_keep_their_whole_activity(spark):
    g = gr.from_activity(spark.createDataFrame([(1, 2, 1, "a"), (1, 2, 2, "b"), (None, 2, 3, None)], "src long, dst long, t long, label string"))
    assert sorted((r.label, r.first, r.last, r.n_active) for r in gr.packed(g).where("src = 1").collect()) == [("a", 1, 2, 2), ("b", 1, 2, 2)]
    bare = gr.from_activity(spark.createDataFrame([(1, 2, 1), (None, 2, 3), (2, None, 3)], "src long, dst long, t long"))
    assert [(r.src, r.dst) for r in gr.packed(bare).collect()] == [(1, 2)]


def test_joins_of_few_edges_keep_their_tasks(spark):
    g = gr.from_activity(spark.createDataFrame([(a, b, a * b % 7 + 1) for a in range(1, 30) for b in range(40, 44)], "src long, dst long, t long"))
    e, n = strategies.settle(gr.packed(g), "packed"), int(spark.conf.get("spark.sql.shuffle.partitions"))
    for limit in ("-1", "10485760"):
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", limit)
        try:
            rows = matching.match(e, pt.in_star(2))
            assert rows.count() == 4 * 29 * 28 // 2 and rows.rdd.getNumPartitions() == n
        finally:
            spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_rules_run_on_what_the_comparisons_leave(spark):
    g = gr.from_activity(spark.createDataFrame([(1, 2, 1), (3, 2, 2), (2, 4, 3)], "src long, dst long, t long"))
    for pattern, cheap in ((pt.in_star(2), "(e1#"), (pt.path(2), "(f1#")):
        line = next(x for x in plan(strategies.solve_full(g, pattern, lib.round_robin(2))).splitlines() if "CASE" in x)
        assert "Join" in line and line.index(cheap) < line.index("CASE")


def test_staged_runs_the_rule_once_for_edges_of_equal_activity(spark):
    rng = random.Random(3)
    edges = {(a, b): sorted(rng.sample(range(1, 4), rng.randrange(1, 3))) for a in range(1, 15) for b in range(1, 6) if a != b}
    g = gr.from_activity(spark.createDataFrame([(*e, t) for e, ts in edges.items() for t in ts], "src long, dst long, t long"))
    whole = gr.packed(g)
    for pattern, rule in ((pt.in_star(2), lib.round_robin(2)), (pt.Pattern.of("(a)-[]->(b), (b)-[]->(c)", distinct_edges=True).bind(c=3), lib.together_for(2, "points"))):
        got, want = (sorted(map(tuple, solve(g, pattern, rule).collect())) for solve in (strategies.solve_staged, strategies.solve_full))
        assert got == want and want, (pattern, rule)
        one = matching.alike(matching.side(whole, pattern, 1), pattern, 1)
        assert one.count() < one.agg(F.sum(F.size("same1"))).first()[0] == matching.side(whole, pattern, 1).count()
    lines = plan(strategies.solve_staged(g, pt.in_star(2), lib.round_robin(2))).splitlines()
    join = next(k for k, x in enumerate(lines) if "Join" in x)
    assert "CASE" in lines[join] and "Generate" in "".join(lines[:join]) and "e1#" not in lines[join]
    assert matching.loose(pt.cycle(2)) is None and matching.loose(pt.path(3)) is None


def test_partial_matches_of_edges_active_once_make_no_word(spark):
    times = [(a, b, c) for a, b, c in itertools.product(range(1, 4), repeat=3) if a <= b <= c]
    names = ", ".join(f"f{i} long, l{i} long, ts{i} array<struct<t:long, r:long>>" for i in (1, 3, 2))
    df = spark.createDataFrame([[x for t in ts for x in (t, t, [(t, 0)])] for ts in times], names)
    got = df.select(F.array(runners.latest_letter((1, 3, 2))).alias("a"), runners.word(3, low=F.col("f2"), variables=(1, 3, 2)).alias("b")).collect()
    assert len(got) == 10 and all(x.a == x.b for x in got)
    g = gr.from_activity(spark.createDataFrame([(1, 2, 1), (2, 3, 2), (3, 4, 3)], "src long, dst long, t long"))
    for name, pattern in (("handoff_path3_TA_0_staged", pt.path(3)), ("handoff_cycle4_TA_0_staged", pt.cycle(4))):
        text = plan(strategies.solve_staged(g, pattern, lib.round_robin(pattern.m)))
        assert re.search(r"CASE WHEN \(\(f1#\w+ = l1#\w+\) AND \(f2#\w+ = l2#\w+\)\) THEN array", text), name


def test_a_stream_decides_edges_active_once_like_the_rule(spark, tmp_path):
    matcher = OnlineMatcher(spark, pt.path(3), lib.round_robin(3), str(tmp_path))
    for k, batch in enumerate(([(1, 2, 1), (2, 3, 2)], [(3, 4, 3), (4, 5, 2), (1, 2, 4), (4, 6, 4)])):
        matcher.batch(spark.createDataFrame(batch, "src long, dst long, t long"), k)
    seen = [(1, 2, 1), (2, 3, 2), (3, 4, 3), (1, 2, 4), (4, 6, 4)]  # (4, 5, 2) came late
    whole = gr.from_activity(spark.createDataFrame(seen, "src long, dst long, t long"))
    got, want = (sorted(map(tuple, df.collect())) for df in (matcher.results(), strategies.solve_full(whole, pt.path(3), lib.round_robin(3))))
    assert got == want and [r[:4] for r in got] == [(1, 2, 3, 4), (2, 3, 4, 6)]


def test_ondemand_makes_the_halves_of_a_cycle_once_and_without_single_times(spark, monkeypatch):
    rng = random.Random(7)
    edges = {(a, b): sorted(rng.sample(range(1, 9), rng.randrange(1, 3))) for a in range(1, 7) for b in range(1, 7) if a != b and rng.random() < 0.7}
    g = gr.from_activity(spark.createDataFrame([(*e, t) for e, ts in edges.items() for t in ts], "src long, dst long, t long"))
    e, low, high, pattern, rule = gr.packed(g), 2, 5, pt.cycle(4), lib.round_robin(4)
    skip, tests, names = analysis.must_not_precede(rule), strategies.first_order(rule), strategies.result_columns(pattern)
    old, both = e.where(F.col("first") <= low), e.where(F.col("first") <= high)
    delta = matching.match_delta(old, both.where(F.col("first") > low), both, pattern, None, skip, tests)
    lasting = matching.match_lasting(e, low, high, pattern, None, skip, tests)
    firsts, last = [F.col(f"f{i}") for i in range(1, 5)], F.greatest(*(f"l{i}" for i in range(1, 5)))
    whole = matching.match(e, pattern, predicates=tests).where((F.greatest(*firsts) > low) & (F.greatest(*firsts) <= high))
    for got, want in ((delta, whole), (lasting, whole.where(last > high))):
        assert sorted(map(tuple, got.select(names).collect())) == sorted(map(tuple, want.select(names).collect())) and want.count()
        assert "Union" not in plan(got)
    kept = []
    monkeypatch.setattr(strategies, "settle", lambda df, label, f=strategies.settle: (out := f(df, label), kept.append((label, out)))[0])
    got, want = (sorted(map(tuple, f(g, pattern, rule).collect())) for f in (strategies.solve_ondemand, strategies.solve_full))
    assert got == want and want
    assert kept[0][1].where("(ts is null) <> (first = last)").count() == 0 and all(df.where("ts1 is null").count() == 0 for label, df in kept if label == "slab")


def test_full_runs_the_rule_once_for_edges_of_equal_activity(spark):
    rng = random.Random(4)
    edges = {(a, b): sorted(rng.sample(range(1, 4), rng.randrange(1, 3))) for a in range(1, 15) for b in range(1, 6) if a != b}
    g = gr.from_activity(spark.createDataFrame([(*e, t) for e, ts in edges.items() for t in ts], "src long, dst long, t long"))
    whole = gr.packed(g)
    for pattern, rule in ((pt.in_star(2), lib.round_robin(2)), (pt.path(2), lib.never_together()), (pt.Pattern.of("(a)-[]->(b), (b)-[]->(c)", distinct_edges=True), lib.together_for(2, "points"))):
        got = strategies.solve_full(g, pattern, rule)
        rows = strategies.verdicts(g, pattern, rule).where("accepted").select(strategies.result_columns(pattern))
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, rows.collect())) and rows.count(), (pattern, rule)
        assert "Generate" in plan(got).split("Join")[0]
    pairs = matching.match_alike(whole, pt.in_star(2))
    assert pairs.count() < matching.match(whole, pt.in_star(2)).count() == matching.each(pairs, pt.in_star(2)).count()


def test_ondemand_runs_and_stores_edges_of_equal_activity_once(spark, monkeypatch):
    rng = random.Random(6)
    edges = {(a, b): sorted(rng.sample(range(1, 6), rng.randrange(1, 3))) for a in range(1, 15) for b in range(1, 5) if a != b}
    g = gr.from_activity(spark.createDataFrame([(*e, t) for e, ts in edges.items() for t in ts], "src long, dst long, t long"))
    kept = []
    monkeypatch.setattr(strategies, "settle", lambda df, label, f=strategies.settle: (out := f(df, label), kept.append((label, out)))[0])
    for pattern, rule in ((pt.in_star(2), lib.round_robin(2)), (pt.path(2), lib.timed_alternation(2)), (pt.in_star(2), lib.together_for(2, "points"))):
        got = strategies.solve_ondemand(g, pattern, rule, slabs=2)
        rows = strategies.verdicts(g, pattern, rule).where("accepted").select(strategies.result_columns(pattern))
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, rows.collect())) and rows.count(), (pattern, rule)
    slabs = [df for label, df in kept if label == "slab"]
    assert all("same1" in df.columns and "e1" not in df.columns for df in slabs) and any(df.where("size(same1) * size(same2) > 1").count() for df in slabs)
