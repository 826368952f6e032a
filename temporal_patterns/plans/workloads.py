"""The experiments on the given tables, as registered queries, with their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import library as lib
from ..functions import pattern as pt
from ..functions.automaton import TimedRule, unfold, with_idle_clocks
from ..operators import matching, relational, runners, strategies
from ..sources import graphs as gr
from ..sources.storage import scratch, settle, stored
from ..streaming.online import OnlineMatcher, drain
from . import metrics, oracles as sql
from .planner import find

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

PATTERNS = {f"{n}{m}": getattr(pt, n)(m) for n in ("path", "cycle", "in_star", "out_star") for m in (2, 3, 4)}


def rule_of(label: str, m: int) -> TimedRule:
    if m > 2:
        return {"TA_0": lib.round_robin, "TA_3": lib.first_strictly_before, "TA_4": lib.first_in_order}[label](m)
    if label == "TA_8r":
        return lib.contained(2, 1)
    return lib.NINE["TA_1" if label == "TA_0" else label]


def ends(df: DataFrame, pattern: pt.Pattern) -> DataFrame:
    return df.select(*(F.col(f"x{i}").cast("long").alias(f"x{i}") for i in range(1, len(pattern.nodes) + 1)))


def answer(spark: SparkSession, sf_dir: str, graph: str, shape: str, label: str, strategy: str) -> DataFrame:
    g, pattern = gr.GRAPHS[graph](spark, sf_dir), PATTERNS[shape]
    if strategy == "relational":
        return ends(relational.solve(g, pattern, rule_of(label, pattern.m)), pattern)
    if strategy == "partial":
        return ends(strategies.solve_partial(g, pattern, rule_of(label, pattern.m)), pattern)
    return ends(find(g, pattern, rule_of(label, pattern.m), strategy), pattern)


def _add(graph: str, shape: str, label: str, strategy: str, twin: bool = True) -> None:
    name = f"{graph}_{shape}_{label}_{strategy}"
    QUERIES[name] = lambda s, d: answer(s, d, graph, shape, label, strategy)
    if not twin:
        return
    rule = "TA_1" if label == "TA_0" else label
    ORACLES[name] = sql.accepted_sql(graph, shape, rule, 3 if label in ("TA_2", "TA_7") else None)


def _edges(graph: str) -> Query:
    return lambda s, d: gr.edge_table(gr.GRAPHS[graph](s, d)).select("src", "dst", "first", "last", "n_active")


def _stats(graph: str) -> Query:
    return lambda s, d: gr.describe(gr.GRAPHS[graph](s, d)).select("nodes", "edges", "active", "snapshots")


for _g in gr.GRAPHS:
    QUERIES[f"graph_{_g}"], ORACLES[f"graph_{_g}"] = _edges(_g), sql.graph_sql(_g)
    QUERIES[f"stats_{_g}"], ORACLES[f"stats_{_g}"] = _stats(_g), sql.stats_sql(_g)

# two-edge rules: strategies rotate, so that each meets each rule on some graph
_WAYS = ("full", "ondemand", "staged", "relational")
for _k, _label in enumerate(lib.NINE):
    for _j, (_g, _s) in enumerate((("rivalry", "path2"), ("handoff", "path2"), ("handoff", "cycle2"), ("visit", "out_star2"))):
        _add(_g, _s, _label, _WAYS[(_k + _j) % 4])
for _s in ("in_star2", "cycle2"):
    _add("rivalry", _s, "TA_7", "staged")
_add("dialogue", "cycle2", "TA_1", "full")
_add("dialogue", "cycle2", "TA_2", "staged")
_add("relay", "cycle2", "TA_1", "ondemand")

# longer patterns
for _s in ("path3", "cycle3", "cycle4"):
    for _w in ("full", "ondemand", "staged"):
        _add("handoff_cohort", _s, "TA_0", _w)
    _add("handoff_cohort", _s, "TA_4", "staged")
_add("rivalry_year", "path3", "TA_0", "staged")
_add("rivalry", "path3", "TA_4", "staged")
for _s in ("path3", "cycle3", "cycle4"):  # DuckDB is too slow for the twins of path3 and cycle4 on a whole graph
    for _w in ("full", "ondemand", "staged"):
        _add("handoff", _s, "TA_0", _w, _s == "cycle3")
    _add("handoff", _s, "TA_4", "staged", _s == "cycle3")
_add("handoff", "cycle3", "TA_3", "auto")


# three strategies (and, where it has a form, the relational one) side by side on one question
_THREE = ("full", "ondemand", "staged")
for _g, _s, _labels in (("rivalry", "path2", ("TA_1", "TA_2", "TA_3")), ("handoff", "path2", ("TA_1", "TA_2", "TA_3")), ("handoff", "cycle2", ("TA_1",)), ("relay", "cycle2", ("TA_1",)), ("rivalry_year", "path3", ("TA_0",)), ("rivalry_year", "cycle3", ("TA_0",)), ("rivalry_year", "out_star3", ("TA_0",)), ("rivalry_year", "in_star3", ("TA_0",)), ("visit", "out_star2", ("TA_1",)), ("visit", "in_star2", ("TA_1",)), ("purchase", "out_star2", ("TA_1",)), ("rivalry", "in_star2", ("TA_7",))):
    for _label in _labels:
        for _w in _THREE:
            _add(_g, _s, _label, _w)
for _s in ("path3", "cycle3"):
    _add("rivalry_year", _s, "TA_0", "relational")
_add("handoff", "path2", "TA_2", "relational")
_add("handoff", "path2", "TA_8r", "auto")
_add("rivalry", "in_star2", "TA_7", "relational")
for _s, _label in (("path2", "TA_1"), ("path2", "TA_6"), ("cycle2", "TA_4")):
    _add("rivalry_year", _s, _label, "partial")


# ---- switches of the strategies, one at a time ----------------------------------------------------------

_SWITCHES = {
    "full_early": lambda g, p, r: strategies.solve_full(g, p, r, early=True),
    "full_no_early": lambda g, p, r: strategies.solve_full(g, p, r, early=False),
    "ondemand_no_early": lambda g, p, r: strategies.solve_ondemand(g, p, r, early=False),
    "ondemand_all_terms": lambda g, p, r: strategies.solve_ondemand(g, p, r, prune_terms=False),
    "ondemand_one_slab": lambda g, p, r: strategies.solve_ondemand(g, p, r, slabs=1),
    "staged_unshared": lambda g, p, r: strategies.solve_staged(g, p, r, share=False),
}
for _n, _f in _SWITCHES.items():
    QUERIES[f"switch_{_n}"] = lambda s, d, f=_f: ends(f(gr.handoff(s, d), pt.cycle(3), lib.round_robin(3)), pt.cycle(3))
    ORACLES[f"switch_{_n}"] = sql.accepted_sql("handoff", "cycle3", "TA_1")


# ---- runners, over one question -------------------------------------------------------------------


def _by_runner(how: str, graph: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, pattern, rule = gr.GRAPHS[graph](spark, sf_dir), pt.cycle(2), lib.round_robin(2)
        if how == "dataflow":
            return ends(strategies.run_dataflow(g, pattern, rule), pattern)
        rows = matching.match(gr.packed(g), pattern).withColumn("word", runners.word(2))
        if how == "exploded":
            words = runners.exploded_word(rows.select("e1", "e2"), g.active, 2)
            rows = rows.drop("word").join(words, ["e1", "e2"])
        if how == "arrow":
            return ends(runners.run_arrow(rows.select("x1", "x2", "word"), rule).where("accepted"), pattern)
        w = F.col("word")
        accepted = {
            "regex": lambda: runners.run_regex(w, rule),
            "monoid": lambda: runners.run_monoid(w, rule, 4),
            "table": lambda: (f := runners.Fold(rule, "table")).accepted(f.run(w)),
            "exploded": lambda: (f := runners.Fold(rule)).accepted(f.run(w)),
        }[how]()
        return ends(rows.where(accepted), pattern)

    return query


for _h in ("dataflow", "regex", "monoid", "table", "arrow", "exploded"):
    QUERIES[f"runner_{_h}"], ORACLES[f"runner_{_h}"] = _by_runner(_h, "handoff_cohort"), sql.accepted_sql("handoff_cohort", "cycle2", "TA_1")
    QUERIES[f"runner_{_h}_handoff"], ORACLES[f"runner_{_h}_handoff"] = _by_runner(_h, "handoff"), sql.accepted_sql("handoff", "cycle2", "TA_1")


# ---- parameter sweeps: one row per value ------------------------------------------------------------


def _rows(parts: list[tuple[int, DataFrame]], name: str) -> DataFrame:
    out = None
    for value, df in parts:
        one = df.agg(F.count("*").alias("accepted")).select(F.lit(value).cast("long").alias(name), "accepted")
        out = one if out is None else out.unionByName(one)
    return out


def _sweep(name: str, column: str, values: tuple[int, ...], graph: Callable, run: Callable, one_sql: Callable[[int], str], store: bool = True) -> None:
    """``run`` for each value, on one ``graph`` that is made once: stored, or by an exchange that all values reuse."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = stored(graph(spark, sf_dir)) if store else graph(spark, sf_dir)
        return _rows([(v, run(g, v)) for v in values], column)

    QUERIES[name] = query
    ORACLES[name] = " UNION ALL ".join(f"SELECT CAST({v} AS BIGINT) AS {column}, {one_sql(v)} AS accepted" for v in values)


BOUNDS, WIDTHS, DOUBLINGS, CLOCKS, DENSITIES = (0, 1, 2, 4, 8, 16, 1024), (1, 4, 12, 24, 48, 120, 360), (0, 2, 4, 6), (0, 2, 4, 8), (100, 400, 700, 1000)
_COHORT = sql.ACTIVITY["handoff_cohort"]
_sweep("sweep_bound", "bound", BOUNDS, gr.handoff_cohort, lambda g, v: strategies.solve_staged(g, pt.path(2), lib.timed_alternation(v)), lambda v: sql.count_sql(_COHORT, "path2", "TA_2", v))
_sweep("sweep_bound_handoff", "bound", BOUNDS, gr.handoff, lambda g, v: strategies.solve_staged(g, pt.path(2), lib.timed_alternation(v)), lambda v: sql.count_sql(sql.ACTIVITY["handoff"], "path2", "TA_2", v))
_sweep("sweep_domain", "width", WIDTHS, lambda s, d: gr.handoff(s, d, "hour"), lambda g, v: strategies.solve_staged(gr.coarsen(g, v), pt.path(2), lib.round_robin(2)), lambda v: sql.count_sql(sql.coarse(sql.ACTIVITY["handoff_hours"], v), "path2", "TA_1"))
_sweep("sweep_states", "doublings", DOUBLINGS, gr.handoff_cohort, lambda g, v: strategies.solve_full(g, pt.cycle(3), unfold(lib.round_robin(3), v)), lambda v: sql.count_sql(_COHORT, "cycle3", "TA_1"))
_sweep("sweep_states_handoff", "doublings", DOUBLINGS, gr.handoff, lambda g, v: strategies.solve_full(g, pt.cycle(3), unfold(lib.round_robin(3), v)), lambda v: sql.count_sql(sql.ACTIVITY["handoff"], "cycle3", "TA_1"))
_sweep("sweep_clocks", "clocks", CLOCKS, gr.handoff_cohort, lambda g, v: strategies.solve_full(g, pt.cycle(3), with_idle_clocks(lib.round_robin(3), v)), lambda v: sql.count_sql(_COHORT, "cycle3", "TA_1"))
_sweep("sweep_clocks_handoff", "clocks", CLOCKS, gr.handoff, lambda g, v: strategies.solve_full(g, pt.cycle(3), with_idle_clocks(lib.round_robin(3), v)), lambda v: sql.count_sql(sql.ACTIVITY["handoff"], "cycle3", "TA_1"))
# a share of the edges of the trade graph, which has nearly all pairs of 25 nations, each active in about half of its quarters
for _s in ("path3", "cycle3", "path4", "cycle4"):
    _sweep(f"sweep_density_{_s}", "density", DENSITIES, gr.rivalry, lambda g, v, p=PATTERNS[_s]: strategies.solve_staged(gr.sample_edges(g, v / 1000), p, lib.first_in_order(p.m)), lambda v, p=_s: sql.count_sql(sql.sampled(sql.ACTIVITY["rivalry"], v), p, "TA_4"), store=False)
# states of the rule of four edges up to 256, and clocks that nothing reads
_sweep("sweep_states_cycle4", "doublings", DOUBLINGS, gr.handoff, lambda g, v: strategies.solve_full(g, pt.cycle(4), unfold(lib.round_robin(4), v)), lambda v: "")
_sweep("sweep_clocks_cycle4", "clocks", CLOCKS, gr.handoff, lambda g, v: strategies.solve_full(g, pt.cycle(4), with_idle_clocks(lib.round_robin(4), v)), lambda v: "")
for _n, _c, _values in (("sweep_states_cycle4", "doublings", DOUBLINGS), ("sweep_clocks_cycle4", "clocks", CLOCKS)):  # the count is the same for each value, so SQL makes it once
    ORACLES[_n] = f"WITH c AS MATERIALIZED (SELECT {sql.count_sql(sql.ACTIVITY['handoff'], 'cycle4', 'TA_1')} AS accepted) SELECT CAST(v AS BIGINT) AS {_c}, accepted FROM c, (SELECT unnest({list(_values)}) AS v)"


# ---- counts, growth, streaming, and plain operators around the methods --------------------------------


def _count_by_degrees(graph: str, m: int) -> Query:
    return lambda s, d: matching.count_paths(gr.GRAPHS[graph](s, d).edges, m)


for _g, _m in (("handoff", 2), ("handoff", 3), ("relay", 2)):
    QUERIES[f"count_{_g}_path{_m}"] = _count_by_degrees(_g, _m)
    _deg = "(SELECT dst AS v, count(*) AS i FROM edg GROUP BY dst) p JOIN {mid} (SELECT src AS v, count(*) AS o FROM edg GROUP BY src) q ON {on}"
    _from = _deg.format(mid="", on="p.v = q.v") if _m == 2 else _deg.format(mid="edg ON edg.src = p.v JOIN", on="q.v = edg.dst")
    ORACLES[f"count_{_g}_path{_m}"] = f"{sql.graph_ctes(sql.ACTIVITY[_g])} SELECT CAST(sum(i * o) AS BIGINT) AS n FROM {_from}"

QUERIES["grow_handoff_cycle3"] = lambda s, d: matching.grow_cycle(gr.handoff(s, d).edges, 3)
ORACLES["grow_handoff_cycle3"] = sql.accepted_sql("handoff", "cycle3", "all")
QUERIES["match_handoff_cycle3"] = lambda s, d: ends(matching.match(gr.packed(gr.handoff(s, d)), pt.cycle(3)), pt.cycle(3))
ORACLES["match_handoff_cycle3"] = sql.accepted_sql("handoff", "cycle3", "all")


def streamed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Handoffs arriving five days at a time, drained, then the matches accepted at the end."""
    path = f"{scratch(spark)}/arrivals-{abs(hash((sf_dir, id(spark))))}"
    g = gr.handoff(spark, sf_dir)
    rows = settle(g.active.join(g.edges, "eid").select("src", "dst", "t"), "activity")  # else each file makes the graph anew
    for k in range(0, 30, 5):  # one file a slab, in order of arrival
        rows.where((F.col("t") > k) & (F.col("t") <= k + 5)).coalesce(1).write.mode("append" if k else "overwrite").parquet(path)
    stream = spark.readStream.schema("src long, dst long, t long").option("maxFilesPerTrigger", 1).parquet(path)
    import uuid

    run = uuid.uuid4().hex
    matcher = OnlineMatcher(spark, pt.path(2), lib.round_robin(2), f"{scratch(spark)}/online-{run}")
    return ends(drain(stream, matcher, f"{scratch(spark)}/offsets-{run}").results(), pt.path(2))


QUERIES["stream_handoff_path2_TA_1"] = streamed
ORACLES["stream_handoff_path2_TA_1"] = sql.accepted_sql("handoff", "path2", "TA_1")


# ---- containers, partial matches and measures ---------------------------------------------------------------


def _partials(maximal: bool) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = gr.handoff(spark, sf_dir)
        return matching.partials(gr.packed(g), pt.path(2), g.nodes, maximal).groupBy("have").agg(F.count("*").alias("n"))

    return query


_HANDOFF = sql.graph_ctes(sql.ACTIVITY["handoff"])
_PAIR = f"SELECT '1,2' AS have, count(*) AS n FROM {sql.SHAPES['path2'][1]}"
QUERIES["partials_handoff_path2"], QUERIES["maximal_partials_handoff_path2"] = _partials(False), _partials(True)
ORACLES["partials_handoff_path2"] = f"{_HANDOFF} SELECT '1' AS have, count(*) AS n FROM edg UNION ALL SELECT '2', count(*) FROM edg UNION ALL {_PAIR}"
ORACLES["maximal_partials_handoff_path2"] = f"SELECT * FROM ({_HANDOFF} SELECT '1' AS have, count(*) AS n FROM edg WHERE dst NOT IN (SELECT src FROM edg) UNION ALL SELECT '2', count(*) FROM edg WHERE src NOT IN (SELECT dst FROM edg) UNION ALL {_PAIR}) WHERE n > 0"

QUERIES["operator_snapshot"] = lambda s, d: gr.snapshot(gr.handoff(s, d), 10).select("src", "dst")
ORACLES["operator_snapshot"] = f"SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM ({sql.ACTIVITY['handoff']}) WHERE t = 10"
QUERIES["operator_new_edges"] = lambda s, d: gr.fresh(gr.edge_table(gr.handoff(s, d)), 9, 10).select("src", "dst")
ORACLES["operator_new_edges"] = f"{_HANDOFF} SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM edg WHERE f = 10"
QUERIES["operator_snapshots_10"] = lambda s, d: gr.edge_table(gr.to_snapshots(gr.handoff(s, d), 10)).groupBy("first").agg(F.count("*").alias("edges"), F.sum("n_active").alias("active"))
ORACLES["operator_snapshots_10"] = f"WITH act AS ({sql.ACTIVITY['handoff']}), wide AS (SELECT DISTINCT src, dst, (t - 1) // (SELECT (max(t) + 9) // 10 FROM act) + 1 AS t FROM act), e AS (SELECT min(t) AS first, count(*) AS n FROM wide GROUP BY src, dst) SELECT CAST(first AS BIGINT) AS first, count(*) AS edges, CAST(sum(n) AS BIGINT) AS active FROM e GROUP BY first"
QUERIES["operator_sample"] = lambda s, d: gr.edge_table(gr.sample_edges(gr.handoff(s, d), 0.25)).select("src", "dst", "n_active")
ORACLES["operator_sample"] = f"{_HANDOFF} SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, CAST(len(ts) AS BIGINT) AS n_active FROM edg WHERE {sql.mixed('src', 'dst', 1)} < 250"
QUERIES["operator_min_stay"] = lambda s, d: gr.edge_table(gr.visit(s, d, 600)).select("src", "dst", "first", "n_active")
ORACLES["operator_min_stay"] = "SELECT src, dst, CAST(min(t) AS BIGINT) AS first, count(DISTINCT t) AS n_active FROM (SELECT CAST(user_id AS BIGINT) AS src, CAST(json_extract(props, '$.k') AS BIGINT) + 1000000 AS dst, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) * 2 + hour(ts) // 12 + 1 AS t, floor(epoch(lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id))) - floor(epoch(ts)) AS stay FROM events) WHERE coalesce(stay, 600) >= 600 GROUP BY src, dst"
QUERIES["operator_densities"] = lambda s, d: gr.describe(gr.handoff(s, d)).select(F.round(F.col("structural_density") * 1e6).cast("long").alias("structural_ppm"), F.round(F.col("temporal_density") * 1e6).cast("long").alias("temporal_ppm"))
ORACLES["operator_densities"] = f"SELECT CAST(round(edges / (nodes * (nodes - 1)) * 1e6) AS BIGINT) AS structural_ppm, CAST(round(active / (edges * snapshots) * 1e6) AS BIGINT) AS temporal_ppm FROM ({sql.stats_sql('handoff')})"
QUERIES["operator_violations"] = lambda s, d: gr.validate(gr.TemporalGraph((g := gr.handoff(s, d)).nodes.where("vid > 10"), g.edges, g.active.where("t > 2")))
ORACLES["operator_violations"] = f"{_HANDOFF} SELECT 'dangling end' AS violation, count(*) AS n FROM (SELECT unnest([src, dst]) AS v FROM edg) WHERE v <= 10 UNION ALL SELECT 'never active', count(*) FROM edg WHERE l <= 2"
QUERIES["measure_selectivity"] = lambda s, d: metrics.counts(gr.handoff(s, d), pt.path(2), lib.round_robin(2)).select("matches", "accepted", "letters")
ORACLES["measure_selectivity"] = f"{sql.accepted_ctes(sql.ACTIVITY['handoff'], 'path2', 'TA_1')} SELECT (SELECT count(*) FROM pairs) AS matches, (SELECT count(*) FROM accepted) AS accepted, (SELECT count(*) FROM letters) AS letters"


def latest_before(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As-of: for each purchase of a user, the time of the latest view before it, by one window."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", "event_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    view = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), True).over(w)
    return e.withColumn("view_id", view).where("event_type = 'purchase'").select("event_id", "view_id")


QUERIES["operator_asof"] = latest_before
ORACLES["operator_asof"] = "SELECT event_id, view_id FROM (SELECT *, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS view_id FROM events) WHERE event_type = 'purchase'"
QUERIES["operator_cube"] = lambda s, d: s.read.parquet(f"{d}/events.parquet").cube("event_type", F.to_date("ts").alias("day")).agg(F.count("*").alias("n")).select("event_type", F.col("day").cast("string").alias("day"), "n")
ORACLES["operator_cube"] = "SELECT event_type, CAST(day AS VARCHAR) AS day, count(*) AS n FROM (SELECT event_type, CAST(ts AS DATE) AS day FROM events) GROUP BY CUBE (event_type, day)"
QUERIES["operator_busiest"] = lambda s, d: gr.edge_table(gr.handoff(s, d)).withColumn("rank", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("n_active"), "dst"))).where("rank <= 3").select("src", "dst", "n_active", "rank")
ORACLES["operator_busiest"] = f"{sql.graph_ctes(sql.ACTIVITY['handoff'])} SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, CAST(len(ts) AS BIGINT) AS n_active, CAST(row_number() OVER (PARTITION BY src ORDER BY len(ts) DESC, dst) AS INTEGER) AS rank FROM edg QUALIFY rank <= 3"
QUERIES["operator_history"] = lambda s, d: gr.history(gr.handoff(s, d), 10).select("src", "dst")
ORACLES["operator_history"] = f"{sql.graph_ctes(sql.ACTIVITY['handoff'])} SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM edg WHERE f <= 10"


#: Queries on users 1 to 50 alone: fixtures of the tests, which aren't registered.  Each has a whole-graph query beside it.
FIXTURES = {n for n in QUERIES if "handoff_cohort" in n} | {f"runner_{h}" for h in ("dataflow", "regex", "monoid", "table", "arrow", "exploded")} | {"sweep_bound", "sweep_states", "sweep_clocks"}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exchanges in conversations that strictly alternate."""
    return answer(spark, sf_dir, "dialogue", "cycle2", "TA_1", "full")
