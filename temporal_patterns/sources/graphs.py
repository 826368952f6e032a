"""Temporal graphs from ordinary tables.

A graph is three relations: nodes (vid, label), edges and their activity (eid, t).  Timepoints are
whole ticks from 1 on.  ``packed`` keeps an edge's activity as one sorted array, so that rules run on
a match's row without another shuffle.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class TemporalGraph:
    nodes: DataFrame
    #: eid, src, dst, label
    edges: DataFrame
    #: eid, t
    active: DataFrame
    #: eid, src, dst, label, t: edges and activity in one, where no edge has two labels
    rows: DataFrame | None = None


def edge_id(src: Column, dst: Column) -> Column:
    """An identity that can't collide while node ids are below 2**31."""
    return src * F.lit(1 << 31) + dst


def from_activity(rows: DataFrame, nodes: DataFrame | None = None) -> TemporalGraph:
    """From rows (src, dst, t[, label]); repeated activity counts once."""
    labelled = "label" in rows.columns
    base = rows.select(*(F.col(c).cast("long").alias(c) for c in ("src", "dst", "t")), *(["label"] if labelled else [])).distinct()
    base = base.withColumn("eid", edge_id(F.col("src"), F.col("dst")))
    if not labelled:
        base = base.withColumn("label", F.lit(None).cast("string"))
    if nodes is None:
        ends = base.select(F.col("src").alias("vid")).unionByName(base.select(F.col("dst").alias("vid"))).distinct()
        nodes = ends.withColumn("label", F.lit(None).cast("string"))
    return TemporalGraph(nodes, base.select("eid", "src", "dst", "label").distinct(), base.select("eid", "t"), None if labelled else base)


def domain(g: TemporalGraph) -> DataFrame:
    """t, r: the distinct timepoints and their ranks (as many rows as timepoints)."""
    return g.active.select("t").distinct().withColumn("r", F.row_number().over(Window.orderBy("t")).cast("long"))


def packed(g: TemporalGraph, ranked: bool = False) -> DataFrame:
    """eid, src, dst, label, first, last, n_active, ts: one row per edge, ``ts`` sorted; one shuffle of the
    activity.  ``ranked``: ts holds (t, r) with the rank in the graph's domain, else (t, 0)."""
    act = g.active
    if ranked:
        act = act.join(domain(g), "t")  # Spark broadcasts it if its size at run time allows
    elif g.rows is not None:  # its rows are distinct: the graph is made once, and edges don't meet their activity in a join
        line = F.array_sort(F.collect_list(F.struct("t", F.lit(0).cast("long").alias("r"))))
        per = g.rows.where("eid is not null").groupBy("src", "dst").agg(line.alias("ts"), F.min("t").alias("first"), F.max("t").alias("last"))
        return per.select(edge_id(F.col("src"), F.col("dst")).alias("eid"), "src", "dst", F.lit(None).cast("string").alias("label"), "ts", "first", "last", F.size("ts").alias("n_active"))
    else:
        act = act.withColumn("r", F.lit(0).cast("long"))
    per = act.groupBy("eid").agg(F.array_sort(F.collect_set(F.struct("t", "r"))).alias("ts"), F.min("t").alias("first"), F.max("t").alias("last"))
    return g.edges.join(per, "eid").withColumn("n_active", F.size("ts"))


def edge_table(g: TemporalGraph) -> DataFrame:
    per = g.active.groupBy("eid").agg(F.min("t").alias("first"), F.max("t").alias("last"), F.count("*").alias("n_active"))
    return g.edges.join(per, "eid")


def snapshot(g: TemporalGraph, t: int) -> DataFrame:
    return g.edges.join(g.active.where(F.col("t") == t), "eid", "left_semi")


def history(g: TemporalGraph, t: int) -> DataFrame:
    return g.edges.join(g.active.where(F.col("t") <= t), "eid", "left_semi")


def fresh(edges: DataFrame, low: int, high: int) -> DataFrame:
    return edges.where((F.col("first") > low) & (F.col("first") <= high))


def coarsen(g: TemporalGraph, width: int) -> TemporalGraph:
    t = F.floor((F.col("t") - 1) / width).cast("long") + 1
    return TemporalGraph(g.nodes, g.edges, g.active.select("eid", t.alias("t")).distinct())


def to_snapshots(g: TemporalGraph, count: int) -> TemporalGraph:
    """The same activity in ``count`` snapshots at most, of equal width."""
    last = g.active.agg(F.max("t")).first()[0]
    return g if last is None else coarsen(g, max(1, -(-last // count)))


def sample_edges(g: TemporalGraph, density: float, seed: int = 1) -> TemporalGraph:
    """A share of the edges, by an integer mix of their ends that any engine can repeat."""
    kept = g.edges.where(mixed("src", "dst", seed) < int(density * 1000))
    return TemporalGraph(g.nodes, kept, g.active.join(kept.select("eid"), "eid", "left_semi"))


def mixed(a: str, b: str, seed: int) -> Column:
    """0 .. 999 from two columns, by 64-bit arithmetic without overflow."""
    return F.pmod(F.pmod(F.col(a) * 7919 + F.col(b) * 104729 + seed * 1299709, F.lit(1000003)) * 31337, F.lit(1000003)) % 1000


def describe(g: TemporalGraph, bipartite: bool = False) -> DataFrame:
    """nodes, edges, active, snapshots, structural and temporal density, in one row."""
    ends = g.edges.agg(F.countDistinct("src").alias("s"), F.countDistinct("dst").alias("d"), F.count("*").alias("edges"))
    acts = g.active.agg(F.count("*").alias("active"), F.countDistinct("t").alias("snapshots"))
    both = g.nodes.agg(F.count("*").alias("nodes")).join(ends.hint("broadcast")).join(acts.hint("broadcast"))  # one row each
    pairs = F.col("s") * F.col("d") if bipartite else F.col("nodes") * (F.col("nodes") - 1)
    return both.select("nodes", "edges", "active", "snapshots", (F.col("edges") / pairs).alias("structural_density"), (F.col("active") / (F.col("edges") * F.col("snapshots"))).alias("temporal_density"))


def validate(g: TemporalGraph) -> DataFrame:
    """violation, n: dangling ends, non-positive times, edges that are never active, repeated ids."""
    ends = g.edges.select(F.explode(F.array("src", "dst")).alias("vid"))
    checks = [
        ("dangling end", ends.join(g.nodes, "vid", "left_anti")),
        ("time below 1", g.active.where("t < 1")),
        ("never active", g.edges.join(g.active, "eid", "left_anti")),
        ("activity without edge", g.active.join(g.edges, "eid", "left_anti")),
        ("repeated edge id", g.edges.groupBy("eid").count().where("count > 1")),
        ("repeated activity", g.active.groupBy("eid", "t").count().where("count > 1")),
    ]
    out = None
    for name, rows in checks:
        one = rows.agg(F.count("*").alias("n")).select(F.lit(name).alias("violation"), "n")
        out = one if out is None else out.unionByName(one)
    return out.where("n > 0")


# ---- builders over the given tables ------------------------------------------------------------------


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _day(ts: str | Column, origin: str) -> Column:
    return F.datediff(ts, F.lit(origin).cast("date"))


def handoff(spark: SparkSession, sf_dir: str, tick: str = "day") -> TemporalGraph:
    """Who handed over to whom: user of an event to the user of the next one in the same hour."""
    e = _table(spark, sf_dir, "events").select("ts", "user_id", "event_id")
    hour = F.date_trunc("hour", "ts")
    e = e.withColumn("next", F.lead("user_id").over(Window.partitionBy(hour).orderBy("ts", "event_id")))
    day = _day("ts", "2024-01-01")
    t = day + 1 if tick == "day" else day * 24 + F.hour("ts") + 1
    return from_activity(e.where("user_id <> next").select(F.col("user_id").alias("src"), F.col("next").alias("dst"), t.alias("t")))


def handoff_cohort(spark: SparkSession, sf_dir: str, upto: int = 50) -> TemporalGraph:
    g = handoff(spark, sf_dir)
    edges = g.edges.where((F.col("src") <= upto) & (F.col("dst") <= upto))
    return TemporalGraph(g.nodes.where(F.col("vid") <= upto), edges, g.active.join(edges.select("eid"), "eid", "left_semi"))


def dialogue(spark: SparkSession, sf_dir: str) -> TemporalGraph:
    """Speakers of a conversation: role of a turn to the role of the next one."""
    c = _table(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    code = F.when(F.col("role") == "user", 0).when(F.col("role") == "assistant", 1).otherwise(2)
    c = c.withColumn("node", F.col("conv_id") * 3 + code)
    c = c.withColumn("next", F.lead("node").over(Window.partitionBy("conv_id").orderBy("turn")))
    nodes = c.select(F.col("node").alias("vid"), F.col("role").alias("label")).distinct()
    return from_activity(c.where("next is not null and node <> next").select(F.col("node").alias("src"), F.col("next").alias("dst"), (F.col("turn") + 1).alias("t")), nodes)


def visit(spark: SparkSession, sf_dir: str, min_stay_s: int = 0) -> TemporalGraph:
    """Users at places, in half-day windows; a stay lasts to the user's next event."""
    e = _table(spark, sf_dir, "events").select("ts", "user_id", "event_id", "props")
    if min_stay_s:
        stay = F.unix_timestamp(F.lead("ts").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))) - F.unix_timestamp("ts")
        e = e.withColumn("stay", stay).where(F.col("stay").isNull() | (F.col("stay") >= min_stay_s))
    place = F.get_json_object("props", "$.k").cast("long") + 1_000_000
    t = _day("ts", "2024-01-01") * 2 + F.floor(F.hour("ts") / 12) + 1
    return from_activity(e.select(F.col("user_id").alias("src"), place.alias("dst"), t.alias("t")))


def relay(spark: SparkSession, sf_dir: str) -> TemporalGraph:
    """Buyer of a part to its next buyer, at the day of the later order."""
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber")
    orders = _table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    b = lines.join(orders, lines.l_orderkey == orders.o_orderkey)
    along = Window.partitionBy("l_partkey").orderBy("o_orderdate", "o_orderkey", "l_linenumber")
    b = b.withColumns({"next": F.lead("o_custkey").over(along), "day": F.lead("o_orderdate").over(along)})
    return from_activity(b.where("next is not null and o_custkey <> next").select(F.col("o_custkey").alias("src"), F.col("next").alias("dst"), (_day("day", "1995-01-01") + 1).alias("t")))


def purchase(spark: SparkSession, sf_dir: str) -> TemporalGraph:
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    orders = _table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    b = lines.join(orders, lines.l_orderkey == orders.o_orderkey)
    t = (F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate")
    return from_activity(b.select(F.col("o_custkey").alias("src"), (F.col("l_suppkey") + 10_000_000).alias("dst"), t.alias("t")))


def rivalry(spark: SparkSession, sf_dir: str, tick: str = "quarter") -> TemporalGraph:
    """Nations that trade with each other: per period, from the larger bilateral seller to the smaller (both, when equal)."""
    o = _table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_extendedprice")
    c = _table(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").alias("a"))
    s = _table(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").alias("b"))
    year = F.year("o_orderdate")
    t = year - 1994 if tick == "year" else (year - 1995) * 4 + F.quarter("o_orderdate")
    # orders get their nation before they meet the lines, and both directions of a pair are one row: the lines are joined once
    bought = o.join(c, o.o_custkey == c.c_custkey).select("o_orderkey", "a", t.alias("t"))
    sold = lines.join(s, lines.l_suppkey == s.s_suppkey).select("l_orderkey", "b", F.round(F.col("l_extendedprice") * 100).cast("long").alias("cents"))
    low, high = F.least("a", "b").cast("long"), F.greatest("a", "b").cast("long")
    sales = sold.join(bought, sold.l_orderkey == bought.o_orderkey).where("a <> b").groupBy(low.alias("low"), high.alias("high"), "t")
    pairs = sales.agg(F.sum(F.when(F.col("a") < F.col("b"), F.col("cents"))).alias("up"), F.sum(F.when(F.col("a") > F.col("b"), F.col("cents"))).alias("down"))
    way = lambda src, dst, cents, against: F.struct(F.col(src).alias("src"), F.col(dst).alias("dst"), (F.col(cents) >= F.coalesce(F.when(F.col("t").isNotNull(), F.col(against)), F.lit(0))).alias("sells"))
    both = pairs.select("t", F.explode(F.array(way("low", "high", "up", "down"), way("high", "low", "down", "up"))).alias("way"))
    return from_activity(both.where("way.sells").select("way.src", "way.dst", "t"))


def complete_sample(spark: SparkSession, n: int, snapshots: int, density: float, temporal: float = 0.5) -> TemporalGraph:
    """All ordered pairs of ``n`` nodes, a share of them kept, each active at a share of the snapshots."""
    pairs = spark.range(n * n).select((F.col("id") % n).alias("src"), F.floor(F.col("id") / n).cast("long").alias("dst")).where("src <> dst")
    pairs = pairs.where(mixed("src", "dst", 1) < int(density * 1000))
    rows = pairs.withColumn("t", F.explode(F.sequence(F.lit(1), F.lit(snapshots)))).withColumn("e", F.col("src") * n + F.col("dst"))
    return from_activity(rows.where(mixed("e", "t", 2) < int(temporal * 1000)).select("src", "dst", "t"))


def office_example(spark: SparkSession, v4_label: str = "customer") -> TemporalGraph:
    """The running example, times multiplied by ten."""
    edges = [
        (1, 1, 2, "message", [10, 30]), (2, 1, 3, "message", [11, 19]), (3, 2, 4, "message", [10, 30]), (4, 3, 4, "message", [10]),
        (5, 5, 1, "message", [10, 30, 50]), (6, 1, 5, "message", [20, 40, 60]), (7, 6, 1, "message", [20]), (8, 7, 1, "message", [20, 30, 40]),
        (9, 1, 7, "message", [90]), (10, 2, 3, "message", [20, 40, 60]), (11, 2, 8, "visit", [10, 30, 60]), (12, 4, 8, "visit", [20, 40]),
    ]
    labels = {1: "employee", 2: "employee", 3: "employee", 4: v4_label, 5: "customer", 6: "customer", 7: "customer", 8: "office"}
    return TemporalGraph(
        spark.createDataFrame(list(labels.items()), "vid long, label string"),
        spark.createDataFrame([e[:4] for e in edges], "eid long, src long, dst long, label string"),
        spark.createDataFrame([(e[0], t) for e in edges for t in e[4]], "eid long, t long"),
    )


def borders_of_intervals(rows: DataFrame) -> DataFrame:
    """Activity at both ends of intervals: (src, dst, from, to) -> (src, dst, t, label start / end)."""
    ends = F.explode(F.array(F.struct(F.col("from").alias("t"), F.lit("start").alias("label")), F.struct(F.col("to").alias("t"), F.lit("end").alias("label"))))
    return rows.select("src", "dst", ends.alias("x")).select("src", "dst", "x.t", "x.label")


GRAPHS: dict[str, Callable[[SparkSession, str], TemporalGraph]] = {
    "rivalry": rivalry, "rivalry_year": lambda s, d: rivalry(s, d, "year"), "visit": visit, "handoff": handoff,
    "handoff_cohort": handoff_cohort, "relay": relay, "purchase": purchase, "dialogue": dialogue,
}
