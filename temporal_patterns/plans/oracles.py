"""SQL for DuckDB that computes the registered results without any automaton of ours: graphs by window
functions, words by string_agg, rules by regular expressions, comparisons, lags and islands."""

from __future__ import annotations

_DAY = "date_diff('day', DATE '{o}', CAST({c} AS DATE))"
_D24, _D95 = _DAY.format(o="2024-01-01", c="ts"), _DAY.format(o="1995-01-01", c="d")
_HAND = "SELECT ts, user_id AS src, lead(user_id) OVER (PARTITION BY date_trunc('hour', ts) ORDER BY ts, event_id) AS dst FROM events"
_BUY = "FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
_ROLE = "conv_id * 3 + CASE role WHEN 'user' THEN 0 WHEN 'assistant' THEN 1 ELSE 2 END"


def _trade(t: str) -> str:
    sales = f"SELECT c_nationkey AS a, s_nationkey AS b, {t} AS t, sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS cents {_BUY} JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> s_nationkey GROUP BY ALL"
    return f"SELECT x.a AS src, x.b AS dst, x.t FROM ({sales}) x LEFT JOIN ({sales}) y ON x.a = y.b AND x.b = y.a AND x.t = y.t WHERE x.cents >= coalesce(y.cents, 0)"


ACTIVITY = {
    "handoff": f"SELECT DISTINCT src, dst, {_D24} + 1 AS t FROM ({_HAND}) WHERE src <> dst",
    "handoff_hours": f"SELECT DISTINCT src, dst, {_D24} * 24 + hour(ts) + 1 AS t FROM ({_HAND}) WHERE src <> dst",
    "handoff_cohort": f"SELECT DISTINCT src, dst, {_D24} + 1 AS t FROM ({_HAND}) WHERE src <> dst AND src <= 50 AND dst <= 50",
    "dialogue": f"SELECT DISTINCT src, dst, t FROM (SELECT {_ROLE} AS src, lead({_ROLE}) OVER (PARTITION BY conv_id ORDER BY turn) AS dst, turn + 1 AS t FROM conversations) WHERE src <> dst",
    "visit": f"SELECT DISTINCT user_id AS src, CAST(json_extract(props, '$.k') AS BIGINT) + 1000000 AS dst, {_D24} * 2 + hour(ts) // 12 + 1 AS t FROM events",
    "relay": f"SELECT DISTINCT src, dst, {_D95} + 1 AS t FROM (SELECT o_custkey AS src, lead(o_custkey) OVER w AS dst, lead(o_orderdate) OVER w AS d {_BUY} WINDOW w AS (PARTITION BY l_partkey ORDER BY o_orderdate, o_orderkey, l_linenumber)) WHERE src <> dst",
    "purchase": f"SELECT DISTINCT o_custkey AS src, l_suppkey + 10000000 AS dst, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) AS t {_BUY}",
    "rivalry": _trade("(year(o_orderdate) - 1995) * 4 + quarter(o_orderdate)"),
    "rivalry_year": _trade("year(o_orderdate) - 1994"),
}
_NODES = {"dialogue": f"SELECT count(DISTINCT {_ROLE}) FROM conversations", "handoff_cohort": f"SELECT count(DISTINCT v) FROM (SELECT unnest([src, dst]) AS v FROM ({ACTIVITY['handoff']})) WHERE v <= 50"}

#: The rows of a shape over edg aliases a, b, c, d: nodes, joins.
SHAPES = {
    "path2": (["a.src", "a.dst", "b.dst"], "edg a JOIN edg b ON a.dst = b.src", 2),
    "path3": (["a.src", "a.dst", "b.dst", "c.dst"], "edg a JOIN edg b ON a.dst = b.src JOIN edg c ON b.dst = c.src", 3),
    "cycle2": (["a.src", "a.dst"], "edg a JOIN edg b ON a.dst = b.src AND b.dst = a.src", 2),
    "cycle3": (["a.src", "a.dst", "b.dst"], "edg a JOIN edg b ON a.dst = b.src JOIN edg c ON b.dst = c.src AND c.dst = a.src", 3),
    "cycle4": (["a.src", "a.dst", "b.dst", "c.dst"], "edg a JOIN edg b ON a.dst = b.src JOIN edg c ON b.dst = c.src JOIN edg d ON c.dst = d.src AND d.dst = a.src", 4),
    "path4": (["a.src", "a.dst", "b.dst", "c.dst", "d.dst"], "edg a JOIN edg b ON a.dst = b.src JOIN edg c ON b.dst = c.src JOIN edg d ON c.dst = d.src", 4),
    "out_star3": (["a.src", "a.dst", "b.dst", "c.dst"], "edg a JOIN edg b ON a.src = b.src AND a.eid < b.eid JOIN edg c ON a.src = c.src AND b.eid < c.eid", 3),
    "in_star3": (["a.dst", "a.src", "b.src", "c.src"], "edg a JOIN edg b ON a.dst = b.dst AND a.eid < b.eid JOIN edg c ON a.dst = c.dst AND b.eid < c.eid", 3),
    "out_star2": (["a.src", "a.dst", "b.dst"], "edg a JOIN edg b ON a.src = b.src AND a.eid < b.eid", 2),
    "in_star2": (["a.dst", "a.src", "b.src"], "edg a JOIN edg b ON a.dst = b.dst AND a.eid < b.eid", 2),
}


def graph_ctes(activity: str) -> str:
    return f"WITH act AS ({activity}), edg AS (SELECT src, dst, src * 2147483648 + dst AS eid, min(t) AS f, max(t) AS l, list_sort(list(t)) AS ts FROM act GROUP BY src, dst)"


def graph_sql(name: str) -> str:
    return f"{graph_ctes(ACTIVITY[name])} SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, CAST(f AS BIGINT) AS first, CAST(l AS BIGINT) AS last, CAST(len(ts) AS BIGINT) AS n_active FROM edg"


def stats_sql(name: str) -> str:
    nodes = _NODES.get(name, "SELECT count(DISTINCT v) FROM (SELECT unnest([src, dst]) AS v FROM edg)")
    return f"{graph_ctes(ACTIVITY[name])} SELECT ({nodes}) AS nodes, (SELECT count(*) FROM edg) AS edges, (SELECT count(*) FROM act) AS active, (SELECT count(DISTINCT t) FROM act) AS snapshots"


def _round_robin(m: int) -> str:
    turn = [chr(65 + (1 << i)) for i in range(m)]
    ends = "|".join("".join(turn[:k]) for k in range(1, m))
    return f"({''.join(turn)})*({ends})?"


def accepted_ctes(activity: str, shape: str, rule: str, argument: int | None = None) -> str:
    """CTEs ending in ``accepted`` (x1..xk)."""
    nodes, joins, m = SHAPES[shape]
    names = ", ".join(f"x{i + 1}" for i in range(len(nodes)))
    shown = ", ".join(f"{n} AS x{i + 1}" for i, n in enumerate(nodes))
    parts = ", ".join(f"{a}.f AS f{i}, {a}.l AS l{i}, {a}.ts AS ts{i}" for i, a in enumerate("abcd"[:m], 1))
    head = f"{graph_ctes(activity)}, pairs AS (SELECT {shown}, {parts} FROM {joins})"
    plain = {
        "TA_e": "f1 < l2",
        "TA_3": " AND ".join(f"f{i} < f{i + 1}" for i in range(1, m)),
        "TA_4": " AND ".join(f"f{i} <= f{i + 1}" for i in range(1, m)),
        "TA_5": "ts1 = ts2",
        "TA_6": "len(list_intersect(ts1, ts2)) = 0",
        "TA_8": "len(list_intersect(ts1, ts2)) = len(ts1)",
        "TA_8r": "len(list_intersect(ts1, ts2)) = len(ts2)",
        "all": "true",
    }
    if rule in plain:
        return f"{head}, accepted AS (SELECT {names} FROM pairs WHERE {plain[rule]})"
    if rule == "TA_7":
        return (
            f"{head}, dom AS (SELECT t, row_number() OVER (ORDER BY t) AS r FROM (SELECT DISTINCT t FROM act)), joint AS (SELECT {names}, unnest(list_intersect(ts1, ts2)) AS t FROM pairs), "
            f"isl AS (SELECT {names}, r - row_number() OVER (PARTITION BY {names} ORDER BY r) AS i FROM joint JOIN dom USING (t)), "
            f"accepted AS (SELECT DISTINCT {names} FROM (SELECT {names}, i FROM isl GROUP BY ALL HAVING count(*) >= {argument}))"
        )
    mask = " + ".join(f"CASE WHEN list_contains(ts{i}, t) THEN {1 << (i - 1)} ELSE 0 END" for i in range(1, m + 1))
    times = "ts1"
    for i in range(2, m + 1):
        times = f"list_concat({times}, ts{i})"
    head += f", times AS (SELECT *, unnest(list_distinct({times})) AS t FROM pairs), letters AS (SELECT {names}, t, chr(65 + {mask}) AS c FROM times), lags AS (SELECT *, t - lag(t) OVER (PARTITION BY {names} ORDER BY t) AS gap FROM letters)"
    late = f" AND NOT coalesce(bool_or(c = 'C' AND gap >= {argument}), false)" if rule == "TA_2" else ""
    return f"{head}, accepted AS (SELECT {names} FROM lags GROUP BY {names} HAVING regexp_full_match(string_agg(c, '' ORDER BY t), '{_round_robin(m)}'){late})"


def accepted_sql(graph: str, shape: str, rule: str, argument: int | None = None) -> str:
    n = len(SHAPES[shape][0])
    return f"{accepted_ctes(ACTIVITY[graph], shape, rule, argument)} SELECT {', '.join(f'CAST(x{i} AS BIGINT) AS x{i}' for i in range(1, n + 1))} FROM accepted"


def count_sql(activity: str, shape: str, rule: str, argument: int | None = None) -> str:
    return f"({accepted_ctes(activity, shape, rule, argument)} SELECT count(*) FROM accepted)"


def coarse(activity: str, width: int) -> str:
    return f"SELECT DISTINCT src, dst, (t - 1) // {width} + 1 AS t FROM ({activity})"


def mixed(a: str, b: str, s: int) -> str:
    return f"((({a} * 7919 + {b} * 104729 + {s * 1299709}) % 1000003 * 31337) % 1000003 % 1000)"


def complete(n: int, snapshots: int, density: float, temporal: float = 0.5) -> str:
    pairs = f"SELECT i % {n} AS src, i // {n} AS dst FROM range({n * n}) r(i)"
    return f"SELECT src, dst, t FROM ({pairs}), range(1, {snapshots + 1}) s(t) WHERE src <> dst AND {mixed('src', 'dst', 1)} < {int(density * 1000)} AND {mixed(f'(src * {n} + dst)', 't', 2)} < {int(temporal * 1000)}"


def sampled(activity: str, density: int) -> str:
    """The activity of ``density`` of 1,000 edges."""
    return f"SELECT src, dst, t FROM ({activity}) WHERE {mixed('CAST(src AS BIGINT)', 'CAST(dst AS BIGINT)', 1)} < {density}"
