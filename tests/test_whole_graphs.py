"""Registered queries run on whole graphs."""

import duckdb

import __spark_entry__
from temporal_patterns.plans import oracles, workloads


def test_no_registered_query_is_on_a_cohort(spark, sf):
    names = __spark_entry__.queries()
    assert not [n for n in names if "cohort" in n] and not workloads.FIXTURES & set(names)
    for name in ("handoff_cycle3_TA_0_full", "runner_regex_handoff"):
        got = names[name](spark, sf("0.01")).where("x1 > 50").limit(1).count()
        assert got == 1


def test_whole_cycle4_equals_its_sql(spark, sf):
    con = duckdb.connect()
    con.execute(f"create view events as select * from '{sf('0.001')}/events.parquet'")
    want = sorted(con.execute(oracles.accepted_sql("handoff", "cycle4", "TA_4")).fetchall())
    got = __spark_entry__.queries()["handoff_cycle4_TA_4_staged"](spark, sf("0.001"))
    assert sorted(map(tuple, got.collect())) == want and want
