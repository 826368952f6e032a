"""Rules over activity that arrives as a stream.

Each micro-batch is a time slab: its activity is stored under the batch's id (a replayed batch writes the
same place again), new matches come from delta joins and catch up from the history, live matches advance by
the slab's letters, and those without a living run are dropped.  The live table and the slab's end are written per batch,
so a new matcher at the same path goes on from the last one.  Activity at or before the last slab's end is late: letters must come in
order, so it goes to a table of its own.
"""

from __future__ import annotations

import functools
import operator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.automaton import TimedRule
from ..functions.pattern import Pattern
from ..operators.matching import match_delta
from ..operators.runners import Fold, once, word
from ..operators.strategies import first_order, result_columns
from ..sources.graphs import from_activity, packed
from ..sources.storage import scratch, settle


class OnlineMatcher:
    """Feed it batches of (src, dst, t) in time order; rules that ignore empty letters only."""

    def __init__(self, spark: SparkSession, pattern: Pattern, rule: TimedRule, path: str | None = None):
        self.fold = Fold(rule)
        if self.fold.kind != "neutral":
            raise ValueError("online matching needs a rule that ignores empty letters")
        self.spark, self.pattern = spark, pattern
        self.path = path or f"{scratch(spark)}/online-{id(self)}"
        self.ends: dict[int, int] = self._stored_ends()

    def _stored_ends(self) -> dict[int, int]:
        """The slabs that an earlier matcher has finished at this path, with their ends: a row each."""
        at = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/ends")
        if not at.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(at):
            return {}
        rows = self.spark.read.schema("batch long, end long").option("recursiveFileLookup", True).parquet(f"{self.path}/ends")
        return {r.batch: r.end for r in rows.collect()}

    def _read(self, name: str, ids: list[int]) -> DataFrame | None:
        return self.spark.read.parquet(*(f"{self.path}/{name}/{i}" for i in ids)) if ids else None

    def batch(self, rows: DataFrame, batch_id: int) -> None:
        """One slab; its activity ends at its latest time."""
        past = sorted(i for i in self.ends if i < batch_id)
        low = max((self.ends[i] for i in past), default=0)
        rows.where(F.col("t") <= low).write.mode("overwrite").parquet(f"{self.path}/late/{batch_id}")
        rows.where(F.col("t") > low).select("src", "dst", "t").distinct().write.mode("overwrite").parquet(f"{self.path}/active/{batch_id}")
        high = self._read("active", [batch_id]).agg(F.max("t")).first()[0]
        self.ends[batch_id] = high or low
        m, names = self.pattern.m, result_columns(self.pattern)
        keys = [*names, *(f"f{i}" for i in range(1, m + 1))]
        both = settle(packed(from_activity(self._read("active", [*past, batch_id]))), "packed")
        old, new = both.where(F.col("first") <= low), both.where(F.col("first") > low)
        fresh = match_delta(old, new, both, self.pattern, predicates=first_order(self.fold.rule))
        until = F.lit(self.ends[batch_id] + 1)
        acc = self.fold.run(word(m, high=until))
        if self.fold.bits:
            acc = F.when(once(range(1, m + 1)), self.fold.run_once()).otherwise(acc)
        out = fresh.withColumn("acc", acc).select(*keys, "acc")
        if past:
            live = self.spark.read.parquet(f"{self.path}/live/{past[-1]}")
            for i in range(1, m + 1):
                live = live.join(both.where(F.col("last") > low).select(F.col("eid").alias(f"e{i}"), F.col("ts").alias(f"ts{i}")), f"e{i}", "left")
                live = live.withColumn(f"ts{i}", F.coalesce(f"ts{i}", F.array().cast(both.schema["ts"].dataType)))  # no activity in this slab
            idle = functools.reduce(operator.and_, [F.size(f"ts{i}") == 0 for i in range(1, m + 1)])
            live = live.withColumn("acc", F.when(idle, F.col("acc")).otherwise(self.fold.run(word(m, low=F.lit(low + 1), high=until), F.col("acc"))))
            out = out.unionByName(live.select(*keys, "acc"))
        out.where(self.fold.alive(F.col("acc"))).write.mode("overwrite").parquet(f"{self.path}/live/{batch_id}")
        # written last: a slab counts as done once its live table is whole
        end = self.spark.range(1).select(F.lit(batch_id).cast("long").alias("batch"), F.lit(self.ends[batch_id]).cast("long").alias("end"))
        end.write.mode("overwrite").parquet(f"{self.path}/ends/{batch_id}")

    def results(self) -> DataFrame:
        """Matches accepted as of the last slab."""
        live = self.spark.read.parquet(f"{self.path}/live/{max(self.ends)}")
        return live.where(self.fold.accepted(F.col("acc"))).select(result_columns(self.pattern))

    def late(self) -> DataFrame:
        return self._read("late", sorted(self.ends))


def drain(stream: DataFrame, matcher: OnlineMatcher, checkpoint: str) -> OnlineMatcher:
    """Runs all that has arrived through ``matcher``, a micro-batch at a time."""
    query = stream.writeStream.foreachBatch(lambda df, i: matcher.batch(df, i)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return matcher


def activity_windows(events: DataFrame, width: str = "1 day", lateness: str = "1 hour") -> DataFrame:
    """Events (ts, src, dst) as activity per tumbling window, with late data dropped by a watermark."""
    return events.withWatermark("ts", lateness).groupBy(F.window("ts", width), "src", "dst").agg(F.count("*").alias("n")).select("src", "dst", F.col("window.start").alias("t"), "n")
