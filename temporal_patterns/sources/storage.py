"""Stores of temporal graphs and of tables between jobs."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

from .graphs import TemporalGraph

NODES = "vid long, label string"
EDGES = "eid long, src long, dst long, label string"
ACTIVE = "eid long, t long"
_SCHEMAS = {"nodes": NODES, "edges": EDGES, "active": ACTIVE}
_local: dict[str, str] = {}


def write_graph(g: TemporalGraph, path: str, fmt: str = "parquet") -> None:
    """The three relations under ``path`` (parquet, orc, json or csv); activity in order of time within files."""
    for name in _SCHEMAS:
        df = getattr(g, name)
        df = df.sortWithinPartitions("t") if name == "active" else df
        df.write.format(fmt).mode("overwrite").option("header", True).save(f"{path}/{name}")


def read_graph(spark: SparkSession, path: str, fmt: str = "parquet") -> TemporalGraph:
    reader = spark.read.format(fmt).option("header", True)
    return TemporalGraph(*(reader.schema(s).load(f"{path}/{name}") for name, s in _SCHEMAS.items()))


def stream_active(spark: SparkSession, path: str, schema: str = "src long, dst long, t long") -> DataFrame:
    """Activity that arrives as files."""
    return spark.readStream.schema(schema).parquet(path)


def scratch(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; a local session without it has a folder of its own."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not spark.conf.get("spark.master", "local").startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _local:
        _local[app] = "file://" + tempfile.mkdtemp(prefix="spark-temporal-")
    return _local[app]


def settle(df: DataFrame, label: str) -> DataFrame:
    """``df`` written and read again: its lineage ends here."""
    path = f"{scratch(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stored(g: TemporalGraph) -> TemporalGraph:
    """``g`` written once, for queries that solve on it several times."""
    return TemporalGraph(*(settle(getattr(g, name), name) for name in _SCHEMAS))
