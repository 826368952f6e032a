"""Tables written between jobs, in the folder that all executors share."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; only a local session without it gets a folder of its own."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not spark.conf.get("spark.master", "local").startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _own:
        _own[app] = "file://" + tempfile.mkdtemp(prefix="spark-workspace-")
    return _own[app]


def keep(df: DataFrame, label: str) -> DataFrame:
    """``df`` written once and read again: its lineage ends here and no later job computes it anew."""
    path = f"{shared_dir(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.kept_at = path
    return out


def _delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def forget(*tables: DataFrame, shuffles: bool = True) -> None:
    """Deletes tables of ``keep`` that nothing reads any more.  Shuffle files of finished jobs go with the next
    collection of the driver's garbage, which is asked for here (with ``shuffles``)."""
    for t in tables:
        _delete(t.sparkSession, t.kept_at)
    if shuffles:
        collect_garbage(tables[0].sparkSession)


def collect_garbage(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of plans that the driver no longer holds; the last one run is held
    until another one ends."""
    spark.range(1).count()
    gc.collect()
    spark._jvm.System.gc()


def keep_dealt(df: DataFrame, label: str, column: str) -> tuple[DataFrame, str]:
    """``df`` written once in buckets of ``column``, and the name of its table: joins on it move only the other
    side.  There are as many buckets as shuffles have partitions, so none is dealt anew."""
    spark = df.sparkSession
    name = f"{label}_{uuid.uuid4().hex}"
    df.write.format("parquet").bucketBy(buckets(spark), column).option("path", f"{shared_dir(spark)}/{name}").saveAsTable(name)
    return spark.table(name), name


def forget_dealt(df: DataFrame, name: str) -> None:
    """Drops the table of ``keep_dealt`` and its files."""
    spark = df.sparkSession
    spark.sql(f"DROP TABLE {name}")
    _delete(spark, f"{shared_dir(spark)}/{name}")


def buckets(spark: SparkSession) -> int:
    return min(100_000, int(spark.conf.get("spark.sql.shuffle.partitions")))
