"""Tables spilled to the shared folder: they cut lineage and outlive executors."""

from __future__ import annotations

import atexit
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession


#: Least time between two collections.
COLLECT_SECONDS = 3
_collected = 0.0


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where none is set and Spark is local."""
    got = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if got:
        return got.rstrip("/")
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get().rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    made = tempfile.mkdtemp(prefix="partgraph-")
    spark.sparkContext.setCheckpointDir(made)
    return made


def spill(df: DataFrame, *done: DataFrame) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it back; then ``done``, spilled before, are deleted.

    The shuffle files of the written plan are of no more use: a collection on the driver lets Spark remove them. Loops of
    short rounds collect now and then only.
    """
    global _collected
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/spill-{uuid.uuid4().hex}"
    df.write.parquet(path)
    atexit.register(_delete, spark, path)
    table = spark.read.schema(df.schema).parquet(path)
    table._spilled = path
    forget(*done)
    if time.monotonic() - _collected > COLLECT_SECONDS:
        spark.sparkContext._jvm.System.gc()
        _collected = time.monotonic()
    return table


def forget(*tables: DataFrame | None) -> None:
    """Delete spilled tables that no plan reads any more; other DataFrames are left alone."""
    for table in tables:
        path = getattr(table, "_spilled", None)
        if path:
            table._spilled = None
            _delete(table.sparkSession, path)


def _delete(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # noqa: BLE001  the session may be gone at exit
        pass
