"""Intermediate tables in the folder that the driver and all executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The cluster's checkpoint folder; a temporary one only in local mode with none set (tests)."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = _LOCAL.setdefault("dir", "file://" + tempfile.mkdtemp(prefix="edgeblocks-"))
    if "://" not in base and base.startswith("/") and spark.sparkContext.master.startswith("local"):
        base = "file://" + base
    return base.rstrip("/")


def fresh_dir(spark: SparkSession, label: str) -> str:
    """A new folder below the shared one; removed when the driver ends."""
    path = f"{shared_dir(spark)}/edgeblocks-{label}-{uuid.uuid4().hex}"
    atexit.register(remove_dir, spark, path)
    return path


def remove_dir(spark: SparkSession, path: str) -> None:
    """Delete a folder of intermediate files; a stopped session leaves it to the folder's owner."""
    try:
        jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(conf).delete(where, True)
    except Exception:  # noqa: BLE001  at exit the JVM may be gone
        pass


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write once and read back: cuts lineage, survives lost executors, is computed a single time."""
    spark = df.sparkSession
    path = fresh_dir(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
