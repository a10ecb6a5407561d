"""Where results go."""

from __future__ import annotations

from pyspark.sql import DataFrame

#: Blocks up to which each gets a folder of its own.
FOLDERS = 1000


def blocks(assign: DataFrame, path: str, k: int) -> None:
    """eid, u, v by block: a folder per block, or ranges of blocks for many."""
    rows = assign.select("eid", "u", "v", "block")
    if k <= FOLDERS:
        rows.repartition("block").write.partitionBy("block").parquet(path)
    else:
        rows.repartitionByRange("block").sortWithinPartitions("block").write.parquet(path)


def runs(rows: DataFrame, path: str) -> None:
    """Appends result rows."""
    rows.write.mode("append").parquet(path)


def noop(df: DataFrame) -> None:
    """Runs the plan and keeps nothing, for timing."""
    df.write.format("noop").mode("overwrite").save()
