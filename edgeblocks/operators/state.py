"""What is remembered of earlier batches: the blocks of each vertex, or the latest one."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def seen(assign: DataFrame, seq: str = "batch") -> DataFrame:
    """(v, block, seq): blocks that a vertex met in assign (eid, u, v, block, batch), with the last time."""
    ends = assign.select(F.explode(F.array("u", "v")).alias("v"), "block", F.col(seq).alias("seq"), "eid")
    return ends.groupBy("v", "block").agg(F.max(F.struct("seq", "eid")).alias("at")).select("v", "block", F.col("at.seq").alias("seq"), F.col("at.eid").alias("eid"))


def merge(memory: DataFrame, mode: str) -> DataFrame:
    """One row per vertex (minimal: that of its last edge) or per vertex and block."""
    if mode == "minimal":
        return memory.groupBy("v").agg(F.max_by(F.struct("block", "seq", "eid"), F.struct("seq", "eid")).alias("x")).select("v", "x.block", "x.seq", "x.eid")
    return memory.groupBy("v", "block").agg(F.max(F.struct("seq", "eid")).alias("at")).select("v", "block", F.col("at.seq").alias("seq"), F.col("at.eid").alias("eid"))


def update(memory: DataFrame | None, assign: DataFrame, mode: str) -> DataFrame:
    """Memory after a batch. Minimal keeps the block of the vertex's last edge, the others every block; rows: (v, block, seq, eid)."""
    new = seen(assign)
    return merge(new if memory is None else memory.unionByName(new), mode)


def cells(memory: DataFrame) -> DataFrame:
    """One row: entries kept."""
    return memory.agg(F.count(F.lit(1)).alias("cells"))


def block_bitmap(assign: DataFrame) -> DataFrame:
    """(v, bucket, bits): blocks of a vertex as bitmaps, for many blocks; they merge with bitmap_or_agg."""
    ends = assign.select(F.explode(F.array("u", "v")).alias("v"), (F.col("block").cast("long") + 1).alias("block"))  # bit positions count from 1
    return ends.groupBy("v", F.bitmap_bucket_number("block").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("block")).alias("bits"))
