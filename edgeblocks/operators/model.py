"""The model of a batch: links between its edges, plus links to fixed items that stand for the blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import linegraph

MODES = ("none", "minimal", "subset", "maximal")


def block_links(owned: DataFrame, memory: DataFrame, mode: str, r: int = 5, seed: int = 0) -> DataFrame:
    """(batch, eid, block, w = 1). memory: (v, block, seq) with seq the batch of the entry; only earlier batches count.

    minimal links the block met last, maximal every block, subset r of them drawn by hash, so a retried task draws the same.
    """
    if mode not in MODES:
        raise ValueError(mode)
    past = owned.where("past IS NOT NULL").select("batch", "eid", "past")
    if mode == "none":
        return past.where("false").select("batch", "eid", F.lit(0).alias("block"), F.lit(1).alias("w"))
    known = past.join(memory.select(F.col("v").alias("past"), "block", "seq", *[c for c in ("eid",) if c in memory.columns and mode == "minimal"]).withColumnsRenamed({"eid": "last_eid"}), "past").where("seq < batch")
    if mode == "minimal":
        last = F.struct("seq", "last_eid") if "last_eid" in known.columns else F.struct("seq", "block")
        return known.groupBy("batch", "eid").agg(F.max_by("block", last).alias("block")).withColumn("w", F.lit(1))
    known = known.select("batch", "eid", "block").distinct()
    if mode == "subset":
        draw = Window.partitionBy("batch", "eid").orderBy(F.pmod(F.col("eid") * 7919 + F.col("block") * 104729 + F.lit(seed), F.lit(1_000_003)), "block")
        known = known.withColumn("_r", F.row_number().over(draw)).where(F.col("_r") <= r).drop("_r")
    return known.withColumn("w", F.lit(1))


def build(owned: DataFrame, memory: DataFrame | None, mode: str, order: str = "eid", r: int = 5) -> tuple[DataFrame, DataFrame]:
    """(links between edges, links to blocks) of all batches in owned."""
    links = linegraph.contracted(owned, order)
    none = memory is None or mode == "none"
    blocks = block_links(owned, memory if not none else owned.select("v", F.lit(0).alias("block"), F.lit(0).alias("seq")), "none" if none else mode, r)
    return links, blocks


def model_size(owned: DataFrame, memory: DataFrame | None, mode: str, r: int = 5) -> DataFrame:
    """(batch, items, links, block_links)."""
    links, blocks = build(owned, memory, mode, r=r)
    out = owned.groupBy("batch").agg(F.count(F.lit(1)).alias("items"))
    out = out.join(links.groupBy("batch").agg(F.count(F.lit(1)).alias("links")), "batch", "left").join(blocks.groupBy("batch").agg(F.count(F.lit(1)).alias("block_links")), "batch", "left")
    return out.na.fill(0, ["links", "block_links"])
