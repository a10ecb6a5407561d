"""Edges as vertices: the split-and-connect graph and its contracted form.

Every table may carry a batch column; without one, all edges are one batch (batch 0).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .batching import arcs_with


def _batched(edges: DataFrame) -> DataFrame:
    return edges if "batch" in edges.columns else edges.withColumn("batch", F.lit(0).cast("long"))


def _order(kind: str, seed: int = 0) -> list:
    """Where a copy stands on its vertex's path."""
    return {"eid": ["eid"], "nbr": ["nbr", "eid"], "random": [F.xxhash64("eid", "v", F.lit(seed)), "eid"]}[kind]


def split_vertices(edges: DataFrame, order: str = "eid") -> DataFrame:
    """(batch, v, pos, eid): as many copies of a vertex as it has edges."""
    pos = F.row_number().over(Window.partitionBy("batch", "v").orderBy(*_order(order))) - 1
    return arcs_with(_batched(edges), "batch").select("batch", "v", pos.alias("pos"), "eid")


def dominant_edges(split: DataFrame, heavy: float = 1e9) -> DataFrame:
    """One heavy link (batch, eid, v1, pos1, v2, pos2, w) between the two copies of each edge."""
    ends = split.groupBy("batch", "eid").agg(F.min(F.struct("v", "pos")).alias("a"), F.max(F.struct("v", "pos")).alias("b"))
    return ends.select("batch", "eid", F.col("a.v").alias("v1"), F.col("a.pos").alias("pos1"), F.col("b.v").alias("v2"), F.col("b.pos").alias("pos2"), F.lit(heavy).alias("w"))


def auxiliary_edges(split: DataFrame) -> DataFrame:
    """Unit links (batch, v, pos, next_pos, e1, e2) along each vertex's path of copies."""
    w = Window.partitionBy("batch", "v").orderBy("pos")
    steps = split.select("batch", "v", "pos", F.lead("pos").over(w).alias("next_pos"), F.col("eid").alias("e1"), F.lead("eid").over(w).alias("e2"))
    return steps.where("next_pos IS NOT NULL")


def contract_dominant(auxiliary: DataFrame) -> DataFrame:
    """Links between edges (batch, e1 < e2, w): the copies of an edge become one vertex, parallel links merge, loops go."""
    return auxiliary.where("e1 <> e2").groupBy("batch", F.least("e1", "e2").alias("e1"), F.greatest("e1", "e2").alias("e2")).agg(F.count(F.lit(1)).alias("w"))


def contracted(edges: DataFrame, order: str = "eid") -> DataFrame:
    """Links (batch, v, e1 < e2, w = 1) straight from the edges: one shuffle by (batch, v) and a sort, no copies, no joins."""
    w = Window.partitionBy("batch", "v").orderBy(*_order(order))
    steps = arcs_with(_batched(edges), "batch").select("batch", "v", F.col("eid").alias("a"), F.lead("eid").over(w).alias("b")).where("b IS NOT NULL")
    return steps.select("batch", "v", F.least("a", "b").alias("e1"), F.greatest("a", "b").alias("e2"), F.lit(1).alias("w"))


def tight_order(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """Links with paths ordered by block, for which the cut is exactly the number of extra copies."""
    placed = arcs_with(_batched(edges), "batch").join(assign.select("eid", "block"), "eid")
    w = Window.partitionBy("batch", "v").orderBy("block", "eid")
    steps = placed.select("batch", "v", F.col("eid").alias("a"), F.lead("eid").over(w).alias("b")).where("b IS NOT NULL")
    return steps.select("batch", "v", F.least("a", "b").alias("e1"), F.greatest("a", "b").alias("e2"), F.lit(1).alias("w"))


def spac_to_edges(split_blocks: DataFrame, policy: str = "first", loads: DataFrame | None = None) -> DataFrame:
    """(eid, block) from blocks of the copies (batch, v, pos, eid, block); where the two copies of an edge were cut apart,
    both go to the block of the first copy, to the lighter of the two blocks, or to that of the copy with more links in its block."""
    if policy == "first":
        return split_blocks.groupBy("eid").agg(F.min_by("block", F.struct("v", "pos")).alias("block"))
    if policy == "lighter":
        sizes = loads if loads is not None else split_blocks.groupBy("block").agg(F.count(F.lit(1)).alias("load"))
        return split_blocks.join(F.broadcast(sizes), "block").groupBy("eid").agg(F.min_by("block", F.struct("load", "block")).alias("block"))
    if policy == "heavier_aux":
        w = Window.partitionBy("batch", "v").orderBy("pos")
        same = lambda c: F.coalesce((c == F.col("block")).cast("int"), F.lit(0))
        scored = split_blocks.withColumn("links", same(F.lag("block").over(w)) + same(F.lead("block").over(w)))
        return scored.groupBy("eid").agg(F.max_by("block", F.struct("links", -F.col("block"))).alias("block"))
    raise ValueError(policy)


def size_law(edges: DataFrame) -> DataFrame:
    """(batch, items, vertices, links, expected): links = 2 x edges - vertices that have one."""
    arcs = arcs_with(_batched(edges), "batch")
    sizes = arcs.groupBy("batch", "v").agg(F.count(F.lit(1)).alias("d")).groupBy("batch").agg(F.count(F.lit(1)).alias("vertices"), (F.sum("d") / 2).cast("long").alias("items"))
    links = contracted(edges).groupBy("batch").agg(F.count(F.lit(1)).alias("links"))
    out = sizes.join(links, "batch", "left").select("batch", "items", "vertices", F.coalesce("links", F.lit(0)).alias("links"))
    return out.withColumn("expected", 2 * F.col("items") - F.col("vertices"))
