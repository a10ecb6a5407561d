"""Batches of vertices and the edges they own: an edge belongs to the batch of its later end."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .canonical import arcs


def batch_count(n: int, delta: int) -> int:
    return -(-n // delta)


def batch_of(vertex: Column, delta: int) -> Column:
    return F.floor(vertex / F.lit(delta)).cast("long")


def own_edges(edges: DataFrame, delta: int) -> DataFrame:
    """edges with batch, and past: the end of an earlier batch, null if both are in this one. No shuffle: u < v."""
    owned = edges.withColumn("batch", batch_of(F.col("v"), delta))
    return owned.withColumn("past", F.when(batch_of(F.col("u"), delta) < F.col("batch"), F.col("u")))


def own_from_adjacency(adj: DataFrame, delta: int) -> DataFrame:
    """The same from rows (v, nbrs): each vertex keeps neighbours of smaller id and drops the rest when it is read."""
    kept = adj.select("v", F.explode("nbrs").alias("u")).where("u < v")
    return own_edges(kept.select("u", "v"), delta)


def batch_sizes(edges: DataFrame, delta: int) -> DataFrame:
    return own_edges(edges, delta).groupBy("batch").agg(F.count(F.lit(1)).alias("edges"), F.countDistinct("past").alias("past_vertices"))


def batch_vertices(owned: DataFrame, delta: int) -> DataFrame:
    """(batch, v, is_past, label): labels below delta for the batch's own vertices, from delta on for past ones."""
    ends = owned.select("batch", F.explode(F.array("u", "v")).alias("v")).distinct()
    ends = ends.withColumn("is_past", batch_of(F.col("v"), delta) < F.col("batch"))
    rank = F.row_number().over(Window.partitionBy("batch", "is_past").orderBy("v")) - 1
    return ends.withColumn("label", F.when(F.col("is_past"), F.lit(delta) + rank).otherwise(F.col("v") - F.col("batch") * delta).cast("long"))


def _prefix_batches(owned: DataFrame, budget: int, step: int = 4096) -> DataFrame:
    """(v, batch) from (v, own): edges owned before v over the budget. Sums per range of ids first, then within each range; no task sees all vertices."""
    owned = owned.withColumn("r", F.floor(F.col("v") / step))
    before = F.sum("s").over(Window.orderBy("r").rowsBetween(Window.unboundedPreceding, -1))
    ranges = owned.groupBy("r").agg(F.sum("own").alias("s")).select("r", F.coalesce(before, F.lit(0)).alias("base"))
    inside = F.sum("own").over(Window.partitionBy("r").orderBy("v").rowsBetween(Window.unboundedPreceding, 0))
    return owned.withColumn("upto", inside).join(ranges, "r").select("v", F.floor((F.col("upto") + F.col("base") - F.col("own")) / budget).alias("batch"))


def budget_cuts(edges: DataFrame, budget: int) -> DataFrame:
    """Vertex to batch by owned edges instead of vertex count: (v, batch), for vertices that own an edge. A batch ends once it owns budget edges."""
    return _prefix_batches(edges.groupBy("v").agg(F.count(F.lit(1)).alias("own")), budget)


def budget_batches(edges: DataFrame, budget: int) -> DataFrame:
    """The same for every vertex that has an edge."""
    ends = F.array(F.struct(F.col("v").alias("v"), F.lit(1).alias("own")), F.struct(F.col("u").alias("v"), F.lit(0).alias("own")))
    return _prefix_batches(edges.select(F.explode(ends).alias("x")).groupBy("x.v").agg(F.sum("x.own").alias("own")), budget)


def hub_pieces(edges: DataFrame, budget: int) -> DataFrame:
    """Edges of a vertex that owns more than budget of them, numbered in pieces of that size: (eid, u, v, piece)."""
    rank = F.row_number().over(Window.partitionBy("v").orderBy("u")) - 1
    return edges.withColumn("piece", F.floor(rank / budget))


def batch_arcs(owned: DataFrame) -> DataFrame:
    """(batch, v, nbr, eid) from both ends of the owned edges."""
    return arcs_with(owned, "batch")


def arcs_with(edges: DataFrame, *more: str) -> DataFrame:
    ends = F.array(F.struct(F.col("u").alias("v"), F.col("v").alias("nbr")), F.struct(F.col("v").alias("v"), F.col("u").alias("nbr")))
    return edges.select(*more, "eid", F.explode(ends).alias("x")).select(*more, "x.v", "x.nbr", "eid")


__all__ = ["arcs", "arcs_with", "batch_arcs", "batch_count", "batch_of", "batch_sizes", "batch_vertices", "budget_batches", "budget_cuts", "hub_pieces", "own_edges", "own_from_adjacency"]
