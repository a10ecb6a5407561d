"""Computing on a partition: each block works on its own edges in a task, copies of a vertex are brought together once a step.

A block is as large as the partition made it, L_max edges at most, which is what bounds a task here: choose k so that a block fits. Results
equal those on the unpartitioned graph; what a step sends is a row for each copy (see metrics.sync_messages).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import materialise
from .canonical import Graph, arcs, degrees
from .components import connected_components
from .metrics import replicas


def mirrors(assign: DataFrame) -> DataFrame:
    """(v, block, is_master): the copy in the smallest block leads."""
    first = replicas(assign).groupBy("v").agg(F.min("block").alias("master"))
    return replicas(assign).join(first, "v").select("v", "block", (F.col("block") == F.col("master")).alias("is_master"))


def _local_roots(table: pa.Table) -> pa.Table:
    """(block, v, root): the least vertex that each vertex of a block reaches inside it, by hooking and jumping on arrays."""
    block, u, v = (table.column(c).to_numpy() for c in ("block", "u", "v"))
    ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(ids))
    while True:
        low = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, root[a], low)
        np.minimum.at(new, root[b], low)
        while (new[new] != new).any():
            new = new[new]
        if (new == root).all():
            break
        root = new
    return pa.table({"block": np.full(len(ids), block[0] if len(block) else 0, np.int32), "v": ids, "root": ids[root]})


def components(assign: DataFrame) -> DataFrame:
    """(v, component). Each block finds its own components; only copied vertices and the roots they have in their blocks meet across blocks."""
    local = materialise(assign.select("block", "u", "v").groupBy("block").applyInArrow(_local_roots, "block int, v bigint, root bigint"), "local-roots")
    copied = local.groupBy("v").agg(F.count(F.lit(1)).alias("lam")).where("lam > 1").select("v")
    meets = local.join(copied, "v").select(F.col("v").alias("a"), F.col("root").alias("b"))
    found = connected_components(meets).select(F.col("node").alias("root"), "component")
    whole = local.join(found, "root", "left").select("v", F.coalesce("component", "root").alias("component"))
    return whole.groupBy("v").agg(F.min("component").alias("component"))


def _local_sums(arcs_: pa.Table, ranks: pa.Table) -> pa.Table:
    """(v, part): what the edges of a block send to each of its vertices; ranks are those of the block's copies, already over degree."""
    if not arcs_.num_rows:
        return pa.table({"v": pa.array([], pa.int64()), "part": pa.array([], pa.float64())})
    u, v = (arcs_.column(c).to_numpy() for c in ("u", "v"))
    ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    share = np.zeros(len(ids))
    share[np.searchsorted(ids, ranks.column("v").to_numpy())] = ranks.column("share").to_numpy()
    a, b = at[: len(u)], at[len(u) :]
    return pa.table({"v": ids, "part": np.bincount(np.concatenate([b, a]), weights=share[np.concatenate([a, b])], minlength=len(ids))})


def pagerank(g: Graph, assign: DataFrame | None = None, rounds: int = 10, damping: float = 0.85) -> DataFrame:
    """(v, rank) after some rounds on the undirected graph.

    With assign, a round adds up inside each block and sends a row per copy each way; the blocks' edges stay where they are. Without, the
    sums are a join over all arcs.
    """
    rank = g.vertices.select(F.col("id").alias("v"), F.lit(1.0 / g.n).alias("rank"))
    if assign is None:
        arcs_ = arcs(g.edges)
        ends = materialise(arcs_.select(F.col("v").alias("s"), F.col("nbr").alias("t")).join(arcs_.groupBy("v").agg(F.count(F.lit(1)).alias("d")).withColumnRenamed("v", "s"), "s"), "pagerank-arcs")
    else:
        held = materialise(assign.select("block", "u", "v"), "pagerank-blocks").repartition("block").persist()
        copies = materialise(replicas(assign).join(degrees(g.edges), "v"), "pagerank-copies")
    for i in range(rounds):
        if assign is None:
            total = ends.join(rank, ends["s"] == rank["v"]).groupBy("t").agg(F.sum(F.col("rank") / F.col("d")).alias("total"))
        else:
            shares = copies.join(rank, "v").select("block", "v", (F.col("rank") / F.col("deg")).alias("share"))
            parts = held.groupBy("block").cogroup(shares.groupBy("block")).applyInArrow(_local_sums, "v bigint, part double")
            total = parts.groupBy(F.col("v").alias("t")).agg(F.sum("part").alias("total"))
        rank = g.vertices.select(F.col("id").alias("v")).join(total, F.col("v") == total["t"], "left").select("v", ((1 - damping) / g.n + damping * F.coalesce("total", F.lit(0.0))).alias("rank"))
        if i % 5 == 4 or i == rounds - 1:
            rank = materialise(rank, "pagerank")
    if assign is not None:
        held.unpersist()
    return rank


def triangles(edges: DataFrame) -> DataFrame:
    """One row: triangles. Edges point from the smaller degree to the larger (ties: the smaller id), so that a hub has few edges out; the
    wedges of a vertex's edges out are closed by an edge."""
    d = degrees(edges)
    with_d = edges.join(d.select(F.col("v").alias("u"), F.col("deg").alias("du")), "u").join(d.select("v", F.col("deg").alias("dv")), "v")
    turned = (F.col("dv") < F.col("du"))
    out = with_d.select(F.when(turned, F.col("v")).otherwise(F.col("u")).alias("s"), F.when(turned, F.col("u")).otherwise(F.col("v")).alias("t"))
    wedges = out.join(out.withColumnRenamed("t", "y"), "s").where("t < y").select(F.col("t").alias("u"), F.col("y").alias("v"))
    return wedges.join(edges.select("u", "v"), ["u", "v"], "left_semi").agg(F.count(F.lit(1)).alias("triangles"))
