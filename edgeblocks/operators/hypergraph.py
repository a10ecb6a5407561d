"""The dual hypergraph: edges are its pins' items, vertices its nets."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .canonical import Graph, arcs


def dual(g: Graph) -> DataFrame:
    """(net, pin): the arcs under other names; every pin lies in exactly two nets."""
    return arcs(g.edges).select(F.col("v").alias("net"), F.col("eid").alias("pin"))


def net_blocks(pins: DataFrame, blocks: DataFrame) -> DataFrame:
    """(net, block): the connectivity sets in long form. blocks: (item, block)."""
    return pins.join(blocks, pins["pin"] == blocks["item"]).select("net", "block").distinct()


def connectivity_sets(pins: DataFrame, blocks: DataFrame) -> DataFrame:
    """(net, blocks, lam)."""
    sets = net_blocks(pins, blocks).groupBy("net").agg(F.array_sort(F.collect_list("block")).alias("blocks"))
    return sets.withColumn("lam", F.size("blocks").cast("long"))


def connectivity(pins: DataFrame, blocks: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """One row: sum over nets of (lambda - 1) x weight."""
    lam = net_blocks(pins, blocks).groupBy("net").agg(F.count(F.lit(1)).alias("lam"))
    if weights is None:
        return lam.agg(F.sum(F.col("lam") - 1).alias("connectivity"))
    return lam.join(weights, "net").agg(F.sum((F.col("lam") - 1) * F.col("w")).alias("connectivity"))


def cut_net(pins: DataFrame, blocks: DataFrame) -> DataFrame:
    """One row: nets that touch more than one block."""
    lam = net_blocks(pins, blocks).groupBy("net").agg(F.count(F.lit(1)).alias("lam"))
    return lam.agg(F.count_if(F.col("lam") > 1).alias("cut_nets"))


def stream_partition(pins: DataFrame, k: int, eps: float | str = "0.03") -> DataFrame:
    """(item, block): hypergraph items that lie in two nets each, placed one by one in the order of their later net, then the other, by
    hits on the blocks their nets used last less the penalty of the load. One task; for many items see onthefly.partition."""
    from .metrics import block_cap
    from .onthefly import place_stream

    ends = pins.groupBy("pin").agg(F.min("net").alias("a"), F.max("net").alias("b")).withColumn("lane", F.lit(0))

    def place(t: pa.Table) -> pa.Table:
        item, a, b = (t.column(c).to_numpy() for c in ("pin", "a", "b"))
        order = np.lexsort((a, b))
        item, a, b = item[order], a[order], b[order]
        n = len(np.unique(np.concatenate([a, b])))
        top = int(b.max(initial=-1)) + 1
        block = place_stream(a, b, top, k, np.full(k, block_cap(len(item), k, eps)), len(item), n)
        return pa.table({"item": item, "block": np.asarray(block, np.int32)})

    return ends.groupBy("lane").applyInArrow(place, "item bigint, block int")


def edge_partition_via(partition: Callable[[DataFrame], DataFrame], g: Graph) -> DataFrame:
    """assign (eid, u, v, block) from any partitioner of hypergraph items: pins (net, pin) to (item, block)."""
    blocks = partition(dual(g))
    return g.edges.join(blocks.select(F.col("item").alias("eid"), F.col("block").cast("int").alias("block")), "eid").select("eid", "u", "v", "block")
