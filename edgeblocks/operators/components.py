"""Connected components by alternating large-star and small-star steps, in a logarithmic number of rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import materialise


def _large_star(pairs: DataFrame) -> DataFrame:
    """Every larger neighbour of a node is hung below the least of the node and its neighbours."""
    both = pairs.union(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(pairs: DataFrame) -> DataFrame:
    """The smaller neighbours of a node, and the node, are hung below the least of them."""
    least = pairs.groupBy("u").agg(F.min("v").alias("m"))
    moved = pairs.join(least, "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of an edge between two nodes; component is its least node.

    Minima combine before the shuffle, so a hub costs one row per task; the joins on a hub are split by AQE. Each round is
    written to the shared folder, which cuts lineage; the driver sees a count and a checksum. Null ends are dropped.
    """
    x, y = F.col(a), F.col(b)
    now = materialise(edges.where(x != y).select(F.greatest(x, y).alias("u"), F.least(x, y).alias("v")).distinct(), "pairs")
    mark = None
    for _ in range(max_rounds):
        seen = now.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v")), F.sum(F.hash("u", "v"))).first()
        if seen == mark or seen[0] == 0:
            return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select("v", "v").distinct())
        mark, now = seen, materialise(_small_star(_large_star(now)), "stars")
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
