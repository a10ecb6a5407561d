"""Steps of the multilevel cut as DataFrame plans, for batches that outgrow a task: links (e1, e2, w), labels and blocks as tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def both_ways(links: DataFrame) -> DataFrame:
    """(item, other, w) from either end."""
    ends = F.array(F.struct(F.col("e1").alias("item"), F.col("e2").alias("other")), F.struct(F.col("e2").alias("item"), F.col("e1").alias("other")))
    return links.select(F.explode(ends).alias("x"), "w").select("x.item", "x.other", "w")


def cluster_round(links: DataFrame, labels: DataFrame, cap: int, parity: int = 0) -> DataFrame:
    """labels (item, label) after a round: items of one parity move to the label of strongest connection, while it stays within cap items.

    Moves into a label are admitted by strength; the running count is per label, so a window's partition has at most the moves
    into one cluster.
    """
    near = both_ways(links).join(labels.select(F.col("item").alias("other"), "label"), "other")
    pull = near.groupBy("item", "label").agg(F.sum("w").alias("w"))
    own = labels.select("item", F.col("label").alias("own"))
    pull = pull.join(own, "item")
    held = pull.groupBy("item").agg(F.coalesce(F.max(F.when(F.col("label") == F.col("own"), F.col("w"))), F.lit(0)).alias("held"), F.max_by(F.struct("label", "w"), F.when(F.col("label") != F.col("own"), F.struct("w", -F.col("label")))).alias("to"))
    moves = held.where((F.col("to.w") > F.col("held")) & (F.pmod("item", F.lit(2)) == parity)).select("item", F.col("to.label").alias("to"), F.col("to.w").alias("w"))
    sizes = labels.groupBy("label").agg(F.count(F.lit(1)).alias("size"))
    rank = F.row_number().over(Window.partitionBy("to").orderBy(F.desc("w"), "item"))
    admitted = moves.withColumn("r", rank).join(sizes, moves["to"] == sizes["label"]).where(F.col("size") + F.col("r") <= cap).select("item", "to")
    return labels.join(admitted, "item", "left").select("item", F.coalesce("to", "label").alias("label"))


def contract(links: DataFrame, labels: DataFrame) -> DataFrame:
    """Links between labels: parallel ones merge with their sum, loops go."""
    a, b = labels.select(F.col("item").alias("e1"), F.col("label").alias("a")), labels.select(F.col("item").alias("e2"), F.col("label").alias("b"))
    merged = links.join(a, "e1").join(b, "e2").where("a <> b")
    return merged.groupBy(F.least("a", "b").alias("e1"), F.greatest("a", "b").alias("e2")).agg(F.sum("w").alias("w"))


def project(blocks: DataFrame, labels: DataFrame) -> DataFrame:
    """(item, block) from (label, block)."""
    return labels.join(blocks, "label").select("item", "block")


def refine_round(links: DataFrame, assign: DataFrame, alpha: float, cap: int, parity: int = 0) -> DataFrame:
    """assign (item, block) after a round of moves to adjacent blocks of larger gain, with blocks of at most cap unit items.

    Gains take few values for a pair of blocks, so moves are admitted by whole groups of (from, to, gain): groups in falling order of
    gain, as long as the target's room lasts. Only groups are sorted, a few for each pair of blocks.
    """
    loads = assign.groupBy("block").agg(F.count(F.lit(1)).alias("load"))
    cost = lambda c: F.lit(alpha * 1.5) * F.sqrt(c.cast("double"))
    near = both_ways(links).join(assign.select(F.col("item").alias("other"), F.col("block").alias("to")), "other").groupBy("item", "to").agg(F.sum("w").alias("w"))
    full = near.join(assign, "item").join(F.broadcast(loads.select(F.col("block").alias("to"), F.col("load").alias("to_load"))), "to").join(F.broadcast(loads), "block")  # a row per block
    value = F.when(F.col("to") == F.col("block"), F.col("w") - cost(F.col("load") - 1)).otherwise(F.col("w") - cost(F.col("to_load")))
    scored = full.withColumn("gain", value).withColumn("stay", -cost(F.col("load") - 1))
    best = scored.groupBy("item", "block").agg(
        F.coalesce(F.max(F.when(F.col("to") == F.col("block"), F.col("gain"))), F.max("stay")).alias("now"),
        F.max_by(F.struct("to", "gain"), F.when(F.col("to") != F.col("block"), F.struct("gain", -F.col("to_load"), -F.col("to")))).alias("x"),
    )
    moves = best.where((F.col("x.gain") > F.col("now")) & (F.pmod("item", F.lit(2)) == parity)).select("item", "block", F.col("x.to").alias("to"), (F.col("x.gain") - F.col("now")).alias("better"))
    groups = moves.groupBy("to", "block", "better").agg(F.count(F.lit(1)).alias("n")).join(F.broadcast(loads.select(F.col("block").alias("to"), "load")), "to")
    upto = F.sum("n").over(Window.partitionBy("to").orderBy(F.desc("better"), "block"))
    admitted = groups.withColumn("upto", upto).where(F.col("load") + F.col("upto") <= cap).select("to", "block", "better")
    moved = moves.join(admitted, ["to", "block", "better"]).select("item", "to")
    return assign.join(moved, "item", "left").select("item", F.coalesce("to", "block").cast("int").alias("block"))
