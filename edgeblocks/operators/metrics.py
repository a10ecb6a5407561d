"""Cost and accuracy of an edge partition: assign (eid, u, v, block)."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .canonical import Graph


def block_cap(m: int, k: int, eps: float | str = "0.03") -> int:
    """Largest block size: (1 + eps) m / k rounded up, in whole numbers; at least 1."""
    return max(1, -(-((1 + Fraction(str(eps))) * m) // k))


def replicas(assign: DataFrame) -> DataFrame:
    """(v, block) without repeats. Repeats combine before the shuffle, which is by vertex and block, so hubs spread."""
    return assign.select(F.explode(F.array("u", "v")).alias("v"), "block").distinct()


def covered(assign: DataFrame) -> DataFrame:
    """(block, vertices) per block that has an edge."""
    return replicas(assign).groupBy("block").agg(F.count(F.lit(1)).alias("vertices"))


def loads(assign: DataFrame, k: int | None = None) -> DataFrame:
    """(block, load), with empty blocks if k is given."""
    out = assign.groupBy("block").agg(F.count(F.lit(1)).alias("load"))
    if k is None:
        return out
    every = assign.sparkSession.range(k).select(F.col("id").cast("int").alias("block"))
    return every.join(out, "block", "left").na.fill(0, ["load"])


def lambdas(assign: DataFrame) -> DataFrame:
    """(v, lam): blocks of each vertex that has an edge."""
    return replicas(assign).groupBy("v").agg(F.count(F.lit(1)).alias("lam"))


def lambda_histogram(assign: DataFrame) -> DataFrame:
    return lambdas(assign).groupBy("lam").agg(F.count(F.lit(1)).alias("vertices"))


def replication(assign: DataFrame, g: Graph) -> DataFrame:
    """One row: replicas, extra_copies, rf (over all vertices), rf_nonisolated."""
    total = lambdas(assign).agg(F.coalesce(F.sum("lam"), F.lit(0)).alias("replicas"), F.count(F.lit(1)).alias("_seen"))
    return total.select(
        "replicas", (F.col("replicas") - F.col("_seen")).alias("extra_copies"),
        F.round(F.col("replicas") / F.lit(g.n), 6).alias("rf"), F.round(F.col("replicas") / F.col("_seen"), 6).alias("rf_nonisolated"),
    )


def replication_preview(assign: DataFrame, g: Graph, rsd: float = 0.02) -> DataFrame:
    """Approximate rf from one sketch per block, which merge across batches."""
    per = assign.select(F.explode(F.array("u", "v")).alias("v"), "block").groupBy("block").agg(F.approx_count_distinct("v", rsd).alias("c"))
    return per.agg((F.sum("c") / F.lit(g.n)).alias("rf_approx"))


def balance(assign: DataFrame, k: int, eps: float | str = "0.03") -> DataFrame:
    """One row: blocks, max_load, min_load, l_max, imbalance, feasible."""
    per = loads(assign, k)
    sums = per.agg(F.sum("load").alias("m"), F.max("load").alias("max_load"), F.min("load").alias("min_load"))
    e = Fraction(str(eps))
    num, den = (1 + e).numerator, (1 + e).denominator
    cap = F.greatest(F.lit(1), F.expr(f"(m * {num} + {den * k - 1}) div {den * k}"))
    return sums.select(F.lit(k).alias("blocks"), "max_load", "min_load", cap.alias("l_max"), F.round(F.col("max_load") * k / F.col("m") - 1, 6).alias("imbalance"), (F.col("max_load") <= cap).alias("feasible"))


def load_quantiles(assign: DataFrame, k: int) -> DataFrame:
    return loads(assign, k).agg(F.percentile_approx("load", F.array(F.lit(0.5), F.lit(0.9), F.lit(1.0)), 10000).alias("quantiles"))


def new_replicas(assign: DataFrame, seq: Column | None = None) -> DataFrame:
    """(batch, gamma): (vertex, block) pairs first met in a batch, less one for each vertex first met in it. assign has batch.

    seq: what orders the batches (their number, if not given). Batches of equal seq do not see each other: each counts against what came before.
    """
    ends = assign.select(F.explode(F.array("u", "v")).alias("v"), "block", "batch", (F.col("batch") if seq is None else seq).alias("seq"))
    if seq is None:
        pairs = ends.groupBy("v", "block").agg(F.min("batch").alias("batch"))
        starts = ends.groupBy("v").agg(F.min("batch").alias("batch"))
    else:  # a pair is new to every batch of the first seq that has it
        seen = ends.distinct()
        pairs = seen.join(seen.groupBy("v", "block").agg(F.min("seq").alias("seq")), ["v", "block", "seq"]).select("v", "block", "batch")
        visits = seen.select("v", "batch", "seq").distinct()
        starts = visits.join(visits.groupBy("v").agg(F.min("seq").alias("seq")), ["v", "seq"]).select("v", "batch")
    gained = pairs.groupBy("batch").agg(F.count(F.lit(1)).alias("p"))
    fresh = starts.groupBy("batch").agg(F.count(F.lit(1)).alias("s"))
    every = assign.select("batch").distinct().join(gained, "batch", "left").join(fresh, "batch", "left").na.fill(0, ["p", "s"])
    return every.select("batch", (F.col("p") - F.col("s")).alias("gamma"))


def cut_links(links: DataFrame, blocks: DataFrame) -> DataFrame:
    """links (e1, e2, w, …) whose ends are in different blocks (eid, block)."""
    a = blocks.select(F.col("eid").alias("e1"), F.col("block").alias("b1"))
    b = blocks.select(F.col("eid").alias("e2"), F.col("block").alias("b2"))
    return links.join(a, "e1").join(b, "e2").where("b1 <> b2")


def edge_cut(links: DataFrame, blocks: DataFrame) -> DataFrame:
    """One row: weight of the cut links."""
    return cut_links(links, blocks).agg(F.coalesce(F.sum("w"), F.lit(0)).alias("cut"))


def model_cut(links: DataFrame, block_links: DataFrame, blocks: DataFrame) -> DataFrame:
    """(batch, cut): cut links between edges and cut links to blocks of each batch."""
    one = cut_links(links, blocks).select("batch", "w")
    two = block_links.join(blocks.select("eid", F.col("block").alias("own")), "eid").where("block <> own").select("batch", "w")
    return one.unionByName(two).groupBy("batch").agg(F.sum("w").alias("cut"))


def sync_messages(assign: DataFrame) -> DataFrame:
    """One row: messages in a superstep, one each way for every copy beyond a vertex's first."""
    return lambdas(assign).agg((2 * F.sum(F.col("lam") - 1)).alias("messages"))


def certificate(assign: DataFrame, g: Graph, k: int, eps: float | str = "0.03", stats: DataFrame | None = None) -> DataFrame:
    """One row that a right partition shares with the base tables: placed, distinct_edges, bad_blocks, over_cap, bound_violations.

    bound_violations counts the batches of stats in which new replicas (gamma) exceed the cut of the batch's model, or are not known;
    without stats the whole graph is one batch.
    """
    from . import linegraph

    cap = block_cap(g.m, k, eps)
    base = assign.agg(F.count(F.lit(1)).alias("placed"), F.countDistinct("eid").alias("distinct_edges"), F.count_if((F.col("block") < 0) | (F.col("block") >= k) | F.col("block").isNull()).alias("bad_blocks"))
    over = loads(assign).agg(F.count_if(F.col("load") > cap).alias("over_cap"))
    if stats is None:
        extra = lambdas(assign).agg(F.coalesce(F.sum(F.col("lam") - 1), F.lit(0)).alias("extra"))
        bound = extra.crossJoin(edge_cut(linegraph.contracted(g.edges), assign)).select((F.col("extra") > F.col("cut")).cast("long").alias("bound_violations"))
    else:
        bound = stats.agg(F.count_if(F.col("gamma").isNull() | (F.col("gamma") > F.col("cut"))).alias("bound_violations"))
    return base.crossJoin(over).crossJoin(bound)


def against_hashing(assign: DataFrame, g: Graph, k: int) -> DataFrame:
    """One row: replicas that plain hashing makes (hash_copies), and whether assign makes fewer (below_hash)."""
    from . import baselines

    ours, plain = (replicas(a).agg(F.count(F.lit(1)).alias(n)) for a, n in ((assign, "copies"), (baselines.hash_edges(g, k), "hash_copies")))
    return plain.crossJoin(ours).select("hash_copies", (F.col("copies") < F.col("hash_copies")).alias("below_hash"))
