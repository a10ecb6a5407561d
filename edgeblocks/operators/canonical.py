"""Canonical graphs: undirected, simple, dense ids from 0, and what follows from them."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..storage import materialise


@dataclass
class Graph:
    """edges (eid, u, v) with u < v and eid the rank of (u, v); vertices (id, kind, num, str); n counts the vertices."""

    edges: DataFrame
    vertices: DataFrame
    n: int
    m: int
    name: str = ""
    extra: dict = field(default_factory=dict)


def dense_ids(df: DataFrame, order: list, name: str) -> DataFrame:
    """df with a column name: 0, 1, … in the given order.

    Rows are dealt out by range and sorted within their partition; the partitions' sizes give the offsets. No task sees all rows.
    """
    ranged = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id())
    ranged = materialise(ranged, "ranged")
    part = F.shiftright("_at", 33)
    sizes = ranged.groupBy(part.alias("_part")).agg(F.count(F.lit(1)).alias("_rows"))
    before = F.sum("_rows").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))
    offsets = sizes.select("_part", F.coalesce(before, F.lit(0)).alias("_before"))
    joined = ranged.join(F.broadcast(offsets), part == F.col("_part"))  # a row per partition
    return joined.withColumn(name, F.col("_before") + F.col("_at").bitwiseAND((1 << 33) - 1)).drop("_at", "_part", "_before")


def simple_pairs(pairs: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Loops dropped, ends ordered, repeats merged with their count as weight (mult)."""
    x, y = F.col(a), F.col(b)
    kept = pairs.where(x.isNotNull() & y.isNotNull() & (x != y)).select(F.least(x, y).alias("u"), F.greatest(x, y).alias("v"))
    return kept.groupBy("u", "v").agg(F.count(F.lit(1)).alias("mult"))


def build(pairs: DataFrame, name: str = "", id_order: str = "small_side_first", isolated: DataFrame | None = None, first: DataFrame | None = None) -> Graph:
    """Graph from pairs (a_kind, a_num, a_str, b_kind, b_num, b_str); isolated adds vertices (kind, num, str) without edges.

    id_order: small_side_first ranks kinds by how many vertices they have; natural keeps the kinds' own order; large_side_first
    is the opposite; random orders by hash; event_time by the time (kind, num, str, at) of first, unseen vertices last.
    """
    ends = lambda s: [F.col(f"{s}_kind").cast("int").alias("kind"), F.col(f"{s}_num").cast("long").alias("num"), F.col(f"{s}_str").cast("string").alias("str")]
    known = F.coalesce("a_num", F.when(F.col("a_str").isNotNull(), 0)).isNotNull() & F.coalesce("b_num", F.when(F.col("b_str").isNotNull(), 0)).isNotNull()
    pairs = materialise(pairs.where(known).distinct(), "pairs")
    different = (F.col("a_kind") != F.col("b_kind")) | ~F.col("a_num").eqNullSafe(F.col("b_num")) | ~F.col("a_str").eqNullSafe(F.col("b_str"))
    both = pairs.where(different).select(*ends("a")).union(pairs.where(different).select(*ends("b")))
    if isolated is not None:
        both = both.union(isolated.select(F.col("kind").cast("int"), F.col("num").cast("long"), F.col("str").cast("string")))
    vertices = both.distinct()
    sizes = {r.kind: r["count"] for r in vertices.groupBy("kind").count().collect()}
    by_size = {"small_side_first": lambda k: (sizes[k], k), "large_side_first": lambda k: (-sizes[k], k), "natural": lambda k: k, "random": lambda k: k, "event_time": lambda k: k}[id_order]
    rank = {k: i for i, k in enumerate(sorted(sizes, key=by_size))}
    if rank:
        vertices = vertices.withColumn("kind_rank", F.element_at(F.create_map(*(F.lit(x) for kv in rank.items() for x in kv)), F.col("kind")))
    else:
        vertices = vertices.withColumn("kind_rank", F.lit(0))
    if id_order == "random":
        vertices = vertices.withColumn("_h", F.xxhash64("kind", "num", "str"))
    if id_order == "event_time":
        seen = first.select(F.col("kind").cast("int").alias("f_kind"), F.col("num").cast("long").alias("f_num"), F.col("str").cast("string").alias("f_str"), F.col("at").alias("_at_first"))
        vertices = vertices.join(seen, (F.col("kind") == F.col("f_kind")) & F.col("num").eqNullSafe(F.col("f_num")) & F.col("str").eqNullSafe(F.col("f_str")), "left").drop("f_kind", "f_num", "f_str")
    order = {"random": ["_h", "kind", "num", "str"], "event_time": [F.col("_at_first").asc_nulls_last(), "kind", "num", "str"]}.get(id_order, ["kind_rank", "num", "str"])
    vertices = materialise(dense_ids(vertices, order, "id").select("id", F.col("kind_rank").alias("kind"), F.col("kind").alias("_own"), "num", "str"), f"vertices-{name}")

    def key(s: str, out: str) -> tuple[DataFrame, Column]:
        v = vertices.select(F.col("_own").alias(f"{s}_k"), F.col("num").alias(f"{s}_n"), F.col("str").alias(f"{s}_s"), F.col("id").alias(out))
        same = (F.col(f"{s}_kind") == F.col(f"{s}_k")) & F.col(f"{s}_num").eqNullSafe(F.col(f"{s}_n")) & F.col(f"{s}_str").eqNullSafe(F.col(f"{s}_s"))
        return v, same

    va, on_a = key("a", "ia")
    vb, on_b = key("b", "ib")
    linked = simple_pairs(pairs.join(va, on_a).join(vb, on_b), "ia", "ib")
    edges = materialise(dense_ids(linked.select("u", "v"), ["u", "v"], "eid").select("eid", "u", "v"), f"edges-{name}")
    return Graph(edges, vertices.select("id", "kind", "num", "str"), vertices.count(), edges.count(), name)


def from_pairs(pairs: DataFrame, a: str = "a", b: str = "b", name: str = "") -> Graph:
    """Graph over one kind of whole-number keys."""
    wide = pairs.select(F.lit(0).alias("a_kind"), F.col(a).alias("a_num"), F.lit(None).cast("string").alias("a_str"), F.lit(0).alias("b_kind"), F.col(b).alias("b_num"), F.lit(None).cast("string").alias("b_str"))
    return build(wide, name)


def arcs(edges: DataFrame) -> DataFrame:
    """(v, nbr, eid): every edge from both ends."""
    return edges.select(F.explode(F.array(F.struct(F.col("u").alias("v"), F.col("v").alias("nbr"), "eid"), F.struct(F.col("v").alias("v"), F.col("u").alias("nbr"), "eid"))).alias("x")).select("x.*")


def degrees(edges: DataFrame) -> DataFrame:
    return arcs(edges).groupBy("v").agg(F.count(F.lit(1)).alias("deg"))


def degree_histogram(edges: DataFrame) -> DataFrame:
    return degrees(edges).groupBy("deg").agg(F.count(F.lit(1)).alias("vertices"))


def adjacency(edges: DataFrame) -> DataFrame:
    """(v, nbrs sorted): the vertex-centric form, for interfaces only."""
    ends = F.array(F.struct(F.col("u").alias("v"), F.col("v").alias("nbr")), F.struct(F.col("v").alias("v"), F.col("u").alias("nbr")))
    return edges.select(F.explode(ends).alias("x")).groupBy("x.v").agg(F.array_sort(F.collect_list("x.nbr")).alias("nbrs"))


def induced(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """Edges with both ends among ids (id)."""
    return edges.join(ids.select(F.col("id").alias("u")), "u", "left_semi").join(ids.select(F.col("id").alias("v")), "v", "left_semi").select("eid", "u", "v")


def isolated_vertices(g: Graph) -> DataFrame:
    touched = arcs(g.edges).select(F.col("v").alias("id"))
    return g.vertices.join(touched, "id", "left_anti")


def weight_sum(items: DataFrame, weight: str, by: str) -> DataFrame:
    """Weights are additive over sets; null counts 1."""
    return items.groupBy(by).agg(F.sum(F.coalesce(F.col(weight), F.lit(1))).alias("weight"))


def summary(g: Graph) -> DataFrame:
    """One row: n, m, largest degree, vertices of degree at most two."""
    d = degrees(g.edges)
    return d.agg(F.coalesce(F.max("deg"), F.lit(0)).alias("max_degree"), F.count_if(F.col("deg") <= 2).alias("low_degree")).select(F.lit(g.n).cast("long").alias("n"), F.lit(g.m).cast("long").alias("m"), "max_degree", "low_degree")
