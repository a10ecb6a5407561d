"""The methods in SQL: scalar functions that Catalyst inlines, table functions, and views over a partition."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from ..operators import metrics
from ..operators.buffered import Partition

SCALARS = [
    "edge_batch(u BIGINT, v BIGINT, delta BIGINT) RETURNS BIGINT RETURN greatest(u div delta, v div delta)",
    "fennel_gain(w_in DOUBLE, weight DOUBLE, block_load DOUBLE, alpha DOUBLE, gamma DOUBLE) RETURNS DOUBLE RETURN w_in - weight * alpha * gamma * power(block_load, gamma - 1)",
    "block_cap(m BIGINT, k BIGINT, eps_permille BIGINT) RETURNS BIGINT RETURN greatest(1, ((1000 + eps_permille) * m + 1000 * k - 1) div (1000 * k))",
    "hash_block(u BIGINT, v BIGINT, k BIGINT) RETURNS INT RETURN cast(pmod(u * 31 + v * 17, k) AS INT)",
]


def register(spark: SparkSession) -> None:
    """Temporary functions of this session."""
    for f in SCALARS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {f}")
    spark.udtf.register("metis_rows", MetisRows)
    spark.udtf.register("path_links", PathLinks)


@udtf(returnType="u: bigint, v: bigint")
class MetisRows:
    """metis_rows(vertex, line): the edges of one METIS line to larger ids, from 0."""

    def eval(self, vertex: int, line: str) -> Iterator[tuple[int, int]]:
        for x in (line or "").split():
            if int(x) - 1 > vertex:
                yield vertex, int(x) - 1


@udtf(returnType="batch: bigint, v: bigint, e1: bigint, e2: bigint")
class PathLinks:
    """path_links(TABLE(arcs) PARTITION BY batch, v ORDER BY eid): a link from each of a vertex's edges to the next."""

    def __init__(self):
        self.last = None

    def eval(self, row) -> Iterator[tuple[int, int, int, int]]:
        if self.last is not None:
            yield row["batch"], row["v"], min(self.last, row["eid"]), max(self.last, row["eid"])
        self.last = row["eid"]


def views(p: Partition, prefix: str = "") -> None:
    """edge_blocks, block_loads and vertex_mirrors as temporary views."""
    from ..operators.analytics import mirrors

    p.assign.select("eid", "u", "v", "block").createOrReplaceTempView(f"{prefix}edge_blocks")
    metrics.loads(p.assign, p.k).createOrReplaceTempView(f"{prefix}block_loads")
    mirrors(p.assign).createOrReplaceTempView(f"{prefix}vertex_mirrors")


def sql(spark: SparkSession, text: str) -> DataFrame:
    register(spark)
    return spark.sql(text)
