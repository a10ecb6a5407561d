"""Graph formats: text edge list, binary edge list, METIS text, binary adjacency. Schemas are fixed, never inferred."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.canonical import adjacency, arcs, dense_ids
from ..storage import materialise


# ---- text edge list

def edge_list(spark: SparkSession, path: str, sep: str = " ", comment: str = "#") -> DataFrame:
    """(u, v) from lines "u<sep>v"."""
    return spark.read.schema("u long, v long").csv(path, sep=sep, comment=comment, mode="FAILFAST")


def write_edge_list(edges: DataFrame, path: str, sep: str = " ") -> None:
    edges.select("u", "v").write.csv(path, sep=sep)


# ---- binary edge list

def binary_edges(spark: SparkSession, path: str, bits: int = 32) -> DataFrame:
    """(u, v) from little-endian unsigned pairs; fixed-length records, so files split anywhere."""
    width = bits // 4
    records = spark.sparkContext.binaryRecords(path, width).map(lambda r: (bytearray(r),))
    kind = f"<u{bits // 8}"

    def unpack(it):
        for b in it:
            x = np.frombuffer(b"".join(b.column(0).to_pylist()), kind).astype(np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([pa.array(x[:, 0].copy()), pa.array(x[:, 1].copy())], names=["u", "v"])

    return spark.createDataFrame(records, "r binary").mapInArrow(unpack, "u bigint, v bigint")


def write_binary_edges(edges: DataFrame, folder: str, bits: int = 32) -> DataFrame:
    """One file per task with pairs of little-endian unsigned numbers; returns (path, edges). folder: a pyarrow file system URI."""
    kind = f"<u{bits // 8}"

    def write(it):
        import uuid

        from pyarrow import fs

        system, root = fs.FileSystem.from_uri(folder)
        system.create_dir(root, recursive=True)
        name, n = f"{root}/edges-{uuid.uuid4().hex}.bin", 0
        with system.open_output_stream(name) as out:
            for b in it:
                x = np.stack([b.column("u").to_numpy(), b.column("v").to_numpy()], axis=1)
                if x.size and (x.min() < 0 or x.max() >= 1 << bits):
                    raise ValueError(f"an id needs more than {bits} bits")
                out.write(x.astype(kind).tobytes())
                n += len(x)
        yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([n], pa.int64())], names=["path", "edges"])

    return materialise(edges.select("u", "v").mapInArrow(write, "path string, edges bigint"), "binary-edges")


# ---- METIS text

def _numbered_lines(spark: SparkSession, path: str) -> DataFrame:
    """(line, value): lines of one text in file order; parts are ordered by file name, block start and position in the block."""
    lines = spark.read.text(path).select("value", F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("start"), F.monotonically_increasing_id().alias("at"))
    lines = materialise(lines, "metis-lines").where("NOT value LIKE '\\%%' ESCAPE '\\\\'")
    return dense_ids(lines, ["file", "start", "at"], "line").select("line", "value")


def metis(spark: SparkSession, path: str) -> DataFrame:
    """(u, v) with u < v, ids from 0: a header "n m [fmt]", then line i with the neighbours of vertex i, from 1."""
    lines = _numbered_lines(spark, path)
    head = lines.where("line = 0").first()["value"].split()
    if len(head) > 2 and int(head[2]):
        raise ValueError("weights in METIS files are not read")
    rows = lines.where("line > 0").select((F.col("line") - 1).alias("u"), F.explode(F.split(F.trim("value"), r"\s+")).alias("x")).where("x <> ''")
    return rows.select("u", (F.col("x").cast("long") - 1).alias("v")).where("u < v")


def metis_lines(edges: DataFrame, n: int) -> DataFrame:
    """(line, value): header and a line per vertex, isolated ones empty."""
    spark = edges.sparkSession
    m = edges.count()
    rows = spark.range(n).select(F.col("id").alias("v")).join(adjacency(edges), "v", "left")
    body = rows.select((F.col("v") + 1).alias("line"), F.coalesce(F.array_join(F.transform("nbrs", lambda x: (x + 1).cast("string")), " "), F.lit("")).alias("value"))
    return spark.createDataFrame([(0, f"{n} {m}")], "line long, value string").unionByName(body)


def write_metis(edges: DataFrame, n: int, path: str) -> None:
    metis_lines(edges, n).repartitionByRange("line").sortWithinPartitions("line").select("value").write.text(path)


# ---- binary adjacency

def write_adjacency(edges: DataFrame, path: str) -> None:
    """Rows (v, nbrs): the neighbours as packed little-endian 64-bit numbers, ordered by v."""

    def pack(it):
        for b in it:
            yield pa.RecordBatch.from_arrays([b.column("v"), pa.array([np.array(x, "<i8").tobytes() for x in b.column("nbrs").to_pylist()], pa.binary())], names=["v", "nbrs"])

    adjacency(edges).repartitionByRange("v").sortWithinPartitions("v").mapInArrow(pack, "v bigint, nbrs binary").write.parquet(path)


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """(v, nbrs array<bigint>)."""

    def unpack(it):
        for b in it:
            yield pa.RecordBatch.from_arrays([b.column("v"), pa.array([np.frombuffer(x, "<i8") for x in b.column("nbrs").to_pylist()], pa.list_(pa.int64()))], names=["v", "nbrs"])

    return spark.read.schema("v bigint, nbrs binary").parquet(path).mapInArrow(unpack, "v bigint, nbrs array<bigint>")


READERS = {"edge_list": edge_list, "binary": binary_edges, "metis": metis, "adjacency": lambda s, p: read_adjacency(s, p).select(F.col("v").alias("a"), F.explode("nbrs").alias("b")).where("a < b").select(F.col("a").alias("u"), F.col("b").alias("v"))}
WRITERS = {"edge_list": lambda e, n, p: write_edge_list(e, p), "binary": lambda e, n, p: write_binary_edges(e, p), "metis": write_metis, "adjacency": lambda e, n, p: write_adjacency(e, p)}


def convert(spark: SparkSession, src: str, src_format: str, dst: str, dst_format: str, n: int) -> None:
    """Reads one format and writes another."""
    WRITERS[dst_format](READERS[src_format](spark, src), n, dst)


__all__ = ["READERS", "WRITERS", "arcs", "binary_edges", "convert", "edge_list", "metis", "metis_lines", "read_adjacency", "write_adjacency", "write_binary_edges", "write_edge_list", "write_metis"]
