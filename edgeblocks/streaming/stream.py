"""Edges and vertices as streams.

A buffered stream cuts each micro-batch as one buffer against state kept in versioned tables, so a replayed micro-batch overwrites what it
wrote. A one-pass stream keeps its state per lane in the state store. Windows, late edges and joins of streams make timed graphs.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import buffered, onthefly, state
from ..operators.metrics import block_cap


def source(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    """Files of a folder as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def rate_edges(spark: SparkSession, rows_per_second: int, n: int) -> DataFrame:
    """Test edges at a steady rate: (ts, u, v)."""
    s = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    pair = [F.pmod(F.xxhash64("value", F.lit(i)), F.lit(n)) for i in (1, 2)]
    return s.select(F.col("timestamp").alias("ts"), F.least(*pair).alias("u"), F.greatest(*pair).alias("v")).where("u < v")


class BufferedStream:
    """foreachBatch target: rows (eid, u, v) are one buffer; vertices placed in earlier buffers are its past.

    folder/assign, folder/memory and folder/loads hold a subfolder per micro-batch, written whole or not at all: version b is made
    from version b - 1 alone, so a replay gives the same rows again. m_hint bounds the largest block from the start; without it
    the bound grows with the edges seen. mode: none looks nothing up, subset links r of the blocks that an edge's ends met, drawn by hash.
    """

    def __init__(self, folder: str, k: int, eps: float | str = "0.03", m_hint: int | None = None, mode: str = "minimal", r: int = 5):
        if mode not in buffered.MODES:
            raise ValueError(mode)
        self.folder, self.k, self.eps, self.m_hint, self.mode, self.r = folder.rstrip("/"), k, eps, m_hint, mode, r

    def _last(self, batch_id: int, spark: SparkSession) -> int | None:
        """The version before batch_id."""
        hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs
        top = hadoop.Path(f"{self.folder}/loads")
        fs = top.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        if not fs.exists(top):
            return None
        done = [int(s.getPath().getName()[2:]) for s in fs.listStatus(top) if fs.exists(hadoop.Path(s.getPath(), "_SUCCESS"))]
        return max((b for b in done if b < batch_id), default=None)

    def step(self, rows: DataFrame, batch_id: int) -> None:
        spark = rows.sparkSession
        before = self._last(batch_id, spark)
        loads = np.zeros(self.k, np.int64)
        memory = None
        if before is not None:
            for r in spark.read.parquet(f"{self.folder}/loads/b={before}").collect():
                loads[r["block"]] = r["load"]
            memory = spark.read.parquet(f"{self.folder}/memory/b={before}")
        new = rows.select("eid", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).where("u < v").dropDuplicates(["u", "v"])
        if memory is None or self.mode == "none":
            known = new.select("eid", "u", "v", F.array().cast("array<bigint>").alias("blocks"))
        else:
            ends = new.select("eid", F.explode(F.array("u", "v")).alias("x")).join(memory.select(F.col("v").alias("x"), F.col("block").cast("long").alias("block")), "x")
            draw = F.pmod(F.col("eid") * 7919 + F.col("block") * 104729, F.lit(1_000_003))
            met = ends.select("eid", F.struct((draw if self.mode == "subset" else F.lit(0)).alias("h"), "block").alias("x")).groupBy("eid").agg(F.array_sort(F.collect_set("x")).alias("x"))
            first = F.slice("x", 1, self.r) if self.mode == "subset" else F.col("x")
            known = new.join(met.select("eid", F.transform(first, lambda x: x["block"]).alias("blocks")), "eid", "left").select("eid", "u", "v", "blocks")
        size = known.count()
        cap = block_cap(self.m_hint or int(loads.sum()) + size, self.k, self.eps)
        o = buffered.Options(self.k, 1, cap, self.m_hint or int(loads.sum()) + size, self.mode)
        limits = np.maximum(np.full(self.k, cap), loads)

        def cut(table: pa.Table) -> pa.Table:
            table = table.sort_by("eid")
            eid, u, v = (table.column(c).to_numpy() for c in ("eid", "u", "v"))
            col = table.column("blocks").combine_chunks()
            counts = np.array(col.value_lengths().fill_null(0))
            items = np.repeat(np.arange(len(eid)), counts)
            block, _ = buffered.cut_batch(u, v, eid, None, items.tolist(), np.array(col.flatten()).tolist(), loads.copy(), limits, o, [0, 0, 0])
            return pa.table({"eid": eid, "u": u, "v": v, "block": block.astype(np.int32)})

        placed = known.withColumn("lane", F.lit(0)).groupBy("lane").applyInArrow(lambda t: cut(t.drop(["lane"])), "eid bigint, u bigint, v bigint, block int")
        placed.write.mode("overwrite").parquet(f"{self.folder}/assign/b={batch_id}")
        placed = spark.read.parquet(f"{self.folder}/assign/b={batch_id}").withColumn("batch", F.lit(batch_id).cast("long"))
        state.update(memory, placed, "minimal" if self.mode == "minimal" else "maximal").write.mode("overwrite").parquet(f"{self.folder}/memory/b={batch_id}")
        for r in placed.groupBy("block").count().collect():
            loads[r["block"]] += r["count"]
        spark.createDataFrame([(i, int(x)) for i, x in enumerate(loads)], "block int, load long").write.mode("overwrite").parquet(f"{self.folder}/loads/b={batch_id}")

    def start(self, edges: DataFrame, checkpoint: str):
        return edges.writeStream.foreachBatch(self.step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()

    def assign(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.folder}/assign").select("eid", "u", "v", "block", F.col("b").cast("long").alias("batch"))


def lane_limits(load: np.ndarray, more: int, k: int, m: int, lanes: int, eps: float | str) -> np.ndarray:
    """Limits of a lane's blocks for the next more edges: its share of the cap, or what the edges it has seen need where that is more. There is
    always room; a lane that gets more than its share of the edges raises its blocks in step, evenly."""
    share = block_cap(m, k, eps) if lanes == 1 else max(1, block_cap(m, k, eps) // lanes)
    return np.full(k, max(share, block_cap(int(load.sum()) + more, k, eps)))


def _placed(f: pd.DataFrame, load: np.ndarray, last: dict[int, int], k: int, m: int, n: int, lanes: int, eps: float | str) -> pd.DataFrame:
    """The rows of f with their blocks; load and last are carried on."""
    f = f.sort_values(["v", "u"])
    held = defaultdict(lambda: -1, last)
    blocks = onthefly.place_stream(f["u"].to_numpy(), f["v"].to_numpy(), 0, k, lane_limits(load, len(f), k, m, lanes, eps), m, n, loads=load, last=held)
    last.update(held)
    return f[["eid", "u", "v"]].assign(block=blocks.astype(np.int32))


def one_pass(edges: DataFrame, k: int, m: int, n: int, lanes: int = 1, eps: float | str = "0.03") -> DataFrame:
    """Blocks for a stream of (eid, u, v): state per lane is the last block of each vertex and the loads."""

    def place(key, frames: Iterator[pd.DataFrame], st: GroupState) -> Iterator[pd.DataFrame]:
        ids, blocks, loads = (list(x) for x in st.get) if st.exists else ([], [], [0] * k)
        last, load = dict(zip(ids, blocks)), np.array(loads, np.int64)
        for f in frames:
            yield _placed(f, load, last, k, m, n, lanes, eps)
        st.update((list(last), list(last.values()), load.tolist()))

    laned = edges.withColumn("lane", F.pmod(F.xxhash64("v"), F.lit(lanes)).cast("int"))
    return laned.groupBy("lane").applyInPandasWithState(place, "eid long, u long, v long, block int", "ids array<long>, blocks array<long>, loads array<long>", "append", GroupStateTimeout.NoTimeout)


#: Vertices whose blocks one entry of the placer's map state holds.
PAGE = 1024


class OnePassPlacer(StatefulProcessor):
    """The same with a map state, pages of PAGE vertices to their last blocks (32-bit numbers, -1: none), and the loads as one value. Only the pages of a
    micro-batch's vertices are read and written, each once, since every access is a message to the JVM."""

    def __init__(self, k: int, m: int, n: int, lanes: int, eps: float | str):
        self.k, self.m, self.n, self.lanes, self.eps = k, m, n, lanes, eps

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getMapState("pages", "page long", "blocks binary")
        self.loads = handle.getValueState("loads", "loads array<long>")

    def _page(self, page: int) -> np.ndarray:
        found = self.last.getValue((page,)) if self.last.containsKey((page,)) else None
        return np.full(PAGE, -1, np.int32) if found is None else np.frombuffer(bytes(found[0]), np.int32).copy()

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        load = np.array(self.loads.get()[0] if self.loads.exists() else [0] * self.k, np.int64)
        pages: dict[int, np.ndarray] = {}
        for f in rows:
            ends = np.unique(np.concatenate([f["u"].to_numpy(), f["v"].to_numpy()]))
            at, place = ends // PAGE, ends % PAGE
            for page in np.unique(at).tolist():
                if page not in pages:
                    pages[page] = self._page(page)
            met = np.concatenate([pages[p][place[at == p]] for p in np.unique(at).tolist()]) if len(ends) else np.zeros(0, np.int32)
            known = met >= 0
            last = dict(zip(ends[known].tolist(), met[known].tolist()))
            placed = _placed(f, load, last, self.k, self.m, self.n, self.lanes, self.eps)
            blocks = np.fromiter((last.get(x, -1) for x in ends.tolist()), np.int32, len(ends))
            for p in np.unique(at).tolist():
                mine = at == p
                pages[p][place[mine]] = blocks[mine]
            yield placed
        for page, held in pages.items():
            self.last.updateValue((page,), (held.tobytes(),))
        self.loads.update((load.tolist(),))

    def close(self) -> None:
        pass


ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def one_pass_stateful(edges: DataFrame, k: int, m: int, n: int, lanes: int = 1, eps: float | str = "0.03") -> DataFrame:
    """one_pass on a state store with column families. The session's spark.sql.streaming.stateStore.providerClass must be ROCKS when it starts."""
    laned = edges.withColumn("lane", F.pmod(F.xxhash64("v"), F.lit(lanes)).cast("int"))
    return laned.groupBy("lane").transformWithStateInPandas(OnePassPlacer(k, m, n, lanes, eps), "eid long, u long, v long, block int", "Append", "None")


# ---- timed graphs

def unique_edges(edges: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Each edge once within the watermark of ts."""
    ends = edges.withColumns({"u": F.least("u", "v"), "v": F.greatest("u", "v")})
    return ends.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["u", "v"])


def windowed(edges: DataFrame, length: str = "1 day", slide: str | None = None, delay: str | None = None) -> DataFrame:
    """(start, u, v, mult) per tumbling or sliding window."""
    timed = edges.withWatermark("ts", delay) if delay else edges
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return timed.groupBy(w.alias("w"), F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).agg(F.count(F.lit(1)).alias("mult")).select(F.col("w.start").alias("start"), "u", "v", "mult")


def sessions(edges: DataFrame, gap: str = "30 minutes", delay: str | None = None) -> DataFrame:
    """(v, start, end, events): sessions of a vertex."""
    timed = edges.withWatermark("ts", delay) if delay else edges
    return timed.groupBy("v", F.session_window("ts", gap).alias("s")).agg(F.count(F.lit(1)).alias("events")).select("v", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "events")


def late_rows(query) -> int:
    """Rows that a finished streaming query dropped for coming after the watermark."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def coactivity(left: DataFrame, right: DataFrame, within: str = "10 minutes", delay: str | None = None) -> DataFrame:
    """(p, q, ts): two users on the same key within a time of each other. Both sides (ts, user, key); watermarks bound the state.

    Rows meet by key and stretch of time, the left ones in their own stretch and the next, so a key that occurs all the time is
    many small groups.
    """
    stretch = lambda c: F.floor(F.unix_micros(c.cast("timestamp")) / F.expr(f"unix_micros(timestamp_micros(0) + INTERVAL {within})"))
    a = left.select(F.col("ts").alias("ts_a"), F.col("user").alias("p"), F.col("key").alias("k_a"))
    b = right.select(F.col("ts").alias("ts_b"), F.col("user").alias("q"), F.col("key").alias("k_b"))
    if delay:
        a, b = a.withWatermark("ts_a", delay), b.withWatermark("ts_b", delay)
    a = a.withColumn("s_a", F.explode(F.array(stretch(F.col("ts_a")), stretch(F.col("ts_a")) + 1)))
    b = b.withColumn("s_b", stretch(F.col("ts_b")))
    near = F.expr(f"k_a = k_b AND s_a = s_b AND ts_b >= ts_a AND ts_b <= ts_a + INTERVAL {within} AND p < q")
    return a.join(b, near).select("p", "q", F.col("ts_b").alias("ts"))
