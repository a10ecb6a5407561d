"""Formats by round trip, streams by replay, the SQL surface."""

from datetime import datetime

import pytest
from pyspark.sql import functions as F

from edgeblocks.functions import sqlapi
from edgeblocks.operators import buffered, metrics
from edgeblocks.operators.canonical import from_pairs
from edgeblocks.plans.graphs import graph
from edgeblocks.sources import formats, sinks
from edgeblocks.streaming import stream

TAIL = [(0, 1), (0, 2), (1, 2), (2, 3), (3, 4)]


@pytest.fixture(scope="module")
def g(spark):
    return from_pairs(spark.createDataFrame(TAIL, "a long, b long"))


def pairs(df):
    return sorted(map(tuple, df.select("u", "v").collect()))


def test_metis_text(spark, g, tmp_path):
    lines = [r.value for r in formats.metis_lines(g.edges, g.n).orderBy("line").collect()]
    assert lines == ["5 5", "2 3", "1 3", "1 2 4", "3 5", "4"]
    formats.write_metis(g.edges, g.n, f"{tmp_path}/m")
    assert pairs(formats.metis(spark, f"{tmp_path}/m")) == TAIL
    (tmp_path / "one.metis").write_text("% note\n4 2\n2\n1 3\n2\n\n")
    assert pairs(formats.metis(spark, str(tmp_path / "one.metis"))) == [(0, 1), (1, 2)]
    (tmp_path / "weights.metis").write_text("2 1 1\n2 5\n1 5\n")
    with pytest.raises(ValueError):
        formats.metis(spark, str(tmp_path / "weights.metis"))


@pytest.mark.parametrize("kind", ["edge_list", "binary", "metis", "adjacency"])
def test_round_trips(spark, small, tmp_path, kind):
    part = graph(spark, small, "part_order")
    path = f"file://{tmp_path}/{kind}"
    formats.WRITERS[kind](part.edges, part.n, path)
    assert pairs(formats.READERS[kind](spark, path)) == pairs(part.edges)


def test_binary_widths(spark, g, tmp_path):
    formats.write_binary_edges(g.edges, f"file://{tmp_path}/wide", 64)
    assert pairs(formats.binary_edges(spark, f"file://{tmp_path}/wide", 64)) == TAIL
    with pytest.raises(Exception, match="needs more than 32 bits"):
        formats.write_binary_edges(spark.createDataFrame([(0, 1 << 40)], "u long, v long"), f"file://{tmp_path}/bad")


def test_convert(spark, g, tmp_path):
    formats.write_edge_list(g.edges, f"{tmp_path}/a")
    formats.convert(spark, f"{tmp_path}/a", "edge_list", f"{tmp_path}/b", "metis", g.n)
    assert pairs(formats.metis(spark, f"{tmp_path}/b")) == TAIL


def test_sinks(spark, g, tmp_path):
    p = buffered.partition(g, 2, delta=3)
    sinks.blocks(p.assign, f"{tmp_path}/few", 2)
    sinks.blocks(p.assign, f"{tmp_path}/many", 5000)
    assert pairs(spark.read.parquet(f"{tmp_path}/few")) == pairs(spark.read.parquet(f"{tmp_path}/many")) == TAIL
    for _ in range(2):
        sinks.runs(p.stats, f"{tmp_path}/runs")
    assert spark.read.parquet(f"{tmp_path}/runs").count() == 2 * p.stats.count()


def test_views_and_functions(spark, g):
    p = buffered.partition(g, 2, delta=3)
    sqlapi.views(p)
    assert spark.sql("SELECT sum(load) FROM block_loads").first()[0] == 5
    assert spark.sql("SELECT count_if(is_master) FROM vertex_mirrors").first()[0] == 5
    assert sqlapi.sql(spark, "SELECT edge_batch(1, 9, 4), block_cap(5, 2, 30), hash_block(1, 2, 8)").first() == (2, 3, 1)
    assert sorted(map(tuple, sqlapi.sql(spark, "SELECT * FROM metis_rows(0, '2 3')").collect())) == [(0, 1), (0, 2)]


def test_buffered_stream_replays(spark, small, tmp_path):
    part = graph(spark, small, "user_prop")
    b = stream.BufferedStream(f"file://{tmp_path}/s", 4, m_hint=part.m)
    halves = [part.edges.where(f"eid % 2 = {i}") for i in (0, 1)]
    b.step(halves[0], 0)
    b.step(halves[1], 1)
    first = sorted(map(tuple, b.assign(spark).collect()))
    b.step(halves[1], 1)  # the same micro-batch again
    assert sorted(map(tuple, b.assign(spark).collect())) == first
    assert tuple(metrics.certificate(b.assign(spark), part, 4).first())[:4] == (part.m, part.m, 0, 0)
    with_bound = stream.BufferedStream(f"file://{tmp_path}/t", 4)  # without a known number of edges
    with_bound.step(halves[0], 0)
    with_bound.step(halves[1], 5)
    assert with_bound.assign(spark).count() == part.m


def test_coactivity_and_sessions(spark):
    rows = [("2024-01-01 00:00:00", 1, 7), ("2024-01-01 00:05:00", 2, 7), ("2024-01-01 02:00:00", 3, 7), ("2024-01-01 00:01:00", 9, 8)]
    e = spark.createDataFrame(rows, "ts string, user long, key long").withColumn("ts", F.to_timestamp("ts"))
    assert [tuple(r)[:2] for r in stream.coactivity(e, e, "10 MINUTES").collect()] == [(1, 2)]
    s = stream.sessions(e.select(F.col("key").alias("v"), "ts"), "30 minutes").orderBy("v", "start").collect()
    assert [(r.v, r.events) for r in s] == [(7, 2), (7, 1), (8, 1)]


def star_and_pairs(spark):
    """A hub whose edges all fall in one lane of the later end, and some more."""
    rows = [(i, 0, 1000) if i == 0 else (i, i, 1000) for i in range(60)] + [(60 + i, 2000 + i, 3000 + i) for i in range(20)]
    return spark.createDataFrame([(datetime(2024, 1, 1), *r) for r in rows], "ts timestamp, eid long, u long, v long")


@pytest.mark.parametrize("way", ["one_pass", "one_pass_stateful"])
def test_lane_with_a_hub(spark, tmp_path, way):
    """A lane that gets far more than its share of the edges places them all, evenly."""
    star_and_pairs(spark).coalesce(1).write.parquet(f"{tmp_path}/in")
    edges = stream.source(spark, f"{tmp_path}/in", "ts timestamp, eid long, u long, v long")
    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name)
    spark.conf.set(name, stream.ROCKS)
    try:
        getattr(stream, way)(edges, 4, 80, 101, lanes=4).writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/c").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    finally:
        spark.conf.set(name, before)
    got = spark.read.parquet(f"{tmp_path}/out").toPandas()
    assert sorted(got["eid"]) == list(range(80)) and got["block"].between(0, 3).all()
    assert got["block"].value_counts().max() <= 21 + 4  # the cap, and an edge more for each lane


def test_buffered_stream_modes(spark, tmp_path):
    """Without a memory a buffer is cut alone; with it, earlier blocks count; subset links some of what maximal links."""
    import numpy as np

    rng = np.random.default_rng(2)
    pairs = sorted({(int(a), int(b)) for a, b in rng.integers(0, 40, (300, 2)) if a < b}, key=lambda e: (e[1], e[0]))
    rows = [(i, a, b) for i, (a, b) in enumerate(pairs)]
    cut = len(rows) // 2
    got = {}
    for mode in buffered.MODES:
        b = stream.BufferedStream(f"file://{tmp_path}/{mode}", 4, m_hint=len(rows), mode=mode, r=1)
        for at, part in enumerate((rows[:cut], rows[cut:])):
            b.step(spark.createDataFrame(part, "eid long, u long, v long"), at)
        got[mode] = [r.block for r in b.assign(spark).orderBy("eid").collect()]
        assert len(got[mode]) == len(rows)
        loads = np.bincount(got[mode][:cut], minlength=4)
        part = np.array(rows[cut:])
        met = {}
        for (_, u, v), block in zip(rows[:cut], got[mode][:cut]):
            met.setdefault(u, {})[block] = met.setdefault(v, {})[block] = 1
        last = {}
        for (_, u, v), block in zip(rows[:cut], got[mode][:cut]):
            last[u] = last[v] = block
        items, ids = [], []
        for i, (e, u, v) in enumerate(rows[cut:]):
            blocks = {"none": [], "minimal": sorted({last[x] for x in (u, v) if x in last}), "maximal": sorted({y for x in (u, v) for y in met.get(x, {})})}.get(mode)
            if blocks is None:
                blocks = sorted({y for x in (u, v) for y in met.get(x, {})}, key=lambda y, e=e: ((e * 7919 + y * 104729) % 1_000_003, y))[:1]
            items += [i] * len(blocks)
            ids += blocks
        cap = buffered.block_cap(len(rows), 4)
        o = buffered.Options(4, 1, cap, len(rows), mode)
        want, _ = buffered.cut_batch(part[:, 1], part[:, 2], part[:, 0], None, items, ids, loads, np.full(4, cap), o, [0, 0, 0])
        assert got[mode][cut:] == want.tolist()
    assert got["none"] != got["maximal"]
    with pytest.raises(ValueError):
        stream.BufferedStream("x", 2, mode="other")


def test_components_inside_blocks(spark):
    """Only copied vertices meet across blocks, and the result is that of the whole graph."""
    import numpy as np

    from edgeblocks.operators import analytics, baselines
    from edgeblocks.operators.canonical import from_pairs

    rng = np.random.default_rng(1)
    g = from_pairs(spark.createDataFrame([(int(a), int(b)) for a, b in rng.integers(0, 300, (220, 2))], "a long, b long"))
    parent = list(range(g.n))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for r in g.edges.collect():
        a, b = find(r.u), find(r.v)
        parent[max(a, b)] = min(a, b)
    got = {r.v: r.component for r in analytics.components(baselines.hash_edges(g, 5)).collect()}
    assert got == {x: find(x) for x in range(g.n)}


def test_placer_reads_and_writes_pages():
    """Blocks as with all of the state in one dictionary, and no more accesses to the state than pages."""
    import numpy as np
    import pandas as pd

    class State:
        def __init__(self):
            self.held, self.calls = {}, 0

        def __getattr__(self, name):
            def call(*args):
                self.calls += 1
                key = args[0] if name in ("getValue", "containsKey", "updateValue") else ()
                if name in ("updateValue", "update"):
                    self.held[key] = args[-1]
                return key in self.held if name in ("containsKey", "exists") else self.held.get(key)

            return call

    class Handle:
        def __init__(self):
            self.map, self.value = State(), State()

        def getMapState(self, *_):  # noqa: N802
            return self.map

        def getValueState(self, *_):  # noqa: N802
            return self.value

    rng = np.random.default_rng(4)
    n, handle, load, last, calls = 3 * stream.PAGE + 7, Handle(), np.zeros(4, np.int64), {}, []
    for _ in range(3):  # micro-batches
        frames = [pd.DataFrame({"eid": range(500), "u": rng.integers(0, n - 1, 500), "v": n - 1}) for _ in range(2)]
        placer = stream.OnePassPlacer(4, 3000, n, 1, "0.03")
        placer.init(handle)
        before = handle.map.calls
        got = pd.concat(placer.handleInputRows(("lane",), iter(frames), None))
        calls.append(handle.map.calls - before)
        assert got["block"].tolist() == pd.concat([stream._placed(f, load, last, 4, 3000, n, 1, "0.03") for f in frames])["block"].tolist()
    assert max(calls) <= 3 * 4
