"""The experiments on the given tables: a row per run with quality, time, memory, state and balance.

Every experiment comes as two queries: its name gives what SQL can check of each run from the base tables (edges placed, blocks over the limit, whole
replica counts where the method is a formula, and failures), name_figures the measured table. Runs are made once per session and
folder; see trials for how they are timed.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, batching, buffered, linegraph, metrics, onthefly, sequential
from ..operators.buffered import Partition
from ..operators.canonical import Graph
from ..sources.tables import table
from ..storage import fresh_dir, materialise
from ..streaming import stream
from . import profiles, trials
from .graphs import HUGE, TEST, TUNING, graph, sql_prefix
from .trials import CELLS_LIMIT, Trial

Method = Callable[[Graph, int], Partition]


def deltas(n: int) -> tuple[int, int]:
    """A small and a large buffer for a graph of n vertices, in the place of 32 x 1024 and 256 x 1024 vertices."""
    return max(16, n // 16), max(64, n // 2)


METHODS: dict[str, Method] = {
    "buffered_small": lambda g, k: buffered.partition(g, k, delta=deltas(g.n)[0]),
    "buffered_large": lambda g, k: buffered.partition(g, k, delta=deltas(g.n)[1]),
    "onthefly": lambda g, k: onthefly.partition(g, k),
    "two_phase_hdrf": lambda g, k: baselines.two_phase(g, k),
    "two_phase_linear": lambda g, k: baselines.two_phase(g, k, "linear"),
    "hdrf": lambda g, k: baselines.hdrf(g, k),
    "dbh": lambda g, k: sequential.relational(g, baselines.dbh(g, k), k),
    "hash": lambda g, k: sequential.relational(g, baselines.hash_edges(g, k), k),
}
#: The methods whose table of vertices times blocks may not fit.
TABLES = ("hdrf", "two_phase_hdrf", "two_phase_linear")
POWERS = [2**i for i in range(1, 15)]
#: The values of k in the published table of large instances.
HUGE_KS = [4, 32, 128, 256, 512, 1024, 2048, 4096, 8192, 16384]


def trial(alg: str, g: Graph, k: int) -> Trial:
    """A method of METHODS, HDRF scanning all blocks as published."""
    small, large = deltas(g.n)
    kind, options = {
        "buffered_small": ("buffered", {"delta": small}), "buffered_large": ("buffered", {"delta": large}), "onthefly": ("onthefly", {}), "hdrf": ("hdrf", {}),
        "two_phase_hdrf": ("two_phase", {}), "two_phase_linear": ("two_phase", {"second": "linear"}), "dbh": ("dbh", {}), "hash": ("hash", {}),
    }[alg]
    return Trial(alg, g.name, k, kind, options)


def ks_for(g: Graph, ks: Iterable[int] = POWERS) -> list[int]:
    """Those up to a quarter of the edges, 2 at least."""
    return [k for k in ks if k <= max(2, g.m // 4)]


_done: dict[tuple, DataFrame] = {}


def _graphs(spark: SparkSession, d: str, names: Iterable[str]) -> dict[str, Graph]:
    return {n: graph(spark, d, n) for n in names}


def _runs(spark: SparkSession, d: str, name: str, graphs: dict[str, Graph], make: Callable[[], list[Trial]]) -> DataFrame:
    """The measured runs of an experiment, made once per session and folder."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _done:
        _done[key] = trials.measured(spark, graphs, trials.run_all(spark, graphs, make()))
    return _done[key]


def compare(spark: SparkSession, d: str) -> DataFrame:
    """All methods on all test graphs for k = 2, 4, 8, …, 16384 up to a quarter of the edges."""
    gs = _graphs(spark, d, TEST)
    return _runs(spark, d, "compare", gs, lambda: [trial(alg, g, k) for g in gs.values() for k in ks_for(g) for alg in METHODS])


def huge(spark: SparkSession, d: str) -> DataFrame:
    """All methods on the stand-ins of the large graphs, for the published values of k."""
    gs = _graphs(spark, d, HUGE)
    return _runs(spark, d, "huge", gs, lambda: [trial(alg, g, k) for g in gs.values() for k in ks_for(g, HUGE_KS) for alg in METHODS])


#: Studies of one parameter on the tuning graphs: label, then options of the buffered method.
STUDIES: dict[str, dict[str, dict]] = {
    "initial_partitioning": {"all_k": {"init": "all_k"}, "two_set": {}, "two_set_bucket": {"init": "two_set_bucket"}},
    "model_mode": {"none": {"mode": "none"}, "minimal": {}, "subset": {"mode": "subset"}, "maximal": {"mode": "maximal"}},
    "alpha": {"static": {"alpha": "static"}, "batch": {}, "dynamic": {"alpha": "dynamic"}, "dynamic_low": {"alpha": "dynamic_low"}},
    "line_graph": {"contracted": {}, "split": {"line": "split"}},
    "buffer_sweep": {"n_64": {"share": 64}, "n_16": {"share": 16}, "n_8": {"share": 8}, "n_2": {"share": 2}, "whole": {"share": 1}},
}
STUDY_KS = [2, 8, 32, 128, 512, 2048, 8192]


def study(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        gs = _graphs(spark, d, TUNING)

        def one(g: Graph, k: int, value: str, options: dict) -> Trial:
            own = {**options}
            return Trial(value, g.name, k, "buffered", {"delta": max(16, -(-g.n // own.pop("share", 16))), **own})

        return _runs(spark, d, name, gs, lambda: [one(g, k, v, o) for g in gs.values() for k in ks_for(g, STUDY_KS) for v, o in STUDIES[name].items()])

    return run


#: Orders of the vertex numbers: by kind and key, the other way round, by hash, as in the keys, by first time seen.
ORDERS = {"part_order": ("small_side_first", "large_side_first", "random", "natural"), "user_prop": ("small_side_first", "random", "natural", "event_time")}


def id_order(spark: SparkSession, d: str) -> DataFrame:
    """The order of ids, which decides which edges a batch owns."""
    gs = {}
    for name, orders in ORDERS.items():
        for o in orders:
            gs[f"{name}/{o}"] = graph(spark, d, name, o)
    return _runs(spark, d, "id_order", gs, lambda: [Trial("buffered", label, k, "buffered", {"delta": max(16, g.n // 16)}) for label, g in gs.items() for k in ks_for(g, [8, 32])])


SIZES = ("trade_nation", "user_prop", "trade_region", "supp_cust", "part_order", "copurchase", "doc_token")


def size(spark: SparkSession, d: str) -> DataFrame:
    """Time against edges: the same methods over graphs of two thousand to some hundred thousand edges (at scale factor 0.01), and over both smaller
    tables of part_order."""
    gs = _graphs(spark, d, SIZES)
    return _runs(spark, d, "size", gs, lambda: [trial(alg, g, 8) for g in gs.values() for alg in ("buffered_small", "onthefly")])


def growth(spark: SparkSession, d: str) -> DataFrame:
    """(alg, slope): growth of seconds with edges as a power, by least squares on logarithms."""
    return size(spark, d).where("seconds > 0").groupBy("alg").agg(F.round(F.regr_slope(F.ln("seconds"), F.ln("edges")), 4).alias("slope"), F.count(F.lit(1)).alias("graphs"))


def k_independence(spark: SparkSession, d: str) -> DataFrame:
    """Growth of time, peak memory and remembered entries with k, per method over the test graphs."""
    got = compare(spark, d).where("error IS NULL").withColumn("peak_bytes", F.col("peak_bytes") + 1)
    out = None
    for m in ("seconds", "peak_bytes", "cells"):
        one = profiles.slope(got, m).groupBy("alg").agg(F.round(F.avg("slope"), 4).alias(f"{m}_slope"))
        out = one if out is None else out.join(one, "alg", "left")
    return out


def line_graphs(spark: SparkSession, d: str) -> DataFrame:
    """Size and time of the split graph with its contraction against the direct way, as plans."""
    rows = []
    for name in ("part_order", "copurchase"):
        own = batching.own_edges(graph(spark, d, name).edges, 1024)
        for way in ("contracted", "split"):
            began = time.perf_counter()
            if way == "contracted":
                vertices, links = own.count(), linegraph.contracted(own).count()
            else:
                split = linegraph.split_vertices(own)
                vertices, links = split.count(), linegraph.dominant_edges(split).count() + linegraph.auxiliary_edges(split).count()
            rows.append((name, way, vertices, links, round(time.perf_counter() - began, 3)))
    return spark.createDataFrame(rows, "graph string, way string, vertices long, links long, seconds double")


def messages(spark: SparkSession, d: str, name: str = "trade_region", k: int = 8) -> DataFrame:
    """What a step of a computation on blocks sends, by method."""
    g = graph(spark, d, name)
    rows = [(alg, metrics.sync_messages(run(g, k).assign).first()["messages"]) for alg, run in METHODS.items()]
    return spark.createDataFrame(rows, "alg string, messages long")


def by_k(spark: SparkSession, d: str) -> DataFrame:
    """(alg, k, graphs, rf, seconds, mb): geometric means over the test graphs for each k."""
    got = compare(spark, d).where("error IS NULL")
    return got.groupBy("alg", "k").agg(F.count(F.lit(1)).alias("graphs"), F.round(profiles.geomean(F.col("rf")), 4).alias("rf"), F.round(profiles.geomean(F.col("seconds")), 4).alias("seconds"), F.round(profiles.geomean(F.col("peak_bytes") + 1) / 1e6, 3).alias("mb"))


TAUS = [1.0, 1.05, 1.1, 1.25, 1.5, 2.0, 5.0, 10.0]


def profile(measure: str, least_k: int | None = None) -> Callable[[SparkSession, str], DataFrame]:
    """Performance profile of all methods over the test graphs; runs that failed are within no factor."""
    return lambda s, d: profiles.performance_profile(compare(s, d), measure, TAUS, least_k)


def instances(spark: SparkSession, d: str) -> DataFrame:
    """A row per large instance: replication, seconds and megabytes of every method."""
    got = huge(spark, d).withColumn("mb", F.round(F.col("peak_bytes") / 1e6, 1)).withColumn("seconds", F.round("seconds", 3))
    return got.groupBy("graph", "k").pivot("alg", list(METHODS)).agg(F.first("rf").alias("rf"), F.first("seconds").alias("seconds"), F.first("mb").alias("mb"))


def improvements(spark: SparkSession, d: str) -> DataFrame:
    """(band, measure, other, instances, improvement, win_rate) of each of our methods over each other one, for all k, up to 256 and from 512 on."""
    got, out = compare(spark, d), None
    for band, keep in (("all", "true"), ("k <= 256", "k <= 256"), ("k >= 512", "k >= 512")):
        for measure in ("rf", "seconds", "peak_bytes"):
            for ours in ("buffered_small", "buffered_large", "onthefly"):
                for other in ("hdrf", "two_phase_hdrf", "two_phase_linear", "dbh", "hash"):
                    one = profiles.mean_improvement(got.where(keep), ours, other, measure).select(F.lit(band).alias("band"), F.lit(measure).alias("measure"), F.lit(ours).alias("alg"), F.lit(other).alias("other"), "instances", "improvement", "win_rate")
                    out = one if out is None else out.union(one)
    return out


def checked(runs: DataFrame) -> DataFrame:
    """(alg, graph, k, edges, placed, over_cap, bad_blocks, replicas): replicas only of the methods that are formulas, all null but edges where a
    run failed."""
    formula = F.col("alg").isin("hash", "dbh")
    return runs.select("alg", "graph", "k", "edges", "placed", "bad_blocks", "over_cap", F.when(formula, F.col("replicas")).alias("replicas"))


def _names(values: Iterable[str]) -> str:
    return "[" + ", ".join(f"'{v}'" for v in values) + "]"


def grid_sql(names: Iterable[str], algs: Iterable[str], ks: Iterable[int]) -> str:
    """What checked must show, from the base tables."""
    parts = []
    for name in names:
        parts.append(f"""SELECT * FROM (WITH {sql_prefix(name)}, z AS (SELECT (SELECT count(*) FROM v) AS n, (SELECT count(*) FROM e) AS m),
ks AS (SELECT unnest({list(ks)})::INT AS k), g AS (SELECT alg, k, n, m FROM (SELECT unnest({_names(algs)}) AS alg), ks, z WHERE k <= greatest(2, m // 4)),
dg AS (SELECT v AS x, count(*) AS c FROM arc GROUP BY v),
h AS (SELECT 'hash' AS alg, k, eid, u, v, (u * 31 + v * 17) % k AS block FROM e, ks, z WHERE k <= greatest(2, m // 4) AND 'hash' IN (SELECT alg FROM g)
  UNION ALL SELECT 'dbh', k, eid, u, v, CASE WHEN b.c < a.c THEN v ELSE u END % k FROM e JOIN dg a ON a.x = u JOIN dg b ON b.x = v, ks, z WHERE k <= greatest(2, m // 4) AND 'dbh' IN (SELECT alg FROM g)),
r AS (SELECT alg, k, count(*) AS replicas FROM (SELECT DISTINCT alg, k, x, block FROM (SELECT alg, k, u AS x, block FROM h UNION ALL SELECT alg, k, v, block FROM h)) GROUP BY alg, k),
o AS (SELECT alg, k, count(*) FILTER (load > greatest(1, (103 * m + 100 * k - 1) // (100 * k))) AS over_cap FROM (SELECT alg, k, block, count(*) AS load FROM h GROUP BY ALL), z GROUP BY alg, k),
f AS (SELECT *, alg IN {tuple(TABLES)} AND n * k > {CELLS_LIMIT} AS failed FROM g)
SELECT f.alg, '{name}' AS graph, f.k, f.m AS edges, CASE WHEN NOT failed THEN f.m END AS placed, CASE WHEN NOT failed THEN 0::BIGINT END AS bad_blocks, CASE WHEN NOT failed THEN coalesce(o.over_cap, 0) END AS over_cap, r.replicas
FROM f LEFT JOIN r USING (alg, k) LEFT JOIN o USING (alg, k))""")
    return " UNION ALL ".join(parts)


def _order_sql() -> str:
    parts = []
    for name, orders in ORDERS.items():
        for o in orders:
            parts.append(f"SELECT * FROM (WITH {sql_prefix(name)}, z AS (SELECT count(*) AS m FROM e) SELECT 'buffered' AS alg, '{name}/{o}' AS graph, k::INT AS k, m AS edges, m AS placed, 0::BIGINT AS bad_blocks, 0::BIGINT AS over_cap, NULL::BIGINT AS replicas FROM z, (SELECT unnest([8, 32]) AS k) WHERE k <= greatest(2, m // 4))")
    return " UNION ALL ".join(parts)


def claims(spark: SparkSession, d: str) -> DataFrame:
    """(claim, holds): what the runs on the test graphs show of the reported behaviour, by geometric means over the instances at hand.

    Only what does not hang on the machine is in here: replication and counted state. Times are in the figures.
    """
    got = compare(spark, d).where("error IS NULL")
    mean = {(r.alg, r.band): r.q for r in got.withColumn("band", F.when(F.col("k") >= 512, "many").otherwise("few")).groupBy("alg", "band").agg(profiles.geomean(F.col("rf")).alias("q")).collect()}
    slopes = {r.alg: r.s for r in profiles.slope(got.where("cells > 0"), "cells").groupBy("alg").agg(F.avg("slope").alias("s")).collect()}
    few = lambda a: mean[a, "few"]
    rows = [
        ("a larger buffer copies less", few("buffered_large") < few("buffered_small")),
        ("the large buffer copies less than the linear two-phase method", few("buffered_large") < few("two_phase_linear")),
        ("the one-pass method copies less than hashing", few("onthefly") < few("hash")),
        ("the state of the buffered method grows less than a quarter as fast with k as that of HDRF", slopes["buffered_small"] < slopes["hdrf"] / 4),
        ("the state of HDRF grows in proportion to k", abs(slopes["hdrf"] - 1) < 0.1),
    ]
    return spark.createDataFrame([(a, bool(b)) for a, b in rows], "claim string, holds boolean")


CLAIMS = ["a larger buffer copies less", "the large buffer copies less than the linear two-phase method", "the one-pass method copies less than hashing", "the state of the buffered method grows less than a quarter as fast with k as that of HDRF", "the state of HDRF grows in proportion to k"]

Run = Callable[[SparkSession, str], DataFrame]
#: Runs whose checkable part has SQL: (runs, SQL).
CHECKED: dict[str, tuple[Run, str]] = {
    "experiment_compare": (compare, grid_sql(TEST, METHODS, POWERS)), "experiment_huge_sweep": (huge, grid_sql(HUGE, METHODS, HUGE_KS)),
    **{f"experiment_{n}": (study(n), grid_sql(TUNING, STUDIES[n], STUDY_KS)) for n in STUDIES},
    "experiment_id_order": (id_order, _order_sql()), "experiment_size": (size, grid_sql(SIZES, ("buffered_small", "onthefly"), [8])),
}
EXPERIMENTS: dict[str, Run] = {
    **{f"{n}_figures": run for n, (run, _) in CHECKED.items()},
    "experiment_k_sweep": by_k, "experiment_k_independence": k_independence, "experiment_size_growth": growth, "experiment_line_graphs": line_graphs, "experiment_messages": messages, "experiment_instances": instances, "experiment_improvements": improvements,
    **{f"experiment_profile_{m}{'' if k is None else '_large_k'}": profile(c, k) for m, c in (("rf", "rf"), ("time", "seconds"), ("memory", "peak_bytes")) for k in (None, 512)},
}


# ---- streams

def _timed(spark: SparkSession, d: str, parts: int = 4) -> tuple[str, Graph]:
    """A folder with the user-property edges in order of first occurrence, cut in parts."""
    g = graph(spark, d, "user_prop")
    ids = g.vertices.select("id", "kind", "num")
    props = table(spark, d, "events").select("ts", F.get_json_object("props", "$.k").cast("long").alias("key"), "user_id")
    sides = [r["kind"] for r in ids.groupBy("kind").agg(F.count(F.lit(1)).alias("c")).orderBy("kind").collect()]
    keys = props.select("key").distinct().count()
    key_kind = sides[0] if ids.where(F.col("kind") == sides[0]).count() == keys and ids.where(F.col("kind") == sides[-1]).count() != keys else sides[-1]
    user_kind = next(x for x in sides if x != key_kind)
    a = ids.where(F.col("kind") == key_kind).select(F.col("id").alias("ka"), F.col("num").alias("key"))
    b = ids.where(F.col("kind") == user_kind).select(F.col("id").alias("ub"), F.col("num").alias("user_id"))
    first = props.join(a, "key").join(b, "user_id").groupBy(F.least("ka", "ub").alias("u"), F.greatest("ka", "ub").alias("v")).agg(F.min("ts").alias("ts"))
    timed = first.join(g.edges, ["u", "v"]).select("ts", "eid", "u", "v")
    return _in_parts(spark, timed, parts), g


def _in_parts(spark: SparkSession, timed: DataFrame, parts: int = 4, late: DataFrame | None = None) -> str:
    """A folder with the rows in order of ts, a file after the other as they would arrive; late rows come in a last file."""
    folder = fresh_dir(spark, "stream-source")
    timed = materialise(timed.withColumn("ts", F.col("ts").cast("timestamp")), "timed")
    lo, hi = timed.agg(F.min(F.unix_micros("ts")), F.max(F.unix_micros("ts"))).first()
    for i in range(parts):
        part = F.least(F.lit(parts - 1), F.floor((F.unix_micros("ts") - lo) * parts / max(1, hi - lo)))
        timed.where(part == i).coalesce(1).sortWithinPartitions("ts").write.mode("append").parquet(folder)
    if late is not None:
        late.coalesce(1).write.mode("append").parquet(folder)
    return folder


def _placed(assign: DataFrame, k: int) -> DataFrame:
    return assign.agg(F.count(F.lit(1)).alias("placed"), F.countDistinct("eid").alias("distinct_edges"), F.count_if((F.col("block") < 0) | (F.col("block") >= k)).alias("bad_blocks"))


def stream_buffered(spark: SparkSession, d: str, k: int = 8) -> DataFrame:
    folder, g = _timed(spark, d)
    out = fresh_dir(spark, "buffered-stream")
    b = stream.BufferedStream(out, k, m_hint=g.m)
    b.start(stream.source(spark, folder, "ts timestamp, eid long, u long, v long"), f"{out}/checkpoint").awaitTermination()
    return _placed(b.assign(spark), k)


def stream_one_pass(spark: SparkSession, d: str, k: int = 8) -> DataFrame:
    folder, g = _timed(spark, d)
    out = fresh_dir(spark, "one-pass-stream")
    placed = stream.one_pass(stream.source(spark, folder, "ts timestamp, eid long, u long, v long"), k, g.m, g.n)
    placed.writeStream.format("parquet").option("path", f"{out}/assign").option("checkpointLocation", f"{out}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return _placed(spark.read.parquet(f"{out}/assign"), k)


def stream_one_pass_stateful(spark: SparkSession, d: str, k: int = 8) -> DataFrame:
    """The same on the state store; the provider and one store for the one lane are set for the run only."""
    folder, g = _timed(spark, d)
    out = fresh_dir(spark, "stateful-stream")
    wanted = {"spark.sql.streaming.stateStore.providerClass": stream.ROCKS, "spark.sql.shuffle.partitions": "1"}
    before = {name: spark.conf.get(name) for name in wanted}
    for name, value in wanted.items():
        spark.conf.set(name, value)
    try:
        placed = stream.one_pass_stateful(stream.source(spark, folder, "ts timestamp, eid long, u long, v long"), k, g.m, g.n)
        placed.writeStream.format("parquet").option("path", f"{out}/assign").option("checkpointLocation", f"{out}/checkpoint").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    finally:
        for name, value in before.items():
            spark.conf.set(name, value)
    return _placed(spark.read.parquet(f"{out}/assign"), k)


def stream_late(spark: SparkSession, d: str) -> DataFrame:
    """Daily edge windows over the stream with a watermark of an hour; the edges of the first day come once more at the end. One row: windows
    closed, edges in them, late edges dropped."""
    folder, _ = _timed(spark, d)
    timed = materialise(spark.read.schema("ts timestamp, eid long, u long, v long").parquet(folder), "timed")
    start = timed.agg(F.min("ts")).first()[0]
    folder, out = _in_parts(spark, timed, 4, timed.where(F.col("ts") < F.lit(start) + F.expr("INTERVAL 1 DAY"))), fresh_dir(spark, "late-stream")
    w = stream.windowed(stream.source(spark, folder, "ts timestamp, eid long, u long, v long"), "1 day", None, "1 hour")
    q = w.writeStream.format("parquet").option("path", f"{out}/w").option("checkpointLocation", f"{out}/c").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    closed = spark.read.schema("start timestamp, u long, v long, mult long").parquet(f"{out}/w")
    return closed.agg(F.countDistinct("start").alias("windows"), F.count(F.lit(1)).alias("edges")).withColumn("late", F.lit(stream.late_rows(q)).cast("long"))


def stream_coactivity(spark: SparkSession, d: str) -> DataFrame:
    """(p, q, times): pairs of users with events on one key within an hour, from a join of two streams."""
    rows = table(spark, d, "events").select("ts", F.col("user_id").alias("user"), F.get_json_object("props", "$.k").cast("long").alias("key"))
    folder, out = _in_parts(spark, rows), fresh_dir(spark, "coactivity-stream")
    one, two = (stream.source(spark, folder, "ts timestamp, user long, key long") for _ in range(2))
    pairs = stream.coactivity(one, two, "60 MINUTES", "10 days")
    pairs.writeStream.format("parquet").option("path", f"{out}/p").option("checkpointLocation", f"{out}/c").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("p long, q long, ts timestamp").parquet(f"{out}/p").groupBy("p", "q").agg(F.count(F.lit(1)).alias("times"))


def stream_dedup(spark: SparkSession, d: str) -> DataFrame:
    """The stream read twice over: each edge comes out once."""
    folder, _ = _timed(spark, d)
    out = fresh_dir(spark, "dedup-stream")
    twice = stream.source(spark, folder, "ts timestamp, eid long, u long, v long").withColumn("x", F.explode(F.array(F.lit(1), F.lit(2)))).drop("x")
    stream.unique_edges(twice, "30 days").writeStream.format("parquet").option("path", f"{out}/e").option("checkpointLocation", f"{out}/c").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{out}/e").agg(F.count(F.lit(1)).alias("edges"), F.countDistinct("eid").alias("distinct_edges"))


__all__ = ["CHECKED", "CLAIMS", "EXPERIMENTS", "METHODS", "checked", "claims"]
