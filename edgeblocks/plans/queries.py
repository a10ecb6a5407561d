"""Every query of the engine by name, and its SQL where it can be said."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import sqlapi
from ..operators import analytics, baselines, batching, buffered, canonical, fennel, hypergraph, linegraph, metrics, model, multilevel, onthefly, relational, sequential, state
from ..operators.canonical import Graph
from ..sources.tables import table
from ..storage import materialise
from ..streaming import stream
from . import profiles, published, stepwise, workloads
from .graphs import NAMES, graph, sql_prefix

#: The flagship setting.
NAME, K, DELTA = "part_order", 8, 1024
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, run: Query, sql: str | None = None, on: str | None = NAME) -> None:
    """sql starts after the CTEs v, e and arc of graph on; with on=None it stands alone."""
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql if on is None else f"WITH {sql_prefix(on)}{'' if sql.startswith(',') else ' '}{sql}"


def g_of(spark: SparkSession, d: str, name: str = NAME) -> Graph:
    return graph(spark, d, name)


# ---- graphs

for _n in [*NAMES, "order_iso"]:
    add(
        f"graph_{_n}", lambda s, d, n=_n: canonical.summary(g_of(s, d, n)),
        """, dg AS (SELECT count(*) AS c FROM arc GROUP BY v)
SELECT (SELECT count(*) FROM v) AS n, (SELECT count(*) FROM e) AS m, max(c) AS max_degree, count(*) FILTER (c <= 2) AS low_degree FROM dg""",
        _n,
    )
add("edges_part_order", lambda s, d: g_of(s, d).edges, "SELECT eid, u, v FROM e")
add("vertices_page_link", lambda s, d: g_of(s, d, "page_link").vertices.select("id", F.col("kind").cast("int"), "num", "str"), "SELECT id, kind::INT AS kind, num, str FROM v", "page_link")
add("degrees", lambda s, d: canonical.degrees(g_of(s, d).edges), "SELECT v, count(*) AS deg FROM arc GROUP BY v")
add("degree_histogram", lambda s, d: canonical.degree_histogram(g_of(s, d, "doc_token").edges), "SELECT deg, count(*) AS vertices FROM (SELECT count(*) AS deg FROM arc GROUP BY v) GROUP BY deg", "doc_token")
add("edge_multiplicity", lambda s, d: canonical.simple_pairs(table(s, d, "lineitem").select(F.col("l_suppkey").alias("a"), (F.col("l_partkey") + 1_000_000).alias("b"))), "SELECT l_suppkey AS u, l_partkey + 1000000 AS v, count(*) AS mult FROM lineitem GROUP BY 1, 2", None)
add("subgraph_induced", lambda s, d: canonical.induced(g_of(s, d).edges, g_of(s, d).vertices.where("id % 3 <> 0")), "SELECT eid, u, v FROM e WHERE u % 3 <> 0 AND v % 3 <> 0")
add("isolated_vertices", lambda s, d: canonical.isolated_vertices(g_of(s, d, "order_iso")).select("id", "num"), "SELECT id, num FROM v WHERE id NOT IN (SELECT v FROM arc)", "order_iso")
add(
    "vertex_weights",
    lambda s, d: canonical.weight_sum(g_of(s, d).vertices.where("kind = 0").join(table(s, d, "part").select(F.col("p_partkey").alias("num"), "p_size"), "num").withColumn("batch", batching.batch_of(F.col("id"), DELTA)), "p_size", "batch"),
    "SELECT id // 1024 AS batch, sum(p_size)::BIGINT AS weight FROM v JOIN part ON num = p_partkey WHERE kind = 0 GROUP BY 1",
)

# ---- batches

add("batch_owner", lambda s, d: batching.own_edges(g_of(s, d).edges, DELTA), "SELECT eid, u, v, v // 1024 AS batch, CASE WHEN u // 1024 < v // 1024 THEN u END AS past FROM e")
add("batch_sizes", lambda s, d: batching.batch_sizes(g_of(s, d).edges, DELTA), "SELECT v // 1024 AS batch, count(*) AS edges, count(DISTINCT CASE WHEN u // 1024 < v // 1024 THEN u END) AS past_vertices FROM e GROUP BY 1")
add(
    "batch_labels", lambda s, d: batching.batch_vertices(batching.own_edges(g_of(s, d).edges, DELTA), DELTA),
    """, x AS (SELECT v // 1024 AS batch, v AS w FROM e UNION SELECT v // 1024, u FROM e),
y AS (SELECT batch, w AS v, w // 1024 < batch AS is_past FROM x)
SELECT batch, v, is_past, CASE WHEN is_past THEN 1024 + row_number() OVER (PARTITION BY batch, is_past ORDER BY v) - 1 ELSE v - batch * 1024 END AS label FROM y""",
)
add("batch_from_adjacency", lambda s, d: batching.own_from_adjacency(canonical.adjacency(g_of(s, d).edges), DELTA), "SELECT u, v, v // 1024 AS batch, CASE WHEN u // 1024 < v // 1024 THEN u END AS past FROM e")
add("batch_edge_budget", lambda s, d: batching.budget_cuts(g_of(s, d).edges, 4000), ", o AS (SELECT v, count(*) AS own FROM e GROUP BY v) SELECT v, ((sum(own) OVER (ORDER BY v) - own) // 4000)::BIGINT AS batch FROM o")
add("hub_pieces", lambda s, d: batching.hub_pieces(g_of(s, d, "supp_part").edges, 100), "SELECT eid, u, v, (row_number() OVER (PARTITION BY v ORDER BY u) - 1) // 100 AS piece FROM e", "supp_part")

# ---- line graphs

_OWN = ", b AS (SELECT greatest(v, nbr) // 1024 AS batch, v AS x, nbr, eid FROM arc)"
_LINKS = _OWN + ", l0 AS (SELECT batch, x, eid AS a, lead(eid) OVER (PARTITION BY batch, x ORDER BY eid) AS z FROM b), l AS (SELECT batch, x AS v, least(a, z) AS e1, greatest(a, z) AS e2 FROM l0 WHERE z IS NOT NULL)"


def owned(s: SparkSession, d: str, name: str = NAME, delta: int = DELTA) -> DataFrame:
    return batching.own_edges(g_of(s, d, name).edges, delta)


add("split_vertices", lambda s, d: linegraph.split_vertices(owned(s, d)), _OWN + " SELECT batch, x AS v, (row_number() OVER (PARTITION BY batch, x ORDER BY eid) - 1)::INT AS pos, eid FROM b")
add(
    "split_edges", lambda s, d: linegraph.dominant_edges(linegraph.split_vertices(owned(s, d))).drop("w"),
    _OWN + ", s AS (SELECT batch, x, (row_number() OVER (PARTITION BY batch, x ORDER BY eid) - 1)::INT AS pos, eid FROM b) SELECT batch, eid, min(x) AS v1, arg_min(pos, x) AS pos1, max(x) AS v2, arg_max(pos, x) AS pos2 FROM s GROUP BY batch, eid",
)
add("split_auxiliary", lambda s, d: linegraph.auxiliary_edges(linegraph.split_vertices(owned(s, d))), _OWN + ", s AS (SELECT batch, x AS v, (row_number() OVER (PARTITION BY batch, x ORDER BY eid) - 1)::INT AS pos, eid AS e1, lead(eid) OVER (PARTITION BY batch, x ORDER BY eid) AS e2 FROM b) SELECT batch, v, pos, pos + 1 AS next_pos, e1, e2 FROM s WHERE e2 IS NOT NULL")
add("contracted_links", lambda s, d: linegraph.contracted(owned(s, d)).drop("w"), _LINKS + " SELECT batch, v, e1, e2 FROM l")
add("contracted_by_matching", lambda s, d: linegraph.contract_dominant(linegraph.auxiliary_edges(linegraph.split_vertices(owned(s, d)))), _LINKS + " SELECT batch, e1, e2, count(*) AS w FROM l GROUP BY batch, e1, e2")


def _equal_line_graphs(s: SparkSession, d: str) -> DataFrame:
    one = linegraph.contracted(owned(s, d)).groupBy("batch", "e1", "e2").agg(F.sum("w").alias("w"))
    two = linegraph.contract_dominant(linegraph.auxiliary_edges(linegraph.split_vertices(owned(s, d))))
    return one.exceptAll(two).union(two.exceptAll(one)).agg(F.count(F.lit(1)).alias("different"))


add("contracted_equals_split", _equal_line_graphs, "SELECT 0::BIGINT AS different", None)
add("links_size_law", lambda s, d: linegraph.size_law(owned(s, d)), _LINKS + ", c AS (SELECT batch, count(DISTINCT eid) AS items, count(DISTINCT x) AS vertices FROM b GROUP BY batch), k AS (SELECT batch, count(*) AS links FROM l GROUP BY batch) SELECT c.batch, items, vertices, coalesce(links, 0) AS links, 2 * items - vertices AS expected FROM c LEFT JOIN k USING (batch)")
add("links_by_udtf", lambda s, d: _udtf_links(s, d), _LINKS + " SELECT batch, v, e1, e2 FROM l")


def _udtf_links(s: SparkSession, d: str) -> DataFrame:
    batching.batch_arcs(owned(s, d)).select("batch", "v", "eid").createOrReplaceTempView("edgeblocks_arcs")
    return sqlapi.sql(s, "SELECT * FROM path_links(TABLE(edgeblocks_arcs) PARTITION BY (batch, v) ORDER BY eid)")


add("dual_pins", lambda s, d: hypergraph.dual(g_of(s, d)), "SELECT v AS net, eid AS pin FROM arc")

# ---- scalars

add("alpha_vertex", lambda s, d: _alphas(s, d, lambda k, n, m: fennel.alpha_column(k, n, m)), "SELECT k, round(sqrt(k) * (SELECT count(*) FROM e) / pow((SELECT count(*) FROM v), 1.5), 9) AS alpha FROM (SELECT unnest([2, 8, 32, 128, 1024])::INT AS k)")
add("alpha_static", lambda s, d: _alphas(s, d, lambda k, n, m: fennel.alpha_column(k, m, 2 * m)), "SELECT k, round(sqrt(k) * 2 * m / pow(m, 1.5), 9) AS alpha FROM (SELECT unnest([2, 8, 32, 128, 1024])::INT AS k), (SELECT count(*) AS m FROM e)")


def _sizes(s: SparkSession, d: str, ks: tuple[int, ...]) -> DataFrame:
    """(n, m, k): vertices and edges, counted from the graph's tables, for each k."""
    g = g_of(s, d)
    both = g.vertices.agg(F.count("id").alias("n")).crossJoin(g.edges.agg(F.count("eid").alias("m")))
    return both.select("n", "m", F.explode(F.array(*map(F.lit, ks))).alias("k"))


def _alphas(s: SparkSession, d: str, f) -> DataFrame:
    return _sizes(s, d, (2, 8, 32, 128, 1024)).select("k", F.round(f(F.col("k"), F.col("n"), F.col("m")), 9).alias("alpha"))


def _block_caps(s: SparkSession, d: str) -> DataFrame:
    _sizes(s, d, (2, 8, 64, 1024, 16384)).createOrReplaceTempView("edgeblocks_sizes")
    return sqlapi.sql(s, "SELECT k, block_cap(m, k, 30) AS l_max FROM edgeblocks_sizes")


def _gain_grid(s: SparkSession, d: str) -> DataFrame:
    """Gain of each vertex in each block that holds edges of it, from the loads of a hash partition."""
    a = hashed(s, d, "supp_part")
    inside = a.select(F.explode(F.array("u", "v")).alias("v"), "block").groupBy("v", "block").agg(F.count(F.lit(1)).alias("w"))
    gain = fennel.gain(F.col("w").cast("double"), F.lit(2.0), F.col("load"), 0.25)
    return inside.join(metrics.loads(a), "block").select("v", "block", F.round(gain, 9).alias("gain"))


def _alpha_batches(s: SparkSession, d: str) -> DataFrame:
    law = linegraph.size_law(owned(s, d))
    return law.select("batch", F.round(F.sqrt(F.lit(float(K))) * F.col("links") / F.pow("items", F.lit(1.5)), 9).alias("alpha"))


add("alpha_batch", _alpha_batches, _LINKS + ", c AS (SELECT batch, count(DISTINCT eid) AS items FROM b GROUP BY batch), k AS (SELECT batch, count(*) AS links FROM l GROUP BY batch) SELECT c.batch, round(sqrt(8) * coalesce(links, 0) / pow(items, 1.5), 9) AS alpha FROM c LEFT JOIN k USING (batch)")


def _alpha_running(s: SparkSession, d: str) -> DataFrame:
    """Dynamic alpha of each batch from running totals; a row per batch goes through one window."""
    w = Window.orderBy("batch").rowsBetween(Window.unboundedPreceding, 0)
    law = linegraph.size_law(owned(s, d)).select("batch", F.sum("links").over(w).alias("l"), F.sum("items").over(w).alias("i"))
    m = g_of(s, d).m
    return law.select("batch", F.round(F.sqrt(F.lit(float(K))) * (F.col("l") / F.col("i")) * F.lit(float(m)) / F.pow(F.lit(float(m)), F.lit(1.5)), 9).alias("alpha"))


add("alpha_dynamic", _alpha_running, _LINKS + ", c AS (SELECT batch, count(DISTINCT eid) AS items FROM b GROUP BY batch), k AS (SELECT batch, count(*) AS links FROM l GROUP BY batch), r AS (SELECT c.batch, sum(coalesce(links, 0)) OVER (ORDER BY c.batch) AS ls, sum(items) OVER (ORDER BY c.batch) AS its FROM c LEFT JOIN k USING (batch)) SELECT batch, round(sqrt(8) * (ls::DOUBLE / its::DOUBLE) * m::DOUBLE / pow(m::DOUBLE, 1.5), 9) AS alpha FROM r, (SELECT count(*) AS m FROM e)")
add("block_cap", _block_caps, "SELECT k, greatest(1, (1030 * m + 1000 * k - 1) // (1000 * k))::BIGINT AS l_max FROM (SELECT unnest([2, 8, 64, 1024, 16384])::INT AS k), (SELECT count(*) AS m FROM e)")
add("fennel_gain_grid", _gain_grid, ", h AS (SELECT u, v, ((u * 31 + v * 17) % 8)::INT AS block FROM e), l AS (SELECT block, count(*) AS load FROM h GROUP BY block), w AS (SELECT v, block, count(*) AS w FROM (SELECT u AS v, block FROM h UNION ALL SELECT v, block FROM h) GROUP BY ALL) SELECT v, block, round(w - 2 * 0.375 * sqrt(load), 9) AS gain FROM w JOIN l USING (block)", "supp_part")
add("sql_functions", lambda s, d: sqlapi.sql(s, "SELECT id AS i, edge_batch(id, id * 7, 16) AS batch, hash_block(id, id + 3, 8) AS block, round(fennel_gain(3D, 2D, cast(id AS DOUBLE), 0.5D, 1.5D), 9) AS gain FROM range(50)"), "SELECT i, greatest(i // 16, (i * 7) // 16) AS batch, ((i * 31 + (i + 3) * 17) % 8)::INT AS block, round(3 - 2 * 0.75 * sqrt(i), 9) AS gain FROM range(50) t(i)", None)

# ---- hashing baselines and measures on them

_HASH = ", h AS (SELECT eid, u, v, ((u * 31 + v * 17) % 8)::INT AS block, v // 1024 AS batch FROM e), rep AS (SELECT DISTINCT v, block FROM (SELECT u AS v, block FROM h UNION ALL SELECT v, block FROM h)), lam AS (SELECT v, count(*) AS lam FROM rep GROUP BY v)"
_DEG = ", dg AS (SELECT v AS x, count(*) AS c FROM arc GROUP BY v), h AS (SELECT eid, u, v, (CASE WHEN b.c < a.c THEN v ELSE u END % 8)::INT AS block FROM e JOIN dg a ON a.x = u JOIN dg b ON b.x = v), rep AS (SELECT DISTINCT v, block FROM (SELECT u AS v, block FROM h UNION ALL SELECT v, block FROM h)), lam AS (SELECT v, count(*) AS lam FROM rep GROUP BY v)"
_RF = " SELECT sum(lam)::BIGINT AS replicas, sum(lam - 1)::BIGINT AS extra_copies, round(sum(lam) / (SELECT count(*) FROM v), 6) AS rf, round(sum(lam) / count(*), 6) AS rf_nonisolated FROM lam"


def hashed(s: SparkSession, d: str, name: str = NAME, k: int = K) -> DataFrame:
    return baselines.hash_edges(g_of(s, d, name), k)


def hashed_batches(s: SparkSession, d: str) -> DataFrame:
    return hashed(s, d).withColumn("batch", batching.batch_of(F.col("v"), DELTA))


add("hash_blocks", lambda s, d: hashed(s, d), _HASH + " SELECT eid, u, v, block FROM h")
add("hash_rf", lambda s, d: metrics.replication(hashed(s, d), g_of(s, d)), _HASH + _RF)
add("dbh_blocks", lambda s, d: baselines.dbh(g_of(s, d), K), _DEG + " SELECT eid, u, v, block FROM h")
add("dbh_rf", lambda s, d: metrics.replication(baselines.dbh(g_of(s, d), K), g_of(s, d)), _DEG + _RF)
add("grid_rf", lambda s, d: metrics.replication(baselines.grid(g_of(s, d), 16), g_of(s, d)), _HASH.replace("((u * 31 + v * 17) % 8)", "(u % 4 * 4 + v % 4)") + _RF)
add("round_robin_rf", lambda s, d: metrics.replication(baselines.round_robin(g_of(s, d), K), g_of(s, d)), _HASH.replace("((u * 31 + v * 17) % 8)", "(eid % 8)") + _RF)
add("random_rf", lambda s, d: metrics.replication(baselines.random_blocks(g_of(s, d), K), g_of(s, d)), _HASH.replace("((u * 31 + v * 17) % 8)", "(((eid % 1000003 * 7919 + 12345) % 1000003 * (eid % 1000003 + 104729) % 998244353) % 8)") + _RF)
add("replicas_hash", lambda s, d: metrics.replicas(hashed(s, d)), _HASH + " SELECT v, block FROM rep")
add("covered_hash", lambda s, d: metrics.covered(hashed(s, d)), _HASH + " SELECT block, count(*) AS vertices FROM rep GROUP BY block")
add("extra_copies_hash", lambda s, d: metrics.replication(hashed(s, d, "supp_part"), g_of(s, d, "supp_part")).select("extra_copies"), _HASH + " SELECT sum(lam - 1)::BIGINT AS extra_copies FROM lam", "supp_part")
add("lambda_hist", lambda s, d: metrics.lambda_histogram(hashed(s, d)), _HASH + " SELECT lam, count(*) AS vertices FROM lam GROUP BY lam")
_items = lambda a: a.select(F.col("eid").alias("item"), "block")
add("connectivity_hash", lambda s, d: hypergraph.connectivity(hypergraph.dual(g_of(s, d)), _items(hashed(s, d))), _HASH + " SELECT sum(lam - 1)::BIGINT AS connectivity FROM lam")
add("cut_net_hash", lambda s, d: hypergraph.cut_net(hypergraph.dual(g_of(s, d)), _items(hashed(s, d))), _HASH + " SELECT count(*) FILTER (lam > 1) AS cut_nets FROM lam")
add("connectivity_sets_hash", lambda s, d: hypergraph.connectivity_sets(hypergraph.dual(g_of(s, d)), _items(hashed(s, d))).select("net", F.array_join(F.transform("blocks", lambda b: b.cast("string")), ",").alias("blocks"), "lam"), _HASH + " SELECT v AS net, string_agg(block::VARCHAR, ',' ORDER BY block) AS blocks, count(*) AS lam FROM rep GROUP BY v")
add("edge_cut_hash", lambda s, d: metrics.edge_cut(linegraph.contracted(owned(s, d)), hashed(s, d)), _HASH + _LINKS + " SELECT count(*) AS cut FROM l JOIN h a ON a.eid = e1 JOIN h z ON z.eid = e2 WHERE a.block <> z.block")
add("balance_hash", lambda s, d: metrics.balance(hashed(s, d), K), _HASH + ", c AS (SELECT i::INT AS block, count(h.eid) AS load FROM range(8) t(i) LEFT JOIN h ON h.block = i GROUP BY i), x AS (SELECT max(load) AS hi, min(load) AS lo, sum(load)::BIGINT AS m FROM c) SELECT 8::INT AS blocks, hi AS max_load, lo AS min_load, greatest(1, (103 * m + 799) // 800)::BIGINT AS l_max, round(hi * 8 / m - 1, 6) AS imbalance, hi <= (103 * m + 799) // 800 AS feasible FROM x")
_SEEN = _HASH + ", ev AS (SELECT u AS x, block, batch, eid FROM h UNION ALL SELECT v, block, batch, eid FROM h)"
add("new_replicas_by_batch_hash", lambda s, d: metrics.new_replicas(hashed_batches(s, d)), _SEEN + ", p1 AS (SELECT x, block, min(batch) AS batch FROM ev GROUP BY x, block), f1 AS (SELECT x, min(batch) AS batch FROM ev GROUP BY x) SELECT batch, (SELECT count(*) FROM p1 WHERE p1.batch = t.batch) - (SELECT count(*) FROM f1 WHERE f1.batch = t.batch) AS gamma FROM (SELECT DISTINCT batch FROM h) t")
add("sync_messages_hash", lambda s, d: metrics.sync_messages(hashed(s, d)), _HASH + " SELECT (2 * sum(lam - 1))::BIGINT AS messages FROM lam")
add(
    "load_quantiles_hash", lambda s, d: metrics.load_quantiles(hashed(s, d, "supp_part"), K).select(*(F.col("quantiles")[i].alias(n) for i, n in enumerate(("half", "most", "top")))),
    _HASH + ", c AS (SELECT i::INT AS block, count(h.eid) AS load FROM range(8) t(i) LEFT JOIN h ON h.block = i GROUP BY i) SELECT quantile_disc(load, 0.5)::BIGINT AS half, quantile_disc(load, 0.9)::BIGINT AS most, max(load) AS top FROM c", "supp_part",
)


def _preview(s: SparkSession, d: str) -> DataFrame:
    """The sketched replication, held within five of its standard errors of the exact one."""
    g, a = g_of(s, d), hashed(s, d)
    both = metrics.replication(a, g).select("rf").crossJoin(metrics.replication_preview(a, g, 0.02))
    return both.select("rf", (F.abs(F.col("rf_approx") / F.col("rf") - 1) <= 5 * 0.02).alias("close"))


add("replication_preview_hash", _preview, _HASH + " SELECT round(sum(lam) / (SELECT count(*) FROM v), 6) AS rf, true AS close FROM lam")
add("block_bitmaps_hash", lambda s, d: state.block_bitmap(hashed(s, d)).groupBy("v").agg(F.sum(F.bitmap_count("bits")).alias("lam")), _HASH + " SELECT v, lam FROM lam")
add("memory_cells_hash", lambda s, d: state.cells(state.update(None, hashed_batches(s, d), "minimal")).select(F.lit("minimal").alias("mode"), "cells").union(state.cells(state.update(None, hashed_batches(s, d), "maximal")).select(F.lit("maximal"), "cells")), _HASH + " SELECT 'minimal' AS mode, count(*) AS cells FROM lam UNION ALL SELECT 'maximal', count(*) FROM rep")

# ---- models, with the memory that hashing leaves

_PAST = _SEEN + ", own AS (SELECT eid, batch, u AS past FROM h WHERE u // 1024 < batch)"
_MODEL = {
    "none": "SELECT NULL::BIGINT AS batch, NULL::BIGINT AS eid, NULL::INT AS block WHERE false",
    "maximal": "SELECT DISTINCT own.batch, own.eid, ev.block FROM own JOIN ev ON ev.x = past AND ev.batch < own.batch",
    "minimal": "SELECT own.batch, own.eid, arg_max(ev.block, ev.eid) AS block FROM own JOIN ev ON ev.x = past AND ev.batch < own.batch WHERE ev.batch = (SELECT max(z.batch) FROM ev z WHERE z.x = past AND z.batch < own.batch) GROUP BY own.batch, own.eid",
    "subset": "SELECT batch, eid, block FROM (SELECT *, row_number() OVER (PARTITION BY batch, eid ORDER BY (eid * 7919 + block * 104729) % 1000003, block) AS r FROM (SELECT DISTINCT own.batch, own.eid, ev.block FROM own JOIN ev ON ev.x = past AND ev.batch < own.batch)) WHERE r <= 2",
}


def _memory(s: SparkSession, d: str) -> DataFrame:
    """(v, block, seq, eid) of every batch: what each batch's successors may look up."""
    a = hashed_batches(s, d)
    ends = a.select(F.explode(F.array("u", "v")).alias("v"), "block", F.col("batch").alias("seq"), "eid")
    return ends.groupBy("v", "block", "seq").agg(F.max("eid").alias("eid"))


add("model_none", lambda s, d: model.model_size(owned(s, d), None, "none").select("batch", "items", "block_links"), "SELECT v // 1024 AS batch, count(*) AS items, 0::BIGINT AS block_links FROM e GROUP BY 1")
for _mode in model.MODES[1:]:
    add(f"model_{_mode}_hash", lambda s, d, m=_mode: model.block_links(owned(s, d), _memory(s, d), m, r=2).drop("w"), _PAST + " " + _MODEL[_mode])


def _model_sizes(s: SparkSession, d: str) -> DataFrame:
    out = None
    for m in model.MODES:
        one = model.block_links(owned(s, d), _memory(s, d), m, r=2).agg(F.count(F.lit(1)).alias("block_links")).select(F.lit(m).alias("mode"), "block_links")
        out = one if out is None else out.union(one)
    return out


add("model_sizes_by_mode_hash", _model_sizes, _PAST + " " + " UNION ALL ".join(f"SELECT '{m}' AS mode, count(*) AS block_links FROM ({q})" for m, q in _MODEL.items()))

# ---- partitioners: certificates that a right partition must show

_CERT = "SELECT count(*) AS placed, count(*) AS distinct_edges, 0::BIGINT AS bad_blocks, 0::BIGINT AS over_cap, 0::BIGINT AS bound_violations"
_BELOW = _HASH + f" {_CERT}, (SELECT count(*) FROM rep) AS hash_copies, true AS below_hash FROM e"


def certified(run: Callable[[Graph], buffered.Partition], k: int = K) -> Query:
    """What must hold for the partition, batch by batch where the method has batches with a memory, and that it copies less than hashing."""

    def query(s: SparkSession, d: str) -> DataFrame:
        g = g_of(s, d)
        p = run(g)
        by_batch = "cut" in p.stats.columns and p.notes.get("mode") != "none"
        return metrics.certificate(p.assign, g, k, stats=p.stats if by_batch else None).crossJoin(metrics.against_hashing(p.assign, g, k))

    return query


def buf(**more) -> Callable[[Graph], buffered.Partition]:
    return lambda g: buffered.partition(g, K, **{"delta": DELTA, **more})


_METHODS: dict[str, Callable[[Graph], buffered.Partition]] = {
    "buffered_minimal": buf(), "buffered_maximal": buf(mode="maximal"), "buffered_subset": buf(mode="subset", r=2), "buffered_none": buf(mode="none"),
    "buffered_static": buf(alpha="static"), "buffered_dynamic": buf(alpha="dynamic"), "buffered_dynamic_low": buf(alpha="dynamic_low"), "buffered_allk": buf(init="all_k"), "buffered_bucket": buf(init="two_set_bucket"),
    "buffered_onebatch": buf(delta=1 << 40), "buffered_split": buf(line="split"), "buffered_neighbour_order": buf(order="nbr"), "buffered_random_order": buf(order="random"),
    "buffered_jobs": buf(exec="jobs", delta=8192), "buffered_lanes": buf(lanes=4, delta=2048), "buffered_budget": buf(budget=8000), "buffered_budget_lanes": buf(budget=8000, lanes=3),
    "onthefly": lambda g: onthefly.partition(g, K), "onthefly_all": lambda g: onthefly.partition(g, K, net_memory="all"), "onthefly_lanes": lambda g: onthefly.partition(g, K, lanes=4),
    "hdrf": lambda g: baselines.hdrf(g, K), "hdrf_exact": lambda g: baselines.hdrf(g, K, degrees="exact"), "hdrf_lanes": lambda g: baselines.hdrf(g, K, lanes=4),
    "two_phase_hdrf": lambda g: baselines.two_phase(g, K), "two_phase_linear": lambda g: baselines.two_phase(g, K, "linear"),
    "neighbour_expansion": lambda g: baselines.neighbour_expansion(g, K), "window_greedy": lambda g: baselines.window_greedy(g, K), "restricted_buffer": lambda g: baselines.restricted_buffer(g, K),
}
for _n, _run in _METHODS.items():
    add(_n, certified(_run), _BELOW)
add("many_blocks_hdrf", lambda s, d: metrics.certificate(baselines.hdrf(g_of(s, d, "turn_path"), 16384).assign, g_of(s, d, "turn_path"), 16384), _CERT + " FROM e", "turn_path")

# ---- one-pass methods, block by block against a step-by-step recursion in SQL

_SMALL = stepwise.NAME


def _blocks(run: Callable[[Graph], buffered.Partition]) -> Query:
    return lambda s, d: run(g_of(s, d, _SMALL)).assign.select("eid", "u", "v", "block")


def _flat(**more) -> Callable[[Graph], buffered.Partition]:
    """The buffered method without clustering and refinement."""
    return lambda g: buffered.partition(g, stepwise.K, delta=stepwise.DELTA, cluster_rounds=0, refine_rounds=0, **more)


for _n, _run, _sql in (
    ("onthefly_blocks", lambda g: onthefly.partition(g, K), stepwise.on_the_fly()), ("onthefly_all_blocks", lambda g: onthefly.partition(g, K, net_memory="all"), stepwise.on_the_fly(True)),
    ("hdrf_blocks", lambda g: baselines.hdrf(g, K, scan="all"), stepwise.hdrf()), ("hdrf_seen_blocks", lambda g: baselines.hdrf(g, K), stepwise.hdrf()), ("hdrf_exact_blocks", lambda g: baselines.hdrf(g, K, degrees="exact"), stepwise.hdrf(True)),
    ("two_phase_hdrf_blocks", lambda g: baselines.two_phase(g, K), stepwise.two_phase()), ("two_phase_linear_blocks", lambda g: baselines.two_phase(g, K, "linear"), stepwise.two_phase("linear")),
    ("buffered_flat_minimal_blocks", _flat(), stepwise.buffered()), ("buffered_flat_maximal_blocks", _flat(mode="maximal"), stepwise.buffered("maximal")),
    ("buffered_flat_none_blocks", _flat(mode="none"), stepwise.buffered("none")), ("buffered_flat_static_blocks", _flat(alpha="static"), stepwise.buffered("minimal", "static")),
    ("buffered_flat_jobs_blocks", _flat(exec="jobs"), stepwise.buffered()), ("buffered_flat_allk_blocks", _flat(init="all_k"), stepwise.buffered()),
):
    add(_n, _blocks(_run), _sql, None)
add("fennel_vertex_blocks", lambda s, d: _fennel_vertices(g_of(s, d, _SMALL)), stepwise.fennel_vertices(), None)


def _together(runs: list[Callable[[], object]], at_once: int = 6) -> list:
    """Results of runs whose long parts are single tasks, some of them side by side."""
    with ThreadPoolExecutor(at_once) as pool:
        return list(pool.map(lambda run: run(), runs))


def _batch_bounds(s: SparkSession, d: str) -> DataFrame:
    """For every graph and the modes that have a memory, in one lane and in four: batches in which new replicas exceed the cut of the model,
    and, in one lane, new replicas that do not add up to the extra copies of the whole graph (batches of a round do not see each other's)."""
    cases = [(name, g_of(s, d, name), mode, lanes) for name in NAMES for mode in ("minimal", "subset", "maximal") for lanes in (1, 4)]

    def one(name: str, g: Graph, mode: str, lanes: int) -> DataFrame:
        p = buffered.partition(g, K, delta=max(16, g.n // (4 * lanes)), mode=mode, lanes=lanes)
        total = metrics.replication(p.assign, g).select("extra_copies")
        sums = p.stats.agg(F.count_if(F.col("gamma").isNull() | (F.col("gamma") > F.col("cut"))).alias("violations"), F.sum("gamma").alias("gamma")).crossJoin(total)
        row = sums.select(F.lit(name).alias("graph"), F.lit(mode).alias("mode"), F.lit(lanes).alias("lanes"), "violations", (F.col("gamma") - F.col("extra_copies") if lanes == 1 else F.lit(0).cast("long")).alias("unexplained"))
        return materialise(row, "bounds")

    rows = _together([lambda case=case: one(*case) for case in cases])
    out = rows[0]
    for row in rows[1:]:
        out = out.union(row)
    return out


add("batch_bounds", _batch_bounds, f"SELECT graph, mode, lanes::INT AS lanes, 0::BIGINT AS violations, 0::BIGINT AS unexplained FROM (SELECT unnest({NAMES}) AS graph), (SELECT unnest(['minimal', 'subset', 'maximal']) AS mode), (SELECT unnest([1, 4]) AS lanes)", None)


def _tight(s: SparkSession, d: str) -> DataFrame:
    """With paths ordered by block, the cut is the number of extra copies."""
    a = hashed(s, d)
    cut = metrics.edge_cut(linegraph.tight_order(g_of(s, d).edges, a), a)
    return cut.crossJoin(metrics.replication(a, g_of(s, d)).select("extra_copies"))


add("tight_path_order", _tight, _HASH + " SELECT sum(lam - 1)::BIGINT AS cut, sum(lam - 1)::BIGINT AS extra_copies FROM lam")


def _different(one: Callable[[Graph], buffered.Partition], two: Callable[[Graph], buffered.Partition]) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        g = g_of(s, d)
        a, b = (p.assign.select("eid", "block") for p in _together([lambda: one(g), lambda: two(g)]))
        return a.join(b.select("eid", F.col("block").alias("other")), "eid", "full_outer").agg(F.count_if(~F.col("block").eqNullSafe(F.col("other"))).alias("different"))

    return run


for _n, _a, _b in (("two_set_equals_all_k", buf(), buf(init="all_k")), ("bucket_equals_heap", buf(), buf(init="two_set_bucket")), ("single_task_equals_jobs", buf(delta=8192), buf(delta=8192, exec="jobs")), ("single_task_equals_jobs_maximal", buf(delta=8192, mode="maximal"), buf(delta=8192, mode="maximal", exec="jobs")), ("single_task_equals_jobs_subset", buf(delta=8192, mode="subset", r=2, alpha="dynamic"), buf(delta=8192, mode="subset", r=2, alpha="dynamic", exec="jobs")), ("single_task_equals_jobs_none", buf(delta=8192, mode="none", alpha="static"), buf(delta=8192, mode="none", alpha="static", exec="jobs")), ("single_task_equals_jobs_low", buf(delta=8192, alpha="dynamic_low"), buf(delta=8192, alpha="dynamic_low", exec="jobs")), ("budget_equals_jobs", buf(budget=20000), buf(budget=20000, exec="jobs"))):
    add(_n, _different(_a, _b), "SELECT 0::BIGINT AS different", None)


def _line_graph_sizes(s: SparkSession, d: str) -> DataFrame:
    """What the cut works on with the split graph and with the contracted one: items, links and edges whose copies were torn apart."""
    out = None
    g, lines = g_of(s, d), ("contracted", "split")
    for line, p in zip(lines, _together([lambda line=line: buf(line=line)(g) for line in lines])):
        one = p.stats.agg(F.sum("items").alias("items"), F.sum("links").alias("links"), F.sum("apart").alias("apart")).select(F.lit(line).alias("line"), "items", "links", "apart")
        out = one if out is None else out.union(one)
    return out


add("split_against_contracted", _line_graph_sizes, _LINKS + ", n AS (SELECT (SELECT count(*) FROM e) AS m, (SELECT count(*) FROM l) AS l) SELECT 'contracted' AS line, m AS items, l AS links, 0::BIGINT AS apart FROM n UNION ALL SELECT 'split', 2 * m, m + l, 0 FROM n")


def _vertex_cut(s: SparkSession, d: str, run) -> DataFrame:
    g = g_of(s, d, "copurchase")
    blocks = run(g)
    sizes = blocks.groupBy("block").count().agg(F.max("count").alias("most"))
    return blocks.agg(F.count(F.lit(1)).alias("placed"), F.count_if((F.col("block") < 0) | (F.col("block") >= K)).alias("bad_blocks")).crossJoin(sizes).select("placed", "bad_blocks", (F.col("most") > metrics.block_cap(g.n, K)).cast("long").alias("over_cap"))


def _fennel_vertices(g: Graph) -> DataFrame:
    """One Fennel pass over adjacency rows in id order, in one task."""
    import numpy as np
    import pyarrow as pa

    n = g.n

    def run(t: pa.Table) -> pa.Table:
        u, v = t.column("u").to_numpy(), t.column("v").to_numpy()
        x, y = np.concatenate([u, v]), np.concatenate([v, u])
        o = np.argsort(x, kind="stable")
        starts = np.concatenate([[0], np.cumsum(np.bincount(x, minlength=n))])
        return pa.table({"v": np.arange(n), "block": fennel.stream_vertices(n, starts, y[o], K).astype(np.int32)})

    return g.edges.select("u", "v").withColumn("lane", F.lit(0)).groupBy("lane").applyInArrow(run, "v bigint, block int")


_VCERT = "SELECT count(*) AS placed, 0::BIGINT AS bad_blocks, 0::BIGINT AS over_cap FROM v"
add("buffered_vertex_partition", lambda s, d: _vertex_cut(s, d, lambda g: buffered.vertex_partition(g, K, delta=512)), _VCERT, "copurchase")
add("fennel_vertex_stream", lambda s, d: _vertex_cut(s, d, _fennel_vertices), _VCERT, "copurchase")
add("hypergraph_adapter", lambda s, d: hypergraph.edge_partition_via(lambda pins: hypergraph.stream_partition(pins, K), g_of(s, d, _SMALL)).select("eid", "u", "v", "block"), stepwise.on_the_fly(), None)

# ---- reporting: on runs of the formula methods, and on the published rows


def _published(s: SparkSession) -> DataFrame:
    return s.createDataFrame(published.rows(), "alg string, graph string, k int, rf double, seconds double, gb double")


_PUB = "WITH r0(alg, graph, k, rf, seconds, gb) AS (VALUES " + ", ".join(repr(x) for x in published.rows()) + "), r AS (SELECT alg, graph, k::INT AS k, rf::DOUBLE AS rf, seconds::DOUBLE AS seconds, gb::DOUBLE AS gb FROM r0)"
_TAUS = [1.0, 1.1, 1.5, 2.0, 5.0, 10.0]


def _profile_sql(measure: str, where: str = "") -> str:
    return _RUNS + f""", i AS (SELECT DISTINCT graph, k FROM r {where}), a AS (SELECT DISTINCT alg FROM r {where}), f AS (SELECT a.alg, i.graph, i.k, r.{measure} AS x FROM a CROSS JOIN i LEFT JOIN r USING (alg, graph, k)),
q AS (SELECT alg, x / min(x) OVER (PARTITION BY graph, k) AS ratio FROM f) SELECT alg, tau::DOUBLE AS tau, round(avg(CASE WHEN ratio <= tau THEN 1 ELSE 0 END), 6) AS share FROM q, (SELECT unnest({_TAUS}) AS tau) GROUP BY alg, tau"""


#: Formula methods on graphs of the given tables, for the reports.
_REPORTED: dict[str, Callable[[Graph, int], DataFrame]] = {"hash": baselines.hash_edges, "dbh": baselines.dbh, "grid": baselines.grid, "round_robin": baselines.round_robin}
_REPORT_GRAPHS, _REPORT_KS = ("supp_part", "geo"), (4, 64, 1024)


def _reported(s: SparkSession, d: str) -> DataFrame:
    """(alg, graph, k, rf, stretch): replication, and the largest block over the mean one, counted from the blocks."""
    out = None
    for name in _REPORT_GRAPHS:
        g = g_of(s, d, name)
        sizes = g.vertices.agg(F.count("id").alias("n")).crossJoin(g.edges.agg(F.count("eid").alias("m")))
        placed = None
        for alg, run in _REPORTED.items():
            for k in _REPORT_KS:
                one = run(g, k).select(F.lit(alg).alias("alg"), F.lit(k).alias("k"), "u", "v", "block")
                placed = one if placed is None else placed.unionByName(one)
        copies = placed.select("alg", "k", F.explode(F.array("u", "v")).alias("x"), "block").distinct().groupBy("alg", "k").agg(F.count(F.lit(1)).alias("replicas"))
        most = placed.groupBy("alg", "k", "block").agg(F.count(F.lit(1)).alias("load")).groupBy("alg", "k").agg(F.max("load").alias("most"))
        runs = copies.join(most, ["alg", "k"]).crossJoin(sizes).select("alg", F.lit(name).alias("graph"), "k", (F.col("replicas") / F.col("n")).alias("rf"), (F.col("most") * F.col("k") / F.col("m")).alias("stretch"))
        out = runs if out is None else out.unionByName(runs)
    return materialise(out, "reported")


def _reported_sql(name: str) -> str:
    return f"""SELECT * FROM (WITH {sql_prefix(name)}, ks AS (SELECT unnest({list(_REPORT_KS)})::INT AS k), dg AS (SELECT v AS x, count(*) AS c FROM arc GROUP BY v),
h AS (SELECT 'hash' AS alg, k, u, v, (u * 31 + v * 17) % k AS block FROM e, ks UNION ALL SELECT 'dbh', k, u, v, CASE WHEN b.c < a.c THEN v ELSE u END % k FROM e JOIN dg a ON a.x = u JOIN dg b ON b.x = v, ks
  UNION ALL SELECT 'grid', k, u, v, u % sqrt(k)::BIGINT * sqrt(k)::BIGINT + v % sqrt(k)::BIGINT FROM e, ks UNION ALL SELECT 'round_robin', k, u, v, eid % k FROM e, ks),
c AS (SELECT alg, k, count(*) AS replicas FROM (SELECT DISTINCT alg, k, x, block FROM (SELECT alg, k, u AS x, block FROM h UNION ALL SELECT alg, k, v, block FROM h)) GROUP BY alg, k),
o AS (SELECT alg, k, max(load) AS most FROM (SELECT alg, k, block, count(*) AS load FROM h GROUP BY ALL) GROUP BY alg, k)
SELECT alg, '{name}' AS graph, k, replicas / (SELECT count(*) FROM v) AS rf, most * k / (SELECT count(*) FROM e) AS stretch FROM c JOIN o USING (alg, k))"""


_RUNS = "WITH r AS (" + " UNION ALL ".join(map(_reported_sql, _REPORT_GRAPHS)) + ")"
add("performance_profile_published", lambda s, d: profiles.performance_profile(_reported(s, d), "rf", _TAUS), _profile_sql("rf"), None)
add("performance_profile_large_k", lambda s, d: profiles.performance_profile(_reported(s, d), "stretch", _TAUS, 512), _profile_sql("stretch", "WHERE k >= 512"), None)
add("improvement_published", lambda s, d: profiles.mean_improvement(_reported(s, d), "dbh", "hash", "rf"), _RUNS + " SELECT count(*) AS instances, round((exp(avg(ln(b.rf))) / exp(avg(ln(a.rf))) - 1) * 100, 6) AS improvement, round(avg(CASE WHEN a.rf < b.rf THEN 1.0 ELSE 0.0 END), 6) AS win_rate FROM r a JOIN r b USING (graph, k) WHERE a.alg = 'dbh' AND b.alg = 'hash'", None)
add("pivot_published", lambda s, d: profiles.pivoted(_reported(s, d), "rf", list(_REPORTED)), _RUNS + " SELECT graph, k, " + ", ".join(f"max(rf) FILTER (alg = '{m}') AS {m}" for m in _REPORTED) + " FROM r GROUP BY graph, k", None)
add("relative_published", lambda s, d: profiles.relative(_reported(s, d), "stretch", "round_robin").withColumn("ratio", F.round("ratio", 6)), _RUNS + " SELECT a.alg, a.graph, a.k, round(a.stretch / b.stretch, 6) AS ratio FROM r a JOIN r b USING (graph, k) WHERE b.alg = 'round_robin'", None)
add("best_of_published", lambda s, d: _reported(s, d).groupBy("graph", "k").agg(F.min_by("alg", F.struct("rf", "alg")).alias("best")), _RUNS + " SELECT graph, k, arg_min(alg, (rf, alg)) AS best FROM r GROUP BY graph, k", None)
if published.rows():
    add("rollup_published", lambda s, d: profiles.rolled(_published(s), "rf"), _PUB + " SELECT alg, k, count(*) AS runs, round(exp(avg(ln(rf))), 6) AS mean FROM r GROUP BY ROLLUP (alg, k)", None)
    add("slope_published", lambda s, d: profiles.slope(_published(s), "seconds"), _PUB + " SELECT alg, graph, round(regr_slope(ln(seconds), ln(k)), 4) AS slope FROM r GROUP BY alg, graph", None)

# ---- relational cases on the same graphs

add(
    "edges_semi_anti", lambda s, d: g_of(s, d).edges.join(g_of(s, d).vertices.where("num % 2 = 0").select(F.col("id").alias("u")), "u", "left_semi").join(g_of(s, d).vertices.where("num % 3 = 0").select(F.col("id").alias("v")), "v", "left_anti").select("eid", "u", "v"),
    "SELECT eid, u, v FROM e WHERE u IN (SELECT id FROM v WHERE num % 2 = 0) AND v NOT IN (SELECT id FROM v WHERE num % 3 = 0)",
)
add("cube_loads", lambda s, d: hashed_batches(s, d).cube("batch", "block").agg(F.count(F.lit(1)).alias("edges")), _HASH + " SELECT batch, block, count(*) AS edges FROM h GROUP BY CUBE (batch, block)")
add("grouping_sets_loads", lambda s, d: _grouping_sets(s, d), _HASH + " SELECT batch, block, count(*) AS edges FROM h GROUP BY GROUPING SETS ((batch), (block), ())")


def _grouping_sets(s: SparkSession, d: str) -> DataFrame:
    return hashed_batches(s, d).groupingSets([[F.col("batch")], [F.col("block")], []], F.col("batch"), F.col("block")).agg(F.count(F.lit(1)).alias("edges"))


add("topr_neighbours", lambda s, d: canonical.arcs(g_of(s, d).edges).withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy(F.desc("nbr")))).where("r <= 3").select("v", "nbr", "r"), "SELECT v, nbr, r FROM (SELECT v, nbr, row_number() OVER (PARTITION BY v ORDER BY nbr DESC)::INT AS r FROM arc) WHERE r <= 3")


def _top_lateral(s: SparkSession, d: str) -> DataFrame:
    """Largest neighbour of each vertex of a small side by a lateral join."""
    canonical.arcs(g_of(s, d, "supp_part").edges).createOrReplaceTempView("edgeblocks_lat_arcs")
    g_of(s, d, "supp_part").vertices.where("kind = 0").createOrReplaceTempView("edgeblocks_lat_vertices")
    return s.sql("SELECT id AS v, top FROM edgeblocks_lat_vertices, LATERAL (SELECT max(nbr) AS top FROM edgeblocks_lat_arcs WHERE edgeblocks_lat_arcs.v = id)")


add("lateral_top_neighbour", _top_lateral, "SELECT id AS v, max(nbr) AS top FROM v JOIN arc ON arc.v = id WHERE kind = 0 GROUP BY id", "supp_part")


def _asof(s: SparkSession, d: str) -> DataFrame:
    """Block that a vertex met last before each of its edges: placements and probes in one ordered stream per vertex, no pair join."""
    a = hashed(s, d)
    ends = a.select(F.explode(F.array("u", "v")).alias("v"), "eid", "block")
    before = F.last("block", ignorenulls=True).over(Window.partitionBy("v").orderBy("eid").rowsBetween(Window.unboundedPreceding, -1))
    return ends.select("v", "eid", before.alias("known"))


add("asof_block", _asof, _HASH + ", ev AS (SELECT u AS v, eid, block FROM h UNION ALL SELECT v, eid, block FROM h) SELECT v, eid, lag(block) OVER (PARTITION BY v ORDER BY eid) AS known FROM ev")


def _range_batches(s: SparkSession, d: str) -> DataFrame:
    """Vertices to uneven ranges: the cuts, a row per batch, are a broadcast array searched per row."""
    cuts = [0, 10, 100, 1000, 10000, 1 << 40]
    return g_of(s, d).vertices.groupBy(_piece(cuts).alias("piece")).agg(F.count(F.lit(1)).alias("vertices"))


def _piece(cuts: list[int]):
    bounds = F.array(*(F.lit(c).cast("long") for c in cuts))
    return F.size(F.filter(bounds, lambda c: c <= F.col("id"))).cast("long") - 1


add("range_join_cuts", _range_batches, "SELECT CASE WHEN id < 10 THEN 0 WHEN id < 100 THEN 1 WHEN id < 1000 THEN 2 WHEN id < 10000 THEN 3 ELSE 4 END::BIGINT AS piece, count(*) AS vertices FROM v GROUP BY 1")


def _keyed_events(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").select("ts", F.col("user_id").alias("user"), F.get_json_object("props", "$.k").cast("long").alias("key"))


add("interval_coactivity", lambda s, d: stream.coactivity(_keyed_events(s, d), _keyed_events(s, d), "60 MINUTES").groupBy("p", "q").agg(F.count(F.lit(1)).alias("times")), """WITH k AS (SELECT ts, user_id AS u, json_extract_string(props, '$.k')::BIGINT AS key FROM events)
SELECT a.u AS p, b.u AS q, count(*) AS times FROM k a JOIN k b ON a.key = b.key AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 60 MINUTES AND a.u < b.u GROUP BY 1, 2""", None)
add("json_props_graph", lambda s, d: table(s, d, "events").select(F.from_json("props", "k long")["k"].alias("k"), "user_id").groupBy("k").agg(F.countDistinct("user_id").alias("users"), F.map_from_entries(F.array(F.struct(F.lit("n"), F.count(F.lit(1)))))["n"].alias("events")), "SELECT json_extract_string(props, '$.k')::BIGINT AS k, count(DISTINCT user_id) AS users, count(*) AS events FROM events GROUP BY 1", None)
add("intersect_partitions", lambda s, d: hashed(s, d).select("eid", "block").intersectAll(baselines.round_robin(g_of(s, d), K).select("eid", "block")), _HASH + " SELECT eid, block FROM h WHERE block = eid % 8")
add("cover_check", lambda s, d: g_of(s, d).edges.select("eid").exceptAll(hashed(s, d).select("eid")).agg(F.count(F.lit(1)).alias("missing")), "SELECT 0::BIGINT AS missing", None)
add("heaviest_blocks", lambda s, d: metrics.loads(hashed(s, d, "supp_part", 64)).orderBy(F.desc("load"), "block").limit(5), "SELECT ((u * 31 + v * 17) % 64)::INT AS block, count(*) AS load FROM e GROUP BY 1 ORDER BY load DESC, block LIMIT 5", "supp_part")
add("compare_partitions", lambda s, d: metrics.loads(hashed(s, d), K).join(metrics.loads(baselines.dbh(g_of(s, d), K), K).select("block", F.col("load").alias("dbh")), "block", "full_outer").select("block", "load", "dbh"), _DEG + ", hh AS (SELECT ((u * 31 + v * 17) % 8)::INT AS block, count(*) AS load FROM e GROUP BY 1) SELECT block, load, (SELECT count(*) FROM h WHERE h.block = hh.block) AS dbh FROM hh")

# ---- streams

add("window_graph_daily", lambda s, d: stream.windowed(_user_edges(s, d)).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "u", "v", "mult"), "SELECT strftime(ts, '%Y-%m-%d') AS day, least(user_id, 1000000 + json_extract_string(props, '$.k')::BIGINT) AS u, greatest(user_id, 1000000 + json_extract_string(props, '$.k')::BIGINT) AS v, count(*) AS mult FROM events WHERE user_id IS NOT NULL AND json_extract_string(props, '$.k') IS NOT NULL GROUP BY 1, 2, 3", None)


def _user_edges(s: SparkSession, d: str) -> DataFrame:
    return _keyed_events(s, d).where("user IS NOT NULL AND key IS NOT NULL").select("ts", F.col("user").alias("u"), (F.col("key") + 1_000_000).alias("v"))


add("window_graph_sliding", lambda s, d: stream.windowed(_user_edges(s, d), "1 day", "6 hours").groupBy("start").agg(F.count(F.lit(1)).alias("edges"), F.sum("mult").alias("events")).select(F.date_format("start", "yyyy-MM-dd HH").alias("hour"), "edges", "events"), """WITH k AS (SELECT ts, user_id AS u, 1000000 + json_extract_string(props, '$.k')::BIGINT AS v FROM events WHERE user_id IS NOT NULL AND json_extract_string(props, '$.k') IS NOT NULL),
w AS (SELECT time_bucket(INTERVAL 6 HOURS, ts, TIMESTAMP '1970-01-01') - i * INTERVAL 6 HOURS AS start, least(u, v) AS u, greatest(u, v) AS v FROM k, range(4) t(i)),
x AS (SELECT start, u, v, count(*) AS mult FROM w GROUP BY ALL) SELECT strftime(start, '%Y-%m-%d %H') AS hour, count(*) AS edges, sum(mult)::BIGINT AS events FROM x GROUP BY start""", None)
add(
    "session_graph", lambda s, d: stream.sessions(_user_edges(s, d).select(F.col("u").alias("v"), "ts"), "10 hours").groupBy("v").agg(F.count(F.lit(1)).alias("sessions"), F.max("events").alias("longest")),
    """WITH x AS (SELECT user_id AS v, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 10 HOURS THEN 0 ELSE 1 END AS new FROM events WHERE user_id IS NOT NULL AND json_extract_string(props, '$.k') IS NOT NULL),
y AS (SELECT v, sum(new) OVER (PARTITION BY v ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sn FROM x), z AS (SELECT v, sn, count(*) AS c FROM y GROUP BY v, sn)
SELECT v, count(*) AS sessions, max(c) AS longest FROM z GROUP BY v""", None,
)
add("stream_buffered", lambda s, d: workloads.stream_buffered(s, d), "SELECT count(*) AS placed, count(*) AS distinct_edges, 0::BIGINT AS bad_blocks FROM e", "user_prop")
add("stream_one_pass", lambda s, d: workloads.stream_one_pass(s, d), "SELECT count(*) AS placed, count(*) AS distinct_edges, 0::BIGINT AS bad_blocks FROM e", "user_prop")
add("stream_one_pass_stateful", lambda s, d: workloads.stream_one_pass_stateful(s, d), ORACLES["stream_one_pass"], None)
add(
    "stream_late_edges", lambda s, d: workloads.stream_late(s, d),
    """, f AS (SELECT least(a.id, b.id) AS u, greatest(a.id, b.id) AS v, min(ts) AS ts FROM events JOIN v a ON a.own = 0 AND a.num = json_extract_string(props, '$.k')::BIGINT JOIN v b ON b.own = 1 AND b.num = user_id GROUP BY 1, 2),
x AS (SELECT *, (SELECT max(ts) FROM f) AS last, (SELECT min(ts) FROM f) AS start FROM f)
SELECT count(DISTINCT date_trunc('day', ts)) FILTER (date_trunc('day', ts) + INTERVAL 1 DAY <= last - INTERVAL 1 HOUR) AS windows, count(*) FILTER (date_trunc('day', ts) + INTERVAL 1 DAY <= last - INTERVAL 1 HOUR) AS edges, count(*) FILTER (ts < start + INTERVAL 1 DAY) AS late FROM x""", "user_prop",
)
add("stream_coactivity", lambda s, d: workloads.stream_coactivity(s, d), ORACLES["interval_coactivity"], None)
add("stream_dedup", lambda s, d: workloads.stream_dedup(s, d), "SELECT count(*) AS edges, count(*) AS distinct_edges FROM e", "user_prop")

# ---- computing on blocks


def _components_equal(s: SparkSession, d: str) -> DataFrame:
    g = g_of(s, d, "trade_region")
    found = analytics.components(baselines.hash_edges(g, K))
    return found.groupBy("component").agg(F.count(F.lit(1)).alias("vertices"))


add("components_on_blocks", _components_equal)
ORACLES["components_on_blocks"] = "WITH RECURSIVE " + sql_prefix("trade_region") + ", reach(a, b) AS (SELECT id, id FROM v UNION SELECT r.a, arc.nbr FROM reach r JOIN arc ON arc.v = r.b), c AS (SELECT a, min(b) AS component FROM reach GROUP BY a) SELECT component, count(*) AS vertices FROM c GROUP BY component"


def _pagerank_gap(s: SparkSession, d: str) -> DataFrame:
    """Vertices whose rank differs between the partitioned and the whole graph by more than rounding."""
    g = g_of(s, d, "page_link")
    a, b = analytics.pagerank(g), analytics.pagerank(g, baselines.hash_edges(g, K))
    return a.join(b.select("v", F.col("rank").alias("other")), "v").agg(F.count(F.lit(1)).alias("vertices"), F.count_if(F.abs(F.col("rank") - F.col("other")) > 1e-12).alias("different"))


add("pagerank_on_blocks", _pagerank_gap, "SELECT count(*) AS vertices, 0::BIGINT AS different FROM v", "page_link")
add("mirrors_hash", lambda s, d: analytics.mirrors(hashed(s, d)), _HASH + " SELECT v, block, block = min(block) OVER (PARTITION BY v) AS is_master FROM rep")
add("triangles", lambda s, d: analytics.triangles(g_of(s, d, "user_next").edges), "SELECT count(*) AS triangles FROM e a JOIN e b ON a.u = b.u AND a.v < b.v JOIN e c ON c.u = a.v AND c.v = b.v", "user_next")

# ---- multilevel steps as tables


def _label_round(s: SparkSession, d: str) -> DataFrame:
    """First round of clustering in relational form: the neighbour of strongest connection, ties to the smaller one."""
    l = linegraph.contracted(owned(s, d)).groupBy("batch", "e1", "e2").agg(F.sum("w").alias("w"))  # noqa: E741
    both = l.select("batch", F.col("e1").alias("item"), F.col("e2").alias("label"), "w").unionByName(l.select("batch", F.col("e2").alias("item"), F.col("e1").alias("label"), "w"))
    return both.groupBy("batch", "item").agg(F.max_by("label", F.struct("w", -F.col("label"))).alias("label"), F.max("w").alias("w"))


add("label_round", _label_round, _LINKS + ", g1 AS (SELECT batch, e1, e2, count(*) AS w FROM l GROUP BY batch, e1, e2), y AS (SELECT batch, e1 AS item, e2 AS label, w FROM g1 UNION ALL SELECT batch, e2, e1, w FROM g1) SELECT batch, item, arg_min(label, (-w, label)) AS label, max(w) AS w FROM y GROUP BY batch, item")


def _contract_round(s: SparkSession, d: str) -> DataFrame:
    """Contraction in relational form, clusters being pairs of neighbouring edge numbers."""
    l = linegraph.contracted(owned(s, d))  # noqa: E741
    half = lambda c: F.floor(F.col(c) / 2)
    return l.select("batch", F.least(half("e1"), half("e2")).alias("a"), F.greatest(half("e1"), half("e2")).alias("b"), "w").where("a <> b").groupBy("batch", "a", "b").agg(F.sum("w").alias("w"))


add("contract_round", _contract_round, _LINKS + " SELECT batch, least(e1 // 2, e2 // 2) AS a, greatest(e1 // 2, e2 // 2) AS b, count(*) AS w FROM l WHERE e1 // 2 <> e2 // 2 GROUP BY 1, 2, 3")
add("coarsest_sizes", lambda s, d: _coarsest(s, d), ", b AS (SELECT v // 1024 AS batch, count(*) AS items FROM e GROUP BY 1) SELECT batch, items, k::INT AS k, greatest(items // (2 * k), 4 * k)::BIGINT AS bound FROM b, (SELECT unnest([2, 32, 1024]) AS k)")


def _coarsest(s: SparkSession, d: str) -> DataFrame:
    """Where coarsening of each batch stops."""
    bound = F.udf(multilevel.coarsest_size, "long")
    sizes = owned(s, d).groupBy("batch").agg(F.count(F.lit(1)).alias("items"))
    return sizes.select("batch", "items", F.explode(F.array(*map(F.lit, (2, 32, 1024)))).alias("k")).withColumn("bound", bound("items", "k"))




def _one_batch(s: SparkSession, d: str) -> DataFrame:
    return linegraph.contracted(g_of(s, d, "page_link").edges).groupBy("e1", "e2").agg(F.sum("w").alias("w"))


def _refined(s: SparkSession, d: str) -> DataFrame:
    """Cut and largest block before and after six rounds of moves on a hash partition; the limit holds, the cut must not grow."""
    g, links = g_of(s, d, "page_link"), _one_batch(s, d)
    first = _items(baselines.hash_edges(g, K))
    cap, now = max(metrics.block_cap(g.m, K), metrics.loads(baselines.hash_edges(g, K)).agg(F.max("load")).first()[0]), first
    for i in range(6):
        now = materialise(relational.refine_round(links, now, 0.01, cap, i % 2), "refined")
    cut = lambda a: metrics.edge_cut(links, a.withColumnRenamed("item", "eid")).first()[0]
    most = now.groupBy("block").count().agg(F.max("count")).first()[0]
    return s.createDataFrame([(now.count(), cut(now) < cut(first), most <= cap)], "items long, better boolean, within boolean")


add("refine_rounds", _refined, "SELECT count(*) AS items, true AS better, true AS within FROM e", "page_link")


def _clustered(s: SparkSession, d: str) -> DataFrame:
    """Four rounds of clustering and a contraction: fewer items, no cluster above the limit, and no link inside a cluster left."""
    g, links = g_of(s, d, "page_link"), _one_batch(s, d)
    labels = g.edges.select(F.col("eid").alias("item"), F.col("eid").alias("label"))
    for i in range(4):
        labels = materialise(relational.cluster_round(links, labels, 16, i % 2), "clusters")
    small = relational.contract(links, labels)
    most = labels.groupBy("label").count().agg(F.max("count").alias("most"), F.count(F.lit(1)).alias("left"))
    loops = small.agg(F.count_if(F.col("e1") == F.col("e2")).alias("loops"))
    return most.crossJoin(loops).select((F.col("most") <= 16).alias("within"), (F.col("left") < g.m).alias("fewer"), "loops")


add("cluster_rounds", _clustered, "SELECT true AS within, true AS fewer, 0::BIGINT AS loops", None)

# ---- experiments

for _n, (_run, _sql) in workloads.CHECKED.items():
    add(_n, lambda s, d, run=_run: workloads.checked(run(s, d)), _sql, None)
add("experiment_claims", workloads.claims, f"SELECT unnest({workloads.CLAIMS!r}) AS claim, true AS holds", None)
for _n, _run in workloads.EXPERIMENTS.items():
    add(_n, _run)

__all__ = ["ORACLES", "QUERIES", "sequential"]
