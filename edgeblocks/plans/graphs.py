"""Graphs on the given tables: how each one's pairs are made, in DataFrame operations and in SQL."""

from __future__ import annotations

from functools import cache

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.canonical import Graph, build, dense_ids
from ..sources.tables import table



def _pairs(df: DataFrame, a_kind: int, a, b_kind: int, b) -> DataFrame:
    """Typed pairs; an end is a whole number or a string."""

    def end(s: str, kind: int, col) -> list:
        kind_of = dict(df.select(col.alias("x")).dtypes)["x"]
        text = kind_of == "string"
        return [F.lit(kind).alias(f"{s}_kind"), (F.lit(None).cast("long") if text else col.cast("long")).alias(f"{s}_num"), (col if text else F.lit(None).cast("string")).alias(f"{s}_str")]

    return df.select(*end("a", a_kind, a), *end("b", b_kind, b))


def _lines(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")


def _trade(spark: SparkSession, d: str) -> DataFrame:
    """Supplier and customer of each line with their nations and regions."""
    orders = table(spark, d, "orders").select("o_orderkey", "o_custkey")
    nation = table(spark, d, "nation").select("n_nationkey", "n_regionkey")
    supplier = table(spark, d, "supplier").join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "s_nationkey", F.col("n_regionkey").alias("s_region"))
    customer = table(spark, d, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "c_nationkey", F.col("n_regionkey").alias("c_region"))
    pairs = _lines(spark, d).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select("l_suppkey", "o_custkey").distinct()
    return pairs.join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))


def _with_orders(spark, d):
    return _lines(spark, d).join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))


def _copurchase(spark, d):
    a = _lines(spark, d).select("l_orderkey", F.col("l_partkey").alias("p")).distinct()
    b = a.select("l_orderkey", F.col("p").alias("q"))
    return a.join(b, "l_orderkey").where("p < q").select("p", "q").distinct()


def _geo(spark, d):
    c, s, n = (table(spark, d, t) for t in ("customer", "supplier", "nation"))
    parts = [_pairs(c, 3, F.col("c_custkey"), 1, F.col("c_nationkey")), _pairs(s, 2, F.col("s_suppkey"), 1, F.col("s_nationkey")), _pairs(n, 1, F.col("n_nationkey"), 0, F.col("n_regionkey"))]
    return parts[0].union(parts[1]).union(parts[2])


def user_steps(spark: SparkSession, d: str) -> DataFrame:
    """Users of consecutive events by (ts, event_id): neighbours in a dense order meet by an equi-join on rank."""
    ranked = dense_ids(table(spark, d, "events").select("ts", "event_id", "user_id"), ["ts", "event_id"], "r")
    return ranked.select(F.col("user_id").alias("p"), "r").join(ranked.select(F.col("user_id").alias("q"), (F.col("r") - 1).alias("r")), "r").select("p", "q")


def _links(spark, d):
    return table(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))


def _tokens(spark, d):
    return table(spark, d, "documents").select("doc_id", F.explode(F.split("text", r"[ \t\n\r\f\x0B]+")).alias("token")).where("token <> ''").distinct()


def _turns(spark, d):
    t = table(spark, d, "conversations").select("conv_id", "turn")
    after = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    steps = t.withColumn("next", after).where("next IS NOT NULL")
    return steps.select((F.col("conv_id") * 1_000_000 + F.col("turn")).alias("p"), (F.col("conv_id") * 1_000_000 + F.col("next")).alias("q"))


#: Vectors that are compared with a pack at once.
SLICE = 256


def _largest(r, k: int):
    """Positions of the k largest, largest first, ties to the smaller position."""
    import numpy as np

    at = np.arange(len(r))
    if len(r) > k:
        at = np.flatnonzero(r >= np.partition(r, len(r) - k)[len(r) - k])
    return at[np.lexsort((at, -r[at]))[:k]]


def _knn(spark: SparkSession, d: str, k: int = 10) -> DataFrame:
    """The k nearest by cosine, ties by id: blocks of all vectors against a bounded broadcast of them, pack by pack."""
    import numpy as np
    import pyarrow as pa

    rows = table(spark, d, "embeddings").select("vec_id", "embedding").where("embedding IS NOT NULL")
    pack, total = 20_000, rows.count()
    parts = []
    for p in range(max(1, -(-total // pack))):
        got = rows.where(F.pmod(F.xxhash64("vec_id"), F.lit(max(1, -(-total // pack)))) == p).toArrow().combine_chunks()
        if not got.num_rows:
            continue
        got = got.sort_by("vec_id")
        ids = got.column("vec_id").to_numpy()
        x = np.concatenate([np.array(got.column("embedding").slice(lo, SLICE).to_pylist(), float) for lo in range(0, len(ids), SLICE)])
        sent = spark.sparkContext.broadcast((ids, x / np.linalg.norm(x, axis=1, keepdims=True)))

        def near(it, sent=sent):
            ids, x = sent.value
            for b in it:
                for part in (b.slice(lo, SLICE) for lo in range(0, b.num_rows, SLICE)):
                    own = part.column("vec_id").to_numpy()
                    q = np.array(part.column("embedding").to_pylist(), float)
                    s = np.round(q / np.linalg.norm(q, axis=1, keepdims=True) @ x.T, 12)
                    for row, lo, hi in zip(s, np.searchsorted(ids, own), np.searchsorted(ids, own, "right")):
                        row[lo:hi] = -9
                    top = np.stack([_largest(r, k) for r in s])
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(own, top.shape[1])), pa.array(ids[top].ravel()), pa.array(np.take_along_axis(s, top, 1).ravel())], names=["p", "q", "s"])

        parts.append(rows.mapInArrow(near, "p bigint, q bigint, s double"))
    every = parts[0] if parts else spark.createDataFrame([], "p long, q long, s double")
    for more in parts[1:]:
        every = every.unionByName(more)
    best = Window.partitionBy("p").orderBy(F.desc("s"), "q")
    return every.withColumn("r", F.row_number().over(best)).where(F.col("r") <= k).select("p", "q")


def pairs_of(spark: SparkSession, d: str, name: str) -> DataFrame:
    c = F.col
    make = {
        "part_order": lambda: _pairs(_lines(spark, d), 0, c("l_partkey"), 1, c("l_orderkey")),
        "supp_part": lambda: _pairs(_lines(spark, d), 0, c("l_suppkey"), 1, c("l_partkey")),
        "supp_cust": lambda: _pairs(_with_orders(spark, d), 0, c("l_suppkey"), 1, c("o_custkey")),
        "cust_part": lambda: _pairs(_with_orders(spark, d), 0, c("o_custkey"), 1, c("l_partkey")),
        "copurchase": lambda: _pairs(_copurchase(spark, d), 0, c("p"), 0, c("q")),
        "trade_region": lambda: _pairs(_trade(spark, d).where("s_region = c_region"), 0, c("l_suppkey"), 1, c("o_custkey")),
        "trade_nation": lambda: _pairs(_trade(spark, d).where("s_nationkey = c_nationkey"), 0, c("l_suppkey"), 1, c("o_custkey")),
        "geo": lambda: _geo(spark, d),
        "user_prop": lambda: _pairs(table(spark, d, "events").select(F.get_json_object("props", "$.k").cast("long").alias("k"), "user_id"), 0, c("k"), 1, c("user_id")),
        "user_next": lambda: _pairs(user_steps(spark, d), 0, c("p"), 0, c("q")),
        "page_link": lambda: _pairs(_links(spark, d), 0, c("page_id"), 1, c("href")),
        "doc_token": lambda: _pairs(_tokens(spark, d), 0, c("doc_id"), 1, c("token")),
        "turn_path": lambda: _pairs(_turns(spark, d), 0, c("p"), 0, c("q")),
        "knn": lambda: _pairs(_knn(spark, d), 0, c("p"), 0, c("q")),
    }
    return make[name]()


NAMES = "part_order supp_part supp_cust cust_part copurchase trade_region trade_nation geo user_prop user_next page_link doc_token turn_path knn".split()
#: Our sets in the place of the three disjoint ones.
TUNING, TEST, HUGE = ["part_order", "geo", "turn_path"], ["trade_region", "trade_nation", "supp_part", "supp_cust", "copurchase", "cust_part", "user_prop", "user_next", "page_link", "knn"], ["doc_token", "copurchase"]

_built: dict[tuple, Graph] = {}


def first_seen(spark: SparkSession, d: str) -> DataFrame:
    """(kind, num, str, at): when each property and each user of user_prop occurs first."""
    e = table(spark, d, "events").select("ts", F.get_json_object("props", "$.k").cast("long").alias("k"), "user_id")
    sides = [e.groupBy(F.col(c).alias("num")).agg(F.min("ts").alias("at")).select(F.lit(kind).alias("kind"), "num", F.lit(None).cast("string").alias("str"), "at") for kind, c in ((0, "k"), (1, "user_id"))]
    return sides[0].union(sides[1]).where("num IS NOT NULL")


def graph(spark: SparkSession, sf_dir: str, name: str, id_order: str = "small_side_first") -> Graph:
    """The canonical graph; id_order event_time is for user_prop; order_iso is part_order with the orders that have no line. Built once per session and folder."""
    key = (spark.sparkContext.applicationId, sf_dir, name, id_order)
    if key not in _built:
        base, lonely = name, None
        if name == "order_iso":
            base = "part_order"
            lonely = table(spark, sf_dir, "orders").select(F.lit(1).alias("kind"), F.col("o_orderkey").alias("num"), F.lit(None).cast("string").alias("str"))
        _built[key] = build(pairs_of(spark, sf_dir, base), name, id_order, lonely, first_seen(spark, sf_dir) if id_order == "event_time" else None)
    return _built[key]


_SQL_PAIRS = {
    "part_order": "SELECT 0 ak, l_partkey an, NULL::VARCHAR a_s, 1 bk, l_orderkey bn, NULL::VARCHAR b_s FROM lineitem",
    "supp_part": "SELECT 0 ak, l_suppkey an, NULL::VARCHAR a_s, 1 bk, l_partkey bn, NULL::VARCHAR b_s FROM lineitem",
    "supp_cust": "SELECT 0 ak, l_suppkey an, NULL::VARCHAR a_s, 1 bk, o_custkey bn, NULL::VARCHAR b_s FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "cust_part": "SELECT 0 ak, o_custkey an, NULL::VARCHAR a_s, 1 bk, l_partkey bn, NULL::VARCHAR b_s FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "copurchase": "SELECT 0 ak, a.l_partkey an, NULL::VARCHAR a_s, 0 bk, b.l_partkey bn, NULL::VARCHAR b_s FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey",
    "trade_region": "SELECT 0 ak, l_suppkey an, NULL::VARCHAR a_s, 1 bk, o_custkey bn, NULL::VARCHAR b_s FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey JOIN nation x ON x.n_nationkey = s_nationkey JOIN nation y ON y.n_nationkey = c_nationkey WHERE x.n_regionkey = y.n_regionkey",
    "trade_nation": "SELECT 0 ak, l_suppkey an, NULL::VARCHAR a_s, 1 bk, o_custkey bn, NULL::VARCHAR b_s FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey WHERE s_nationkey = c_nationkey",
    "geo": "SELECT 3 ak, c_custkey::BIGINT an, NULL::VARCHAR a_s, 1 bk, c_nationkey::BIGINT bn, NULL::VARCHAR b_s FROM customer UNION ALL SELECT 2, s_suppkey, NULL, 1, s_nationkey, NULL FROM supplier UNION ALL SELECT 1, n_nationkey, NULL, 0, n_regionkey, NULL FROM nation",
    "user_prop": "SELECT 0 ak, json_extract_string(props, '$.k')::BIGINT an, NULL::VARCHAR a_s, 1 bk, user_id bn, NULL::VARCHAR b_s FROM events",
    "user_next": "SELECT 0 ak, user_id an, NULL::VARCHAR a_s, 0 bk, lead(user_id) OVER (ORDER BY ts, event_id) bn, NULL::VARCHAR b_s FROM events",
    "page_link": "SELECT 0 ak, page_id an, NULL::VARCHAR a_s, 1 bk, NULL::BIGINT bn, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) b_s FROM pages",
    "doc_token": "SELECT 0 ak, doc_id an, NULL::VARCHAR a_s, 1 bk, NULL::BIGINT bn, tok b_s FROM (SELECT doc_id, unnest(regexp_split_to_array(text, '[ \\t\\n\\r\\f\\x0B]+')) tok FROM documents) WHERE tok <> ''",
    "knn": """SELECT 0 ak, p an, NULL::VARCHAR a_s, 0 bk, q bn, NULL::VARCHAR b_s FROM (SELECT a.vec_id AS p, b.vec_id AS q,
  row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.x, b.x), 12) DESC, b.vec_id) AS r
  FROM (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings) a JOIN (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings) b ON a.vec_id <> b.vec_id) WHERE r <= 10""",
    "turn_path": "SELECT 0 ak, conv_id * 1000000 + turn an, NULL::VARCHAR a_s, 0 bk, conv_id * 1000000 + lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) bn, NULL::VARCHAR b_s FROM conversations",
}


@cache
def sql_prefix(name: str) -> str:
    """CTEs v (id, kind, num, str) and e (eid, u, v) of a graph, without the leading WITH."""
    lonely = " UNION SELECT 1, o_orderkey, NULL::VARCHAR FROM orders" if name == "order_iso" else ""
    pairs = _SQL_PAIRS["part_order" if name == "order_iso" else name]
    return f"""p0 AS (SELECT DISTINCT * FROM ({pairs}) WHERE (an IS NOT NULL OR a_s IS NOT NULL) AND (bn IS NOT NULL OR b_s IS NOT NULL)),
p AS (SELECT * FROM p0 WHERE ak <> bk OR an IS DISTINCT FROM bn OR a_s IS DISTINCT FROM b_s),
k0 AS (SELECT ak kind, an num, a_s str FROM p UNION SELECT bk, bn, b_s FROM p{lonely}),
kr AS (SELECT kind, row_number() OVER (ORDER BY count(*), kind) - 1 r FROM k0 GROUP BY kind),
v AS (SELECT row_number() OVER (ORDER BY r, num, str) - 1 AS id, r AS kind, k0.kind AS own, num, str FROM k0 JOIN kr USING (kind)),
e0 AS (SELECT DISTINCT least(a.id, b.id) u, greatest(a.id, b.id) v FROM p
  JOIN v a ON a.own = ak AND a.num IS NOT DISTINCT FROM an AND a.str IS NOT DISTINCT FROM a_s
  JOIN v b ON b.own = bk AND b.num IS NOT DISTINCT FROM bn AND b.str IS NOT DISTINCT FROM b_s WHERE a.id <> b.id),
e AS (SELECT row_number() OVER (ORDER BY u, v) - 1 AS eid, u, v FROM e0),
arc AS (SELECT u AS v, v AS nbr, eid FROM e UNION ALL SELECT v, u, eid FROM e)"""
