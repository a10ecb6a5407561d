"""One-pass methods said in SQL, a step per edge, for comparison block by block.

A recursive query with keys holds the method's state as rows (kind, id, val): each step reads the whole state, places the next edge of the
stream and writes the few rows that change. Kinds: 0 load of a block, 1 what a vertex remembers, 2 block of a placed item, 3 the
step, 4 a second kind of memory. The text is DuckDB's; nothing of it runs in Spark.
"""

from __future__ import annotations

from .graphs import sql_prefix

#: The cut-down graph on which methods are compared block by block, its blocks, and the vertices of a batch.
NAME, K, DELTA = "trade_nation", 8, 128
_STREAM = f""", s AS MATERIALIZED (SELECT row_number() OVER (ORDER BY v, u) - 1 AS p, eid, u, v FROM e),
c AS MATERIALIZED (SELECT count(*) AS m, (SELECT count(*) FROM v) AS n, greatest(1, (103 * count(*) + {100 * K - 1}) // {100 * K}) AS cap FROM e),
dg AS MATERIALIZED (SELECT v AS x, count(*) AS d FROM arc GROUP BY v)"""
_OUT = " SELECT s.eid, s.u, s.v, out.val::INT AS block FROM s JOIN st out ON out.kind = 2 AND out.id = s.p"


def _recursion(name: str, start: str, now: str, blocks: str, score: str, writes: str) -> str:
    """name(kind, id, val): start rows; now is the row of the step at hand, blocks the candidates with load and score's inputs; least score,
    then load, then number wins; writes lists the rows (kind, id, val) that change."""
    return f""", {name}(kind, id, val) USING KEY (kind, id) AS (
  {start}
  UNION (
  WITH now AS ({now}), cand AS ({blocks}),
  best AS (SELECT b, load FROM cand ORDER BY {score}, load, b LIMIT 1)
  SELECT w.kind, w.id, w.val FROM (SELECT unnest([{writes}]) AS w FROM now, best)))"""


def _row(kind: str, at: str, val: str) -> str:
    return f"{{'kind': {kind}, 'id': ({at})::BIGINT, 'val': ({val})::BIGINT}}"


_LOADS = f"SELECT 0 AS kind, i::BIGINT AS id, 0::BIGINT AS val FROM range({K}) t(i) UNION ALL SELECT 3, 0, 0"
_ROOM = "l.kind = 0 AND l.val < (SELECT cap FROM c)"
_STEP = "SELECT s.* FROM st a JOIN s ON a.kind = 3 AND s.p = a.val"


def _sql(body: str) -> str:
    return f"WITH RECURSIVE {sql_prefix(NAME)}{_STREAM}{body}"


def on_the_fly(every: bool = False) -> str:
    """Hits on the block that each end used last, or on all it used; less the penalty."""
    if every:
        blocks = f"SELECT l.id AS b, l.val AS load, count(r.id) AS hits FROM recurring.st l CROSS JOIN now n LEFT JOIN recurring.st r ON r.kind = 1 AND (r.id = n.u * {K} + l.id OR r.id = n.v * {K} + l.id) WHERE {_ROOM} GROUP BY ALL"
        keep = [_row("1", f"u * {K} + b", "1"), _row("1", f"v * {K} + b", "1")]
    else:
        blocks = f"SELECT l.id AS b, l.val AS load, count(r.id) AS hits FROM recurring.st l CROSS JOIN now n LEFT JOIN recurring.st r ON r.kind = 1 AND r.val = l.id AND (r.id = n.u OR r.id = n.v) WHERE {_ROOM} GROUP BY ALL"
        keep = [_row("1", "u", "b"), _row("1", "v", "b")]
    score = f"(SELECT sqrt({K}::DOUBLE) * n / pow(greatest(m, 1), 1.5) * 1.5 FROM c) * pow(load, 0.5) - hits"
    return _sql(_recursion("st", _LOADS, _STEP, blocks, score, ", ".join([_row("0", "b", "load + 1"), *keep, _row("2", "p", "b"), _row("3", "0", "p + 1")]))) + _OUT


def _greedy(share: str, start: str, step: str, name: str = "st", extra_writes: tuple[str, ...] = ()) -> str:
    """Replica and balance scores over all blocks; copies are rows of kind 1, vertex and block in one number."""
    blocks = f"""SELECT l.id AS b, l.val AS load, n.share, count(ra.id) AS ra, count(rb.id) AS rb, (SELECT max(val) FROM recurring.{name} WHERE kind = 0) AS hi, (SELECT min(val) FROM recurring.{name} WHERE kind = 0) AS lo
    FROM recurring.{name} l CROSS JOIN (SELECT now.*, {share} AS share FROM now) n LEFT JOIN recurring.{name} ra ON ra.kind = 1 AND ra.id = n.u * {K} + l.id LEFT JOIN recurring.{name} rb ON rb.kind = 1 AND rb.id = n.v * {K} + l.id
    WHERE {_ROOM} GROUP BY ALL"""
    score = "-(ra * (2 - share) + rb * (1 + share) + 1.1::DOUBLE * (hi - load) / (1e-9::DOUBLE + hi - lo)), b"
    writes = [_row("0", "b", "load + 1"), _row("1", f"u * {K} + b", "1"), _row("1", f"v * {K} + b", "1"), _row("2", "p", "b"), _row("3", "0", "q + 1"), *extra_writes]
    return _recursion(name, start, step, blocks, score, ", ".join(writes))


def hdrf(exact: bool = False) -> str:
    """Degrees seen so far (kind 4), or exact ones."""
    if exact:
        step = "SELECT s.*, s.p AS q, a1.d::DOUBLE AS da, b1.d::DOUBLE AS db FROM st a JOIN s ON a.kind = 3 AND s.p = a.val JOIN dg a1 ON a1.x = s.u JOIN dg b1 ON b1.x = s.v"
        return _sql(_greedy("da / (da + db)", _LOADS, step)) + _OUT
    step = "SELECT s.*, s.p AS q, coalesce(x.val, 0) + 1 AS da, coalesce(y.val, 0) + 1 AS db FROM st a JOIN s ON a.kind = 3 AND s.p = a.val LEFT JOIN recurring.st x ON x.kind = 4 AND x.id = s.u LEFT JOIN recurring.st y ON y.kind = 4 AND y.id = s.v"
    return _sql(_greedy("da::DOUBLE / (da + db)", _LOADS, step, extra_writes=(_row("4", "u", "da"), _row("4", "v", "db")))) + _OUT


def _clusters() -> str:
    """cl: cluster of a vertex (kind 1) and volume of a cluster (kind 4); home: cluster, volume and block of each vertex."""
    step = "SELECT s.*, x.val AS ca, y.val AS cb, i.val AS va, j.val AS vb, dx.d AS da, dy.d AS db FROM cl a JOIN s ON a.kind = 3 AND s.p = a.val JOIN recurring.cl x ON x.kind = 1 AND x.id = s.u JOIN recurring.cl y ON y.kind = 1 AND y.id = s.v JOIN recurring.cl i ON i.kind = 4 AND i.id = x.val JOIN recurring.cl j ON j.kind = 4 AND j.id = y.val JOIN dg dx ON dx.x = s.u JOIN dg dy ON dy.x = s.v"
    cap = f"(SELECT 2 * m / {K}::DOUBLE FROM c)"
    return f""", cl(kind, id, val) USING KEY (kind, id) AS (
  SELECT 1 AS kind, x AS id, x AS val FROM dg UNION ALL SELECT 4, x, d FROM dg UNION ALL SELECT 3, 0, 0
  UNION (
  WITH now AS ({step}),
  move AS (SELECT *, CASE WHEN va <= vb THEN u ELSE v END AS who, CASE WHEN va <= vb THEN ca ELSE cb END AS small, CASE WHEN va <= vb THEN cb ELSE ca END AS large,
           least(va, vb) AS vs, greatest(va, vb) AS vl, CASE WHEN va <= vb THEN da ELSE db END AS dw FROM now),
  ok AS (SELECT *, ca <> cb AND va <= {cap} AND vb <= {cap} AND vl + dw <= {cap} AS yes FROM move)
  SELECT w.kind, w.id, w.val FROM (SELECT unnest([{_row('3', '0', 'p + 1')}, {_row('CASE WHEN yes THEN 1 ELSE 5 END', 'who', 'large')}, {_row('CASE WHEN yes THEN 4 ELSE 5 END', 'small', 'vs - dw')}, {_row('CASE WHEN yes THEN 4 ELSE 5 END', 'large', 'vl + dw')}]) AS w FROM ok))),
cv AS MATERIALIZED (SELECT id AS cluster, val AS volume, row_number() OVER (ORDER BY val DESC, id) - 1 AS p FROM cl WHERE kind = 4 AND val > 0),
pk(kind, id, val) USING KEY (kind, id) AS (
  {_LOADS}
  UNION (
  WITH now AS (SELECT cv.* FROM pk a JOIN cv ON a.kind = 3 AND cv.p = a.val),
  best AS (SELECT id AS b, val AS load FROM recurring.pk WHERE kind = 0 ORDER BY val, id LIMIT 1)
  SELECT w.kind, w.id, w.val FROM (SELECT unnest([{_row('0', 'b', 'load + volume')}, {_row('2', 'cluster', 'b')}, {_row('3', '0', 'p + 1')}]) AS w FROM now, best))),
home AS MATERIALIZED (SELECT o.id AS x, o.val AS cluster, z.val AS volume, k.val AS block FROM cl o JOIN cl z ON z.kind = 4 AND z.id = o.val JOIN pk k ON k.kind = 2 AND k.id = o.val WHERE o.kind = 1),
agreed AS MATERIALIZED (SELECT p, u, v, block FROM (SELECT s.p, s.u, s.v, a.block, row_number() OVER (PARTITION BY a.block ORDER BY s.p) AS r FROM s JOIN home a ON a.x = s.u JOIN home b ON b.x = s.v AND b.block = a.block) WHERE r <= (SELECT cap FROM c)),
left_over AS MATERIALIZED (SELECT s.*, row_number() OVER (ORDER BY s.p) - 1 AS q FROM s WHERE s.p NOT IN (SELECT p FROM agreed))"""


_AGREED = f"""SELECT 0 AS kind, i::BIGINT AS id, (SELECT count(*) FROM agreed WHERE block = i) AS val FROM range({K}) t(i) UNION ALL SELECT 3, 0, 0
  UNION ALL SELECT 2, p, block FROM agreed UNION ALL SELECT DISTINCT 1, x * {K} + block, 1 FROM (SELECT u AS x, block FROM agreed UNION ALL SELECT v, block FROM agreed)"""


def two_phase(second: str = "hdrf") -> str:
    """Clusters, packing, what agrees, then the rest."""
    step = "SELECT s.*, dx.d::DOUBLE AS da, dy.d::DOUBLE AS db FROM st a JOIN left_over s ON a.kind = 3 AND s.q = a.val JOIN dg dx ON dx.x = s.u JOIN dg dy ON dy.x = s.v"
    if second == "hdrf":
        return _sql(_clusters() + _greedy("da / (da + db)", _AGREED, step)) + _OUT
    step = step.replace("SELECT s.*,", "SELECT s.*, hu.block AS bu, hv.block AS bv, hu.volume AS zu, hv.volume AS zv,").replace(" JOIN dg dx", " JOIN home hu ON hu.x = s.u JOIN home hv ON hv.x = s.v JOIN dg dx")
    blocks = f"""SELECT b, load, CASE WHEN b IN (bu, bv) THEN 0 WHEN b = (CASE WHEN da >= db THEN u ELSE v END) % {K} THEN 1 ELSE 2 END AS tier,
    greatest(CASE WHEN b = bu THEN ra * (2 - share) + rb * (1 + share) + zu / total END, CASE WHEN b = bv THEN ra * (2 - share) + rb * (1 + share) + zv / total END) AS gain
    FROM (SELECT l.id AS b, l.val AS load, n.*, count(ra.id) AS ra, count(rb.id) AS rb
    FROM recurring.st l CROSS JOIN (SELECT now.*, da / (da + db) AS share, greatest(1, zu + zv)::DOUBLE AS total FROM now) n LEFT JOIN recurring.st ra ON ra.kind = 1 AND ra.id = n.u * {K} + l.id LEFT JOIN recurring.st rb ON rb.kind = 1 AND rb.id = n.v * {K} + l.id
    WHERE {_ROOM} GROUP BY ALL)"""
    score = "tier, CASE WHEN tier = 0 THEN -gain ELSE 0 END, CASE WHEN tier = 0 THEN b ELSE 0 END"
    writes = [_row("0", "b", "load + 1"), _row("1", f"u * {K} + b", "1"), _row("1", f"v * {K} + b", "1"), _row("2", "p", "b"), _row("3", "0", "q + 1")]
    return _sql(_clusters() + _recursion("st", _AGREED, step, blocks, score, ", ".join(writes))) + _OUT


def fennel_vertices() -> str:
    """(v, block) by a Fennel pass over the vertices."""
    step = "SELECT v.id AS x FROM st a JOIN v ON a.kind = 3 AND v.id = a.val"
    room = f"l.kind = 0 AND l.val < (SELECT greatest(1, ceil((1 + 0.03::DOUBLE) * n / {K})) FROM c)"
    blocks = f"SELECT l.id AS b, l.val AS load, count(r.id) AS inside FROM recurring.st l CROSS JOIN now n LEFT JOIN (SELECT r.id, r.val FROM now JOIN arc ON arc.v = now.x JOIN recurring.st r ON r.kind = 2 AND r.id = arc.nbr) r ON r.val = l.id WHERE {room} GROUP BY ALL"
    score = f"-(inside - (SELECT sqrt({K}::DOUBLE) * m / pow(n, 1.5) * 1.5 FROM c) * pow(load, 0.5))"
    return _sql(_recursion("st", _LOADS, step, blocks, score, ", ".join([_row("0", "b", "load + 1"), _row("2", "x", "b"), _row("3", "0", "x + 1")]))) + " SELECT id AS v, val::INT AS block FROM st WHERE kind = 2"


def buffered(mode: str = "minimal", alpha: str = "batch") -> str:
    """The buffered method with clustering and refinement off: every batch's edges by number, each beside its neighbours on the paths of its
    batch and the blocks that its earlier end met in earlier batches."""
    met = {
        "none": "SELECT NULL::BIGINT AS eid, NULL::BIGINT AS other WHERE false",
        "minimal": "SELECT o.eid, arg_max(w.eid, w.batch * 4294967296 + w.eid) AS other FROM own o JOIN arcs w ON w.x = o.u AND w.batch < o.batch WHERE o.past GROUP BY o.eid",
        "maximal": "SELECT o.eid, w.eid AS other FROM own o JOIN arcs w ON w.x = o.u AND w.batch < o.batch WHERE o.past",
    }[mode]
    a = {
        "batch": f"sqrt({K}::DOUBLE) * links / pow(items, 1.5)",
        "static": f"(SELECT sqrt({K}::DOUBLE) * (2.0::DOUBLE * m) / pow(m, 1.5) FROM c)",
    }[alpha]
    body = f""", own AS (SELECT eid, u, v, v // {DELTA} AS batch, u // {DELTA} < v // {DELTA} AS past FROM e),
arcs AS (SELECT u AS x, eid, batch FROM own UNION ALL SELECT v, eid, batch FROM own),
path AS (SELECT x, eid, batch, lag(eid) OVER (PARTITION BY batch, x ORDER BY eid) AS other FROM arcs),
near AS MATERIALIZED (SELECT eid, other, 0 AS fixed FROM path WHERE other IS NOT NULL UNION ALL SELECT eid, other, 1 FROM ({met})),
sizes AS (SELECT batch, count(DISTINCT eid) AS items, count(other) AS links FROM path GROUP BY batch),
ord AS MATERIALIZED (SELECT own.*, {a} * 1.5 AS ag, row_number() OVER (ORDER BY own.batch, own.eid) - 1 AS q FROM own JOIN sizes USING (batch))"""
    step = "SELECT o.* FROM st a JOIN ord o ON a.kind = 3 AND o.q = a.val"
    inside = "(SELECT r.val AS b, count(*) FILTER (fixed = 0) + least(1, count(*) FILTER (fixed = 1)) AS w FROM now JOIN near ON near.eid = now.eid JOIN recurring.st r ON r.kind = 2 AND r.id = near.other GROUP BY r.val)"
    blocks = f"SELECT l.id AS b, l.val AS load, n.ag, coalesce(r.w, 0) AS inside FROM recurring.st l CROSS JOIN now n LEFT JOIN {inside} r ON r.b = l.id WHERE {_ROOM}"
    writes = ", ".join([_row("0", "b", "load + 1"), _row("2", "eid", "b"), _row("3", "0", "q + 1")])
    return _sql(body + _recursion("st", _LOADS, step, blocks, "-(inside - ag * pow(load, 0.5))", writes)) + " SELECT o.eid, o.u, o.v, out.val::INT AS block FROM own o JOIN st out ON out.kind = 2 AND out.id = o.eid"
