"""Secret scan with corpus-wide ownership frequency (DataFrame operations only).

Patterns propose spans; the hash of each proposed value is then counted over the whole corpus by distinct repository
(document) and distinct owner (source). A value that many owners hold is a copied example, one that a single owner holds looks
live. Pattern spans always stay; the count decides about the generic mixed-character tokens, which are added only where they
belong to few owners. Redaction spares only what is copied widely: by many owners and many repositories together.

Defined cases: null text is empty; null ids and owners count as one value each; repeated rows are counted once as a
repository; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..storage import materialise
from .columns import unused

#: Fixed patterns: kind, pattern, group that must be long enough, its least length.
BASE = [
    ("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    ("access", r"AKIA[A-Z0-9]+", 0, 16),
    ("hex", r"[0-9a-f]+", 0, 32),
]
#: The same two kinds with the length inside: a greedy run that is too short holds no longer one.
QUICK = {"access": r"AKIA[A-Z0-9]{12,}", "hex": r"[0-9a-f]{32,}"}
#: What the method adds: long tokens with a digit, a capital and a small letter.
GENERIC = ("generic", r"[A-Za-z0-9+/_-]{20,}")
KINDS = ["assign", "access", "hex", "generic"]
#: A value is owner-specific if at most so many owners hold it.
MAX_OWNERS = 1
#: Redaction spares a value held by more owners and also by more repositories than these.
SPARED_OWNERS, SPARED_REPOS = 3, 10


def _found(text: Column, kind: str) -> Column:
    """array<struct<start, kind, end, value>> of one kind, in code points; empty where the pattern is absent.

    The pieces between matches give the offsets: start of match i is the length of all pieces and matches before it.
    """
    if kind == "generic":
        pattern, group, least = GENERIC[1], 0, 20
    else:
        _, pattern, group, least = next(x for x in BASE if x[0] == kind)
        pattern = QUICK.get(kind, pattern)
    pieces = F.split(text, pattern, -1)
    whole = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    value = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else whole
    steps = F.arrays_zip(F.transform(F.slice(pieces, 1, F.size(whole)), F.length).alias("gap"), F.transform(whole, F.length).alias("long"), value.alias("value"))
    none = F.array().cast("array<struct<start:int,kind:int,end:int,value:string>>")

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + x["gap"]
        one = F.struct(start.alias("start"), F.lit(KINDS.index(kind)).alias("kind"), (start + x["long"]).alias("end"), x["value"].alias("value"))
        return F.struct((start + x["long"]).alias("at"), F.concat(acc["out"], F.array(one)).alias("out"))

    begin = F.struct(F.lit(0).alias("at"), none.alias("out"))
    spans = F.aggregate(steps, begin, step)["out"]
    spans = F.filter(spans, lambda s: F.length(s["value"]) >= least)
    if kind == "generic":
        spans = F.filter(spans, lambda s: s["value"].rlike("[0-9]") & s["value"].rlike("[A-Z]") & s["value"].rlike("[a-z]"))
    return F.when(text.rlike(pattern), spans).otherwise(none)


def candidates(text: Column) -> tuple[Column, Column]:
    """Pattern spans and generic ones, each an array of structs."""
    text = F.coalesce(text, F.lit(""))
    return F.concat(*(_found(text, k) for k in KINDS[:3])), _found(text, "generic")


def scanned(docs: DataFrame, repo: str = "doc_id", owner: str = "source") -> DataFrame:
    """One row per document: its row number, repository, owner and spans with the hash of each value; no text."""
    base, generic = candidates(F.col("text"))
    rows = docs.select(F.col(repo).alias("repo"), F.col(owner).alias("owner"), base.alias("base"), generic.alias("generic"), F.xxhash64("text").alias("text_hash"))
    touches = lambda g: F.exists("base", lambda b: (b["start"] < g["end"]) & (g["start"] < b["end"]))
    spans = F.concat("base", F.filter("generic", lambda g: ~touches(g)))
    hashed = F.transform(F.array_sort(spans), lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end"), F.sha2(s["value"], 256).alias("value")))
    return materialise(rows.select(F.monotonically_increasing_id().alias("row"), "repo", "owner", "text_hash", hashed.alias("spans")), "secret-spans")


def ownership(scan: DataFrame) -> DataFrame:
    """value, repos, owners over the whole corpus.

    Distinct (value, owner, repository) first, then two sums: each step combines before it shuffles, so a value that a
    third of all documents hold reaches no task as more than one row per task and owner.
    """
    held = scan.where(F.size("spans") > 0).select("owner", "repo", F.explode(F.array_distinct(F.transform("spans", lambda s: s["value"]))).alias("value"))
    per_owner = held.groupBy("value", "owner", "repo").agg(F.lit(1).alias("one")).groupBy("value", "owner").agg(F.count("one").alias("repos"))
    return per_owner.groupBy("value").agg(F.sum("repos").alias("repos"), F.count(F.lit(1)).alias("owners"))


def judged(scan: DataFrame, max_owners: int = MAX_OWNERS) -> DataFrame:
    """scan with each span's repos, owners and live flag; rows without spans pass by the joins."""
    some = scan.where(F.size("spans") > 0).select("row", F.explode("spans").alias("s"))
    counts = ownership(scan)
    joined = some.join(counts, some["s"]["value"] == counts["value"], "left")
    one = F.struct(F.col("s.start").alias("start"), F.col("s.kind").alias("kind"), F.col("s.end").alias("end"), F.col("repos"), F.col("owners"), (F.col("owners") <= max_owners).alias("live"))
    per_row = joined.groupBy("row").agg(F.array_sort(F.collect_list(one)).alias("judged"))
    out = scan.join(per_row, "row", "left")
    empty = F.array().cast(per_row.schema["judged"].dataType)
    return out.withColumn("judged", F.coalesce("judged", empty))


def _text_of(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def scan_secrets(docs: DataFrame, max_owners: int = MAX_OWNERS) -> DataFrame:
    """doc_id, counts by kind, digest of the pattern spans, all spans, and how many of them look live or copied."""
    rows = judged(scanned(docs), max_owners)
    base = F.filter("judged", lambda s: s["kind"] < 3)
    kept = F.filter("judged", lambda s: (s["kind"] < 3) | s["live"])
    count = lambda k: F.size(F.filter("judged", lambda s: s["kind"] == k)).cast("long")
    return rows.select(
        F.col("repo").alias("doc_id"), count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"),
        F.sha2(_text_of(base), 256).alias("base_sha256"), _text_of(kept).alias("spans"),
        F.size(F.filter("judged", lambda s: s["live"])).cast("long").alias("n_live"), F.size(F.filter("judged", lambda s: ~s["live"])).cast("long").alias("n_copied"),
    )


def _cut(text: Column, spans: Column, mark: str) -> Column:
    """text with every span replaced; overlapping spans merge into one mark."""
    begin = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(acc: Column, s: Column) -> Column:
        gap = F.substring(text, acc["at"] + 1, s["start"] - acc["at"])
        fresh = F.struct(s["end"].alias("at"), F.concat(acc["out"], gap, F.lit(mark)).alias("out"))
        return F.when(s["start"] >= acc["at"], fresh).otherwise(F.struct(F.greatest(acc["at"], s["end"]).alias("at"), acc["out"].alias("out")))

    done = F.aggregate(spans, begin, step)
    return F.concat(done["out"], F.substring(text, done["at"] + 1, F.length(text)))


def redact(docs: DataFrame, max_owners: int = SPARED_OWNERS, max_repos: int = SPARED_REPOS, mark: str = "<secret>") -> DataFrame:
    """docs with secrets that aren't copied widely replaced in the text; n_chars follows it if there is such a column.

    Only documents that hold a span are shuffled; the others pass by untouched.
    """
    base, generic = candidates(F.col("text"))
    flagged = F.coalesce((F.size(base) + F.size(generic)) > 0, F.lit(False))
    key, hashed, spans = unused(docs, "key", "hashed", "spans")
    rows = judged(scanned(docs))
    rare = F.filter("judged", lambda s: (s["owners"] <= max_owners) | (s["repos"] <= max_repos))
    live = rows.select(F.col("repo").alias(key), F.col("text_hash").alias(hashed), rare.alias(spans)).where(F.size(spans) > 0).dropDuplicates([key, hashed])
    hit = docs.where(flagged)
    hit = hit.join(live, hit["doc_id"].eqNullSafe(F.col(key)) & (F.xxhash64(hit["text"]) == F.col(hashed)), "left")
    hit = hit.withColumn("text", F.when(F.col(spans).isNotNull(), _cut(F.col("text"), F.col(spans), mark)).otherwise(F.col("text")))
    if "n_chars" in docs.columns:
        hit = hit.withColumn("n_chars", F.when(F.col(spans).isNotNull(), F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return docs.where(~flagged).unionByName(hit.select(*docs.columns))


def op8_secrets(spark, sf_dir: str) -> DataFrame:
    return scan_secrets(spark.read.parquet(f"{sf_dir}/documents.parquet"))


#: The same in SQL: pieces between matches give the offsets, as above.
SQL = r"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, source, coalesce(text, '') AS t FROM documents),
k(kind, name, pattern, grp, least) AS (VALUES
  (0, 'assign', '((?i:password|passwd|secret|token|api_?key))["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)', 2, 8),
  (1, 'access', 'AKIA[A-Z0-9]+', 0, 16), (2, 'hex', '[0-9a-f]+', 0, 32), (3, 'generic', '[A-Za-z0-9+/_-]{20,}', 0, 20)),
c AS (
  SELECT rid, 0 AS kind, regexp_extract_all(t, (SELECT pattern FROM k WHERE kind = 0)) AS ms, regexp_extract_all(t, (SELECT pattern FROM k WHERE kind = 0), 2) AS vs, string_split_regex(t, (SELECT pattern FROM k WHERE kind = 0)) AS ps FROM d
  UNION ALL SELECT rid, 1, regexp_extract_all(t, 'AKIA[A-Z0-9]+'), regexp_extract_all(t, 'AKIA[A-Z0-9]+'), string_split_regex(t, 'AKIA[A-Z0-9]+') FROM d
  UNION ALL SELECT rid, 2, regexp_extract_all(t, '[0-9a-f]{32,}'), regexp_extract_all(t, '[0-9a-f]{32,}'), string_split_regex(t, '[0-9a-f]{32,}') FROM d
  UNION ALL SELECT rid, 3, regexp_extract_all(t, '[A-Za-z0-9+/_-]{20,}'), regexp_extract_all(t, '[A-Za-z0-9+/_-]{20,}'), string_split_regex(t, '[A-Za-z0-9+/_-]{20,}') FROM d),
u AS (SELECT rid, kind, i, ms[i] AS m, vs[i] AS v, ps[i] AS p FROM (SELECT *, unnest(range(1, len(ms) + 1)) AS i FROM c)),
o AS (SELECT rid, kind, v, m, sum(length(p) + length(m)) OVER (PARTITION BY rid, kind ORDER BY i ROWS UNBOUNDED PRECEDING) AS stop FROM u),
b AS (SELECT rid, kind, v, (stop - length(m))::BIGINT AS start, stop::BIGINT AS stop FROM o JOIN k USING (kind) WHERE length(v) >= least
  AND (kind < 3 OR (regexp_matches(v, '[0-9]') AND regexp_matches(v, '[A-Z]') AND regexp_matches(v, '[a-z]')))),
s AS (SELECT * FROM b WHERE kind < 3 OR NOT EXISTS (SELECT 1 FROM b x WHERE x.rid = b.rid AND x.kind < 3 AND x.start < b.stop AND b.start < x.stop)),
w AS (SELECT v, count(DISTINCT coalesce(source, chr(1))) AS owners FROM s JOIN d USING (rid) GROUP BY v),
j AS (SELECT s.rid, s.kind, s.start, s.stop, name, owners FROM s JOIN w USING (v) JOIN k USING (kind)),
a AS (SELECT rid, count(*) FILTER (kind = 0) AS n_assign, count(*) FILTER (kind = 1) AS n_access, count(*) FILTER (kind = 2) AS n_hex,
  string_agg(name || ':' || start || ':' || stop, ',' ORDER BY start, kind) FILTER (kind < 3) AS base,
  string_agg(name || ':' || start || ':' || stop, ',' ORDER BY start, kind) FILTER (kind < 3 OR owners <= 1) AS spans,
  count(*) FILTER (owners <= 1) AS n_live, count(*) FILTER (owners > 1) AS n_copied FROM j GROUP BY rid)
SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(base, '')) AS base_sha256,
  coalesce(spans, '') AS spans, coalesce(n_live, 0) AS n_live, coalesce(n_copied, 0) AS n_copied FROM d LEFT JOIN a USING (rid)
"""
