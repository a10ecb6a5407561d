"""Mix sources to target weights with hash-threshold histograms (DataFrame operations only).

Every document gets a 48-bit hash of its id. Word counts are summed per source and hash bucket; the bucket in which a
source's budget runs out is split again by the next hash bits, level by level, until a single hash value is left. A document
is taken when its hash lies below its source's threshold, so nothing is sorted and reruns agree.

Defined cases: null text counts 0 words; a null source is a source of its own, last in order; documents of equal id share
their hash and so their fate; no document is taken more often than the cap says, those without words included; an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..storage import materialise
from .columns import unused

WORD = r"[^\x20\x09-\x0D]+"
#: Hash bits of a level's bucket number, and the levels: 48 bits in all.
BITS, LEVELS = 12, 4
#: Sources up to which the thresholds are broadcast (a row of about 60 bytes each); more go through a shuffled join.
BROADCAST_SOURCES = 50_000


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def id_hash(doc_id: Column) -> Column:
    """48 bits from the md5 of the id's decimal form; a null id hashes as the empty string."""
    return F.conv(F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.lit(""))), 1, 12), 16, 10).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: int = 3) -> DataFrame:
    """(source, source_size) to (…, target): shares of all words by weight, none above cap times its source.

    The level at which weights share the words is found in one pass over sources ordered by cap over weight: it is the
    first at which the next source would not be capped. One row per source passes a single task, never a document.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    by_ratio = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*map(F.lit, weights)), ((F.row_number().over(by_name) - 1) % len(weights) + 1).cast("int"))
    ranked = sizes.withColumn("w", weight.cast("long")).withColumn("ceiling", F.col("source_size") * cap)
    ranked = ranked.withColumn("ratio", F.col("ceiling").cast("double") / F.col("w"))
    left = F.sum("source_size").over(Window.partitionBy()) - (F.sum("ceiling").over(by_ratio.rowsBetween(Window.unboundedPreceding, 0)) - F.col("ceiling"))
    heavy = F.sum("w").over(by_ratio.rowsBetween(0, Window.unboundedFollowing))
    ranked = ranked.withColumn("level", left.cast("double") / heavy)
    level = F.min_by("level", F.when(F.col("ratio") >= F.col("level"), F.col("ratio"))).over(Window.partitionBy())
    ranked = ranked.withColumn("share", level)
    return ranked.select("source", "source_size", F.least(F.col("ceiling").cast("double"), F.col("share") * F.col("w")).alias("target"))


def _narrow(sized: DataFrame, marks: DataFrame, level: int) -> DataFrame:
    """One level of refinement: only documents of each source's boundary bucket are counted again."""
    shift = BITS * (LEVELS - level)
    inside = sized.join(marks, sized["source"].eqNullSafe(marks["m_source"]))
    if level > 1:
        inside = inside.where(F.shiftright("h", shift + BITS) == F.col("m_prefix"))
    counts = inside.groupBy("m_source", F.shiftright("h", shift).alias("prefix"), "m_rest").agg(F.sum("size").alias("words"))
    upto = F.sum("words").over(Window.partitionBy("m_source").orderBy("prefix").rowsBetween(Window.unboundedPreceding, 0))
    edge = counts.withColumn("upto", upto).where((F.col("upto") > F.col("m_rest")) & (F.col("upto") - F.col("words") <= F.col("m_rest")))
    return edge.select("m_source", F.col("prefix").alias("m_prefix"), (F.col("m_rest") - (F.col("upto") - F.col("words"))).alias("m_rest"), F.col("words").alias("m_words"))


def _sized(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), id_hash(F.col("doc_id")).alias("h"))


def bounds(sized: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: int = 3) -> tuple[DataFrame, bool]:
    """(b_source, source_size, target, rounds, bound) of each source, and whether they are few enough for a broadcast.

    Every document is taken rounds times, and once more if its hash is below the bound.
    """
    targets = materialise(source_targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, cap), "mix-targets")
    few = targets.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    small = F.broadcast if few else lambda df: df
    size = F.col("source_size").cast("double")
    plan = targets.withColumn("rounds", F.when(F.col("source_size") > 0, F.floor(F.col("target") / size)).otherwise(0).cast("long"))
    marks = plan.select(F.col("source").alias("m_source"), F.lit(0).cast("long").alias("m_prefix"), (F.col("target") - F.col("rounds") * size).alias("m_rest"), F.col("source_size").alias("m_words"))
    for level in range(1, LEVELS + 1):
        marks = _narrow(sized, small(marks), level)
    # a hash value at the very edge is taken whole if that ends nearer to the budget
    found = plan.join(marks, plan["source"].eqNullSafe(marks["m_source"]), "left").select(
        F.col("source").alias("b_source"), "source_size", "target", "rounds",
        F.when(F.col("m_words") - F.col("m_rest") < F.col("m_rest"), F.col("m_prefix") + 1).otherwise(F.col("m_prefix")).alias("bound"),
    )
    return materialise(found, "mix-bounds"), few


def _repeats(h: Column, rounds: Column, bound: Column, cap: int) -> Column:
    return F.least(rounds + F.when(h < bound, 1).otherwise(0), F.lit(cap))


def mix(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: int = 3) -> DataFrame:
    """doc_id, size, source, source_size, target, taken: the words that the mix takes of each document.

    A target above its source's size repeats every document target // size times; the remainder is taken by hash order.
    """
    sized = materialise(_sized(docs), "mix-sizes")
    found, few = bounds(sized, weights, cap)
    picked = sized.join(F.broadcast(found) if few else found, sized["source"].eqNullSafe(F.col("b_source")))
    repeats = _repeats(F.col("h"), F.col("rounds"), F.col("bound"), cap)
    return picked.select("doc_id", "source", "size", "source_size", "target", (F.col("size") * repeats).alias("taken"), repeats.alias("repeats"))


def apply_mix(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: int = 3) -> DataFrame:
    """The mixed corpus: each document as often as the mix takes it, with the columns of docs. Texts are not shuffled: a document's
    own hash and its source's bound decide."""
    found, few = bounds(materialise(_sized(docs), "mix-sizes"), weights, cap)
    source, rounds, bound, copy = unused(docs, "b_source", "rounds", "bound", "copy")
    small = found.select(F.col("b_source").alias(source), F.col("rounds").alias(rounds), F.col("bound").alias(bound))
    met = docs.join(F.broadcast(small) if few else small, docs["source"].eqNullSafe(small[source]))
    repeats = _repeats(id_hash(docs["doc_id"]), F.col(rounds), F.col(bound), cap).cast("int")
    kept = met.withColumn(copy, F.explode(F.when(repeats > 0, F.sequence(F.lit(1), repeats))))
    return kept.select(*(docs[c] for c in docs.columns))


def op3_mixing(spark, sf_dir: str) -> DataFrame:
    out = mix(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "size", "source_size", "target", "taken")


SQL = r"""
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 12))::BIGINT AS h FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS w, source_size * 3 AS ceiling FROM s),
r AS (SELECT *, ceiling::DOUBLE / w AS ratio FROM w),
l AS (SELECT *, (sum(source_size) OVER () - (sum(ceiling) OVER (ORDER BY ratio, source NULLS LAST ROWS UNBOUNDED PRECEDING) - ceiling))::DOUBLE
         / (sum(w) OVER (ORDER BY ratio, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))::DOUBLE AS lev FROM r),
t AS (SELECT source, source_size, least(ceiling::DOUBLE, (SELECT arg_min(lev, ratio) FROM l WHERE ratio >= lev) * w) AS target FROM l),
p AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS rounds FROM t),
g AS (SELECT d.source, h, sum(size)::BIGINT AS words FROM d GROUP BY d.source, h),
c AS (SELECT g.*, sum(words) OVER (PARTITION BY source ORDER BY h ROWS UNBOUNDED PRECEDING) AS upto FROM g),
e AS (SELECT c.source, h, CASE WHEN upto - (target - rounds * source_size::DOUBLE) < (target - rounds * source_size::DOUBLE) - (upto - words) THEN h + 1 ELSE h END AS bound
      FROM c JOIN p ON c.source IS NOT DISTINCT FROM p.source
      WHERE upto > target - rounds * source_size::DOUBLE AND upto - words <= target - rounds * source_size::DOUBLE)
SELECT d.doc_id, d.size, p.source_size, p.target, d.size * (p.rounds + CASE WHEN d.h < e.bound THEN 1 ELSE 0 END) AS taken
FROM d JOIN p ON d.source IS NOT DISTINCT FROM p.source LEFT JOIN e ON d.source IS NOT DISTINCT FROM e.source
"""
