"""Mixing sources to target weights.

Tokens (words) are summed by source, the targets are levelled under their caps in closed form, and each
document is emitted floor(rate) times plus one Bernoulli copy drawn from a hash of its id with
probability rate - floor(rate). The hash offers DRAWS independent seeds; each source takes the one whose total
lies nearest its target, found in one more aggregate of narrow rows. Every decision depends on
(doc_id, source plan) alone, so reruns, retries and other partitionings agree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from voxtable.llm.common import WORD, broadcast_if_small, cut, text_of

#: Weights by rank of the source, repeating; most copies of a document.
WEIGHTS = (5, 2, 1)
MOST = 3
DRAWS = 32  # four from each md5
SEED = "mix"
BROADCAST_SOURCES = 100_000


def n_words(col: Column) -> Column:
    return F.regexp_count(col, F.lit(WORD)).cast("long")


def _draw(doc_id: Column, j: int) -> Column:
    """The j-th uniform number of a document, a multiple of 2**-32 in [0, 1)."""
    digest = F.md5(F.concat(F.lit(f"{SEED}:{j // 4}:"), F.coalesce(doc_id.cast("string"), F.lit(""))))
    return F.conv(F.substring(digest, 1 + 8 * (j % 4), 8), 16, 10).cast("double") / F.lit(2.0**32)


def source_targets(by_source: DataFrame) -> DataFrame:
    """source, source_size -> also weight, target: level x weight, or MOST x size where that is less.

    Sorted by cap / weight the capped sources come first, so the level is found by running sums. One row for
    each source: the only window here without a partition.
    """
    ranked = by_source.withColumn("rank", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1)
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in WEIGHTS]), (F.col("rank") % len(WEIGHTS) + 1).cast("int"))
    ranked = ranked.withColumn("weight", weight).withColumn("cap", F.col("source_size").cast("double") * MOST)
    ranked = ranked.withColumn("full_at", F.col("cap") / F.col("weight"))
    up = Window.orderBy("full_at", "rank")
    before = up.rowsBetween(Window.unboundedPreceding, -1)
    after = up.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    whole = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    total = F.sum("source_size").over(whole).cast("double")
    level = (total - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after)
    levelled = ranked.withColumn("level", level)
    first = F.min(F.when(F.col("level") <= F.col("full_at"), F.struct("full_at", "rank", "level"))).over(whole)
    return levelled.withColumn("best", first["level"]).select(
        "source", "source_size", "weight", F.least(F.col("cap"), F.col("best") * F.col("weight")).alias("target")
    )


def source_plan(sizes: DataFrame) -> DataFrame:
    """doc_id, source, size -> source, source_size, target, rate, draw (index of the seed taken)."""
    by_source = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    plan = source_targets(by_source).withColumn("rate", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0)))
    plan = cut(plan)
    rows = sizes.join(broadcast_if_small(plan, BROADCAST_SOURCES).withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s")))
    share = F.col("rate") - F.floor("rate")
    sums = [F.sum(F.when(_draw(F.col("doc_id"), j) < share, F.col("size")).otherwise(F.lit(0))).alias(f"d{j}") for j in range(DRAWS)]
    drawn = rows.groupBy("source", "source_size", "target", "rate").agg(*sums)
    miss = [F.struct(F.abs(F.floor("rate") * F.col("source_size") + F.col(f"d{j}") - F.col("target")).alias("miss"), F.lit(j).alias("j")) for j in range(DRAWS)]
    return drawn.select("source", "source_size", "target", "rate", F.array_min(F.array(*miss))["j"].alias("draw"))


def with_copies(rows: DataFrame, plan: DataFrame) -> DataFrame:
    """rows (doc_id, source, ...) and their source's plan -> rows, its target and size, copies."""
    plan = broadcast_if_small(plan, BROADCAST_SOURCES).withColumnRenamed("source", "_source")
    both = rows.join(plan, F.col("source").eqNullSafe(F.col("_source"))).drop("_source")
    u = F.element_at(F.array(*[_draw(F.col("doc_id"), j) for j in range(DRAWS)]), F.col("draw") + 1)
    copies = F.floor("rate") + F.when(u < F.col("rate") - F.floor("rate"), F.lit(1)).otherwise(F.lit(0))
    return both.withColumn("copies", F.least(copies, F.lit(MOST)).cast("int"))


def _sizes(docs: DataFrame) -> DataFrame:
    return cut(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), n_words(text_of()).alias("size")))


def mix_table(docs: DataFrame) -> DataFrame:
    """doc_id, size, source_size, target, taken, copies for every row.

    Null texts have size 0; null is a source of its own, the last; a source without words has target and rate 0.
    Rows that repeat a doc_id count each and draw alike. An empty table gives an empty result.
    """
    sizes = _sizes(docs)
    rows = with_copies(sizes, cut(source_plan(sizes)))
    return rows.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).cast("long").alias("taken"), F.col("copies").cast("long").alias("copies"))


def mixed(docs: DataFrame) -> DataFrame:
    """The mix itself: rows of docs, each as often as its copies say; columns as in docs.

    The plan's columns take names that docs cannot have, so extra columns of docs stay as they are.
    """
    plan = cut(source_plan(_sizes(docs)))
    packed = docs.select("doc_id", F.col("source").cast("string").alias("source"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    many = with_copies(packed, plan).filter("copies > 0")
    return many.select("row", F.explode(F.array_repeat(F.lit(0), F.col("copies"))).alias("copy")).select("row.*")


ORACLE = rf"""
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{WORD}'))::BIGINT AS size FROM documents
), s AS (
  SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source
), r AS (
  SELECT *, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS rnk FROM s
), c AS (
  SELECT *, (CASE rnk % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END)::DOUBLE AS weight, source_size::DOUBLE * {MOST} AS cap FROM r
), f AS (
  SELECT *, cap / weight AS full_at FROM c
), l AS (
  SELECT *, ((sum(source_size) OVER ())::DOUBLE - coalesce(sum(cap) OVER (ORDER BY full_at, rnk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
            / sum(weight) OVER (ORDER BY full_at, rnk ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM f
), t AS (
  SELECT source, source_size, least(cap, weight * (SELECT level FROM l WHERE level <= full_at ORDER BY full_at, rnk LIMIT 1)) AS target FROM l
), p AS (
  SELECT *, CASE WHEN source_size > 0 THEN target / source_size ELSE 0.0::DOUBLE END AS rate FROM t
), u AS (
  SELECT d.doc_id, d.size, p.*, j, ('0x' || substr(md5('{SEED}:' || (j // 4) || ':' || coalesce(d.doc_id::VARCHAR, '')), (1 + 8 * (j % 4))::INT, 8))::BIGINT / 4294967296.0::DOUBLE < rate - floor(rate) AS extra
  FROM d JOIN p ON d.source IS NOT DISTINCT FROM p.source, range({DRAWS}) AS q(j)
), b AS (
  SELECT source, j, abs(floor(any_value(rate)) * any_value(source_size) + sum(CASE WHEN extra THEN size ELSE 0 END) - any_value(target)) AS miss FROM u GROUP BY source, j
), k AS (
  SELECT source, j FROM b QUALIFY row_number() OVER (PARTITION BY source ORDER BY miss, j) = 1
)
SELECT u.doc_id, u.size, u.source_size, u.target, ((floor(u.rate) + u.extra::INT) * u.size)::BIGINT AS taken, (floor(u.rate) + u.extra::INT)::BIGINT AS copies
FROM u JOIN k ON u.source IS NOT DISTINCT FROM k.source AND u.j = k.j
"""
