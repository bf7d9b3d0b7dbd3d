"""Exact deduplication that a hot text cannot skew, in DataFrame functions only.

Three combining stages, each comparing the full normalised text (it is a grouping
key, beside its digest, not merely hashed):

1. every map task combines its own rows (the partial aggregate of the first groupBy);
2. rows meet by (digest, text, salt), so a text that a third of all rows share is spread over
   ``salts`` tasks, each of which leaves one winner;
3. the at most ``salts`` winners of a text meet in one place.

Only winners (digest, keeper, size) are kept for the way back to the documents, which is a join by
digest of narrow rows; the adaptive skew join splits a hot digest. Should two texts ever share a
SHA-256, those digests alone are joined by full text as well.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from voxtable.llm.common import SPACES, cut, text_of

_ID_SPAN = 2**65  # above every value of _order's last part


def _order(n_chars: Column, doc_id: Column) -> Column:
    """One fixed-width number that sorts by length, then by smaller id, rows without an id last: hash aggregates keep it."""
    earlier = F.coalesce(F.lit(str(2**63)).cast("decimal(20,0)") - doc_id.cast("decimal(19,0)"), F.lit(0).cast("decimal(20,0)"))
    return (n_chars.cast("decimal(11,0)") * F.lit(str(_ID_SPAN)).cast("decimal(20,0)") + earlier).cast("decimal(38,0)")


def _keeper(order: Column) -> Column:
    part = order % F.lit(str(_ID_SPAN)).cast("decimal(20,0)")
    return F.when(part > 0, (F.lit(str(2**63)).cast("decimal(20,0)") - part.cast("decimal(20,0)")).cast("long"))


def _rows(docs: DataFrame) -> DataFrame:
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("raw"))
    rows = rows.select("doc_id", F.char_length("raw").alias("n_chars"), F.translate("raw", SPACES, "").alias("body"))
    return rows.withColumn("text_sha256", F.sha2("body", 256))


def _winners(docs: DataFrame, salts: int) -> DataFrame:
    """(text_sha256, body, best, group_size), one row for each distinct normalised text."""
    salted = _rows(docs).select(
        "text_sha256", "body", F.pmod(F.xxhash64("doc_id"), F.lit(salts)).alias("salt"), _order(F.col("n_chars"), F.col("doc_id")).alias("best")
    )
    by_salt = salted.groupBy("text_sha256", "body", "salt").agg(F.max("best").alias("best"), F.count(F.lit(1)).alias("n"))
    return by_salt.repartition("text_sha256").groupBy("text_sha256", "body").agg(F.max("best").alias("best"), F.sum("n").alias("group_size"))


def exact_groups(docs: DataFrame, salts: int = 16) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every row of docs.

    Texts are equal if they are the same after deleting ASCII white space; null counts as empty, so
    null, empty and blank texts are one group. The longest original text stays, then the smallest doc_id;
    a null doc_id only stays where its group has no other. Rows that repeat a doc_id count
    each, and are kept or dropped together. An empty table gives an empty result; other columns are not read.
    """
    winners = _winners(docs, salts)
    by_digest = cut(
        winners.groupBy("text_sha256").agg(
            F.count(F.lit(1)).alias("texts"), F.max("best").alias("best"), F.max("group_size").alias("group_size")
        )
    )
    rows = _rows(docs)
    found = rows.select("doc_id", "text_sha256").join(by_digest.filter("texts = 1"), "text_sha256")
    found = found.select("doc_id", "text_sha256", "best", "group_size")
    if not by_digest.filter("texts > 1").isEmpty():
        clashing = by_digest.filter("texts > 1").select("text_sha256")
        exact = rows.join(clashing, "text_sha256", "left_semi").join(winners, ["text_sha256", "body"])
        found = found.unionByName(exact.select("doc_id", "text_sha256", "best", "group_size"))
    keep = _keeper(F.col("best"))
    return found.select("doc_id", keep.alias("keep_id"), "group_size", F.col("doc_id").eqNullSafe(keep).alias("kept"), "text_sha256")


ORACLE = r"""
WITH r AS (
  SELECT doc_id, coalesce(text, '') AS raw, regexp_replace(coalesce(text, ''), '[ \t\n\x0b\x0c\r]', '', 'g') AS body FROM documents
), w AS (
  SELECT doc_id, sha256(body) AS text_sha256, count(*) OVER (PARTITION BY body) AS group_size,
         first_value(doc_id) OVER (PARTITION BY body ORDER BY length(raw) DESC, doc_id) AS keep_id
  FROM r
)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM w
"""
