"""Sources and sinks: the given tables and the views that stand for recordings, features and transcripts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from voxtable.schemas import require_schema

#: The clock of stand-in recordings: 8640 event seconds are one second of audio.
CLOCK = 8640


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return require_schema(spark.read.parquet(f"{sf_dir}/{table}.parquet"), table)


def micros(ts: str) -> F.Column:
    """Microseconds since 1970 of a timestamp without zone, whatever the session's zone is."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {ts})")


def frames(events: DataFrame) -> DataFrame:
    """rec_id, frame, us, kind, amp: events as frames of one recording for each user."""
    return events.select(F.col("user_id").alias("rec_id"), F.col("event_id").alias("frame"), micros("ts").alias("us"), F.col("event_type").alias("kind"), F.col("value").alias("amp"))


def write_pairs(df: DataFrame, path: str, by: str = "lang") -> None:
    """Training pairs as Parquet, partitioned; only partitions in the frame are replaced."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(by).parquet(path)


def write_manifest(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)


def page_text(pages: DataFrame) -> DataFrame:
    """page_id, text: scripts, styles and tags out, the common entities back, blanks collapsed."""
    text = F.regexp_replace("html", r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    text = F.regexp_replace(text, r"<[^>]+>", " ")
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        text = F.replace(text, F.lit(entity), F.lit(char))
    return pages.select("page_id", F.trim(F.regexp_replace(text, r"\s+", " ")).alias("text"))
