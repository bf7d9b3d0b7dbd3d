"""Structured Streaming over event files: windows, sessions, late data, keyed state, joins.

Every builder makes a streaming frame; ``finished`` runs one over what is there (availableNow) and gives its output as a
batch frame, which is how the queries compare a stream with batch SQL.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from voxtable.functions.shared import shared_folder
from voxtable.operators.segment import MAX_LEN_S, SECOND
from voxtable.schemas import COLUMNS
from voxtable.sources.tables import micros


def events(spark: SparkSession, sf_dir: str, delay: str = "1 day") -> DataFrame:
    """Event files as they come: event_id, user_id, event_type, value, us and a zone-free event time t with a watermark."""
    rows = spark.readStream.schema(COLUMNS["events"]).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    timed = rows.withColumn("us", micros("ts")).withColumn("t", F.expr("timestamp_micros(us)"))
    return timed.select("event_id", "user_id", "event_type", "value", "us", "t").withWatermark("t", delay)


def _folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"


def finished(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """The stream's output over all that is there. Complete mode keeps the last result; append mode the file sink's rows."""
    folder = _folder(stream.sparkSession)
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True)
    if mode == "complete":
        writer = writer.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(f"{folder}/out"))
        writer.start().awaitTermination()
    else:
        writer.format("parquet").option("path", f"{folder}/out").start().awaitTermination()
    return stream.sparkSession.read.parquet(f"{folder}/out")


def tumbling(rows: DataFrame, width: str = "1 day") -> DataFrame:
    by = rows.groupBy(F.window("t", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return by.select(F.unix_micros("w.start").alias("start"), "event_type", "n", "total")


def sliding(rows: DataFrame, width: str = "2 days", slide: str = "1 day") -> DataFrame:
    by = rows.groupBy(F.window("t", width, slide).alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return by.select(F.unix_micros("w.start").alias("start"), "n")


def sessions(rows: DataFrame, gap: str = "12 hours") -> DataFrame:
    """Speech of a speaker between pauses of at least the gap: the stream's form of segmentation."""
    by = rows.groupBy(F.session_window("t", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"), F.max("us").alias("us1"))
    return by.select("user_id", F.unix_micros("w.start").alias("us0"), "us1", "n")


def capped(rows: DataFrame, max_len_s: float = MAX_LEN_S) -> DataFrame:
    """event_id, user_id, piece: the greedy duration cap, its state a piece's start and number by speaker."""
    size = int(max_len_s * SECOND)

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:  # noqa: ANN001
        start, piece = state.get if state.exists else (None, 0)
        frames = pd.concat(batches).sort_values(["us", "event_id"])
        pieces = []
        for us in frames["us"]:
            if start is None:
                start = int(us)
            elif us - start >= size:
                start, piece = int(us), piece + 1
            pieces.append(piece)
        state.update((start, piece))
        yield pd.DataFrame({"event_id": frames["event_id"].to_numpy(), "user_id": key[0], "piece": pieces})

    return rows.groupBy("user_id").applyInPandasWithState(step, "event_id bigint, user_id bigint, piece int", "start bigint, piece int", "append", "NoTimeout")


def deduplicated(rows: DataFrame, *keys: str) -> DataFrame:
    return rows.dropDuplicatesWithinWatermark([*keys])


def enriched(rows: DataFrame, static: DataFrame) -> DataFrame:
    """Stream-static join with a dimension."""
    joined = rows.join(static, F.pmod("user_id", F.lit(25)).cast("int") == F.col("n_nationkey"))
    return joined.groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


def followed(rows: DataFrame, other: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: sign-ups and the same user's purchases within the interval after."""
    a = rows.filter("event_type = 'signup'").select(F.col("user_id").alias("u"), F.col("event_id").alias("signup"), F.col("t").alias("t0"))
    b = other.filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), "t")
    return a.join(b, (F.col("u") == F.col("user_id")) & (F.col("t") >= F.col("t0")) & (F.col("t") <= F.expr(f"t0 + interval {within}"))).select("signup", "purchase")
