"""Helpers shared by the training-data operators."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The six ASCII white-space characters, and a word as a Java, Python or RE2 pattern.
SPACES = " \t\n\x0b\x0c\r"
WORD = r"[^ \t\n\x0b\x0c\r]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_of(name: str = "text") -> Column:
    """The text, with null as empty."""
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def columns_of(df: DataFrame) -> list[Column]:
    """All columns, whatever their names hold."""
    return [F.col("`" + c.replace("`", "``") + "`") for c in df.columns]


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value), with the value computed once."""
    return F.transform(F.array(value), use)[0]


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; one of this machine's only where all is on this machine."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if shared is None and not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir is not set: a cluster needs a shared folder")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="voxtable-checkpoint-"))
    return sc.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Written to the shared folder as a table and read again: ends the lineage, survives lost executors; later reads take the columns they need.

    One job: an eager checkpoint computes its last stage twice, once to count and once to write. No dictionaries: hashes and texts hardly repeat.
    """
    out = f"{shared_folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.option("parquet.enable.dictionary", "false").option("compression", "zstd").parquet(out)
    return df.sparkSession.read.schema(df.schema).parquet(out)


def release(spark: SparkSession) -> None:
    """Shuffle files of frames that are out of use go now; else they stay until the driver happens to collect its garbage.

    Twice: right after a job its threads still hold some of it.
    """
    for pause in (0.5, 0):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(pause)


def broadcast_if_small(df: DataFrame, max_rows: int) -> DataFrame:
    """A broadcast hint if the (checkpointed, narrow) frame has at most max_rows rows; else the frame, to be shuffled."""
    return F.broadcast(df) if df.limit(max_rows + 1).count() <= max_rows else df
