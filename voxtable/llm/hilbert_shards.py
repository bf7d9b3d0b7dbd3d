"""Sharding along a Hilbert curve over document metadata.

Language, source and length are each quantised to SIDE cells; a document's place on the curve through that cube orders the
corpus, and the order is cut into runs of equal row counts (law ``rows``). Documents that are near each other in all
three dimensions share shards, so the min/max statistics of a shard's files prune on any of them.

No task sorts a whole key: positions are cell start + bucket start + rank within bucket, where a cell of the curve is
dealt into BUCKETS hash buckets. Cells are at most SIDE**3 rows, by construction.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from voxtable.llm.common import cut, text_of

BITS = 5
SIDE = 2**BITS
SHARDS = 16
BUCKETS = 256


def hilbert_index(coords: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Position on the Hilbert curve of integer points, shape (n, dims): the published transpose form, on whole columns."""
    x = coords.astype(np.int64).T.copy()
    dims = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        p = q - 1
        for i in range(dims):
            high = (x[i] & q) != 0
            swap = np.where(high, 0, (x[0] ^ x[i]) & p)
            x[0] ^= np.where(high, p, swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, dims):
        x[i] ^= x[i - 1]
    flip = np.zeros_like(x[0])
    q = 1 << (bits - 1)
    while q > 1:
        flip = np.where((x[dims - 1] & q) != 0, flip ^ (q - 1), flip)
        q >>= 1
    x ^= flip
    out = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(dims):
            out = (out << 1) | ((x[i] >> b) & 1)
    return out


@F.pandas_udf(LongType())
def _curve(x: pd.Series, y: pd.Series, z: pd.Series) -> pd.Series:
    return pd.Series(hilbert_index(np.stack([x, y, z], axis=1)))


def _category(col: Column) -> Column:
    """A cell for a category: null is cell 0, others by hash, the same for every table and run."""
    return F.when(col.isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64(col), F.lit(SIDE))).cast("int")


def _length_cell(size: Column) -> Column:
    """Half octaves of the size in bytes."""
    return F.least(F.lit(SIDE - 1), F.floor(F.log2(size.cast("double")) * 1.25)).cast("int")


def place(docs: DataFrame, shards: int = SHARDS) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard, curve for every row.

    Null texts have size 1 and the CRC of the empty text. Ties on the curve fall by a hash of the doc_id, then doc_id and CRC; rows
    equal in all of these are interchangeable. An empty table gives an empty result; fewer rows
    than shards leave shards empty; extra columns are not read.
    """
    columns = ["doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard", "curve"]
    return _placed(docs, shards).select(columns)


def _placed(docs: DataFrame, shards: int, *carried: Column) -> DataFrame:
    """What place() returns, with the carried columns of each row after it."""
    text = text_of()
    rows = docs.select(
        *carried,
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.col("lang").cast("string").alias("lang"),
        F.col("source").cast("string").alias("source"),
    )
    rows = rows.withColumn("curve", _curve(_category(F.col("lang")), _category(F.col("source")), _length_cell(F.col("size"))))
    rows = rows.withColumn("mix", F.xxhash64("doc_id", "text_crc32")).withColumn("bucket", F.pmod("mix", F.lit(BUCKETS)).cast("int"))
    names = [c for c in rows.columns if c not in ("doc_id", "size", "text_crc32", "lang", "source", "curve", "bucket", "mix")]
    rows = cut(rows.select("doc_id", "size", "text_crc32", "curve", "bucket", "mix", *names))
    # bucket starts within a cell, then cell starts: the latter is a window over at most SIDE**3 rows
    buckets = rows.groupBy("curve", "bucket").agg(F.count(F.lit(1)).alias("n"))
    in_cell = Window.partitionBy("curve").orderBy("bucket")
    buckets = buckets.withColumn("before", F.sum("n").over(in_cell) - F.col("n"))
    cells = buckets.groupBy("curve").agg(F.sum("n").alias("n"))
    cells = cells.select("curve", (F.sum("n").over(Window.orderBy("curve")) - F.col("n")).alias("start"), F.sum("n").over(Window.partitionBy()).alias("total"))
    starts = buckets.join(F.broadcast(cells), "curve").select("curve", "bucket", (F.col("start") + F.col("before")).alias("start"), "total")
    rank = F.row_number().over(Window.partitionBy("curve", "bucket").orderBy("mix", "doc_id", "text_crc32"))
    ranked = rows.withColumn("rank", rank).join(starts, ["curve", "bucket"])
    at = F.col("start") + F.col("rank") - 1
    ranked = ranked.withColumn("at", at)
    shard = F.expr(f"int(at * {shards} div total)")
    first = F.expr(f"(int(at * {shards} div total) * total + {shards - 1}) div {shards}")
    return ranked.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), shard.alias("shard"), (F.col("at") - first).alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "curve", *names
    )


def write_shards(docs: DataFrame, path: str, shards: int = SHARDS) -> None:
    """The documents as Parquet, one folder for each shard, sorted along the curve, for pruning by file statistics."""
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    where = _placed(docs, shards, row).select("row.*", "shard", "slot")
    where.repartition("shard").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
