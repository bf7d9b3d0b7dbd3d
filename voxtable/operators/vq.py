"""Vector quantisers for comparison: one codebook, residual stages, clusters of features."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from voxtable.functions.hashing import draw
from voxtable.functions.vectors import matrix, squared_distance


def nearest(v: Column, codebook: Column) -> Column:
    """Struct (dist, id) of the nearest entry, ties to the smaller id; distances rounded to nine places."""
    return F.array_min(F.transform(codebook, lambda c, i: F.struct(F.round(squared_distance(c, v), 9).alias("dist"), i.alias("id"))))


def assign(df: DataFrame, codebook: Sequence[Sequence[float]], col: str = "embedding") -> DataFrame:
    best = nearest(F.col(col), matrix(codebook))
    return df.withColumn("code", best["id"])


def seeds(df: DataFrame, k: int, col: str = "embedding", key: str = "vec_id") -> list[list[float]]:
    """k rows in hash order: bounded by k."""
    return [list(map(float, r[0])) for r in df.orderBy(draw("vq", F.col(key)), key).select(col).limit(k).collect()]


def fit(df: DataFrame, k: int, iters: int = 5, col: str = "embedding", key: str = "vec_id") -> list[list[float]]:
    """Lloyd iterations: only k sums and counts reach the driver; an empty cluster keeps its centre."""
    book = np.array(seeds(df, k, col, key))
    for _ in range(iters):
        sums = assign(df.select(col), book.tolist(), col).select("code", F.posexplode(col).alias("at", "x")).groupBy("code", "at").agg(F.sum(F.col("x").cast("double")).alias("s"), F.count(F.lit(1)).alias("n"))
        new = book.copy()
        for r in sums.collect():
            new[r["code"], r["at"]] = r["s"] / r["n"]
        if np.abs(new - book).max() < 1e-9:
            break
        book = new
    return book.tolist()


def residual(df: DataFrame, codebooks: Sequence[Sequence[Sequence[float]]], col: str = "embedding") -> DataFrame:
    """codes: the nearest entry of each stage to what the stages before leave over."""
    out = df.withColumn("rest", F.transform(col, lambda x: x.cast("double"))).withColumn("codes", F.array().cast("array<int>"))
    for book in codebooks:
        best = nearest(F.col("rest"), matrix(book))["id"]
        out = out.withColumn("c", best)
        entry = F.element_at(matrix(book), F.col("c") + 1)
        out = out.withColumn("rest", F.zip_with("rest", entry, lambda a, b: a - b)).withColumn("codes", F.concat("codes", F.array("c"))).drop("c")
    return out
