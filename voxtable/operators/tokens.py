"""Token streams: packing at 25 a second, use of the codebook, task-tagged examples, probes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from voxtable.functions.vectors import squared_distance

RATE = 25


def pack(df: DataFrame, utt: str = "utt_id", t: str = "t", token: str = "token", rate: int = RATE) -> DataFrame:
    """Ordered tokens and duration of each utterance; at most some 750 a row where segments are under 30 s."""
    packed = df.groupBy(utt).agg(F.array_sort(F.collect_list(F.struct(t, token))).alias("ts"))
    return packed.select(utt, F.transform("ts", lambda x: x[token]).alias("tokens"), (F.size("ts") / F.lit(rate)).alias("duration_s"))


def usage(df: DataFrame, codebook_size: int, token: str = "token") -> DataFrame:
    """n, used codes, share of the codebook, entropy (nats) and perplexity of the token histogram."""
    counts = df.groupBy(token).agg(F.count(F.lit(1)).alias("c"))
    sums = counts.agg(F.sum("c").alias("n"), F.count(F.lit(1)).alias("used"), F.sum(F.col("c") * F.ln(F.col("c").cast("double"))).alias("clc"))
    entropy = F.ln(F.col("n").cast("double")) - F.col("clc") / F.col("n")
    return sums.select("n", "used", (F.col("used") / F.lit(codebook_size)).alias("share"), entropy.alias("entropy"), F.exp(entropy).alias("perplexity"))


def majority_probe(df: DataFrame, token: str, label: str) -> DataFrame:
    """Accuracy of answering each token's most frequent label (ties to the smaller label)."""
    counts = df.groupBy(token, label).agg(F.count(F.lit(1)).alias("n"))
    return counts.groupBy(token).agg(F.max("n").alias("hit"), F.sum("n").alias("n")).agg((F.sum("hit") / F.sum("n")).alias("accuracy"), F.sum("n").alias("n"))


def centroids(df: DataFrame, label: str, col: str) -> DataFrame:
    """label, centre: mean vector of each label; partial sums by (label, place)."""
    means = df.select(label, F.posexplode(col).alias("at", "x")).groupBy(label, "at").agg(F.avg(F.col("x").cast("double")).alias("m"))
    return means.groupBy(label).agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "m"))), lambda s: s["m"]).alias("centre"))


def centroid_probe(df: DataFrame, label: str, col: str) -> DataFrame:
    """Accuracy of answering the label of the nearest mean; labels are few, so the means are one array."""
    means = centroids(df, label, col).agg(F.array_sort(F.collect_list(F.struct(F.col(label).alias("id"), "centre"))).alias("means"))
    best = F.array_min(F.transform("means", lambda m: F.struct(F.round(squared_distance(m["centre"], F.col(col)), 9).alias("d"), m["id"].alias("id"))))
    return df.crossJoin(F.broadcast(means)).agg(F.avg((best["id"] == F.col(label)).cast("double")).alias("accuracy"), F.count(F.lit(1)).alias("n"))


def multitask_examples(df: DataFrame, tasks: dict[str, str], key: str) -> DataFrame:
    """key, task, truth: one row for each task whose label is known."""
    each = F.array(*[F.struct(F.lit(t).alias("task"), F.expr(e).cast("string").alias("truth")) for t, e in tasks.items()])
    return df.select(key, F.explode(each).alias("x")).select(key, "x.*").filter("truth IS NOT NULL")


def moving(df: DataFrame, col: str, width: int, *by: str) -> DataFrame:
    """Centred mean, as the renderer's smoothing stand-in."""
    w = Window.partitionBy(*by[:-1]).orderBy(by[-1]).rowsBetween(-width, width)
    return df.withColumn(col, F.avg(col).over(w))
