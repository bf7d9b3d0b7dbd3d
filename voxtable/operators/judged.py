"""Similarity, opinion and accuracy measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from voxtable.functions.vectors import cosine

VIEWS = {"a": (1, 32), "b": (33, 32)}


def view(vector: Column, name: str) -> Column:
    """One of two halves of an embedding, standing for two speaker models."""
    return F.slice(vector, *VIEWS[name])


def paired(df: DataFrame, by: str, key: str, vector: str) -> DataFrame:
    """by, key, x, y: each row and the next of its group."""
    nxt = F.lead(vector).over(Window.partitionBy(by).orderBy(key))
    return df.select(by, key, F.col(vector).alias("x"), nxt.alias("y")).filter("y IS NOT NULL")


def speaker(pairs: DataFrame, name: str) -> DataFrame:
    return pairs.withColumn("similarity", cosine(view(F.col("x"), name), view(F.col("y"), name)))


def mos_pred(n_chars: Column, quality: Column) -> Column:
    """Stand-in for a quality predictor: from 1 to 5, higher with quality and moderate length."""
    return F.least(F.lit(5.0), 2.0 + 1.5 * F.coalesce(quality.cast("double"), F.lit(0.5)) + F.least(F.lit(1.5), n_chars / 2000.0))


def ratings(events: DataFrame) -> DataFrame:
    """system, sentence, rater, gender, score: event values as scores from 1 to 5 by halves."""
    score = F.least(F.lit(5.0), 1 + 0.5 * F.floor(F.least(F.col("value"), F.lit(200.0)) / 25))
    rater = (F.col("user_id") % 10).cast("int")
    lang = F.when(F.col("event_id") % 2 == 0, "zh").otherwise("en")
    return events.select(F.col("event_type").alias("system"), (F.col("event_id") % 200).alias("sentence"), rater.alias("rater"), F.when(rater % 2 == 0, "f").otherwise("m").alias("gender"), lang.alias("lang"), score.alias("score"))


def opinion(rows: DataFrame) -> DataFrame:
    """n, mos, ci95 by (system, lang), and by system alone (lang null), in one pass."""
    grouped = rows.groupingSets([["system", "lang"], ["system"]], "system", "lang")
    out = grouped.agg(F.count(F.lit(1)).alias("n"), F.avg("score").alias("mos"), F.stddev_samp("score").alias("sd"))
    return out.select("system", "lang", "n", "mos", (1.96 * F.try_divide(F.col("sd"), F.sqrt(F.col("n").cast("double")))).alias("ci95"))


def mean_of_languages(rows: DataFrame) -> DataFrame:
    """The other average: of the language means."""
    return rows.groupBy("system", "lang").agg(F.avg("score").alias("m")).groupBy("system").agg(F.avg("m").alias("mos"))


def validate(rows: DataFrame) -> DataFrame:
    """system, sentence, n_f, n_m, balanced, on_grid: five raters of either gender, scores by halves from 1 to 5."""
    grid = (F.col("score") * 2 == F.floor(F.col("score") * 2)) & F.col("score").between(1, 5)
    by = rows.groupBy("system", "sentence").agg(F.count_if(F.col("gender") == "f").alias("n_f"), F.count_if(F.col("gender") == "m").alias("n_m"), F.bool_and(grid).alias("on_grid"))
    return by.withColumn("balanced", (F.col("n_f") == 5) & (F.col("n_m") == 5))


def accuracy(rows: DataFrame, *by: str) -> DataFrame:
    """Share of predictions that equal the truth."""
    return rows.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.avg((F.col("pred") == F.col("truth")).cast("double")).alias("accuracy"))


def confusion(rows: DataFrame, classes: list[str]) -> DataFrame:
    return rows.groupBy("truth").pivot("pred", classes).count().na.fill(0)


def macro_f1(rows: DataFrame) -> DataFrame:
    """Mean over classes of 2 tp / (2 tp + fp + fn), from counts of (truth, pred)."""
    pairs = rows.groupBy("truth", "pred").agg(F.count(F.lit(1)).alias("n"))
    each = pairs.select(F.explode(F.array(F.struct(F.col("truth").alias("c"), (F.col("pred") == F.col("truth")).alias("hit"), "n"), F.struct(F.col("pred").alias("c"), (F.col("pred") == F.col("truth")).alias("hit"), "n"))).alias("x")).select("x.*")
    return each.groupBy("c").agg((F.sum(F.when(F.col("hit"), F.col("n")).otherwise(0)) / F.sum("n")).alias("f1")).agg(F.avg("f1").alias("macro_f1"))


def correction_rate(rows: DataFrame, *by: str) -> DataFrame:
    """errors, corrected, rate (%): null where there were no errors."""
    sums = rows.groupBy(*by).agg(F.sum("errors").alias("errors"), F.sum("corrected").alias("corrected"))
    return sums.withColumn("rate", F.try_divide(100.0 * F.col("corrected"), F.col("errors")))
