"""Comparison tables: relative gains, ranks of cells, unsupported cells, gaps, wins, bounds."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Metrics where less is better; the others are scores.
ERRORS = ("cer", "wer", "error")


def _lower(metric: F.Column) -> F.Column:
    return metric.isin(*ERRORS)


def relative(cells: DataFrame, base: str, new: str) -> DataFrame:
    """subset, metric, base, new, gain (%): fall of errors, rise of scores, against the base."""
    keys = [c for c in ("tbl", "subset", "metric") if c in cells.columns]
    old = cells.filter(F.col("model") == base).select(*keys, F.col("value").alias("base"))
    now = cells.filter(F.col("model") == new).select(*keys, F.col("value").alias("new"))
    both = old.join(now, keys)
    gain = F.when(_lower(F.col("metric")), F.col("base") - F.col("new")).otherwise(F.col("new") - F.col("base"))
    return both.withColumn("gain", F.try_divide(gain * 100, F.col("base")))


def podium(cells: DataFrame) -> DataFrame:
    """rank: 1 best, 2 second in each (subset, metric), ties sharing; null cells have none."""
    signed = F.when(_lower(F.col("metric")), F.col("value")).otherwise(-F.col("value"))
    keys = [c for c in ("tbl", "subset", "metric") if c in cells.columns]
    rank = F.dense_rank().over(Window.partitionBy(*keys, F.col("value").isNull()).orderBy(signed))
    return cells.withColumn("rank", F.when(F.col("value").isNotNull(), rank))


def fill_unsupported(cells: DataFrame) -> DataFrame:
    """As plotted: an error of 100, a similarity of 0."""
    return cells.withColumn("value", F.coalesce("value", F.when(_lower(F.col("metric")), F.lit(100.0)).otherwise(F.lit(0.0))))


def table(cells: DataFrame, rows: str, cols: str, values: list[str]) -> DataFrame:
    """Matrix of cells; the values are listed, so no job looks for them."""
    return cells.groupBy(rows).pivot(cols, values).agg(F.first("value"))


def size_gap(cells: DataFrame, small: str, large: str) -> DataFrame:
    pick = lambda m: F.max(F.when(F.col("model") == m, F.col("value")))
    keys = [c for c in ("tbl", "subset", "metric") if c in cells.columns]
    return cells.groupBy(*keys).agg((pick(large) - pick(small)).alias("gap"))


def below(cells: DataFrame, bound: float) -> DataFrame:
    """n cells, n below, all below."""
    return cells.agg(F.count("value").alias("n"), F.count_if(F.col("value") < bound).alias("n_below"), F.bool_and(F.col("value") < bound).alias("all_below"))


def wins(cells: DataFrame, a: str, b: str) -> DataFrame:
    """metric -> wins, ties, losses of a against b over cells that both have."""
    both = relative(cells, b, a)
    return both.groupBy("metric").agg(F.count_if(F.col("gain") > 0).alias("wins"), F.count_if(F.col("gain") == 0).alias("ties"), F.count_if(F.col("gain") < 0).alias("losses"))


def gain_histogram(gains: DataFrame) -> DataFrame:
    """n, over 50 %, 20 to 50 %, below 20 %."""
    g = F.col("gain")
    return gains.agg(F.count("gain").alias("n"), F.count_if(g > 50).alias("over_50"), F.count_if((g >= 20) & (g <= 50)).alias("from_20_to_50"), F.count_if(g < 20).alias("below_20"))


def gain_gap(gains: DataFrame, hard: str, full: str) -> DataFrame:
    """metric -> gain on the hard subset less that on the full one."""
    pick = lambda s: F.max(F.when(F.col("subset") == s, F.col("gain")))
    return gains.groupBy("metric").agg((pick(hard) - pick(full)).alias("gap"))


def scaling_gain(rows: DataFrame, scale: str, value: str, *by: str) -> DataFrame:
    """gain of each scale over the one before, as a share; few rows, one for each scale."""
    last = F.lag(value).over(Window.partitionBy(*by).orderBy(scale))
    return rows.withColumn("gain", F.try_divide(last - F.col(value), last))
