"""Trimming utterances whose length ratio lies in either tail."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from voxtable.functions.shared import stored

LOW, HIGH = 0.01, 0.05


def with_ratio(pairs: DataFrame, num: str = "n_speech_tok", den: str = "n_text_tok") -> DataFrame:
    """ratio, null where there are no text tokens."""
    return pairs.withColumn("ratio", F.try_divide(F.col(num).cast("double"), F.col(den)))


def trim(pairs: DataFrame, low: float = LOW, high: float = HIGH, method: str = "rank", by: str | None = None, buckets: int = 1024, held: bool = False) -> DataFrame:
    """Rows between the tails; rows without a ratio are rejected.

    "rank": floor(n x low) rows go below and floor(n x high) above in the order (ratio, utt_id). No task sorts the table: an
    approximate histogram cuts the ratios into ranges, ranks within a range are offset by the ranges before it.
    "quantile": exact percentiles, then a comparison. "sketch": the same by one mergeable sketch, one pass.
    by: quantiles for each group. held: rank mode reads the rows three times, so they are written to the shared folder first.
    """
    valid = pairs.filter("ratio IS NOT NULL")
    if method == "rank":
        valid = stored(valid) if held else valid
        cuts = valid.agg(F.percentile_approx("ratio", F.array(*[F.lit(i / buckets) for i in range(1, buckets)]), 10_000).alias("cuts"))
        # every 32nd cut first, then those behind the last one below
        ranged = valid.join(F.broadcast(cuts), F.lit(True))
        heads = F.array(*[F.get("cuts", F.lit(32 * i - 1)) for i in range(1, (buckets - 1) // 32 + 1)]).cast("array<double>")
        ranged = ranged.withColumn("range", 32 * F.size(F.filter(heads, lambda c: c < F.col("ratio"))))
        ranged = ranged.withColumn("range", F.col("range") + F.size(F.filter(F.slice("cuts", F.col("range") + 1, F.lit(32)), lambda c: c < F.col("ratio")))).drop("cuts")
        before = ranged.groupBy("range").agg(F.count(F.lit(1)).alias("n"))
        before = before.select("range", (F.sum("n").over(Window.orderBy("range")) - F.col("n")).alias("before"), F.sum("n").over(Window.partitionBy()).alias("total"))
        rank = F.row_number().over(Window.partitionBy("range").orderBy("ratio", "utt_id"))
        ranked = ranged.withColumn("rank", rank).join(F.broadcast(before), "range").withColumn("rank", F.col("rank") + F.col("before"))
        kept = (F.col("rank") > F.floor(F.col("total") * low)) & (F.col("rank") <= F.col("total") - F.floor(F.col("total") * high))
        return ranked.filter(kept).drop("range", "rank", "before", "total")
    quantile = F.percentile_approx("ratio", F.array(F.lit(low), F.lit(1 - high)), 10_000) if method == "sketch" else F.percentile("ratio", F.array(F.lit(low), F.lit(1 - high)))
    cuts = (valid.groupBy(by) if by else valid.groupBy()).agg(quantile.alias("cut"))
    joined = valid.join(cuts, by) if by else valid.join(F.broadcast(cuts), F.lit(True))
    return joined.filter((F.col("ratio") >= F.col("cut")[0]) & (F.col("ratio") <= F.col("cut")[1])).drop("cut")
