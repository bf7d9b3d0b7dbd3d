"""Hours, shares, nested scales, budgets and mixtures of a training corpus; stages and model cards."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from voxtable.functions.hashing import draw, uniform

#: Stand-in rate: characters of a document that count as an hour.
CHARS_PER_HOUR = 54_000
#: The parts of the tokenizer's training hours, in thousands.
TOKENIZER_KHOURS = {"recognition": 365, "language": 85, "emotion": 48, "events": 21, "speaker": 11}


def hours(df: DataFrame, dims: tuple[str, ...], level: str = "groupby", measure: str = "hours") -> DataFrame:
    """hours and rows by dimension, with totals for "rollup" and "cube"; level_id tells the totals apart."""
    grouped = {"groupby": df.groupBy, "rollup": df.rollup, "cube": df.cube}[level](*dims)
    out = [F.sum(measure).alias("hours"), F.count(F.lit(1)).alias("n")]
    return grouped.agg(*out, *([F.grouping_id().alias("level_id")] if level != "groupby" else []))


def share(df: DataFrame, dim: str, exclude: tuple[str, ...] = (), measure: str = "hours") -> DataFrame:
    """Share of the total by dimension, of what is not excluded. The window runs over one row for each group."""
    sums = df.filter(~F.col(dim).isin(*exclude)) if exclude else df
    sums = sums.groupBy(dim).agg(F.sum(measure).alias("hours"))
    return sums.withColumn("share", F.try_divide("hours", F.sum("hours").over(Window.partitionBy())))


def nested_scales(df: DataFrame, fracs: dict[str, float], key: str, seed: str = "scale") -> DataFrame:
    """Each row once for every scale that holds it; a smaller scale is a subset of a larger one, by one draw."""
    u = uniform(seed, F.col(key))
    each = F.filter(F.array(*[F.struct(F.lit(s).alias("scale"), F.lit(f).alias("frac")) for s, f in fracs.items()]), lambda x: u < x["frac"])
    return df.select("*", F.explode(each).alias("x")).withColumn("scale", F.col("x")["scale"]).drop("x")


def to_budget(df: DataFrame, budgets: dict[str, float], dim: str, key: str, measure: str = "hours", buckets: int = 4096, seed: str = "budget") -> DataFrame:
    """Rows of each group in hashed order while the hours before them are under the group's budget.

    Two passes without a giant partition: hours by (group, hash bucket) find the bucket where the budget ends; only that
    bucket is put in order.
    """
    limit = F.coalesce(*[F.when(F.col(dim) == d, F.lit(float(b))) for d, b in budgets.items()])
    rows = df.withColumn("h", draw(seed, F.col(key))).withColumn("bucket", F.floor(F.col("h") / F.lit(2**32 // buckets)))
    sums = rows.groupBy(dim, "bucket").agg(F.sum(measure).alias("in_bucket"))
    order = Window.partitionBy(dim).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    edges = sums.select(dim, "bucket", F.coalesce(F.sum("in_bucket").over(order), F.lit(0.0)).alias("before"), "in_bucket")
    both = rows.join(edges, [dim, "bucket"]).withColumn("limit", limit).filter("before < limit")
    within = Window.partitionBy(dim, "bucket").orderBy("h", key).rowsBetween(Window.unboundedPreceding, -1)
    ordered = both.withColumn("so_far", F.col("before") + F.coalesce(F.sum(measure).over(within), F.lit(0.0)))
    return ordered.filter("so_far < limit").select(df.columns)


def rebalance(df: DataFrame, weights: dict[str, float], dim: str, key: str, seed: str = "rebalance") -> DataFrame:
    """copies of each row: floor(weight), and one more by a hashed draw of the rest; rows without copies go."""
    w = F.coalesce(*[F.when(F.col(dim) == d, F.lit(float(x))) for d, x in weights.items()], F.lit(1.0))
    copies = (F.floor(w) + (uniform(seed, F.col(key)) < w - F.floor(w)).cast("int")).cast("int")
    return df.withColumn("copies", copies).filter("copies > 0")


def temperature_weights(sizes: dict[str, float], temp: float) -> dict[str, float]:
    """Weights that turn shares p into p**(1 / temp), renormalised."""
    total = sum(sizes.values())
    raised = {k: (v / total) ** (1 / temp) for k, v in sizes.items() if v > 0}
    whole = sum(raised.values())
    return {k: raised[k] / whole / (sizes[k] / total) for k in raised}


def coverage(df: DataFrame, rows: str, cols: str, values: list[str]) -> DataFrame:
    return df.groupBy(rows).pivot(cols, values).count().na.fill(0)


def rare_cases(df: DataFrame, text: Column, key: str, max_df: int, n: int) -> DataFrame:
    """word, df, key: for each of the rarest words, its first row; n words by (df, word)."""
    words = df.select(key, F.explode(F.array_distinct(text)).alias("word"))
    counts = words.groupBy("word").agg(F.count(F.lit(1)).alias("df"), F.min(key).alias(key))
    return counts.filter(F.col("df") <= max_df).orderBy("df", "word").limit(n)


def holdout(df: DataFrame, dim: str, values: tuple[str, ...]) -> tuple[DataFrame, DataFrame]:
    """Rows without and with the values: fit on the first, measure on the second."""
    held = F.col(dim).isin(*values)
    return df.filter(~held), df.filter(held)


def self_train(rare: DataFrame) -> DataFrame:
    """Rare cases composed into items for an earlier model to render."""
    return rare.select(F.concat_ws(" ", "word", "word").alias("text"), F.lit("self").alias("part"))


STAGES = (("pretraining", None, "base, phones, text forms"), ("post_training", "pretraining", "reward tasks"), ("continual_pretraining", "post_training", "instructions, languages"), ("speaker_fine_tuning", "continual_pretraining", "target speakers, masked prompts"))


def stages(spark: SparkSession) -> DataFrame:
    """stage, after, inputs."""
    return spark.createDataFrame([*STAGES], "stage string, after string, inputs string")


def lineage(stages: DataFrame) -> DataFrame:
    """stage, depth, path: each stage's way from the start, by a recursive query."""
    stages.createOrReplaceTempView("voxtable_stages")
    return stages.sparkSession.sql(
        """WITH RECURSIVE walk(stage, depth, path) AS (SELECT stage, 0, stage FROM voxtable_stages WHERE after IS NULL
        UNION ALL SELECT s.stage, w.depth + 1, concat(w.path, ' > ', s.stage) FROM walk w JOIN voxtable_stages s ON s.after = w.stage) SELECT stage, depth, path FROM walk"""
    )


def model_card(rows: DataFrame, model: str, unit: Column, pieces: Column) -> DataFrame:
    """model, lm_params, renderer_params: distinct units, and distinct pieces of them; repeats go before anything is counted."""
    parts = F.concat(F.array(F.struct(F.lit("lm").alias("part"), unit.alias("x"))), F.transform(F.array_distinct(pieces), lambda c: F.struct(F.lit("renderer").alias("part"), c.alias("x"))))
    each = rows.select(F.col(model).alias("model"), F.explode(parts).alias("p")).select("model", "p.*").distinct()
    return each.groupBy("model").agg(F.count_if(F.col("part") == "lm").alias("lm_params"), F.count_if(F.col("part") == "renderer").alias("renderer_params"))
