"""Benchmark construction: stratified, hard, cross-lingual, emotion, expressive, continuation and dialect sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from voxtable.functions.binding import let
from voxtable.functions.hashing import draw
from voxtable.functions.units import words


def stratified(df: DataFrame, by: tuple[str, ...], n: int, key: str, seed: str) -> DataFrame:
    """n rows of each stratum in hash order; the engine keeps n of each before dealing them."""
    order = Window.partitionBy(*by).orderBy(draw(seed, F.col(key)), key)
    return df.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= n)


def hard_scores(df: DataFrame, key: str, text: str = "text") -> DataFrame:
    """rarity (mean of 1 / document frequency), alliteration (neighbours with one initial), repetition (1 - distinct share)."""
    toks = words(F.lower(F.col(text)))
    items = df.select(key, F.explode(F.array_distinct(toks)).alias("w"))
    counts = items.groupBy("w").agg(F.count(F.lit(1)).alias("df"))
    rarity = items.join(counts, "w").groupBy(key).agg(F.avg(1 / F.col("df")).alias("rarity"))
    n = F.size(toks)
    same = F.size(F.filter(F.arrays_zip(F.slice(toks, F.lit(1), F.greatest(n - 1, F.lit(0))), F.slice(toks, F.lit(2), F.greatest(n - 1, F.lit(0)))), lambda p: F.substring(p["0"], 1, 1) == F.substring(p["1"], 1, 1)))
    shaped = df.select("*", F.try_divide(same, n - 1).alias("alliteration"), (1 - F.try_divide(F.size(F.array_distinct(toks)), n)).alias("repetition"))
    return shaped.join(rarity, key, "left")


def hard(df: DataFrame, key: str, n: int, by: str = "lang") -> DataFrame:
    """The n rows of each language with the highest sum of the three scores, ties by key."""
    score = F.round(F.coalesce("rarity", F.lit(0.0)) + F.coalesce("alliteration", F.lit(0.0)) + F.coalesce("repetition", F.lit(0.0)), 9)
    scored = hard_scores(df, key).withColumn("score", score)
    return scored.withColumn("rank", F.row_number().over(Window.partitionBy(by).orderBy(F.desc("score"), key))).filter(F.col("rank") <= n)


def cross_lingual(prompts: DataFrame, targets: DataFrame, langs: list[str], n: int, key: str) -> DataFrame:
    """n pairs for every ordered pair of languages: direction rows join both sides on (language, rank), never a product."""
    spark = prompts.sparkSession
    pairs = spark.createDataFrame([(a, b) for a in langs for b in langs if a != b], "prompt_lang string, target_lang string")
    left = stratified(prompts.filter(F.col("lang").isin(langs)), ("lang",), n, key, "prompt").select(F.col("lang").alias("prompt_lang"), F.col(key).alias("prompt_id"), "rank")
    right = stratified(targets.filter(F.col("lang").isin(langs)), ("lang",), n, key, "target").select(F.col("lang").alias("target_lang"), F.col(key).alias("target_id"), "rank")
    return left.join(F.broadcast(pairs), "prompt_lang").join(right, ["target_lang", "rank"]).select("prompt_lang", "target_lang", "rank", "prompt_id", "target_id")


def tails(df: DataFrame, col: str, low: float, high: float) -> DataFrame:
    """Rows in either tail: tail is "low" or "high"."""
    cuts = df.agg(F.percentile(col, F.array(F.lit(low), F.lit(high))).alias("cut"))
    tail = F.when(F.col(col) <= F.col("cut")[0], "low").when(F.col(col) >= F.col("cut")[1], "high")
    return df.join(F.broadcast(cuts), F.lit(True)).withColumn("tail", tail).filter("tail IS NOT NULL").drop("cut")


def continuation(tokens: Column, prompt_s: float = 3.0, rate: int = 25) -> tuple[Column, Column]:
    """Prompt and remainder of a token array."""
    n = int(prompt_s * rate)
    return F.slice(tokens, 1, n), F.when(F.size(tokens) > n, F.slice(tokens, F.lit(n + 1), F.size(tokens) - n)).otherwise(F.slice(tokens, 1, 0))


def pair(df: DataFrame, key: str, by: str, seed: str = "pair") -> DataFrame:
    """Each row's partner is the next in its group's hash order, the last one's the first: nobody alone with others around pairs with itself."""
    w = Window.partitionBy(by).orderBy(draw(seed, F.col(key)), key)
    nxt = F.coalesce(F.lead(key).over(w), F.first(key).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    return df.withColumn("partner", nxt).filter(F.col("partner") != F.col(key))


def leakage(train: DataFrame, items: DataFrame, key: str, n: int = 8) -> DataFrame:
    """key, item_id: training rows that hold an item's text, found by its first n words and then verified whole; shorter items are looked for in every row."""
    gram = lambda t, i: F.xxhash64(F.array_join(F.slice(t, i, F.lit(n - 2)), " "))
    grams = lambda text: let(text, lambda t: F.transform(F.sequence(F.lit(1), F.size(t) - (n - 2) + 1), lambda i: gram(t, i)))
    toks, itoks = F.split("text", " "), F.split("text", " ")
    starts = items.filter(F.size(itoks) >= n).select("item_id", F.col("text").alias("item"), F.xxhash64(F.array_join(F.slice(itoks, 2, n - 2), " ")).alias("g"))
    held = train.filter(F.size(toks) >= n).select(key, F.explode(F.array_distinct(grams(toks))).alias("g"))
    met = held.join(starts, "g").select(key, "item_id", "item").distinct()
    held_whole = lambda df: df.filter(F.contains(F.col("text"), F.col("item"))).select(key, "item_id")
    short = items.filter(F.size(itoks) < n).select("item_id", F.col("text").alias("item"))
    return held_whole(train.join(met, key)).unionAll(held_whole(train.join(short))).distinct()
