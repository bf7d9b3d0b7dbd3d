"""Next-token policies from smoothed counts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from voxtable.functions.binding import let


def contexts(seq: DataFrame, key: str, order: tuple[str, ...], token: str, history: int = 1) -> DataFrame:
    """Each token with its history (the tokens before it, "^" at the start)."""
    by = Window.partitionBy(key).orderBy(*order)
    past = [F.coalesce(F.lag(token, h).over(by).cast("string"), F.lit("^")) for h in range(history, 0, -1)]
    return seq.withColumn("ctx", F.concat_ws(" ", *past) if past else F.lit("*"))


def from_counts(ctx: DataFrame, token: str, n_codes: int, alpha: float = 1.0) -> DataFrame:
    """ctx, code, n, logit: ln((n + alpha) / (N + alpha x codes)) for the codes seen after a context."""
    counts = ctx.groupBy("ctx", F.col(token).alias("code")).agg(F.count(F.lit(1)).alias("n"))
    total = F.sum("n").over(Window.partitionBy("ctx"))
    return counts.withColumn("logit", F.ln((F.col("n") + alpha) / (total + alpha * n_codes)))


def dense(counts: DataFrame, codes: list[str], alpha: float = 1.0) -> DataFrame:
    """ctx, logits: an array over all codes, in their order; for small codebooks."""
    seen = F.map_from_entries(F.collect_list(F.struct("code", "n")))
    packed = counts.groupBy("ctx").agg(seen.alias("seen"), F.sum("n").alias("total"))
    one = lambda c: F.ln((F.coalesce(F.try_element_at("seen", F.lit(c)), F.lit(0)) + alpha) / (F.col("total") + alpha * len(codes)))
    return packed.select("ctx", "total", F.array(*[one(c) for c in codes]).alias("logits"))


def perplexity(ctx: DataFrame, model: DataFrame, token: str, n_codes: int, alpha: float = 1.0) -> DataFrame:
    """n and perplexity of a token sequence under counts (ctx, code, n, logit); unseen pairs fall back to the smoothed zero count."""
    totals = model.groupBy("ctx").agg(F.sum("n").alias("total"))
    rows = ctx.join(model.select("ctx", F.col("code").alias(token), "logit"), ["ctx", token], "left").join(totals, "ctx", "left")
    score = F.coalesce("logit", F.ln(F.lit(alpha) / (F.coalesce("total", F.lit(0)) + alpha * n_codes)))
    return rows.agg(F.count(F.lit(1)).alias("n"), F.exp(-F.avg(score)).alias("perplexity"))


def nested_perplexity(rows: DataFrame, tokens: Column, subsets: dict[str, Column], n_codes: int, alpha: float = 1.0, scored: Column | None = None) -> DataFrame:
    """subset, n, perplexity: of the sequences (those that scored marks) under pair counts of each subset of the rows, all in one pass.

    Only counts of distinct pairs are shuffled, so the sequences' length does not matter after the first scan.
    """
    pairs = let(tokens, lambda t: F.zip_with(F.slice(F.concat(F.array(F.lit("^")), t), F.lit(1), F.size(t)), t, lambda a, b: F.struct(a.alias("ctx"), b.alias("code"))))
    flags = {f"in_{i}": on for i, on in enumerate(subsets.values())}
    each = rows.select(*[on.alias(c) for c, on in flags.items()], (F.lit(True) if scored is None else scored).alias("scored"), F.explode(pairs).alias("p")).select(*flags, "scored", "p.*")
    counts = each.groupBy("ctx", "code").agg(F.count_if("scored").alias("n"), *[F.count_if(c).alias(c) for c in flags])
    by = Window.partitionBy("ctx")
    cells = counts.select("n", *[F.struct(F.lit(name).alias("subset"), F.ln((F.col(c) + alpha) / (F.sum(c).over(by) + alpha * n_codes)).alias("logit")).alias(c) for c, name in zip(flags, subsets, strict=True)])
    long = cells.select("n", F.explode(F.array(*flags)).alias("x")).select("n", "x.*")
    return long.groupBy("subset").agg(F.sum("n").alias("n"), F.exp(-F.sum(F.col("n") * F.col("logit")) / F.sum("n")).alias("perplexity"))
