"""Error measures between references and hypotheses."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from voxtable.functions.hashing import uniform
from voxtable.functions.units import edits, length

#: Distribution function of the Poisson law with mean one, from none to six.
POISSON_ONE = (0.36787944, 0.73575888, 0.91969860, 0.98101184, 0.99634015, 0.99940582, 0.99991676)


def scored(rows: DataFrame, unit: Column) -> DataFrame:
    """edits, n_ref beside ref and hyp; computed once, aggregated often."""
    return rows.withColumn("edits", edits(F.col("ref"), F.col("hyp"), unit).cast("long")).withColumn("n_ref", length(F.col("ref"), unit).cast("long"))


def corpus_rate(rows: DataFrame, *by: str) -> DataFrame:
    """n, micro (all edits over all reference units) and macro (mean of utterances), one pass."""
    return rows.groupBy(*by).agg(
        F.count(F.lit(1)).alias("n"), F.try_divide(F.sum("edits"), F.sum("n_ref")).alias("micro"), F.avg(F.try_divide("edits", "n_ref")).alias("macro")
    )


def within(ref: Column, hyp: Column, limit: int) -> Column:
    """Whether at most limit character edits part them; the distance stops early beyond."""
    return F.levenshtein(ref, hyp, limit) >= 0


def _counts(ref: list[str], hyp: list[str]) -> tuple[int, int, int]:
    """Substitutions, deletions, insertions of one cheapest alignment, substitutions first."""
    m, n = len(ref), len(hyp)
    cost = np.zeros((m + 1, n + 1), dtype=np.int32)
    cost[:, 0], cost[0, :] = np.arange(m + 1), np.arange(n + 1)
    for i in range(1, m + 1):
        for j in range(1, n + 1):
            cost[i, j] = min(cost[i - 1, j - 1] + (ref[i - 1] != hyp[j - 1]), cost[i - 1, j] + 1, cost[i, j - 1] + 1)
    s = d = k = 0
    i, j = m, n
    while i or j:
        if i and j and cost[i, j] == cost[i - 1, j - 1] + (ref[i - 1] != hyp[j - 1]):
            s += ref[i - 1] != hyp[j - 1]
            i, j = i - 1, j - 1
        elif i and cost[i, j] == cost[i - 1, j] + 1:
            d, i = d + 1, i - 1
        else:
            k, j = k + 1, j - 1
    return int(s), d, k


def align_counts(rows: DataFrame) -> DataFrame:
    """sub, del, ins of the word alignment: the one measure here that needs a back-trace, hence an Arrow map."""

    def one(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            found = [_counts((r or "").split(), (h or "").split()) for r, h in zip(b["ref"], b["hyp"], strict=True)]
            yield b.assign(sub=[f[0] for f in found], dele=[f[1] for f in found], ins=[f[2] for f in found])

    kinds = ", ".join(f"`{c}` {t}" for c, t in rows.dtypes)
    return rows.mapInPandas(one, f"{kinds}, sub int, dele int, ins int").withColumnRenamed("dele", "del")


def bootstrap(rows: DataFrame, by: str, key: str, replicates: int, seed: str = "boot") -> DataFrame:
    """by, replicate, micro: each row weighs by hashed Poisson draws, so all replicates come from one pass without resampling."""
    u = uniform(seed, F.col(key), F.col("replicate"))
    weight = sum((F.when(u > p, F.lit(1)).otherwise(F.lit(0)) for p in POISSON_ONE), F.lit(0))
    each = rows.select(by, key, "edits", "n_ref", F.explode(F.sequence(F.lit(1), F.lit(replicates))).alias("replicate")).withColumn("w", weight)
    return each.groupBy(by, "replicate").agg(F.try_divide(F.sum(F.col("w") * F.col("edits")), F.sum(F.col("w") * F.col("n_ref"))).alias("micro"))
