"""Rewards from recognisers over tokens, and policies optimised through relaxed samples.

State of a policy is a small table (context, logits); data size enters only through counts by context, so an optimiser step moves
contexts x codes numbers however many utterances there are.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from voxtable.operators.dist import expected, softmax, token_kl


def fit_token2text(pairs: DataFrame, token: str, symbol: str, n_symbols: int, alpha: float = 0.5) -> DataFrame:
    """token, symbol, logp: smoothed log P(symbol | token) of a recogniser over tokens."""
    counts = pairs.groupBy(token, symbol).agg(F.count(F.lit(1)).alias("n"))
    total = F.sum("n").over(Window.partitionBy(token))
    return counts.select(token, symbol, F.ln((F.col("n") + alpha) / (total + alpha * n_symbols)).alias("logp"))


def asr(sampled: DataFrame, table: DataFrame, token: str, symbol: str, floor: float, by: str, reduce: str = "sum") -> DataFrame:
    """Reward of each utterance: log posterior of its symbols given its sampled tokens, per position, summed or averaged."""
    scored = sampled.join(table, [token, symbol], "left").withColumn("logp", F.coalesce("logp", F.lit(floor)))
    return scored.groupBy(by).agg((F.sum if reduce == "sum" else F.avg)("logp").alias("reward"))


def multi(rows: DataFrame, tasks: dict[str, str], weights: dict[str, float] | None = None) -> DataFrame:
    """rewards (by task) and their weighted sum: expressions give each task's log posterior."""
    weights = weights or {}
    each = F.create_map(*[x for t, e in tasks.items() for x in (F.lit(t), F.expr(e).cast("double"))])
    total = sum((F.expr(e).cast("double") * F.lit(weights.get(t, 1.0)) for t, e in tasks.items()), F.lit(0.0))
    return rows.withColumn("rewards", each).withColumn("reward", total)


def objective(policy: DataFrame, beta: float) -> DataFrame:
    """policy: ctx, n, logits, ref (logits), values (reward of each code) -> reward, kl, objective, means over tokens."""
    p, q = softmax(F.col("logits")), softmax(F.col("ref"))
    rows = policy.select("n", expected(p, F.col("values")).alias("r"), token_kl(p, q).alias("d"))
    mean = lambda c: F.sum(F.col(c) * F.col("n")) / F.sum("n")
    return rows.agg(mean("r").alias("reward"), mean("d").alias("kl")).withColumn("objective", F.col("reward") - beta * F.col("kl"))


@dataclass(frozen=True)
class Settings:
    iters: int = 20
    lr: float = 0.5
    beta: float = 0.1
    tau: float = 1.0
    seed: int = 1
    samples: int = 16
    tol: float = 1e-6


def _noise(seed: int, step: int, ctx: str, shape: tuple[int, int]) -> np.ndarray:
    import zlib

    rng = np.random.default_rng([seed, step, zlib.crc32(ctx.encode())])
    return -np.log(-np.log(rng.uniform(1e-12, 1.0, shape)))


def gradient(theta: np.ndarray, ref: np.ndarray, values: np.ndarray, noise: np.ndarray, cfg: Settings, score_function: bool = False) -> tuple[np.ndarray, float, float]:
    """Gradient of mean relaxed reward - beta x divergence by the logits of one context; reward and divergence.

    Relaxed: back through w = softmax((theta + noise) / tau). score_function: the loop-style comparator, with sampled tokens
    and a mean baseline.
    """
    p = np.exp(theta - theta.max())
    p /= p.sum()
    q = np.exp(ref - ref.max())
    q /= q.sum()
    ratio = np.log(p / q)
    kl = float((p * ratio).sum())
    if score_function:
        picked = (theta + noise).argmax(axis=1)
        r = values[picked]
        hot = np.eye(len(theta))[picked]
        grad = ((r - r.mean())[:, None] * (hot - p)).mean(axis=0)
        reward = float(r.mean())
    else:
        x = (theta + noise) / cfg.tau
        w = np.exp(x - x.max(axis=1, keepdims=True))
        w /= w.sum(axis=1, keepdims=True)
        mean = w @ values
        grad = (w * (values - mean[:, None])).mean(axis=0) / cfg.tau
        reward = float(mean.mean())
    return grad - cfg.beta * p * (ratio - kl), reward, kl


def optimize(policy: DataFrame, cfg: Settings, score_function: bool = False) -> tuple[DataFrame, list[dict]]:
    """policy (ctx, n, logits, ref, values) -> the same with optimised logits, and the trace of objective, reward, kl, norm.

    The table is dealt by context; each step is an Arrow map over contexts (data-parallel, no shuffle), of which the
    driver sees four sums. Lineage is cut every few steps at the shared checkpoint folder where one is set.
    """
    spark = policy.sparkSession
    total = policy.agg(F.sum("n")).first()[0] or 0
    trace: list[dict] = []
    now = policy.select("ctx", "n", "logits", "ref", "values")
    for step in range(cfg.iters):

        def one(batches, step=step):  # noqa: ANN001, ANN202
            for b in batches:
                theta, out = [], []
                for ctx, n, logits, ref, values in zip(b["ctx"], b["n"], b["logits"], b["ref"], b["values"], strict=True):
                    t = np.array(logits, dtype=float)
                    g, r, kl = gradient(t, np.array(ref), np.array(values), _noise(cfg.seed, step, ctx, (cfg.samples, len(t))), cfg, score_function)
                    theta.append((t + cfg.lr * g).tolist())
                    out.append((n * r, n * kl, n * float(np.abs(g).max())))
                yield b.assign(logits=theta, r=[o[0] for o in out], kl=[o[1] for o in out], g=[o[2] for o in out])

        schema = "ctx string, n bigint, logits array<double>, ref array<double>, values array<double>, r double, kl double, g double"
        stepped = now.mapInPandas(one, schema).persist()
        sums = stepped.agg(F.sum("r"), F.sum("kl"), F.sum("g")).first()
        r, kl, g = ((x or 0.0) / max(total, 1) for x in sums)
        trace.append({"step": step, "reward": r, "kl": kl, "objective": r - cfg.beta * kl, "norm": g})
        now = stepped.drop("r", "kl", "g")
        if step % 5 == 4 and spark.sparkContext.getCheckpointDir():
            now = now.checkpoint()
        if g < cfg.tol:
            break
    return now, trace


def trace_frame(spark, trace: list[dict]) -> DataFrame:  # noqa: ANN001
    return spark.createDataFrame(pd.DataFrame(trace))


def side_effects(before: DataFrame, after: DataFrame) -> DataFrame:
    """metric, before, after, delta: every metric of either side."""
    both = before.withColumnRenamed("value", "before").join(after.withColumnRenamed("value", "after"), "metric", "full")
    return both.withColumn("delta", F.col("after") - F.col("before"))


def spread(candidates: DataFrame, by: str, raw: str, rendered: str) -> DataFrame:
    """Variance of rewards among candidates of one text, of tokens and after rendering."""
    return candidates.groupBy(by).agg(F.var_samp(raw).alias("token_var"), F.var_samp(rendered).alias("rendered_var"))


