"""Distributions over codes: stable log-softmax, reproducible Gumbel noise, relaxed samples, divergences."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from voxtable.functions.binding import let
from voxtable.functions.hashing import uniform


def _sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def log_softmax(logits: Column) -> Column:
    """Array of log-probabilities, shifted by the largest logit."""
    shift = lambda a: F.array_max(a) + F.ln(let(F.array_max(a), lambda top: _sum(F.transform(a, lambda y: F.exp(y - top)))))
    return let(logits, lambda a: let(shift(a), lambda s: F.transform(a, lambda x: x - s)))


def softmax(logits: Column) -> Column:
    return F.transform(log_softmax(logits), F.exp)


def gumbel(seed: str, *keys: Column) -> Column:
    return -F.ln(-F.ln(uniform(seed, *keys)))


def gumbel_softmax(logits: Column, noise: Column, tau: float, mode: str = "soft") -> Column:
    """Weights of a relaxed sample at temperature tau; "hard" and "straight" give the arg max as one-hot (the latter takes the
    relaxed weights' gradient, see reward.optimize). Ties go to the first code."""
    shifted = F.zip_with(logits, noise, lambda x, g: (x + g) / tau)
    if mode == "soft":
        return softmax(shifted)
    return let(shifted, lambda a: let(F.array_position(a, F.array_max(a)), lambda best: F.transform(a, lambda x, i: (i + 1 == best).cast("double"))))


def token_kl(p: Column, q: Column) -> Column:
    """Divergence of one step: sum over codes of p ln(p / q); codes without mass add nothing."""
    return _sum(F.zip_with(p, q, lambda a, b: F.when(a > 0, a * F.ln(a / b)).otherwise(F.lit(0.0))))


def expected(weights: Column, values: Column) -> Column:
    return _sum(F.zip_with(weights, values, lambda a, b: a * b))
