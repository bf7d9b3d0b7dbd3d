"""Bounded scalar quantiser: down-projection, rounding into [-K, K], mixed-radix index, and back."""

from __future__ import annotations

from dataclasses import dataclass
from hashlib import md5

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from voxtable.functions.vectors import project, squared_distance


@dataclass(frozen=True)
class FsqSpec:
    """D digits in [-K, K]; a seeded sign projection from width values, scaled by gain."""

    digits: int = 4
    k: int = 4
    width: int = 64
    gain: float = 2.0
    bound: str = "clip"
    offset: str = "shifted"
    first: int = 0  # first value of the vector that is read: views of one embedding

    @property
    def radix(self) -> int:
        return 2 * self.k + 1

    @property
    def codebook_size(self) -> int:
        return self.radix**self.digits

    @property
    def codebook_size_as_printed(self) -> int:
        """One power less: kept for comparison only; the index reaches codebook_size."""
        return self.radix ** (self.digits - 1)

    def down(self) -> list[list[float]]:
        """Signs over sqrt(width), times the gain."""
        sign = lambda j, i: 1.0 if int(md5(f"proj|{j}|{i}".encode()).hexdigest()[:8], 16) % 2 == 0 else -1.0
        return [[self.gain * sign(j, i) / self.width**0.5 for i in range(self.width)] for j in range(self.digits)]

    def up(self) -> list[list[float]]:
        """The transpose, scaled so that up x down keeps the span of the rows: hidden width rows of digits values."""
        down = self.down()
        return [[down[j][i] / self.gain**2 for j in range(self.digits)] for i in range(self.width)]


def codes(v: Column, spec: FsqSpec) -> Column:
    """Projected values, rounded to six places so that engines agree at the edges."""
    part = F.slice(v, spec.first + 1, spec.width)
    return F.transform(project(part, spec.down()), lambda x: F.round(x, 6))


def bounded_round(x: Column, k: int, bound: str = "clip") -> Column:
    """Digits in [-K, K]: halves go away from zero."""
    if bound == "tanh":
        return F.transform(x, lambda v: F.round(F.tanh(v) * k).cast("int"))
    return F.transform(x, lambda v: F.round(F.greatest(F.lit(-float(k)), F.least(F.lit(float(k)), v))).cast("int"))


def encode(digits: Column, k: int, offset: str = "shifted") -> Column:
    """Index in radix 2K + 1, first digit lowest. "printed" keeps signed digits; "shifted" adds K to each."""
    add = k if offset == "shifted" else 0
    radix = 2 * k + 1
    return F.aggregate(F.reverse(digits), F.lit(0).cast("long"), lambda s, d: s * radix + d + add)


def decode(token: Column, digits: int, k: int, offset: str = "shifted") -> Column:
    radix = 2 * k + 1
    shifted = token if offset == "shifted" else token + F.lit(sum(k * radix**j for j in range(digits)))
    places = F.array(*[F.lit(radix**j).cast("long") for j in range(digits)])
    return F.transform(places, lambda p: (F.pmod(F.floor(shifted / p), F.lit(radix)) - k).cast("int"))


def reconstruct(digits: Column, spec: FsqSpec) -> Column:
    return project(F.transform(digits, lambda d: d.cast("double")), spec.up())


def tokenize(df: DataFrame, spec: FsqSpec, col: str = "embedding") -> DataFrame:
    """digits and token beside the vector: one narrow stage."""
    digits = bounded_round(codes(F.col(col), spec), spec.k, spec.bound)
    return df.withColumn("digits", digits).withColumn("token", encode(F.col("digits"), spec.k, spec.offset))


def reconstruction_error(spec: FsqSpec, col: str = "embedding") -> Column:
    """Mean squared error of a tokenized row's vector."""
    part = F.slice(F.col(col), spec.first + 1, spec.width)
    return squared_distance(part, reconstruct(F.col("digits"), spec)) / spec.width


def ste_grad(grad: Column, x: Column, k: int) -> Column:
    """Straight-through gradient: passed on inside the bound, nothing outside."""
    return F.zip_with(grad, x, lambda g, v: F.when(F.abs(v) <= k, g).otherwise(F.lit(0.0)))


