"""Sample-level steps: smoothing in the enhancer's slot, truncation screen, trimming, volume, rate matching."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from voxtable.functions.binding import let

PEAK = 0.6


def moving_mean(frames: DataFrame, width: int = 1) -> DataFrame:
    """Noise reduction stand-in: centred mean over 2 x width + 1 frames of a segment."""
    by = Window.partitionBy("rec_id", "seg_id").orderBy("us", "frame").rowsBetween(-width, width)
    return frames.withColumn("amp", F.avg("amp").over(by))


def pack_samples(frames: DataFrame) -> DataFrame:
    """rec_id, seg_id, samples: a segment's amplitudes in time order."""
    packed = F.array_sort(F.collect_list(F.struct("us", "frame", "amp")))
    return frames.groupBy("rec_id", "seg_id").agg(F.transform(packed, lambda f: f["amp"]).alias("samples"))


def _mean(samples: Column) -> Column:
    return F.aggregate(samples, F.lit(0.0), lambda s, x: s + x) / F.size(samples)


def screen_truncated(packed: DataFrame, n: int = 1, floor: float = 100.0) -> DataFrame:
    """truncated: the energy of the leading or trailing n frames is above the floor, so speech was cut there."""
    lead, trail = _mean(F.slice("samples", 1, n)), _mean(F.slice("samples", -F.least(F.lit(n), F.size("samples")), F.least(F.lit(n), F.size("samples"))))
    return packed.withColumn("truncated", (lead > floor) | (trail > floor))


def trim_silence(packed: DataFrame, floor: float = 10.0) -> DataFrame:
    """Leading and trailing samples below the floor go; an all-silent segment becomes empty."""
    loud = F.filter(F.transform("samples", lambda x, i: F.when(x >= floor, i + 1)), lambda i: i.isNotNull())
    cut = lambda at: F.when(F.size(at) > 0, F.slice(F.col("samples"), F.array_min(at), F.array_max(at) - F.array_min(at) + 1)).otherwise(F.array().cast("array<double>"))
    return packed.withColumn("samples", let(loud, cut))


def normalize_volume(packed: DataFrame, peak: str = "max", target: float = PEAK) -> DataFrame:
    """Samples over their peak times the target; vol_degenerate marks peaks that are missing or not positive: kept as they are."""
    top = F.array_max("samples") if peak == "max" else F.array_max(F.transform("samples", F.abs))
    fine = F.coalesce(top > 0, F.lit(False))
    scaled = let(top, lambda t: F.transform("samples", lambda x: x / t * target))
    return packed.withColumn("vol_degenerate", ~fine).withColumn("samples", F.when(fine, scaled).otherwise(F.col("samples")))


def resample(col: Column, src_rate: float, dst_rate: float, mode: str = "linear") -> Column:
    """A sequence at another rate; ends are held."""
    n_out = F.floor(F.size(col) * F.lit(dst_rate) / F.lit(src_rate)).cast("int")
    at = lambda i: i.cast("double") * src_rate / dst_rate
    value = lambda k: F.element_at(col, F.least(k, F.size(col) - 1).cast("int") + 1).cast("double")

    def one(i: Column) -> Column:
        low = F.floor(at(i))
        if mode == "nearest":
            return value(F.floor(at(i) + 0.5))
        return value(low) + (at(i) - low) * (value(low + 1) - value(low))

    return F.when(n_out > 0, F.transform(F.sequence(F.lit(0), n_out - 1), one)).otherwise(F.array().cast("array<double>"))
