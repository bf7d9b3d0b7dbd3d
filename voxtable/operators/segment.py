"""Speech detection and segmentation: gaps and islands over frames, speaker turns, duration caps."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from voxtable.sources.tables import CLOCK

SECOND = 1_000_000 * CLOCK  # event microseconds in a second of audio
MAX_GAP_S = 5
MAX_LEN_S = 30


def drop_events(frames: DataFrame, kinds: tuple[str, ...], mode: str = "drop") -> DataFrame:
    """Event detection: frames of non-speech kinds go; with mode "cut" the next frame also begins a segment."""
    if mode == "drop":
        return frames.filter(~F.col("kind").isin(*kinds))
    order = Window.partitionBy("rec_id").orderBy("us", "frame")
    marked = frames.withColumn("cut", F.coalesce(F.lag(F.col("kind").isin(*kinds)).over(order), F.lit(False)))
    return marked.filter(~F.col("kind").isin(*kinds))


def voice_activity(frames: DataFrame, energy_floor: float) -> DataFrame:
    """Whether a frame is speech: its energy reaches the floor."""
    return frames.withColumn("is_speech", F.coalesce(F.abs("amp") >= energy_floor, F.lit(False)))


def with_segments(frames: DataFrame, max_gap_s: float = MAX_GAP_S) -> DataFrame:
    """seg_id by recording: a gap of over max_gap_s, or a cut, begins the next. One shuffle, by recording."""
    order = Window.partitionBy("rec_id").orderBy("us", "frame")
    begins = F.coalesce(F.col("us") - F.lag("us").over(order) > int(max_gap_s * SECOND), F.lit(True))
    if "cut" in frames.columns:
        begins = begins | F.col("cut")
    marked = frames.withColumn("begins", begins.cast("int"))
    return marked.withColumn("seg_id", F.sum("begins").over(order.rowsBetween(Window.unboundedPreceding, 0)) - 1).drop("begins")


def summarise(frames: DataFrame, *keys: str) -> DataFrame:
    """One row for each segment; grouping keys begin with the recording, so its partitioning is used again."""
    return frames.groupBy(*keys).agg(
        F.min("us").alias("us0"), F.max("us").alias("us1"), F.count(F.lit(1)).alias("n_frames"), F.round((F.max("us") - F.min("us")) / F.lit(float(SECOND)), 6).alias("dur_s")
    )


def segment_frames(frames: DataFrame, max_gap_s: float = MAX_GAP_S, nonspeech: tuple[str, ...] = ("error",)) -> DataFrame:
    return summarise(with_segments(drop_events(frames, nonspeech), max_gap_s), "rec_id", "seg_id")


def speaker_turns(rows: DataFrame, rec: str, order: str, speaker: str) -> DataFrame:
    """Diarization stand-in: runs of one speaker are turns."""
    by = Window.partitionBy(rec).orderBy(order)
    change = (~F.col(speaker).eqNullSafe(F.lag(speaker).over(by)) | F.lag(F.lit(1)).over(by).isNull()).cast("int")
    run = rows.withColumn("change", change).withColumn("run", F.sum("change").over(by.rowsBetween(Window.unboundedPreceding, 0)))
    return run.groupBy(rec, "run", speaker).agg(F.count(F.lit(1)).alias("n_turns"), F.min(order).alias("first_turn"))


def cap_duration(framed: DataFrame, max_len_s: float = MAX_LEN_S, cap: str = "grid") -> DataFrame:
    """Frames with seg_id -> frames with piece: "grid" by multiples of the cap from the segment's start, "greedy" a new piece when a
    frame would make the piece as long as the cap.

    Greedy folds a segment's ordered frames, held as one array: segments of speech between pauses are short; a recording never is one array.
    """
    size = int(max_len_s * SECOND)
    if cap == "grid":
        start = F.min("us").over(Window.partitionBy("rec_id", "seg_id"))
        return framed.withColumn("piece", F.floor((F.col("us") - start) / F.lit(size)).cast("int"))
    packed = framed.groupBy("rec_id", "seg_id").agg(F.array_sort(F.collect_list(F.struct("us", "frame"))).alias("fs"))
    zero = F.struct(F.col("fs")[0]["us"].alias("t0"), F.lit(0).alias("piece"), F.array().cast("array<struct<frame:bigint,us:bigint,piece:int>>").alias("out"))

    def step(s: F.Column, f: F.Column) -> F.Column:
        new = f["us"] - s["t0"] >= size
        piece = F.when(new, s["piece"] + 1).otherwise(s["piece"])
        return F.struct(F.when(new, f["us"]).otherwise(s["t0"]).alias("t0"), piece.alias("piece"), F.concat(s["out"], F.array(F.struct(f["frame"].alias("frame"), f["us"].alias("us"), piece.alias("piece")))).alias("out"))

    return packed.select("rec_id", "seg_id", F.explode(F.aggregate("fs", zero, step)["out"]).alias("f")).select("rec_id", "seg_id", "f.*")


def drop_short(pieces: DataFrame, min_len_s: float = 0.0) -> DataFrame:
    return pieces.filter(F.col("dur_s") >= min_len_s)
