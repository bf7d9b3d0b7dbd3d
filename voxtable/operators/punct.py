"""Punctuation from pauses: long ones after bare words gain a comma, short ones lose their mark."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from voxtable.functions.binding import let
from voxtable.functions.digests import drawn_together
from voxtable.functions.hashing import draw
from voxtable.functions.units import words

ADD_MS, DROP_MS = 300, 50
MARKS = ",;:.?!"
MARKS_WIDE = "，；：。？！"


def align(text: Column, key: Column) -> Column:
    """Aligner stand-in: word, mark and following pause (hashed; none after the last word)."""
    mark = lambda w: F.regexp_extract(w, r"([,;:.?!]?)$", 1)
    gap = lambda i: F.pmod(draw("gap", key, i), F.lit(600)).cast("int")
    one = lambda ws: lambda w, i: F.struct(F.regexp_replace(w, r"[,;:.?!]$", "").alias("word"), mark(w).alias("punct"), F.when(i < F.size(ws) - 1, gap(i)).alias("gap_ms"))
    return let(words(text), lambda ws: F.transform(ws, one(ws)))


def adjusted(aligned: Column, add_ms: int = ADD_MS, drop_ms: int = DROP_MS, marks: str = MARKS) -> Column:
    """Both bounds are inclusive; a mark before a long pause stays; no pause known: no change."""

    def one(w: Column) -> Column:
        bare = w["punct"] == ""
        kept = F.when(bare & (w["gap_ms"] >= add_ms), F.lit(",")).when((w["gap_ms"] <= drop_ms) & F.contains(F.lit(marks), w["punct"]), F.lit("")).otherwise(w["punct"])
        return F.concat(w["word"], kept)

    return F.array_join(F.transform(aligned, one), " ")


#: Line ends that are no white space; a mark before one ends a word too.
_ENDS = tuple(c.encode() for c in "\u0085\u2028\u2029")


def _bare(word: bytes) -> tuple[bytes, bytes]:
    """A word without its mark, and the mark."""
    end = next((e for e in _ENDS if word.endswith(e)), b"")
    body = word[: len(word) - len(end)]
    return (body[:-1] + end, body[-1:]) if body[-1:] and body[-1:] in MARKS.encode() else (word, b"")


def adjust_together(rows: DataFrame, add_ms: int = ADD_MS, drop_ms: int = DROP_MS) -> DataFrame:
    """adjust, with pauses drawn over arrays in an Arrow map: the engine's md5 takes some six microseconds a word."""

    def one(ws: list[bytes], gaps: list[int]) -> str:
        out = []
        for w, gap in zip(ws[:-1], gaps[:-1], strict=True):
            word, mark = _bare(w)
            if not mark and gap >= add_ms:
                mark = b","
            elif gap <= drop_ms:
                mark = b""
            out.append(word + mark)
        return b" ".join(out + [b"".join(_bare(w)) for w in ws[-1:]]).decode("utf-8", "surrogatepass")

    def told(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for texts, keys in batches:
            out = [None if ws is None else one(ws, (draws[0] % 600).tolist()) for some in drawn_together(texts, keys, [b"gap"]) for ws, draws in some]
            yield pd.Series(out, dtype=object)

    told.__annotations__ = {"batches": Iterator[tuple[pd.Series, pd.Series]], "return": Iterator[pd.Series]}
    return rows.withColumn("text", F.pandas_udf(told, "string")("text", F.col("utt_id").cast("string")))


def adjust(rows: DataFrame, **bounds: int) -> DataFrame:
    return rows.withColumn("text", adjusted(align(F.col("text"), F.col("utt_id")), **bounds))
