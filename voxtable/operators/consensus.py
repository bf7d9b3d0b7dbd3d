"""Transcripts: language identification, several recognisers, and the agreement that selects among them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from voxtable.functions.binding import let
from voxtable.functions.digests import drawn_together
from voxtable.functions.hashing import draw
from voxtable.functions.units import one_point_each, words

#: Recogniser stand-ins: chances in 10,000 of dropping, reversing and doubling a word.
RECOGNISERS = {"asr_1": (100, 150, 50), "asr_2": (300, 300, 100), "asr_3": (800, 800, 200)}
THRESHOLD = 0.15
#: Frequent words by language, for the identification stand-in.
STOP_WORDS = {"de": ("der", "die", "und", "das", "ist"), "en": ("the", "and", "of", "is", "that"), "es": ("los", "las", "por", "una", "del"), "fr": ("les", "des", "est", "dans", "une")}


def identify_language(rows: DataFrame) -> DataFrame:
    """guess: the language most of whose frequent words occur, ties by code; null where none does."""
    tokens = F.split(F.lower(F.regexp_replace("text", r"[^\p{L}]+", " ")), " ")
    hits = lambda ws, stop: F.size(F.filter(ws, lambda w: w.isin(*stop)))
    best = let(tokens, lambda ws: F.array_min(F.array(*[F.struct((-hits(ws, stop)).alias("n"), F.lit(lang).alias("lang")) for lang, stop in STOP_WORDS.items()])))
    return rows.withColumn("guess", F.when(best["n"] < 0, best["lang"]))


def corrupt(text: F.Column, key: F.Column, system: str, rates: tuple[int, int, int]) -> F.Column:
    """A seeded copy of a text: words dropped, reversed, or followed by a filler. Edits are at most those drawn."""
    drop, swap, extra = rates

    def one(w: F.Column, i: F.Column) -> F.Column:
        changed = lambda u: F.when(u < drop, F.lit("")).when(u < drop + swap, F.reverse(w)).when(u < drop + swap + extra, F.concat(w, F.lit(" uh"))).otherwise(w)
        return let(F.pmod(draw(system, key, i), F.lit(10_000)), changed)

    return F.array_join(F.filter(F.transform(words(text), one), lambda w: w != ""), " ")


def transcribe(rows: DataFrame, systems: dict[str, tuple[int, int, int]] | None = None) -> DataFrame:
    """utt_id, text -> utt_id, system, ref, hyp: one row for each recogniser."""
    systems = systems or RECOGNISERS
    each = F.array(*[F.struct(F.lit(s).alias("system"), corrupt(F.col("text"), F.col("utt_id"), s, r).alias("hyp")) for s, r in systems.items()])
    return rows.select("utt_id", F.col("text").alias("ref"), F.explode(each).alias("t")).select("utt_id", "ref", "t.*")


def words_said(ws: list[bytes], changed: list[tuple[int, int]], rates: tuple[int, int, int]) -> list[bytes]:
    """The words of corrupt, by (place, draw) of those that change: dropped, reversed or followed by a filler."""
    drop, swap, _ = rates
    out, done = [], 0
    for i, u in changed:
        out += ws[done:i]
        if u >= drop:
            out += [ws[i].decode()[::-1].encode()] if u < drop + swap else [ws[i], b"uh"]
        done = i + 1
    return out + ws[done:]


def transcribe_together(rows: DataFrame, systems: dict[str, tuple[int, int, int]] | None = None) -> DataFrame:
    """The rows with ts, the transcripts of transcribe by system in one row, with an utterance's words split once and drawn over arrays: the engine's md5 takes
    some six microseconds a word and system."""
    names = sorted((systems := systems or RECOGNISERS))

    def said(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for texts, keys in batches:
            out = []
            for key_texts in drawn_together(texts, keys, [n.encode() for n in names]):
                for ws, draws in key_texts:
                    hyps = []
                    for name, u in zip(names, draws, strict=True) if ws is not None else ():
                        u = u % 10_000
                        hits = np.flatnonzero(u < sum(systems[name]))
                        hyps.append(b" ".join(words_said(ws, list(zip(hits.tolist(), u[hits].tolist(), strict=True)), systems[name])).decode("utf-8", "surrogatepass"))
                    out.append(hyps or [None] * len(names))
            yield pd.Series(out, dtype=object)

    said.__annotations__ = {"batches": Iterator[tuple[pd.Series, pd.Series]], "return": Iterator[pd.Series]}
    heard = rows.withColumn("said", F.pandas_udf(said, "array<string>")("text", F.col("utt_id").cast("string")))
    each = F.array(*[F.struct(F.lit(s).alias("system"), F.get("said", F.lit(i)).alias("hyp")) for i, s in enumerate(names)])
    return heard.select(*rows.columns, each.alias("ts"))


def _packed(transcripts: DataFrame, direction: str, *keep: str) -> DataFrame:
    """utt_id, ts (system, hyp by system), ps (s1, s2, rate): all pairs of an utterance's transcripts in one row, its words coded once.

    The reference of a rate is the first system ("first"), both in turn ("ordered"), or both at once ("symmetric").
    """
    rows = transcripts if "ts" in transcripts.columns else transcripts.groupBy("utt_id").agg(F.array_sort(F.collect_list(F.struct("system", "hyp"))).alias("ts"))

    def rate(a: F.Column, b: F.Column) -> F.Column:
        def of(d: F.Column) -> F.Column:
            n, m = a["n"], b["n"]
            out = {"first": F.try_divide(d, n), "symmetric": F.try_divide(2 * d, n + m), "ordered": (F.try_divide(d, n) + F.try_divide(d, m)) / 2}[direction]
            return F.struct(a["system"].alias("s1"), b["system"].alias("s2"), out.cast("double").alias("rate"))

        return let(F.levenshtein(a["code"], b["code"]), of)

    def coded(ws: F.Column) -> F.Column:
        one = lambda known: F.transform(ws, lambda w: F.struct(w["system"].alias("system"), one_point_each(w["ws"], known).alias("code"), F.size(w["ws"]).alias("n")))
        return let(F.array_distinct(F.flatten(F.transform(ws, lambda w: w["ws"]))), one)

    split = F.transform("ts", lambda t: F.struct(t["system"].alias("system"), words(t["hyp"]).alias("ws")))
    pairs = lambda cs: F.flatten(F.transform(cs, lambda a: F.transform(F.filter(cs, lambda b: b["system"] > a["system"]), lambda b: rate(a, b))))
    return rows.select("utt_id", *keep, "ts", let(split, lambda ws: let(coded(ws), pairs)).alias("ps"))


def pairwise(transcripts: DataFrame, direction: str = "first") -> DataFrame:
    """utt_id, s1, s2, rate: word error of each pair of systems, within a row for each utterance: no self-join."""
    return _packed(transcripts, direction).select("utt_id", F.explode("ps").alias("p")).select("utt_id", "p.*")


def _mean(rates: F.Column) -> F.Column:
    """Mean of the rates that are not null; null without any."""
    return let(F.array_compact(rates), lambda r: F.try_divide(F.aggregate(r, F.lit(0.0), lambda s, x: s + x), F.size(r)))


def select(transcripts: DataFrame, threshold: float = THRESHOLD, scope: str = "utterance", direction: str = "first", pick: str = "all", keep: tuple[str, ...] = ()) -> DataFrame:
    """Transcripts whose mean pairwise error is below the threshold (strictly).

    scope "utterance": one mean of all pairs; "transcript": a system against the others. pick "all", "medoid" (least mean error to the
    others, then system name) or "priority" (system name). One shuffle, by utterance; what lambdas capture is bound once. Transcripts as of transcribe_together
    need none if no utt_id repeats; with columns to keep, an utterance without a transcript below the threshold has a row of nulls.
    """
    rates = lambda ps: F.transform(ps, lambda p: p["rate"])

    def ranked(ps: F.Column) -> F.Column:
        own = lambda t: _mean(rates(F.filter(ps, lambda p: (p["s1"] == t["system"]) | (p["s2"] == t["system"]))))

        def with_mean(mean: F.Column) -> F.Column:
            error = (lambda o: mean) if scope == "utterance" else (lambda o: o)
            one = lambda t, o: F.struct(o.isNull().alias("none"), F.round(o, 9).alias("near"), t["system"].alias("system"), t["hyp"].alias("hyp"), error(o).alias("error"))
            return F.filter(F.transform("ts", lambda t: let(own(t), lambda o: one(t, o))), lambda r: r["error"] < threshold)

        return let(_mean(rates(ps)), with_mean)

    rs = let(F.col("ps"), ranked)
    if pick == "medoid":
        rs = F.slice(F.array_sort(rs), 1, 1)
    elif pick == "priority":
        rs = F.slice(F.array_sort(F.transform(rs, lambda r: F.struct(r["system"].alias("system"), r["hyp"].alias("hyp"), r["error"].alias("error")))), 1, 1)
    rows = _packed(transcripts, direction, *keep).select("utt_id", *keep, (F.explode_outer if keep else F.explode)(rs).alias("t"))
    return rows.select("utt_id", *keep, "t.system", "t.hyp", "t.error")
