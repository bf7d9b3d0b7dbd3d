"""Pronunciation lexicon and mixed word-phoneme sequences."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from voxtable.functions.hashing import draw

#: Letter-to-sound stand-ins by language: every letter is a phone but for these, applied in order.
SOUNDS = {"de": (("sch", "S"), ("ch", "x"), ("ei", "Y"), ("z", "ts")), "en": (("th", "T"), ("sh", "S"), ("ea", "i"), ("c", "k")), "es": (("ll", "y"), ("qu", "k"), ("z", "T"), ("j", "x")), "fr": (("eau", "o"), ("ou", "u"), ("ch", "S"), ("ai", "e"))}


def symbols(text: Column) -> Column:
    """Lower-case letter runs of a text."""
    return F.filter(F.split(F.lower(F.regexp_replace(text, r"[^\p{L}]+", " ")), " "), lambda w: w != "")


def sound(word: Column, lang: Column) -> Column:
    """The phone string of a word by its language's rule."""
    out = word
    for code, rules in SOUNDS.items():
        spelt = word
        for letters, phone in rules:
            spelt = F.replace(spelt, F.lit(letters), F.lit(phone))
        out = F.when(lang == code, spelt).otherwise(out)
    return out


def build(rows: DataFrame) -> DataFrame:
    """text, lang -> symbol, lang, phones, n_readings, is_mono: distinct readings of a symbol over all languages.

    One shuffle by symbol; the vocabulary, not the text, is what is dealt.
    """
    words = rows.select(F.explode(symbols(F.col("text"))).alias("symbol"), "lang").distinct()
    read = words.withColumn("phones", sound(F.col("symbol"), F.col("lang")))
    by = read.groupBy("symbol").agg(F.countDistinct("phones").alias("n_readings"), F.array_sort(F.collect_set(F.struct("lang", "phones"))).alias("all"))
    return by.select("symbol", F.explode("all").alias("r"), "n_readings").select("symbol", "r.lang", "r.phones", "n_readings", (F.col("n_readings") == 1).alias("is_mono"))


def load(spark: SparkSession, path: str) -> DataFrame:
    """A lexicon from CSV with a header: symbol, lang, phones."""
    return spark.read.schema("symbol string, lang string, phones string").option("header", True).csv(path)


def placed(rows: DataFrame, lexicon: DataFrame, *keep: str) -> DataFrame:
    """kept columns, pos, symbol, pick (the smallest reading of any, the stand-in predictor's), n_readings: every symbol at its place."""
    readings = lexicon.groupBy("symbol").agg(F.min("phones").alias("pick"), F.max("n_readings").alias("n_readings"))
    return rows.select(*keep, F.posexplode(symbols(F.col("text"))).alias("pos", "symbol")).join(readings, "symbol", "left")


def replaced(which: Column) -> Column:
    """Whether a placed symbol gives way to its phones: "mono" where it has one reading, "all" where it has any."""
    return F.col("pick").isNotNull() & ((which == "all") | (F.col("n_readings") == 1))


def piece(shown: Column, render: Column) -> Column:
    """Phones between slashes, alone ("phones") or behind the symbol shown ("both")."""
    phones = F.concat(F.lit("/"), F.col("pick"), F.lit("/"))
    return F.when(render == "both", F.concat(shown, phones)).otherwise(phones)


def inpaint(rows: DataFrame, lexicon: DataFrame, which: str = "mono", render: str = "phones", rate: float = 1.0, seed: str = "inpaint", noise: float = 0.0) -> DataFrame:
    """utt_id, text, lang -> utt_id, rendered, n_replaced: symbols replaced by (or followed by) their phones.

    which: "mono" takes symbols with one reading, "all" takes the smallest reading of any (the stand-in predictor's pick). render: "phones"
    alone, or "both" the symbol and its phones. rate: the hashed share of symbols replaced. noise: with "both", the hashed share whose
    symbol is swapped for a different-sounding one (its letters reversed) while the right phones stay.
    The lexicon meets exploded symbols by an equi-join; Spark broadcasts it only while it is small.
    """
    items = placed(rows, lexicon, "utt_id")
    share = lambda name, part: F.lit(part >= 1) if part <= 0 or part >= 1 else F.pmod(draw(name, F.col("utt_id"), F.col("pos")), F.lit(10_000)) < int(part * 10_000)
    chosen = replaced(F.lit(which)) & share(seed, rate)
    swapped = share(seed + ":noise", noise)
    shown = F.when(swapped & (F.reverse("symbol") != F.col("symbol")), F.reverse("symbol")).otherwise(F.col("symbol"))
    value = F.when(chosen, piece(shown, F.lit(render))).otherwise(F.col("symbol"))
    packed = items.withColumn("value", value).withColumn("hit", chosen.cast("int")).groupBy("utt_id").agg(F.array_sort(F.collect_list(F.struct("pos", "value"))).alias("vs"), F.sum("hit").alias("n_replaced"))
    return packed.select("utt_id", F.array_join(F.transform("vs", lambda v: v["value"]), " ").alias("rendered"), "n_replaced")


def apply_hints(rows: DataFrame, hints: DataFrame) -> DataFrame:
    """utt_id, text and hints (utt_id, pos, phones) -> utt_id, rendered: given phones at given places, counted from 0."""
    forced = hints.groupBy("utt_id").agg(F.map_from_entries(F.collect_list(F.struct("pos", "phones"))).alias("at"))
    both = rows.join(forced, "utt_id", "left")
    one = lambda w, i: F.coalesce(F.concat(F.lit("/"), F.try_element_at("at", i), F.lit("/")), w)
    return both.select("utt_id", F.array_join(F.transform(symbols(F.col("text")), one), " ").alias("rendered"))


def expand_vocab(lexicon: DataFrame) -> DataFrame:
    """token, kind: the words, and the phone strings that are added to them."""
    words = lexicon.select(F.col("symbol").alias("token"), F.lit("word").alias("kind"))
    phones = lexicon.select(F.concat(F.lit("/"), F.col("phones"), F.lit("/")).alias("token"), F.lit("phone").alias("kind"))
    return words.unionByName(phones).distinct()


def append(base: DataFrame, aux: DataFrame, tag: str) -> DataFrame:
    """Auxiliary rows behind base rows, tagged; columns that one side lacks are null."""
    return base.withColumn("part", F.lit("base")).unionByName(aux.withColumn("part", F.lit(tag)), allowMissingColumns=True)
