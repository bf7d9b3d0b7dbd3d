"""Text normalisation: rules, a prompted route, the inverse, auxiliary sets, script folding, scoring forms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


#: Digit names and symbol names by language.
DIGITS = {
    "de": "null eins zwei drei vier fünf sechs sieben acht neun".split(),
    "en": "zero one two three four five six seven eight nine".split(),
    "es": "cero uno dos tres cuatro cinco seis siete ocho nueve".split(),
    "fr": "zéro un deux trois quatre cinq six sept huit neuf".split(),
}
SIGNS = {"%": {"de": "prozent", "en": "percent", "es": "por ciento", "fr": "pour cent"}, "&": {"de": "und", "en": "and", "es": "y", "fr": "et"}, "@": {"de": "at", "en": "at", "es": "arroba", "fr": "arobase"}, "$": {"de": "dollar", "en": "dollars", "es": "dólares", "fr": "dollars"}, "=": {"de": "gleich", "en": "equals", "es": "igual", "fr": "égal"}}
FOLD = ("áàâäãéèêëíìîïóòôöõúùûüñçß", "aaaaaeeeeiiiiooooouuuuncs")


def has_symbols(text: Column) -> Column:
    return F.regexp_like(text, F.lit("[0-9%&@$=]"))


def normalize(text: Column, lang: Column, verbose: bool = False) -> Column:
    """Digits one by one and symbols as words of the language; verbose marks each symbol word, as the prompted route does."""
    out = F.lit(None).cast("string")
    for code, names in DIGITS.items():
        spoken = text
        for sign, by in SIGNS.items():
            word = f"{by[code]} sign" if verbose else by[code]
            spoken = F.replace(spoken, F.lit(sign), F.lit(f" {word} "))
        for d, name in enumerate(names):
            spoken = F.replace(spoken, F.lit(str(d)), F.lit(f" {name} "))
        out = F.when(lang == code, spoken).otherwise(out)
    return F.trim(F.regexp_replace(F.coalesce(out, text), " +", " "))


def denormalize(text: Column, lang: Column) -> Column:
    """Inverse: digit and symbol names, as whole words, become what they name."""
    table = {code: {**{n: str(d) for d, n in enumerate(DIGITS[code])}, **{by[code]: s for s, by in SIGNS.items() if " " not in by[code]}} for code in DIGITS}
    maps = F.create_map(*[x for code, names in table.items() for x in (F.lit(code), F.create_map(*[F.lit(y) for kv in names.items() for y in kv]))])
    mine = F.try_element_at(maps, lang)
    return F.array_join(F.transform(F.split(text, " "), lambda w: F.coalesce(F.try_element_at(mine, w), w)), " ")


def build_aux(rows: DataFrame) -> DataFrame:
    """utt_id, raw, spoken, route: rules, prompted, and inverse pairs, repeats of (raw, spoken) out, the first route staying."""
    sym = rows.filter(has_symbols(F.col("text")))
    ways = F.array(
        F.struct(F.lit(1).alias("route"), F.col("text").alias("raw"), normalize(F.col("text"), F.col("lang")).alias("spoken")),
        F.struct(F.lit(2).alias("route"), F.col("text").alias("raw"), normalize(F.col("text"), F.col("lang"), True).alias("spoken")),
        F.struct(F.lit(3).alias("route"), denormalize(normalize(F.col("text"), F.col("lang")), F.col("lang")).alias("raw"), normalize(F.col("text"), F.col("lang")).alias("spoken")),
    )
    each = sym.select("utt_id", F.explode(ways).alias("w")).select("utt_id", "w.*")
    return each.groupBy(F.md5("raw").alias("raw_md5"), F.md5("spoken").alias("spoken_md5")).agg(F.min(F.struct("route", "utt_id")).alias("f")).select("f.utt_id", "f.route", "raw_md5", "spoken_md5")


def multi_format(rows: DataFrame) -> DataFrame:
    """Raw and spoken text of one utterance share its audio."""
    return rows.select(F.col("utt_id").alias("audio_id"), F.expr("stack(2, 'raw', text, 'spoken', spoken) AS (format, text)"))


def coverage(rows: DataFrame) -> DataFrame:
    """symbol, n, handled: characters that are no letter, blank or common mark, and whether a rule names them."""
    chars = F.split(F.regexp_replace("text", r"[\p{L}\p{M}\s.,;:!?]", ""), "")
    counts = rows.select(F.explode(chars).alias("symbol")).filter("symbol <> ''").groupBy("symbol").agg(F.count(F.lit(1)).alias("n"))
    return counts.withColumn("handled", F.col("symbol").isin(*SIGNS, *"0123456789"))


def fold_script(text: Column, table: tuple[str, str] = FOLD) -> Column:
    """Letters by a table of equals: accents here; the two kana sets are such a table too (see kana_table)."""
    return F.translate(text, *table)


def kana_table() -> tuple[str, str]:
    """Katakana to hiragana: the blocks lie 0x60 apart."""
    return "".join(chr(c) for c in range(0x30A1, 0x30F7)), "".join(chr(c - 0x60) for c in range(0x30A1, 0x30F7))


def to_kana(text: Column, words: dict[str, str]) -> Column:
    """Dictionary conversion, longest entries first."""
    for w in sorted(words, key=lambda w: (-len(w), w)):
        text = F.replace(text, F.lit(w), F.lit(words[w]))
    return text


def for_scoring(text: Column) -> Column:
    """Lower case, marks out, blanks collapsed."""
    return F.trim(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "))


def ambiguity(lexicon: DataFrame) -> DataFrame:
    """lang -> symbols, share with several readings."""
    return lexicon.groupBy("lang").agg(F.count(F.lit(1)).alias("symbols"), F.avg((F.col("n_readings") > 1).cast("double")).alias("ambiguous"))


