"""Instructions, inline control tags, styles, speaker prompts, fine-tuning sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from voxtable.functions.binding import let
from voxtable.functions.hashing import draw, uniform

END = "<|endofprompt|>"
#: Our own grouping of style words.
STYLE_TYPES = {"happy": "emotion", "sad": "emotion", "angry": "emotion", "fast": "speed", "slow": "speed", "loud": "tone", "soft": "tone", "robot": "role", "poet": "role", "dialect": "dialect", "accent": "accent"}
BURSTS = ("laughter", "breath")
#: Our own wording by language: speaker, then language name.
POLYGLOT = {"de": "Sie sind Sprecher {s}. Bitte auf {l}.", "en": "Be speaker {s}, please, in {l}.", "es": "Sea el hablante {s}. Hable en {l}.", "fr": "Soyez le locuteur {s}. Parlez en {l}."}


def with_prompt(desc: Column, text: Column, end: str = END) -> Column:
    """Description, end marker, text; no marker without a description. A marker inside the text is taken out: it occurs once."""
    clean = F.replace(text, F.lit(end), F.lit(""))
    return F.when(F.coalesce(desc, F.lit("")) == "", clean).otherwise(F.concat(desc, F.lit(end), clean))


def bursts(text: Column) -> Column:
    """Names of the vocal bursts in square brackets."""
    return F.regexp_extract_all(text, F.lit(r"\[([a-z]+)\]"), F.lit(1))


def emphasis(text: Column) -> Column:
    """Spans between paired emphasis tags."""
    return F.regexp_extract_all(text, F.lit(r"<strong>([^<]*)</strong>"), F.lit(1))


def well_formed(text: Column) -> Column:
    """Every emphasis tag is paired and none is nested."""
    rest = F.regexp_replace(text, r"<strong>[^<]*</strong>", "")
    return ~F.regexp_like(rest, F.lit("</?strong>"))


def inject(words: Column, key: Column, seed: str = "tag") -> Column:
    """Hashed tags for words: one in ten is followed by a burst, one in ten emphasised."""

    def one(w: Column, i: Column) -> Column:
        tagged = lambda u: F.when(u < 5, F.concat(w, F.lit(f" [{BURSTS[0]}]"))).when(u < 10, F.concat(w, F.lit(f" [{BURSTS[1]}]"))).when(u < 20, F.concat(F.lit("<strong>"), w, F.lit("</strong>"))).otherwise(w)
        return let(F.pmod(draw(seed, key, i), F.lit(100)), tagged)

    return F.array_join(F.transform(words, one), " ")


def strip_tags(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.regexp_replace(text, r"\[[a-z]+\]|</?strong>", ""), " +", " "))


def top_styles(rows: DataFrame, n: int = 100) -> DataFrame:
    """style, n: the most frequent, ties by name. Partial counts, then a top-n of each task: no full sort."""
    return rows.groupBy("style").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "style").limit(n)


def style_type(style: Column) -> Column:
    """The first type whose word the style holds."""
    out = F.lit("other")
    for word, kind in reversed(STYLE_TYPES.items()):
        out = F.when(F.contains(style, F.lit(word)), kind).otherwise(out)
    return out


def polyglot_prompt(speaker: Column, lang: Column) -> Column:
    """Speaker and language instruction in the wording of the language."""
    out = F.lit(None).cast("string")
    for code, wording in POLYGLOT.items():
        before, after = wording.split("{s}")
        middle, end = after.split("{l}")
        out = F.when(lang == code, F.concat(F.lit(before), speaker, F.lit(middle), lang, F.lit(end))).otherwise(out)
    return out


def speaker_style_prompt(speaker: Column, style: Column) -> Column:
    """Both parts, each blank where its field is missing."""
    one = F.coalesce(F.concat(F.lit("Speaker "), speaker, F.lit(".")), F.lit(""))
    two = F.coalesce(F.concat(F.lit("Style: "), style, F.lit(".")), F.lit(""))
    return F.trim(F.concat_ws(" ", one, two))


def mask(rows: DataFrame, p_speaker: float, p_style: float, seed: str = "mask", key: str = "utt_id") -> DataFrame:
    """Speaker or style nulled by hashed draws of given rates."""
    hide = lambda what, p: F.when(uniform(f"{seed}:{what}", F.col(key)) >= p, F.col(what))
    return rows.withColumns({"speaker": hide("speaker", p_speaker), "style": hide("style", p_style)})


def select_monolingual(rows: DataFrame, per_lang: int, seed: str = "mono") -> DataFrame:
    """lang, speaker: per_lang speakers of one language only, in hash order, for every language."""
    single = rows.groupBy("speaker").agg(F.countDistinct("lang").alias("n"), F.min("lang").alias("lang")).filter("n = 1")
    order = Window.partitionBy("lang").orderBy(draw(seed, F.col("speaker")), "speaker")
    return single.withColumn("rn", F.row_number().over(order)).filter(F.col("rn") <= per_lang).select("lang", "speaker")


def build_sft(target: DataFrame, instruction: DataFrame) -> DataFrame:
    """Target-speaker rows and instruction rows; speaker or style is null where it is not labelled."""
    a = target.select("utt_id", "text", "speaker", "style", F.lit("target").alias("part"))
    b = instruction.select("utt_id", "text", F.lit(None).cast("string").alias("speaker"), "style", F.lit("instruction").alias("part"))
    return a.unionByName(b)
