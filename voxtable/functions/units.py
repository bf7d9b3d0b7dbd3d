"""Edit distance over words or characters with the engine's own character distance: units become code points."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from voxtable.functions.binding import let

#: Languages scored by character; the others are scored by word.
BY_CHARACTER = ("zh", "ja", "ko")
_FEW = 200  # so many words fit between a blank and the end of one byte
_FIRST = 0x10000  # beyond them: a million code points without surrogates


def words(text: Column) -> Column:
    """Words between blanks; no words in an empty text."""
    return F.filter(F.split(F.trim(text), r"\s+"), lambda w: w != "")


def one_point_each(tokens: Column, of: Column) -> Column:
    """A string with one character for each word: its place among the distinct words given."""
    at = lambda w: F.array_position(of, w)
    few = F.array_join(F.transform(tokens, lambda w: F.char(at(w) + 32)), "")
    many = F.array_join(F.transform(tokens, lambda w: F.decode(F.unhex(F.lpad(F.hex(at(w) + _FIRST), 8, "0")), "UTF-32")), "")
    return F.when(F.size(of) <= _FEW, few).otherwise(many)


def word_edits(ref: Column, hyp: Column) -> Column:
    """Substitutions, deletions and insertions between word sequences."""
    both = F.struct(words(ref).alias("r"), words(hyp).alias("h"))
    return let(both, lambda b: let(F.array_distinct(F.concat(b["r"], b["h"])), lambda known: F.levenshtein(one_point_each(b["r"], known), one_point_each(b["h"], known))))


def char_edits(ref: Column, hyp: Column) -> Column:
    return F.levenshtein(ref, hyp)


def edits(ref: Column, hyp: Column, unit: Column) -> Column:
    return F.when(unit == "char", char_edits(ref, hyp)).otherwise(word_edits(ref, hyp))


def length(ref: Column, unit: Column) -> Column:
    return F.when(unit == "char", F.char_length(ref)).otherwise(F.size(words(ref)))


def unit_of(lang: Column) -> Column:
    return F.when(lang.isin(*BY_CHARACTER), F.lit("char")).otherwise(F.lit("word"))


# DuckDB counts bytes: on its side words and characters are first coded as ASCII.


def _sql_coded_edits(ref: str, hyp: str) -> str:
    """Distance of two lists, what lambdas capture bound once; at most 94 distinct items a pair."""
    coded = lambda x: f"array_to_string(list_transform({x}, lambda w: chr((32 + list_position(k, w))::INT)), '')"
    return f"list_transform([{{'r': {ref}, 'h': {hyp}}}], lambda p: list_transform([list_distinct(list_concat(p.r, p.h))], lambda k: levenshtein({coded('p.r')}, {coded('p.h')}))[1])[1]"


def sql_word_edits(ref: str, hyp: str) -> str:
    """DuckDB form over two SQL expressions."""
    return _sql_coded_edits(sql_words(ref), sql_words(hyp))


def sql_char_edits(ref: str, hyp: str) -> str:
    return _sql_coded_edits(f"string_split({ref}, '')", f"string_split({hyp}, '')")


def sql_words(text: str) -> str:
    return f"list_filter(regexp_split_to_array(trim({text}), '\\s+'), lambda w: w <> '')"
