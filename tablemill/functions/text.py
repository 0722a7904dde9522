"""Tokens, lines and n-grams as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TOKEN = r"\S+"

# Frequent function words of four languages.
FUNCTION_WORDS = {
    "en": ["the", "of", "and", "to", "in", "is", "that", "for", "on", "with", "as", "was", "at", "by", "be", "this", "are", "from", "or", "an"],
    "fr": ["le", "la", "les", "de", "des", "du", "et", "est", "une", "en", "que", "pour", "dans", "au", "aux", "sur", "par", "ne", "pas", "ce"],
    "de": ["der", "die", "das", "und", "ist", "ein", "eine", "den", "von", "zu", "mit", "auf", "für", "im", "dem", "nicht", "des", "sich", "als", "auch"],
    "es": ["el", "los", "las", "del", "que", "y", "un", "una", "por", "con", "para", "se", "no", "su", "al", "lo", "como", "más", "es", "o"],
}


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(TOKEN), F.lit(0))


def lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n")


def share(part: Column, whole: Column) -> Column:
    """part / whole, null for an empty whole."""
    return F.when(whole > 0, part / whole)


def let(value: Column, fn) -> Column:
    """``fn(value)`` with the value computed once per row, also inside lambdas."""
    return F.transform(F.array(value), lambda v: fn(v))[0]


def ngrams(words: Column, n: int) -> Column:
    """Runs of n words joined by a space; none if there are fewer."""
    none = F.expr("cast(array() as array<string>)")
    return let(words, lambda w: F.when(F.size(w) >= n, F.transform(F.sequence(F.lit(1), F.size(w) - (n - 1)), lambda i: F.array_join(F.slice(w, i, n), " "))).otherwise(none))


def shingles(words: Column, n: int) -> Column:
    """Distinct n-grams, or the whole text if it is shorter."""
    return let(words, lambda w: F.array_distinct(F.when(F.size(w) >= n, ngrams(w, n)).otherwise(F.array(F.array_join(w, " ")))))


def count_matches(text: Column, pattern: str) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(pattern)).cast("long")
