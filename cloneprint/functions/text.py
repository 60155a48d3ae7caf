"""Tokens, normal forms and skeletons as column expressions; all stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TOKEN = r"(\w+|[^\w\s])"
WORD = r"(\w+)"
SENTENCE_END = r"[.!?]+\s*"
#: what whole-file and class comparison ignores in code: comments, quoted text, package header, blanks
# one pattern, so that what opens first wins: marks of a comment inside quotes are no comment, and the other way round
_QUOTED = r"\"{3}[\s\S]*?\"{3}|\"[^\"\\\n]*+(?:\\.[^\"\\\n]*+)*+\"|'[^'\\\n]*+(?:\\.[^'\\\n]*+)*+'"
_CODE_NOISE = (r"/\*[\s\S]*?\*/|//[^\n]*|" + _QUOTED, r"(?m)^\s*package\s+[\w.]+\s*;", r"\s+")


def normalize(text: Column, lang: str = "prose") -> Column:
    """Text without what carries no meaning: blanks in prose; also comments, quoted text and package header in code."""
    for pattern in _CODE_NOISE if lang == "java" else (r"\s+",):
        text = F.regexp_replace(text, pattern, "")
    return text


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(TOKEN), F.lit(1))


def words(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(WORD), F.lit(1))


def skeleton(token: Column, level: str = "exact") -> Column:
    """Label of one token: itself, its shape, or only its kind."""
    if level == "exact":
        return F.lower(token)
    number, capital, word = token.rlike("^[0-9]+$"), token.rlike("^[A-Z]"), token.rlike(r"^\w")
    if level == "shape":
        return F.when(number, "NUM").when(capital, "CAP").when(word, "WORD").otherwise(token)
    if level == "kind":
        return F.when(number, "LITERAL").when(word, "NAME").otherwise("PUNCT")
    raise ValueError(f"no skeleton level {level!r}")


def labels(text: Column, level: str = "exact") -> Column:
    """A text's label array."""
    if level == "exact":  # lower-cased whole, not token by token
        return tokens(F.lower(text))
    return F.transform(tokens(text), lambda t: skeleton(t, level))


def shingles(word_array: Column, k: int) -> Column:
    """Distinct runs of k words; empty if there are fewer."""
    runs = word_array
    for shift in range(1, k):  # the array beside itself, shifted; what overhangs is null
        runs = F.zip_with(runs, F.slice(word_array, shift + 1, 1 << 30), lambda a, b: F.concat(a, F.lit(" "), b))
    return F.array_distinct(F.filter(runs, lambda r: r.isNotNull()))


def declared_name(text: Column, least: int = 4) -> Column:
    """First word of a unit, lower-cased, if it is long enough to be called by."""
    first = F.lower(F.regexp_extract(text, WORD, 1))
    return F.when(F.length(first) >= least, first)


def name_words(name: Column) -> Column:
    """Words of an identifier, split at case changes, digits and marks, lower-cased."""
    spaced = F.regexp_replace(F.regexp_replace(name, r"([a-z0-9])([A-Z])", "$1 $2"), r"[^A-Za-z0-9]+", " ")
    return F.filter(F.split(F.lower(spaced), " "), lambda w: w != "")
