"""Complexity of a function from its Halstead volume, cyclomatic number and length, and the maintainability index."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from . import text as T

TRIVIAL_BELOW, MAINTAINABLE = 60, 171
# Weights of volume, cyclomatic number and lines.
W_VOLUME, W_CYCLOMATIC, W_LINES = 5.2, 0.23, 16.2


def complexity(volume: Column, cyclomatic: Column, loc: Column, variant: str = "log") -> Column:
    """``log`` takes logarithms of volume and lines, ``linear`` the values."""
    of = (lambda c: F.ln(F.greatest(c.cast("double"), F.lit(1.0)))) if variant == "log" else (lambda c: c.cast("double"))
    if variant not in ("log", "linear"):
        raise ValueError(f"no variant {variant!r}")
    return F.lit(W_VOLUME) * of(volume) + F.lit(W_CYCLOMATIC) * cyclomatic + F.lit(W_LINES) * of(loc)


def maintainability(value: Column) -> Column:
    return F.lit(float(MAINTAINABLE)) - value


def prose_volume(text: Column) -> Column:
    """Halstead volume with tokens as operators and operands."""
    found = T.tokens(F.lower(text))
    return F.size(found) * F.log2(F.greatest(F.size(F.array_distinct(found)), F.lit(1)).cast("double"))


def prose_cyclomatic(text: Column) -> Column:
    return 1 + F.length(F.regexp_replace(text, "[^,;]", ""))


def prose_loc(text: Column) -> Column:
    """Sentences, at least one."""
    parts = F.filter(F.split(text, T.SENTENCE_END), lambda s: F.trim(s) != "")
    return F.greatest(F.size(parts), F.lit(1))


def prose_complexity(text: Column, variant: str = "log") -> Column:
    return complexity(prose_volume(text), prose_cyclomatic(text), prose_loc(text), variant)
