"""Hashes of labels and order-insensitive sums of them.

``portable`` takes 60 bits of md5, which any SQL engine repeats; ``fast`` takes 60 bits of xxHash and is
what to use at scale. Sums are exact, modulo 2**61 - 1: inside a row they are reduced at each step and so stay in a bigint; over rows the
upper and lower bits are added apart.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MODULUS = (1 << 61) - 1
_WIDE = "decimal(38,0)"


def own_hash(label: Column, kind: str = "portable") -> Column:
    if kind == "portable":
        return F.conv(F.substring(F.md5(label), 1, 15), 16, 10).cast("bigint")
    if kind == "fast":
        return F.xxhash64(label).bitwiseAND(F.lit((1 << 60) - 1))
    raise ValueError(f"no hash {kind!r}")


def reduced(total: Column) -> Column:
    return F.pmod(total.cast(_WIDE), F.lit(MODULUS).cast(_WIDE)).cast("bigint")


def bag_hash(labels: Column, kind: str = "portable") -> Column:
    """Sum of the labels' hashes: equal for equal bags of labels, in any order; 0 for none."""
    # never null, else a join on it would test it for null below the projection and so compute it twice
    return F.coalesce(F.aggregate(labels, F.lit(0).cast("bigint"), lambda acc, x: added(acc, own_hash(x, kind))), F.lit(0).cast("bigint"))


def added(a: Column, b: Column) -> Column:
    """Sum of two values below 2**62 together: no step leaves a bigint."""
    return (a + b) % F.lit(MODULUS)


def total(column: Column) -> Column:
    """The aggregate of ``bag_hash`` over rows (up to 2**32 of them in a group)."""
    high, low = F.sum(F.shiftright(column, 31)), F.sum(column.bitwiseAND(F.lit((1 << 31) - 1)))
    return reduced(high.cast(_WIDE) * F.lit(1 << 31).cast("decimal(10,0)") + low.cast(_WIDE))


def node_hash(label: str, children: Column, kind: str = "portable") -> Column:
    """Hash of a tree node from its label and the sum of its children."""
    return own_hash(F.concat(F.lit(label + ":"), children.cast("string")), kind)
