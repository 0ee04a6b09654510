"""Values and their q-grams."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PAD = "_"


def normalise(value: Column) -> Column:
    """Lower case, trimmed, blanks collapsed; empty values are missing."""
    return F.nullif(F.trim(F.regexp_replace(F.lower(value), r"\s+", " ")), F.lit(""))


def qgrams(value: Column, q: int = 2, pad: str = PAD) -> Column:
    """Distinct q-grams of a value with q - 1 pads at both ends; null for a missing value."""
    padded = F.concat(F.lit(pad * (q - 1)), value, F.lit(pad * (q - 1)))
    spans = F.transform(F.sequence(F.lit(1), F.length(padded) - q + 1), lambda i: F.substring(padded, i, q))
    return F.when(F.length(value) > 0, F.array_distinct(spans))


def set_dice(left: Column, right: Column) -> Column:
    """Dice coefficient of two arrays of distinct elements; null if either is missing."""
    return 2.0 * F.size(F.array_intersect(left, right)) / (F.size(left) + F.size(right))
