"""Who labels pairs: a simulated human, a table of given labels, and the masked display that a human sees."""

from __future__ import annotations

import difflib

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from linkveil.functions.crypto import uniform

MASK = "*"


def human(truth: Column, err: float, seed: int = 0, pair_id: str = "pair_id") -> Column:
    """The true label, flipped with probability ``err`` by a draw for each pair."""
    return F.when(uniform(F.col(pair_id), f"human{seed}") < err, ~truth).otherwise(truth)


def from_table(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """Labels that someone else has given: pairs without one stay null."""
    return pairs.join(labels.select("pair_id", F.col("g").alias("human_g")), "pair_id", "left")


def mask_positions(left: Column, right: Column) -> Column:
    """The left value with each character that the right one has at the same place masked; equal values are masked whole."""
    chars = F.split(left, "")
    shown = F.zip_with(chars, F.split(F.rpad(right, F.greatest(F.length(left), F.lit(1)), F.lit("\u0000")), ""), lambda a, b: F.when(a == b, MASK).otherwise(a))
    body = F.concat_ws("", F.slice(shown, 1, F.length(left)))
    return F.when(left.isNull(), None).when(right.isNull() | (F.length(left) == 0), left).otherwise(body)


def mask_pair(left: Column, right: Column) -> Column:
    """struct(left, right) as displayed at the same places: equal parts hidden, differences shown."""
    return F.struct(mask_positions(left, right).alias("left"), mask_positions(right, left).alias("right"))


def _aligned(a: str | None, b: str | None) -> str | None:
    if a is None or b is None:
        return a
    out = list(a)
    for i, _, n in difflib.SequenceMatcher(None, a, b, autojunk=False).get_matching_blocks():
        out[i : i + n] = MASK * n
    return "".join(out)


@F.pandas_udf(T.StringType())
def mask_aligned(left: pd.Series, right: pd.Series) -> pd.Series:
    """Like ``mask_positions``, but after aligning the values, so that an inserted letter doesn't unmask what follows."""
    return pd.Series([_aligned(a, b) for a, b in zip(left, right, strict=True)])
