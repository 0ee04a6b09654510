"""Similarities of bit vectors and of pairs' attributes."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkveil.functions import bits
from linkveil.sources.registry import ATTRIBUTES


def common_ones(m: int, left: str = "l_", right: str = "r_") -> Column:
    return bits.popcount([F.col(f"{left}w{i}").bitwiseAND(F.col(f"{right}w{i}")) for i in range(m // 64)])


def dice(common: Column, ones_left: Column, ones_right: Column) -> Column:
    """2 common / (left + right); null for two empty filters."""
    return F.try_divide(2.0 * common, ones_left + ones_right)


def jaccard(common: Column, ones_left: Column, ones_right: Column) -> Column:
    return F.try_divide(1.0 * common, ones_left + ones_right - common)


def overlap(common: Column, ones_left: Column, ones_right: Column) -> Column:
    return F.try_divide(1.0 * common, F.least(ones_left, ones_right))


def hamming(common: Column, ones_left: Column, ones_right: Column) -> Column:
    return ones_left + ones_right - 2 * common


def can_reach(floor: float, ones_left: Column, ones_right: Column) -> Column:
    """Whether filters of these sizes can have a Dice coefficient of ``floor``: 2 min / (left + right) >= floor."""
    return F.least(ones_left, ones_right) * 2.0 >= floor * (ones_left + ones_right)


def record_similarity(pairs: DataFrame, m: int, floor: float | None = None) -> DataFrame:
    """Adds common and sim to pairs with l_w0.., r_w0.., l_ones, r_ones; drops the words.  With a floor, pairs that can't reach it go first."""
    left, right = F.col("l_ones"), F.col("r_ones")
    if floor is not None:
        pairs = pairs.where(can_reach(floor, left, right))
    common = common_ones(m)
    words = [f"{s}{w}" for s in ("l_", "r_") for w in bits.names(m)]
    found = pairs.withColumn("common", common.cast("int")).withColumn("sim", dice(F.col("common"), left, right)).drop(*words)
    return found if floor is None else found.where(F.col("sim") >= floor)


def attribute_similarities(left: DataFrame, right: DataFrame, on: Sequence[str] = ("pair_id",), m: int = 256, attributes: Sequence[str] = ATTRIBUTES) -> DataFrame:
    """One row a pair with sim_<attr> from two tables (on..., attr, w0.., ones); null if a side misses the value.

    Both sides must know all of a pair's attributes; the join is on pair and attribute, and one aggregation turns
    attributes to columns.
    """
    names = bits.names(m)
    a = left.select(*on, "attr", F.col("ones").alias("l_ones"), *(F.col(w).alias(f"l_{w}") for w in names))
    b = right.select(*on, "attr", F.col("ones").alias("r_ones"), *(F.col(w).alias(f"r_{w}") for w in names))
    each = record_similarity(a.join(b, [*on, "attr"]), m)
    return each.groupBy(*on).agg(*(F.max(F.when(F.col("attr") == x, F.col("sim"))).alias(f"sim_{x}") for x in attributes))


def frequency_feature(left_class: Column, right_class: Column, equal: Column) -> Column:
    """The class of a shared value, 0 for different ones."""
    return F.when(equal, F.least(left_class, right_class)).otherwise(0)


def signature_similarities(left: DataFrame, right: DataFrame, attributes: Sequence[str] = ATTRIBUTES) -> DataFrame:
    """(pair_id, sim_<attr>): share of equal minima of the two signatures, null where a side has no value."""
    both = left.select("pair_id", "attr", F.col("signature").alias("l")).join(right.select("pair_id", "attr", F.col("signature").alias("r")), ["pair_id", "attr"])
    same = F.size(F.filter(F.zip_with("l", "r", lambda a, b: a == b), lambda x: x)) / F.size("l")
    return both.groupBy("pair_id").agg(*(F.max(F.when(F.col("attr") == a, same)).alias(f"sim_{a}") for a in attributes))


def weighted_mean(weights: dict[str, float], prefix: str = "sim_") -> Column:
    """Weighted mean of the similarities that aren't missing; null if all are."""
    present = [(F.col(prefix + a), w) for a, w in weights.items()]
    total = sum((F.coalesce(s * w, F.lit(0.0)) for s, w in present), F.lit(0.0))
    return F.try_divide(total, sum((F.when(s.isNotNull(), w).otherwise(0.0) for s, w in present), F.lit(0.0)))


def top_features(m: int, with_fill: bool = False) -> list[Column]:
    """Features of the top model: the similarity, and if asked for the ratio of the filters' fill rates (which folding distorts)."""
    ratio = F.try_divide(F.least("l_ones", "r_ones").cast("double"), F.greatest("l_ones", "r_ones"))
    return [F.col("sim"), *([ratio.alias("fill_ratio")] if with_fill else [])]
