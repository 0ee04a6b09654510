"""The top layer's model: one threshold, a probability, and its shift by labelled pairs."""

from __future__ import annotations

from collections.abc import Sequence
from typing import Protocol

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BELOW, ABOVE = 0.05, 0.1
DIGITS = 9


class Model(Protocol):
    """Any classifier of similarities: adds ``g`` (match or not) and ``p`` in [0.5, 1]."""

    def classify(self, pairs: DataFrame) -> DataFrame: ...


def ramp(sim: Column, t: Column | float, below: float = BELOW, above: float = ABOVE) -> Column:
    """Probability that grows from 0.5 at the threshold to 1 at ``below`` under it and ``above`` over it."""
    t = F.lit(t) if isinstance(t, (int, float)) else t
    width = F.when(sim < t, below).otherwise(above)
    return F.round(0.5 * (1 + F.least(F.lit(1.0), F.abs(sim - t) / width)), DIGITS)


def threshold(pairs: DataFrame, t: Column | float, below: float = BELOW, above: float = ABOVE) -> DataFrame:
    """Adds g and p by the similarity ``sim``."""
    limit = F.lit(t) if isinstance(t, (int, float)) else t
    return pairs.withColumn("g", F.col("sim") >= limit).withColumn("p", ramp(F.col("sim"), limit, below, above))


def uncertain_interval(t: float, p_limit: float = 0.8, below: float = BELOW, above: float = ABOVE) -> tuple[float, float]:
    """Similarities with a probability under ``p_limit`` lie between these two: a range that Parquet can prune by."""
    share = 2 * p_limit - 1
    return t - below * share, t + above * share


class Threshold:
    def __init__(self, t: float, below: float = BELOW, above: float = ABOVE):
        self.t, self.below, self.above = t, below, above

    def classify(self, pairs: DataFrame) -> DataFrame:
        return threshold(pairs, self.t, self.below, self.above)


def grid(t_current: float, t_initial: float, max_drift: float, max_step: float, step: float) -> np.ndarray:
    """Thresholds within both limits, in whole steps from the current one, ascending."""
    reach = int(round(max_step / step))
    values = np.round(t_current + step * np.arange(-reach, reach + 1), DIGITS)
    return values[np.abs(values - t_initial) <= max_drift + 1e-9]


def shift(
    sims: Sequence[float], matches: Sequence[bool], weights: Sequence[float], t_current: float, t_initial: float,
    max_drift: float = 0.10, max_step: float = 0.02, measure: str = "accuracy", step: float = 0.001,
) -> float:
    """The threshold that is best for weighted labelled pairs (bounded by the review budget); ties go to the nearest to the current one, then to the lower."""
    s, m, w = np.asarray(sims, dtype=float), np.asarray(matches, dtype=bool), np.asarray(weights, dtype=float)
    if not len(s):
        return t_current
    values = grid(t_current, t_initial, max_drift, max_step, step)
    if not len(values):
        return t_current
    over = np.round(s, DIGITS)[None, :] >= values[:, None]
    tp, fp = (over & m) @ w, (over & ~m) @ w
    fn, tn = w[m].sum() - tp, w[~m].sum() - fp
    quality = (tp + tn) / w.sum() if measure == "accuracy" else 2 * tp / np.maximum(2 * tp + fp + fn, 1e-12)
    quality = np.round(quality, DIGITS)
    best = values[quality == quality.max()]
    return float(best[np.lexsort((best, np.round(np.abs(best - t_current), DIGITS)))[0]])


def shift_table(labels: DataFrame, t_current: float, t_initial: float, max_drift: float = 0.10, max_step: float = 0.02, measure: str = "accuracy", step: float = 0.001) -> DataFrame:
    """The same choice as a query: quality of each threshold of the grid over labels (sim, match, weight), and the chosen one.

    A row is added to the sums of all grid steps it passes by one aggregation over (step, row); the grid has at most
    2 max_step / step + 1 rows, which are sent to the tasks.
    """
    values = [float(v) for v in grid(t_current, t_initial, max_drift, max_step, step)]
    steps = labels.sparkSession.createDataFrame([(v,) for v in values], "t double")
    joined = labels.crossJoin(F.broadcast(steps))
    over, match, w = F.round("sim", DIGITS) >= F.col("t"), F.col("match"), F.col("weight")
    tp, fp, fn, tn = (F.sum(F.when(c, w).otherwise(0.0)) for c in (over & match, over & ~match, ~over & match, ~over & ~match))
    quality = (tp + tn) / (tp + fp + fn + tn) if measure == "accuracy" else 2 * tp / F.greatest(2 * tp + fp + fn, F.lit(1e-12))
    scored = joined.groupBy("t").agg(F.round(quality, DIGITS).alias("quality"))
    best = scored.agg(F.min(F.struct((-F.col("quality")).alias("q"), F.round(F.abs(F.col("t") - t_current), DIGITS).alias("d"), F.col("t").alias("t"))).alias("b"))
    return scored.crossJoin(F.broadcast(best)).select("t", "quality", (F.col("t") == F.col("b.t")).alias("chosen"))
