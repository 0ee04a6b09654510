"""The attribute layer's model: an evolving forest.

Ten trees are grown on the first labelled batch; each update grows ten more on all labelled pairs so far and appends them;
over a hundred, the oldest go.  Pairs count by the probability of their label, twice that if a human gave it.  Missing
similarities are -1.  Two back ends share the rule: trees in numpy, trained inside grouped tasks so that all runs of a
scenario advance together, and Spark's own forest for training sets over a task's memory.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkveil.cart import Tree, grow_forest, predict_forest
from linkveil.sources.registry import ATTRIBUTES

FEATURES = tuple(f"sim_{a}" for a in ATTRIBUTES) + tuple(f"fq_{a}" for a in ATTRIBUTES)
MISSING = -1.0


class EvolvingForest:
    """A queue of trees."""

    def __init__(self, trees: Sequence[Tree] = (), first: int = 10, added: int = 10, most: int = 100, depth: int = 6, bag: float = 0.7, seed: int = 1, born: int = 0):
        self.trees, self.first, self.added, self.most = list(trees), first, added, most
        self.depth, self.bag, self.seed, self.born = depth, bag, seed, born

    def update(self, x: np.ndarray, y: np.ndarray, w: np.ndarray) -> EvolvingForest:
        """A forest with trees grown on these rows appended; the first call bootstraps it."""
        count = self.added if self.trees else self.first
        fresh = grow_forest(np.asarray(x, float), np.asarray(y, float), np.asarray(w, float), count, self.depth, self.bag, seed=self.seed * 1000 + self.born) if len(y) else []
        kept = (self.trees + fresh)[-self.most :]
        return EvolvingForest(kept, self.first, self.added, self.most, self.depth, self.bag, self.seed, self.born + len(fresh))

    def classify(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(g, p) of each row; p is the mean share of the better class, in [0.5, 1]."""
        share = predict_forest(self.trees, np.asarray(x, float))
        return share >= 0.5, np.maximum(share, 1 - share)

    @property
    def sequence(self) -> list[int]:
        return list(range(self.born - len(self.trees), self.born))


def matrix(pairs: pd.DataFrame, features: Sequence[str] = FEATURES) -> np.ndarray:
    return pairs[list(features)].astype(float).fillna(MISSING).to_numpy()


def weight(p: np.ndarray, human: np.ndarray) -> np.ndarray:
    """Probability of the label, twice that for a human's (whose label has probability 1)."""
    return np.where(human, 2.0, p)


def train(labelled: DataFrame, features: Sequence[str], by: str = "run_id", updates: int = 1, **options) -> DataFrame:
    """Trees of a forest for each group: (by, seq, feature, threshold, left, right, value) from rows with features, label and weight.

    A group is one run's labelled pairs, bounded by its review budget.
    """
    names = list(features)

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        forest = EvolvingForest(**options)
        ordered = rows.sort_values(names + ["label"])
        x = matrix(ordered, names)
        for _ in range(updates):
            forest = forest.update(x, ordered["label"].astype(float).to_numpy(), ordered["weight"].astype(float).to_numpy())
        table = [(rows[by].iloc[0], seq, *t.as_lists()) for seq, t in zip(forest.sequence, forest.trees, strict=True)]
        return pd.DataFrame(table, columns=[by, "seq", "feature", "threshold", "left", "right", "value"])

    kind = dict(labelled.dtypes)[by]
    return labelled.select(by, *names, F.col("label").cast("double").alias("label"), "weight").groupBy(by).applyInPandas(
        run, f"{by} {kind}, seq long, feature array<long>, threshold array<double>, left array<long>, right array<long>, value array<double>"
    )


def newest(trees: DataFrame, most: int = 100, by: str = "run_id") -> DataFrame:
    """The living trees of each run: the ``most`` with the greatest seq."""
    from pyspark.sql.window import Window

    age = F.row_number().over(Window.partitionBy(by).orderBy(F.desc("seq")))
    return trees.withColumn("age", age).where(F.col("age") <= most).drop("age")


def score(pairs: DataFrame, forest: EvolvingForest, features: Sequence[str] = FEATURES) -> DataFrame:
    """Adds g and p to any number of pairs; the trees (100 of 127 nodes at most) travel with the function."""
    names, trees = list(features), forest.trees

    @F.pandas_udf("struct<g: boolean, p: double>")
    def classify(*columns: pd.Series) -> pd.DataFrame:
        x = np.stack([c.astype(float).fillna(MISSING).to_numpy() for c in columns], axis=1)
        g, p = EvolvingForest(trees).classify(x)
        return pd.DataFrame({"g": g, "p": np.round(p, 9)})

    return pairs.withColumn("gp", classify(*(F.col(n).cast("double") for n in names))).select("*", "gp.g", "gp.p").drop("gp")


class SparkForest:
    """The same queue on Spark's forest: chunks of trees as models, scored by the sum of their raw predictions."""

    def __init__(self, features: Sequence[str], per_chunk: int = 10, most: int = 100, depth: int = 6, bag: float = 0.7, seed: int = 1):
        self.features, self.per_chunk, self.most, self.depth, self.bag, self.seed, self.chunks = list(features), per_chunk, most, depth, bag, seed, []
        self.grown = 0

    def _assembled(self, rows: DataFrame) -> DataFrame:
        from pyspark.ml.feature import VectorAssembler

        filled = rows.withColumns({f: F.coalesce(F.col(f).cast("double"), F.lit(MISSING)) for f in self.features})
        return VectorAssembler(inputCols=self.features, outputCol="features_").transform(filled)

    def update(self, labelled: DataFrame) -> SparkForest:
        from pyspark.ml.classification import RandomForestClassifier

        per_split = str(min(len(self.features), len(self.features).bit_length()))
        learner = RandomForestClassifier(
            featuresCol="features_", labelCol="label", weightCol="weight", numTrees=self.per_chunk, maxDepth=self.depth, subsamplingRate=self.bag, featureSubsetStrategy=per_split, seed=self.seed + self.grown
        )
        self.chunks = [*self.chunks, learner.fit(self._assembled(labelled))][-(self.most // self.per_chunk) :]
        self.grown += 1
        return self

    def score(self, pairs: DataFrame) -> DataFrame:
        from pyspark.ml.functions import vector_to_array

        out = self._assembled(pairs)
        for i, model in enumerate(self.chunks):
            out = model.setPredictionCol(f"y{i}_").setRawPredictionCol(f"r{i}_").setProbabilityCol(f"p{i}_").transform(out)
        raw = [vector_to_array(f"r{i}_") for i in range(len(self.chunks))]
        ones, every = sum((r[1] for r in raw), F.lit(0.0)), sum((r[0] + r[1] for r in raw), F.lit(0.0))
        share = F.try_divide(ones, every)
        drop = ["features_", *(f"{k}{i}_" for i in range(len(self.chunks)) for k in "yrp")]
        return out.withColumn("share_", share).drop(*drop).withColumn("g", F.col("share_") >= 0.5).withColumn("p", F.greatest(F.col("share_"), 1 - F.col("share_"))).drop("share_")
