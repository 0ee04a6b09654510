"""Which pairs to review: query strategies over classified pairs (pair_id, p), and what batch size to ask for."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

P_LIMIT, BUCKETS = 0.8, 10


def lot(seed: int | Column, *ids: str) -> Column:
    """A number that orders rows at random, but in the same way in every run and engine."""
    seed = F.lit(str(seed)) if isinstance(seed, int) else seed.cast("string")
    return F.md5(F.concat_ws("|", seed, *(F.col(i).cast("string") for i in ids)).cast("binary"))


def bucket(p: Column, p_limit: float = P_LIMIT, buckets: int = BUCKETS) -> Column:
    """Number of the bucket of a probability under the limit; buckets are equally wide from 0.5 on."""
    width = (p_limit - 0.5) / buckets
    return F.least(F.floor(F.round((p - 0.5) / width, 6)).cast("int"), F.lit(buckets - 1))


def most_uncertain(pairs: DataFrame, size: int) -> DataFrame:
    """The pairs with the smallest p; ties by pair_id."""
    return pairs.orderBy("p", "pair_id").limit(size)


def random_sample(pairs: DataFrame, size: int, seed: int = 0) -> DataFrame:
    return pairs.withColumn("lot", lot(seed, "pair_id")).orderBy("lot").limit(size).drop("lot")


def _turns(pairs: DataFrame, size: int, p_limit: float, buckets: int, seed: int | Column, by: Sequence[str] = ()) -> DataFrame:
    inside = pairs.where(F.col("p") < p_limit).withColumn("bucket", bucket(F.col("p"), p_limit, buckets)).withColumn("lot", lot(seed, "pair_id"))
    turn = F.row_number().over(Window.partitionBy(*by, "bucket").orderBy("lot", "pair_id"))
    return inside.withColumn("turn", turn).where(F.col("turn") <= size)


def shortlist(pairs: DataFrame, size: int, p_limit: float = P_LIMIT, buckets: int = BUCKETS, seed: int = 0) -> DataFrame:
    """The first ``size`` pairs of each bucket: ``bucketed`` of several parts' shortlists is that of all their pairs."""
    return _turns(pairs, size, p_limit, buckets, seed).select(*pairs.columns)


def bucketed(pairs: DataFrame, size: int, p_limit: float = P_LIMIT, buckets: int = BUCKETS, seed: int | Column = 0, by: Sequence[str] = ()) -> DataFrame:
    """One random pair of each bucket in turn, from the lowest bucket on, until there are ``size`` (within each group of ``by``).

    Ranks are limited to ``size`` inside each bucket, so Spark keeps at most that many of a task's rows before it shuffles.
    """
    turns = _turns(pairs, size, p_limit, buckets, seed, by)
    if not by:
        return turns.orderBy("turn", "bucket").limit(size).drop("lot")
    place = F.row_number().over(Window.partitionBy(*by).orderBy("turn", "bucket"))
    return turns.withColumn("place", place).where(F.col("place") <= size).drop("place", "lot")


def diverse(pairs: DataFrame, size: int, features: Sequence[str], p_limit: float = P_LIMIT, cells: int = 4, seed: int = 0) -> DataFrame:
    """Pairs spread over feature vectors: similarities are cut in ``cells`` steps, and one pair of each cell is taken in turn."""
    code = F.concat_ws("", *(F.coalesce(F.least(F.floor(F.col(f) * cells), F.lit(cells - 1)).cast("string"), F.lit("-")) for f in features))
    inside = pairs.where(F.col("p") < p_limit).withColumn("cell", code).withColumn("lot", lot(seed, "pair_id"))
    turn = F.row_number().over(Window.partitionBy("cell").orderBy("lot", "pair_id"))
    return inside.withColumn("turn", turn).where(F.col("turn") <= size).orderBy("turn", "lot").limit(size).drop("lot")


def batch_for(wanted: int, rate: float) -> int:
    """Pairs to request so that ``wanted`` are answered by both owners, who answer independently."""
    return math.ceil(round(wanted / (rate * rate), 6)) if rate > 0 else 0


def batch_of(wanted: int, rate: Column) -> Column:
    """``batch_for`` of a column of rates."""
    return F.when(rate > 0, F.ceil(F.round(F.lit(float(wanted)) / (rate * rate), 6))).otherwise(F.lit(0)).cast("long")


def decoys_for(drawn: DataFrame, share: float) -> int:
    return math.ceil(drawn.count() * share)


def with_decoys(drawn: DataFrame, certain: DataFrame, share: float, seed: int = 0) -> DataFrame:
    """Mixes certain pairs into a request batch (``share`` of it), so that owners can't take a request for an uncertain pair."""
    size = decoys_for(drawn, share)
    return drawn.withColumn("decoy", F.lit(False)).unionByName(random_sample(certain, size, seed).withColumn("decoy", F.lit(True)), allowMissingColumns=True)
