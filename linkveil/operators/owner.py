"""What data owners do: queues of requests that they pull, policies, and the attributes that they provide.

A request names a pair, a record, an owner and the pair's key.  Owners never see outcomes.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkveil.functions.crypto import uniform
from linkveil.operators.encode import new_pair_key
from linkveil.session import sent
from linkveil.sources.registry import ATTRIBUTES


def enqueue(drawn: DataFrame, round_: int = 0, seed: int | None = None) -> DataFrame:
    """Two requests for each drawn pair: round, pair_id, pair_key, owner, rec_id.  Without a seed the keys are random; see ``new_pair_key``."""
    sides = F.explode(F.array(F.struct(F.lit("A").alias("owner"), F.col("left_id").alias("rec_id")), F.struct(F.lit("B").alias("owner"), F.col("right_id").alias("rec_id"))))
    keyed = drawn.select("pair_id", new_pair_key(F.col("pair_id"), round_, seed).alias("pair_key"), sides.alias("side"))
    return keyed.select(F.lit(round_).alias("round"), "pair_id", "pair_key", "side.owner", "side.rec_id")


def pull(queue: DataFrame, owner: str, answered: DataFrame | None = None, size: int | None = None) -> DataFrame:
    """An owner's next batch: its requests that aren't answered yet, oldest rounds first."""
    mine = queue.where(F.col("owner") == owner)
    if answered is not None:
        mine = mine.join(answered.select("pair_id", "owner", "rec_id"), ["pair_id", "owner", "rec_id"], "left_anti")
    return mine if size is None else mine.orderBy("round", "pair_id", "rec_id").limit(size)


@dataclass(frozen=True)
class Policy:
    """Share of records that an owner answers for; ``deny`` names records that it never gives (such as ``rare_records``)."""

    rate: float = 1.0
    seed: int = 0

    def replies(self, requests: DataFrame, deny: DataFrame | None = None) -> DataFrame:
        """Requests that are answered, by a draw for each record."""
        found = requests if self.rate >= 1 else requests.where(uniform(F.col("rec_id"), f"reply{self.seed}") < self.rate)
        return found if deny is None else found.join(deny.select("rec_id"), "rec_id", "left_anti")


def answer_level(seed: int = 0, left: str = "left_id", right: str = "right_id") -> Column:
    """The least response rate at which both owners of a pair answer."""
    return F.greatest(*(uniform(F.col(c), f"reply{seed}") for c in (left, right)))


def complete_pairs(replies: DataFrame) -> DataFrame:
    """Pairs that both owners have answered."""
    return replies.groupBy("pair_id").agg(F.countDistinct("owner").alias("owners")).where("owners = 2").select("pair_id")


def rare_records(records: DataFrame, attributes: Sequence[str], least: int) -> DataFrame:
    """Records whose combination of values is shared by fewer than ``least``: a high-profile list for owners to withhold."""
    groups = records.groupBy(*attributes).agg(F.count(F.lit(1)).alias("k")).where(F.col("k") < least)
    same = reduce(lambda a, b: a & b, (records[a].eqNullSafe(groups[a]) for a in attributes))
    return records.join(groups, same, "left_semi").select("rec_id")


def selected(attribute: str, mode: str = "all", low: Column | float = 0.4, prefix: str = "sim_") -> Column:
    """Whether a pair's attribute is asked for in plaintext.

    ``all``; ``unequal``: similarity under 1; ``intermediate``: at least ``low`` too; ``adaptive``: like that, where ``low`` is the
    attribute's mean.  A pair of which a side misses the value has no similarity: it is given (where present) by ``all`` only.
    """
    sim = F.col(prefix + attribute)
    low = F.lit(low) if isinstance(low, (int, float)) else low
    if mode == "all":
        return F.lit(True)
    if mode == "unequal":
        return F.coalesce(sim < 1, F.lit(False))
    if mode in ("intermediate", "adaptive"):
        return F.coalesce((sim < 1) & (sim >= low), F.lit(False))
    raise ValueError(mode)


def select_attributes(pairs: DataFrame, mode: str = "all", low: float = 0.4, attributes: Sequence[str] = ATTRIBUTES) -> DataFrame:
    """Adds ask_<attr> to pairs with sim_<attr>."""
    if mode == "adaptive":
        means = pairs.agg(*(F.avg(f"sim_{a}").alias(f"mean_{a}") for a in attributes))
        pairs = pairs.crossJoin(F.broadcast(means))  # one row
        asked = pairs.withColumns({f"ask_{a}": selected(a, mode, F.col(f"mean_{a}")) for a in attributes})
        return asked.drop(*(f"mean_{a}" for a in attributes))
    return pairs.withColumns({f"ask_{a}": selected(a, mode, low) for a in attributes})


def provide(pairs: DataFrame, records: DataFrame, attributes: Sequence[str] = ATTRIBUTES, most: int | None = None) -> DataFrame:
    """Plaintext replies (pair_id, owner, rec_id, FN..POB) for pairs with ask_<attr>: values that are asked for, else null.

    Pairs are bounded by the review budget and are sent to the tasks, if they are few enough.  ``most`` lets owners give no more than so many, in order.
    """
    asks = [f"ask_{a}" for a in attributes]
    sides = F.explode(F.array(F.struct(F.lit("A").alias("owner"), F.col("left_id").alias("rec_id")), F.struct(F.lit("B").alias("owner"), F.col("right_id").alias("rec_id"))))
    wanted = pairs.select("pair_id", *asks, sides.alias("side")).select("pair_id", *asks, "side.owner", "side.rec_id")
    joined = records.join(sent(wanted), ["owner", "rec_id"])
    given, so_far = {}, F.lit(0)
    for a in attributes:
        may = F.col(f"ask_{a}") & F.col(a).isNotNull()
        if most is not None:
            may = may & (so_far < most)
            so_far = so_far + F.when(may, 1).otherwise(0)
        given[a] = F.when(may, F.col(a))
    return joined.select("pair_id", "owner", "rec_id", *(v.alias(a) for a, v in given.items()))
