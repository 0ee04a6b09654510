"""Standard blocking on several hashed keys, without duplicate pairs."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkveil.functions import crypto
from linkveil.session import durable, sent

#: Pairs of a block that one task makes, about, and parts of a block at most.
PAIRS_A_TASK = 2_000_000
PARTS = 4096


def soundex(value: Column) -> Column:
    return F.soundex(value)


#: Parts of each blocking key.
KEYS: dict[str, tuple] = {
    "fn_yob": (F.col, ("FN", "YOB")),
    "ln_yob": (F.col, ("LN", "YOB")),
    "sounds": (lambda c: F.soundex(F.col(c)), ("FN", "LN")),
}


def keys(records: DataFrame, key: str, spec: Sequence[str] = tuple(KEYS)) -> DataFrame:
    """Adds ``keys``: the keyed digest of each blocking key, null where a part is missing (no block)."""

    def digest(name: str) -> Column:
        make, columns = KEYS[name]
        parts = [make(c) for c in columns]
        whole = reduce(lambda a, b: a & b, (p.isNotNull() for p in parts))
        return F.when(whole, crypto.hmac_sha256(F.concat_ws("|", F.lit(name), *parts), key))

    return records.withColumn("keys", F.array(*(digest(n) for n in spec)))


def _short(digest: Column) -> Column:
    """128 bits of a digest, a quarter of its hexadecimal form's bytes."""
    return F.unhex(F.md5(digest.cast("binary")))


def candidates(
    left: DataFrame, right: DataFrame, columns: Sequence[str] = (), max_block: int | None = None, per_task: int | None = PAIRS_A_TASK, n_keys: int = len(KEYS)
) -> DataFrame:
    """Pairs of records that share a blocking key: left_id, right_id and ``columns`` of each side with l_ and r_.

    Both sides have rec_id and keys.  Instead of a distinct over all pairs, a pair stays under the first key that it
    shares only.  ``columns`` (the filters' words) travel with the keys, so that pairs are compared where they come up and
    aren't shuffled.  Blocks with over ``per_task`` pairs are counted first and dealt out: their left rows by a hash of the id,
    their right rows to each part; all others are joined as they are.  Blocks with over ``max_block`` pairs go, if that is
    set; ``purged`` tells the loss.  Pairs grow with the square of the records, so they are never written here: what is
    shuffled are the records, each with 128 bits of its digest and of those before it (``n_keys`` keys at most).
    """
    guarded = F.when(F.size("keys") > n_keys, F.raise_error(F.lit(f"records have more than {n_keys} keys"))).otherwise(F.transform("keys", _short))
    before = [f"before{i}" for i in range(n_keys - 1)]

    def spread(df: DataFrame, p: str) -> DataFrame:
        each = df.select("rec_id", *columns, guarded.alias("short")).select("*", F.posexplode("short").alias("key_no", "digest")).where("digest IS NOT NULL")
        earlier = [F.when(F.col("key_no") > i, F.get("short", F.lit(i))).alias(p + name) for i, name in enumerate(before)]
        return each.select("key_no", "digest", F.col("rec_id").alias(f"{p}id"), *earlier, *(F.col(c).alias(f"{p}{c}") for c in columns))

    a, b, on = spread(left, "l_"), spread(right, "r_"), ["key_no", "digest"]
    if max_block is not None:
        sizes = _sizes(a, b).where(F.col("pairs") <= max_block).select(*on)
        a = a.join(sizes, on, "left_semi")
    if per_task is not None:
        parts = F.least(F.lit(PARTS), F.ceil(F.col("pairs") / per_task)).cast("int")
        large = durable(_sizes(a, b).where(F.col("pairs") > per_task).select(*on, parts.alias("parts")))
        if not large.isEmpty():
            large = sent(large)
            a = a.join(large, on, "left").withColumn("part", F.coalesce(F.pmod(F.xxhash64("l_id"), F.col("parts")), F.lit(0)).cast("int")).drop("parts")
            b = b.join(large, on, "left").withColumn("part", F.explode(F.sequence(F.lit(0), F.coalesce(F.col("parts"), F.lit(1)) - 1))).drop("parts")
            on = [*on, "part"]
    pairs = a.join(b, on).drop("part")
    for name in before:  # null from the pair's own key on
        pairs = pairs.where(~F.coalesce(F.col(f"l_{name}") == F.col(f"r_{name}"), F.lit(False)))
    return pairs.drop("digest", *(p + name for p in ("l_", "r_") for name in before)).withColumnsRenamed({"l_id": "left_id", "r_id": "right_id"})


def all_pairs(left: DataFrame, right: DataFrame) -> DataFrame:
    """Brute force for tests: every pair."""
    return left.select(F.col("rec_id").alias("left_id")).crossJoin(right.select(F.col("rec_id").alias("right_id")))


def block_sizes(left: DataFrame, right: DataFrame) -> DataFrame:
    """(key_no, digest, n_left, n_right, pairs) of each block that both sides have."""
    each = lambda df: df.select(F.posexplode("keys").alias("key_no", "digest")).where("digest IS NOT NULL")
    return _sizes(each(left), each(right))


def _sizes(left: DataFrame, right: DataFrame) -> DataFrame:
    """Of rows (key_no, digest)."""
    count = lambda df, name: df.groupBy("key_no", "digest").agg(F.count(F.lit(1)).alias(name))
    return count(left, "n_left").join(count(right, "n_right"), ["key_no", "digest"]).withColumn("pairs", F.col("n_left") * F.col("n_right"))


def purged(left: DataFrame, right: DataFrame, max_block: int) -> DataFrame:
    """Blocks and pairs that a limit would drop, so that the loss can be seen."""
    return block_sizes(left, right).where(F.col("pairs") > max_block).agg(F.count(F.lit(1)).alias("blocks"), F.coalesce(F.sum("pairs"), F.lit(0)).alias("pairs"))
