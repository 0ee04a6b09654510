"""Bloom-filter encodings of records and attributes.

Grams of a fixed key come from a small alphabet, so they are hashed once: the distinct grams get their bit masks, and
records pick the masks up by a join and combine them with ``bit_or``, which Spark does before its shuffle (one row a
record).  The mask table is sent to the tasks only if it has at most MASK_ROWS rows.  Pair-keyed encodings can't share
masks; there are few of them, and each request's grams are hashed on their own.
"""

from __future__ import annotations

import math
import secrets
from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from linkveil.functions import bits, crypto, text
from linkveil.session import durable, sent
from linkveil.sources.registry import ATTRIBUTES

#: Hash functions of each attribute's filter.
HASHES = {"FN": 18, "MN": 21, "LN": 17, "YOB": 26, "CITY": 13, "ZIP": 21, "POB": 43}
#: Attribute weights of the attribute-only baseline.
WEIGHTS = {"FN": 12.04, "MN": 15.15, "LN": 5.12, "YOB": 6.58, "CITY": 8.23, "ZIP": 10.95, "POB": 6.63}
MASK_ROWS = 200_000
PREFIX = 3


@dataclass(frozen=True)
class Parameters:
    """What owners agree on and units never see."""

    key: str
    m: int = 1024
    h: int = 12
    q: int = 2
    attribute_m: int = 256
    hashes: Mapping[str, int] = field(default_factory=lambda: dict(HASHES))
    attributes: tuple[str, ...] = ATTRIBUTES
    family: str = "random"


def grams(records: DataFrame, attributes: Sequence[str], q: int = 2, keep: Sequence[str] = ("rec_id", "owner")) -> DataFrame:
    """(keep..., attr, gram): each distinct gram of each attribute of a record; missing values have none."""
    values = F.array(*(F.struct(F.lit(a).alias("attr"), text.qgrams(F.col(a), q).alias("grams")) for a in attributes))
    each = records.select(*keep, F.explode(values).alias("v"))
    return each.select(*keep, F.col("v.attr").alias("attr"), F.explode("v.grams").alias("gram"))


def _joined(left: DataFrame, masks: DataFrame, on: list[str], rows: int | None) -> DataFrame:
    return left.join(F.broadcast(masks) if rows is not None and rows <= MASK_ROWS else masks, on)


def _combine(rows: DataFrame, by: Sequence[str], m: int) -> DataFrame:
    """Bits of each group and their number.

    ``ones`` is computed inside the aggregation: as a projection over the words it would become a constraint of the plan, of
    which the optimiser keeps a variant for each set of words that a later step renames.
    """
    merged = [F.bit_or(w) for w in bits.names(m)]
    ones = bits.popcount(merged).cast("int").alias("ones")
    return rows.groupBy(*by).agg(*(x.alias(w) for x, w in zip(merged, bits.names(m), strict=True)), ones)


def gram_masks(found: DataFrame, by: Sequence[str], key: Column | str, h: Column | int, m: int, family: str = "random", most: int = 48) -> DataFrame:
    """(by..., w0...): the bits of each distinct gram under a key that may depend on ``by``."""
    seeds = found.select(*by).distinct().withColumn("p", crypto.positions(crypto.hmac_sha256(F.col("gram"), key), h, m, family, most))
    return seeds.select(*by, *bits.pack(F.col("p"), m))


def record_filter(records: DataFrame, p: Parameters, salt_by_attribute: bool = False, record_salt: str | None = None) -> DataFrame:
    """All attributes of a record in one filter: rec_id, owner, w0..., ones.

    ``salt_by_attribute`` adds the attribute's name to the key.  ``record_salt`` adds a value of the record (hardening);
    records without that value are encoded without salt.
    """
    keep = ["rec_id", "owner"] + (["salt"] if record_salt else [])
    records = records.repartition("rec_id")  # short values are dealt out, not filters
    source = records.withColumn("salt", F.coalesce(F.col(record_salt).cast("string"), F.lit(""))) if record_salt else records
    found = grams(source, p.attributes, p.q, keep)
    by = (["attr"] if salt_by_attribute else []) + (["salt"] if record_salt else []) + ["gram"]
    parts = ([F.col("attr")] if salt_by_attribute else []) + ([F.col("salt")] if record_salt else [])
    key = crypto.composed(crypto.check_key(p.key), *parts) if parts else p.key
    masks = gram_masks(found, by, key, p.h, p.m, p.family, p.h)
    rows = None
    if not record_salt:  # grams alone are bounded by the alphabet; the optimiser sees to salted ones
        masks = durable(masks)
        rows = masks.count()
    return _combine(_joined(found, masks, by, rows), ["rec_id", "owner"], p.m)


def xor_fold(filters: DataFrame, m: int = 1024, times: int = 1) -> DataFrame:
    """Halves of each filter exclusive-or'ed, ``times`` over; ``ones`` follows."""
    for _ in range(times):
        half = m // 128
        folded = {f"w{i}": F.col(f"w{i}").bitwiseXOR(F.col(f"w{i + half}")) for i in range(half)}
        filters = filters.withColumns(folded).drop(*(f"w{i}" for i in range(half, m // 64)))
        m //= 2
    return filters.withColumn("ones", bits.popcount([F.col(w) for w in bits.names(m)]).cast("int"))


def attribute_filters(records: DataFrame, p: Parameters) -> DataFrame:
    """(rec_id, owner, attr, w0..w3, ones): one filter an attribute under the owners' key and the attribute's name; missing values have no row."""
    found = grams(records.repartition("rec_id"), p.attributes, p.q)
    h = F.create_map(*(F.lit(x) for a in p.attributes for x in (a, p.hashes[a])))
    key = crypto.composed(crypto.check_key(p.key), F.col("attr"))
    masks = durable(gram_masks(found, ["attr", "gram"], key, h[F.col("attr")], p.attribute_m, p.family, max(p.hashes.values())))
    return _combine(_joined(found, masks, ["attr", "gram"], masks.count()), ["rec_id", "owner", "attr"], p.attribute_m)


def new_pair_key(pair_id: Column, round_: Column | int = 0, seed: str | int | None = None) -> Column:
    """A key of 24 letters for one pair and round.

    The unit draws a secret of 256 bits for each call, and the keys are an HMAC under it, so who knows a pair's id knows
    nothing of its key.  The secret is drawn once for a plan, so a task that runs again gives the same keys; keep the requests
    written.  A ``seed`` takes the secret's place, for tests and simulations that must be repeatable."""
    round_ = F.lit(round_) if isinstance(round_, int) else round_
    secret = secrets.token_hex(32) if seed is None else f"pair keys {seed}"
    return crypto.letters(F.substring(crypto.hmac_sha256(F.concat_ws("|", pair_id.cast("string"), round_.cast("string")), secret), 1, 24))


def pair_keyed_filters(requests: DataFrame, records: DataFrame, p: Parameters) -> DataFrame:
    """(pair_id, owner, rec_id, attr, w0..w3, ones) for requests (pair_id, owner, rec_id, pair_key).

    Requests are bounded by the review budget; up to BROADCAST_ROWS of them are sent to the tasks, so the registry isn't
    shuffled.  The key is the owners' key, the pair's key and the attribute's name.
    """
    wanted = records.join(sent(requests.select("pair_id", "owner", "rec_id", "pair_key")), ["owner", "rec_id"])
    found = grams(wanted, p.attributes, p.q, ["pair_id", "owner", "rec_id", "pair_key"])
    h = F.create_map(*(F.lit(x) for a in p.attributes for x in (a, p.hashes[a])))
    key = crypto.composed(crypto.check_key(p.key), F.col("pair_key"), F.col("attr"))
    seeded = found.withColumn("p", crypto.positions(crypto.hmac_sha256(F.col("gram"), key), h[F.col("attr")], p.attribute_m, p.family, max(p.hashes.values())))
    rows = seeded.select("pair_id", "owner", "rec_id", "attr", *bits.pack(F.col("p"), p.attribute_m))
    return _combine(rows, ["pair_id", "owner", "rec_id", "attr"], p.attribute_m)


def bit_plan(weights: Mapping[str, float], m: int, attribute_m: int, key: str) -> list[tuple[int, str, int]]:
    """(position, attribute, bit): bits of the attribute filters in proportion to the weights, drawn and permuted by keyed hash."""
    import hashlib

    total, plan, names = sum(weights.values()), [], sorted(weights)
    exact = {a: m * weights[a] / total for a in names}
    share = {a: int(exact[a]) for a in names}
    for a in sorted(names, key=lambda a: (share[a] - exact[a], a))[: m - sum(share.values())]:
        share[a] += 1
    for a in names:
        for k in range(share[a]):
            bit = int(hashlib.sha256(f"{key}|{a}|{k}".encode()).hexdigest()[:8], 16) % attribute_m
            plan.append((a, bit))
    order = sorted(range(m), key=lambda i: hashlib.sha256(f"{key}|place|{i}".encode()).hexdigest())
    return [(place, *plan[i]) for place, i in enumerate(order)]


def sampled_filter(records: DataFrame, p: Parameters, weights: Mapping[str, float] = WEIGHTS, m: int = 1024) -> DataFrame:
    """One filter a record whose bits are sampled from its attribute filters: rec_id, owner, w0..., ones."""
    return sampled_values(records, p, weights, m).select("rec_id", "owner", *bits.names(m), "ones")


def sampled_values(records: DataFrame, p: Parameters, weights: Mapping[str, float] = WEIGHTS, m: int = 1024) -> DataFrame:
    """``sampled_filter`` beside the attributes, for an audit that knows the values."""
    from linkveil.operators import pairwise

    return pairwise.sampled_filters(records, p, bit_plan(weights, m, p.attribute_m, p.key), m)


def fit_hash_counts(records: DataFrame, m: int = 256, fill: float = 0.4, q: int = 2, attributes: Sequence[str] = ATTRIBUTES) -> DataFrame:
    """(attr, avg_grams, h): h = floor(m ln(1 / (1 - fill)) / average number of grams)."""
    sizes = records.select(*(F.size(text.qgrams(F.col(a), q)).alias(a) for a in attributes))
    means = sizes.agg(*(F.avg(F.when(F.col(a) > 0, F.col(a))).alias(a) for a in attributes))
    rows = F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("avg_grams")) for a in attributes)))
    bound = m * math.log(1 / (1 - fill))
    return means.select(rows.alias("r")).select("r.attr", "r.avg_grams").withColumn("h", F.floor(F.lit(bound) / F.col("avg_grams")).cast("int"))


def fill_rate(filters: DataFrame, m: int, by: Sequence[str] = ()) -> DataFrame:
    """Mean share of set bits."""
    return filters.groupBy(*by).agg(F.avg(F.col("ones") / float(m)).alias("fill"))


def frequency_classes(records: DataFrame, attributes: Sequence[str] = ATTRIBUTES) -> DataFrame:
    """(attr, value, n, freq_class): 1 for the top one per cent of an attribute's distinct values by count, 2 for the top five, else 3.

    Values of equal count are ranked by value.  Ranks come from the number of values by count, a table with a row for each
    different count.  Only the counts in which a border lies have their values ranked one by one, within the values of a
    common prefix of PREFIX characters, so no task sees all values.
    """
    values = F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")) for a in attributes))
    counts = durable(records.select(F.explode(values).alias("v")).select("v.*").where("value IS NOT NULL").groupBy("attr", "value").agg(F.count(F.lit(1)).alias("n")))
    sizes = counts.groupBy("attr", "n").agg(F.count(F.lit(1)).alias("size"))
    down = Window.partitionBy("attr").orderBy(F.desc("n")).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy("attr")
    ranked = sizes.withColumn("before", F.coalesce(F.sum("size").over(down), F.lit(0))).withColumn("total", F.sum("size").over(whole))
    share = lambda rank: F.coalesce(F.try_divide(rank, F.col("total") - 1), F.lit(0.0))
    kind = lambda rank: F.when(share(rank) < 0.01, 1).when(share(rank) < 0.05, 2).otherwise(3)
    ranked = ranked.withColumn("first", kind(F.col("before"))).withColumn("last", kind(F.col("before") + F.col("size") - 1))
    ranked = durable(ranked.withColumnRenamed("n", "level"))  # a row for each different count
    joined = counts.join(ranked, (counts["attr"] == ranked["attr"]) & (F.col("n") == F.col("level"))).select(counts["attr"], "value", "n", "before", "size", "total", "first", "last")
    settled = joined.where(F.col("first") == F.col("last")).select("attr", "value", "n", F.col("first").alias("freq_class"))
    cut = joined.where(F.col("first") != F.col("last"))
    # a border's ties: ranked within a prefix, with the number of ties under smaller prefixes in front
    prefix = F.substring("value", 1, PREFIX)
    cut = cut.withColumn("prefix", prefix)
    groups = cut.groupBy("attr", "n", "prefix").agg(F.count(F.lit(1)).alias("ties"))
    under = Window.partitionBy("attr", "n").orderBy("prefix").rowsBetween(Window.unboundedPreceding, -1)
    groups = groups.withColumn("smaller", F.coalesce(F.sum("ties").over(under), F.lit(0)))
    place = F.row_number().over(Window.partitionBy("attr", "n", "prefix").orderBy("value")) - 1
    tied = cut.withColumn("place", place).join(groups.select("attr", "n", "prefix", "smaller"), ["attr", "n", "prefix"])
    tied = tied.select("attr", "value", "n", kind(F.col("before") + F.col("smaller") + F.col("place")).alias("freq_class"))
    return settled.unionByName(tied)


def minhash_signature(values: Column, key: Column | str, size: int = 16) -> Column:
    """Another perturbation with a pair's key: minima of keyed hashes of an array of grams."""
    key = F.lit(key) if isinstance(key, str) else key
    return F.array(*(F.array_min(F.transform(values, lambda g, k=k: F.xxhash64(key, F.lit(k), g))) for k in range(size)))


def pair_keyed_minhash(requests: DataFrame, records: DataFrame, p: Parameters, size: int = 64) -> DataFrame:
    """(pair_id, owner, rec_id, attr, signature): MinHash in place of ``pair_keyed_filters``; the hashes' key is an HMAC of the pair's key and the attribute."""
    wanted = records.join(sent(requests.select("pair_id", "owner", "rec_id", "pair_key")), ["owner", "rec_id"])
    values = F.array(*(F.struct(F.lit(a).alias("attr"), text.qgrams(F.col(a), p.q).alias("grams")) for a in p.attributes))
    each = wanted.select("pair_id", "owner", "rec_id", "pair_key", F.explode(values).alias("v")).select("pair_id", "owner", "rec_id", "pair_key", "v.*").where("grams IS NOT NULL")
    secret = crypto.hmac_sha256(F.concat_ws(crypto.SEPARATOR, "pair_key", "attr"), p.key)
    return each.withColumn("secret", secret).select("pair_id", "owner", "rec_id", "attr", minhash_signature(F.col("grams"), F.col("secret"), size).alias("signature"))


def either(*conditions: Column) -> Column:
    return reduce(lambda a, b: a | b, conditions)
