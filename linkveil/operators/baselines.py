"""What the protocol is compared with."""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkveil.operators import block, classify, compare, encode, measures, oracle, pairwise
from linkveil.session import sent


def fitted_weights(records: DataFrame, error: float | Mapping[str, float] = 0.01, attributes=encode.ATTRIBUTES, approximate: bool = False) -> DataFrame:
    """(attr, n_values, weight): log2((1 - error) / frequency), with 1 / number of distinct values as the average frequency."""
    count = F.approx_count_distinct if approximate else F.countDistinct
    row = records.agg(*(count(a).alias(a) for a in attributes))
    rows = F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("n_values"), F.lit(float(error if isinstance(error, (int, float)) else error[a])).alias("error")) for a in attributes)))
    return row.select(rows.alias("r")).select("r.attr", "r.n_values", F.round(F.log2((1 - F.col("r.error")) * F.greatest("r.n_values", F.lit(1))), 9).alias("weight"))


def top_only(candidates: DataFrame, t: float) -> DataFrame:
    """The top layer alone at a threshold: pairs with g."""
    return classify.threshold(candidates, t)


def attribute_only(pairs: DataFrame, records: DataFrame, p: encode.Parameters, weights: Mapping[str, float] = encode.WEIGHTS) -> DataFrame:
    """Pairs (left_id, right_id, ...) with sim_<attr> of attribute filters without pair keys, and sim, their weighted mean."""
    filters = encode.attribute_filters(records, p)
    found = plain_similarities(pairs, filters, p.attribute_m)
    return found.withColumn("sim", compare.weighted_mean(dict(weights)))


def blocked_scores(records: DataFrame, p: encode.Parameters, weights: Mapping[str, float] = encode.WEIGHTS, rows: DataFrame | None = None, single: bool = False, sims: bool = True) -> DataFrame:
    """``attribute_only`` of all pairs of the blocking (left_id, right_id, truth), compared where they come up: the records' filters
    are shuffled once, the pairs aren't.  ``rows`` are the records' dealt rows or a pass of them, if there are any yet; for ``single``
    and ``sims`` see ``pairwise.scores``."""
    if rows is None:
        keyed = block.keys(records, p.key)
        large = pairwise.large_blocks(keyed.select("owner", "keys"))
        rows = pairwise.dealt(pairwise.attribute_filters(keyed, p, ["keys"]), large, pairwise.attribute_bits(p), records.count())
    return pairwise.scores(rows, p, weights, single, sims)


def wide_filters(filters: DataFrame, m: int = 256) -> DataFrame:
    """One row a record (rec_id, <attr>_<word>, <attr>_ones)."""
    words = [*measures.names(m), "ones"]
    return filters.groupBy("rec_id").agg(*(F.max(F.when(F.col("attr") == a, F.col(w))).alias(f"{a}_{w}") for a in encode.ATTRIBUTES for w in words))


def plain_similarities(pairs: DataFrame, filters: DataFrame, m: int = 256) -> DataFrame:
    """Adds sim_<attr> to pairs from filters (rec_id, attr, words, ones): one wide row a record, joined once for each side."""
    wide = wide_filters(filters, m)
    side = lambda s, name: wide.select(F.col("rec_id").alias(name), *(F.col(c).alias(f"{s}{c}") for c in wide.drop("rec_id").columns))
    return wide_similarities(pairs.join(side("l_", "left_id"), "left_id").join(side("r_", "right_id"), "right_id"), m)


def wide_similarities(joined: DataFrame, m: int = 256) -> DataFrame:
    """Adds sim_<attr> to pairs that have both records' wide filters with l_ and r_, and drops those."""
    words = [*measures.names(m), "ones"]
    sims = {}
    for a in encode.ATTRIBUTES:
        common = compare.common_ones(m, f"l_{a}_", f"r_{a}_")
        sims[f"sim_{a}"] = compare.dice(common, F.col(f"l_{a}_ones"), F.col(f"r_{a}_ones"))
    return joined.withColumns(sims).drop(*(f"{s}{a}_{w}" for s in ("l_", "r_") for a in encode.ATTRIBUTES for w in words))


def full_review(pairs: DataFrame, err: float = 0.0, seed: int = 0) -> DataFrame:
    """A human with full plaintext labels every candidate (with truth and pair_id): the upper bound of quality, the worst of effort."""
    return pairs.withColumn("g", oracle.human(F.col("truth"), err, seed))


def full_plaintext_review(pairs: DataFrame, records: DataFrame, attributes=encode.ATTRIBUTES) -> DataFrame:
    """(attr, values, characters, shown): what reviewers of ``pairs`` (left_id, right_id) read with full plaintext, and how many of
    those characters the masked display shows."""
    sides = F.explode(F.array(*(F.struct(F.lit(s).alias("side"), F.col(f"{s}_id").alias("rec_id")) for s in ("left", "right"))))
    wanted = pairs.select("pair_id", sides.alias("s")).select("pair_id", "s.*")
    values = F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")) for a in attributes)))
    read = records.join(sent(wanted), "rec_id").select("pair_id", "side", values.alias("v")).select("pair_id", "side", "v.*")
    both = read.groupBy("pair_id", "attr").agg(*(F.max(F.when(F.col("side") == s, F.col("value"))).alias(s) for s in ("left", "right")))
    each = [(F.col(x), oracle.mask_positions(F.col(x), F.col(y))) for x, y in (("left", "right"), ("right", "left"))]
    size = lambda c: F.coalesce(F.length(c), F.lit(0))
    return both.groupBy("attr").agg(
        F.sum(sum((c.isNotNull().cast("long") for c, _ in each), F.lit(0))).alias("values"),
        F.sum(sum((size(c) for c, _ in each), F.lit(0))).cast("long").alias("characters"),
        F.sum(sum((size(F.translate(m, oracle.MASK, "")) for _, m in each), F.lit(0))).cast("long").alias("shown"),
    )


def exact_grams(pairs: DataFrame, records: DataFrame, attributes=encode.ATTRIBUTES, q: int = 2) -> DataFrame:
    """Plaintext reference of the record filter: Dice coefficient of the union of all attributes' grams."""
    from linkveil.functions import text

    whole = F.array_distinct(F.flatten(F.array_compact(F.array(*(text.qgrams(F.col(a), q) for a in attributes)))))
    sets = records.select("rec_id", whole.alias("grams"))
    left, right = sets.withColumnsRenamed({"rec_id": "left_id", "grams": "l_grams"}), sets.withColumnsRenamed({"rec_id": "right_id", "grams": "r_grams"})
    joined = pairs.join(left, "left_id").join(right, "right_id")
    return joined.withColumn("sim", text.set_dice(F.col("l_grams"), F.col("r_grams"))).drop("l_grams", "r_grams")
