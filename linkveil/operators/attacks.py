"""Privacy audits: what an attacker could read off the engine's own output.  Each returns a small table of counts and rates."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from linkveil.functions import bits
from linkveil.operators import encode
from linkveil.session import sent

DIGITS = 9


def _pattern(m: int):
    return F.concat_ws("|", *(F.col(w).cast("string") for w in bits.names(m)))


def frequency_alignment(filters: DataFrame, records: DataFrame, m: int = 256, top: int = 20, by: Sequence[str] = ()) -> DataFrame:
    """Ranks of filter patterns against ranks of plaintext values, per attribute: how many of the ``top`` most frequent patterns
    are encodings of the value of the same rank, and how often the most frequent pattern occurs.

    ``filters``: rec_id, owner, attr, words and ``by`` (a pair's id for pair-keyed filters); with value, if they lie beside their values.
    """
    values = records.select("rec_id", "owner", F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")) for a in encode.ATTRIBUTES))).alias("v")).select("rec_id", "owner", "v.*")
    beside = ["value"] if "value" in filters.columns else []
    seen = filters.select(*by, "rec_id", "owner", "attr", *beside, F.md5(_pattern(m).cast("binary")).alias("pattern"))
    seen = seen if beside else seen.join(values, ["rec_id", "owner", "attr"])
    place = lambda order: F.row_number().over(Window.partitionBy("attr").orderBy(*order))
    patterns = seen.groupBy("attr", "pattern").agg(F.count(F.lit(1)).alias("n"), F.min("value").alias("value"))
    patterns = patterns.withColumn("place", place([F.desc("n"), "value", "pattern"])).where(F.col("place") <= top)
    plain = values.where("value IS NOT NULL").groupBy("attr", "value").agg(F.count(F.lit(1)).alias("n"))
    plain = plain.withColumn("place", place([F.desc("n"), "value"])).where(F.col("place") <= top).select("attr", "place", F.col("value").alias("guess"))
    joined = patterns.join(plain, ["attr", "place"])
    return joined.groupBy("attr").agg(F.count(F.lit(1)).alias("tried"), F.count(F.when(F.col("value") == F.col("guess"), 1)).alias("hits"), F.max("n").alias("most_frequent"))


def one_difference(pairs: DataFrame, attributes: Sequence[str] = encode.ATTRIBUTES) -> DataFrame:
    """Pairs with sim_<attr> of which one is under 1 and none is missing."""
    count = sum((F.coalesce(F.col(f"sim_{a}") < 1, F.lit(False)).cast("int") for a in attributes), F.lit(0))
    missing = sum((F.col(f"sim_{a}").isNull().cast("int") for a in attributes), F.lit(0))
    return pairs.where((count == 1) & (missing == 0))


def attribute_bits(pairs: DataFrame, m: int = 1024, attributes: Sequence[str] = encode.ATTRIBUTES) -> DataFrame:
    """(attr, pairs, bits): from pairs with l_w.., r_w.. and sim_<attr> that differ in one attribute only, the bits that differ.

    One aggregation of exclusive-or'ed words; a bit of a sampled filter belongs to one attribute, so its attribute is
    found, while a joint filter's bits come up under several.
    """
    which = F.coalesce(*(F.when(F.col(f"sim_{a}") < 1, F.lit(a)) for a in attributes))
    single = one_difference(pairs, attributes).withColumn("attr", which)
    merged = single.groupBy("attr").agg(F.count(F.lit(1)).alias("pairs"), *(F.bit_or(F.col(f"l_w{i}").bitwiseXOR(F.col(f"r_w{i}"))).alias(f"w{i}") for i in range(m // 64)))
    return merged.select("attr", "pairs", bits.unpack([F.col(w) for w in bits.names(m)]).alias("bits"))


def attribution_precision(found: DataFrame, plan: DataFrame) -> DataFrame:
    """Share of attributed bits that the plan (position, attr) gives to the same attribute; a bit found for several attributes counts for each."""
    guesses = found.select("attr", F.explode("bits").alias("position"))
    joined = guesses.join(F.broadcast(plan.select("position", F.col("attr").alias("owner_attr"))), "position")  # m rows
    return joined.agg(F.count(F.lit(1)).alias("guesses"), F.count(F.when(F.col("attr") == F.col("owner_attr"), 1)).alias("right")).withColumn(
        "precision", F.round(F.try_divide(F.col("right").cast("double"), F.col("guesses")), DIGITS)
    )


def ambiguous_bits(found: DataFrame) -> DataFrame:
    """Bits that the attack gives to one attribute, and to more than one."""
    each = found.select("attr", F.explode("bits").alias("position")).groupBy("position").agg(F.count(F.lit(1)).alias("attrs"))
    return each.agg(F.count(F.when(F.col("attrs") == 1, 1)).alias("clear"), F.count(F.when(F.col("attrs") > 1, 1)).alias("ambiguous"))


def token_bits(filters: DataFrame, records: DataFrame, m: int = 256) -> DataFrame:
    """Token inference from known plaintext: an attacker who knows value and filter of one record of a pair tests whether the
    filter holds another record's value.  Share of filters of the same value that the known filter predicts, inside the pair
    and in the next pair of the same value: with pair keys nothing carries over.
    """
    values = records.select("rec_id", "owner", F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")) for a in encode.ATTRIBUTES))).alias("v")).select("rec_id", "owner", "v.*")
    known = filters.join(values, ["rec_id", "owner", "attr"]).withColumn("pattern", F.md5(_pattern(m).cast("binary"))).select("pair_id", "owner", "attr", "value", "pattern")
    a, b = known.where("owner = 'A'"), known.where("owner = 'B'")
    inside = a.join(b.select("pair_id", "attr", "value", F.col("pattern").alias("other")), ["pair_id", "attr", "value"])
    nxt = Window.partitionBy("owner", "attr", "value").orderBy("pair_id")
    across = a.withColumn("other", F.lead("pattern").over(nxt)).where("other IS NOT NULL")
    rate = lambda df, name: df.agg(F.count(F.lit(1)).alias(f"{name}_tests"), F.count(F.when(F.col("pattern") == F.col("other"), 1)).alias(f"{name}_hits"))
    return rate(inside, "inside").crossJoin(rate(across, "across"))  # one row each


def token_inference(filters: DataFrame, records: DataFrame, m: int = 256, q: int = 2) -> DataFrame:
    """Token inference from known plaintext: (attr, grams, tests, right, wrong).

    The attacker knows values and filters of half the records, takes the bits that all filters with a gram have in common for
    the gram's, and says that an unknown record has the gram if its filter has those bits.  ``right`` counts grams found among
    ``tests`` that unknown records have, ``wrong`` those said of records without them.  Grams come from a small alphabet, so the
    table of their bits is sent to the tasks where it is few enough.  Filters under different keys have no bits in common, so a
    gram's table is empty and every record is said to have it."""
    words = bits.names(m)
    known = F.pmod(F.crc32(F.col("rec_id").cast("binary")), F.lit(2)) == 0
    grams = encode.grams(records, encode.ATTRIBUTES, q)
    merged = filters.where(known).join(grams, ["rec_id", "owner", "attr"]).groupBy("attr", "gram").agg(F.count(F.lit(1)).alias("seen"), *(F.bit_and(w).alias(f"g_{w}") for w in words))
    said = F.lit(True)
    for w in words:
        said = said & (F.col(w).bitwiseAND(F.col(f"g_{w}")) == F.col(f"g_{w}"))
    unknown = filters.where(~known)
    found = unknown.join(sent(merged.where("seen > 1")), "attr").groupBy("attr").agg(F.countDistinct("gram").alias("grams"), F.count(F.when(said, 1)).alias("said"))
    true = unknown.join(grams, ["rec_id", "owner", "attr"]).join(merged.where("seen > 1"), ["attr", "gram"]).groupBy("attr").agg(F.count(F.lit(1)).alias("tests"), F.count(F.when(said, 1)).alias("right"))
    return found.join(true, "attr").select("attr", "grams", "tests", "right", (F.col("said") - F.col("right")).alias("wrong"))


def aligned_after_attribution(found: DataFrame, filters: DataFrame, records: DataFrame, m: int = 1024, top: int = 20) -> DataFrame:
    """The step after ``attribute_bits``: each attribute's bits alone make a pattern, and the most frequent patterns are set beside
    the most frequent values, as in ``frequency_alignment``.  Filters that lie beside their records' attributes aren't joined with them again."""
    masks = found.select("attr", *(x.alias(f"m_{w}") for w, x in zip(bits.names(m), bits.pack(F.col("bits"), m), strict=True)))
    parts = filters.crossJoin(F.broadcast(masks))  # one row an attribute
    known = [F.coalesce(*(F.when(F.col("attr") == a, F.col(a)) for a in encode.ATTRIBUTES)).alias("value")] if set(encode.ATTRIBUTES) <= set(filters.columns) else []
    parts = parts.select("rec_id", "owner", "attr", *known, *(F.col(w).bitwiseAND(F.col(f"m_{w}")).alias(w) for w in bits.names(m)))
    return frequency_alignment(parts, records, m, top)


def dictionary(filters: DataFrame, guesses: DataFrame, attribute: str, key: str, p: encode.Parameters) -> DataFrame:
    """If the owners' key leaks: encodes a public list of values (column ``value``) and joins it with an attribute's filters by pattern."""
    listed = guesses.select(F.col("value").alias("rec_id"), F.lit("-").alias("owner"), *(F.col("value").alias(a) if a == attribute else F.lit(None).cast("string").alias(a) for a in p.attributes))
    stolen = encode.Parameters(key=key, m=p.m, h=p.h, q=p.q, attribute_m=p.attribute_m, hashes=p.hashes, attributes=p.attributes, family=p.family)
    table = encode.attribute_filters(listed, stolen).select(_pattern(p.attribute_m).alias("pattern"), F.col("rec_id").alias("value"))
    seen = filters.where(F.col("attr") == attribute).select("rec_id", "owner", _pattern(p.attribute_m).alias("pattern"))
    return seen.join(table, "pattern").select("rec_id", "owner", "value")


def graph_exposure(candidates: DataFrame, requested: DataFrame, floor: float = 0.5) -> DataFrame:
    """Edges (pairs over a similarity) and nodes of the full similarity graph, and of the part that a lower layer sees."""
    edges = candidates.where(F.col("sim") >= floor)
    if {"sim", "left_id", "right_id"} <= set(requested.columns):  # requested pairs are candidates and tell their similarity
        part = requested.where(F.col("sim") >= floor).dropDuplicates(["pair_id"])
    else:
        part = edges.join(sent(requested.select("pair_id").distinct()), "pair_id", "left_semi")
    return _exposure(_edges(edges, "all"), part)


def node_exposure(nodes: DataFrame, requested: DataFrame, floor: float = 0.5) -> DataFrame:
    """``graph_exposure`` from the nodes of all edges (is_left, rec_id, n), of which a node may have several rows, and requested
    pairs (pair_id, left_id, right_id, sim)."""
    each = nodes.groupBy("is_left", "rec_id").agg(F.sum("n").alias("n"))
    left = F.col("is_left")
    edges = F.coalesce(F.sum(F.when(left, F.col("n"))), F.lit(0)).alias("all_edges")
    counts = each.agg(edges, F.count(F.when(left, 1)).alias("all_left"), F.count(F.when(~left, 1)).alias("all_right"))
    return _exposure(counts, requested.where(F.col("sim") >= floor).dropDuplicates(["pair_id"]))


def _edges(df: DataFrame, name: str) -> DataFrame:
    return df.agg(F.count(F.lit(1)).alias(f"{name}_edges"), F.countDistinct("left_id").alias(f"{name}_left"), F.countDistinct("right_id").alias(f"{name}_right"))


def _exposure(counts: DataFrame, part: DataFrame) -> DataFrame:
    return counts.crossJoin(_edges(part, "seen")).withColumn("edge_share", F.round(F.try_divide(F.col("seen_edges").cast("double"), F.col("all_edges")), DIGITS))  # one row each
