"""Quality, effort and privacy measures."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from linkveil.functions import bits
from linkveil.session import durable, sent
from linkveil.sources.registry import ATTRIBUTES

DIGITS = 9
#: Part of a bin beside its borders in which similarities are rounded.
BORDER = 1e-4


def f1(tp: Column, fp: Column, fn: Column) -> Column:
    return F.coalesce(F.try_divide(2.0 * tp, 2 * tp + fp + fn), F.lit(0.0))


def quality(result: DataFrame, truth: DataFrame) -> DataFrame:
    """tp, fp, fn, precision, recall, f1 of predicted pairs (left_id, right_id, g) against all true ones; pairs that blocking lost count as missed."""
    predicted = result.where("g").select("left_id", "right_id", F.lit(1).alias("said"))
    both = predicted.join(truth.select("left_id", "right_id", F.lit(1).alias("true")), ["left_id", "right_id"], "full")
    counts = both.agg(
        F.count(F.when(F.col("said").isNotNull() & F.col("true").isNotNull(), 1)).alias("tp"),
        F.count(F.when(F.col("true").isNull(), 1)).alias("fp"),
        F.count(F.when(F.col("said").isNull(), 1)).alias("fn"),
    )
    return counts.withColumns({
        "precision": F.coalesce(F.try_divide(F.col("tp").cast("double"), F.col("tp") + F.col("fp")), F.lit(0.0)),
        "recall": F.coalesce(F.try_divide(F.col("tp").cast("double"), F.col("tp") + F.col("fn")), F.lit(0.0)),
        "f1": f1(F.col("tp"), F.col("fp"), F.col("fn")),
    })


def micro_f1(metrics: DataFrame, by: Sequence[str] = ("round",)) -> DataFrame:
    """F1 of the summed counts of all runs, with the least and greatest of single runs and their distance."""
    each = metrics.withColumn("f1", f1(F.col("tp"), F.col("fp"), F.col("fn")))
    out = each.groupBy(*by).agg(F.count(F.lit(1)).alias("runs"), F.sum("tp").alias("tp"), F.sum("fp").alias("fp"), F.sum("fn").alias("fn"), F.min("f1").alias("min_f1"), F.max("f1").alias("max_f1"))
    return out.withColumn("micro_f1", f1(F.col("tp"), F.col("fp"), F.col("fn"))).withColumn("f1_range", F.col("max_f1") - F.col("min_f1"))


def histogram(pairs: DataFrame, sim: str = "sim", step: float = 0.001, digits: int | None = None, weight: str | None = None) -> DataFrame:
    """(bin, n, n_true): pairs and true pairs by similarity, rounded to ``digits`` if given; 1 / step + 1 rows at most, which is
    all that later rounds read.  A row stands for ``weight`` pairs, if that is named.

    Rounding takes a decimal number for each pair, so only similarities next to a bin's border are rounded; others can't leave their bin."""
    value = F.col(sim) / step
    exact = F.floor(F.round((F.col(sim) if digits is None else F.round(sim, digits)) / step, 6))
    if digits is None or 0.5 * 10.0**-digits / step < BORDER / 2:
        rest = value - F.floor(value)
        exact = F.when((rest > BORDER) & (rest < 1 - BORDER), F.floor(value)).otherwise(exact)
    one, true = (F.count(F.lit(1)), F.col("truth").cast("long")) if weight is None else (F.sum(weight), F.when(F.col("truth"), F.col(weight)).otherwise(0))
    return pairs.groupBy(exact.cast("int").alias("bin")).agg(one.alias("n"), F.sum(true).alias("n_true"))


def quality_by_threshold(counts: DataFrame, n_true: Column | int, step: float = 0.001) -> DataFrame:
    """tp, fp, fn, f1 at each bin's lower end, by running sums over a histogram (bounded, so one window is fine)."""
    above = Window.orderBy(F.desc("bin")).rowsBetween(Window.unboundedPreceding, 0)
    total = F.lit(n_true) if isinstance(n_true, int) else n_true
    sums = counts.withColumn("tp", F.sum("n_true").over(above)).withColumn("fp", F.sum(F.col("n") - F.col("n_true")).over(above)).withColumn("fn", total - F.col("tp"))
    return sums.select(F.round(F.col("bin") * step, DIGITS).alias("t"), "tp", "fp", "fn", F.round(f1(F.col("tp"), F.col("fp"), F.col("fn")), DIGITS).alias("f1"))


def best_threshold(counts: DataFrame, n_true: Column | int, step: float = 0.001) -> DataFrame:
    """The threshold with the greatest F1, the lowest of equals: one row."""
    return quality_by_threshold(counts, n_true, step).orderBy(F.desc("f1"), "t").limit(1)


def true_pairs(records: DataFrame) -> DataFrame:
    """All pairs of equal entities across owners."""
    side = lambda o, name: records.where(F.col("owner") == o).select(F.col("rec_id").alias(name), "entity_id")
    return side("A", "left_id").join(side("B", "right_id"), "entity_id").select("left_id", "right_id")


def blocking(candidates: DataFrame, records: DataFrame) -> DataFrame:
    """n_candidates, n_true, n_kept, pair completeness and reduction ratio.  Where candidates say whether they are true, they are
    counted in one pass and not joined."""
    truth = true_pairs(records)
    n, n_kept = F.count(F.lit(1)).alias("n_candidates"), F.count(F.when(F.col("truth"), 1)).alias("n_kept") if "truth" in candidates.columns else F.count(F.lit(1)).alias("n_kept")
    if "truth" in candidates.columns:
        counted = candidates.agg(n, n_kept)
    else:
        counted = candidates.agg(n).crossJoin(candidates.join(truth, ["left_id", "right_id"], "left_semi").agg(n_kept))  # one row each
    sizes = records.agg(F.count(F.when(F.col("owner") == "A", 1)).alias("n_a"), F.count(F.when(F.col("owner") == "B", 1)).alias("n_b"))
    row = counted.crossJoin(truth.agg(F.count(F.lit(1)).alias("n_true"))).crossJoin(sizes)  # one row each
    return row.select(
        "n_candidates", "n_true", "n_kept",
        F.round(F.try_divide(F.col("n_kept").cast("double"), F.col("n_true")), DIGITS).alias("pair_completeness"),
        F.round(1 - F.try_divide(F.col("n_candidates").cast("double"), F.col("n_a") * F.col("n_b")), DIGITS).alias("reduction_ratio"),
    )


def blocking_difference(one: tuple[DataFrame, DataFrame], other: tuple[DataFrame, DataFrame], name: str, other_name: str) -> DataFrame:
    """Pairs of two top layers (records with keys, candidates), and pairs that only one of them has: one row.

    A pair comes up by its two records' keys alone, so pairs of records with the same keys in both layers are in both.  Only pairs
    of other records are set against each other; all pairs are counted, and none of them is shuffled."""
    keys = lambda records, column: records.select("owner", "rec_id", F.col("keys").alias(column), F.lit(True).alias(f"has_{column}"))
    both = keys(one[0], "one").join(keys(other[0], "other"), ["owner", "rec_id"], "full")
    same = F.col("has_one").eqNullSafe(F.col("has_other")) & F.col("one").eqNullSafe(F.col("other"))
    moved = durable(both.where(~same).select("rec_id").distinct())
    count = lambda df, column: df.agg(F.count(F.lit(1)).alias(column))
    row = count(one[1], name).crossJoin(count(other[1], other_name))  # one row each
    if moved.isEmpty():
        return row.withColumns({f"only_{n}": F.lit(0).cast("long") for n in (name, other_name)})
    some = sent(moved)
    side = lambda pairs, c: pairs.join(some.withColumnRenamed("rec_id", c), c, "left_semi").select("left_id", "right_id")
    touched = lambda pairs: side(pairs, "left_id").union(side(pairs.join(some.withColumnRenamed("rec_id", "left_id"), "left_id", "left_anti"), "right_id"))
    a, b = touched(one[1]), touched(other[1])
    return row.crossJoin(count(a.exceptAll(b), f"only_{name}")).crossJoin(count(b.exceptAll(a), f"only_{other_name}"))


def bit_counts(filters: DataFrame, m: int, by: Sequence[str] = ()) -> DataFrame:
    """(by..., bit, cnt) for every bit of every group, 0 where no filter has it.

    Each word becomes a row and its 64 bits are summed as columns of one aggregation, so no row is made for a set bit and the
    sums stay in generated code; m / 64 rows a group are shuffled from each task.
    """
    words = F.explode(F.array(*(F.struct(F.lit(i).alias("i"), F.col(w).alias("w")) for i, w in enumerate(bits.names(m)))))
    each = filters.select(*by, words.alias("x")).select(*by, "x.i", "x.w")
    sums = [F.sum(F.shiftrightunsigned("w", b).bitwiseAND(F.lit(1).cast("long"))).alias(f"b{b}") for b in range(64)]
    wide = each.groupBy(*by, "i").agg(*sums).select(*by, "i", F.array(*(f"b{b}" for b in range(64))).alias("counts"))
    return wide.select(*by, "i", F.posexplode("counts").alias("b", "cnt")).select(*by, (F.col("i") * 64 + F.col("b")).alias("bit"), "cnt")


def unevenness(counts: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """(by..., gini, js_divergence, js_distance) of bit counts against a uniform distribution; logarithms to base 2.

    Every group has m rows, so the windows are small.
    """
    group = Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))
    ranked = counts.withColumn("i", F.row_number().over(group.orderBy("cnt", "bit"))).withColumn("total", F.sum("cnt").over(group)).withColumn("m", F.count(F.lit(1)).over(group))
    share, even = F.col("cnt") / F.col("total"), 1 / F.col("m")
    middle = (share + even) / 2
    term = F.when(F.col("cnt") > 0, share * F.log2(share / middle)).otherwise(0.0) / 2 + even * F.log2(even / middle) / 2
    sums = ranked.groupBy(*by).agg(
        F.sum((2 * F.col("i") - F.col("m") - 1) * F.col("cnt") / (F.col("m") * F.col("total"))).alias("gini"), F.greatest(F.sum(term), F.lit(0.0)).alias("js")
    )
    return sums.select(*by, F.round("gini", DIGITS).alias("gini"), F.round("js", DIGITS).alias("js_divergence"), F.round(F.sqrt("js"), DIGITS).alias("js_distance"))


def encoding_counts(attribute_filters: DataFrame) -> DataFrame:
    return attribute_filters.groupBy("attr").agg(F.count(F.lit(1)).alias("encodings"))


def exposure(requests: DataFrame) -> DataFrame:
    """Pairs, records and record slots that a lower layer has seen."""
    return requests.agg(F.countDistinct("pair_id").alias("pairs"), F.countDistinct("owner", "rec_id").alias("records"), F.count(F.lit(1)).alias("slots"))


def attribute_share(replies: DataFrame, attributes: Sequence[str] = ATTRIBUTES, by: Sequence[str] = ()) -> DataFrame:
    """Share of record slots of the plaintext layer for which each attribute was given."""
    return replies.groupBy(*by).agg(*(F.round(F.avg(F.col(a).isNotNull().cast("double")), DIGITS).alias(a) for a in attributes))


def disclosure(replies: DataFrame, population: DataFrame, attributes: Sequence[str] = ATTRIBUTES, by: Sequence[str] = ()) -> DataFrame:
    """Anonymity-weighted disclosure: mean over record slots of d / (k D).

    d attributes were given, k records of the same owner's population have the same values there.  Only patterns of given
    attributes that occur are counted: each population record is repeated once for each such pattern (128 at most; the
    list is sent to the tasks) with the other values blanked.
    """
    bit = {a: 1 << i for i, a in enumerate(attributes)}
    pattern = reduce(lambda x, y: x + y, (F.when(F.col(a).isNotNull(), b).otherwise(0) for a, b in bit.items()))
    given = replies.withColumn("pattern", pattern).withColumn("d", F.bit_count("pattern"))
    patterns = given.select("pattern").distinct()
    key = lambda shown: F.concat_ws("\u0001", *(F.when(shown(a), F.coalesce(F.col(a), F.lit("\u0002"))).otherwise(F.lit("\u0003")) for a in attributes))
    crossed = population.crossJoin(F.broadcast(patterns)).withColumn("values", key(lambda a: F.col("pattern").bitwiseAND(F.lit(bit[a])) > 0))
    sizes = crossed.groupBy("owner", "pattern", "values").agg(F.count(F.lit(1)).alias("k"))
    valued = given.withColumn("values", key(lambda a: F.col(a).isNotNull()))
    joined = valued.join(sizes, ["owner", "pattern", "values"], "left")
    score = F.avg(F.when(F.col("d") > 0, F.col("d") / F.greatest(F.col("k"), F.lit(1))).otherwise(0.0)) / float(len(attributes))
    return joined.groupBy(*by).agg(F.count(F.lit(1)).alias("slots"), F.round(score, DIGITS).alias("score"))


def human_share(metrics: DataFrame) -> DataFrame:
    """Human reviews among all reviews of the upper loop, by round."""
    return metrics.withColumn("human_share", F.round(F.try_divide(F.col("reviews_human").cast("double"), F.col("reviews_attr")), DIGITS))


def correction_rate(log: DataFrame, by: Sequence[str] = ("round",)) -> DataFrame:
    """Reviewed pairs whose label a lower layer changed, and changes to the right label, by round."""
    wrong_before, right_now = F.col("g_top") != F.col("truth"), F.col("g") == F.col("truth")
    return log.groupBy(*by).agg(
        F.count(F.lit(1)).alias("reviewed"), F.count(F.when(F.col("g") != F.col("g_top"), 1)).alias("changed"), F.count(F.when(wrong_before & right_now, 1)).alias("corrected")
    ).withColumn("rate", F.round(F.col("corrected") / F.col("reviewed"), DIGITS))


def oracle_error(log: DataFrame) -> DataFrame:
    """Share of wrong labels by layer that gave the label."""
    return log.groupBy("layer").agg(F.count(F.lit(1)).alias("labels"), F.round(F.avg((F.col("g") != F.col("truth")).cast("double")), DIGITS).alias("error"))


def rounds_to(metrics: DataFrame, target: float, by: Sequence[str] = ("run_id",)) -> DataFrame:
    """First round, and human reviews by then, at which F1 reaches the target; null if never."""
    reached = F.when(F.col("f1") >= target, F.struct("round", "reviews_human"))
    return metrics.groupBy(*by).agg(F.min(reached).alias("first")).select(*by, F.col("first.round").alias("round"), F.col("first.reviews_human").alias("reviews_human"))


def gap(final_f1: DataFrame, baselines: DataFrame) -> DataFrame:
    """Distance of a result (name, f1) to each baseline (baseline, f1)."""
    return final_f1.crossJoin(F.broadcast(baselines.withColumnRenamed("f1", "baseline_f1"))).withColumn("gap", F.round(F.col("f1") - F.col("baseline_f1"), DIGITS))  # a few rows


def forest_state(state: DataFrame) -> DataFrame:
    """Trees and age range by run and round, from (run_id, round, seq) rows of living trees."""
    return state.groupBy("run_id", "round").agg(F.count(F.lit(1)).alias("trees"), F.min("seq").alias("oldest"), F.max("seq").alias("newest"))


def sampling_floor(filters: int, fill: float) -> float:
    """Gini coefficient that chance alone gives ``filters`` independent filters of a fill rate: 0.564 sqrt((1 - f) / (f n))."""
    return 0.564 * ((1 - fill) / (fill * filters)) ** 0.5


def names(m: int) -> list[str]:
    return bits.names(m)
