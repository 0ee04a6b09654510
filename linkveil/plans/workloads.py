"""The experiment workloads: curves over rounds, reference lines, privacy tables, ablations, and further carriers."""

from __future__ import annotations

import math
from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkveil.functions import text
from linkveil.operators import classify, compare, encode, measures, owner
from linkveil.operators.forest import SparkForest, score, train  # noqa: F401
from linkveil.plans import protocol
from linkveil.session import durable, stored
from linkveil.sources.registry import ATTRIBUTES, registry


def data_set(spark: SparkSession, sf_dir: str, p: encode.Parameters, variant: str = "E1M", hardening: str | None = None) -> protocol.Prepared:
    return protocol.prepare(stored(registry(spark, sf_dir, variant)), p, variant + ("-XOR" if hardening else ""), hardening)


def schedule(prepared: protocol.Prepared, budget: int) -> protocol.Schedule:
    """The published schedule in proportion to the data; ``budget`` is meant for 50,000 records a source (100, 200, 300)."""
    n = prepared.records.where("owner = 'A'").count()
    scale = min(1.0, n / 50_000)
    small = max(4, round(100 * scale))
    return protocol.Schedule(small, 5, max(2 * small, round(1000 * scale)), 4, max(10, round(budget * scale)))


def settings(prepared: protocol.Prepared, budget: int = 100, err: float = 0.2, **changes) -> protocol.Settings:
    return protocol.Settings(schedule=schedule(prepared, budget), err=err, **changes)


def curve(prepared: protocol.Prepared, budget: int = 100, err: float = 0.2, labels: DataFrame | None = None, **changes) -> protocol.Outcome:
    """One scenario over eleven starts and three repetitions (or what ``changes`` says)."""
    return protocol.run_protocol(prepared, settings(prepared, budget, err, **changes), labels)


def curves(prepared: protocol.Prepared, scenarios: Mapping[str, Mapping]) -> dict[str, protocol.Outcome]:
    """Several scenarios, by name, that advance together; each is what ``curve`` takes."""
    return protocol.run_scenarios(prepared, {name: settings(prepared, **s) for name, s in scenarios.items()})


def summary(outcome: protocol.Outcome, **tags) -> DataFrame:
    """Round, micro-average F1, least, greatest and range over the runs, mean threshold and reviews."""
    micro = measures.micro_f1(outcome.metrics)
    means = outcome.metrics.groupBy("round").agg(F.round(F.avg("threshold"), 6).alias("threshold"), F.avg("reviews_attr").alias("reviews_attr"), F.avg("reviews_human").alias("reviews_human"))
    return micro.join(means, "round").select(*(F.lit(v).alias(k) for k, v in tags.items()), "round", "reviews_attr", "reviews_human", "threshold", *(F.round(c, 6).alias(c) for c in ("micro_f1", "min_f1", "max_f1", "f1_range")))


def reference_lines(prepared: protocol.Prepared) -> DataFrame:
    """F1 of the top layer and of the attribute-only baseline, each at its best threshold."""
    spark = prepared.records.sparkSession
    scored = protocol.attribute_tally(prepared.records, prepared.parameters)
    attribute = measures.best_threshold(measures.histogram(scored, digits=8, weight="n"), prepared.n_true).select(F.lit("attribute_only").alias("baseline"), "t", "f1")
    top = spark.createDataFrame([("top_only", prepared.t_best, prepared.f1_best)], "baseline string, t double, f1 double")
    return top.unionByName(attribute).select(F.lit(prepared.name).alias("data"), "baseline", F.round("t", 6).alias("t"), F.round("f1", 6).alias("f1"))


def filter_privacy(prepared: protocol.Prepared, reviewed: DataFrame, seed: int | None = None) -> DataFrame:
    """Counts, Gini and Jensen-Shannon of plain and of pair-keyed attribute filters, per attribute.

    ``reviewed`` (run_id, pair_id, left_id, right_id): of pair-keyed filters the means over the runs.  Each pair is encoded once."""
    p = prepared.parameters
    plain = durable(encode.attribute_filters(prepared.records, p))
    asked = durable(reviewed.select("run_id", "pair_id", "left_id", "right_id"))
    keyed = durable(encode.pair_keyed_filters(owner.enqueue(asked.drop("run_id").distinct(), seed=seed), prepared.records, p))
    measure = lambda filters, by: measures.unevenness(measures.bit_counts(filters, p.attribute_m, by), by).join(filters.groupBy(*by).agg(F.count(F.lit(1)).alias("encodings")), by)
    runs = measure(keyed.join(asked.select("run_id", "pair_id"), "pair_id"), ["run_id", "attr"])
    mean = runs.groupBy("attr").agg(*(F.round(F.avg(c), 9).alias(c) for c in ("encodings", "gini", "js_divergence", "js_distance")), F.count(F.lit(1)).alias("runs"))
    one = measure(plain, ["attr"]).withColumn("runs", F.lit(1).cast("long")).withColumn("encodings", F.col("encodings").cast("double"))
    return one.withColumn("kind", F.lit("plain")).unionByName(mean.withColumn("kind", F.lit("pair_keyed"))).select("kind", "attr", "runs", "encodings", "gini", "js_divergence", "js_distance")


def hardening_privacy(records: DataFrame, p: encode.Parameters) -> DataFrame:
    """Gini and Jensen-Shannon of record filters before and after folding."""
    plain = encode.record_filter(records, p)
    m = p.m
    kinds = (("plain", plain, m), ("folded", encode.xor_fold(plain, m), m // 2))
    tables = [measures.unevenness(measures.bit_counts(f.withColumn("kind", F.lit(k)), size, ["kind"]), ["kind"]) for k, f, size in kinds]
    return tables[0].unionByName(tables[1])


def plaintext_privacy(prepared: protocol.Prepared, outcome: protocol.Outcome) -> DataFrame:
    """Disclosure score and shares of attributes in the plaintext layer by selection: median, least and greatest over the runs."""
    reviewed = durable(outcome.log.where("layer = 'plain'"))
    out = None
    for mode in ("all", "unequal", "intermediate", "adaptive"):
        pairs = reviewed.select("run_id", "left_id", "right_id", F.concat_ws("|", "run_id", "pair_id").alias("pair_id"), *(f"sim_{a}" for a in ATTRIBUTES))
        given = owner.provide(owner.select_attributes(pairs, mode), prepared.records).withColumn("run_id", F.substring_index("pair_id", "|", 1))
        runs = measures.disclosure(given, prepared.records, by=["run_id"]).join(measures.attribute_share(given, by=["run_id"]), "run_id")
        stats = [f(c).alias(f"{n}_{c}") for c in ("score", *ATTRIBUTES) for n, f in (("median", F.median), ("min", F.min), ("max", F.max))]
        row = runs.agg(F.count(F.lit(1)).alias("runs"), *stats).withColumn("mode", F.lit(mode))
        out = row if out is None else out.unionByName(row)
    return out.select("mode", "runs", *(c for c in out.columns if c not in ("mode", "runs")))


ABLATIONS: dict[str, dict] = {
    "full": {},
    "no_attribute_model": {"attribute_model": "reuse_top"},
    "no_threshold_shift": {"update_top": False},
    "updates_only": {"replace_labels": False},
    "closest": {"sampler": "closest"},
    "random": {"sampler": "random"},
    "drift_0.05": {"max_drift": 0.05},
    "per_upper_batch": {"propagate": "per_upper_batch"},
    "f1_shift": {"measure": "f1"},
    "initial_labels": {"label_source": "initial"},
    "rate_0.8": {"reply_rate": 0.8},
    "rate_0.5": {"reply_rate": 0.5},
}


def ablation(prepared: protocol.Prepared, budget: int = 300, err: float = 0.2, names: Sequence[str] = tuple(ABLATIONS), pretrained: bytes | None = None, **changes) -> DataFrame:
    """First and last micro-average F1 and range for each arm; with a forest from another data set also the arm that uses it."""
    arms = {n: ABLATIONS[n] for n in names} | ({"pretrained": {"attribute_model": "pretrained", "pretrained": pretrained}} if pretrained else {})
    return ends(curves(prepared, {name: {"budget": budget, "err": err, **changes, **arm} for name, arm in arms.items()}))


def ends(arms: Mapping[str, protocol.Outcome]) -> DataFrame:
    """(arm, first_f1, first_range, last_f1, last_range, reviews_attr, reviews_human): each arm before and after its reviews."""
    out = None
    for name, outcome in arms.items():
        table = durable(summary(outcome, arm=name))
        last = table.agg(F.max("round").alias("round"))
        first = table.where("round = 0").select("arm", F.col("micro_f1").alias("first_f1"), F.col("f1_range").alias("first_range"))
        row = first.join(table.join(F.broadcast(last), "round").select("arm", F.col("micro_f1").alias("last_f1"), F.col("f1_range").alias("last_range"), "reviews_attr", "reviews_human"), "arm")  # one row each
        out = row if out is None else out.unionByName(row)
    return out


def document_records(documents: DataFrame) -> DataFrame:
    """Documents as records of two owners: parity of the source's number; attributes are opening and closing words, language, length class and longest word."""
    words = F.split(F.trim(F.regexp_replace("text", r"\s+", " ")), " ")
    number = F.coalesce(F.regexp_extract("source", r"(\d+)", 1).try_cast("int"), F.lit(0))
    n = F.size(words)
    longest = F.array_max(F.transform(words, lambda w: F.struct(F.length(w).alias("n"), w.alias("w"))))["w"]
    opening = F.array_join(F.slice(words, 1, 6), " ")
    closing = F.array_join(F.slice(words, F.greatest(n - 5, F.lit(1)), F.lit(6)), " ")
    return documents.where("text IS NOT NULL").select(
        F.concat(F.when(number % 2 == 0, "A").otherwise("B"), F.col("doc_id")).alias("rec_id"),
        F.when(number % 2 == 0, "A").otherwise("B").alias("owner"),
        F.col("doc_id").alias("entity_id"),
        text.normalise(opening).alias("OPEN"),
        text.normalise(closing).alias("CLOSE"),
        F.col("lang").alias("LANG"),
        F.floor(F.log2(F.greatest(n, F.lit(1)))).cast("string").alias("LEN"),
        text.normalise(longest).alias("TOPWORD"),
        F.md5(F.col("text").cast("binary")).alias("digest"),
    )


DOC_ATTRIBUTES = ("OPEN", "CLOSE", "LANG", "LEN", "TOPWORD")


def document_pairs(records: DataFrame) -> DataFrame:
    """Pairs of documents across owners that share opening or closing words: left_id, right_id, exact (equal texts)."""
    from linkveil.operators import block

    digest = lambda c: F.when(F.col(c).isNotNull(), F.sha2(F.concat_ws("|", F.lit(c), F.col(c)).cast("binary"), 256))
    keyed = records.withColumn("keys", F.array(digest("OPEN"), digest("CLOSE"), digest("digest")))
    found = block.candidates(keyed.where("owner = 'A'"), keyed.where("owner = 'B'"), ["digest"])
    return found.select("left_id", "right_id", (F.col("l_digest") == F.col("r_digest")).alias("exact"))


def document_linkage(documents: DataFrame, key: str, t: float = 0.7) -> DataFrame:
    """Record filters of the documents' attributes, compared and classified: left_id, right_id, exact, sim, g, p."""
    from linkveil.functions import bits

    records = document_records(documents)
    p = encode.Parameters(key, attributes=DOC_ATTRIBUTES)
    filters = encode.record_filter(records, p)
    names = [*bits.names(p.m), "ones"]
    side = lambda s, name: filters.select(F.col("rec_id").alias(name), *(F.col(w).alias(s + w) for w in names))
    pairs = document_pairs(records)
    found = compare.record_similarity(pairs.join(side("l_", "left_id"), "left_id").join(side("r_", "right_id"), "right_id"), p.m)
    return classify.threshold(found.select("left_id", "right_id", "exact", "sim"), t)


DOC_FEATURES = ("chars", "words", "symbols", "capitals", "digits", "lines")


def document_features(documents: DataFrame) -> DataFrame:
    """Simple numbers of whole texts for a forest on given labels."""
    size = F.greatest(F.length("text"), F.lit(1))
    share = lambda pattern: (F.length("text") - F.length(F.regexp_replace("text", pattern, ""))) / size
    return documents.select(
        "doc_id", F.log1p(F.length("text").cast("double")).alias("chars"), F.log1p(F.size(F.split("text", r"\s+")).cast("double")).alias("words"),
        share("[#*$%&|<>!]").alias("symbols"), share("[A-Z]").alias("capitals"), share("[0-9]").alias("digits"), share("\n").alias("lines"),
    )


def forest_on_labels(documents: DataFrame, labels: DataFrame, updates: int = 3, seed: int = 1) -> DataFrame:
    """Held-out accuracy of the evolving forest on quality labels after each update (Spark's back end): update, trees, n, accuracy."""
    rows = document_features(documents).join(labels.where("quality IS NOT NULL").select("doc_id", F.col("quality").cast("double").alias("label")), "doc_id").withColumn("weight", F.lit(1.0))
    part = F.pmod(F.xxhash64(F.lit(seed), "doc_id"), F.lit(10))
    rows = durable(rows.withColumn("part", part))
    forest, out = SparkForest(DOC_FEATURES, seed=seed), None
    test = rows.where("part >= 7")
    for i in range(updates):
        forest.update(rows.where((F.col("part") < 7) & (F.pmod("part", F.lit(updates)) <= i)))
        scored = forest.score(test).agg(F.count(F.lit(1)).alias("n"), F.avg((F.col("g").cast("double") == F.col("label")).cast("double")).alias("accuracy"))
        row = durable(scored.select(F.lit(i + 1).alias("update"), F.lit(10 * len(forest.chunks)).alias("trees"), "n", F.round("accuracy", 6).alias("accuracy")))
        out = row if out is None else out.unionByName(row)
    return out


def budget_shares(s: protocol.Schedule) -> tuple[float, float]:
    """Human share of reviews after the warm-up and at the end."""
    warm = s.small * s.n_small
    return s.budget / warm, s.budget / (warm + s.big * s.n_big)


def floor_of(pairs: int, fill: float = 0.4) -> float:
    """Gini that chance gives pair-keyed filters of so many pairs, each two filters that may be alike."""
    return measures.sampling_floor(max(1, math.ceil(1.2 * pairs)), fill)
