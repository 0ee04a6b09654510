"""Queries that run the protocol and the workloads end to end.  SQL can't express a forest, so tests hold them against brute force and invariants."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkveil.operators import encode, forest, measures, oracle
from linkveil.plans import protocol, workloads
from linkveil.queries import linkage
from linkveil.queries import linkage_sql as S

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}
#: The seed of pair keys, so that results are the same in every run; without one keys are random.
SEEDED = dict(key_seed=1)
_prepared: dict = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def twin_sql(sql: str):
    """The query's DuckDB SQL."""

    def register(f):
        ORACLE_SQL[f.__name__] = sql
        return f

    return register


_N_TRUE = "(SELECT count(*) FROM registry a JOIN registry b USING (entity_id) WHERE a.owner = 'A' AND b.owner = 'B')"
_HISTOGRAM = "hist AS (SELECT floor(round(sim / 0.001, 6))::INT AS bin, count(*) AS n, count(*) FILTER (WHERE truth) AS n_true FROM cand GROUP BY 1)"
#: Of runs that no owner answers: the counts at each start, in every round.
_STARTS_ONLY = f"""
grid AS (SELECT k, coalesce(sum(n_true), 0)::BIGINT AS tp, coalesce(sum(n - n_true), 0)::BIGINT AS fp FROM range(0, 1002) g(k) LEFT JOIN hist ON bin >= k GROUP BY k),
best AS (SELECT round(k * 0.001::DOUBLE, 9) AS t FROM grid ORDER BY round(2.0::DOUBLE * tp / greatest(tp + fp + {_N_TRUE}, 1), 9) DESC, k LIMIT 1),
run AS (SELECT printf('%02d.%d', i, r) AS run_id, round(t + round(-0.05::DOUBLE + 0.01::DOUBLE * i, 2), 9) AS threshold FROM best, range(0, 11) o(i), range(0, 3) p(r))
SELECT run_id, round::INT AS round, 0::BIGINT AS reviews_attr, 0::BIGINT AS reviews_human, tp, fp, {_N_TRUE} - tp AS fn,
  round(2.0::DOUBLE * tp / greatest(tp + fp + {_N_TRUE}, 1), 9) AS f1, threshold, 0::INT AS trees, 0::INT AS updates
FROM run JOIN grid ON k = round(threshold / 0.001)::INT, range(0, 10) q(round)"""


def _state(spark, sf_dir) -> tuple:
    return (spark.sparkContext.applicationId, linkage.file_state(spark, sf_dir))


def prepared(spark, sf_dir, variant="E1M", hardening=None) -> protocol.Prepared:
    key = (*_state(spark, sf_dir), variant, hardening)
    if key not in _prepared:
        _prepared[key] = protocol.prepare(linkage.registry(spark, sf_dir, variant), linkage.P, variant + ("-XOR" if hardening else ""), hardening)
    return _prepared[key]


def _curves(spark, sf_dir, specs, variant="E1M", hardening=None) -> list[protocol.Outcome]:
    """An outcome for each of ``specs``; those that no query has asked for yet run together, and all are kept for the session."""
    specs = [dict(budget=300, err=0.2) | SEEDED | s for s in specs]
    keys = [(*_state(spark, sf_dir), variant, hardening, tuple(sorted(s.items()))) for s in specs]
    missing = {f"s{i}": (k, s) for i, (k, s) in enumerate(zip(keys, specs, strict=True)) if k not in _prepared}
    if missing:
        found = workloads.curves(prepared(spark, sf_dir, variant, hardening), {name: s for name, (_, s) in missing.items()})
        _prepared.update({k: found[name] for name, (k, _) in missing.items()})
    return [_prepared[k] for k in keys]


def _curve(spark, sf_dir, variant="E1M", hardening=None, **spec) -> protocol.Outcome:
    return _curves(spark, sf_dir, [spec], variant, hardening)[0]


def _summaries(spark, sf_dir, specs, variant="E1M", hardening=None):
    found = _curves(spark, sf_dir, specs, variant, hardening)
    name = variant + ("-XOR" if hardening else "")
    return [workloads.summary(o, data=name, budget=s.get("budget", 300), err=s.get("err", 0.2)) for o, s in zip(found, specs, strict=True)]


BUDGETS = [dict(budget=b) for b in (100, 200, 300)]


@query
def protocol_e1m(spark, sf_dir):
    """All eleven starts with three repetitions, budget 300, error 0.2: a row a round."""
    return _summaries(spark, sf_dir, [{}])[0]


@query
def curve_e1m_errors(spark, sf_dir):
    """Budget 100 with error rates 0, 0.1 and 0.2."""
    return _union(_summaries(spark, sf_dir, [dict(budget=100, err=e) for e in (0.0, 0.1, 0.2)]))


@query
def curve_e1m_budget(spark, sf_dir):
    """Error rate 0.2 with budgets 100, 200 and 300."""
    return _union(_summaries(spark, sf_dir, BUDGETS))


@query
def curve_overlaps(spark, sf_dir):
    """Error rate 0.2 with budgets 100, 200 and 300."""
    return _union(t for v in ("E1S", "E1L") for t in _summaries(spark, sf_dir, BUDGETS, v))


@query
def curve_disparity(spark, sf_dir):
    """Error rate 0.2 with budgets 100, 200 and 300."""
    return _union(t for v in ("E2S", "E2M") for t in _summaries(spark, sf_dir, BUDGETS, v))


@query
def curve_hardened(spark, sf_dir):
    return _union(t for v in ("E1S", "E1M", "E1L") for t in _summaries(spark, sf_dir, [{}], v, "xor"))


def _union(tables):
    out = None
    for t in tables:
        out = t if out is None else out.unionByName(t)
    return out


@query
def reference_lines(spark, sf_dir):
    return _union(workloads.reference_lines(prepared(spark, sf_dir, v)) for v in ("E1S", "E1M", "E1L", "E2S", "E2M"))


@query
@twin_sql(S.with_(*S.TO_PAIRS, _HISTOGRAM) + ", " + _STARTS_ONLY.strip())
def protocol_no_reply(spark, sf_dir):
    """No owner answers: every run stays at its start, as in linkage without review."""
    return _curve(spark, sf_dir, reply_rate=0.0).metrics.withColumn("f1", F.round("f1", 9))


@query
def protocol_reuse_top(spark, sf_dir):
    """Without an attribute model: its layer repeats the top model's labels."""
    return workloads.summary(_curve(spark, sf_dir, attribute_model="reuse_top"), data="E1M", arm="reuse_top")


def _pretrained(spark, sf_dir) -> bytes:
    """A forest from E1S's uncertain pairs."""
    key = (*_state(spark, sf_dir), "forest")
    if key not in _prepared:
        _prepared[key] = protocol.pretrain(prepared(spark, sf_dir, "E1S"), 200, **SEEDED)
    return _prepared[key]


@query
def protocol_minhash(spark, sf_dir):
    """Another perturbation in the attribute layer: MinHash signatures under the pair's key."""
    return workloads.summary(_curve(spark, sf_dir, encoder="minhash"), data="E1M", arm="minhash")


@query
def protocol_given_labels(spark, sf_dir):
    """A human who isn't simulated: labels come from a table; here that of the truth, for two of three pairs."""
    data = prepared(spark, sf_dir)
    labels = data.candidates.where(F.pmod(F.crc32(F.col("pair_id").cast("binary")), F.lit(3)) > 0).select("pair_id", F.col("truth").alias("g"))
    return workloads.summary(workloads.curve(data, 300, labels=labels, human="table", **SEEDED), data="E1M", arm="given_labels")


@query
def protocol_ask_more(spark, sf_dir):
    """Owners answer for four of five records; batches are raised so that as many pairs come back."""
    few, more = _curves(spark, sf_dir, [dict(reply_rate=0.8), dict(reply_rate=0.8, ask_more=True)])
    return _union(workloads.summary(o, data="E1M", arm=n) for n, o in (("as_scheduled", few), ("ask_more", more)))


@query
def protocol_two_layer(spark, sf_dir):
    """Without plaintext: a forest trained on another data set labels, one loop only."""
    forest = _pretrained(spark, sf_dir)
    return workloads.summary(_curve(spark, sf_dir, layers=("top", "attr"), attribute_model="pretrained", pretrained=forest), data="E1M", arm="two_layer")


@query
def protocol_log(spark, sf_dir):
    """Reviewed pairs of all runs with their labels."""
    return _curve(spark, sf_dir).log


@query
def correction_rate(spark, sf_dir):
    return measures.correction_rate(_curve(spark, sf_dir).log.withColumnRenamed("drawn", "round"))


@query
def oracle_error(spark, sf_dir):
    return measures.oracle_error(_curve(spark, sf_dir).log)


@query
def rounds_to_baseline(spark, sf_dir):
    """Round and human reviews at which each run reaches the top layer's best F1."""
    data = prepared(spark, sf_dir)
    return measures.rounds_to(_curve(spark, sf_dir).metrics, data.f1_best)


@query
def baseline_gap(spark, sf_dir):
    """Final micro-average F1 beside the lines of E1M."""
    table = workloads.summary(_curve(spark, sf_dir))
    last = table.orderBy(F.desc("round")).limit(1).select(F.lit("protocol").alias("name"), F.col("micro_f1").alias("f1"))
    return measures.gap(last, workloads.reference_lines(prepared(spark, sf_dir)).select("baseline", "f1"))


@query
def forest_predictions(spark, sf_dir):
    """The forest of the first batch's pairs with human labels, on the pairs themselves: g and p."""
    rows = _forest_rows(spark, sf_dir)
    grown = forest.EvolvingForest(seed=1)
    for _ in range(3):
        grown = grown.update(forest.matrix(rows), rows["label"].to_numpy(float), np.ones(len(rows)))
    g, p = grown.classify(forest.matrix(rows))
    return spark.createDataFrame([(i, bool(a), float(b)) for i, a, b in zip(rows["pair_id"], g, np.round(p, 9), strict=True)], "pair_id string, g boolean, p double")


@query
@twin_sql("SELECT 'forest' AS run_id, i::INT AS round, least(10 * i, 100)::BIGINT AS trees, (greatest(10 * i - 100, 0))::BIGINT AS oldest, (10 * i - 1)::BIGINT AS newest FROM range(1, 13) r(i)")
def forest_fifo(spark, sf_dir):
    """Living trees after each of twelve updates: ten more each time, a hundred at most, the oldest go."""
    rows, grown, living = _forest_rows(spark, sf_dir), forest.EvolvingForest(seed=1), []
    for i in range(1, 13):
        grown = grown.update(forest.matrix(rows), rows["label"].to_numpy(float), np.ones(len(rows)))
        living += [("forest", i, int(s)) for s in grown.sequence]
    return measures.forest_state(spark.createDataFrame(living, "run_id string, round int, seq long"))


def _forest_rows(spark, sf_dir):
    """Features and labels of the first batch, a hundred rows."""
    classes = encode.frequency_classes(linkage.registry(spark, sf_dir))
    drawn = linkage.drawn(spark, sf_dir)
    frequent = protocol.frequency_features(drawn.select("pair_id", "left_id", "right_id"), classes, linkage.registry(spark, sf_dir))
    return linkage.pair_sims(spark, sf_dir).join(frequent, "pair_id").withColumn("label", oracle.human(F.col("truth"), 0.2)).toPandas().sort_values("pair_id")


@query
def human_share(spark, sf_dir):
    return measures.human_share(_curve(spark, sf_dir).metrics).select("run_id", "round", "reviews_attr", "reviews_human", "human_share")


@query
def filter_privacy(spark, sf_dir):
    """Plain and pair-keyed filters of the reviewed pairs, means over the runs."""
    return workloads.filter_privacy(prepared(spark, sf_dir), _curve(spark, sf_dir).log, seed=1)


@query
@twin_sql(
    "SELECT * FROM (" + S.with_(*S.TO_RECORD, "named AS (SELECT 'plain' AS kind, pos FROM record_filter)", S.bit_counts("named", "kind", 1024)) + S.unevenness("kind") + ") UNION ALL SELECT * FROM ("
    + S.with_(*S.TO_RECORD, S.folded(), "named AS (SELECT 'folded' AS kind, pos FROM folded)", S.bit_counts("named", "kind", 512)) + S.unevenness("kind") + ")"
)
def hardening_privacy(spark, sf_dir):
    return workloads.hardening_privacy(linkage.registry(spark, sf_dir), linkage.P)


@query
def plaintext_privacy(spark, sf_dir):
    """Disclosure by selection for E1M and E2M, budget 200."""
    return _union(workloads.plaintext_privacy(prepared(spark, sf_dir, v), _curve(spark, sf_dir, v, budget=200)).withColumn("data", F.lit(v)) for v in ("E1M", "E2M"))


def _ablation(spark, sf_dir, names, **arms):
    arms = {n: workloads.ABLATIONS[n] for n in names} | arms
    return workloads.ends(dict(zip(arms, _curves(spark, sf_dir, list(arms.values())), strict=True)))


@query
def ablation_models(spark, sf_dir):
    """Arms without parts of the models, and with a forest from another data set."""
    arms = ("full", "no_attribute_model", "no_threshold_shift", "updates_only")
    return _ablation(spark, sf_dir, arms, pretrained=dict(attribute_model="pretrained", pretrained=_pretrained(spark, sf_dir)))


@query
def ablation_sampling(spark, sf_dir):
    """Other samplers and response rates."""
    return _ablation(spark, sf_dir, ("closest", "random", "rate_0.8", "rate_0.5"))


@query
def ablation_updates(spark, sf_dir):
    """Other limits, measures, and granularities of the update."""
    return _ablation(spark, sf_dir, ("drift_0.05", "per_upper_batch", "f1_shift", "initial_labels"))


@query
def forest_on_labels(spark, sf_dir):
    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    return workloads.forest_on_labels(read("documents"), read("labels"))


@query
@twin_sql(S.with_(*S.TO_PAIRS, _HISTOGRAM) + "SELECT bin, n, n_true::BIGINT AS n_true FROM hist")
def bench_block_compare(spark, sf_dir):
    """Encode, block and compare all records; the similarity histogram."""
    data = workloads.data_set(spark, sf_dir, linkage.P)
    return measures.histogram(data.layer.tally(), weight="n")
