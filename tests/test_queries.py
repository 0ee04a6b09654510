"""Every query of the catalogue with a DuckDB twin gives the same rows."""

from types import SimpleNamespace
from unittest.mock import MagicMock

import pytest

import __spark_entry__ as contract
from conftest import rows_of
from linkveil.operators import sampling
from linkveil.plans import protocol, workloads
from linkveil.queries import experiments, linkage, streams, surrounding

#: Three runs instead of 33; registered queries run all.
FEW = dict(offsets=(-0.05, 0.0, 0.05), repetitions=1)
MODULES = (linkage, surrounding, streams, experiments)
TWINS = sorted(k for m in MODULES for k in m.ORACLE_SQL if k != "protocol_no_reply")  # which has a test of its own


@pytest.mark.parametrize("name", TWINS)
def test_twin(name, spark, sf_dir, duck):
    found = contract.queries()[name](spark, sf_dir).toPandas()
    wanted = duck.execute(contract.oracle_sql()[name]).df()
    assert sorted(found.columns) == sorted(wanted.columns)
    assert rows_of(found) == rows_of(wanted)


def test_entry(spark):
    assert contract.entry(spark).limit(1).count() == 1


def test_every_twin_has_a_query():
    assert set(contract.oracle_sql()) <= set(contract.queries())


def test_protocol_without_replies_stays_at_its_start(spark, sf_dir):
    rows = workloads.curve(experiments.prepared(spark, sf_dir), 300, reply_rate=0.0, **FEW).metrics.toPandas()
    assert rows.groupby("run_id").f1.nunique().eq(1).all() and (rows.reviews_attr == 0).all()


def test_queries_run_all_starts_and_budgets(spark, sf_dir, monkeypatch):
    """No registered query has fewer starts or repetitions than a scenario, and the curves have all budgets."""
    asked = []
    for name in ("workloads", "measures", "protocol"):
        monkeypatch.setattr(experiments, name, MagicMock())
    monkeypatch.setattr(experiments, "_prepared", {})
    monkeypatch.setattr(experiments, "prepared", lambda spark, sf_dir, variant="E1M", hardening=None: SimpleNamespace(name=variant, f1_best=0.0, candidates=MagicMock()))
    experiments.workloads.ABLATIONS = workloads.ABLATIONS

    def curves(data, scenarios):
        asked.extend((data.name, s) for s in scenarios.values())
        return {name: MagicMock() for name in scenarios}

    experiments.workloads.curves.side_effect = curves
    experiments.workloads.curve.side_effect = lambda data, budget=300, **s: asked.append((data.name, s | {"budget": budget})) or MagicMock()
    ran = {}
    for name in (k for k in experiments.QUERIES if k.startswith(("curve_", "protocol_", "ablation_")) or k in ("correction_rate", "oracle_error", "rounds_to_baseline", "human_share", "filter_privacy", "plaintext_privacy")):
        experiments._prepared.clear()
        experiments._prepared[(*experiments._state(spark, sf_dir), "forest")] = b""
        asked.clear()
        experiments.QUERIES[name](spark, sf_dir)
        assert asked and not any({"offsets", "repetitions"} & set(s) for _, s in asked), name
        ran[name] = {(data, s["budget"]) for data, s in asked}
    assert ran["curve_overlaps"] == {(v, b) for v in ("E1S", "E1L") for b in (100, 200, 300)}
    assert ran["curve_disparity"] == {(v, b) for v in ("E2S", "E2M") for b in (100, 200, 300)}


def test_protocol_keeps_its_limits(spark, sf_dir):
    data = experiments.prepared(spark, sf_dir)
    out = workloads.curve(data, 300, **FEW, **experiments.SEEDED)
    rows = out.metrics.toPandas().sort_values(["run_id", "round"])
    start = rows.groupby("run_id").threshold.first()
    for run, part in rows.groupby("run_id"):
        assert (part.threshold - start[run]).abs().max() <= 0.1 + 1e-9
        assert part.trees.max() <= 100
        assert part.reviews_attr.is_monotonic_increasing and part.reviews_human.is_monotonic_increasing
    log = out.log.toPandas()
    assert not log.duplicated(["run_id", "pair_id"]).any()
    assert ((log.weight == 2.0) == (log.layer == "plain")).all()
    assert data.f1_best >= rows[rows["round"] == 0].f1.max() - 1e-9


def test_pairs_of_the_blocking_are_not_written(spark, sf_dir, monkeypatch):
    """They grow with the square of the records: what is written or kept for other queries is records, draws and the uncertain band."""
    written = []
    for module in (linkage, protocol):
        for name in ("durable", "stored"):
            if hasattr(module, name):
                monkeypatch.setattr(module, name, lambda df, f=getattr(module, name): written.append(df := f(df)) or df)
    monkeypatch.setattr(linkage, "_kept", {})
    n = linkage.pairs(spark, sf_dir).count()
    data = workloads.data_set(spark, sf_dir, linkage.P)
    assert data.candidates.count() == n and contract.queries()["final_result"](spark, sf_dir).count() == n
    assert contract.queries()["quality_by_threshold"](spark, sf_dir).count() > 0
    assert not [df for df in written if {"left_id", "right_id"} <= set(df.columns) and df.count() > n / 2]


def test_band_holds_what_a_range_asks_for(spark, sf_dir):
    data = workloads.data_set(spark, sf_dir, linkage.P)
    for lo, hi in ((0.6, 0.8), (0.65, 0.7), (0.5, 0.7)):
        wanted = data.candidates.where(f"sim > {lo} AND sim < {hi}").select("pair_id", "left_id", "right_id", "sim", "truth")
        found = data.within(lo, hi)
        assert sorted(found.collect()) == sorted(wanted.collect()) and found.count() > 0


def test_registry_draws_once_an_entity(spark, sf_dir):
    """No filter or join condition draws anew, but for the source's split."""
    plan = linkage.R.registry(spark, sf_dir)._jdf.queryExecution().optimizedPlan().toString()
    assert not [line for line in plan.splitlines() if ("Join" in line or "Filter" in line) and "md5" in line.replace("|split", "") and "|split" not in line]


def test_batch_sizes_read_the_events(spark, sf_dir):
    rows = contract.queries()["batch_sizes"](spark, sf_dir).collect()
    assert len(rows) == spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id").distinct().count()
    assert all(r["pairs"] == sampling.batch_for(100, r["replies"] / r["requests"]) for r in rows) and any(r["replies"] for r in rows)
