"""Attribute scores, pairs of one difference and sampled filters made inside tasks are those of the column expressions."""

import pytest
from pyspark.sql import functions as F

from linkveil.functions import bits
from linkveil.operators import attacks, baselines, block, encode, pairwise
from linkveil.plans import protocol
from linkveil.queries import linkage

P = linkage.P


@pytest.fixture(scope="module")
def records(spark, sf_dir):
    odd = [("", None, None, "", None, None, None), ("x", None, "y", "1950", None, None, ""), ("x", "m", "y", "1950", "c", "1", "AB"), ("x", "m", "z", "1950", "c", "1", "AB"), ("x", "m", "y", "1950", "c", "2", "AC")]
    rows = [(f"{o}-90{i}", o, "base", -900 - i, *v) for i, v in enumerate(odd) for o in "AB"]
    return linkage.registry(spark, sf_dir).where("entity_id % 3 < 2").unionByName(spark.createDataFrame(rows, linkage.R.SCHEMA)).localCheckpoint()


@pytest.fixture(scope="module")
def scored(spark, records):
    """By joins of pairs and filters."""
    keyed = block.keys(records, P.key)
    pairs = block.candidates(keyed.where("owner = 'A'"), keyed.where("owner = 'B'"), ["entity_id"])
    pairs = pairs.select("left_id", "right_id", (F.col("l_entity_id") == F.col("r_entity_id")).alias("truth"))
    return baselines.attribute_only(pairs, records, P).localCheckpoint()


@pytest.mark.parametrize("at_once", [7, pairwise.PAIRS_AT_ONCE])
def test_blocked_scores_equal_those_of_joins(records, scored, at_once, monkeypatch):
    """with missing values, in chunks of any size."""
    monkeypatch.setattr(pairwise, "PAIRS_AT_ONCE", at_once)
    found = baselines.blocked_scores(records, P)
    assert sorted(map(str, found.where("sim IS NOT NULL").collect())) == sorted(map(str, scored.select(found.columns).collect())) and scored.where("sim_MN IS NULL").count() > 0
    short = baselines.blocked_scores(records, P, sims=False)
    assert sorted(map(str, short.collect())) == sorted(map(str, found.select("left_id", "right_id", "truth", "sim").collect()))
    assert [r["left_id"] for r in short.where("sim IS NULL").collect()] == ["A-900"]  # the one pair without any value


def test_scores_are_shuffled_once(records):
    """one shuffle of the records' filters, no join."""
    plan = baselines.blocked_scores(records, P)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange ") == 1 and "Join" not in plan


@pytest.mark.parametrize("many", [1, pairwise.MANY])
def test_pairs_of_one_difference_of_passes(records, scored, many, monkeypatch):
    """tasks hand on what tells anything, pass by pass."""
    monkeypatch.setattr(pairwise, "MANY", many)
    monkeypatch.setattr(pairwise, "BYTES_A_PASS", 200_000)
    monkeypatch.setattr(protocol.Layer, "many", many)
    layer = protocol.attribute_layer(records, P)
    found = layer.gathered(lambda one: baselines.blocked_scores(records, P, rows=layer.dealt(*one), single=True))
    wanted = attacks.one_difference(scored).select(found.columns)
    assert sorted(map(str, found.collect())) == sorted(map(str, wanted.collect())) and wanted.count() > 5


def test_sampled_filters_have_the_planned_bits(records):
    """bit by bit from the attributes' filters."""
    plan, whole = encode.bit_plan(encode.WEIGHTS, 1024, P.attribute_m, P.key), {}
    for r in encode.attribute_filters(records, P).collect():
        whole.setdefault(r["rec_id"], {})[r["attr"]] = sum((r[w] % 2**64) << 64 * i for i, w in enumerate(bits.names(P.attribute_m)))
    found = encode.sampled_filter(records, P).collect()
    for r in found:
        mine = whole.get(r["rec_id"], {})
        wanted = sum(1 << place for place, a, bit in plan if mine.get(a, 0) >> bit & 1)
        assert sum((r[w] % 2**64) << 64 * i for i, w in enumerate(bits.names(1024))) == wanted and r["ones"] == wanted.bit_count()
    assert len(found) == records.count()


def test_alignment_beside_the_values_needs_no_join(spark, records):
    """the same table as with a join by record and attribute."""
    found = spark.createDataFrame([("FN", [*range(0, 400)]), ("POB", [*range(300, 1024)])], "attr string, bits array<int>")
    tables = [attacks.aligned_after_attribution(found, f, records) for f in (encode.sampled_filter(records, P), encode.sampled_values(records, P))]
    assert sorted(tables[0].collect()) == sorted(tables[1].collect()) and tables[0].count() == 2
    plans = [t._jdf.queryExecution().optimizedPlan().toString().count("Join ") for t in tables]
    assert plans[1] < plans[0]
