"""Encoding and comparison inside tasks give what the column expressions give, and records are shuffled once."""

import pytest
from pyspark.sql import functions as F

from linkveil.functions import bits
from linkveil.operators import attacks, baselines, block, classify, compare, encode, measures, pairwise, sampling
from linkveil.plans import protocol
from linkveil.queries import linkage


def people(spark, sf_dir):
    return linkage.registry(spark, sf_dir).where("entity_id % 3 < 2")


@pytest.mark.parametrize(("family", "fold"), [("random", False), ("double", False), ("random", True)])
def test_filters_equal_the_column_expressions(spark, sf_dir, family, fold):
    p = encode.Parameters("k" * 70, family=family)
    odd = [("A-900", "A", "base", -900, "é", None, "", None, None, None, None), ("B-901", "B", "base", -901, None, None, "", None, None, None, None)]
    records = people(spark, sf_dir).where("entity_id % 2 = 0").unionByName(spark.createDataFrame(odd, linkage.R.SCHEMA))
    wanted = encode.record_filter(records, p)
    wanted = encode.xor_fold(wanted, p.m) if fold else wanted
    names = ["rec_id", *bits.names(p.m // 2 if fold else p.m), "ones"]
    found = pairwise.filters(records, p, fold).select(*names).collect()
    assert sorted(found) == sorted(wanted.select(*names).collect())
    assert len(found) > 100 and "B-901" not in {r["rec_id"] for r in found}


@pytest.mark.parametrize("per_task", [block.PAIRS_A_TASK, 5])
def test_pairs_equal_those_of_the_join(spark, sf_dir, per_task):
    records, p = people(spark, sf_dir), linkage.P
    keyed = block.keys(pairwise.filters(records, p), p.key)
    joined = block.candidates(keyed.where("owner = 'A'"), keyed.where("owner = 'B'"), ["entity_id", *bits.names(p.m), "ones"])
    wanted = compare.record_similarity(joined, p.m).select("left_id", "right_id", "common", (F.col("l_entity_id") == F.col("r_entity_id")).alias("truth"))
    rows = pairwise.dealt(keyed, pairwise.large_blocks(keyed.select("owner", "keys"), per_task), p.m, records.count())
    found = pairwise.pairs(rows, p.m)
    assert sorted(found.select(*wanted.columns).collect()) == sorted(wanted.collect()) and found.count() > 0
    whole = found.groupBy("common", (F.col("l_ones") + F.col("r_ones")).alias("ones"), "truth").agg(F.count(F.lit(1)).alias("n"))
    counted = pairwise.tally(rows, p.m).groupBy("common", "ones", "truth").agg(F.sum("n").alias("n"))
    assert sorted(counted.collect()) == sorted(whole.collect())


def test_records_are_shuffled_once(spark, sf_dir):
    """A pass shuffles the records once, not each side and before that for the filters and the digests."""
    candidates = protocol.top_layer(people(spark, sf_dir), linkage.P)[1]
    assert candidates._jdf.queryExecution().executedPlan().toString().count("Exchange ") == 1


@pytest.mark.parametrize("many", [1, pairwise.MANY])
def test_histogram_of_the_tally_is_that_of_the_pairs(spark, sf_dir, many, monkeypatch):
    """Also where keys are counted one after the other, with each key's rows only in a shuffle."""
    monkeypatch.setattr(pairwise, "MANY", many)
    layer = protocol.layer(people(spark, sf_dir), linkage.P)
    layer.many = many
    assert sorted(measures.histogram(layer.tally(), weight="n").collect()) == sorted(measures.histogram(layer.pairs()).collect())
    assert layer.dealt(1).select("key_no").distinct().collect() == [(1,)]


@pytest.fixture
def cut(spark, sf_dir, monkeypatch):
    """A layer that takes several passes for each key, and what is written."""
    monkeypatch.setattr(pairwise, "MANY", 1)
    monkeypatch.setattr(pairwise, "BYTES_A_PASS", 20_000)
    layer = protocol.layer(people(spark, sf_dir), linkage.P)
    layer.many = 1
    return layer


def test_passes_give_each_pair_once(spark, cut):
    """A pass shuffles a part of one key's rows; together they are all pairs."""
    passes = cut.passes()
    assert len(passes) > len(block.KEYS) and {k for k, *_ in passes} == set(range(len(block.KEYS)))
    whole = sorted(r["pair_id"] for r in cut.pairs().select("pair_id").collect())
    assert whole and sorted(r["pair_id"] for one in passes for r in cut.pairs(one=one).select("pair_id").collect()) == whole
    assert max(cut.dealt(*one).count() for one in passes) < cut.dealt().count() / len(block.KEYS)


def test_draws_decoys_and_graph_of_passes_are_those_of_all_pairs(spark, sf_dir, cut):
    """None of them has all keys' rows in one shuffle (F8, F10, F11)."""
    every = classify.threshold(cut.pairs(), linkage.T)
    wanted, found = sampling.bucketed(every, 20), linkage._drawn(cut, 20)
    assert found.columns == wanted.columns and sorted(found.collect()) == sorted(wanted.collect())
    certain = lambda one=(): classify.threshold(cut.pairs(one=one), linkage.T).where("p >= 0.8").select("pair_id")
    assert sorted(sampling.random_sample(cut.gathered(lambda one: sampling.random_sample(certain(one), 7)), 7).collect()) == sorted(sampling.random_sample(certain(), 7).collect())
    nodes = cut.gathered(lambda one: pairwise.nodes(cut.dealt(*one), cut.m, 0.5))
    assert attacks.node_exposure(nodes, found).collect() == attacks.graph_exposure(cut.pairs(), found).collect()


def test_band_is_written_pass_by_pass(spark, sf_dir, cut, monkeypatch):
    """the band's shuffle holds a part of one key's rows at a time."""
    written = []
    monkeypatch.setattr(protocol, "stored", lambda df, f=protocol.stored: written.append(df) or f(df))
    data = protocol.Prepared("", people(spark, sf_dir), cut, None, 0, 0.0, 0.0, linkage.P)
    wanted = cut.pairs(0.6, 0.9).select("pair_id", "left_id", "right_id", "sim", "truth")
    assert sorted(data.within(0.6, 0.9).collect()) == sorted(wanted.collect()) and len(written) == len(cut.passes())


@pytest.mark.parametrize("many", [1, pairwise.MANY])
def test_attribute_tally_is_that_of_the_scores(spark, sf_dir, many, monkeypatch):
    """attribute scores are counted in the tasks; one filter a record and key of a pass is shuffled, no gram and no score."""
    monkeypatch.setattr(pairwise, "MANY", many)
    monkeypatch.setattr(pairwise, "BYTES_A_PASS", 200_000)
    monkeypatch.setattr(protocol.Layer, "many", many)
    odd = [(f"{o}-90{i}", o, "base", -900 - i, *v) for i, v in enumerate([("", None, None, "", None, None, None), ("x", None, "y", "1950", None, None, "")]) for o in "AB"]
    records = people(spark, sf_dir).unionByName(spark.createDataFrame(odd, linkage.R.SCHEMA))
    tally = protocol.attribute_tally(records, linkage.P)
    wanted = measures.histogram(baselines.blocked_scores(records, linkage.P), digits=8)
    assert sorted(measures.histogram(tally, digits=8, weight="n").collect(), key=str) == sorted(wanted.collect(), key=str)
    assert None in {r["bin"] for r in wanted.collect()}
