"""Draws that look only at the pairs which can be drawn are those of all pairs."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from linkveil.operators import encode
from linkveil.plans import protocol, workloads
from linkveil.queries import linkage

RUNS = [("x:00.0", 0.7), ("x:01.0", 0.71), ("x:01.1", 0.71), ("y:02.1", 0.74)]


@pytest.fixture(scope="module")
def many(spark):
    """60,000 pairs, of which fewer the more similar they are, and their numbers by bins."""
    sim = 0.62 + 0.25 * F.pow(F.conv(F.substring(F.md5(F.col("id").cast("string").cast("binary")), 1, 8), 16, 10).cast("double") / 2**32, F.lit(2.5))
    rows = spark.range(60_000).select(F.concat_ws("-", "id", (F.col("id") * 7).cast("string")).alias("pair_id"), F.col("id").cast("string").alias("left_id"), (F.col("id") * 7).cast("string").alias("right_id"), F.floor(sim * 2000).alias("k"), (F.col("id") % 2 == 0).alias("truth"))
    rows = rows.select("pair_id", "left_id", "right_id", (F.col("k") / 2000).alias("sim"), "truth").cache()
    return rows, np.bincount([int(round(r["sim"] / protocol.STEP, 6)) for r in rows.collect()], minlength=1002)


@pytest.mark.parametrize(("sampler", "size"), [("bucketed", 40), ("bucketed", 2000), ("random", 40), ("closest", 40), ("closest", 900)])
def test_low_lots_settle_a_draw(spark, many, sampler, size, monkeypatch):
    """Also after earlier draws, and where runs have to fall back on all their pairs."""
    rows, counts = many
    s = protocol.Settings(sampler=sampler)
    reviewed = protocol.draw_batches(rows, RUNS, None, size, s, 0).select("run_id", "pair_id").localCheckpoint()
    wanted = protocol.draw_batches(rows, RUNS, reviewed, size, s, 1)
    seen = []
    monkeypatch.setattr(protocol, "_drawn", lambda pairs, *a, f=protocol._drawn: seen.append(pairs.count()) or f(pairs, *a))
    found = protocol.draw_batches(rows, RUNS, reviewed, size, s, 1, counts, size)
    assert sorted(found.collect()) == sorted(wanted.collect()) and found.count() > 0
    if size == 40:
        assert sum(seen) < protocol._drawable(rows, RUNS, reviewed, s).count() / 2


@pytest.mark.parametrize(("sizes", "known", "size", "settled"), [({0: 5, 1: 5}, "gg", 99, True), ({0: 5, 1: 5}, ["1", "g"], 10, True), ({0: 4, 1: 9}, ["1", "g"], 9, False), ({1: 9}, ["1", "g"], 1, False), ({0: 9, 1: 3}, ["1", "g"], 12, True)])
def test_when_known_lots_are_enough(sizes, known, size, settled):
    assert protocol._enough(sizes, list(known), size) is settled


def test_the_band_grows_with_the_runs(spark, sf_dir, monkeypatch):
    """Curves are the same whether all similarities that may ever be uncertain are written at once or what the thresholds ask for."""
    data = workloads.data_set(spark, sf_dir, linkage.P)
    few = dict(offsets=(-0.05, 0.05), repetitions=1, key_seed=1)
    metrics = []
    for rows in (10**9, 0):
        monkeypatch.setattr(protocol, "BAND_ROWS", rows)
        one = replace(data, band=None)
        metrics.append(sorted(map(str, workloads.curve(one, 100, **few).metrics.collect())))
        lo, hi = one.band[:2]
        metrics.append(hi - lo)
    assert metrics[0] == metrics[2] and metrics[3] < metrics[1]


def test_a_round_reads_the_registry_once(spark, sf_dir, monkeypatch):
    data = workloads.data_set(spark, sf_dir, linkage.P)
    pairs, read = data.candidates.limit(30).localCheckpoint(), []
    monkeypatch.setattr(protocol, "durable", lambda df, f=protocol.durable: read.append(df.inputFiles()) or f(df))
    classes = encode.frequency_classes(data.records).localCheckpoint()
    assert protocol.pair_features(pairs.select("pair_id", "left_id", "right_id"), data, classes, key_seed=1).count() == 30
    assert sum(any("stored-" in x for x in files) for files in read) == 1
