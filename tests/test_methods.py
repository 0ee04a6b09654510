"""Worked examples and invariants of the record-linkage methods."""

import hashlib
import hmac
import itertools

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from linkveil import cart
from linkveil.functions import bits, crypto, sqlfuncs, text
from linkveil.operators import baselines, block, classify, compare, encode, forest, measures, oracle, owner, sampling
from linkveil.plans import protocol, workloads
from linkveil.sources.registry import ATTRIBUTES, SCHEMA

P = encode.Parameters("ownersecret")


def one(spark, *columns):
    return spark.range(1).select(*columns).first()


def people(spark, rows):
    return spark.createDataFrame([(f"{o}{i}", o, "s", i, *values) for o, i, *values in rows], SCHEMA)


@pytest.mark.parametrize(("sim", "p"), [(0.70, 0.5), (0.67, 0.8), (0.76, 0.8), (0.65, 1.0), (0.6, 1.0), (0.80, 1.0), (0.9, 1.0)])
def test_ramp(spark, sim, p):
    assert one(spark, classify.ramp(F.lit(sim), 0.7))[0] == p


def test_uncertain_interval_is_where_p_is_low():
    assert classify.uncertain_interval(0.7) == pytest.approx((0.67, 0.76))


def test_hmac_and_positions(spark):
    row = one(spark, crypto.hmac_sha256(F.lit("_é"), "key"), crypto.positions(crypto.hmac_sha256(F.lit("_é"), "key"), 20, 256))
    seed = hmac.new(b"key", "_é".encode(), hashlib.sha256).hexdigest()
    stream = "".join(hashlib.sha256(f"{seed}|{k}".encode()).hexdigest() for k in range(2))
    assert row[0] == seed
    assert row[1] == [int(stream[4 * i : 4 * i + 4], 16) % 256 for i in range(20)]


def test_an_empty_key_is_refused():
    with pytest.raises(ValueError):
        crypto.check_key("")


@pytest.mark.parametrize("key", ["k", "ownersecret", "six6 and back\\slash é", "x" * 40, "x" * 64, "y" * 65, "z" * 100])
def test_hmac_with_any_key(spark, key):
    """Literal keys, key columns and the SQL function agree with the standard library, also when parts make a key longer than a block."""
    sqlfuncs.register(spark)
    parts = "|".join([key, "ghijklmnopqrstuvghijklmn", "FN"])
    df = spark.createDataFrame([("_é", key, "ghijklmnopqrstuvghijklmn", "FN")], "m string, k string, p string, a string")
    row = df.select(crypto.hmac_sha256(F.col("m"), key), crypto.hmac_sha256(F.col("m"), F.col("k")), crypto.hmac_sha256(F.col("m"), crypto.composed(key, F.col("p"), F.col("a"))), F.expr("lv_hmac(m, k)")).first()
    want = hmac.new(key.encode(), "_é".encode(), hashlib.sha256).hexdigest()
    assert row[0] == row[1] == row[3] == want
    assert row[2] == hmac.new(parts.encode(), "_é".encode(), hashlib.sha256).hexdigest()


@pytest.mark.parametrize("length", [11, 40, 64, 100])
def test_long_keys_keep_pairs_and_attributes_apart(spark, length):
    df = people(spark, [("A", 1, "anna", None, "anna", "1970", "x", "27001", "NA"), ("B", 1, "anna", None, "anna", "1970", "y", "27001", None)])
    pairs = spark.createDataFrame([("p", "A1", "B1"), ("q", "A1", "B1")], "pair_id string, left_id string, right_id string")
    found = encode.pair_keyed_filters(owner.enqueue(pairs, seed=0), df, encode.Parameters("x" * length, hashes={a: 18 for a in ATTRIBUTES}))
    rows = {(r["pair_id"], r["rec_id"], r["attr"]): tuple(r[w] for w in bits.names(256)) for r in found.collect()}
    assert rows["p", "A1", "FN"] == rows["p", "B1", "FN"] != rows["q", "A1", "FN"]
    assert rows["p", "A1", "FN"] != rows["p", "A1", "LN"]


def test_pair_keys_are_random_without_a_seed(spark):
    pairs = spark.createDataFrame([("p", "A1", "B1")], "pair_id string, left_id string, right_id string")
    keys = {owner.enqueue(pairs).first()["pair_key"] for _ in range(3)}
    assert len(keys) == 3 and owner.enqueue(pairs, seed=1).first()["pair_key"] == owner.enqueue(pairs, seed=1).first()["pair_key"]
    assert owner.enqueue(pairs, 1, seed=1).first()["pair_key"] != owner.enqueue(pairs, seed=1).first()["pair_key"]


def test_a_large_block_is_dealt_out(spark):
    """A third of all records in one block: the same pairs from many tasks."""
    rows = [("A" if i % 2 else "B", i, "anna" if i < 300 else f"name{i % 40}", None, f"l{i % 7}", "1970" if i < 300 else str(1900 + i % 50), "x", "1", None) for i in range(900)]
    k = block.keys(people(spark, rows), "k")
    a, b = k.where("owner = 'A'"), k.where("owner = 'B'")
    whole, dealt = block.candidates(a, b, per_task=None), block.candidates(a, b, per_task=1000)
    assert whole.count() == dealt.count() > 22_000 and whole.exceptAll(dealt).isEmpty()
    assert "part" in dealt._jdf.queryExecution().toString() and block.block_sizes(a, b).agg(F.max("pairs")).first()[0] > 20_000


def test_frequency_classes_with_ties_at_the_borders(spark):
    rows = [("A", i, v, None, None, None, None, None, None) for i, v in enumerate([f"n{k:04d}" for k in range(700)] * 1 + [f"n{k:04d}" for k in range(0, 700, 3)] + ["n0001"] * 5)]
    found = {r["value"]: r["freq_class"] for r in encode.frequency_classes(people(spark, rows), ("FN",)).collect()}
    counts = pd.Series([r[2] for r in rows]).value_counts()
    order = sorted(counts.index, key=lambda v: (-counts[v], v))
    assert found == {v: 1 if i / 699 < 0.01 else 2 if i / 699 < 0.05 else 3 for i, v in enumerate(order)}


def test_values_of_any_length_are_masked(spark):
    row = spark.createDataFrame([("a" * 5000, "a" * 5000, "ab", "a")], "l string, r string, x string, y string").select(oracle.mask_positions(F.col("l"), F.col("r")), oracle.mask_positions(F.col("x"), F.col("y"))).first()
    assert row[0] == "*" * 5000 and row[1] == "*b"


def test_scenarios_that_run_together_equal_those_alone(spark, sf_dir):
    data = workloads.data_set(spark, sf_dir, P)
    few = dict(offsets=(-0.05, 0.05), repetitions=1, key_seed=1)
    specs = {"a": dict(budget=100, **few), "b": dict(budget=300, err=0.0, reply_rate=0.6, sampler="closest", **few)}
    together = workloads.curves(data, specs)
    for name, s in specs.items():
        alone = workloads.curve(data, **s)
        columns = ["run_id", "round", "reviews_attr", "reviews_human", "tp", "fp", "threshold"]
        assert together[name].metrics.select(columns).toPandas().sort_values(["run_id", "round"]).values.tolist() == alone.metrics.select(columns).toPandas().sort_values(["run_id", "round"]).values.tolist()


def test_grams(spark):
    row = one(spark, text.qgrams(F.lit("abab")), text.qgrams(F.lit("")), text.qgrams(F.lit(None).cast("string")), text.qgrams(F.lit("ab"), 3))
    assert row[0] == ["_a", "ab", "ba", "b_"] and row[1] is None and row[2] is None and row[3] == ["__a", "_ab", "ab_", "b__"]


def packed(spark, positions, m):
    return spark.createDataFrame([(positions,)], "p array<int>").select(*bits.pack(F.col("p"), m)).withColumn("ones", bits.popcount([F.col(w) for w in bits.names(m)]).cast("int"))


@pytest.mark.parametrize(("given", "wanted"), [([1, 64, 1023], [1, 64, 511]), ([1, 513, 64, 1023], [64, 511])])
def test_folding(spark, given, wanted):
    folded = encode.xor_fold(packed(spark, given, 1024))
    assert folded.select(bits.unpack([F.col(w) for w in bits.names(512)])).first()[0] == wanted
    assert folded.first()["ones"] == len(wanted)


@pytest.mark.parametrize(("counts", "gini", "divergence", "distance"), [((0, 0, 0, 4), 0.75, 0.548794941, 0.740806952), ((0, 0, 2, 2), 0.5, 0.311278124, 0.557923045), ((1, 2, 3, 4), 0.25, 0.040201582, 0.200503323), ((1, 1, 1, 1), 0, 0, 0)])
def test_unevenness(spark, counts, gini, divergence, distance):
    row = measures.unevenness(spark.createDataFrame(list(enumerate(counts)), "bit int, cnt long")).first()
    assert (row["gini"], row["js_divergence"], row["js_distance"]) == pytest.approx((gini, divergence, distance), abs=2e-8)


def test_weighted_mean(spark):
    sims = {"FN": 1.0, "MN": None, "LN": 0.5, "YOB": 1.0, "CITY": 0.8, "ZIP": 0.9, "POB": None}
    df = spark.createDataFrame([tuple(sims.values())], ", ".join(f"sim_{a} double" for a in sims))
    assert df.select(compare.weighted_mean(encode.WEIGHTS)).first()[0] == pytest.approx(0.876491146)


def test_micro_f1(spark):
    runs = spark.createDataFrame([(0, 80, 10, 20), (0, 90, 5, 10)], "round int, tp long, fp long, fn long")
    assert measures.micro_f1(runs).first()["micro_f1"] == pytest.approx(0.883116883)


def test_disclosure(spark):
    population = spark.createDataFrame([("A", "a", "x"), ("A", "a", "y"), ("A", "b", "x"), ("A", "b", "x")], "owner string, p string, q string")
    given = spark.createDataFrame([("A", "a", "x"), ("A", "a", None), ("A", "b", "x"), ("A", None, None)], "owner string, p string, q string")
    assert measures.disclosure(given, population, ("p", "q")).first()["score"] == 0.4375
    assert measures.disclosure(given.limit(0), population, ("p", "q")).first()["slots"] == 0


SHIFT = [(0.60, 0, 0.9), (0.62, 0, 1), (0.63, 0, 0.8), (0.64, 1, 2), (0.66, 1, 0.6), (0.68, 0, 0.7), (0.69, 0, 0.55), (0.70, 1, 2), (0.71, 0, 2), (0.72, 1, 0.9), (0.74, 1, 0.95), (0.75, 1, 1)]


@pytest.mark.parametrize(("current", "drift", "wanted"), [(0.66, 0.10, 0.64), (0.66, 0.05, 0.66), (0.70, 0.10, 0.70)])
def test_threshold_shift(spark, current, drift, wanted):
    s, m, w = zip(*SHIFT, strict=True)
    assert classify.shift(s, m, w, current, 0.70, drift, 0.02, step=0.01) == pytest.approx(wanted)
    labels = spark.createDataFrame([(a, bool(b), float(c)) for a, b, c in SHIFT], "sim double, match boolean, weight double")
    assert classify.shift_table(labels, current, 0.70, drift, 0.02, step=0.01).where("chosen").first()["t"] == pytest.approx(wanted)


def test_fitted_hash_counts_for_five_six_and_three_grams(spark):
    df = people(spark, [("A", 1, "anna", None, "li", "1970", "x", "27001", "NA")])
    found = {r["attr"]: r["h"] for r in encode.fit_hash_counts(df).collect() if r["attr"] in ("YOB", "ZIP", "POB")}
    assert found == {"YOB": 26, "ZIP": 21, "POB": 43}


def test_pair_keys(spark):
    df = people(spark, [("A", 1, "anna", None, "li", "1970", "x", "27001", "NA"), ("B", 1, "anna", None, "li", "1970", "y", "27001", None), ("A", 2, "anna", None, "li", "1970", "x", "27001", "NA")])
    pairs = spark.createDataFrame([("p", "A1", "B1"), ("q", "A2", "B1")], "pair_id string, left_id string, right_id string")
    f = encode.pair_keyed_filters(owner.enqueue(pairs, seed=0), df, P)
    rows = {(r["pair_id"], r["rec_id"], r["attr"]): tuple(r[w] for w in bits.names(256)) for r in f.collect()}
    assert rows["p", "A1", "FN"] == rows["p", "B1", "FN"]
    assert rows["p", "B1", "FN"] != rows["q", "B1", "FN"] and rows["p", "A1", "FN"] != rows["p", "A1", "LN"]
    assert ("p", "A1", "MN") not in rows
    sims = compare.attribute_similarities(f.where("owner = 'A'"), f.where("owner = 'B'")).where("pair_id = 'p'").first()
    assert sims["sim_FN"] == 1 and sims["sim_CITY"] < 1 and sims["sim_MN"] is None and sims["sim_POB"] is None


def test_blocking_has_no_duplicates_and_no_null_blocks(spark):
    df = people(spark, [("A", 1, "anna", None, "li", "1970", "x", "1", None), ("B", 1, "anna", None, "li", "1970", "x", "1", None), ("A", 2, None, None, None, None, "x", "1", None), ("B", 2, None, None, None, None, "x", "1", None), ("B", 3, "anne", None, "lee", "1980", "x", "1", None)])
    k = block.keys(df, "k")
    found = [(r["left_id"], r["right_id"]) for r in block.candidates(k.where("owner = 'A'"), k.where("owner = 'B'")).collect()]
    assert sorted(found) == [("A1", "B1"), ("A1", "B3")]
    assert block.purged(k.where("owner = 'A'"), k.where("owner = 'B'"), 0).first()["pairs"] == 5 - 1


def test_empty_tables(spark):
    df = people(spark, [("A", 1, "a", "b", "c", "1", "d", "2", "e")]).limit(0)
    assert encode.record_filter(df, P).count() == 0
    k = block.keys(df, "k")
    assert block.candidates(k, k).count() == 0
    assert encode.frequency_classes(df).count() == 0


def test_buckets_take_turns(spark):
    pairs = spark.createDataFrame([(f"p{i}", 0.5 + 0.03 * b + 0.001 * i) for b in (0, 1, 4) for i in range(5)] + [("certain", 0.9)], "pair_id string, p double")
    drawn = sampling.bucketed(pairs.withColumn("pair_id", F.concat("pair_id", F.col("p").cast("string"))), 8).toPandas()
    counts = drawn.groupby("bucket").size()
    assert set(counts.index) == {0, 1, 4} and counts.max() - counts.min() <= 1 and counts[0] == 3 and drawn.p.max() < 0.8


def test_batch_size_and_decoys():
    assert sampling.batch_for(100, 0.5) == 400 and sampling.batch_for(10, 1.0) == 10 and sampling.batch_for(10, 0) == 0


def test_selection(spark):
    sims = spark.createDataFrame([(1.0, 0.9, 0.3, None)], "sim_FN double, sim_MN double, sim_LN double, sim_YOB double")
    ask = lambda mode: [r for r in sims.select(*(owner.selected(a, mode) for a in ("FN", "MN", "LN", "YOB"))).first()]
    assert ask("all") == [True] * 4 and ask("unequal") == [False, True, True, False] and ask("intermediate") == [False, True, False, False]
    with pytest.raises(ValueError):
        owner.selected("FN", "other")


def test_masks(spark):
    row = one(spark, oracle.mask_pair(F.lit("smith"), F.lit("smyth")), oracle.mask_positions(F.lit("ann"), F.lit(None).cast("string")), oracle.mask_aligned(F.lit("xsmith"), F.lit("smith")))
    assert (row[0]["left"], row[0]["right"], row[1], row[2]) == ("**i**", "**y**", "ann", "x*****")


def test_human_error_rate(spark):
    df = spark.range(4000).select(F.col("id").alias("pair_id"), F.lit(True).alias("truth"))
    rate = lambda err: df.select(F.avg((~oracle.human(F.col("truth"), err)).cast("int"))).first()[0]
    assert rate(0.0) == 0 and abs(rate(0.2) - 0.2) < 0.03


def test_forest_grows_and_forgets():
    rng = np.random.default_rng(0)
    x = rng.uniform(size=(200, 14))
    y = (x[:, 0] > 0.5).astype(float)
    f = forest.EvolvingForest()
    sizes = []
    for _ in range(12):
        f = f.update(x, y, np.ones(200))
        sizes.append(len(f.trees))
    assert sizes[:3] == [10, 20, 30] and sizes[-1] == 100 and f.sequence == list(range(20, 120))
    g, p = f.classify(x)
    assert (g == (y > 0)).mean() > 0.95 and p.min() >= 0.5 and p.max() <= 1


def test_tree_by_hand():
    t = cart.grow_tree(np.array([[0.0], [1.0], [2.0], [3.0]]), np.array([0.0, 0, 1, 1]), np.ones(4), 6, 1, np.random.default_rng(0))
    assert t.threshold[0] == 1.5 and t.predict(np.array([[1.4], [1.6]])).tolist() == [0, 1]


def test_a_tree_takes_the_best_split():
    """The first split is that of all places with the greatest gain in weighted Gini impurity, ties of values included."""
    rng = np.random.default_rng(4)
    x, y, w = np.column_stack([rng.integers(0, 4, 80), rng.uniform(size=80).round(2), np.zeros(80)]).astype(float), rng.integers(0, 2, 80).astype(float), rng.uniform(0.5, 2, 80)
    y[x[:, 1] > 0.7] = 1.0
    impurity = lambda rows: (q := (w[rows] * y[rows]).sum() / w[rows].sum()) * (1 - q) * w[rows].sum()
    split = {(f, (a + b) / 2): impurity(x[:, f] <= a) + impurity(x[:, f] > a) for f in range(3) for a, b in itertools.pairwise(np.unique(x[:, f]))}
    t = cart.grow_tree(x, y, w, 1, 3, np.random.default_rng(0))
    assert (t.feature[0], t.threshold[0]) == pytest.approx(min(split, key=split.get)) and len(t.feature) == 3


def test_grouped_training_and_newest(spark):
    rng = np.random.default_rng(1)
    rows = pd.DataFrame({"run_id": ["a"] * 60 + ["b"] * 60, "s": rng.uniform(size=120)})
    rows["label"] = (rows.s > 0.4).astype(float)
    rows["weight"] = 1.0
    trees = forest.train(spark.createDataFrame(rows), ["s"], updates=3)
    assert trees.groupBy("run_id").count().toPandas()["count"].tolist() == [30, 30]
    assert forest.newest(trees, 10).agg(F.min("seq")).first()[0] == 20


def test_latest_and_changed(spark):
    log = spark.createDataFrame([("p", 0, "top", True, 0.6, 0.6), ("p", 1, "plain", False, 1.0, 2.0), ("p", 2, "attr", True, 0.9, 0.9), ("q", 1, "attr", True, 0.7, 0.7), ("q", 2, "attr", False, 0.7, 0.7)], "pair_id string, round int, layer string, g boolean, p double, weight double")
    best = {r["pair_id"]: (r["layer"], r["round"], r["g"]) for r in protocol.latest(log).collect()}
    assert best == {"p": ("plain", 1, False), "q": ("attr", 2, False)}
    a = log.where("pair_id = 'q'")
    assert protocol.changed(a.where("round = 1"), a.where("round = 2")).count() == 1 and protocol.changed(a, a.where("round = 2").unionAll(a.where("round = 1"))).count() >= 0


def test_run_reviews_keep_to_the_budget():
    table = np.zeros((1002, 2), dtype=np.int64)
    table[700:] = 1, 0
    s = protocol.Settings(schedule=protocol.Schedule(20, 5, 40, 4, 20))
    run = protocol.Run("r", 0.7, 0, s, table, 300)
    rng = np.random.default_rng(0)
    for batch in range(9):
        sims = rng.uniform(0.68, 0.75, 20)
        new = pd.DataFrame({"pair_id": [f"{batch}-{i}" for i in range(20)], "left_id": "a", "right_id": "b", "sim": sims, "truth": sims > 0.71} | {f"sim_{a}": sims for a in ATTRIBUTES} | {f"fq_{a}": 0 for a in ATTRIBUTES})
        before = run.t
        run.advance(new, s, batch < 5, table, 300)
        assert abs(run.t - run.t_init) <= 0.1 + 1e-9 and abs(run.t - before) <= 3 * 0.02 + 1e-9
    assert run.reviews_human <= 20 and run.updates == 5 * 3 + 4 and len(run.forest.trees) <= 100


def test_shares():
    assert workloads.budget_shares(protocol.Schedule(budget=300)) == (0.6, 300 / 4500)
    assert measures.sampling_floor(9000, 0.4) == pytest.approx(0.0073, abs=2e-4)


def test_exact_grams_agree_with_filters(spark):
    df = people(spark, [("A", 1, "anna", "eva", "li", "1970", "x", "27001", "NA"), ("B", 1, "anna", "eva", "li", "1970", "x", "27001", "NA"), ("B", 2, "otto", None, "berg", "1931", "y", "28009", "ZZ")])
    pairs = spark.createDataFrame([("A1", "B1"), ("A1", "B2")], "left_id string, right_id string")
    exact = {r["right_id"]: r["sim"] for r in baselines.exact_grams(pairs, df).collect()}
    assert exact["B1"] == 1 and exact["B2"] < 0.3


def test_histogram_rounds_like_its_definition(spark):
    values = [k / 1000 + d for k in range(0, 1000, 7) for d in (0.0, 1e-12, -1e-12, 4e-10, -4e-10, 6e-9, -6e-9, 4e-9, -4e-9, 3e-4)]
    pairs = spark.createDataFrame([(abs(v), i % 3 == 0) for i, v in enumerate(values)], "sim double, truth boolean")
    for digits in (None, 8, 2):
        sim = F.col("sim") if digits is None else F.round("sim", digits)
        wanted = pairs.groupBy(F.floor(F.round(sim / 0.001, 6)).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("truth").cast("long")).alias("n_true"))
        assert sorted(measures.histogram(pairs, digits=digits).collect()) == sorted(wanted.collect())


def test_blocking_difference_finds_moved_records(spark):
    """Layers whose records have other keys: the same counts as from all pairs."""

    def layer(keys):
        records = spark.createDataFrame([(i, i[0], k) for i, k in keys.items()], "rec_id string, owner string, keys array<string>")
        return records, block.candidates(records.where("owner = 'A'"), records.where("owner = 'B'"))

    one = layer({"A1": ["x", "s", None], "A2": ["y", "t", "u"], "B1": ["x", "s", "u"], "B2": ["y", None, "u"]})
    other = layer({"A1": ["x", "s", None], "A2": ["z", "t", "u"], "B1": ["x", "s", "v"], "B3": ["z", "s", "u"]})
    found = measures.blocking_difference(one, other, "one", "other").first()
    sets = [{(r["left_id"], r["right_id"]) for r in x[1].collect()} for x in (one, other)]
    assert [found[c] for c in ("one", "other", "only_one", "only_other")] == [len(sets[0]), len(sets[1]), len(sets[0] - sets[1]), len(sets[1] - sets[0])]
    assert found["only_one"] and found["only_other"]
