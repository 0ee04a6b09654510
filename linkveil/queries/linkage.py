"""Queries of the record-linkage methods, each over whole tables, with a DuckDB twin wherever SQL can express it."""

from __future__ import annotations

import weakref
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkveil.functions import bits, crypto, text
from linkveil.operators import attacks, baselines, block, classify, compare, encode, measures, oracle, owner, pairwise, sampling
from linkveil.plans import protocol
from linkveil.queries import linkage_sql as S
from linkveil.queries import twin
from linkveil.session import durable, released, stored
from linkveil.sources import registry as R
from linkveil.sources.registry import ATTRIBUTES

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}
T = S.T
P = S.P
_kept: weakref.WeakKeyDictionary = weakref.WeakKeyDictionary()


def query(sql: str | None = None):
    def register(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = sql
        return f

    return register


def file_state(spark: SparkSession, sf_dir: str) -> tuple:
    """The folder with the age and size of the tables that the registry is made of: what is kept for it goes out of use when they change."""
    out = [sf_dir]
    for name in ("orders", "customer", "nation", "documents"):
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/{name}.parquet")
        status = path.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(path)
        out.append((status.getModificationTime(), status.getLen()))
    return tuple(out)


def kept(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], DataFrame], write: Callable[[DataFrame], DataFrame] = durable) -> DataFrame:
    """A derived table that several queries of a session use: written once to the checkpoint folder, as long as its sources stay as they are."""
    tables = _kept.setdefault(spark, {})
    key = (name, file_state(spark, sf_dir))
    if key not in tables:
        tables[key] = write(make())
        released(spark)
    return tables[key]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def registry(spark: SparkSession, sf_dir: str, variant: str = "E1M") -> DataFrame:
    return kept(spark, sf_dir, f"registry {variant}", lambda: R.registry(spark, sf_dir, variant), stored)


def record_filters(spark, sf_dir) -> DataFrame:
    return kept(spark, sf_dir, "filters", lambda: encode.record_filter(registry(spark, sf_dir), P))


def attribute_filters(spark, sf_dir) -> DataFrame:
    return kept(spark, sf_dir, "attribute filters", lambda: encode.attribute_filters(registry(spark, sf_dir), P))


def keyed(spark, sf_dir) -> DataFrame:
    return block.keys(registry(spark, sf_dir), S.KEY)


def pairs(spark, sf_dir) -> DataFrame:
    """(pair_id, left_id, right_id, truth) of the blocking.  Pairs grow with the square of the records, so they aren't kept."""
    k = keyed(spark, sf_dir)
    found = block.candidates(k.where("owner = 'A'"), k.where("owner = 'B'"), ["entity_id"])
    return found.select(F.concat_ws("-", "left_id", "right_id").alias("pair_id"), "left_id", "right_id", (F.col("l_entity_id") == F.col("r_entity_id")).alias("truth"))


def candidates(spark, sf_dir, hardening: str | None = None) -> DataFrame:
    """Compared pairs, each time anew."""
    return layer(spark, sf_dir, hardening).pairs()


def layer(spark, sf_dir, hardening: str | None = None) -> protocol.Layer:
    return protocol.layer(registry(spark, sf_dir), P, hardening)


def classified(spark, sf_dir) -> DataFrame:
    return classify.threshold(candidates(spark, sf_dir), T)


def drawn(spark, sf_dir) -> DataFrame:
    return kept(spark, sf_dir, "drawn", lambda: _drawn(layer(spark, sf_dir), 100))


def _drawn(found: protocol.Layer, size: int) -> DataFrame:
    """Drawn from each pass's first pairs of each bucket; the tasks hand on uncertain pairs only."""
    lo, hi = classify.uncertain_interval(T)
    near = lambda one: classify.threshold(found.pairs(lo - protocol.STEP, hi + protocol.STEP, one=one), T)
    return sampling.bucketed(found.gathered(lambda one: sampling.shortlist(near(one), size)), size)


def requests(spark, sf_dir) -> DataFrame:
    return owner.enqueue(drawn(spark, sf_dir), seed=0)


def pair_filters(spark, sf_dir) -> DataFrame:
    return kept(spark, sf_dir, "pair filters", lambda: encode.pair_keyed_filters(requests(spark, sf_dir), registry(spark, sf_dir), P))


def pair_sims(spark, sf_dir) -> DataFrame:
    f = pair_filters(spark, sf_dir)
    sims = compare.attribute_similarities(f.where("owner = 'A'"), f.where("owner = 'B'"))
    return kept(spark, sf_dir, "pair sims", lambda: drawn(spark, sf_dir).join(sims, "pair_id", "left"))


def replies(spark, sf_dir, mode: str = "all") -> DataFrame:
    return owner.provide(owner.select_attributes(pair_sims(spark, sf_dir), mode), registry(spark, sf_dir))


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 9) for c in columns})


# --- registry ---------------------------------------------------------------------------------------------------------


@query(S.with_(S.registry("E1M")) + "SELECT * FROM registry")
def registry_e1m(spark, sf_dir):
    return registry(spark, sf_dir, "E1M")


@query(S.with_(S.registry("E2M")) + "SELECT * FROM registry")
def registry_e2m(spark, sf_dir):
    return registry(spark, sf_dir, "E2M")


_ROLE = "CASE WHEN u < {o} / 3::DOUBLE THEN 'both' WHEN u < 1 / 3::DOUBLE THEN 'A' WHEN u < (2 - {o}) / 3::DOUBLE THEN 'B' END"


@query(
    f"WITH s AS (SELECT {twin.u('o_orderkey', 'split')} AS u FROM orders) "
    + " UNION ALL ".join(f"SELECT '{v}' AS overlap, role, count(*) AS records FROM (SELECT {_ROLE.format(o=o)} AS role FROM s) WHERE role IS NOT NULL GROUP BY role" for v, o in R.OVERLAPS.items())
)
def registry_sizes(spark, sf_dir):
    """Entities in both sources, in A and in B only, by overlap."""
    u = crypto.uniform(F.col("o_orderkey"), "split")
    roles = F.array(*(F.struct(F.lit(v).alias("overlap"), F.when(F.col("u") < o / 3, "both").when(F.col("u") < 1 / 3, "A").when(F.col("u") < (2 - o) / 3, "B").alias("role")) for v, o in R.OVERLAPS.items()))
    each = table(spark, sf_dir, "orders").select(u.alias("u")).select(F.explode(roles).alias("r")).select("r.*")
    return each.where("role IS NOT NULL").groupBy("overlap", "role").agg(F.count(F.lit(1)).alias("records"))


_DIFFERS = {"FN": ("FN",), "MN": ("MN",), "LN": ("LN",), "POB": ("POB",), "PLACE": ("CITY", "ZIP")}


@query(
    S.with_(S.registry())
    + "SELECT n_groups, count(*) AS pairs FROM (SELECT "
    + " + ".join("(" + " OR ".join(f"a.{c} IS DISTINCT FROM b.{c}" for c in cs) + ")::INT" for cs in _DIFFERS.values())
    + " AS n_groups FROM registry a JOIN registry b USING (entity_id) WHERE a.owner = 'A' AND b.owner = 'B') GROUP BY n_groups"
)
def registry_changed_groups(spark, sf_dir):
    """True pairs by the number of changed groups."""
    r = registry(spark, sf_dir)
    a, b = r.where("owner = 'A'").alias("a"), r.where("owner = 'B'").alias("b")
    differs = sum((encode.either(*(~F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}")) for c in cs)).cast("int") for cs in _DIFFERS.values()), F.lit(0))
    return a.join(b, "entity_id").select(differs.alias("n_groups")).groupBy("n_groups").agg(F.count(F.lit(1)).alias("pairs"))


@query(S.with_(S.registry()) + "SELECT lang, token, n, rank FROM vocabulary")
def vocabulary_rank(spark, sf_dir):
    return R.vocabulary(table(spark, sf_dir, "documents")).select("lang", "token", "n", F.col("rank").cast("long"))


# --- text, hashing, encoding -------------------------------------------------------------------------------------------


@query("SELECT p_partkey, nullif(trim(regexp_replace(lower(p_name), '\\s+', ' ', 'g')), '') AS name FROM part")
def normalised_values(spark, sf_dir):
    return table(spark, sf_dir, "part").select("p_partkey", text.normalise(F.col("p_name")).alias("name"))


@query(f"SELECT p_partkey, array_to_string(list_sort({twin.grams('lower(p_name)')}), ',') AS grams FROM part")
def padded_grams(spark, sf_dir):
    return table(spark, sf_dir, "part").select("p_partkey", F.array_join(F.array_sort(text.qgrams(F.lower("p_name"))), ",").alias("grams"))


@query(S.with_(S.registry(), S.VALUE, S.GRAM) + "SELECT attr, gram, count(*) AS records FROM gram_of GROUP BY attr, gram")
def gram_counts(spark, sf_dir):
    return encode.grams(registry(spark, sf_dir), ATTRIBUTES).groupBy("attr", "gram").agg(F.count(F.lit(1)).alias("records"))


def _distinct_grams(spark, sf_dir):
    return encode.grams(registry(spark, sf_dir), ATTRIBUTES).select("gram").distinct()


_SEED = twin.hmac("gram", f"'{S.KEY}'")


@query(S.with_(S.registry(), S.VALUE, S.GRAM) + f"SELECT gram, {_SEED} AS seed FROM (SELECT DISTINCT gram FROM gram_of)")
def hmac_seed(spark, sf_dir):
    return _distinct_grams(spark, sf_dir).select("gram", crypto.hmac_sha256(F.col("gram"), S.KEY).alias("seed"))


def _positions(spark, sf_dir, family):
    found = crypto.positions(crypto.hmac_sha256(F.col("gram"), S.KEY), 12, 1024, family, 12)
    return _distinct_grams(spark, sf_dir).select("gram", F.array_join(found.cast("array<string>"), ",").alias("positions"))


@query(S.with_(S.registry(), S.VALUE, S.GRAM) + f"SELECT gram, array_to_string({twin.positions(_SEED, '12', 1024, most=12)}, ',') AS positions FROM (SELECT DISTINCT gram FROM gram_of)")
def hash_positions(spark, sf_dir):
    return _positions(spark, sf_dir, "random")


@query(S.with_(S.registry(), S.VALUE, S.GRAM) + f"SELECT gram, array_to_string({twin.positions(_SEED, '12', 1024, 'double')}, ',') AS positions FROM (SELECT DISTINCT gram FROM gram_of)")
def hash_positions_double(spark, sf_dir):
    return _positions(spark, sf_dir, "double")


def _unpacked(filters, m):
    return filters.select("rec_id", F.array_join(bits.unpack([F.col(w) for w in bits.names(m)]).cast("array<string>"), ",").alias("positions"))


@query(S.with_(*S.TO_RECORD) + "SELECT rec_id, array_to_string(pos, ',') AS positions FROM record_filter")
def record_filter_positions(spark, sf_dir):
    return _unpacked(record_filters(spark, sf_dir), 1024)


@query(S.with_(*S.TO_RECORD) + "SELECT rec_id, ones::INT AS ones FROM record_filter")
def record_filter_ones(spark, sf_dir):
    return record_filters(spark, sf_dir).select("rec_id", "ones")


@query(S.with_(*S.TO_RECORD, S.folded()) + "SELECT rec_id, array_to_string(pos, ',') AS positions FROM folded")
def folded_positions(spark, sf_dir):
    return _unpacked(encode.xor_fold(record_filters(spark, sf_dir)), 512)


_SALTED = f"""
salted_gram AS (SELECT g.rec_id, g.owner, g.gram, r.YOB AS salt FROM gram_of g JOIN registry r ON r.rec_id = g.rec_id),
salted_mask AS (SELECT gram, salt, {twin.positions(twin.hmac('gram', f"'{S.KEY}|' || salt"), '12', 1024, most=12)} AS p FROM (SELECT DISTINCT gram, salt FROM salted_gram))
SELECT rec_id, len(list_distinct(flatten(list(p))))::INT AS ones FROM salted_gram JOIN salted_mask USING (gram, salt) GROUP BY rec_id"""


@query(S.with_(S.registry(), S.VALUE, S.GRAM, _SALTED.split("\nSELECT rec_id, len")[0]) + "SELECT rec_id, len" + _SALTED.split("\nSELECT rec_id, len")[1])
def salted_ones(spark, sf_dir):
    """Record filters with the year of birth in the key."""
    return encode.record_filter(registry(spark, sf_dir), P, record_salt="YOB").select("rec_id", "ones")


@query(S.with_(S.registry(), S.VALUE, S.GRAM, S.ATTRIBUTE_FILTER) + "SELECT rec_id, attr, ones::INT AS ones FROM attr_filter")
def attribute_filter_ones(spark, sf_dir):
    return attribute_filters(spark, sf_dir).select("rec_id", "attr", "ones")


_PLAN = encode.bit_plan(encode.WEIGHTS, 1024, P.attribute_m, P.key)


@query(
    S.with_(S.registry(), S.VALUE, S.GRAM, S.ATTRIBUTE_FILTER, "plan(position, attr, bit) AS (VALUES " + ", ".join(f"({p}, '{a}', {b})" for p, a, b in _PLAN) + ")")
    + "SELECT r.rec_id, coalesce(n, 0)::INT AS ones FROM registry r LEFT JOIN (SELECT rec_id, count(DISTINCT position) AS n FROM (SELECT rec_id, attr, unnest(pos) AS bit FROM attr_filter) JOIN plan USING (attr, bit) GROUP BY rec_id) USING (rec_id)"
)
def sampled_filter_ones(spark, sf_dir):
    return encode.sampled_filter(registry(spark, sf_dir), P).select("rec_id", "ones")


@query(S.with_(*S.TO_REQUESTS, S.PAIR_KEYED) + "SELECT pair_id, owner, rec_id, attr, ones::INT AS ones FROM pair_filter")
def pair_keyed_ones(spark, sf_dir):
    return pair_filters(spark, sf_dir).select("pair_id", "owner", "rec_id", "attr", "ones")


@query(
    S.with_(S.registry(), S.VALUE)
    + f"SELECT attr, round(avg(len({twin.grams('value')})), 9) AS avg_grams, floor(256 * ln(1 / (1 - 0.4::DOUBLE)) / avg(len({twin.grams('value')})))::INT AS h FROM value_of WHERE value IS NOT NULL GROUP BY attr"
)
def fitted_hash_counts(spark, sf_dir):
    return rounded(encode.fit_hash_counts(registry(spark, sf_dir)), "avg_grams")


@query(S.with_(*S.TO_RECORD, S.ATTRIBUTE_FILTER) + "SELECT 'record' AS name, round(avg(ones / 1024::DOUBLE), 9) AS fill FROM record_filter UNION ALL SELECT attr, round(avg(ones / 256::DOUBLE), 9) FROM attr_filter GROUP BY attr")
def fill_rates(spark, sf_dir):
    whole = encode.fill_rate(record_filters(spark, sf_dir), 1024).select(F.lit("record").alias("name"), "fill")
    single = encode.fill_rate(attribute_filters(spark, sf_dir), 256, ["attr"]).withColumnRenamed("attr", "name")
    return rounded(whole.unionByName(single), "fill")


@query(
    S.with_(S.registry(), S.VALUE)
    + "SELECT attr, value, n, CASE WHEN r < 0.01 THEN 1 WHEN r < 0.05 THEN 2 ELSE 3 END AS freq_class FROM (SELECT attr, value, n, percent_rank() OVER (PARTITION BY attr ORDER BY n DESC, value) AS r FROM (SELECT attr, value, count(*) AS n FROM value_of WHERE value IS NOT NULL GROUP BY attr, value))"
)
def frequency_classes(spark, sf_dir):
    return encode.frequency_classes(registry(spark, sf_dir))


# --- blocking and comparison --------------------------------------------------------------------------------------------


@query(
    S.with_(S.registry(), S.KEYED)
    + " UNION ALL ".join(f"SELECT {i} AS key_no, n_left, n_right, count(*) AS blocks FROM (SELECT k{i}, count(*) FILTER (WHERE owner = 'A') AS n_left, count(*) FILTER (WHERE owner = 'B') AS n_right FROM keyed WHERE k{i} IS NOT NULL GROUP BY k{i}) WHERE n_left > 0 AND n_right > 0 GROUP BY n_left, n_right" for i in range(3))
)
def block_sizes(spark, sf_dir):
    k = keyed(spark, sf_dir)
    return block.block_sizes(k.where("owner = 'A'"), k.where("owner = 'B'")).groupBy("key_no", "n_left", "n_right").agg(F.count(F.lit(1)).alias("blocks"))


@query(S.with_(S.registry(), S.KEYED, S.PAIR) + "SELECT left_id, right_id, truth FROM pair")
def candidate_pairs(spark, sf_dir):
    return pairs(spark, sf_dir).select("left_id", "right_id", "truth")


@query(S.with_(S.registry(), S.KEYED) + "SELECT a.rec_id AS left_id, b.rec_id AS right_id FROM keyed a JOIN keyed b ON a.owner = 'A' AND b.owner = 'B' AND a.k0 = b.k0 UNION SELECT a.rec_id, b.rec_id FROM keyed a JOIN keyed b ON a.owner = 'A' AND b.owner = 'B' AND a.k1 = b.k1")
def candidate_pairs_exact_keys(spark, sf_dir):
    """Without the phonetic key."""
    k = block.keys(registry(spark, sf_dir), S.KEY, ("fn_yob", "ln_yob"))
    return block.candidates(k.where("owner = 'A'"), k.where("owner = 'B'")).select("left_id", "right_id")


@query(
    S.with_(S.registry(), S.KEYED, S.PAIR)
    + "SELECT n_candidates, n_true, n_kept, round(n_kept / n_true::DOUBLE, 9) AS pair_completeness, round(1 - n_candidates / (n_a * n_b)::DOUBLE, 9) AS reduction_ratio FROM (SELECT (SELECT count(*) FROM pair) AS n_candidates, (SELECT count(*) FROM pair WHERE truth) AS n_kept, (SELECT count(*) FROM registry a JOIN registry b USING (entity_id) WHERE a.owner = 'A' AND b.owner = 'B') AS n_true, (SELECT count(*) FROM registry WHERE owner = 'A') AS n_a, (SELECT count(*) FROM registry WHERE owner = 'B') AS n_b)"
)
def blocking_quality(spark, sf_dir):
    return measures.blocking(pairs(spark, sf_dir), registry(spark, sf_dir))


@query(S.with_(S.registry(), S.KEYED, S.PAIR) + "SELECT count(*) AS plain, count(*) AS folded, 0::BIGINT AS only_plain, 0::BIGINT AS only_folded FROM pair")
def candidates_hardened_diff(spark, sf_dir):
    """The same pairs come up whatever the encoding."""
    r = registry(spark, sf_dir)
    return measures.blocking_difference(protocol.top_layer(r, P), protocol.top_layer(r, P, hardening="xor"), "plain", "folded")


@query(S.with_(*S.TO_PAIRS) + "SELECT left_id, right_id, common::INT AS common, round(sim, 9) AS sim FROM cand")
def dice_top(spark, sf_dir):
    return rounded(candidates(spark, sf_dir).select("left_id", "right_id", "common", "sim"), "sim")


@query(S.with_(*S.TO_RECORD, S.folded(), S.KEYED, S.PAIR, S.compared("folded")) + "SELECT left_id, right_id, common::INT AS common, round(sim, 9) AS sim FROM cand")
def dice_folded(spark, sf_dir):
    return rounded(candidates(spark, sf_dir, "xor").select("left_id", "right_id", "common", "sim"), "sim")


@query(S.with_(*S.TO_PAIRS) + "SELECT left_id, right_id, round(common / (l_ones + r_ones - common)::DOUBLE, 9) AS jaccard, round(common / least(l_ones, r_ones)::DOUBLE, 9) AS overlap, (l_ones + r_ones - 2 * common)::INT AS hamming FROM cand")
def jaccard_top(spark, sf_dir):
    """Other similarities of the same filters."""
    c, a, b = F.col("common"), F.col("l_ones"), F.col("r_ones")
    return candidates(spark, sf_dir).select("left_id", "right_id", F.round(compare.jaccard(c, a, b), 9).alias("jaccard"), F.round(compare.overlap(c, a, b), 9).alias("overlap"), compare.hamming(c, a, b).alias("hamming"))


_SIMS = ", ".join(f"round(sim_{a}, 9) AS sim_{a}" for a in ATTRIBUTES)


@query(S.with_(*S.TO_SIMS) + f"SELECT pair_id, {_SIMS} FROM pair_sim")
def dice_attributes(spark, sf_dir):
    """Attribute similarities of the first batch's pairs, from pair-keyed filters."""
    sims = [f"sim_{a}" for a in ATTRIBUTES]
    return rounded(pair_sims(spark, sf_dir).select("pair_id", *sims), *sims)


_PLAIN_SIMS = """
left_part AS MATERIALIZED (SELECT pair_id, right_id, attr, pos, ones FROM pair JOIN attr_filter ON rec_id = left_id),
wide_sim AS (
  SELECT p.*, """ + ", ".join(f"s.sim_{a}" for a in ATTRIBUTES) + """ FROM pair p LEFT JOIN (
    SELECT pair_id, """ + ", ".join(f"max(CASE WHEN attr = '{a}' THEN sim END) AS sim_{a}" for a in ATTRIBUTES) + """
    FROM (SELECT pair_id, l.attr, 2.0::DOUBLE * len(list_intersect(l.pos, r.pos)) / (l.ones + r.ones) AS sim
          FROM left_part l JOIN attr_filter r ON r.rec_id = right_id AND r.attr = l.attr) GROUP BY pair_id) s USING (pair_id)
)"""
_MEAN = "(" + " + ".join(f"coalesce(sim_{a} * {w}, 0)" for a, w in encode.WEIGHTS.items()) + ") / (" + " + ".join(f"CASE WHEN sim_{a} IS NOT NULL THEN {w}::DOUBLE ELSE 0 END" for a, w in encode.WEIGHTS.items()) + ")"
_TO_MEANS = (S.registry(), S.VALUE, S.GRAM, S.ATTRIBUTE_FILTER, S.KEYED, S.PAIR, _PLAIN_SIMS)


@query(S.with_(*_TO_MEANS) + f"SELECT left_id, right_id, round({_MEAN}, 8) AS score FROM wide_sim")
def weighted_mean_scores(spark, sf_dir):
    """The attribute-only baseline's scores of all candidates."""
    records = registry(spark, sf_dir)
    found = baselines.blocked_scores(records, P, rows=protocol.attribute_layer(records, P).dealt(), sims=False)
    return found.select("left_id", "right_id", F.round("sim", 8).alias("score"))


_GRAM_SET = "gram_set AS (SELECT rec_id, list_distinct(list(gram)) AS grams FROM gram_of GROUP BY rec_id)"


@query(S.with_(S.registry(), S.VALUE, S.GRAM, _GRAM_SET, S.KEYED, S.PAIR) + "SELECT left_id, right_id, round(2.0::DOUBLE * len(list_intersect(l.grams, r.grams)) / (len(l.grams) + len(r.grams)), 9) AS sim FROM pair JOIN gram_set l ON l.rec_id = left_id JOIN gram_set r ON r.rec_id = right_id")
def dice_exact_grams(spark, sf_dir):
    return rounded(baselines.exact_grams(pairs(spark, sf_dir), registry(spark, sf_dir)).select("left_id", "right_id", "sim"), "sim")


@query(S.with_(S.registry(), S.VALUE) + "SELECT attr, count(DISTINCT value) AS n_values, round(log2((1 - 0.01::DOUBLE) * count(DISTINCT value)), 9) AS weight FROM value_of GROUP BY attr")
def fitted_weights(spark, sf_dir):
    return baselines.fitted_weights(registry(spark, sf_dir))


# --- classification, sampling, review -----------------------------------------------------------------------------------


@query(S.with_(*S.TO_PAIRS, S.CLASSIFIED) + "SELECT left_id, right_id, g, p FROM classified")
def threshold_predictions(spark, sf_dir):
    return classified(spark, sf_dir).select("left_id", "right_id", "g", "p")


@query(f"SELECT i::INT AS i, {S.ramp('i / 100.0::DOUBLE')} AS p, i / 100.0::DOUBLE >= {T}::DOUBLE AS g FROM range(0, 101) r(i)")
def ramp_grid(spark, sf_dir):
    sims = spark.range(101).select(F.col("id").cast("int").alias("i"), (F.col("id") / 100.0).alias("sim"))
    return classify.threshold(sims, T).select("i", "p", "g")


@query(S.with_(*S.TO_PAIRS, S.CLASSIFIED) + "SELECT pair_id, p FROM classified ORDER BY p, pair_id LIMIT 100")
def uncertain_closest(spark, sf_dir):
    return sampling.most_uncertain(classified(spark, sf_dir), 100).select("pair_id", "p")


@query(S.with_(*S.TO_DRAWN) + "SELECT pair_id, p, bucket, turn::INT AS turn FROM drawn")
def uncertain_bucketed(spark, sf_dir):
    return drawn(spark, sf_dir).select("pair_id", "p", "bucket", "turn")


@query(S.with_(*S.TO_PAIRS, S.CLASSIFIED) + "SELECT pair_id, p FROM classified ORDER BY md5('0|' || pair_id) LIMIT 100")
def uncertain_random(spark, sf_dir):
    return sampling.random_sample(classified(spark, sf_dir), 100).select("pair_id", "p")


@query(S.with_(*S.TO_DRAWN) + "SELECT bucket, count(*) AS pairs, count(*) FILTER (WHERE truth) AS true_pairs FROM turns GROUP BY bucket")
def bucket_sizes(spark, sf_dir):
    inside = classified(spark, sf_dir).where("p < 0.8").withColumn("bucket", sampling.bucket(F.col("p")))
    return inside.groupBy("bucket").agg(F.count(F.lit(1)).alias("pairs"), F.count(F.when(F.col("truth"), 1)).alias("true_pairs"))


_CELL = " || ".join(f"coalesce(least(floor(sim_{a} * 4)::INT, 3)::VARCHAR, '-')" for a in ATTRIBUTES)


@query(S.with_(*S.TO_SIMS) + f"SELECT pair_id, cell, turn::INT AS turn FROM (SELECT *, row_number() OVER (PARTITION BY cell ORDER BY md5('0|' || pair_id), pair_id) AS turn FROM (SELECT pair_id, {_CELL} AS cell FROM pair_sim WHERE p < 0.8)) ORDER BY turn, md5('0|' || pair_id) LIMIT 40")
def uncertain_diverse(spark, sf_dir):
    """Spread over feature vectors: pairs of the first batch, by cells of attribute similarities."""
    return sampling.diverse(pair_sims(spark, sf_dir), 40, [f"sim_{a}" for a in ATTRIBUTES]).select("pair_id", "cell", "turn")


@query(S.with_(*S.TO_REQUESTS) + "SELECT * FROM request")
def owner_requests(spark, sf_dir):
    return requests(spark, sf_dir)


_REPLIED = f"replied AS (SELECT * FROM request WHERE {twin.u('rec_id', 'reply0')} < 0.8)"


@query(S.with_(*S.TO_REQUESTS, _REPLIED) + "SELECT pair_id, count(DISTINCT owner) AS owners FROM replied GROUP BY pair_id")
def owner_replies_rate(spark, sf_dir):
    """With four of five records answered, pairs by answering owners."""
    answered = owner.Policy(rate=0.8).replies(requests(spark, sf_dir))
    return answered.groupBy("pair_id").agg(F.countDistinct("owner").alias("owners"))


@query(S.with_(*S.TO_REQUESTS) + "SELECT pair_id, owner, rec_id FROM request WHERE rec_id NOT IN (SELECT rec_id FROM (SELECT rec_id, count(*) OVER (PARTITION BY YOB, POB) AS k FROM registry) WHERE k < 5)")
def owner_denied(spark, sf_dir):
    """Owners withhold records whose year and place of birth fewer than five share."""
    deny = owner.rare_records(registry(spark, sf_dir), ["YOB", "POB"], 5)
    return owner.Policy().replies(requests(spark, sf_dir), deny).select("pair_id", "owner", "rec_id")


def _selection(mode):
    columns = ", ".join(f"count(*) FILTER (WHERE ask_{a}) AS {a}" for a in ATTRIBUTES)

    def run(spark, sf_dir):
        asked = owner.select_attributes(pair_sims(spark, sf_dir), mode)
        return asked.groupBy("bucket").agg(*(F.count(F.when(F.col(f"ask_{a}"), 1)).alias(a) for a in ATTRIBUTES))

    run.__name__ = f"selection_{mode}"
    query(S.with_(*S.TO_SIMS, S.asks(mode)) + f"SELECT bucket, {columns} FROM asked GROUP BY bucket")(run)


for _mode in ("all", "unequal", "intermediate", "adaptive"):
    _selection(_mode)


@query(S.with_(*S.TO_DRAWN) + f"SELECT pair_id, CASE WHEN {twin.u('pair_id', 'human0')} < 0.2 THEN NOT truth ELSE truth END AS g FROM drawn")
def human_labels(spark, sf_dir):
    return drawn(spark, sf_dir).select("pair_id", oracle.human(F.col("truth"), 0.2).alias("g"))


def _mask_sql(x: str, y: str) -> str:
    each = f"array_to_string(list_transform(range(1, length({x}) + 1), lambda i: CASE WHEN substr({x}, i::INT, 1) = substr({y}, i::INT, 1) THEN '*' ELSE substr({x}, i::INT, 1) END), '')"
    return f"CASE WHEN {x} IS NULL THEN NULL WHEN {y} IS NULL OR length({x}) = 0 THEN {x} ELSE {each} END"


@query(S.with_(*S.TO_DRAWN) + "SELECT pair_id, " + ", ".join(f"{_mask_sql(f'a.{x}', f'b.{x}')} AS l_{x}, {_mask_sql(f'b.{x}', f'a.{x}')} AS r_{x}" for x in ATTRIBUTES) + " FROM drawn JOIN registry a ON a.rec_id = left_id JOIN registry b ON b.rec_id = right_id")
def masked_display(spark, sf_dir):
    """What a reviewer sees of a pair: equal letters hidden."""
    r = registry(spark, sf_dir)
    side = lambda s, name: r.select(F.col("rec_id").alias(name), *(F.col(a).alias(s + a) for a in ATTRIBUTES))
    both = drawn(spark, sf_dir).select("pair_id", "left_id", "right_id").join(side("l_", "left_id"), "left_id").join(side("r_", "right_id"), "right_id")
    shown = {f"{s}{a}": oracle.mask_positions(F.col(f"{s}{a}"), F.col(f"{o}{a}")) for a in ATTRIBUTES for s, o in (("l_", "r_"), ("r_", "l_"))}
    return both.select("pair_id", *(v.alias(k) for k, v in shown.items()))


@query()
def masked_aligned(spark, sf_dir):
    r = registry(spark, sf_dir)
    side = lambda s, name: r.select(F.col("rec_id").alias(name), F.col("LN").alias(s + "LN"))
    both = drawn(spark, sf_dir).select("pair_id", "left_id", "right_id").join(side("l_", "left_id"), "left_id").join(side("r_", "right_id"), "right_id")
    return both.select("pair_id", oracle.mask_aligned("l_LN", "r_LN").alias("left"), oracle.mask_aligned("r_LN", "l_LN").alias("right"))


def _shift_sql(measure: str) -> str:
    q = "(tp + tn) / (tp + fp + fn + tn)" if measure == "accuracy" else "2 * tp / greatest(2 * tp + fp + fn, 1e-12)"
    return (
        S.with_(*S.TO_DRAWN, f"label AS (SELECT sim, CASE WHEN {twin.u('pair_id', 'human0')} < 0.1 THEN NOT truth ELSE truth END AS m, p AS w FROM drawn)", "step AS (SELECT round(0.7::DOUBLE + 0.001::DOUBLE * (i - 20), 9) AS t FROM range(41) r(i))")
        + f""", scored AS (SELECT t, round({q}, 9) AS quality FROM (SELECT t,
          sum(CASE WHEN round(sim, 9) >= t AND m THEN w ELSE 0 END) AS tp, sum(CASE WHEN round(sim, 9) >= t AND NOT m THEN w ELSE 0 END) AS fp,
          sum(CASE WHEN round(sim, 9) < t AND m THEN w ELSE 0 END) AS fn, sum(CASE WHEN round(sim, 9) < t AND NOT m THEN w ELSE 0 END) AS tn FROM label, step GROUP BY t))
        SELECT t, quality, row_number() OVER (ORDER BY quality DESC, round(abs(t - 0.7::DOUBLE), 9), t) = 1 AS chosen FROM scored"""
    )


def _shift(spark, sf_dir, measure):
    labels = drawn(spark, sf_dir).select("sim", oracle.human(F.col("truth"), 0.1).alias("match"), F.col("p").alias("weight"))
    return classify.shift_table(labels, T, T, measure=measure)


@query(_shift_sql("accuracy"))
def threshold_shift_accuracy(spark, sf_dir):
    return _shift(spark, sf_dir, "accuracy")


@query(_shift_sql("f1"))
def threshold_shift_f1(spark, sf_dir):
    return _shift(spark, sf_dir, "f1")


def label_log(spark, sf_dir) -> DataFrame:
    """A log of three layers' labels: the top's in round 0, attribute labels in rounds 1 and 2, a human's for every fifth pair."""
    d = drawn(spark, sf_dir)
    u = lambda tag: crypto.uniform(F.col("pair_id"), tag)
    top = d.select("pair_id", F.lit(0).alias("round"), F.lit("top").alias("layer"), "g", "p", F.col("p").alias("weight"))
    attr = lambda r: d.where(u(f"attr{r}") < 0.7).select("pair_id", F.lit(r).alias("round"), F.lit("attr").alias("layer"), oracle.human(F.col("truth"), 0.2, r).alias("g"), F.round(0.5 + u(f"p{r}") / 2, 9).alias("p")).withColumn("weight", F.col("p"))
    plain = d.where(u("plain") < 0.2).select("pair_id", F.lit(1).alias("round"), F.lit("plain").alias("layer"), oracle.human(F.col("truth"), 0.1, 9).alias("g"), F.lit(1.0).alias("p"), F.lit(2.0).alias("weight"))
    return top.unionByName(attr(1)).unionByName(attr(2)).unionByName(plain)


def _flip(err, seed):
    return f"CASE WHEN {twin.u('pair_id', f'human{seed}')} < {err} THEN NOT truth ELSE truth END"


_LOG = "log_of AS (SELECT pair_id, 0 AS round, 'top' AS layer, 1 AS rank, g, p, p AS weight FROM drawn UNION ALL " + " UNION ALL ".join(
    f"SELECT pair_id, {r}, 'attr', 2, {_flip(0.2, r)}, round(0.5::DOUBLE + {twin.u('pair_id', f'p{r}')} / 2, 9), round(0.5::DOUBLE + {twin.u('pair_id', f'p{r}')} / 2, 9) FROM drawn WHERE {twin.u('pair_id', f'attr{r}')} < 0.7" for r in (1, 2)
) + f" UNION ALL SELECT pair_id, 1, 'plain', 3, {_flip(0.1, 9)}, 1.0, 2.0 FROM drawn WHERE {twin.u('pair_id', 'plain')} < 0.2)"
_LATEST = "latest AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY pair_id ORDER BY rank DESC, round DESC) AS i FROM log_of) WHERE i = 1)"


@query(S.with_(*S.TO_DRAWN, _LOG, _LATEST) + "SELECT pair_id, round, layer, g, p, weight::DOUBLE AS weight FROM latest")
def latest_labels(spark, sf_dir):
    return protocol.latest(label_log(spark, sf_dir)).select("pair_id", "round", "layer", "g", "p", "weight")


@query(S.with_(*S.TO_DRAWN, _LOG) + "SELECT b.pair_id, b.g, b.p FROM (SELECT * FROM log_of WHERE layer = 'attr' AND round = 2) b LEFT JOIN (SELECT * FROM log_of WHERE layer = 'attr' AND round = 1) a USING (pair_id) WHERE a.g IS DISTINCT FROM b.g OR a.p IS DISTINCT FROM b.p")
def changed_outcomes(spark, sf_dir):
    log = label_log(spark, sf_dir).where("layer = 'attr'")
    return protocol.changed(log.where("round = 1"), log.where("round = 2")).select("pair_id", "g", "p")


@query(S.with_(*S.TO_DRAWN, _LOG, _LATEST) + f"SELECT c.pair_id, coalesce(l.g, c.sim >= {T}::DOUBLE) AS g, coalesce(l.layer, 'top') AS layer FROM cand c LEFT JOIN (SELECT * FROM latest WHERE layer <> 'top') l USING (pair_id)")
def final_result(spark, sf_dir):
    labels = protocol.latest(label_log(spark, sf_dir)).where("layer <> 'top'")
    return protocol.result(candidates(spark, sf_dir), labels, T).select("pair_id", "g", "layer")


# --- measures -----------------------------------------------------------------------------------------------------------

_N_TRUE = "(SELECT count(*) FROM registry a JOIN registry b USING (entity_id) WHERE a.owner = 'A' AND b.owner = 'B')"


def _by_threshold_sql(source: str, sim: str) -> str:
    return f"""
hist AS (SELECT floor(round({sim} / 0.001, 6))::INT AS bin, count(*) AS n, count(*) FILTER (WHERE truth) AS n_true FROM {source} GROUP BY 1),
curve AS (SELECT round(bin * 0.001::DOUBLE, 9) AS t, tp, fp, n_all - tp AS fn, round(coalesce(2.0::DOUBLE * tp / nullif(2 * tp + fp + n_all - tp, 0), 0), 9) AS f1
  FROM (SELECT bin, (sum(n_true) OVER w)::BIGINT AS tp, (sum(n - n_true) OVER w)::BIGINT AS fp, {_N_TRUE} AS n_all FROM hist WINDOW w AS (ORDER BY bin DESC ROWS UNBOUNDED PRECEDING)))"""


def _curve(spark, sf_dir, scored, digits=None, weight=None):
    n_true = measures.true_pairs(registry(spark, sf_dir)).count()
    return measures.quality_by_threshold(measures.histogram(scored, digits=digits, weight=weight), n_true)


@query(S.with_(*S.TO_PAIRS, _by_threshold_sql("cand", "sim")) + "SELECT * FROM curve")
def quality_by_threshold(spark, sf_dir):
    return _curve(spark, sf_dir, layer(spark, sf_dir).tally(), weight="n")


@query(S.with_(*S.TO_PAIRS, _by_threshold_sql("cand", "sim")) + "SELECT * FROM curve ORDER BY f1 DESC, t LIMIT 1")
def best_threshold_top(spark, sf_dir):
    """The top layer alone at its best threshold."""
    return _curve(spark, sf_dir, layer(spark, sf_dir).tally(), weight="n").orderBy(F.desc("f1"), "t").limit(1)


@query(S.with_(*_TO_MEANS, _by_threshold_sql("wide_sim", f"round({_MEAN}, 8)")) + "SELECT * FROM curve ORDER BY f1 DESC, t LIMIT 1")
def best_threshold_attribute(spark, sf_dir):
    """The attribute-only baseline at its best threshold."""
    return _curve(spark, sf_dir, protocol.attribute_tally(registry(spark, sf_dir), P), 8, weight="n").orderBy(F.desc("f1"), "t").limit(1)


@query(
    S.with_(*S.TO_PAIRS, S.CLASSIFIED)
    + f"SELECT tp, fp, fn, round(tp / (tp + fp)::DOUBLE, 9) AS precision, round(tp / (tp + fn)::DOUBLE, 9) AS recall, round(2 * tp / (2 * tp + fp + fn)::DOUBLE, 9) AS f1 FROM (SELECT count(*) FILTER (WHERE g AND truth) AS tp, count(*) FILTER (WHERE g AND NOT truth) AS fp, {_N_TRUE} - count(*) FILTER (WHERE g AND truth) AS fn FROM classified)"
)
def quality_counts(spark, sf_dir):
    return rounded(measures.quality(classified(spark, sf_dir), measures.true_pairs(registry(spark, sf_dir))), "precision", "recall", "f1")


_STARTS = [round(0.65 + 0.01 * i, 2) for i in range(11)]
_RUNS = "start(t) AS (VALUES " + ", ".join(f"({t}::DOUBLE)" for t in _STARTS) + f"), run AS (SELECT t, count(*) FILTER (WHERE truth) AS tp, count(*) FILTER (WHERE NOT truth) AS fp, {_N_TRUE} - count(*) FILTER (WHERE truth) AS fn FROM start JOIN cand ON sim >= t GROUP BY t)"


@query(S.with_(*S.TO_PAIRS, _RUNS) + "SELECT 0 AS round, count(*) AS runs, sum(tp)::BIGINT AS tp, sum(fp)::BIGINT AS fp, sum(fn)::BIGINT AS fn, round(min(f), 9) AS min_f1, round(max(f), 9) AS max_f1, round(2 * sum(tp) / (2 * sum(tp) + sum(fp) + sum(fn))::DOUBLE, 9) AS micro_f1, round(max(f) - min(f), 9) AS f1_range FROM (SELECT *, 2.0::DOUBLE * tp / (2 * tp + fp + fn) AS f FROM run)")
def micro_f1(spark, sf_dir):
    """Micro average and range over the eleven starts, before any review."""
    starts = spark.createDataFrame([(t,) for t in _STARTS], "t double")
    n_true = measures.true_pairs(registry(spark, sf_dir)).count()
    over = candidates(spark, sf_dir).join(F.broadcast(starts), F.col("sim") >= F.col("t"))  # eleven rows
    runs = over.groupBy("t").agg(F.count(F.when(F.col("truth"), 1)).alias("tp"), F.count(F.when(~F.col("truth"), 1)).alias("fp")).withColumn("fn", F.lit(n_true) - F.col("tp")).withColumn("round", F.lit(0))
    return rounded(measures.micro_f1(runs), "min_f1", "max_f1", "micro_f1", "f1_range")




@query(S.with_(*S.TO_RECORD, "named AS (SELECT 'plain' AS name, pos FROM record_filter)", S.bit_counts("named", "name", 1024)) + S.unevenness("name"))
def gini_record(spark, sf_dir):
    counts = measures.bit_counts(record_filters(spark, sf_dir).withColumn("name", F.lit("plain")), 1024, ["name"])
    return measures.unevenness(counts, ["name"])


@query(S.with_(*S.TO_RECORD, S.folded(), "named AS (SELECT 'folded' AS name, pos FROM folded)", S.bit_counts("named", "name", 512)) + S.unevenness("name"))
def gini_folded(spark, sf_dir):
    counts = measures.bit_counts(encode.xor_fold(record_filters(spark, sf_dir)).withColumn("name", F.lit("folded")), 512, ["name"])
    return measures.unevenness(counts, ["name"])


@query(S.with_(S.registry(), S.VALUE, S.GRAM, S.ATTRIBUTE_FILTER, S.bit_counts("attr_filter", "attr", 256)) + S.unevenness("attr"))
def gini_attribute(spark, sf_dir):
    return measures.unevenness(measures.bit_counts(attribute_filters(spark, sf_dir), 256, ["attr"]), ["attr"])


@query(S.with_(*S.TO_REQUESTS, S.PAIR_KEYED, S.bit_counts("pair_filter", "attr", 256)) + S.unevenness("attr"))
def gini_pair_keyed(spark, sf_dir):
    return measures.unevenness(measures.bit_counts(pair_filters(spark, sf_dir), 256, ["attr"]), ["attr"])


@query(S.with_(*S.TO_REQUESTS, S.ATTRIBUTE_FILTER, S.PAIR_KEYED) + "SELECT 'plain' AS kind, attr, count(*) AS encodings FROM attr_filter GROUP BY attr UNION ALL SELECT 'pair_keyed', attr, count(*) FROM pair_filter GROUP BY attr")
def encoding_counts(spark, sf_dir):
    kinds = (("plain", attribute_filters(spark, sf_dir)), ("pair_keyed", pair_filters(spark, sf_dir)))
    each = [measures.encoding_counts(f).select(F.lit(k).alias("kind"), "attr", "encodings") for k, f in kinds]
    return each[0].unionByName(each[1])


_SHARES = ", ".join(f"round(avg(({a} IS NOT NULL)::INT), 9) AS {a}" for a in ATTRIBUTES)


@query(" UNION ALL ".join(f"SELECT * FROM ({S.with_(*S.TO_SIMS, S.asks(m), S.REPLY)} SELECT '{m}' AS mode, {_SHARES} FROM reply)" for m in ("all", "unequal", "intermediate")))
def attribute_share(spark, sf_dir):
    """Share of record slots that get each attribute, by selection."""
    each = [measures.attribute_share(replies(spark, sf_dir, m)).select(F.lit(m).alias("mode"), *ATTRIBUTES) for m in ("all", "unequal", "intermediate")]
    return each[0].unionByName(each[1]).unionByName(each[2])


_SAME = " AND ".join(f"(r.{a} IS NULL OR p.{a} = r.{a})" for a in ATTRIBUTES)
_D = " + ".join(f"(r.{a} IS NOT NULL)::INT" for a in ATTRIBUTES)


@query(
    " UNION ALL ".join(
        f"SELECT * FROM ({S.with_(*S.TO_SIMS, S.asks(m), S.REPLY)} SELECT '{m}' AS mode, count(*) AS slots, round(avg(CASE WHEN d > 0 THEN d / k::DOUBLE ELSE 0 END) / 7, 9) AS score FROM (SELECT r.pair_id, r.owner, {_D} AS d, (SELECT count(*) FROM registry p WHERE p.owner = r.owner AND {_SAME}) AS k FROM reply r))"
        for m in ("all", "unequal", "intermediate")
    )
)
def disclosure_score(spark, sf_dir):
    """Anonymity-weighted disclosure of the first batch, by selection."""
    each = [measures.disclosure(replies(spark, sf_dir, m), registry(spark, sf_dir)).select(F.lit(m).alias("mode"), "slots", "score") for m in ("all", "unequal", "intermediate")]
    return each[0].unionByName(each[1]).unionByName(each[2])


@query(S.with_(*S.TO_REQUESTS) + "SELECT count(DISTINCT pair_id) AS pairs, count(DISTINCT rec_id) AS records, count(*) AS slots FROM request")
def exposure_counts(spark, sf_dir):
    return measures.exposure(requests(spark, sf_dir))


@query(S.with_(S.registry(), S.KEYED, S.PAIR) + f", said AS (SELECT truth, CASE WHEN {twin.u('pair_id', 'human0')} < 0.2 THEN NOT truth ELSE truth END AS g FROM pair) SELECT count(*) AS reviews, count(*) FILTER (WHERE g AND truth) AS tp, count(*) FILTER (WHERE g AND NOT truth) AS fp, {_N_TRUE} - count(*) FILTER (WHERE g AND truth) AS fn FROM said")
def full_review(spark, sf_dir):
    """A human who errs in a fifth of the cases labels every candidate."""
    said = baselines.full_review(pairs(spark, sf_dir), 0.2)
    n_true = measures.true_pairs(registry(spark, sf_dir)).count()
    return said.agg(F.count(F.lit(1)).alias("reviews"), F.count(F.when(F.col("g") & F.col("truth"), 1)).alias("tp"), F.count(F.when(F.col("g") & ~F.col("truth"), 1)).alias("fp")).withColumn("fn", F.lit(n_true) - F.col("tp"))


_BOTH = "(SELECT a.{0} AS l, b.{0} AS r FROM drawn JOIN registry a ON a.rec_id = left_id JOIN registry b ON b.rec_id = right_id)"
_SHOWN = " + ".join(f"coalesce(length(replace({_mask_sql(x, y)}, '*', '')), 0)" for x, y in (("l", "r"), ("r", "l")))


@query(
    S.with_(*S.TO_DRAWN)
    + " UNION ALL ".join(f"SELECT '{a}' AS attr, sum((l IS NOT NULL)::INT + (r IS NOT NULL)::INT)::BIGINT AS values, sum(coalesce(length(l), 0) + coalesce(length(r), 0))::BIGINT AS characters, sum({_SHOWN})::BIGINT AS shown FROM {_BOTH.format(a)}" for a in ATTRIBUTES)
)
def full_plaintext_review(spark, sf_dir):
    """Characters that reviewers of the first batch read with full plaintext, and with the masked display."""
    return baselines.full_plaintext_review(drawn(spark, sf_dir), registry(spark, sf_dir))


@query(S.with_(*S.TO_DRAWN) + "SELECT pair_id, false AS decoy FROM drawn UNION ALL SELECT pair_id, true FROM (SELECT pair_id, row_number() OVER (ORDER BY md5('0|' || pair_id)) AS i FROM classified WHERE p >= 0.8) WHERE i <= ceil((SELECT count(*) FROM drawn) * 0.25)")
def decoy_requests(spark, sf_dir):
    """A request batch with a quarter of certain pairs mixed in."""
    found, batch, share = layer(spark, sf_dir), drawn(spark, sf_dir), 0.25
    size = sampling.decoys_for(batch, share)
    certain = lambda one: classify.threshold(found.pairs(one=one), T).where("p >= 0.8").select("pair_id", "p")
    first = found.gathered(lambda one: sampling.random_sample(certain(one), size))
    return sampling.with_decoys(batch, first, share).select("pair_id", "decoy")


@query(S.with_(*S.TO_REQUESTS) + "SELECT pair_id, rec_id FROM request WHERE owner = 'A' AND pair_id NOT IN (SELECT pair_id FROM (SELECT pair_id FROM request WHERE owner = 'A' ORDER BY round, pair_id, rec_id LIMIT 30)) ORDER BY round, pair_id, rec_id LIMIT 30")
def owner_pulls(spark, sf_dir):
    """Owner A's second pull of thirty requests, the first ones being answered."""
    queue = requests(spark, sf_dir)
    return owner.pull(queue, "A", owner.pull(queue, "A", size=30), 30).select("pair_id", "rec_id")


@query(
    "SELECT owner, requests, replies, CASE WHEN replies > 0 THEN ceil(round(100 / ((replies / requests::DOUBLE) * (replies / requests::DOUBLE)), 6))::BIGINT ELSE 0 END AS pairs "
    "FROM (SELECT user_id AS owner, count(*) AS requests, count(*) FILTER (WHERE event_type = 'purchase') AS replies FROM events GROUP BY user_id)"
)
def batch_sizes(spark, sf_dir):
    """Pairs to ask for so that two owners with a user's response rate (purchases among all events) both answer for a hundred."""
    replied = F.count(F.when(F.col("event_type") == "purchase", 1)).alias("replies")
    rates = table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("owner")).agg(F.count(F.lit(1)).alias("requests"), replied)
    return rates.withColumn("pairs", sampling.batch_of(100, F.col("replies") / F.col("requests")))


@query(S.with_(*S.TO_PAIRS) + "SELECT left_id, right_id, round(sim, 9) AS sim, round(least(l_ones, r_ones) / greatest(l_ones, r_ones)::DOUBLE, 9) AS fill_ratio FROM cand")
def top_features(spark, sf_dir):
    """Features of the top model: similarity and ratio of fill rates."""
    return rounded(candidates(spark, sf_dir).select("left_id", "right_id", *compare.top_features(1024, with_fill=True)), "sim", "fill_ratio")


@query(
    S.with_(S.registry(), S.VALUE, S.GRAM, f"mask_of AS (SELECT attr, gram, {twin.positions(twin.hmac('gram', f"'{S.KEY}|' || attr"), '12', 1024, most=12)} AS p FROM (SELECT DISTINCT attr, gram FROM gram_of))")
    + "SELECT rec_id, len(list_distinct(flatten(list(p))))::INT AS ones FROM gram_of JOIN mask_of USING (attr, gram) GROUP BY rec_id"
)
def attribute_salted_ones(spark, sf_dir):
    """Record filters with the attribute's name in the key."""
    return encode.record_filter(registry(spark, sf_dir), P, salt_by_attribute=True).select("rec_id", "ones")


# --- audits -------------------------------------------------------------------------------------------------------------


def _alignment_sql(source: str) -> str:
    return f""" SELECT attr, count(*) AS tried, count(*) FILTER (WHERE value = guess) AS hits, max(n) AS most_frequent FROM (
      SELECT attr, place, n, value FROM (SELECT *, row_number() OVER (PARTITION BY attr ORDER BY n DESC, value, pattern) AS place FROM (
        SELECT f.attr, md5(array_to_string(f.pos, ',')) AS pattern, count(*) AS n, min(v.value) AS value FROM {source} f JOIN value_of v ON v.rec_id = f.rec_id AND v.attr = f.attr GROUP BY f.attr, f.pos)) WHERE place <= 20)
    JOIN (SELECT attr, place, value AS guess FROM (SELECT *, row_number() OVER (PARTITION BY attr ORDER BY n DESC, value) AS place FROM (SELECT attr, value, count(*) AS n FROM value_of WHERE value IS NOT NULL GROUP BY attr, value)) WHERE place <= 20) USING (attr, place) GROUP BY attr"""


@query(S.with_(S.registry(), S.VALUE, S.GRAM, S.ATTRIBUTE_FILTER) + _alignment_sql("attr_filter"))
def attack_frequency_plain(spark, sf_dir):
    return attacks.frequency_alignment(attribute_filters(spark, sf_dir), registry(spark, sf_dir))


@query("SELECT attr, tried, most_frequent FROM (" + S.with_(*S.TO_REQUESTS, S.PAIR_KEYED) + _alignment_sql("pair_filter") + ")")
def attack_frequency_keyed(spark, sf_dir):
    """Patterns under pair keys hardly come up twice, so ranks say nothing; which of many equal counts is set beside a value has no meaning."""
    return attacks.frequency_alignment(pair_filters(spark, sf_dir), registry(spark, sf_dir), by=["pair_id"]).select("attr", "tried", "most_frequent")


def _told(spark, sf_dir) -> DataFrame:
    """Pairs that differ in one attribute only, found pass by pass where pairs come up, and the ids of their records."""
    records, sims = registry(spark, sf_dir), [f"sim_{a}" for a in ATTRIBUTES]
    found = protocol.attribute_layer(records, P)
    each = lambda one: attacks.one_difference(baselines.blocked_scores(records, P, rows=found.dealt(*one), single=True)).select("left_id", "right_id", *sims)
    return kept(spark, sf_dir, "pairs of one difference", lambda: found.gathered(each), lambda df: df)


def _attack(spark, sf_dir, encoded, m=1024):
    """Only pairs that differ in one attribute tell anything, so only their records are encoded by ``encoded``."""
    told = _told(spark, sf_dir)
    few = lambda: registry(spark, sf_dir).join(told.select(F.explode(F.array("left_id", "right_id")).alias("rec_id")).distinct(), "rec_id", "left_semi")
    filters, names = encoded(kept(spark, sf_dir, "records of one difference", few)), [*bits.names(m), "ones"]
    side = lambda s, name: filters.select(F.col("rec_id").alias(name), *(F.col(w).alias(s + w) for w in names))
    return attacks.attribute_bits(told.join(side("l_", "left_id"), "left_id").join(side("r_", "right_id"), "right_id"), m)


@query()
def attack_attribute_bits(spark, sf_dir):
    """Bits of sampled filters that the attack attributes rightly, and of joint filters that stay ambiguous."""
    plan = spark.createDataFrame(_PLAN, "position int, attr string, bit int")
    sampled = _attack(spark, sf_dir, lambda r: encode.sampled_filter(r, P))
    right = attacks.attribution_precision(sampled, plan).select("guesses", "right", "precision")
    whole = lambda r: kept(spark, sf_dir, "filters of one difference", lambda: encode.record_filter(r, P))
    joint = attacks.ambiguous_bits(_attack(spark, sf_dir, whole))
    folded = attacks.ambiguous_bits(_attack(spark, sf_dir, lambda r: encode.xor_fold(whole(r)), 512)).withColumnsRenamed({"clear": "folded_clear", "ambiguous": "folded_ambiguous"})
    return right.crossJoin(joint).crossJoin(folded)  # one row each


@query()
def attack_sampled_alignment(spark, sf_dir):
    """Sampled filters after the attribution of their bits: patterns by attribute against values by frequency."""
    filters = encode.sampled_values(registry(spark, sf_dir), P)
    return attacks.aligned_after_attribution(_attack(spark, sf_dir, lambda r: encode.sampled_filter(r, P)), filters, registry(spark, sf_dir))


@query()
def attack_token_inference(spark, sf_dir):
    """Grams read off attribute filters with half of the records known, under the owners' key and under pair keys."""
    r = registry(spark, sf_dir)
    kinds = (("owner_key", attribute_filters(spark, sf_dir)), ("pair_keys", pair_filters(spark, sf_dir)))
    each = [attacks.token_inference(f, r).select(F.lit(k).alias("kind"), "attr", "grams", "tests", "right", "wrong") for k, f in kinds]
    return each[0].unionByName(each[1])


@query()
def attack_token_bits(spark, sf_dir):
    return attacks.token_bits(pair_filters(spark, sf_dir), registry(spark, sf_dir))


@query(S.with_(S.registry()) + "SELECT rec_id, owner, YOB AS value FROM registry")
def attack_dictionary(spark, sf_dir):
    """With the owners' key, every year of birth is found from a list of years."""
    years = spark.range(1900, 2020).select(F.col("id").cast("string").alias("value"))
    return attacks.dictionary(attribute_filters(spark, sf_dir), years, "YOB", S.KEY, P)


@query(S.with_(S.registry()) + "SELECT rec_id, owner, YOB AS value FROM registry WHERE false")
def attack_dictionary_wrong_key(spark, sf_dir):
    years = spark.range(1900, 2020).select(F.col("id").cast("string").alias("value"))
    return attacks.dictionary(attribute_filters(spark, sf_dir), years, "YOB", "another", P)


@query(
    S.with_(*S.TO_DRAWN)
    + "SELECT *, round(seen_edges / all_edges::DOUBLE, 9) AS edge_share FROM (SELECT count(*) AS all_edges, count(DISTINCT left_id) AS all_left, count(DISTINCT right_id) AS all_right FROM cand WHERE sim >= 0.5), (SELECT count(*) AS seen_edges, count(DISTINCT left_id) AS seen_left, count(DISTINCT right_id) AS seen_right FROM cand WHERE sim >= 0.5 AND pair_id IN (SELECT pair_id FROM drawn))"
)
def graph_exposure(spark, sf_dir):
    batch, found, floor = drawn(spark, sf_dir), layer(spark, sf_dir), 0.5
    return attacks.node_exposure(found.gathered(lambda one: pairwise.nodes(found.dealt(*one), found.m, floor), stored), batch, floor)
