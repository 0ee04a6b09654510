"""The person registry that the experiments run on, derived from the given tables without a random generator.

Entities are orders, households are customers, names and places are frequent tokens of the documents by language.  All
draws are 32 bits of an MD5 of an id and a tag, so another engine builds the same rows.  A source split is a threshold on
such a draw, so no step needs all entities in one place.  B's copy of a shared entity has one (E1) or two (E2) changed
groups at least; each change really differs.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from linkveil.functions.crypto import uniform, uniforms
from linkveil.session import durable

ATTRIBUTES = ("FN", "MN", "LN", "YOB", "CITY", "ZIP", "POB")
#: Language of the vocabulary and its size for each drawn attribute.
VOCABULARIES = {"FN": ("fr", 1000), "MN": ("es", 1000), "LN": ("en", 3000), "CITY": ("de", 300)}
SKEW = 2.2
OVERLAPS = {"S": 0.1, "M": 0.2, "L": 0.3}
#: Groups of attributes that change together, with their weights.
GROUPS = {"FN": 1.0, "MN": 2.0, "LN": 1.5, "POB": 1.0, "PLACE": 3.0}
MISSING_MN, MISSING_POB = 0.078, 0.192
#: Draws by an entity's id, and by the id or household of those who share a name and a place.
DRAWS = (
    "hh", "FN", "MN", "MNo", "LNo", "CITYo", "POBo", "MNmiss", "YOB", "POBmiss", "FNc", "FNp", "FNl", "MNc", "LNc", "LNp", "LNl", "POBc", "more1", "more2",
    *(f"g{g}" for g in GROUPS),
)
SHARED_DRAWS = ("LN", "CITY", "ZIP", "ZIPo")
SCHEMA = T.StructType(
    [T.StructField("rec_id", T.StringType()), T.StructField("owner", T.StringType()), T.StructField("snapshot", T.StringType()), T.StructField("entity_id", T.LongType())]
    + [T.StructField(a, T.StringType()) for a in ATTRIBUTES]
)


@dataclass(frozen=True)
class Variant:
    """E1 or E2 (least number of changed groups) and S, M or L (overlap)."""

    name: str

    @property
    def changes(self) -> int:
        return int(self.name[1])

    @property
    def overlap(self) -> float:
        return OVERLAPS[self.name[2]]


def vocabulary(documents: DataFrame) -> DataFrame:
    """(lang, token, n, rank): tokens of four to twelve letters by language, most frequent first."""
    tokens = documents.select("lang", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]{4,12})"), F.lit(1))).alias("token"))
    counts = tokens.groupBy("lang", "token").agg(F.count(F.lit(1)).alias("n"))
    limits = F.create_map(*(F.lit(x) for lang, size in VOCABULARIES.values() for x in (lang, size)))
    ranked = counts.where(F.col("lang").isin([lang for lang, _ in VOCABULARIES.values()])).withColumn(
        "rank", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "token")) - 1
    )
    return ranked.where(F.col("rank") < limits[F.col("lang")])  # a limit on the rank: Spark keeps the top of each task only


def drawn(tag: str, column: str = "draws") -> Column:
    """One draw of a row.  All draws are made at once into an array: as an expression each, they make code too long to be compiled."""
    return F.get(column, F.lit((DRAWS if column == "draws" else SHARED_DRAWS).index(tag)))


def _edit(value: Column, tag: str) -> Column:
    """The value with one letter replaced by another one."""
    at = (F.floor(F.length(value) * drawn(tag + "p")) + 1).cast("int")
    old = F.ascii(F.substr(value, at, F.lit(1))) - 97
    letter = F.floor(drawn(tag + "l") * 26).cast("int")
    new = F.when(letter == old, (letter + 1) % 26).otherwise(letter)
    return F.concat(F.substr(value, F.lit(1), at - 1), F.char(new + 97), F.substr(value, at + 1, F.length(value)))


def _draw(u: Column, size: Column) -> Column:
    return F.least(F.floor(size * F.pow(u, F.lit(SKEW))).cast("int"), size - 1)


def entities(orders: DataFrame, customer: DataFrame, nation: DataFrame, documents: DataFrame) -> DataFrame:
    """One row an entity: its attributes and those of its changed copy (with suffix ``_b``), and the number of changes' draws.

    The vocabularies are bounded by VOCABULARIES, 5,300 rows, so they are sent to the tasks.
    """
    words = durable(vocabulary(documents))  # read once, not for each attribute
    sizes = words.groupBy("lang").agg(F.count(F.lit(1)).alias("v")).groupBy().pivot("lang", [lang for lang, _ in VOCABULARIES.values()]).agg(F.first("v"))
    k, household = F.col("entity_id"), F.concat(F.lit("h"), F.col("custkey"))
    place_key = F.when(drawn("hh") < 0.5, household).otherwise(k.cast("string"))
    size = {a: F.coalesce(F.col(lang), F.lit(1)).cast("int") for a, (lang, _) in VOCABULARIES.items()}
    people = (
        orders.select(F.col("o_orderkey").alias("entity_id"), F.col("o_custkey").alias("custkey"))
        .join(customer.select(F.col("c_custkey").alias("custkey"), "c_nationkey"), "custkey")
        .join(F.broadcast(nation.select(F.col("n_nationkey").alias("c_nationkey"), "n_name")), "c_nationkey")  # 25 rows
        .crossJoin(F.broadcast(sizes))  # one row
        .repartition("entity_id")
        .withColumn("draws", uniforms(k, DRAWS))
        .withColumn("shared_draws", uniforms(place_key, SHARED_DRAWS))
    )
    other = lambda a, tag: _draw(drawn(tag), size[a])
    ranks = people.select(
        "entity_id", "draws", "shared_draws", "n_name", "c_nationkey",
        other("FN", "FN").alias("r_fn"), other("MN", "MN").alias("r_mn"), _draw(drawn("LN", "shared_draws"), size["LN"]).alias("r_ln"), _draw(drawn("CITY", "shared_draws"), size["CITY"]).alias("r_city"),
        other("MN", "MNo").alias("o_mn"), other("LN", "LNo").alias("o_ln"), F.floor(F.greatest(size["CITY"] - 1, F.lit(1)) * drawn("CITYo")).cast("int").alias("o_city"),
        *(size[a].alias(f"v_{a.lower()}") for a in VOCABULARIES),
    ).withColumns({
        "b_mn": F.when(F.col("o_mn") == F.col("r_mn"), (F.col("o_mn") + 1) % F.col("v_mn")).otherwise(F.col("o_mn")),
        "b_ln": F.when(F.col("o_ln") == F.col("r_ln"), (F.col("o_ln") + 1) % F.col("v_ln")).otherwise(F.col("o_ln")),
        "b_city": (F.col("r_city") + 1 + F.col("o_city")) % F.col("v_city"),
    })
    for column, lang in (("r_fn", "fr"), ("r_mn", "es"), ("r_ln", "en"), ("r_city", "de"), ("b_mn", "es"), ("b_ln", "en"), ("b_city", "de")):
        values = words.where(F.col("lang") == lang).select(F.col("rank").alias(column), F.col("token").alias("t" + column))
        # never null: a filter on nulls would move down to the tables and draw there again
        ranks = ranks.withColumn(column, F.coalesce(column, F.lit(-1))).join(F.broadcast(values), column)
    zip_of = lambda city, tag: (27000 + 5 * F.col(city) + F.floor(5 * drawn(tag, "shared_draws"))).cast("string")
    code = lambda key: F.concat(F.substring("n_name", 1, 1), F.char(key + 65))
    changed_code = code((F.col("c_nationkey") + 1 + F.floor(24 * drawn("POBo")).cast("int")) % 25)
    base = ranks.select(
        "entity_id", "draws",
        F.col("tr_fn").alias("FN"),
        F.when(drawn("MNmiss") >= MISSING_MN, F.col("tr_mn")).alias("MN"),
        F.col("tr_ln").alias("LN"),
        (1930 + F.floor(75 * drawn("YOB"))).cast("string").alias("YOB"),
        F.col("tr_city").alias("CITY"),
        zip_of("r_city", "ZIP").alias("ZIP"),
        F.when(drawn("POBmiss") >= MISSING_POB, code(F.col("c_nationkey"))).alias("POB"),
        F.col("tb_mn").alias("MN_o"), F.col("tb_ln").alias("LN_o"), F.col("tb_city").alias("CITY_b"), zip_of("b_city", "ZIPo").alias("ZIP_b"), changed_code.alias("POB_o"),
    )
    fn_edit = (drawn("FNc") < 0.6) | (F.length("FN") <= 4)
    mn_kind = drawn("MNc")
    return base.select(
        "entity_id", "draws", *ATTRIBUTES,
        F.when(fn_edit, _edit(F.col("FN"), "FN")).otherwise(F.substring("FN", 1, 4)).alias("FN_b"),
        F.when(F.col("MN").isNull() | (mn_kind >= 0.7), F.col("MN_o")).when(mn_kind < 0.4, F.substring("MN", 1, 1)).alias("MN_b"),
        F.when(drawn("LNc") < 0.4, _edit(F.col("LN"), "LN")).otherwise(F.col("LN_o")).alias("LN_b"),
        F.when(F.col("POB").isNull() | (drawn("POBc") >= 0.5), F.col("POB_o")).alias("POB_b"),
        "CITY_b", "ZIP_b",
    )


def changed_groups(people: DataFrame, variant: Variant) -> DataFrame:
    """Adds ``n_changes`` and, for each group, ``ch_<group>``: the groups first in a weighted random order are changed."""
    more = sum((F.when(drawn(f"more{i}") < p, 1).otherwise(0) for i, p in ((1, 0.35), (2, 0.1))), F.lit(variant.changes))
    with_keys = people.withColumn("n_changes", more).withColumns({f"k_{g}": F.round(-F.log(drawn("g" + g) + 1e-12) / w, 9) for g, w in GROUPS.items()})
    order = list(GROUPS)
    before = {
        g: sum((F.when(F.col(f"k_{x}") < F.col(f"k_{g}"), 1).when((F.col(f"k_{x}") == F.col(f"k_{g}")) & F.lit(order.index(x) < order.index(g)), 1).otherwise(0) for x in order if x != g), F.lit(0))
        for g in order
    }
    return with_keys.withColumns({f"ch_{g}": before[g] < F.col("n_changes") for g in order}).drop(*(f"k_{g}" for g in order))


def registry_of(people: DataFrame, variant: Variant) -> DataFrame:
    """Both sources' records: rec_id, owner, snapshot, entity_id and the attributes.  n of a source is a third of the entities."""
    u, share = uniform(F.col("entity_id"), "split"), variant.overlap
    role = F.when(u < share / 3, "both").when(u < 1 / 3, "A").when(u < (2 - share) / 3, "B")
    rows = changed_groups(people, variant).withColumn("role", role).where("role IS NOT NULL")
    pick = {a: F.when(F.col("ch_" + {"CITY": "PLACE", "ZIP": "PLACE"}.get(a, a)) & (F.col("role") == "both"), F.col(f"{a}_b")).otherwise(F.col(a)) for a in ATTRIBUTES if a != "YOB"}
    pick["YOB"] = F.col("YOB")
    ids = lambda owner: (F.concat(F.lit(owner), F.col("entity_id")).alias("rec_id"), F.lit(owner).alias("owner"), F.lit("base" if owner == "A" else "changed").alias("snapshot"), F.col("entity_id"))
    left = F.when(F.col("role") != "B", F.struct(*ids("A"), *(F.col(a) for a in ATTRIBUTES)))
    right = F.when(F.col("role") != "A", F.struct(*ids("B"), *(pick[a].alias(a) for a in ATTRIBUTES)))
    # one row an entity becomes both owners' records, so that entities are drawn once
    return rows.select(F.explode(F.array_compact(F.array(left, right))).alias("r")).select("r.*")


def registry(spark: SparkSession, sf_dir: str, variant: str = "E1M") -> DataFrame:
    """The registry of a variant from the tables of a folder."""
    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    return registry_of(entities(read("orders"), read("customer"), read("nation"), read("documents")), Variant(variant))
