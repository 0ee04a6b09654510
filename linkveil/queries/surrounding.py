"""Operators that a user needs around the methods, each as a query over the given tables with its DuckDB twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from linkveil.functions import sqlfuncs
from linkveil.operators import compare
from linkveil.plans import workloads
from linkveil.queries import linkage_sql, twin
from linkveil.sources import exchange

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def register(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = sql
        return f

    return register


def t(spark, sf_dir, name):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def events(spark, sf_dir):
    return t(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp_ntz"))


_ALL = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@query(" UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS n FROM {n}" for n in _ALL))
def op_scan_tables(spark, sf_dir):
    out = None
    for n in _ALL:
        row = t(spark, sf_dir, n).agg(F.count(F.lit(1)).alias("n")).select(F.lit(n).alias("name"), "n")
        out = row if out is None else out.unionByName(row)
    return out


@query("SELECT c_custkey, c_name FROM customer WHERE c_acctbal BETWEEN 0 AND 1000 AND c_mktsegment IN ('BUILDING', 'MACHINERY') AND c_name LIKE 'Customer%'")
def op_filter_project(spark, sf_dir):
    return t(spark, sf_dir, "customer").where(F.col("c_acctbal").between(0, 1000) & F.col("c_mktsegment").isin("BUILDING", "MACHINERY") & F.col("c_name").like("Customer%")).select("c_custkey", "c_name")


@query("SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_totalprice > 100000")
def op_join_equi(spark, sf_dir):
    return t(spark, sf_dir, "orders").where("o_totalprice > 100000").join(t(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name")


@query("SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def op_join_broadcast(spark, sf_dir):
    return t(spark, sf_dir, "customer").join(F.broadcast(t(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))  # 25 rows


@query("SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey")
def op_join_left(spark, sf_dir):
    o = t(spark, sf_dir, "orders").select("o_custkey", "o_orderkey")
    return t(spark, sf_dir, "customer").join(o, F.col("o_custkey") == F.col("c_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("SELECT count(*) AS n, count(d.doc_id) AS documents, count(l.doc_id) AS labels FROM documents d FULL JOIN (SELECT doc_id FROM labels WHERE quality = 1) l USING (doc_id)")
def op_join_full(spark, sf_dir):
    d, lab = t(spark, sf_dir, "documents").select(F.col("doc_id").alias("d")), t(spark, sf_dir, "labels").where("quality = 1").select(F.col("doc_id").alias("l"))
    return d.join(lab, F.col("d") == F.col("l"), "full").agg(F.count(F.lit(1)).alias("n"), F.count("d").alias("documents"), F.count("l").alias("labels"))


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def op_join_semi(spark, sf_dir):
    return t(spark, sf_dir, "documents").join(t(spark, sf_dir, "labels"), "doc_id", "left_semi").select("doc_id")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti(spark, sf_dir):
    return t(spark, sf_dir, "documents").join(t(spark, sf_dir, "labels"), "doc_id", "left_anti").select("doc_id")


@query("SELECT a.n_name AS one, b.n_name AS other FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def op_join_self(spark, sf_dir):
    n = t(spark, sf_dir, "nation")
    a, b = n.alias("a"), n.alias("b")
    return a.join(b, (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("one"), F.col("b.n_name").alias("other"))


@query("SELECT band, count(*) AS customers FROM customer JOIN (SELECT i AS band, i * 1000 - 1000 AS lo, i * 1000 AS hi FROM range(0, 12) r(i)) b ON c_acctbal >= lo AND c_acctbal < hi GROUP BY band")
def op_join_range(spark, sf_dir):
    bands = spark.range(12).select(F.col("id").alias("band"), (F.col("id") * 1000 - 1000).alias("lo"), (F.col("id") * 1000).alias("hi"))
    return t(spark, sf_dir, "customer").join(F.broadcast(bands), (F.col("c_acctbal") >= F.col("lo")) & (F.col("c_acctbal") < F.col("hi"))).groupBy("band").agg(F.count(F.lit(1)).alias("customers"))  # twelve rows


@query("SELECT a.event_id AS request, b.event_id AS reply FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def op_join_interval(spark, sf_dir):
    """Replies within an hour of a request, keyed by user."""
    e = events(spark, sf_dir).select("event_id", "user_id", "event_type", "ts")
    a, b = e.where("event_type = 'click'").alias("a"), e.where("event_type = 'purchase'").alias("b")
    within = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("b.ts") > F.col("a.ts")) & (F.col("b.ts") <= F.col("a.ts") + F.expr("INTERVAL 1 HOUR"))
    return a.join(b, within).select(F.col("a.event_id").alias("request"), F.col("b.event_id").alias("reply"))


@query("SELECT e.event_id, max(p.event_id) AS last_view FROM events e LEFT JOIN events p ON p.user_id = e.user_id AND p.event_type = 'view' AND (p.ts < e.ts OR (p.ts = e.ts AND p.event_id < e.event_id)) WHERE e.event_type = 'purchase' AND NOT EXISTS (SELECT 1 FROM events q WHERE q.user_id = p.user_id AND q.event_type = 'view' AND (q.ts > p.ts OR (q.ts = p.ts AND q.event_id > p.event_id)) AND (q.ts < e.ts OR (q.ts = e.ts AND q.event_id < e.event_id))) GROUP BY e.event_id")
def op_join_asof(spark, sf_dir):
    """For each purchase the user's latest view before it: one pass of a window instead of a join."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    view = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(order)
    return events(spark, sf_dir).withColumn("last_view", view).where("event_type = 'purchase'").select("event_id", "last_view")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS quantity, round(avg(l_extendedprice), 4) AS price, min(l_shipdate)::DATE::VARCHAR AS first, max(l_shipdate)::DATE::VARCHAR AS last FROM lineitem GROUP BY ALL HAVING count(*) > 10")
def op_aggregate(spark, sf_dir):
    g = t(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus")
    return g.agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.min("l_shipdate").cast("date").cast("string").alias("first"), F.max("l_shipdate").cast("date").cast("string").alias("last")).where("n > 10")


@query("SELECT lang, count(DISTINCT text) AS texts, count(*) FILTER (WHERE n_chars > 1000) AS long_ones, arg_max(doc_id, n_chars * 1000000 + doc_id) AS longest FROM documents GROUP BY lang")
def op_aggregate_distinct(spark, sf_dir):
    return t(spark, sf_dir, "documents").groupBy("lang").agg(F.countDistinct("text").alias("texts"), F.count(F.when(F.col("n_chars") > 1000, 1)).alias("long_ones"), F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest"))


@query("SELECT lang, source, grouping_id(lang, source)::BIGINT AS level, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
def op_cube(spark, sf_dir):
    return t(spark, sf_dir, "documents").cube("lang", "source").agg(F.grouping_id("lang", "source").alias("level"), F.count(F.lit(1)).alias("n"))


@query("SELECT n_regionkey, c_mktsegment, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY ROLLUP (n_regionkey, c_mktsegment)")
def op_rollup(spark, sf_dir):
    joined = t(spark, sf_dir, "customer").join(t(spark, sf_dir, "nation"), F.col("n_nationkey") == F.col("c_nationkey"))
    return joined.rollup("n_regionkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, bit_or(user_id) AS any_bits, bit_xor(event_id) AS parity FROM events GROUP BY event_type")
def op_percentile_bits(spark, sf_dir):
    return events(spark, sf_dir).groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.5)), 6).alias("median"), F.bit_or("user_id").alias("any_bits"), F.bit_xor("event_id").alias("parity"))


@query()
def op_sketches(spark, sf_dir):
    """Approximate counterparts: distinct users, percentiles, a count-min sketch's size."""
    e = events(spark, sf_dir)
    return e.agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", [0.25, 0.5, 0.75], 1000).alias("quartiles"), F.octet_length(F.count_min_sketch("user_id", F.lit(0.01), F.lit(0.95), F.lit(7))).alias("sketch_bytes"))


@query("SELECT lang, coalesce(sum(CASE WHEN source = 'src1' THEN 1 END), 0)::BIGINT AS src1, coalesce(sum(CASE WHEN source = 'src2' THEN 1 END), 0)::BIGINT AS src2 FROM documents GROUP BY lang")
def op_pivot(spark, sf_dir):
    return t(spark, sf_dir, "documents").groupBy("lang").pivot("source", ["src1", "src2"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT doc_id, kind, value FROM (SELECT doc_id, 'quality' AS kind, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels)")
def op_unpivot(spark, sf_dir):
    return t(spark, sf_dir, "labels").unpivot("doc_id", ["quality", "toxic"], "kind", "value")


@query("SELECT o_orderkey, row_number() OVER w AS n, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS r, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS d, ntile(4) OVER w AS quarter FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)")
def op_window_ranks(spark, sf_dir):
    w, p = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return t(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(w).alias("n"), F.rank().over(p).alias("r"), F.dense_rank().over(p).alias("d"), F.ntile(4).over(w).alias("quarter"))


@query("SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after, first_value(event_id) OVER w AS first, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS moving, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 6) AS running FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_window_frames(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    total = lambda a: F.round(F.sum("value").over(w.rowsBetween(a, 0)), 6)
    return events(spark, sf_dir).select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.first("event_id").over(w).alias("first"), total(-2).alias("moving"), total(Window.unboundedPreceding).alias("running"))


@query("SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC NULLS LAST, c_custkey LIMIT 20 OFFSET 5")
def op_sort_limit(spark, sf_dir):
    return t(spark, sf_dir, "customer").orderBy(F.desc_nulls_last("c_acctbal"), "c_custkey").offset(5).limit(20).select("c_custkey", "c_acctbal")


@query("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS i FROM orders) WHERE i <= 2")
def op_top_per_group(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t(spark, sf_dir, "orders").withColumn("i", F.row_number().over(w)).where("i <= 2").select("o_custkey", "o_orderkey")


@query("SELECT 'union' AS op, count(*) AS n FROM (SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier) UNION ALL SELECT 'distinct', count(*) FROM (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier) UNION ALL SELECT 'intersect', count(*) FROM (SELECT c_custkey FROM customer INTERSECT SELECT o_custkey FROM orders) UNION ALL SELECT 'except', count(*) FROM (SELECT c_custkey FROM customer EXCEPT SELECT o_custkey FROM orders)")
def op_sets(spark, sf_dir):
    k = lambda n, c: t(spark, sf_dir, n).select(F.col(c).cast("long").alias("k"))
    both = k("customer", "c_nationkey").unionAll(k("supplier", "s_nationkey"))
    c, o = k("customer", "c_custkey"), k("orders", "o_custkey")
    out = None
    for name, df in (("union", both), ("distinct", both.distinct()), ("intersect", c.intersect(o)), ("except", c.subtract(o))):
        row = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("op"), "n")
        out = row if out is None else out.unionByName(row)
    return out


@query("SELECT p_partkey, upper(trim(p_name)) AS a, substr(p_name, 2, 4) AS b, regexp_extract(p_name, '([a-z]+)$', 1) AS c, regexp_replace(p_name, '[aeiou]', '', 'g') AS d, split_part(p_name, ' ', 1) AS e, levenshtein(p_name, p_type) AS f, md5(p_name) AS g, translate(p_brand, '#', '-') AS h, lpad(p_partkey::VARCHAR, 8, '0') AS i FROM part")
def op_strings(spark, sf_dir):
    n = F.col("p_name")
    return t(spark, sf_dir, "part").select(
        "p_partkey", F.upper(F.trim(n)).alias("a"), F.substring(n, 2, 4).alias("b"), F.regexp_extract(n, "([a-z]+)$", 1).alias("c"), F.regexp_replace(n, "[aeiou]", "").alias("d"), F.split_part(n, F.lit(" "), F.lit(1)).alias("e"),
        F.levenshtein(n, F.col("p_type")).cast("long").alias("f"), F.md5(n.cast("binary")).alias("g"), F.translate("p_brand", "#", "-").alias("h"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("i"),
    )


@query("SELECT o_orderkey, year(o_orderdate)::INT AS y, date_trunc('month', o_orderdate)::DATE::VARCHAR AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS d, dayofweek(o_orderdate)::INT + 1 AS w FROM orders")
def op_dates(spark, sf_dir):
    d = F.col("o_orderdate")
    return t(spark, sf_dir, "orders").select("o_orderkey", F.year(d).alias("y"), F.trunc(d, "month").cast("string").alias("m"), F.datediff(d, F.lit("1992-01-01")).alias("d"), F.dayofweek(d).alias("w"))


@query("SELECT event_id, round(sqrt(abs(value)), 9) AS a, greatest(user_id % 7, 3) AS b, (user_id & 12) | 1 AS c, xor(user_id, 5) AS d, bit_count(user_id)::INT AS e, round(log2(user_id + 1), 9) AS f FROM events")
def op_math_bits(spark, sf_dir):
    u = F.col("user_id")
    return events(spark, sf_dir).select("event_id", F.round(F.sqrt(F.abs("value")), 9).alias("a"), F.greatest(u % 7, F.lit(3)).alias("b"), u.bitwiseAND(F.lit(12)).bitwiseOR(F.lit(1)).alias("c"), u.bitwiseXOR(F.lit(5)).alias("d"), F.bit_count(u).alias("e"), F.round(F.log2(u + 1), 9).alias("f"))


@query("SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::INT AS positive, round(list_sum(list_transform(embedding[1:8], lambda x: x::DOUBLE * x::DOUBLE)), 6) AS head, len(list_distinct(list_transform(embedding, lambda x: floor(x * 4)::INT)))::INT AS cells FROM embeddings")
def op_arrays(spark, sf_dir):
    e = F.col("embedding")
    return t(spark, sf_dir, "embeddings").select(
        "vec_id", F.size(F.filter(e, lambda x: x > 0)).alias("positive"), F.round(F.aggregate(F.slice(e, 1, 8), F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 6).alias("head"),
        F.size(F.array_distinct(F.transform(e, lambda x: F.floor(x * 4)))).alias("cells"),
    )


@query("SELECT event_type, props->>'k' AS k, count(*) AS n FROM events GROUP BY ALL")
def op_json(spark, sf_dir):
    parsed = F.from_json("props", "struct<k: string>")["k"]
    return events(spark, sf_dir).select("event_type", parsed.alias("k")).groupBy("event_type", "k").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT n_nationkey, n_name || ':' || n_regionkey AS entry FROM nation WHERE n_regionkey > 1")
def op_maps(spark, sf_dir):
    """Attributes as a map, filtered by value and shown as entries."""
    m = F.map_filter(F.map_from_arrays(F.array("n_name"), F.array("n_regionkey")), lambda k, v: v > 1)
    return t(spark, sf_dir, "nation").select("n_nationkey", F.explode(F.map_entries(m)).alias("e")).select("n_nationkey", F.concat_ws(":", "e.key", "e.value").alias("entry"))


@query(
    "WITH e AS (SELECT vec_id, label, list_filter(range(0, len(embedding)), lambda i: embedding[i + 1] > 0) AS pos FROM embeddings) "
    "SELECT l.vec_id AS l_id, round(2.0::DOUBLE * len(list_intersect(l.pos, r.pos)) / nullif(len(l.pos) + len(r.pos), 0), 9) AS sim, l.label = r.label AS same FROM e l JOIN e r ON r.vec_id = l.vec_id + 1"
)
def op_sign_bits(spark, sf_dir):
    """Another perturbation: sign bits of embeddings as 64-bit filters, Dice between neighbours by id, and whether labels agree."""
    e = t(spark, sf_dir, "embeddings")
    word = F.aggregate(F.arrays_zip(F.transform("embedding", lambda x: x > 0).alias("s"), F.sequence(F.lit(0), F.size("embedding") - 1).alias("i")), F.lit(0).cast("long"), lambda a, z: F.when(z["s"], a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), z["i"]))).otherwise(a))
    b = e.select("vec_id", "label", word.alias("w0")).withColumn("ones", F.bit_count("w0"))
    left, right = b.select(F.col("vec_id").alias("l_id"), F.col("label").alias("l_label"), F.col("w0").alias("l_w0"), F.col("ones").alias("l_ones")), b.select((F.col("vec_id") - 1).alias("l_id"), F.col("label").alias("r_label"), F.col("w0").alias("r_w0"), F.col("ones").alias("r_ones"))
    found = compare.record_similarity(left.join(right, "l_id"), 64)
    return found.select("l_id", F.round("sim", 9).alias("sim"), (F.col("l_label") == F.col("r_label")).alias("same"))


@query("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, (length(html) - length(regexp_replace(html, '<[^>]*>', '', 'g')))::INT AS markup FROM pages")
def op_url_html(spark, sf_dir):
    return t(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), (F.length("html") - F.length(F.regexp_replace("html", "<[^>]*>", ""))).alias("markup"))


@query("SELECT date_trunc('hour', ts) AS hour, event_type, count(*) AS n FROM events GROUP BY ALL")
def op_time_windows(spark, sf_dir):
    """Batch twin of the streaming throughput windows."""
    return events(spark, sf_dir).select(F.date_trunc("hour", F.col("ts")).cast("timestamp_ntz").alias("hour"), "event_type").groupBy("hour", "event_type").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT user_id, count(*) AS sessions FROM (SELECT user_id, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 END AS starts FROM events) WHERE starts = 1 GROUP BY user_id")
def op_sessions(spark, sf_dir):
    """Reviewer sessions: gaps of half an hour."""
    e = events(spark, sf_dir).withColumn("at", F.col("ts").cast("timestamp"))
    return e.groupBy("user_id", F.session_window("at", "30 minutes")).agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"))


@query(
    f"SELECT n_nationkey, {linkage_sql.ramp('0.6::DOUBLE + n_nationkey / 100::DOUBLE', '0.7')} AS p, {twin.hmac('n_name', chr(39) + 'key' + chr(39))} AS seed, len({twin.grams('lower(n_name)')})::INT AS grams, "
    "CASE WHEN n_name = upper(n_name) THEN repeat('*', length(n_name)) END AS mask FROM nation"
)
def op_sql_functions(spark, sf_dir):
    """The registered SQL names: lv_ramp, lv_hmac, lv_grams, lv_mask."""
    sqlfuncs.register(spark)
    return spark.sql(
        "SELECT n_nationkey, lv_ramp(0.6D + n_nationkey / 100, 0.7D) AS p, lv_hmac(n_name, 'key') AS seed, size(lv_grams(lower(n_name))) AS grams, lv_mask(n_name, upper(n_name)) AS mask FROM {nation}", nation=t(spark, sf_dir, "nation")
    )


@query(f"SELECT n_nationkey, unnest({twin.grams('lower(n_name)')}) AS gram FROM nation")
def op_table_function(spark, sf_dir):
    """A Python table function beside its built-in form: rows of grams."""
    sqlfuncs.register(spark)
    return spark.sql("SELECT n_nationkey, g.gram FROM {nation}, LATERAL lv_gram_rows(lower(n_name)) g", nation=t(spark, sf_dir, "nation"))


@query()
def op_exchange_files(spark, sf_dir):
    """Encodings written to and read from exchange files in four formats: rows that come back unchanged."""
    from linkveil.queries import linkage

    return exchange.round_trip(linkage.record_filters(spark, sf_dir))


@query()
def op_party_views(spark, sf_dir):
    """Columns that each party may hold of a filter table."""
    from linkveil.queries import linkage

    rows = [(party, exchange.allowed(linkage.record_filters(spark, sf_dir).columns, party)) for party in exchange.PARTIES]
    return spark.createDataFrame(rows, "party string, allowed boolean")


# --- documents as records -------------------------------------------------------------------------------------------------


_DOC = """WITH doc AS (
  SELECT doc_id, CASE WHEN coalesce(try_cast(regexp_extract(source, '(\\d+)', 1) AS INT), 0) % 2 = 0 THEN 'A' ELSE 'B' END AS owner, text,
         string_split(trim(regexp_replace(text, '\\s+', ' ', 'g')), ' ') AS ws FROM documents WHERE text IS NOT NULL
)"""


@query(_DOC + " SELECT a.owner || a.doc_id AS left_id, b.owner || b.doc_id AS right_id FROM doc a JOIN doc b ON a.text = b.text AND a.owner = 'A' AND b.owner = 'B'")
def doc_pairs_exact(spark, sf_dir):
    records = workloads.document_records(t(spark, sf_dir, "documents"))
    a, b = (records.where(F.col("owner") == o).select(F.col("rec_id").alias(n), "digest") for o, n in (("A", "left_id"), ("B", "right_id")))
    return a.join(b, "digest").select("left_id", "right_id")


@query()
def doc_pairs_near(spark, sf_dir):
    """Pairs across owners that share opening or closing words, with their similarity."""
    return workloads.document_linkage(t(spark, sf_dir, "documents"), linkage_sql.KEY).select("left_id", "right_id", "exact", F.round("sim", 9).alias("sim"))


@query()
def doc_linkage_quality(spark, sf_dir):
    """How many of the exact copies and of the other candidates the threshold links."""
    found = workloads.document_linkage(t(spark, sf_dir, "documents"), linkage_sql.KEY)
    return found.groupBy("exact").agg(F.count(F.lit(1)).alias("pairs"), F.count(F.when(F.col("g"), 1)).alias("linked"))
