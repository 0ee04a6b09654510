"""DuckDB twins of the record-linkage queries: WITH-clauses from the registry to compared and reviewed pairs."""

from __future__ import annotations

from linkveil.functions import crypto
from linkveil.operators import block, encode
from linkveil.queries import twin
from linkveil.sources.registry import ATTRIBUTES

T = 0.7
#: The owners' key of the queries; a real one is secret.
KEY = "ownersecret"
P = encode.Parameters(KEY)


def with_(*parts: str) -> str:
    return "WITH " + ",\n".join(p.strip().rstrip(",") for p in parts) + "\n"


def registry(variant: str = "E1M") -> str:
    return twin.registry_ctes(variant)


VALUE = "value_of AS (" + " UNION ALL ".join(f"SELECT rec_id, owner, entity_id, '{a}' AS attr, {a} AS value FROM registry" for a in ATTRIBUTES) + ")"
GRAM = f"gram_of AS (SELECT rec_id, owner, attr, unnest({twin.grams('value')}) AS gram FROM value_of WHERE value IS NOT NULL)"
H_OF = "CASE attr " + " ".join(f"WHEN '{a}' THEN {h}" for a, h in P.hashes.items()) + " END"


def record_filters(key: str = f"'{KEY}'", by: str = "gram", name: str = "record_filter", h: int = P.h, m: int = P.m) -> str:
    """Clauses up to (rec_id, owner, pos, ones): sorted distinct positions of all attributes' grams."""
    return f"""
{name}_mask AS (SELECT {by}, {twin.positions(twin.hmac('gram', key), str(h), m, most=h)} AS p FROM (SELECT DISTINCT {by} FROM gram_of)),
{name} AS (
  SELECT rec_id, owner, list_sort(list_distinct(flatten(list(p)))) AS pos, len(list_distinct(flatten(list(p)))) AS ones
  FROM gram_of JOIN {name}_mask USING ({by}) GROUP BY rec_id, owner
)"""


def folded(source: str = "record_filter", name: str = "folded", m: int = P.m) -> str:
    """Positions after exclusive-or'ing the halves: a position stays if just one of the two is set."""
    return f"""
{name} AS (
  SELECT rec_id, owner, list_sort(coalesce(list(b) FILTER (WHERE c = 1), [])) AS pos, count(*) FILTER (WHERE c = 1) AS ones
  FROM (SELECT rec_id, owner, b, count(*) AS c FROM (SELECT rec_id, owner, unnest(pos) % {m // 2} AS b FROM {source}) GROUP BY rec_id, owner, b) GROUP BY rec_id, owner
)"""


ATTRIBUTE_FILTER = f"""
attr_mask AS (SELECT attr, gram, {twin.positions(twin.hmac('gram', f"'{KEY}|' || attr"), H_OF, P.attribute_m)} AS p FROM (SELECT DISTINCT attr, gram FROM gram_of)),
attr_filter AS (
  SELECT rec_id, owner, attr, list_sort(list_distinct(flatten(list(p)))) AS pos, len(list_distinct(flatten(list(p)))) AS ones
  FROM gram_of JOIN attr_mask USING (attr, gram) GROUP BY rec_id, owner, attr
)"""
KEYED = f"""
keyed AS (SELECT rec_id, owner, entity_id, FN || '|' || YOB AS k0, LN || '|' || YOB AS k1, {twin.soundex('FN')} || '|' || {twin.soundex('LN')} AS k2 FROM registry)"""
PAIR = """
pair AS (
  SELECT DISTINCT a.rec_id AS left_id, b.rec_id AS right_id, a.rec_id || '-' || b.rec_id AS pair_id, a.entity_id = b.entity_id AS truth
  FROM keyed a JOIN keyed b ON a.owner = 'A' AND b.owner = 'B' AND (a.k0 = b.k0 OR a.k1 = b.k1 OR a.k2 = b.k2)
)"""
PAIR = """
pair AS (
  SELECT left_id, right_id, left_id || '-' || right_id AS pair_id, truth FROM (""" + " UNION ".join(
    f"SELECT a.rec_id AS left_id, b.rec_id AS right_id, a.entity_id = b.entity_id AS truth FROM keyed a JOIN keyed b ON a.owner = 'A' AND b.owner = 'B' AND a.k{i} = b.k{i}" for i in range(len(block.KEYS))
) + "))"


def compared(source: str = "record_filter", name: str = "cand") -> str:
    return f"""
{name} AS (
  SELECT *, 2.0::DOUBLE * common / (l_ones + r_ones) AS sim FROM (
    SELECT p.*, l.ones AS l_ones, r.ones AS r_ones, len(list_intersect(l.pos, r.pos)) AS common
    FROM pair p JOIN {source} l ON l.rec_id = left_id JOIN {source} r ON r.rec_id = right_id)
)"""


def ramp(sim: str = "sim", t: str = str(T)) -> str:
    return f"round(0.5::DOUBLE * (1 + least(1.0::DOUBLE, abs({sim} - {t}::DOUBLE) / (CASE WHEN {sim} < {t}::DOUBLE THEN 0.05::DOUBLE ELSE 0.1::DOUBLE END))), 9)"


CLASSIFIED = f"classified AS (SELECT *, sim >= {T}::DOUBLE AS g, {ramp()} AS p FROM cand)"
BUCKETED = """
turns AS (
  SELECT *, row_number() OVER (PARTITION BY bucket ORDER BY md5('0|' || pair_id), pair_id) AS turn
  FROM (SELECT *, least(floor(round((p - 0.5::DOUBLE) / ((0.8::DOUBLE - 0.5::DOUBLE) / 10), 6))::INT, 9) AS bucket FROM classified WHERE p < 0.8)
), drawn AS (SELECT * FROM turns ORDER BY turn, bucket LIMIT 100)"""
PAIR_KEY = f"translate(substr({twin.hmac("pair_id || '|0'", "'pair keys 0'")}, 1, 24), '0123456789abcdef', '{crypto.LETTERS}')"
REQUEST = f"""
request AS (
  SELECT 0 AS round, pair_id, {PAIR_KEY} AS pair_key, 'A' AS owner, left_id AS rec_id FROM drawn
  UNION ALL SELECT 0, pair_id, {PAIR_KEY}, 'B', right_id FROM drawn
)"""
PAIR_KEYED = f"""
keyed_gram AS (SELECT r.pair_id, r.pair_key, g.* FROM request r JOIN gram_of g ON g.rec_id = r.rec_id),
pair_filter AS (
  SELECT pair_id, owner, rec_id, attr, list_sort(list_distinct(flatten(list(p)))) AS pos, len(list_distinct(flatten(list(p)))) AS ones
  FROM (SELECT *, {twin.positions(twin.hmac('gram', f"'{KEY}|' || pair_key || '|' || attr"), H_OF, P.attribute_m)} AS p FROM keyed_gram) GROUP BY pair_id, owner, rec_id, attr
)"""
PAIR_SIMS = """
pair_sim AS (
  SELECT d.*, """ + ", ".join(f"s.sim_{a}" for a in ATTRIBUTES) + """ FROM drawn d LEFT JOIN (
    SELECT pair_id, """ + ", ".join(f"max(CASE WHEN attr = '{a}' THEN sim END) AS sim_{a}" for a in ATTRIBUTES) + """
    FROM (SELECT pair_id, attr, 2.0::DOUBLE * len(list_intersect(l.pos, r.pos)) / (l.ones + r.ones) AS sim
          FROM pair_filter l JOIN pair_filter r USING (pair_id, attr) WHERE l.owner = 'A' AND r.owner = 'B') GROUP BY pair_id) s USING (pair_id)
)"""

TO_RECORD = (registry(), VALUE, GRAM, record_filters())
TO_PAIRS = (*TO_RECORD, KEYED, PAIR, compared())
TO_DRAWN = (*TO_PAIRS, CLASSIFIED, BUCKETED)
TO_REQUESTS = (*TO_DRAWN, REQUEST)
TO_SIMS = (*TO_REQUESTS, PAIR_KEYED, PAIR_SIMS)


def asks(mode: str) -> str:
    """The pairs with ask_<attr>."""
    out = []
    for a in ATTRIBUTES:
        low = f"(SELECT avg(sim_{a}) FROM pair_sim)" if mode == "adaptive" else "0.4"
        out.append({"all": "true", "unequal": f"coalesce(sim_{a} < 1, false)"}.get(mode, f"coalesce(sim_{a} < 1 AND sim_{a} >= {low}, false)") + f" AS ask_{a}")
    return f"asked AS (SELECT *, {', '.join(out)} FROM pair_sim)"


REPLY = "reply AS (" + " UNION ALL ".join(
    f"SELECT pair_id, '{o}' AS owner, r.rec_id, " + ", ".join(f"CASE WHEN ask_{a} THEN r.{a} END AS {a}" for a in ATTRIBUTES) + f" FROM asked JOIN registry r ON r.rec_id = {s}_id" for o, s in (("A", "left"), ("B", "right"))
) + ")"


def bit_counts(source: str, by: str, m: int) -> str:
    return f"""
bit_count_of AS (
  SELECT {by}, bit, coalesce(n, 0) AS cnt FROM (SELECT DISTINCT {by} FROM {source}) CROSS JOIN range({m}) AS r(bit)
  LEFT JOIN (SELECT {by}, bit, count(*) AS n FROM (SELECT {by}, unnest(pos) AS bit FROM {source}) GROUP BY {by}, bit) USING ({by}, bit)
)"""


def unevenness(by: str) -> str:
    return f"""
SELECT {by}, round(sum((2 * i - m - 1) * cnt / (m * total)::DOUBLE), 9) AS gini, round(greatest(sum(term), 0), 9) AS js_divergence, round(sqrt(greatest(sum(term), 0)), 9) AS js_distance
FROM (
  SELECT *, CASE WHEN cnt > 0 THEN q * log2(q / ((q + e) / 2)) ELSE 0 END / 2 + e * log2(e / ((q + e) / 2)) / 2 AS term
  FROM (SELECT *, cnt / total::DOUBLE AS q, 1 / m::DOUBLE AS e FROM (
    SELECT *, row_number() OVER (PARTITION BY {by} ORDER BY cnt, bit) AS i, sum(cnt) OVER (PARTITION BY {by}) AS total, count(*) OVER (PARTITION BY {by}) AS m FROM bit_count_of))
) GROUP BY {by}"""
