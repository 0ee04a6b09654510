"""DuckDB SQL that builds what the engine builds, from the same tables: shared WITH-clauses for the oracles."""

from __future__ import annotations

from linkveil.functions import crypto
from linkveil.sources.registry import ATTRIBUTES, GROUPS, MISSING_MN, MISSING_POB, SKEW, VOCABULARIES, Variant


def u(key: str, tag: str) -> str:
    return f"(('0x' || substr(md5(({key})::VARCHAR || '|{tag}'), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"


def _draw(un: str, size: str) -> str:
    return f"least(floor({size} * pow({un}, {SKEW}))::INT, {size} - 1)"


def _edit(value: str, tag: str) -> str:
    at = f"(floor(length({value}) * {u('entity_id', tag + 'p')}) + 1)::INT"
    old = f"(ascii(substr({value}, {at}, 1)) - 97)"
    drawn = f"floor({u('entity_id', tag + 'l')} * 26)::INT"
    new = f"(CASE WHEN {drawn} = {old} THEN ({drawn} + 1) % 26 ELSE {drawn} END)"
    return f"(substr({value}, 1, {at} - 1) || chr({new} + 97) || substr({value}, {at} + 1))"


def registry_ctes(variant: str = "E1M") -> str:
    """WITH-clauses ending in ``registry``."""
    v = Variant(variant)
    langs = ", ".join(f"'{lang}'" for lang, _ in VOCABULARIES.values())
    limit = "CASE lang " + " ".join(f"WHEN '{lang}' THEN {size}" for lang, size in VOCABULARIES.values()) + " END"
    size = {a: f"v_{a.lower()}" for a in VOCABULARIES}
    sizes = ", ".join(f"coalesce((SELECT count(*) FROM vocabulary WHERE lang = '{lang}'), 1)::INT AS {size[a]}" for a, (lang, _) in VOCABULARIES.items())
    k, sh = "entity_id", "shared_key"
    word = lambda lang, column: f"(SELECT any_value(token) FROM vocabulary w WHERE w.lang = '{lang}' AND w.rank = r.{column})"
    zip_of = lambda city, tag: f"(27000 + 5 * {city} + floor(5 * {u(sh, tag)}))::BIGINT::VARCHAR"
    code = lambda key: f"(substr(n_name, 1, 1) || chr(65 + ({key})))"
    order = list(GROUPS)
    keys = ", ".join(f"round(-ln({u(k, 'g' + g)} + 1e-12) / {w}, 9) AS k_{g}" for g, w in GROUPS.items())
    before = {
        g: " + ".join(f"(CASE WHEN k_{x} < k_{g}{f' OR k_{x} = k_{g}' if order.index(x) < order.index(g) else ''} THEN 1 ELSE 0 END)" for x in order if x != g) for g in order
    }
    flags = ", ".join(f"({before[g]}) < n_changes AS ch_{g}" for g in order)
    group = {"CITY": "PLACE", "ZIP": "PLACE"}
    right = ", ".join("YOB" if a == "YOB" else f"CASE WHEN ch_{group.get(a, a)} AND role = 'both' THEN {a}_b ELSE {a} END AS {a}" for a in ATTRIBUTES)
    o = v.overlap
    return f"""
vocabulary AS (
  SELECT * FROM (
    SELECT lang, token, count(*) AS n, row_number() OVER (PARTITION BY lang ORDER BY count(*) DESC, token) - 1 AS rank
    FROM (SELECT lang, unnest(regexp_extract_all(lower(text), '[a-z]{{4,12}}')) AS token FROM documents WHERE lang IN ({langs})) GROUP BY lang, token
  ) WHERE rank < {limit}
), people AS (
  SELECT o_orderkey AS entity_id, c_nationkey, n_name, {sizes},
         CASE WHEN {u('o_orderkey', 'hh')} < 0.5 THEN 'h' || o_custkey ELSE o_orderkey::VARCHAR END AS shared_key
  FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey
), picks AS (
  SELECT *, {_draw(u(k, 'FN'), size['FN'])} AS r_fn, {_draw(u(k, 'MN'), size['MN'])} AS r_mn, {_draw(u(sh, 'LN'), size['LN'])} AS r_ln, {_draw(u(sh, 'CITY'), size['CITY'])} AS r_city,
         {_draw(u(k, 'MNo'), size['MN'])} AS o_mn, {_draw(u(k, 'LNo'), size['LN'])} AS o_ln, floor(greatest(v_city - 1, 1) * {u(k, 'CITYo')})::INT AS o_city
  FROM people
), ranks AS (
  SELECT *, CASE WHEN o_mn = r_mn THEN (o_mn + 1) % v_mn ELSE o_mn END AS b_mn, CASE WHEN o_ln = r_ln THEN (o_ln + 1) % v_ln ELSE o_ln END AS b_ln,
         (r_city + 1 + o_city) % v_city AS b_city FROM picks
), base AS (
  SELECT entity_id, fr.token AS FN, CASE WHEN {u(k, 'MNmiss')} >= {MISSING_MN} THEN es.token END AS MN, en.token AS LN,
         (1930 + floor(75 * {u(k, 'YOB')}))::BIGINT::VARCHAR AS YOB, de.token AS CITY, {zip_of('r_city', 'ZIP')} AS ZIP,
         CASE WHEN {u(k, 'POBmiss')} >= {MISSING_POB} THEN {code('c_nationkey')} END AS POB,
         es2.token AS MN_o, en2.token AS LN_o, de2.token AS CITY_b, {zip_of('b_city', 'ZIPo')} AS ZIP_b,
         {code(f"(c_nationkey + 1 + floor(24 * {u(k, 'POBo')})::INT) % 25")} AS POB_o
  FROM ranks JOIN vocabulary fr ON fr.lang = 'fr' AND fr.rank = r_fn JOIN vocabulary es ON es.lang = 'es' AND es.rank = r_mn
    JOIN vocabulary en ON en.lang = 'en' AND en.rank = r_ln JOIN vocabulary de ON de.lang = 'de' AND de.rank = r_city
    JOIN vocabulary es2 ON es2.lang = 'es' AND es2.rank = b_mn JOIN vocabulary en2 ON en2.lang = 'en' AND en2.rank = b_ln JOIN vocabulary de2 ON de2.lang = 'de' AND de2.rank = b_city
), copies AS (
  SELECT *, CASE WHEN {u(k, 'FNc')} < 0.6 OR length(FN) <= 4 THEN {_edit('FN', 'FN')} ELSE substr(FN, 1, 4) END AS FN_b,
         CASE WHEN MN IS NULL OR {u(k, 'MNc')} >= 0.7 THEN MN_o WHEN {u(k, 'MNc')} < 0.4 THEN substr(MN, 1, 1) END AS MN_b,
         CASE WHEN {u(k, 'LNc')} < 0.4 THEN {_edit('LN', 'LN')} ELSE LN_o END AS LN_b,
         CASE WHEN POB IS NULL OR {u(k, 'POBc')} >= 0.5 THEN POB_o END AS POB_b,
         {v.changes} + CASE WHEN {u(k, 'more1')} < 0.35 THEN 1 ELSE 0 END + CASE WHEN {u(k, 'more2')} < 0.1 THEN 1 ELSE 0 END AS n_changes, {keys},
         CASE WHEN {u(k, 'split')} < {o} / 3::DOUBLE THEN 'both' WHEN {u(k, 'split')} < 1 / 3::DOUBLE THEN 'A' WHEN {u(k, 'split')} < (2 - {o}) / 3::DOUBLE THEN 'B' END AS role
  FROM base
), flagged AS (
  SELECT *, {flags} FROM copies WHERE role IS NOT NULL
), registry AS (
  SELECT 'A' || entity_id AS rec_id, 'A' AS owner, 'base' AS snapshot, entity_id, {', '.join(ATTRIBUTES)} FROM flagged WHERE role <> 'B'
  UNION ALL
  SELECT 'B' || entity_id, 'B', 'changed', entity_id, {right} FROM flagged WHERE role <> 'A'
)"""


def hmac(message: str, key: str) -> str:
    """Hex digest; message and key are SQL expressions."""
    block = f"rpad(CASE WHEN octet_length(encode({key})) > {crypto.BLOCK} THEN sha256({key}) ELSE lower(hex(encode({key}))) END, {2 * crypto.BLOCK}, '0')"
    pad = lambda byte: f"unhex(array_to_string(list_transform(range(0, {crypto.BLOCK}), lambda i: printf('%02x', xor(('0x' || substr({block}, 1 + 2 * i::INT, 2))::INT, {byte}))), ''))"
    return f"sha256({pad(crypto.OUTER)} || unhex(sha256({pad(crypto.INNER)} || encode({message}))))"


def positions(seed: str, h: str, m: int, family: str = "random", most: int = 48) -> str:
    if family == "double":
        part = lambda k: f"('0x' || substr({seed}, {1 + 8 * k}, 8))::BIGINT"
        return f"list_transform(range(0, ({h})::BIGINT), lambda i: (({part(0)} + i * (({part(1)} * 2 + 1) % {m})) % {m})::INT)"
    stream = " || ".join(f"sha256({seed} || '|{k}')" for k in range((most + crypto.SLICES - 1) // crypto.SLICES))
    return f"list_transform(range(0, ({h})::BIGINT), lambda i: (('0x' || substr({stream}, 1 + 4 * i::INT, 4))::BIGINT % {m})::INT)"


def grams(value: str, q: int = 2) -> str:
    """Distinct padded q-grams."""
    padded = f"('{'_' * (q - 1)}' || {value} || '{'_' * (q - 1)}')"
    return f"CASE WHEN length({value}) > 0 THEN list_distinct(list_transform(range(1, length({padded}) - {q} + 2), lambda i: substr({padded}, i::INT, {q}))) END"


def soundex(value: str) -> str:
    """American Soundex as Spark computes it, for values that begin with a letter."""
    code = f"translate(upper({value}), 'AEIOUYHWBFPVCGJKQSXZDTLMNR', '00000099111122222222334556')"
    tail = f"regexp_replace(regexp_replace(substr({code}, 2), '[^0-9]', '', 'g'), '9', '', 'g')"
    joined = f"(substr({code}, 1, 1) || {tail})"
    for d in "123456":
        joined = f"regexp_replace({joined}, '{d}+', '{d}', 'g')"
    return f"rpad(substr(upper({value}), 1, 1) || substr(regexp_replace(substr({joined}, 2), '[09]', '', 'g'), 1, 3), 4, '0')"
