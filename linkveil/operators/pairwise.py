"""Record filters and their comparison by numpy: each record is encoded where it lies, and blocks are compared whole in their task.

One shuffle deals out the records of both sides, once a blocking key, with their filters.  It is all that is written: pairs are
made, compared and, where only their numbers are asked for, counted inside the task.  Of many records a part of the rows is
dealt out at a time (``passes``).
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator, Mapping, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from linkveil.functions import bits, crypto
from linkveil.operators import block, encode
from linkveil.session import durable, sent

#: Masks that a worker remembers, of grams and of values each.
REMEMBERED = 50_000
#: Rows of a task, about, and pairs that it compares at once.
ROWS_A_TASK, PAIRS_AT_ONCE = 60_000, 400_000
#: Records from which on they are dealt to many tasks before they are encoded, and compared in passes.
MANY = 400_000
#: Bytes of rows that a pass shuffles, about; ROW are those beside the filter.
BYTES_A_PASS, ROW = 600_000_000, 64
_FIRST = np.iinfo(np.int64).min


def gram_bits(gram: str, inner: bytes, outer: bytes, h: int, m: int, family: str) -> int:
    """``encode.gram_masks`` of one gram as a number: bit i is position i."""
    seed = hashlib.sha256(outer + hashlib.sha256(inner + gram.encode()).digest()).hexdigest()
    if family == "double":
        a, b = int(seed[:8], 16), (int(seed[8:16], 16) * 2 + 1) % m
        places = [(a + i * b) % m for i in range(h)]
    else:
        blocks = (h + crypto.SLICES - 1) // crypto.SLICES
        stream = "".join(hashlib.sha256(f"{seed}|{k}".encode()).hexdigest() for k in range(blocks))
        places = [int(stream[4 * i : 4 * i + 4], 16) % m for i in range(h)]
    out = 0
    for x in places:
        out |= 1 << x
    return out


def _masker(p: encode.Parameters, key: str, h: int, m: int):
    """The filter's bytes of a value, by a worker that remembers grams and values."""
    inner, outer = crypto.pads(key)
    pad, grams, values = "_" * (p.q - 1), {}, {}

    def mask(value: str) -> bytes:
        if value not in values:
            total, padded = 0, f"{pad}{value}{pad}"
            for g in {padded[i : i + p.q] for i in range(len(padded) - p.q + 1)} if value else ():
                if g not in grams:
                    if len(grams) >= REMEMBERED:
                        grams.clear()
                    grams[g] = gram_bits(g, inner, outer, h, m, p.family)
                total |= grams[g]
            if len(values) >= REMEMBERED:
                values.clear()
            values[value] = total.to_bytes(m // 8, "little")
        return values[value]

    return mask


def _words(column: pa.Array, mask, m: int) -> np.ndarray:
    """The filters' words of a column of values."""
    coded = column.dictionary_encode()
    known = coded.dictionary.to_pylist()
    table = np.frombuffer(b"".join([mask(v) for v in known] + [bytes(m // 8)]), dtype="<u8").reshape(-1, m // 64)
    return table[coded.indices.fill_null(len(known)).to_numpy(zero_copy_only=False)]


def _with_words(batch: pa.RecordBatch, words: np.ndarray) -> pa.RecordBatch:
    columns = [pa.array(np.ascontiguousarray(words[:, i]).view(np.int64)) for i in range(words.shape[1])]
    ones = np.bitwise_count(words).sum(axis=1, dtype=np.int32)
    return pa.RecordBatch.from_arrays([*batch.columns, *columns, pa.array(ones)], names=[*batch.schema.names, *(f"w{i}" for i in range(len(columns))), "ones"])


def _encoder(p: encode.Parameters, fold: bool):
    n_words = p.m // 64

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mask = _masker(p, p.key, p.h, p.m)
        for batch in batches:
            words = np.zeros((batch.num_rows, n_words), dtype="<u8")
            for a in p.attributes:
                words |= _words(batch.column(a), mask, p.m)
            some = words.any(axis=1)  # records without any value have no filter
            if fold:
                words = words[:, : n_words // 2] ^ words[:, n_words // 2 :]
            out = _with_words(batch, words)
            yield out if some.all() else out.filter(pa.array(some))

    return run


def _attribute_encoder(p: encode.Parameters):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        masks = {a: _masker(p, crypto.SEPARATOR.join((crypto.check_key(p.key), a)), p.hashes[a], p.attribute_m) for a in p.attributes}
        for batch in batches:
            yield _with_words(batch, np.concatenate([_words(batch.column(a), masks[a], p.attribute_m) for a in p.attributes], axis=1))

    return run


def _encoded(records: DataFrame, p: encode.Parameters, m: int, encoder, keep: Sequence[str]) -> DataFrame:
    source = records.select("rec_id", "owner", "entity_id", *keep, *(F.col(a).cast("string").alias(a) for a in p.attributes))
    added = [T.StructField(w, T.LongType()) for w in bits.names(m)] + [T.StructField("ones", T.IntegerType())]
    return source.mapInArrow(encoder, T.StructType(source.schema.fields + added))


def _sampler(p: encode.Parameters, plan: Sequence[tuple[int, str, int]], m: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        masks = {}
        for a in p.attributes:
            whole, known, places = _masker(p, crypto.SEPARATOR.join((crypto.check_key(p.key), a)), p.hashes[a], p.attribute_m), {}, [(place, bit) for place, x, bit in plan if x == a]

            def mask(value: str, whole=whole, known=known, places=places) -> bytes:
                if value not in known:
                    if len(known) >= REMEMBERED:
                        known.clear()
                    bits_, out = int.from_bytes(whole(value), "little"), 0
                    for place, bit in places:
                        out |= (bits_ >> bit & 1) << place
                    known[value] = out.to_bytes(m // 8, "little")
                return known[value]

            masks[a] = mask
        for batch in batches:
            words = np.zeros((batch.num_rows, m // 64), dtype="<u8")
            for a in p.attributes:
                words |= _words(batch.column(a), masks[a], m)
            yield _with_words(batch, words)

    return run


def sampled_filters(records: DataFrame, p: encode.Parameters, plan: Sequence[tuple[int, str, int]], m: int) -> DataFrame:
    """``encode.sampled_filter`` beside rec_id, owner, entity_id and the attributes: a bit belongs to one attribute, so a value has its bits
    wherever it occurs, and no row is moved."""
    return _encoded(records, p, m, _sampler(p, plan, m), [])


def attribute_bits(p: encode.Parameters) -> int:
    """Bits of all attributes' filters side by side."""
    return p.attribute_m * len(p.attributes)


def attribute_filters(records: DataFrame, p: encode.Parameters, keep: Sequence[str] = ()) -> DataFrame:
    """``encode.attribute_filters`` side by side: one row a record, with an empty filter for a missing value."""
    return _encoded(records, p, attribute_bits(p), _attribute_encoder(p), keep)


def filters(records: DataFrame, p: encode.Parameters, fold: bool = False, keep: Sequence[str] = ()) -> DataFrame:
    """``encode.record_filter`` (folded once by exclusive or, if asked for) of records that have one row each, beside rec_id, owner,
    entity_id and the attributes: no row is moved, and no gram is hashed twice by a worker that remembers it."""
    return _encoded(records, p, p.m // 2 if fold else p.m, _encoder(p, fold), keep)


def passes(n_records: int, m: int, many: int | None = None, n_keys: int = len(block.KEYS)) -> list[tuple[int, int, int] | None]:
    """Which rows are dealt out at a time: all (None), or of many records a part of one key's blocks (key_no, part, parts), so that
    a shuffle has about BYTES_A_PASS.  All parts together are the whole blocking: a block lies in one part."""
    if n_records < (MANY if many is None else many):
        return [None]
    parts = max(1, math.ceil(n_records * (m // 8 + ROW) / BYTES_A_PASS))
    return [(key_no, part, parts) for key_no in range(n_keys) for part in range(parts)]


def of_pass(keyed: DataFrame, one: tuple[int, int, int] | None) -> DataFrame:
    """Records (keys, ...) that have rows in a pass; others needn't be encoded for it."""
    if one is None:
        return keyed
    key_no, part, parts = one
    digest = F.get("keys", F.lit(key_no))
    return keyed.where(digest.isNotNull() & (F.pmod(F.xxhash64(digest), F.lit(parts)) == part))


def large_blocks(counted: DataFrame, per_task: int = block.PAIRS_A_TASK) -> DataFrame:
    """(key_no, digest, parts) of blocks with over ``per_task`` pairs, among records (owner, keys)."""
    sides = [counted.where(F.col("owner") == o).select(F.posexplode(F.transform("keys", block._short)).alias("key_no", "digest")).where("digest IS NOT NULL") for o in "AB"]
    parts = F.least(F.lit(block.PARTS), F.ceil(F.col("pairs") / per_task)).cast("int")
    return durable(block._sizes(*sides).where(F.col("pairs") > per_task).select("key_no", "digest", parts.alias("parts")))


def dealt(keyed: DataFrame, large: DataFrame, m: int, n_records: int, key_no: int | None = None, n_keys: int = len(block.KEYS)) -> DataFrame:
    """Rows of the blocking, one a record and key, dealt out by block: both sides of a block, or of a part of a large one, are in one
    partition.  ``keyed``: rec_id, owner, entity_id, keys, words; ``large``: its large blocks; ``key_no``: only that key's rows.

    A row has 128 bits of its key and 64 of those before it."""
    guarded = F.when(F.size("keys") > n_keys, F.raise_error(F.lit(f"records have more than {n_keys} keys"))).otherwise(F.transform("keys", block._short))
    words, is_left = bits.names(m), F.col("owner") == "A"
    each = keyed.where("owner IN ('A', 'B')").select(is_left.alias("is_left"), "rec_id", "entity_id", *words, guarded.alias("short")).select("*", F.posexplode("short").alias("key_no", "digest")).where("digest IS NOT NULL")
    before = [F.when(F.col("key_no") > i, F.when(F.get("short", F.lit(i)).isNotNull(), F.xxhash64(F.get("short", F.lit(i))))).alias(f"before{i}") for i in range(n_keys - 1)]
    rows = each.select("key_no", "digest", *before, "is_left", "rec_id", "entity_id", *words)
    if large.isEmpty():
        rows = rows.withColumn("part", F.lit(0))
    else:
        mine = F.array(F.pmod(F.xxhash64("rec_id"), F.col("parts")).cast("int"))
        share = F.when(F.col("parts").isNull(), F.array(F.lit(0))).when(F.col("is_left"), mine).otherwise(F.sequence(F.lit(0), F.col("parts") - 1))
        rows = rows.join(sent(large), ["key_no", "digest"], "left").withColumn("part", F.explode(share)).drop("parts")
    if key_no is not None:
        rows = rows.where(F.col("key_no") == key_no)
    n_rows = n_records * (n_keys if key_no is None else 1)
    usual = int(keyed.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(max(1, min(usual, n_rows // 2000), math.ceil(n_rows / ROWS_A_TASK)), "key_no", "digest", "part")


_TALLY = "common int, ones int, truth boolean, n long"
_PAIRS = "left_id string, right_id string, l_ones int, r_ones int, common int, truth boolean"


def _blocks(batches: Iterator[pa.RecordBatch], m: int, n_before: int):
    """The task's rows by block and side, and chunks (a, b) of rows that are pairs."""
    table = pa.Table.from_batches(batches).combine_chunks() if (batches := [x for x in batches if x.num_rows]) else None
    if table is None:
        return None
    column = lambda name: table.column(name).combine_chunks()
    digest = column("digest").cast(pa.binary(16))
    high, low = np.frombuffer(digest.buffers()[1], dtype="<u8", count=2 * table.num_rows, offset=16 * digest.offset).reshape(-1, 2).T
    key, part, right = column("key_no").to_numpy(), column("part").to_numpy(), ~column("is_left").to_numpy(zero_copy_only=False)
    order = np.lexsort((right, part, low, high, key))
    key, part, right, high, low = (x[order] for x in (key, part, right, high, low))
    words = [column(w).to_numpy()[order].view(np.uint64) for w in bits.names(m)]
    ones = sum(np.bitwise_count(w).astype(np.int32) for w in words)
    before = []
    for i in range(n_before):
        x = column(f"before{i}")
        if x.null_count < len(x):  # null from the pair's own key on; nulls of the two sides are never equal
            before.append(np.where(x.is_valid().to_numpy(zero_copy_only=False)[order], x.fill_null(0).to_numpy()[order], _FIRST + right))
    new = np.ones(len(order), dtype=bool)
    new[1:] = (key[1:] != key[:-1]) | (part[1:] != part[:-1]) | (high[1:] != high[:-1]) | (low[1:] != low[:-1])
    start = np.flatnonzero(new)
    size = np.diff(np.append(start, len(order)))
    n_right = np.add.reduceat(right.astype(np.int64), start)
    n_left = size - n_right
    some = (n_left > 0) & (n_right > 0)
    start, n_left, n_right = start[some], n_left[some], n_right[some]
    size = n_left * n_right
    ends = np.cumsum(size)

    def chunks():
        total = int(ends[-1]) if len(ends) else 0
        for lo in range(0, total, PAIRS_AT_ONCE):
            hi = min(lo + PAIRS_AT_ONCE, total)
            some = np.arange(np.searchsorted(ends, lo, side="right"), np.searchsorted(ends, hi - 1, side="right") + 1)
            i = np.repeat(some, np.minimum(ends[some], hi) - np.maximum(ends[some] - size[some], lo))
            rest, n = np.arange(lo, hi) - (ends - size)[i], n_right[i]
            of_left = rest // n
            a, b = start[i] + of_left, start[i] + n_left[i] + rest - of_left * n
            for value in before:
                other = value[a] != value[b]
                if not other.all():
                    a, b = a[other], b[other]
            yield a, b

    return order, table, words, ones, chunks


def _common(words: Sequence[np.ndarray], a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Bits that the rows of each pair share."""
    common = np.zeros(len(a), dtype=np.int32)
    for w in words:
        common += np.bitwise_count(w[a] & w[b])
    return common


def _dice(common: np.ndarray, both: np.ndarray) -> np.ndarray:
    """``compare.dice``, with NaN for two empty filters."""
    return np.divide(2.0 * common, both, out=np.full(len(both), np.nan), where=both > 0)


def _counter(m: int, n_before: int):
    def run(batches):
        found = _blocks(batches, m, n_before)
        if found is None:
            return
        order, table, words, ones, chunks = found
        entity = table.column("entity_id").combine_chunks().to_numpy()[order]
        width, total = 2 * m + 1, np.zeros(0, dtype=np.int64)
        for a, b in chunks():
            common = _common(words, a, b)
            code = (common.astype(np.int64) * width + ones[a] + ones[b]) * 2 + (entity[a] == entity[b])
            n = np.bincount(code, minlength=len(total))
            n[: len(total)] += total
            total = n
        code = np.flatnonzero(total)
        arrays = [pa.array((code // 2 // width).astype(np.int32)), pa.array((code // 2 % width).astype(np.int32)), pa.array(code % 2 == 1), pa.array(total[code])]
        yield pa.RecordBatch.from_arrays(arrays, names=["common", "ones", "truth", "n"])

    return run


def _lister(m: int, n_before: int, lo: float | None, hi: float | None, floor: float | None):
    def run(batches):
        found = _blocks(batches, m, n_before)
        if found is None:
            return
        order, table, words, ones, chunks = found
        entity, ids = table.column("entity_id").combine_chunks().to_numpy()[order], table.column("rec_id").combine_chunks().take(pa.array(order))
        for a, b in chunks():
            common = _common(words, a, b)
            sim = _dice(common, ones[a] + ones[b])
            keep = np.ones(len(a), dtype=bool)
            for inside in ([sim > lo] if lo is not None else []) + ([sim < hi] if hi is not None else []) + ([sim >= floor] if floor is not None else []):
                keep &= inside
            if not keep.all():
                a, b, common = a[keep], b[keep], common[keep]
            for s in range(0, len(a), 50_000):
                x, y = a[s : s + 50_000], b[s : s + 50_000]
                arrays = [ids.take(pa.array(x)), ids.take(pa.array(y)), pa.array(ones[x]), pa.array(ones[y]), pa.array(common[s : s + 50_000]), pa.array(entity[x] == entity[y])]
                yield pa.RecordBatch.from_arrays(arrays, names=["left_id", "right_id", "l_ones", "r_ones", "common", "truth"])

    return run


def _node_counter(m: int, n_before: int, floor: float):
    def run(batches):
        found = _blocks(batches, m, n_before)
        if found is None:
            return
        order, table, words, ones, chunks = found
        n = np.zeros(len(order), dtype=np.int64)
        for a, b in chunks():
            keep = _dice(_common(words, a, b), ones[a] + ones[b]) >= floor
            n += np.bincount(a[keep], minlength=len(n)) + np.bincount(b[keep], minlength=len(n))
        some = np.flatnonzero(n)
        rows = pa.array(order[some])
        yield pa.RecordBatch.from_arrays([table.column(c).combine_chunks().take(rows) for c in ("is_left", "rec_id")] + [pa.array(n[some])], names=["is_left", "rec_id", "n"])

    return run


def _score_counter(p: encode.Parameters, weights: Mapping[str, float], n_before: int, step: float, border: float):
    m, per = attribute_bits(p), p.attribute_m // 64
    places = [(p.attributes.index(a) * per, w) for a, w in weights.items()]

    def run(batches):
        found = _blocks(batches, m, n_before)
        if found is None:
            return
        order, table, words, _, chunks = found
        entity = table.column("entity_id").combine_chunks().to_numpy()[order]
        single = [sum(np.bitwise_count(w).astype(np.int32) for w in words[k : k + per]) for k, _ in places]
        bins, rest = np.zeros((2, round(1 / step) + 2), dtype=np.int64), {}
        for a, b in chunks():
            total, weight = np.zeros(len(a)), np.zeros(len(a))
            for ones, (k, w) in zip(single, places, strict=True):  # in the order of ``compare.weighted_mean``, so sums are the same
                x, y = ones[a], ones[b]
                both = (x > 0) & (y > 0)
                total += np.where(both, _dice(_common(words[k : k + per], a, b), x + y) * w, 0.0)
                weight += np.where(both, w, 0.0)
            sim, true = np.divide(total, weight, out=np.full(len(a), np.nan), where=weight > 0), entity[a] == entity[b]
            value = sim / step
            whole = np.floor(value)
            inside = (value - whole > border) & (value - whole < 1 - border)
            at = whole[inside].astype(np.int64)
            for t in (False, True):
                bins[int(t)] += np.bincount(at[true[inside] == t], minlength=bins.shape[1])
                for s, n in zip(*np.unique(sim[~inside & (true == t)], return_counts=True), strict=True):
                    key = (None if np.isnan(s) else float(s), t)
                    rest[key] = rest.get(key, 0) + int(n)
        truth, at = np.nonzero(bins)
        out = [((k + 0.5) * step, bool(t), int(bins[t, k])) for t, k in zip(truth.tolist(), at.tolist(), strict=True)] + [(*key, n) for key, n in rest.items()]
        sim, truth, n = zip(*out, strict=True) if out else ((), (), ())
        yield pa.RecordBatch.from_arrays([pa.array(sim, pa.float64()), pa.array(truth, pa.bool_()), pa.array(n, pa.int64())], names=["sim", "truth", "n"])

    return run


def _score_lister(p: encode.Parameters, weights: Mapping[str, float], n_before: int, single: bool, sims: bool):
    m, per = attribute_bits(p), p.attribute_m // 64
    factors = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5)]

    def run(batches):
        found = _blocks(batches, m, n_before)
        if found is None:
            return
        order, table, words, _, chunks = found
        entity, ids = table.column("entity_id").combine_chunks().to_numpy()[order], table.column("rec_id").combine_chunks().take(pa.array(order))
        parts = {a: words[k * per : (k + 1) * per] for k, a in enumerate(p.attributes)}
        ones = {a: sum(np.bitwise_count(w).astype(np.int32) for w in part) for a, part in parts.items()}
        mixed = {}
        if single:
            for name, part in parts.items():  # equal filters have equal numbers
                x = np.zeros(len(order), dtype=np.uint64)
                for j, w in enumerate(part):
                    x = (x ^ w) * factors[j % 4]
                    x ^= x >> np.uint64(29)
                mixed[name] = x
        for a, b in chunks():
            differ = np.zeros(len(a), dtype=np.int8)
            for x in mixed.values():
                differ += x[a] != x[b]
                keep = differ < 2
                a, b, differ = a[keep], b[keep], differ[keep]
            for s in range(0, len(a), 50_000):
                x, y = a[s : s + 50_000], b[s : s + 50_000]
                found, has, total, weight = {}, {}, np.zeros(len(x)), np.zeros(len(x))
                for name, part in parts.items():
                    has[name] = (ones[name][x] > 0) & (ones[name][y] > 0)
                    found[name] = _dice(_common(part, x, y), ones[name][x] + ones[name][y])
                for name, w in weights.items():  # in the order of ``compare.weighted_mean``, so sums are the same
                    total += np.where(has[name], found[name] * w, 0.0)
                    weight += np.where(has[name], w, 0.0)
                columns = {"left_id": ids.take(pa.array(x)), "right_id": ids.take(pa.array(y)), "truth": pa.array(entity[x] == entity[y])}
                columns |= {f"sim_{name}": pa.array(found[name], mask=~has[name]) for name in p.attributes} if sims else {}
                columns["sim"] = pa.array(np.divide(total, weight, out=np.zeros(len(x)), where=weight > 0), mask=weight == 0)
                batch = pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))
                if single:
                    batch = batch.filter(pa.array((sum((found[name] < 1).astype(np.int8) for name in parts) == 1) & np.all(list(has.values()), axis=0)))
                if batch.num_rows:
                    yield batch

    return run


def scores(rows: DataFrame, p: encode.Parameters, weights: Mapping[str, float], single: bool = False, sims: bool = True, n_keys: int = len(block.KEYS)) -> DataFrame:
    """(left_id, right_id, truth, sim_<attr>, sim): the attributes' similarities and their weighted mean, of all pairs of ``dealt`` rows of
    ``attribute_filters``.  With ``single`` only pairs that have all values and differ in one attribute are handed on; ``sims`` may be left out."""
    each = "".join(f"sim_{a} double, " for a in p.attributes) if sims else ""
    return rows.mapInArrow(_score_lister(p, weights, n_keys - 1, single, sims), f"left_id string, right_id string, truth boolean, {each}sim double")


def nodes(rows: DataFrame, m: int, floor: float, n_keys: int = len(block.KEYS)) -> DataFrame:
    """(is_left, rec_id, n): records that ``dealt`` rows pair with a similarity of at least ``floor``, and in how many pairs."""
    return rows.mapInArrow(_node_counter(m, n_keys - 1, floor), "is_left boolean, rec_id string, n long")


def score_tally(rows: DataFrame, p: encode.Parameters, weights: Mapping[str, float], step: float, border: float, n_keys: int = len(block.KEYS)) -> DataFrame:
    """(sim, truth, n): numbers of pairs by the weighted mean of their attributes' similarities, from ``dealt`` rows of
    ``attribute_filters``.  Similarities by over ``border`` of a bin beside the bins' borders stand as the middle of their bin."""
    return rows.mapInArrow(_score_counter(p, weights, n_keys - 1, step, border), "sim double, truth boolean, n long")


def tally(rows: DataFrame, m: int, n_keys: int = len(block.KEYS)) -> DataFrame:
    """(common, ones, truth, n): numbers of pairs by the bits that they share and the sum of both filters' bits, from ``dealt`` rows."""
    return rows.mapInArrow(_counter(m, n_keys - 1), _TALLY)


def pairs(rows: DataFrame, m: int, lo: float | None = None, hi: float | None = None, floor: float | None = None, n_keys: int = len(block.KEYS)) -> DataFrame:
    """(left_id, right_id, l_ones, r_ones, common, truth) of ``dealt`` rows; with limits those with lo < sim < hi, or sim >= floor."""
    return rows.mapInArrow(_lister(m, n_keys - 1, lo, hi, floor), _PAIRS)
