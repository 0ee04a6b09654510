"""Benchmark decontamination with spaced seeds.

A seed is a run of SPAN words of which a fixed mask reads only some, so that a substituted word under a hole of the
mask does no harm.  The seeds of the test items are hashed and joined with the seeds at every word of every text.
Around each hit the words of item and text are compared along the hit's diagonal; it counts if any stretch of at least
MIN_WORDS words (or the whole of a shorter item) has MIN_IDENTITY equal words.  The masks miss no such stretch: one of over
25 words has another in one of its halves, and of 12 to 25 words with at most a fifth substituted, wherever they stand,
one mask always reads equal words only.

All is one pass over the texts, whatever the benchmark's size.  What a Bloom filter of the items' seeds lets through is
joined with the table of those seeds by a hash join; the filter has FILTER_BITS bits at most, so it is bounded, and a
benchmark that fills it costs more rows in the join, not results.  Only documents with such seeds hand their words on.

Defined cases: a null or empty text has no overlap; null and empty items, and items under ``min_item`` words, match
nothing (a phrase of a few words is no evidence; the parameter may be 1); with no items every document is clean.  Items of
up to SPAN - 1 words are found for certain as a whole without substitutions only.  Each row gets a row, so repeated rows are
repeated; items that share an item_id count as one, items with a null id as none.  Of overlaps the longest counts; ties make
no difference.  Words are lower-cased (A-Z and the Latin-1 capitals).  Texts and items of any length are read whole.  An
empty table gives an empty result.  Other columns of any name do no harm.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkveil.llm import words as W
from linkveil.llm.columns import identity
from linkveil.llm.dropping import drop_documents
from linkveil.session import bounded_batches, durable

SPAN = 12
#: Fixed masks: the words of a span that a seed reads.
MASKS = (
    (0, 1, 2, 3, 4, 5, 6), (0, 1, 2, 4, 5, 6, 7), (0, 1, 2, 3, 4, 7, 8), (0, 1, 3, 6, 8, 9, 10),
    (0, 1, 2, 5, 7, 9, 10), (0, 1, 3, 4, 5, 8, 11), (0, 1, 3, 7, 9, 10, 11),
)
MIN_ITEM = 6
MIN_WORDS = 13
MIN_IDENTITY = 0.8
#: The filter: bits of it by seed, at most, and how many of them a seed sets.
FILTER_BITS = 1 << 28
BITS_A_SEED = 32
_PROBES = np.random.default_rng(41).integers(1, 2**63, 8, dtype=np.uint64) * W.U(2) + W.U(1)
#: Seeds, or items, up to which they go to every task of a join.
BROADCAST_ROWS = 200_000


def seeds(hashes: np.ndarray, first: np.ndarray, mask: tuple[int, ...], salt: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash and start of the seeds of one mask; mask positions are offsets from the start."""
    span = mask[-1] + 1
    n = len(hashes) - span + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
    total = np.full(n, salt, dtype=np.uint64)
    for k in mask:
        total *= W.U(0xD6E8FEB86659FD93)
        total += hashes[k : k + n]
    fits = np.ones(n, dtype=bool)
    for back in range(1, span):
        cut = first[1:] - back
        fits[cut[(cut >= 0) & (cut < n) & (cut >= first[:-1])]] = False
    starts = np.flatnonzero(fits)
    total = total[starts]
    total ^= total >> W.U(29)
    total *= W.U(0xBF58476D1CE4E5B9)
    return total ^ (total >> W.U(32)), starts


def whole_mask(n: int) -> tuple[tuple[int, ...], int]:
    """The mask and salt of items of n words, fewer than SPAN: they are one seed as a whole."""
    return tuple(range(n)), 100 + n


def positions(keys: np.ndarray, probe: int, bits: int) -> np.ndarray:
    """The bit of a filter of 2 ** bits that a probe looks at."""
    return (W.mix(keys * _PROBES[probe]) >> W.U(64 - bits)).astype(np.int64)


@W.tidy
def _items(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for lo, hi, data, offsets in W.slices(batch.column("text")):
            found = W.Words(W.fold_latin(data), offsets)
            hashes, counts = found.hashes(), found.counts()
            raw = hashes.tobytes()
            cut = found.first.tolist()
            words = [raw[8 * a : 8 * b] for a, b in zip(cut[:-1], cut[1:], strict=True)]
            keys, places = [[] for _ in words], [[] for _ in words]
            masks = [(m, 1 + i) for i, m in enumerate(MASKS)] + [whole_mask(n) for n in sorted(set(counts.tolist())) if 0 < n < SPAN]
            for mask, salt in masks:
                k, s = seeds(hashes, found.first, mask, salt)
                of = np.searchsorted(found.first, s, side="right") - 1
                if salt > 100:
                    fits = counts[of] == len(mask)
                    k, s, of = k[fits], s[fits], of[fits]
                for d, key, at in zip(of.tolist(), k.view(np.int64).tolist(), (s - found.first[of]).tolist(), strict=True):
                    keys[d].append(key)
                    places[d].append(at)
            yield pa.RecordBatch.from_arrays(
                [batch.column("item_id").slice(lo, hi - lo), pa.array(counts, pa.int64()), pa.array(words, pa.binary()), pa.array(keys, pa.list_(pa.int64())), pa.array(places, pa.list_(pa.int64()))],
                names=["item_id", "n_item", "item_words", "keys", "places"],
            )


def _setter(bits: int):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = batch.column("key").to_numpy().view(np.uint64)
            at = np.unique(np.concatenate([positions(keys, k, bits) for k in range(len(_PROBES))]))
            yield pa.RecordBatch.from_arrays([pa.array(at >> 6), pa.array((W.U(1) << (at & 63).astype(np.uint64)).view(np.int64))], names=["at", "word"])

    return run


def bloom(item_seeds: DataFrame, n: int) -> tuple[int, np.ndarray]:
    """(bits, words): a filter that passes every seed of the items; FILTER_BITS bits at most reach the driver."""
    bits = min(FILTER_BITS.bit_length() - 1, max(16, math.ceil(math.log2(BITS_A_SEED * max(1, n)))))
    found = item_seeds.select("key").mapInArrow(_setter(bits), "at long, word long").groupBy("at").agg(F.bit_or("word").alias("word")).toArrow()
    words = np.zeros(1 << (bits - 6), dtype=np.uint64)
    words[found.column("at").to_numpy()] = found.column("word").to_numpy().view(np.uint64)
    return bits, words


def _searcher(broadcast):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        masks, bits, words = broadcast.value
        for batch in batches:
            for lo, hi, data, offsets in W.slices(batch.column("text")):
                found = W.Words(W.fold_latin(data), offsets)
                hashes, first = found.hashes(), found.first
                keys, starts = [np.zeros(0, dtype=np.uint64)], [np.zeros(0, dtype=np.int64)]
                for mask, salt in masks:
                    k, s = seeds(hashes, first, mask, salt)
                    for probe in range(len(_PROBES)):
                        at = positions(k, probe, bits)
                        hit = (words[at >> 6] >> (at & 63).astype(np.uint64)) & W.U(1) > 0
                        k, s = k[hit], s[hit]
                    keys.append(k)
                    starts.append(s)
                keys, starts = np.concatenate(keys), np.concatenate(starts)
                of = np.searchsorted(first, starts, side="right") - 1
                order = np.argsort(of, kind="stable")
                keys, starts, of = keys[order], starts[order], of[order]
                cut = pa.array(np.searchsorted(of, np.arange(hi - lo + 1)).astype(np.int32))
                raw, spans = hashes.tobytes(), first.tolist()
                some = np.diff(np.searchsorted(of, np.arange(hi - lo + 1))) > 0
                mine = [raw[8 * a : 8 * b] if hit else None for a, b, hit in zip(spans[:-1], spans[1:], some.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [
                        *(batch.column(c).slice(lo, hi - lo) for c in ("doc_id", "id", "mark")), pa.array(found.counts(), pa.int64()), pa.array(mine, pa.binary()),
                        pa.ListArray.from_arrays(cut, pa.array(keys.view(np.int64))), pa.ListArray.from_arrays(cut, pa.array(starts - first[of])),
                    ],
                    names=["doc_id", "id", "mark", "n_words", "words", "keys", "starts"],
                )

    return run


def longest_stretch(same: np.ndarray, n_item: int) -> int:
    """Words of the longest good stretch of a diagonal of an item of ``n_item`` words; 0 if there is none."""
    # whole numbers: a stretch has MIN_IDENTITY if its sum isn't negative
    part = round(100 * MIN_IDENTITY)
    sums = np.concatenate(([0], np.cumsum(np.where(same, 100 - part, -part))))
    begin = np.searchsorted(-np.minimum.accumulate(sums), -sums)  # the first place with a sum as small
    length = int((np.arange(len(sums)) - begin).max())
    return length if length >= min(MIN_WORDS, n_item) else 0


@W.tidy
def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found = []
        for x, y, n in zip(batch.column("own"), batch.column("others"), batch.column("n_item").to_pylist(), strict=True):
            x, y = np.frombuffer(x.as_buffer(), dtype=np.uint64), np.frombuffer(y.as_buffer(), dtype=np.uint64)
            found.append(longest_stretch(x == y, n))
        yield pa.RecordBatch.from_arrays([batch.column("row"), batch.column("item_id"), pa.array(found, pa.int64())], names=["row", "item_id", "overlap"])


def _sent(rows: DataFrame, n: int) -> DataFrame:
    return F.broadcast(rows) if n <= BROADCAST_ROWS else rows


def search(docs: DataFrame, items: DataFrame, min_item: int = MIN_ITEM) -> DataFrame:
    """doc_id, id and mark (the row's identity), n_words, item_ids (sorted), overlap (words of the longest stretch): one row a row."""
    bounded_batches(docs.sparkSession)
    texts = items.select(F.col("item_id").cast("long"), F.col("text").cast("string")).where("item_id IS NOT NULL AND text IS NOT NULL")
    read = texts.mapInArrow(_items, "item_id long, n_item long, item_words binary, keys array<long>, places array<long>")
    read = durable(read.where(F.col("n_item") >= max(1, min_item)).withColumn("item", F.monotonically_increasing_id()))
    item_seeds = durable(read.select("item", F.explode(F.arrays_zip("keys", "places")).alias("s")).select("item", F.col("s.keys").alias("key"), F.col("s.places").alias("place")))
    n_items, n_seeds = read.count(), item_seeds.count()
    short = sorted(r["n_item"] for r in read.where(F.col("n_item") < SPAN).select("n_item").distinct().collect())  # SPAN - 1 at most
    masks = [(m, 1 + i) for i, m in enumerate(MASKS)] + [whole_mask(n) for n in short]
    sent = docs.sparkSession.sparkContext.broadcast((masks if n_items else [], *bloom(item_seeds, n_seeds)))

    key, mark = identity()
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), key.alias("id"), mark.alias("mark"), F.col("text").cast("string").alias("text")).mapInArrow(
        _searcher(sent), "doc_id long, id long, mark long, n_words long, words binary, keys array<long>, starts array<long>"
    )
    rows = durable(rows.withColumn("row", F.monotonically_increasing_id()))
    hits = rows.where("words IS NOT NULL").select("row", F.explode(F.arrays_zip("keys", "starts")).alias("s")).select("row", F.col("s.keys").alias("key"), F.col("s.starts").alias("start"))
    pairs = hits.join(_sent(item_seeds, n_seeds), "key").select("row", "item", (F.col("start") - F.col("place")).alias("shift")).distinct()
    both = pairs.join(_sent(read.select("item", "item_id", "n_item", "item_words"), n_items), "item").join(rows.select("row", "n_words", "words"), "row")
    lo, hi = F.greatest(F.lit(0), -F.col("shift")), F.least(F.col("n_item"), F.col("n_words") - F.col("shift"))
    part = lambda words, at: F.substr(words, (8 * at + 1).cast("int"), (8 * (hi - lo)).cast("int"))
    diagonals = both.select("row", "item_id", "n_item", part(F.col("words"), lo + F.col("shift")).alias("own"), part(F.col("item_words"), lo).alias("others"))
    good = diagonals.mapInArrow(_verify, "row long, item_id long, overlap long").where("overlap > 0")
    found = good.groupBy("row").agg(F.sort_array(F.collect_set("item_id")).alias("item_ids"), F.max("overlap").alias("overlap"))
    return rows.select("row", "doc_id", "id", "mark", "n_words").join(found, "row", "left").select(
        "doc_id", "id", "mark", "n_words", F.coalesce("item_ids", F.array().cast("array<long>")).alias("item_ids"), F.coalesce("overlap", F.lit(0)).alias("overlap")
    )


def find(docs: DataFrame, items: DataFrame, min_item: int = MIN_ITEM) -> DataFrame:
    """doc_id, n_words, item_ids (sorted), overlap (words of the longest stretch), contaminated: one row a row."""
    return search(docs, items, min_item).drop("id", "mark").withColumn("contaminated", F.size("item_ids") > 0)


def clean(docs: DataFrame, items: DataFrame, min_item: int = MIN_ITEM) -> DataFrame:
    """The documents without an overlap, with the columns of ``docs``."""
    return drop_documents(docs, search(docs, items, min_item).where(F.size("item_ids") > 0))
