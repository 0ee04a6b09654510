"""Quality rules at host level.

Each document is measured by word rules.  Failures are counted by host (the ``source`` of a document), each host's
failure rate is shrunk towards the rates of all hosts with a beta prior fitted by moments, and documents of a host
whose shrunk rate is over a limit go as well.

Defined cases: a null text has no words, so it fails; an empty text likewise.  A null host has no verdict: its
documents are judged one by one.  An empty table gives an empty result.  Repeated rows and ids are measured each on
their own.  A host whose rate is just the limit stays.  Very long texts are read whole.  Further columns of the input stay out of ``measure`` and pass through ``apply`` unchanged.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkveil.llm import words as W
from linkveil.llm.columns import plain, restored
from linkveil.llm.dropping import drop_keys
from linkveil.session import bounded_batches, durable

WINDOW = 5
SYMBOLS = np.zeros(256, dtype=bool)
SYMBOLS[list(b"#*$%&|<>")] = True
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
SALTS = 32


def measures(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One column for each of MEASURES, one row for each document of a slice."""
    words = W.Words(data, offsets)
    inside = ~W.SPACE[data]
    out = np.zeros((len(offsets) - 1, len(MEASURES)), dtype=np.int64)
    out[:, 0] = words.counts()
    out[:, 1] = W.per_document(inside & ((data & 0xC0) != 0x80), offsets)
    out[:, 2] = W.per_document(SYMBOLS[data], offsets)
    out[:, 3] = repeated_lines(data, offsets, inside)
    out[:, 4] = W.per_document(repeated_words(words), words.first)
    return out


def repeated_lines(data: np.ndarray, offsets: np.ndarray, inside: np.ndarray) -> np.ndarray:
    """Lines with a word that equal an earlier line of their document."""
    ends = np.union1d(np.flatnonzero(data == 10), offsets[1:])
    starts = np.concatenate(([0], ends[:-1] + (data[np.minimum(ends[:-1], len(data) - 1)] == 10 if len(data) else 0)))
    # a break that is the last byte of a document ends its line; the next document starts right after it
    keep = starts < ends
    starts, ends = starts[keep], ends[keep]
    if not len(starts):
        return np.zeros(len(offsets) - 1, dtype=np.int64)
    seen = np.zeros(len(data) + 1, dtype=np.int64)
    np.cumsum(inside, out=seen[1:])
    worded = seen[ends] > seen[starts]
    starts, ends = starts[worded], ends[worded]
    of = np.searchsorted(offsets, starts, side="right") - 1
    keys = W.mix(W.span_hashes(data, starts, ends, lower=False) + of.astype(np.uint64) * W._BASE)
    _, earliest = np.unique(keys, return_index=True)
    n = len(offsets) - 1
    return np.bincount(of, minlength=n) - np.bincount(of[earliest], minlength=n)


def repeated_words(words: W.Words) -> np.ndarray:
    """For each word, whether it stands in a window of five that its document has twice."""
    hashes = words.hashes(lower=False)
    cover = np.zeros(len(hashes) + 1, dtype=np.int32)
    keys, starts = W.windows(hashes, words.first, WINDOW)
    if len(keys):
        of = np.searchsorted(words.first, starts, side="right") - 1
        keys = W.mix(keys + of.astype(np.uint64) * W._BASE)
        order = np.argsort(keys, kind="stable")
        ordered = keys[order]
        same = ordered[1:] == ordered[:-1]
        twice = np.zeros(len(keys), dtype=bool)
        twice[order[1:][same]] = True
        twice[order[:-1][same]] = True
        hit = starts[twice]
        cover[hit] += 1
        cover[hit + WINDOW] -= 1
    return np.cumsum(cover[:-1]) > 0


@W.tidy
def _measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        parts = [measures(data, offsets) for _, _, data, offsets in W.slices(batch.column("text"))]
        table = np.concatenate(parts) if parts else np.zeros((0, len(MEASURES)), dtype=np.int64)
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), batch.column("source"), *(pa.array(table[:, k]) for k in range(table.shape[1]))],
            names=["doc_id", "source", *MEASURES],
        )


def measure(docs: DataFrame) -> DataFrame:
    """doc_id, source and the five measures of each text."""
    bounded_batches(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), F.col("source").cast("string"), F.col("text").cast("string")).mapInArrow(
        _measure, "doc_id long, source string, " + ", ".join(f"{m} long" for m in MEASURES)
    )


def base_failed(min_words: int = 10, max_repeat_percent: int = 20):
    return (F.col("n_words") < min_words) | (F.col("n_repeat_words") * 100 > F.col("n_words") * max_repeat_percent)


def host_rates(measured: DataFrame) -> DataFrame:
    """Per host: documents, failures, and the rate shrunk by a beta prior that is fitted to all hosts by moments.

    Mean m and variance v of the hosts' rates, each host counting by its documents, less the variance that counting
    alone would give, set the strength of the prior: s = m (1 - m) / v - 1, between 1 and 1e6.
    """
    hosts = measured.where("source IS NOT NULL").groupBy("source").agg(
        F.count(F.lit(1)).alias("n"), F.sum(F.col("base_failed").cast("long")).alias("k")
    )
    total = hosts.agg(
        F.sum("n").alias("all_n"),
        F.sum("k").alias("all_k"),
        F.count(F.lit(1)).alias("hosts"),
        F.sum(F.col("k") * F.col("k") / F.col("n")).alias("square"),
    ).select(
        F.coalesce(F.try_divide("all_k", "all_n"), F.lit(0.0)).alias("m"),
        F.coalesce(F.try_divide("square", "all_n"), F.lit(0.0)).alias("q"),
        F.coalesce(F.try_divide("hosts", "all_n"), F.lit(0.0)).alias("each"),
    )
    spread = F.col("q") - F.col("m") * F.col("m") - F.col("each") * F.col("m") * (1 - F.col("m"))
    strength = F.when(spread > 0, F.least(F.lit(1e6), F.greatest(F.lit(1.0), F.col("m") * (1 - F.col("m")) / spread - 1)))
    prior = total.select("m", F.coalesce(strength, F.lit(1e6)).alias("s"))
    return hosts.crossJoin(F.broadcast(prior)).select(  # one row
        "source", "n", "k", ((F.col("k") + F.col("m") * F.col("s")) / (F.col("n") + F.col("s"))).alias("host_rate")
    )


def judge(measured: DataFrame, max_host_rate: float = 0.5) -> DataFrame:
    """Adds ``base_failed``, ``host_rate`` and ``kept``.

    The verdicts go to the documents by a join whose document side is salted: a host with a third of all documents
    is dealt to many tasks, and the hosts' side, one row a host, is repeated for each salt.
    """
    measured = measured.withColumn("base_failed", base_failed())
    hosts = host_rates(measured).select(
        F.col("source").alias("host"), "host_rate", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("host_salt")
    )
    salted = measured.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int"))
    joined = salted.join(hosts, (F.col("source") == F.col("host")) & (F.col("salt") == F.col("host_salt")), "left")
    kept = ~F.col("base_failed") & (F.coalesce("host_rate", F.lit(0.0)) <= max_host_rate)
    return joined.withColumn("kept", kept).drop("host", "salt", "host_salt")


def verdicts(docs: DataFrame, max_host_rate: float = 0.5) -> DataFrame:
    """doc_id, source, the measures, base_failed, host_rate, kept."""
    return judge(durable(measure(docs)), max_host_rate)


def _passer(min_words: int, max_repeat_percent: int):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parts = [measures(data, offsets) for _, _, data, offsets in W.slices(batch.column("text"))]
            if parts:
                table = np.concatenate(parts)
                n_words, repeated = table[:, 0], table[:, 4]
                yield batch.filter(pa.array((n_words >= min_words) & (100 * repeated <= max_repeat_percent * n_words)))

    return run


def apply(docs: DataFrame, max_host_rate: float = 0.5, min_words: int = 10, max_repeat_percent: int = 20) -> DataFrame:
    """The documents that the rules keep, with the columns of ``docs``.

    Only the hosts that are rejected are joined to the texts, so texts are shuffled only if those are very many.
    """
    docs, names = plain(docs)
    measured = measure(docs).withColumn("base_failed", base_failed(min_words, max_repeat_percent))
    bad = host_rates(durable(measured.select("source", "base_failed"))).where(F.col("host_rate") > max_host_rate)
    return restored(drop_keys(docs.mapInArrow(_passer(min_words, max_repeat_percent), docs.schema), "source", bad.select("source")), names)
