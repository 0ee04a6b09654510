"""Quality classifier: random Fourier features, ridge scores, isotonic calibration.

Statistics of a whole text are standardised and mapped by random Fourier features, which approximate a Gaussian
kernel.  Each partition sums its part of the normal equations, in two folds; the sums are added level by level and solved
with a ridge.  Scores that the model of the other fold gives are counted in a fixed number of bins, from which an
isotonic map to shares of label 1 is fitted.

Defined cases: null and empty texts have the statistics of no words and are scored; rows that share a doc_id each get a
row; a document with several labels counts for each; null labels are left out.  Without labels every score is 0.5.  A
null doc_id has no label.  Scores of just the threshold count as 1.  Very long texts are read whole, in one pass; an empty
table gives an empty result.  Only doc_id, text and the labels' quality are read, so other columns of any name do no harm.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkveil.llm import host_rules
from linkveil.llm import words as W
from linkveil.llm.treesum import emit, tree_sum
from linkveil.session import bounded_batches, durable

STATISTICS = (
    "log_words", "word_length", "symbols", "digits", "capitals", "punctuation", "exclamations", "other_bytes", "dup_lines", "repeated_words",
    "distinct_words", "log_lines", "words_a_line", "short_words", "long_words", "symbol_ends", "stops", "capital_words",
)
DIMENSIONS = 192
SPREAD = 0.25
RIDGE = 1.0
BINS = 1000

_DIGIT, _CAPITAL, _PUNCTUATION = (np.zeros(256, dtype=bool) for _ in range(3))
_DIGIT[48:58] = True
_CAPITAL[65:91] = True
_PUNCTUATION[list(b".,;:'\"-()")] = True


def statistics(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One row of STATISTICS for each document of a slice."""
    words = W.Words(data, offsets)
    n_words = words.counts()
    base = host_rules.measures(data, offsets)
    size = np.maximum(np.diff(offsets), 1)
    some = np.maximum(n_words, 1)
    share = lambda flags: W.per_document(flags, offsets) / size
    by_word = lambda flags: W.per_document(flags, words.first) / some
    lines = W.per_document(data == 10, offsets) + 1
    lengths = words.end - words.start
    doc = words.documents()
    keys = W.mix(words.hashes() + doc.astype(np.uint64) * W._BASE)
    _, one = np.unique(keys, return_index=True)
    last = data[words.end - 1] if len(words.end) else data[:0]
    first = data[words.start] if len(words.start) else data[:0]
    table = [
        np.log1p(n_words), base[:, 1] / some, share(host_rules.SYMBOLS[data]), share(_DIGIT[data]), share(_CAPITAL[data]), share(_PUNCTUATION[data]), share(data == 33),
        share(data >= 0x80), base[:, 3] / lines, base[:, 4] / some, np.bincount(doc[one], minlength=len(size)) / np.sqrt(some), np.log1p(lines), np.log1p(n_words / lines),
        by_word(lengths <= 3), by_word(lengths > 15), by_word(host_rules.SYMBOLS[last]), by_word(last == 46), by_word(_CAPITAL[first]),
    ]
    return np.stack(table, axis=1).astype(np.float64)


@W.tidy
def _measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        parts = [statistics(data, offsets) for _, _, data, offsets in W.slices(batch.column("text"))]
        table = np.concatenate(parts) if parts else np.zeros((0, len(STATISTICS)))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(np.ascontiguousarray(c)) for c in table.T)], names=["doc_id", *STATISTICS])


def measure(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(
        _measure, "doc_id long, " + ", ".join(f"{s} double" for s in STATISTICS)
    )


class Fourier:
    """Standardised statistics to cosines of random projections, with a constant."""

    def __init__(self, mean: np.ndarray, deviation: np.ndarray, dimensions: int = DIMENSIONS, spread: float = SPREAD, seed: int = 5):
        rng = np.random.default_rng(seed)
        self.mean, self.scale = mean, 1 / np.where(deviation > 1e-9, deviation, 1.0)
        self.projection = rng.normal(0, spread, (len(mean), dimensions))
        self.phase = rng.uniform(0, 2 * np.pi, dimensions)

    def __call__(self, table: np.ndarray) -> np.ndarray:
        x = np.clip((table - self.mean) * self.scale, -8, 8)
        z = np.sqrt(2 / len(self.phase)) * np.cos(x @ self.projection + self.phase)
        return np.concatenate([z, np.ones((len(z), 1))], axis=1)


def _matrix(batch: pa.RecordBatch) -> np.ndarray:
    return np.stack([batch.column(s).to_numpy(zero_copy_only=False) for s in STATISTICS], axis=1) if batch.num_rows else np.zeros((0, len(STATISTICS)))


def _equations(fourier: Fourier):
    """Normal equations of each fold: z'z with z'y as its last row."""

    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[int, np.ndarray] = {}
        for batch in batches:
            z, y = fourier(_matrix(batch)), batch.column("quality").to_numpy(zero_copy_only=False).astype(float)
            fold = batch.column("fold").to_numpy(zero_copy_only=False)
            for k in (0, 1):
                mine = z[fold == k]
                part = np.concatenate([mine.T @ mine, (mine.T @ y[fold == k])[None]])
                totals[k] = totals[k] + part if k in totals else part
        if totals:
            yield emit(totals)

    return run


def _binned(fourier: Fourier, weights: list[np.ndarray]):
    """Rows and labels 1 by bin of the score that the other fold's model gives."""

    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, BINS))
        for batch in batches:
            z, y = fourier(_matrix(batch)), batch.column("quality").to_numpy(zero_copy_only=False).astype(float)
            fold = batch.column("fold").to_numpy(zero_copy_only=False)
            for k in (0, 1):
                at = bin_of(z[fold == k] @ weights[1 - k])
                total[0] += np.bincount(at, minlength=BINS)
                total[1] += np.bincount(at, y[fold == k], minlength=BINS)
        yield emit({0: total})

    return run


def bin_of(raw: np.ndarray) -> np.ndarray:
    return np.clip(((raw + 0.5) / 2 * BINS).astype(np.int64), 0, BINS - 1)


def solve(equations: np.ndarray, ridge: float = RIDGE) -> np.ndarray:
    size = equations.shape[1]
    penalty = ridge * np.eye(size)
    penalty[-1, -1] = 1e-6
    return np.linalg.solve(equations[:-1] + penalty, equations[-1])


def isotonic(weight: np.ndarray, value: np.ndarray) -> np.ndarray:
    """Non-decreasing means of ``value`` (sums over bins of ``weight``) by pooling neighbours; empty bins are interpolated."""
    blocks: list[list[float]] = []
    used = np.flatnonzero(weight > 0)
    for i in used.tolist():
        blocks.append([weight[i], value[i], 1])
        while len(blocks) > 1 and blocks[-2][1] / blocks[-2][0] >= blocks[-1][1] / blocks[-1][0]:
            w, v, n = blocks.pop()
            blocks[-1] = [blocks[-1][0] + w, blocks[-1][1] + v, blocks[-1][2] + n]
    fitted = np.repeat([v / w for w, v, _ in blocks], [n for *_, n in blocks])
    return np.interp(np.arange(len(weight)), used, fitted)


class Model:
    def __init__(self, fourier: Fourier, weights: np.ndarray, levels: np.ndarray):
        self.fourier, self.weights, self.levels = fourier, weights, levels

    def scores(self, table: np.ndarray) -> np.ndarray:
        """Calibrated shares; a thousandth of the raw score parts ties within a level."""
        raw = self.fourier(table) @ self.weights
        middle = (np.arange(BINS) + 0.5) / BINS * 2 - 0.5
        return 0.999 * np.interp(raw, middle, self.levels) + 0.001 * np.clip((raw + 0.5) / 2, 0, 1)


def held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(True))


def fit(measured: DataFrame, labels: DataFrame) -> Model | None:
    """The model of all labelled documents that aren't held out."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality")).where("quality IS NOT NULL")
    fold = F.pmod(F.xxhash64(F.lit("fold"), "doc_id"), F.lit(2)).cast("int")
    rows = durable(measured.where(~held_out()).join(known, "doc_id").withColumn("fold", fold))
    moments = rows.agg(F.count(F.lit(1)), *(f(s) for s in STATISTICS for f in (F.avg, F.stddev_pop))).first()
    if not moments[0]:
        return None
    fourier = Fourier(np.array(moments[1::2], dtype=float), np.array(moments[2::2], dtype=float))
    size = DIMENSIONS + 1
    folds = {k: v.reshape(size + 1, size) for k, v in tree_sum(rows, _equations(fourier)).items()}
    weights = [solve(folds.get(k, np.zeros((size + 1, size)))) for k in (0, 1)]
    weight, value = tree_sum(rows, _binned(fourier, weights))[0].reshape(2, BINS)
    return Model(fourier, solve(sum(folds.values())), isotonic(weight, value))


def _scorer(model: Model | None, threshold: float):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = np.full(batch.num_rows, 0.5) if model is None else np.clip(model.scores(_matrix(batch)), 0, 1)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("held_out"), pa.array(score), pa.array((score >= threshold).astype(np.int32))],
                names=["doc_id", "held_out", "score", "predicted"],
            )

    return run


def score(docs: DataFrame, labels: DataFrame, threshold: float = 0.7) -> DataFrame:
    """doc_id, held_out, score, predicted for each document."""
    bounded_batches(docs.sparkSession)
    measured = durable(measure(docs))
    model = fit(measured, labels)
    return measured.withColumn("held_out", held_out()).mapInArrow(_scorer(model, threshold), "doc_id long, held_out boolean, score double, predicted int")
