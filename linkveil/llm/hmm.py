"""Scoring of texts by a hidden Markov language model.

A text's tokens are its words (A-Z lower-cased) and one end.  Each token has a class: the end, CLASS_WORDS frequent words
each on their own, and SHAPES classes by the last bytes of the other words.  Hidden states emit classes, and a class
emits its words by their counts in the whole training part, (c + 1) / (N_class + V_class + 1), so the vocabulary may
grow without bound while the states' tables stay small.  Baum-Welch starts from a model of all pairs of neighbouring tokens of
the training part, which are counted by coarser classes and fitted on the driver in a table of fixed size, and then adds up the
expected counts of all training documents by partition.  The scaled forward recursion gives the exact probability of a
text's classes; with the words' shares in their classes it is the text's log10 probability.

Word counts are kept by 64-bit hash.  The most frequent words, LOCAL_WORDS at most, travel to the tasks; the rest is
looked up by a join on the hash, after each text's rare words are added up.  A word that is hot in held-out texts only is a
hot key of that join, which adaptive execution splits.

Words of one class share their states' emission: what a state prefers is known by class, and a class deals its share out to
its words by their counts alone.

Defined cases: null and empty texts have one token, the end.  Rows that share a doc_id each get a row.  A null doc_id
counts as held out.  With an empty training part all counts are 0 and V is 1, the end; a training part without words has
ends only.  Words of equal counts at the border of the LOCAL_WORDS are told apart by a hash, which moves work, not results.
An empty table gives an empty result.  Texts of any length are scored whole; a batch holds its texts' classes.  Only
doc_id and text are read, so other columns of any name do no harm.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkveil.llm import words as W
from linkveil.llm.treesum import emit, tree_sum
from linkveil.session import bounded_batches, durable

STATES = 8
CLASS_WORDS = 2000
SHAPES = 1024
CLASSES = 1 + CLASS_WORDS + SHAPES
LOCAL_WORDS = 100_000
SUFFIX = 3
ROUNDS = 2
#: Coarser classes, by which neighbouring tokens are counted: the end, frequent words, and the others by their class.
PAIR_WORDS, PAIR_SHAPES = 500, 128
PAIR_CLASSES = 1 + PAIR_WORDS + PAIR_SHAPES
PAIR_ROUNDS = 300
#: Tokens that are drawn for a start: none, as the whole training part is counted.
SEED_TOKENS = 0
GROUP_TOKENS = 300_000
PENDING = 1_500_000


def held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7 == 2, F.lit(True))


class Slice:
    """Hashes and shape classes of the words of a slice."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        words = W.Words(data, offsets)
        self.first, self.hashes = words.first, words.hashes()
        tails = W.span_hashes(data, np.maximum(words.start, words.end - SUFFIX), words.end, lower=True)
        self.shapes = (1 + CLASS_WORDS + (tails % W.U(SHAPES)).astype(np.int64)).astype(np.int16)


class Table:
    """Looks up the place of hashes in a sorted array; -1 for none."""

    def __init__(self, keys: np.ndarray):
        self.keys = keys
        self.shift = W.U(64 - max(12, min(22, math.ceil(math.log2(8 * max(1, len(keys)))))))
        slots = (keys >> self.shift).astype(np.int64)
        self.slot = np.full(1 << int(64 - int(self.shift)), -1, dtype=np.int32)
        self.slot[slots] = np.arange(len(keys))
        crowded = slots[1:][slots[1:] == slots[:-1]]
        self.slot[crowded] = -2

    def find(self, hashes: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.full(len(hashes), -1, dtype=np.int32)
        at = self.slot[(hashes >> self.shift).astype(np.int64)]
        crowded = np.flatnonzero(at == -2)
        if len(crowded):
            at[crowded] = np.minimum(np.searchsorted(self.keys, hashes[crowded]), len(self.keys) - 1)
        at[(at >= 0) & (self.keys[np.maximum(at, 0)] != hashes)] = -1
        return at


@W.tidy
def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Words of a partition with counts, merged until PENDING of them wait."""
    waiting: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    size = 0

    def merge(parts):
        keys, shapes, counts = (np.concatenate(x) for x in zip(*parts, strict=True))
        unique, first, back = np.unique(keys, return_index=True, return_inverse=True)
        return unique, shapes[first], np.bincount(back, counts, minlength=len(unique)).astype(np.int64)

    def out(parts):
        keys, shapes, counts = parts
        return pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(shapes.astype(np.int32)), pa.array(counts)], names=["word", "shape", "c"])

    for batch in batches:
        for _, _, data, offsets in W.slices(batch.column("text")):
            found = Slice(data, offsets)
            waiting.append(merge([(found.hashes, found.shapes, np.ones(len(found.hashes), dtype=np.int64))]))
            size += len(waiting[-1][0])
            if size > PENDING:
                waiting = [merge(waiting)]
                size = len(waiting[0][0])
                if size > PENDING // 2:
                    yield out(waiting[0])
                    waiting, size = [], 0
    if waiting:
        yield out(merge(waiting))


class Vocabulary:
    """What tasks know of the counts: frequent words, totals, and the size of each class."""

    def __init__(self, keys, counts, n_docs: int, n_words: int, n_distinct: int, class_n, class_v):
        order = np.argsort(keys)
        self.keys, self.counts = keys[order], counts[order]
        best = np.lexsort((self.keys, -self.counts))[:CLASS_WORDS]
        self.own = np.zeros(len(self.keys), dtype=np.int16)
        self.own[best] = 1 + np.arange(len(best))
        self.n_docs, self.tokens, self.distinct = n_docs, n_words + n_docs, n_distinct + 1
        self.class_n, self.class_v = class_n, class_v

    def log_sizes(self) -> np.ndarray:
        return np.log10(self.class_n + self.class_v + 1)


def frequent(level: Column, levels: list) -> Column:
    """Which words are among the LOCAL_WORDS most frequent: whole levels of counts, and of the first level that doesn't fit
    the share that does, by a hash of the word (six standard deviations short of the room, so LOCAL_WORDS holds)."""
    room, chosen = LOCAL_WORDS, F.lit(False)
    for row in levels:
        if row["v"] > room:
            share = max(0.0, room - 6 * math.sqrt(room)) / row["v"]
            lot = F.pmod(F.xxhash64(F.lit("local"), "word"), F.lit(1 << 30))
            return chosen | ((level == row["level"]) & (lot < int(share * (1 << 30))))
        room -= row["v"]
        chosen = level >= row["level"]
    return chosen


def count(docs: DataFrame) -> tuple[DataFrame, Vocabulary]:
    """(word, shape, c) of all words of the training part, written, and what tasks need of it."""
    training = docs.where(~held_out())
    counts = durable(
        training.select(F.col("text").cast("string")).mapInArrow(_count, "word long, shape int, c long").groupBy("word").agg(F.min("shape").alias("shape"), F.sum("c").alias("c"))
    )
    level = F.floor(F.log2("c") * 16).cast("int")
    levels = counts.groupBy(level.alias("level")).agg(F.count(F.lit(1)).alias("v"), F.sum("c").alias("n")).orderBy(F.desc("level")).collect()  # 16 a power of two
    chosen = frequent(level, levels)
    local = counts.where(chosen).select("word", "shape", "c").toArrow()  # LOCAL_WORDS rows at most
    keys, found, shapes = (local.column(c).to_numpy() for c in ("word", "c", "shape"))
    keys = keys.view(np.uint64)
    class_n, class_v = np.zeros(CLASSES), np.zeros(CLASSES)
    for row in counts.groupBy("shape").agg(F.count(F.lit(1)).alias("v"), F.sum("c").alias("n")).collect():  # SHAPES rows
        class_n[row["shape"]], class_v[row["shape"]] = row["n"], row["v"]
    n_docs = training.count()
    vocabulary = Vocabulary(keys, found, n_docs, sum(r["n"] for r in levels), sum(r["v"] for r in levels), class_n, class_v)
    shapes = shapes[np.argsort(keys)]
    for i in np.flatnonzero(vocabulary.own):
        c = vocabulary.counts[i]
        class_n[shapes[i]] -= c
        class_v[shapes[i]] -= 1
        class_n[vocabulary.own[i]], class_v[vocabulary.own[i]] = c, 1
    class_n[0], class_v[0] = n_docs, 1
    return counts, vocabulary


def sequences(found: Slice, at: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Classes of all tokens, an end after each document's words, and where documents begin."""
    classes = found.shapes.copy()
    some = np.flatnonzero(at >= 0)
    mine = own[at[some]]
    classes[some[mine > 0]] = mine[mine > 0]
    return np.insert(classes, found.first[1:], 0), found.first + np.arange(len(found.first))


class Hmm:
    """start [state], moves [state, state], emits [state, class]; all rows sum to 1."""

    def __init__(self, start: np.ndarray, moves: np.ndarray, emits: np.ndarray):
        self.start, self.moves, self.emits = start, moves, emits
        self.by_class = np.ascontiguousarray(emits.T)

    @classmethod
    def seeded(cls, totals: np.ndarray, states: int = STATES, seed: int = 1) -> Hmm:
        rng = np.random.default_rng(seed)
        emits = (totals + 0.5) * rng.gamma(1.0, 1.0, (states, len(totals)))
        moves = np.full((states, states), 0.3 / states) + 0.7 * np.eye(states)
        return cls(np.full(states, 1 / states), moves, emits / emits.sum(axis=1, keepdims=True))

    @classmethod
    def from_counts(cls, start: np.ndarray, moves: np.ndarray, emits: np.ndarray, totals: np.ndarray) -> Hmm:
        """Expected counts, smoothed by the shares of the classes in the corpus."""
        share = (totals + 0.5) / (totals + 0.5).sum()
        emits = emits + 20 * share
        return cls((start + 0.1) / (start + 0.1).sum(), (moves + 0.1) / (moves + 0.1).sum(axis=1, keepdims=True), emits / emits.sum(axis=1, keepdims=True))

    def _groups(self, classes: np.ndarray, begin: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Documents of like length: numbers, classes by (time, document) and how many are alive at each time."""
        lengths = np.diff(begin)
        order = np.argsort(-lengths, kind="stable")
        sums = np.cumsum(lengths[order])
        lo = 0
        while lo < len(order):
            done = sums[lo - 1] if lo else 0
            hi = max(lo + 1, int(np.searchsorted(sums, done + GROUP_TOKENS, side="right")))
            chosen = order[lo:hi]
            size = lengths[chosen]
            seen = np.zeros((int(size[0]), len(chosen)), dtype=np.int16)
            for k, (a, n) in enumerate(zip(begin[chosen].tolist(), size.tolist(), strict=True)):
                seen[:n, k] = classes[a : a + n]
            alive = len(chosen) - np.searchsorted(size[::-1], np.arange(int(size[0])), side="right")
            yield chosen, seen, alive
            lo = hi

    def log_likelihood(self, classes: np.ndarray, begin: np.ndarray) -> np.ndarray:
        """Natural logarithm of each sequence's probability, by the scaled forward recursion."""
        out = np.zeros(len(begin) - 1)
        for chosen, seen, alive in self._groups(classes, begin):
            total = np.zeros(len(chosen))
            alpha = np.broadcast_to(self.start, (len(chosen), len(self.start)))
            for t, n in enumerate(alive.tolist()):
                alpha = (alpha[:n] @ self.moves if t else alpha[:n]) * self.by_class[seen[t, :n]]
                scale = alpha.sum(axis=1)
                alpha /= scale[:, None]
                total[:n] += np.log(scale)
            out[chosen] = total
        return out

    def expected(self, classes: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
        """Expected counts of starts, moves and emissions over all sequences, and their log likelihood."""
        k = len(self.start)
        start, moves, emits, total = np.zeros(k), np.zeros((k, k)), np.zeros(self.emits.shape), 0.0
        for _, seen, alive in self._groups(classes, begin):
            steps = alive.tolist()
            at = np.concatenate(([0], np.cumsum(alive)))
            flat = np.concatenate([seen[t, :n] for t, n in enumerate(steps)])
            likely = self.by_class[flat]
            alpha, scale = np.empty((len(flat), k)), np.empty(len(flat))
            now = np.broadcast_to(self.start, (seen.shape[1], k))
            for t, n in enumerate(steps):
                lo = at[t]
                now = (now[:n] @ self.moves if t else now[:n]) * likely[lo : lo + n]
                s = now.sum(axis=1)
                now /= s[:, None]
                alpha[lo : lo + n], scale[lo : lo + n] = now, s
            total += float(np.log(scale).sum())
            likely /= scale[:, None]
            beta = np.ones((len(flat), k))
            back = np.ascontiguousarray(self.moves.T)
            for t in range(len(steps) - 1, 0, -1):
                lo, n, before = at[t], steps[t], at[t - 1]
                ahead = likely[lo : lo + n]
                ahead *= beta[lo : lo + n]
                beta[before : before + n] = ahead @ back
                moves += alpha[before : before + n].T @ ahead
            alpha *= beta
            start += alpha[: steps[0]].sum(axis=0)
            for j in range(k):
                emits[j] += np.bincount(flat, alpha[:, j], minlength=emits.shape[1])
        return start, moves * self.moves, emits, total


def _classes_of(batch: pa.RecordBatch, table: Table, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    parts, begins, base = [], [np.zeros(1, dtype=np.int64)], 0
    for _, _, data, offsets in W.slices(batch.column("text")):
        found = Slice(data, offsets)
        classes, begin = sequences(found, table.find(found.hashes), own)
        parts.append(classes)
        begins.append(begin[1:] + base)
        base += len(classes)
    return (np.concatenate(parts) if parts else np.zeros(0, np.int16)), np.concatenate(begins)


def _baum_welch(keys: np.ndarray, own: np.ndarray, model: Hmm):
    parameters = (model.start, model.moves, model.emits)

    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, hmm = Table(keys), Hmm(*parameters)
        totals = None
        for batch in batches:
            start, moves, emits, likelihood = hmm.expected(*_classes_of(batch, table, own))
            part = np.concatenate([start, moves.ravel(), emits.ravel(), [likelihood]])
            totals = part if totals is None else totals + part
        if totals is not None:
            yield emit({0: totals})

    return run


def coarser() -> np.ndarray:
    """The coarser class of each class."""
    found = np.arange(CLASSES)
    return np.where(found <= PAIR_WORDS, found, 1 + PAIR_WORDS + found % PAIR_SHAPES)


def _neighbours(keys: np.ndarray, own: np.ndarray):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, coarse = Table(keys), coarser()
        totals = np.zeros(PAIR_CLASSES**2)
        for batch in batches:
            classes, begin = _classes_of(batch, table, own)
            inner = np.ones(len(classes), dtype=bool)
            inner[begin[1:] - 1] = False  # an end has no next token
            at, short = np.flatnonzero(inner), coarse[classes]
            totals += np.bincount(short[at] * PAIR_CLASSES + short[at + 1], minlength=len(totals))
        if totals.any():
            yield emit({0: totals})

    return run


def from_pairs(pairs: np.ndarray, totals: np.ndarray, states: int = STATES, rounds: int = PAIR_ROUNDS, seed: int = 1) -> Hmm:
    """The model of two neighbouring states that is likeliest for the counts of neighbouring coarser classes, by expectation
    maximisation; a coarser class deals its share out to its classes by their counts."""
    coarse = coarser()
    whole = np.bincount(coarse, totals + 0.5, minlength=PAIR_CLASSES)
    emits = whole * np.random.default_rng(seed).gamma(1.0, 1.0, (states, PAIR_CLASSES))
    emits /= emits.sum(axis=1, keepdims=True)
    joint = (np.full((states, states), 0.3 / states) + 0.7 * np.eye(states)) / states
    for _ in range(rounds):
        ratio = pairs / np.maximum(emits.T @ joint @ emits, 1e-300)
        before, after = emits @ ratio, emits @ ratio.T
        counts = emits * (joint @ after) + emits * (joint.T @ before) + 20 * whole / whole.sum()
        joint = joint * (before @ emits.T) + 0.1
        joint /= joint.sum()
        emits = counts / counts.sum(axis=1, keepdims=True)
    fine = emits[:, coarse] * (totals + 0.5) / whole[coarse]
    start = joint.sum(axis=1)
    return Hmm(start, joint / start[:, None], fine / fine.sum(axis=1, keepdims=True))


def fit(docs: DataFrame, vocabulary: Vocabulary, states: int = STATES, rounds: int = ROUNDS) -> Hmm:
    """Baum-Welch over the whole training part: a start from the counts of all its neighbouring tokens, then ``rounds`` passes."""
    totals = vocabulary.class_n
    model = Hmm.seeded(totals, states)
    chosen = np.flatnonzero(vocabulary.own)
    keys, own = vocabulary.keys[chosen], vocabulary.own[chosen]
    training = docs.where(~held_out()).select(F.col("text").cast("string"))
    pairs = tree_sum(training, _neighbours(keys, own))
    if pairs:  # none if all texts are empty
        model = from_pairs(pairs[0].reshape(PAIR_CLASSES, PAIR_CLASSES), totals, states)
    for _ in range(rounds):
        sums = tree_sum(training, _baum_welch(keys, own, model))
        if not sums:  # no training documents
            return model
        flat = sums[0]
        start, moves, emits = flat[:states], flat[states : states + states**2], flat[states + states**2 : -1]
        model = Hmm.from_counts(start, moves.reshape(states, states), emits.reshape(states, -1), totals)
    return model


_LOG10 = math.log(10)


def _scorer(broadcast):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, parameters = broadcast.value
        table, hmm, sizes = Table(vocabulary.keys), Hmm(*parameters), vocabulary.log_sizes()
        log_counts = np.append(np.log10(vocabulary.counts + 1.0), 0.0)  # the last one, at -1, for words that aren't there
        end = (math.log10(vocabulary.n_docs + 1), int(vocabulary.n_docs > 0))
        for batch in batches:
            tokens, known, logs, shares, rare = [], [], [], [], []
            parts, begins, base = [], [np.zeros(1, dtype=np.int64)], 0
            for _, _, data, offsets in W.slices(batch.column("text")):
                found = Slice(data, offsets)
                at = table.find(found.hashes)
                classes, begin = sequences(found, at, vocabulary.own)
                parts.append(classes)
                begins.append(begin[1:] + base)
                base += len(classes)
                n = np.diff(found.first)
                local = at >= 0
                sums = lambda x, first: (s := np.concatenate(([0.0], np.cumsum(x))))[first[1:]] - s[first[:-1]]
                tokens.append(n + 1)
                known.append(W.per_document(local, found.first) + end[1])
                logs.append(sums(log_counts[at], found.first) + end[0])
                shares.append(sums(sizes[classes], begin))
                far = np.flatnonzero(~local)
                doc = np.searchsorted(found.first, far, side="right") - 1
                cut = np.searchsorted(doc, np.arange(len(n) + 1))
                keys = found.hashes[far].view(np.int64)
                rare.append(pa.ListArray.from_arrays(pa.array(cut.astype(np.int32)), pa.array(keys)))
            if not parts:
                continue
            chain = hmm.log_likelihood(np.concatenate(parts), np.concatenate(begins)) / _LOG10
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"), batch.column("held_out"), pa.array(np.concatenate(tokens)), pa.array(np.concatenate(known)), pa.array(np.concatenate(logs)),
                    pa.array(chain - np.concatenate(shares)), pa.concat_arrays(rare),
                ],
                names=["doc_id", "held_out", "n_tokens", "known", "logs", "chain", "rare"],
            )

    return run


def score(docs: DataFrame, states: int = STATES, rounds: int = ROUNDS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (both log10) of each document."""
    bounded_batches(docs.sparkSession)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    counts, vocabulary = count(docs)
    model = fit(docs, vocabulary, states, rounds)
    sent = docs.sparkSession.sparkContext.broadcast((vocabulary, (model.start, model.moves, model.emits)))  # LOCAL_WORDS and the states' tables
    schema = "doc_id long, held_out boolean, n_tokens long, known long, logs double, chain double, rare array<long>"
    rows = docs.select("doc_id", held_out().alias("held_out"), "text").mapInArrow(_scorer(sent), schema)
    rows = durable(rows.withColumn("row", F.monotonically_increasing_id()))
    rare = rows.select("row", F.explode("rare").alias("word")).groupBy("row", "word").agg(F.count(F.lit(1)).alias("n"))
    found = rare.join(counts.select("word", "c"), "word")
    sums = found.groupBy("row").agg(F.sum(F.col("n") * F.log10(F.col("c") + 1.0)).alias("more_logs"), F.sum("n").alias("more_known"))
    logs = F.col("logs") + F.coalesce("more_logs", F.lit(0.0))
    return rows.drop("rare").join(sums, "row", "left").select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("known") + F.coalesce("more_known", F.lit(0))).alias("n_known"),
        F.lit(vocabulary.tokens).cast("long").alias("train_tokens"),
        (logs - F.col("n_tokens") * F.lit(math.log10(vocabulary.tokens + vocabulary.distinct + 1))).alias("base_score"),
        (logs + F.col("chain")).alias("score"),
    )
