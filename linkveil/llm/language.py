"""Language identification by segmentation-marginalised unigrams.

The pieces are those of a fixed public vocabulary (a byte-level one for many languages), all of them.  Each language has a
probability for each piece, fitted by expectation-maximisation on labelled words, whose expected counts are added up by
partition.  A word, marked by a blank in front, is scored whole by a forward recursion that sums the products of piece
probabilities over all of its segmentations, with scaling where the sums get too small; a text's score is the sum of its
words' logarithms, and ``score`` the posterior of the best language under a flat prior.

The fit reads a bounded sample of the labelled documents, about ``train_bytes`` of text over all languages together, drawn
by a hash of id and text; a language with less than its share is read whole.  Scoring reads whole texts.

Defined cases: ``und`` with score 0 if a text is null or has no letter, or if nothing was learned.  Words and texts may have
any length.  Ties go to the language first in alphabetical order.  Repeated rows give repeated rows, an empty table an empty
result.  A-Z are lower-cased.  Only doc_id, text and lang are read, so other columns of any name do no harm.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkveil.llm import words as W
from linkveil.llm.treesum import emit, tree_sum
from linkveil.session import bounded_batches, durable

VOCABULARY = "/opt/tokenizers/byte_bpe_multi_50k.tiktoken"
TRAIN_BYTES = 12 << 20
SMOOTHING = 0.05
ROUNDS = 4
#: Numbers of a matrix of forward sums; more words of a length are handled in several matrices.
CELLS = 4_000_000
#: Longer marked words are read one by one, not in matrices of words of one length, as are words with a sum under EXACT.  Results
#: are the same.
SINGLE = 64
EXACT = 1e-280
_LETTER = np.zeros(256, dtype=bool)
_LETTER[[*range(65, 91), *range(97, 123)]] = True


def read_vocabulary(path: str = VOCABULARY) -> list[bytes]:
    """All pieces of a rank file and all single bytes; read on the driver, bounded by the file."""
    with open(path, "rb") as f:
        pieces = {base64.b64decode(line.split()[0]) for line in f if line.strip()}
    return sorted({bytes([b]) for b in range(256)} | pieces)


class Pieces:
    """Finds the pieces inside byte matrices, all rows at once."""

    def __init__(self, pieces: list[bytes]):
        self.n = len(pieces)
        self.longest = max(map(len, pieces))
        by_length: dict[int, list[int]] = {}
        for i, p in enumerate(pieces):
            by_length.setdefault(len(p), []).append(i)
        self.by_length = {}
        for length, mine in by_length.items():
            keys = self.key(np.array([list(pieces[i]) for i in mine], dtype=np.uint64))
            order = np.argsort(keys)
            likely = np.zeros(1 << 18, dtype=bool)
            likely[(keys >> W.U(46)).astype(np.int64)] = True
            self.by_length[length] = keys[order], np.array(mine)[order], likely

    @staticmethod
    def key(rows: np.ndarray) -> np.ndarray:
        total = np.zeros(len(rows), dtype=np.uint64)
        for k in range(rows.shape[1]):
            total = (total + rows[:, k] + W.U(1)) * W._BASE
        return W.mix(total)

    def _hits(self, total: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
        keys, ids, likely = self.by_length[length]
        mixed = W.mix(total)
        some = np.flatnonzero(likely[(mixed >> W.U(46)).astype(np.int64)])
        if not len(some):
            return some, some
        at = np.minimum(np.searchsorted(keys, mixed[some]), len(keys) - 1)
        hit = keys[at] == mixed[some]
        return some[hit], ids[at[hit]]

    def steps(self, rows: np.ndarray) -> list[list[tuple[int, np.ndarray, np.ndarray]]]:
        """For each end in a matrix of equally long words: (length, words, piece ids) of the pieces that end there."""
        n = rows.shape[1]
        wide = rows.astype(np.uint64) + W.U(1)
        out: list[list] = [[] for _ in range(n + 1)]
        for start in range(n):
            total = np.zeros(len(rows), dtype=np.uint64)
            for length in range(1, min(self.longest, n - start) + 1):
                total = (total + wide[:, start + length - 1]) * W._BASE
                if length in self.by_length:
                    where, ids = self._hits(total, length)
                    if len(where):
                        out[start + length].append((length, where, ids))
        return out

    def inside(self, word: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(end, length, piece id) of all pieces inside one word, by end."""
        wide, total = word.astype(np.uint64) + W.U(1), np.zeros(len(word), dtype=np.uint64)
        found = []
        for length in range(1, min(self.longest, len(word)) + 1):
            total = (total[: len(word) - length + 1] + wide[length - 1 :]) * W._BASE
            if length in self.by_length:
                where, ids = self._hits(total, length)
                found.append((where + length, np.full(len(where), length), ids))
        end, length, ids = (np.concatenate(x) for x in zip(*found, strict=True))
        order = np.argsort(end, kind="stable")
        return end[order], length[order], ids[order]


def forward(steps: list, n_words: int, table: np.ndarray) -> np.ndarray:
    """alpha[end, word, language]: summed probability of all segmentations of the first ``end`` bytes.

    Sums at the last end of EXACT or more have lost nothing: what is too small for a number on the way adds less than 1e-308."""
    alpha = np.zeros((len(steps), n_words, table.shape[1]))
    alpha[0] = 1
    for end in range(1, len(steps)):
        for length, rows, ids in steps[end]:
            alpha[end, rows] += alpha[end - length, rows] * table[ids]
    return alpha


def backward(steps: list, n_words: int, table: np.ndarray) -> np.ndarray:
    beta = np.zeros((len(steps), n_words, table.shape[1]))
    beta[-1] = 1
    for end in range(len(steps) - 1, 0, -1):
        for length, rows, ids in steps[end]:
            beta[end - length, rows] += table[ids] * beta[end, rows]
    return beta


def log_sums(end: np.ndarray, start: np.ndarray, ids: np.ndarray, size: int, logs: np.ndarray) -> np.ndarray:
    """``forward`` of one word in logarithms, [end, language]; the pieces are in order of ``end``."""
    alpha = np.full((size + 1, logs.shape[1]), -np.inf)
    alpha[0] = 0
    cut = np.searchsorted(end, np.arange(size + 2))
    for e in range(1, size + 1):
        lo, hi = cut[e], cut[e + 1]
        paths = alpha[start[lo:hi]] + logs[ids[lo:hi]]
        most = paths.max(axis=0)
        alpha[e] = most + np.log(np.exp(paths - most).sum(axis=0))
    return alpha


def scaled_sum(end: np.ndarray, start: np.ndarray, ids: np.ndarray, size: int, table: np.ndarray, longest: int) -> np.ndarray:
    """The logarithm of ``forward``'s last sum for one word of any length: what later bytes still read is scaled again and again."""
    alpha, total, p = np.zeros((size + 1, table.shape[1])), np.zeros(table.shape[1]), table[ids]
    alpha[0] = 1
    cut = np.searchsorted(end, np.arange(size + 2)).tolist()
    with np.errstate(over="ignore", divide="ignore", invalid="ignore"):
        for e in range(1, size + 1):
            lo, hi = cut[e], cut[e + 1]
            np.add.reduce(alpha[start[lo:hi]] * p[lo:hi], axis=0, out=alpha[e])
            if e % 8 == 0 or e == size:
                scale = alpha[e].copy()
                total += np.log(scale)
                alpha[max(0, e - longest) : e + 1] /= scale
    return total if np.isfinite(total).all() else log_sums(end, start, ids, size, np.log(table))[-1]


def matrices(words: np.ndarray, n: int, width: int) -> Iterator[np.ndarray]:
    """``words`` of n bytes in parts that a matrix of CELLS numbers holds."""
    size = max(1, CELLS // ((n + 1) * max(1, width)))
    for lo in range(0, len(words), size):
        yield words[lo : lo + size]


def expect(finder: Pieces, words: list[bytes], counts: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Expected counts [piece, language] of marked words with counts [word, language]."""
    expected, logs = np.zeros_like(table), np.log(table)
    lengths = np.array([len(w) for w in words], dtype=np.int64)
    single = np.flatnonzero(lengths > SINGLE).tolist()
    for n in np.unique(lengths[lengths <= SINGLE]).tolist():
        for part in matrices(np.flatnonzero(lengths == n), n, table.shape[1]):
            steps = finder.steps(np.frombuffer(b"".join(words[i] for i in part), dtype=np.uint8).reshape(len(part), n))
            alpha, beta = forward(steps, len(part), table), backward(steps, len(part), table)
            good = (alpha[-1] >= EXACT).all(axis=1)
            single += part[~good].tolist()
            weight = counts[part] * good[:, None] / np.maximum(alpha[-1], EXACT)
            for end in range(1, len(steps)):
                for length, rows, ids in steps[end]:
                    share = alpha[end - length, rows] * table[ids] * beta[end, rows] * weight[rows]
                    for k in range(table.shape[1]):
                        expected[:, k] += np.bincount(ids, share[:, k], minlength=finder.n)
    for i in single:
        n = len(words[i])
        end, length, ids = finder.inside(np.frombuffer(words[i], dtype=np.uint8))
        alpha = log_sums(end, end - length, ids, n, logs)
        back = np.argsort(n - end + length, kind="stable")  # the same sums from the last byte to the first
        beta = log_sums((n - end + length)[back], (n - end)[back], ids[back], n, logs)[::-1]
        np.add.at(expected, ids, np.exp(alpha[end - length] + logs[ids] + beta[end] - alpha[n]) * counts[i])
    return expected


class Model:
    def __init__(self, pieces: list[bytes], languages: list[str], table: np.ndarray):
        self.finder, self.languages, self.table = Pieces(pieces), languages, table

    def word_scores(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """log probability [word, language] of byte spans, each marked by a blank in front."""
        out = np.zeros((len(start), len(self.languages)))
        lengths = end - start
        single = np.flatnonzero(lengths >= SINGLE).tolist()
        for n in np.unique(lengths[lengths < SINGLE]).tolist():
            for part in matrices(np.flatnonzero(lengths == n), n, len(self.languages)):
                rows = np.full((len(part), n + 1), 32, dtype=np.uint8)
                rows[:, 1:] = data[start[part][:, None] + np.arange(n)]
                last = forward(self.finder.steps(rows), len(part), self.table)[-1]
                good = (last >= EXACT).all(axis=1)
                out[part[good]] = np.log(last[good])
                single += part[~good].tolist()
        for i in single:
            word = np.concatenate(([np.uint8(32)], data[start[i] : end[i]]))
            at, length, ids = self.finder.inside(word)
            out[i] = scaled_sum(at, at - length, ids, len(word), self.table, self.finder.longest)
        return out

    def predict(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Log probability [document, language] of the texts of a slice."""
        data = W.LOWER[data]
        words = W.Words(data, offsets)
        keys = W.span_hashes(data, words.start, words.end, lower=False)
        _, one, which = np.unique(keys, return_index=True, return_inverse=True)
        scores = self.word_scores(data, words.start[one], words.end[one])
        total = np.zeros((len(offsets) - 1, len(self.languages)))
        full = np.flatnonzero(words.counts())
        if len(full):
            total[full] = np.add.reduceat(scores[which], words.first[:-1][full], axis=0)
        return total


def has_letter(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    found = W.per_document(_LETTER[data], offsets) > 0
    other = W.per_document(data >= 0x80, offsets) > 0
    for d in np.flatnonzero(other & ~found).tolist():
        found[d] = any(map(str.isalpha, data[offsets[d] : offsets[d + 1]].tobytes().decode()))
    return found


def held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(True))


@W.tidy
def _word_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Words of the sample by language, added up within each batch."""
    for batch in batches:
        lang = np.array(batch.column("lang").to_pylist(), dtype=object)
        for lo, hi, data, offsets in W.slices(batch.column("text")):
            data = W.LOWER[data]
            words = W.Words(data, offsets)
            start, end = words.start, words.end
            of = np.repeat(lang[lo:hi], words.counts())
            counts: dict[tuple[str, bytes], int] = {}
            raw = data.tobytes()
            for key in zip(of, (raw[a:b] for a, b in zip(start.tolist(), end.tolist(), strict=True)), strict=True):
                counts[key] = counts.get(key, 0) + 1
            yield pa.RecordBatch.from_arrays(
                [pa.array([k for k, _ in counts], pa.string()), pa.array([w for _, w in counts], pa.binary()), pa.array(list(counts.values()), pa.int64())],
                names=["lang", "word", "n"],
            )


def learn(docs: DataFrame, train_bytes: int = TRAIN_BYTES, vocabulary: str = VOCABULARY) -> tuple[list[str], list[bytes], np.ndarray]:
    """Languages, pieces, and piece probabilities from the labelled documents that aren't held out."""
    known = docs.where(~held_out()).where("text IS NOT NULL AND lang IS NOT NULL").select(
        F.col("doc_id").cast("long"), F.col("text").cast("string"), F.col("lang").cast("string")
    )
    sizes = known.groupBy("lang").agg(F.sum(F.octet_length("text")).alias("bytes"))
    sizes = {r["lang"]: r["bytes"] or 0 for r in sizes.collect()}  # one row a language
    languages, pieces = sorted(sizes), read_vocabulary(vocabulary)
    if not languages:
        return [], pieces, np.zeros((len(pieces), 0))
    share = train_bytes / len(languages)
    rate = F.create_map(*(F.lit(x) for lang in languages for x in (lang, min(1.0, share / max(1, sizes[lang])))))
    draw = F.pmod(F.xxhash64(F.lit("sample"), "doc_id", "text"), F.lit(1 << 20)) / float(1 << 20)
    sample = known.where(draw < rate[F.col("lang")])
    rows = sample.select("lang", "text").mapInArrow(_word_counts, "lang string, word binary, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    rows = durable(rows.repartition(max(8, docs.sparkSession.sparkContext.defaultParallelism), "word"))  # bounded by train_bytes
    context = docs.sparkSession.sparkContext
    table = np.full((len(pieces), len(languages)), 1.0 / len(pieces))
    for _ in range(ROUNDS):
        sent = context.broadcast((pieces, languages, table))  # pieces x languages
        sums = tree_sum(rows, _expected(sent))
        expected = np.stack([sums.get(k, np.zeros(len(pieces))) for k in range(len(languages))], axis=1) + SMOOTHING
        table = expected / expected.sum(axis=0)
        sent.unpersist()
    return languages, pieces, table


def _expected(broadcast):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[str, tuple[list[bytes], list[int]]] = {}
        for batch in batches:
            for lang, word, n in zip(*(batch.column(c).to_pylist() for c in ("lang", "word", "n")), strict=True):
                mine = found.setdefault(lang, ([], []))
                mine[0].append(b" " + word)
                mine[1].append(n)
        if found:
            pieces, languages, table = broadcast.value
            finder = _finder(pieces)
            number = {lang: k for k, lang in enumerate(languages)}
            for lang, (words, counts) in found.items():
                k = number[lang]
                yield emit({k: expect(finder, words, np.array(counts, dtype=float)[:, None], np.ascontiguousarray(table[:, k : k + 1]))[:, 0]})

    return run


_cache: dict = {}


def _finder(pieces: list[bytes]) -> Pieces:
    """The pieces' index, made once for a worker."""
    if _cache.get("pieces") != pieces:
        _cache.update(pieces=pieces, finder=Pieces(pieces))
    return _cache["finder"]


def _loaded(broadcast) -> Model:
    parts = broadcast.value
    if _cache.get("of") is not parts:
        _cache.update(of=parts, model=Model(*parts[1:]))
    return _cache["model"]


def _predictor(broadcast, n_languages: int):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            best, score = ["und"] * batch.num_rows, np.zeros(batch.num_rows)
            if n_languages:
                model = _loaded(broadcast)
                for lo, _, data, offsets in W.slices(batch.column("text"), max(1 << 20, (32 << 20) // max(4, n_languages))):
                    total = model.predict(data, offsets)
                    total -= total.max(axis=1, keepdims=True)
                    share = np.exp(total)
                    share /= share.sum(axis=1, keepdims=True)
                    for d in np.flatnonzero(has_letter(data, offsets)).tolist():
                        k = int(share[d].argmax())
                        best[lo + d], score[lo + d] = model.languages[k], share[d, k]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(best), pa.array(score)], names=["doc_id", "held_out", "lang_pred", "score"])

    return run


def identify(docs: DataFrame, train_bytes: int = TRAIN_BYTES, vocabulary: str = VOCABULARY) -> DataFrame:
    """doc_id, held_out, lang_pred, score of each document."""
    bounded_batches(docs.sparkSession)
    languages, pieces, table = learn(docs, train_bytes, vocabulary)
    broadcast = docs.sparkSession.sparkContext.broadcast((0, pieces, languages, table))  # bounded: vocabulary x languages
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return texts.select("doc_id", held_out().alias("held_out"), "text").mapInArrow(
        _predictor(broadcast, len(languages)), "doc_id long, held_out boolean, lang_pred string, score double"
    )
