"""Substring dedup by sliding sentence spans.

Texts are cut into sentences (after ``.``, ``!``, ``?`` with white space behind, and at line ends); a sentence of over
LONG words is cut every LONG words, so that a passage without full stops still has several.  Every run of two or more
consecutive sentences with MIN_WORDS words or more counts.  Hashed are, for each sentence, the shortest such run from it and
the shortest one up to it: these cover every other run.  (Take a repeated run R.  The shortest run from its first sentence
and the one up to its last lie in R.  A sentence between them has MIN_WORDS words of R before it, so the one up to it does as
well.)  Cuts depend on where a sentence begins, so a passage that begins inside sentences of different leads is cut
differently in each place.  Runs of MIN_WORDS words that are chosen by their content alone are therefore taken as well:
each that has the smallest hash of WINDOW neighbouring ones.  Any MIN_WORDS + WINDOW - 1 equal words share one, and of a
longer passage at most WINDOW - 1 words at either end stay uncovered.  All runs are hashed (words A-Z lower-cased) and
grouped over the whole corpus; the first place of a run, by doc_id and then by position, stays.  Of what the later places
cover, sentences of up to LONG words are removed if they are covered as a whole, and longer ones word by word; the rest of
the text is kept as it is.  MIN_WORDS is a threshold: what repeats in fewer words is common speech and stays.

A run that a document has twice is settled within the document, so only one place a document goes to the run's group.  Runs
that a sample of the documents shows to be in very many are dealt into parts first, of which one place each goes on.

``n_sentences`` counts sentences and the pieces of long ones, ``n_removed`` those that repeated runs of sentences cover,
``n_cut`` the further ones that lose words to runs chosen by content; ``removed_words`` counts the words of both.

Defined cases: null texts stay null, empty ones empty; nothing is removed from texts under MIN_WORDS words.  Rows that share
a doc_id are told apart by their texts; rows of equal id and text are one document, and each loses the same.  Rows with
null ids are told apart by their texts.  Repeats inside one document are removed too.  Columns named as an own result (OWN)
give way to it; others of any name stay.  An empty table gives an empty result.  Texts of any length are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from linkveil.llm import words as W
from linkveil.llm.columns import MARK_BITS, fresh, identity, plain, quoted, restored
from linkveil.session import bounded_batches, durable

MIN_WORDS = 25
LONG = 20
WINDOW = 12
#: A run's place in one number: first word * PACK + its words (0 for a run chosen by content); no run has MIN_WORDS + LONG words.
PACK = 64
#: Bits of a place; the bits of the text's digest go before them.
PLACE_BITS = 63 - MARK_BITS
#: One of so many documents is read to find hot runs; hot is a run with HOT_LEAST documents of it and a HOT_SHARE-th of its runs.
SAMPLE = 64
HOT_LEAST = 64
HOT_SHARE = 2_000
PARTS = 64
OWN = ("n_sentences", "n_removed", "n_cut", "removed_words")

_STOP = np.zeros(256, dtype=bool)
_STOP[list(b".!?")] = True


class Sentences:
    """Sentences of a slice: word spans, and for each document the number of its first sentence."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        self.words = words = W.Words(data, offsets)
        n = len(words.start)
        opens = np.zeros(n, dtype=bool)
        if n:
            opens[words.first[:-1][np.diff(words.first) > 0]] = True
            opens[1:] |= _STOP[data[words.end[:-1] - 1]]
            lines = np.concatenate(([0], np.cumsum(data == 10)))
            opens[1:] |= lines[words.start[1:]] > lines[words.end[:-1]]
            at = np.flatnonzero(opens)
            sizes = np.diff(np.append(at, n))
            inside = np.arange(n) - np.repeat(at, sizes)
            self.short = np.repeat(sizes <= LONG, sizes)
            opens |= inside % LONG == 0
        else:
            self.short = opens
        self.open = np.flatnonzero(opens)
        self.close = np.append(self.open[1:], n)[: len(self.open)]
        self.first = np.searchsorted(self.open, words.first)

    def runs(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Document, first word, end word (both of the slice; 0 for a run chosen by content) and hash of each run."""
        m = len(self.open)
        if not m:
            none = np.zeros(0, dtype=np.int64)
            return none, none, none, none.astype(np.uint64)
        doc = np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))
        ends = self.first[1:][doc]
        begins = self.first[:-1][doc]
        each = np.arange(m)
        forward = np.maximum(np.searchsorted(self.close, self.open + MIN_WORDS) + 1, each + 2)
        backward = np.minimum(np.searchsorted(self.open, self.close - MIN_WORDS, side="right") - 1, each - 1)
        good, back = forward <= ends, backward >= begins
        a = np.concatenate([each[good], backward[back]])
        b = np.concatenate([forward[good], each[back] + 1])
        keep = np.unique(a * np.int64(m + 1) + b)
        a, b = keep // (m + 1), keep % (m + 1)
        # the hash of a run's words by a polynomial over the words' hashes
        up, down = W._power_tables(len(self.words.start) + 1)
        hashes = self.words.hashes()
        sums = np.zeros(len(hashes) + 1, dtype=np.uint64)
        np.cumsum(hashes * up[: len(hashes)], out=sums[1:])
        hashed = lambda lo, hi: W.mix((sums[hi] - sums[lo]) * down[lo] + (hi - lo).astype(np.uint64))
        lo, hi = self.open[a], self.close[b - 1]
        word = np.arange(len(hashes))
        of = self.words.documents()
        word = word[word + MIN_WORDS <= self.words.first[1:][of]]
        values = hashed(word, word + MIN_WORDS)
        chosen = smallest(values, of[word])
        word, values = word[chosen], values[chosen]
        return np.concatenate([doc[a], of[word]]), np.concatenate([lo, word]), np.concatenate([hi, np.zeros_like(word)]), np.concatenate([hashed(lo, hi), ~values])


def smallest(values: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Which values are the smallest (or equal to it) of any WINDOW neighbours of one document."""
    n = len(values) - WINDOW + 1
    if n <= 0:
        return np.zeros(len(values), dtype=bool)
    least = np.lib.stride_tricks.sliding_window_view(values, WINDOW).min(axis=1)
    least[doc[:n] != doc[WINDOW - 1 :]] = 0
    around = np.zeros(len(values), dtype=np.uint64)
    for k in range(WINDOW):
        np.maximum(around[k : k + n], least, out=around[k : k + n])
    return (values == around) & (around > 0)


@W.tidy
def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = batch.column("id")  # never null
        marks = batch.column("mark").to_numpy()
        for lo, _, data, offsets in W.slices(batch.column("text")):
            found = Sentences(data, offsets)
            doc, a, b, hashes = found.runs()
            place = (a - found.words.first[doc]) * PACK + np.where(b, b - a, 0) + (marks[doc + lo] << PLACE_BITS)
            order = np.lexsort((place, hashes, doc))
            again = np.zeros(len(order), dtype=bool)
            again[order[1:]] = (doc[order[1:]] == doc[order[:-1]]) & (hashes[order[1:]] == hashes[order[:-1]])
            # a later place of the document goes in any case: it is marked, and a key of the document's own keeps such rows together
            own = W.mix(ids.to_numpy()[doc + lo].view(np.uint64) ^ W._BASE)
            hashes = np.where(again, own, hashes)
            yield pa.RecordBatch.from_arrays(
                [pa.array(hashes.view(np.int64)), ids.take(pa.array(doc + lo)), pa.array(np.where(again, ~place, place))], names=["run", "id", "at"]
            )


def own_marks(docs: DataFrame) -> tuple[Column, Column]:
    """A row's identity (id, mark); the mark is 0, which takes no room in a shuffle, as long as no two rows share an id."""
    key, mark = identity()
    shared = docs.select(F.col("doc_id").cast("long").alias("doc_id")).where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    return key, F.lit(0).cast("long") if shared.isEmpty() else mark


def marked(docs: DataFrame, key: Column, mark: Column) -> DataFrame:
    """id, mark (the row's identity) and text."""
    return docs.select(key.alias("id"), mark.alias("mark"), F.col("text").cast("string").alias("text"))


def runs(texts: DataFrame) -> DataFrame:
    """run (hash), id, at: every run with its place (and digest); ``at`` is inverted where the document has the run before."""
    return texts.mapInArrow(_runs, "run long, id long, at long")


def hot_runs(texts: DataFrame) -> DataFrame | None:
    """The runs (HOT_SHARE at most) that very many documents have, by a sample; this moves work, not results."""
    sample = texts.where(F.pmod(F.xxhash64(F.lit("hot"), "id", "mark"), F.lit(SAMPLE)) == 0)
    counts = durable(runs(sample).where("at >= 0").groupBy("run").agg(F.count(F.lit(1)).alias("n")))
    total = counts.agg(F.sum("n")).first()[0] or 0
    hot = counts.where(F.col("n") >= max(HOT_LEAST, total / HOT_SHARE)).select("run")
    return hot if hot.count() else None


def later_places(texts: DataFrame) -> DataFrame:
    """id, mark, cuts (the place of each run that another place has first): a row for each document that has any."""
    hot, found, place = hot_runs(texts), runs(texts), F.struct("id", "at")
    own = F.when(F.col("at") >= 0, place)
    if hot is None:
        first = F.min(own).over(Window.partitionBy("run"))
        again = found.withColumn("first", first).where((F.col("at") < 0) | (place != F.col("first")))
    else:
        # a hot run's part goes into its key, so rows get no wider
        part = lambda run, number: F.xxhash64(run, number)
        keys = hot.select("run", F.explode(F.sequence(F.lit(0), F.lit(PARTS - 1))).alias("part")).select("run", part(F.col("run"), F.col("part")).alias("key"))
        number = F.pmod(F.xxhash64("id", "at"), F.lit(PARTS)).cast("int")
        key = F.when(F.col("hot"), part(F.col("run"), number)).otherwise(F.col("run"))
        dealt = found.join(F.broadcast(hot.withColumn("hot", F.lit(True))), "run", "left").select(key.alias("key"), "id", "at")  # HOT_SHARE rows at most
        # a window reads each run's places in one shuffle, where an aggregation and a join back take two
        dealt = dealt.withColumn("first", F.min(own).over(Window.partitionBy("key")))
        again = dealt.where((F.col("at") < 0) | (place != F.col("first"))).select("id", "at")
        leaders = dealt.where((F.col("at") >= 0) & (place == F.col("first"))).join(F.broadcast(keys), "key")  # PARTS times as many
        leaders = leaders.withColumn("first", F.min(place).over(Window.partitionBy("run")))
        again = again.unionByName(leaders.where(place != F.col("first")).select("id", "at"))
    at = F.when(F.col("at") < 0, F.bitwise_not("at")).otherwise(F.col("at"))
    cut, mark = at.bitwiseAND(F.lit((1 << PLACE_BITS) - 1)).alias("cut"), F.shiftright(at, PLACE_BITS).alias("mark")
    return again.select("id", mark, cut).groupBy("id", "mark").agg(F.collect_set("cut").alias("cuts"))  # bounded by the document


def covered(cuts: list[int], count: int) -> np.ndarray:
    """Which of a document's ``count`` words the runs cover."""
    depth = np.zeros(count + 1, dtype=np.int64)
    for c in cuts:
        depth[min(c // PACK, count)] += 1
        depth[min(c // PACK + (c % PACK or MIN_WORDS), count)] -= 1
    return np.cumsum(depth[:-1]) > 0


def _remover(keep: list[str], own_text: str, own_cuts: str):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            texts = batch.column(own_text)
            cuts = batch.column(own_cuts).to_pylist()
            removed, cut, sentences, gone_words = (np.zeros(n, np.int64) for _ in range(4))
            out: list = [None] * n
            for lo, hi, data, offsets in W.slices(texts):
                found = Sentences(data, offsets)
                sentences[lo:hi] = np.diff(found.first)
                start = found.words.start
                for d in range(hi - lo):
                    if cuts[lo + d] is None:
                        continue
                    base, count = int(found.words.first[d]), int(found.words.first[d + 1] - found.words.first[d])
                    spanned, gone = covered([c for c in cuts[lo + d] if c % PACK], count), covered(cuts[lo + d], count)
                    at = found.open[found.first[d] : found.first[d + 1]] - base
                    if count:  # a short sentence stays if any of its words does
                        part = np.repeat(~np.logical_and.reduceat(gone, at), np.diff(np.append(at, count)))
                        gone &= ~(part & found.short[base : base + count])
                        removed[lo + d] = spanned[at].sum()
                        cut[lo + d] = (np.logical_or.reduceat(gone, at) & ~spanned[at]).sum()
                    gone_words[lo + d] = gone.sum()
                    alive = np.ones(int(offsets[d + 1] - offsets[d]), dtype=bool)
                    edges = np.flatnonzero(np.diff(np.concatenate(([0], gone, [0]))))
                    for p, q in zip(edges[::2].tolist(), edges[1::2].tolist(), strict=True):  # words go with the white space behind them
                        stop = start[base + q] if q < count else offsets[d + 1]
                        alive[start[base + p] - offsets[d] : stop - offsets[d]] = False
                    out[lo + d] = data[offsets[d] : offsets[d + 1]][alive].tobytes().decode().rstrip("\x20\x09\x0a\x0b\x0c\x0d")
            column = pa.array([x if c is not None else None for x, c in zip(out, cuts, strict=True)], pa.large_string())
            whole = texts.cast(pa.large_string())
            text = pa.compute.coalesce(column, whole).cast(pa.string())
            columns = [text if c == "text" else batch.column(c) for c in keep]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(sentences), pa.array(removed), pa.array(cut), pa.array(gone_words)], names=[*keep, *OWN])

    return run


def remove(docs: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` (all but own results by default) with ``text`` less its repeats, and OWN."""
    docs, names = plain(docs)
    keep = [c for c in docs.columns if c not in OWN] if keep is None else [names.get(c, c) for c in keep]
    key, mark = own_marks(docs)
    own_id, own_mark, own_cuts, own_text = (fresh(f"__{c}", docs.columns) for c in ("id", "mark", "cuts", "text"))
    bounded_batches(docs.sparkSession)
    cuts = durable(later_places(marked(docs, key, mark))).select(F.col("id").alias(own_id), F.col("mark").alias(own_mark), F.col("cuts").alias(own_cuts))
    rows = docs.select(*(quoted(c) for c in keep), key.alias(own_id), mark.alias(own_mark), F.col("text").cast("string").alias(own_text))
    joined = rows.join(cuts.hint("shuffle_hash"), [own_id, own_mark], "left").drop(own_id, own_mark)
    fields = [T.StructField("text", T.StringType()) if f.name == "text" else f for f in docs.select(*(quoted(c) for c in keep)).schema]
    schema = T.StructType([*fields, *(T.StructField(c, T.LongType()) for c in OWN)])
    return restored(joined.mapInArrow(_remover(keep, own_text, own_cuts), schema), names)
