"""SentencePiece encoding and decoding by a shared-prefix Viterbi recursion.

The vocabulary is a public SentencePiece model with BPE merges and byte fallback; it is read, never trained.  A text is
marked (a blank in front, blanks as U+2581) and cut into marked words; no piece crosses such a cut.  The distinct words
of a slice are sorted, so that walking them in order is a depth-first walk of their trie, and the forward states of a
common prefix are kept from word to word.

The forward recursion of each prefix scores the pieces that may end there.  With BPE merges the score of a path is 0 if
every two neighbouring pieces stay apart when their strings are merged by rank, else minus infinity; just one path of
each prefix is admissible, and it is what merging the prefix gives.  So the state of a prefix is its last piece.  Whether
two pieces stay apart is found by merging their joined string, and kept.

Defined cases: a null text gives null tokens; an empty one gives none; U+2581 in a text counts as a blank.  Very long
words take time in proportion to their length.  Repeated rows give repeated rows, an empty table an empty result.  Columns
named as an own result (n_tokens, token_ids, round_trip) give way to it; others of any name stay.  A prefix has one
admissible path, so there are no ties.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from linkveil.llm import words as W
from linkveil.llm.columns import plain, quoted, restored
from linkveil.session import bounded_batches

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁"
KEPT_WORDS = 300_000
GROUP = 768


class Vocabulary:
    """Pieces of a SentencePiece BPE model, sendable to tasks."""

    def __init__(self, pieces: list[tuple[str, float, str]]):
        self.ids = {p: i for i, (p, _, kind) in enumerate(pieces) if kind == "normal"}
        self.scores = {p: s for p, s, kind in pieces if kind == "normal"}
        self.byte_ids = [0] * 256
        self.bytes_of = []
        for i, (p, _, kind) in enumerate(pieces):
            if kind == "byte":
                self.byte_ids[int(p[3:5], 16)] = i
            self.bytes_of.append(p.replace(MARK, " ").encode() if kind == "normal" else bytes([int(p[3:5], 16)]) if kind == "byte" else b"")
        self.longest = max(map(len, self.ids), default=1)
        if any(MARK in p.lstrip(MARK) for p in self.ids):
            raise ValueError("a piece has a blank inside; words can't be cut at blanks")
        self.break_lines = not any("\n" in p for p in self.ids if len(p) > 1)
        self.cut = re.compile(r"\n| *[^ \n]+| +" if self.break_lines else r" *[^ ]+| +")
        self.apart: dict[tuple[str, str], bool] = {}
        self.raw = {p: i.to_bytes(2, "little") for p, i in self.ids.items()}
        self.good = {p for p in self.ids if self.merge(p) == [p]}  # a piece that merging never makes can't end a path

    def __reduce__(self):
        raise TypeError("send the pieces instead")

    def merge(self, text: str) -> list[str]:
        """Merges by best score, leftmost first; for short strings."""
        parts, none = list(text), -float("inf")
        score = self.scores.get
        gains = [score(x + y, none) for x, y in zip(parts, parts[1:], strict=False)]
        while gains and (best := max(gains)) > none:
            at = gains.index(best)
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
            del gains[at]
            if at:
                gains[at - 1] = score(parts[at - 1] + parts[at], none)
            if at < len(gains):
                gains[at] = score(parts[at] + parts[at + 1], none)
        return parts

    def stay_apart(self, a: str, b: str) -> bool:
        known = self.apart.get((a, b))
        if known is None:
            known = self.merge(a + b) == [a, b]
            if len(self.apart) < 200_000:
                self.apart[a, b] = known
        return known

    def fall_back(self, piece: str) -> bytes:
        """Ids of the bytes of a character that is no piece."""
        return b"".join(self.byte_ids[b].to_bytes(2, "little") for b in piece.encode("utf-8", "surrogatepass"))

    def encode_words(self, words: list[str]) -> Iterator[tuple[str, bytes]]:
        """(word, its ids as two-byte numbers), for sorted marked words."""
        last: list[str] = [""]  # last[i]: the last piece of the word's first i characters
        before = ""
        good, longest, apart, raw = self.good, self.longest, self.apart, self.raw
        for word in words:
            n, same = len(word), 0
            for x, y in zip(word, before, strict=False):
                if x != y:
                    break
                same += 1
            del last[same + 1 :]
            for i in range(same + 1, n + 1):
                # just one piece fits; mostly the last one grown by the character, or the character alone
                end, prev = word[i - 1], last[-1]
                piece = prev + end
                if piece in good:
                    j = i - len(piece)
                    fits = j == 0 or apart.get((last[j], piece))
                    if fits is None:
                        fits = self.stay_apart(last[j], piece)
                    if fits:
                        last.append(piece)
                        continue
                if i > 1:
                    fits = apart.get((prev, end))
                    if fits is None:
                        fits = self.stay_apart(prev, end)
                    if fits:
                        last.append(end)
                        continue
                for j in range(i - longest if i > longest else 0, i):
                    piece = word[j:i]
                    if piece in good or j == i - 1:
                        fits = j == 0 or apart.get((last[j], piece))
                        if fits is None:
                            fits = self.stay_apart(last[j], piece)
                        if fits:
                            last.append(piece)
                            break
            before = word
            path, i = [], n
            while i > 0:
                piece = last[i]
                path.append(raw.get(piece) or self.fall_back(piece))
                i -= len(piece)
            path.reverse()
            yield word, b"".join(path)

    def encode_texts(self, texts: list[str | None], known: list[dict[str, bytes]]) -> list[np.ndarray | None]:
        """Ids of each text. ``known``: ids of words met of late and before; the older half goes when both are full."""
        cut = [self.cut.findall(" " + t.replace(MARK, " ")) if t else [] for t in texts]
        words = set().union(*cut)
        if len(known[0]) > KEPT_WORDS // 2:
            known[:] = [{}, known[0]]
        new, old = known
        words -= new.keys()
        again = words & old.keys()
        new.update(zip(again, map(old.__getitem__, again), strict=True))
        fresh = sorted(w.replace(" ", MARK) for w in words - again)
        new.update((w.replace(MARK, " "), b) for w, b in self.encode_words(fresh))
        return [None if t is None else np.frombuffer(b"".join(map(new.__getitem__, c)), dtype="<u2") for t, c in zip(texts, cut, strict=True)]

    def decode(self, ids: list[int]) -> str:
        raw = b"".join(map(self.bytes_of.__getitem__, ids))
        return (raw[1:] if raw[:1] == b" " else raw).decode("utf-8", "replace")


def read_pieces(path: str = MODEL) -> list[tuple[str, float, str]]:
    """(piece, score, kind) of a model file; read on the driver, bounded by the file."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    kind = lambda i: "byte" if model.is_byte(i) else "control" if model.is_control(i) or model.is_unknown(i) else "normal"
    return [(model.id_to_piece(i), model.get_score(i), kind(i)) for i in range(model.get_piece_size())]


_cache: dict = {}


def _loaded(broadcast) -> Vocabulary:
    """One vocabulary for each Python worker and broadcast."""
    pieces = broadcast.value
    if _cache.get("of") is not pieces:
        _cache.update(of=pieces, vocabulary=Vocabulary(pieces))
    return _cache["vocabulary"]


def _ids_array(ids: list[np.ndarray | None]) -> pa.Array:
    sizes = np.array([0 if x is None else len(x) for x in ids], dtype=np.int32)
    offsets = np.concatenate(([0], np.cumsum(sizes))).astype(np.int32)
    flat = np.concatenate([x for x in ids if x is not None] or [np.zeros(0, np.uint16)]).astype(np.int32)
    missing = pa.array([x is None for x in ids], pa.bool_())
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat), mask=missing)


def _encoder(broadcast, keep: list[str]):
    @W.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = _loaded(broadcast)
        known: list[dict[str, bytes]] = [{}, {}]
        for batch in batches:
            for lo in range(0, batch.num_rows, GROUP):
                part = batch.slice(lo, GROUP)
                texts = part.column("text").to_pylist()
                ids = vocabulary.encode_texts(texts, known)
                decoded = [None if x is None else vocabulary.decode(x.tolist()) for x in ids]
                good = [None if d is None else d == t.replace(MARK, " ") for d, t in zip(decoded, texts, strict=True)]
                columns = [part.column(c) if c != "text" else pa.array(decoded, pa.string()) for c in keep]
                sizes = pa.array([None if x is None else len(x) for x in ids], pa.int64())
                yield pa.RecordBatch.from_arrays([*columns, sizes, _ids_array(ids), pa.array(good, pa.bool_())], names=[*keep, "n_tokens", "token_ids", "round_trip"])

    return run


def encode(docs: DataFrame, keep: list[str] | None = None, model: str = MODEL) -> DataFrame:
    """The columns ``keep`` (all but own results by default; ``text`` as decoded from its ids), n_tokens, token_ids, round_trip."""
    own = ["n_tokens", "token_ids", "round_trip"]
    docs, names = plain(docs)
    keep = [c for c in docs.columns if c not in own] if keep is None else [names.get(c, c) for c in keep]
    bounded_batches(docs.sparkSession)
    broadcast = docs.sparkSession.sparkContext.broadcast(read_pieces(model))
    source = docs.select(*(quoted(c) for c in dict.fromkeys([*keep, "text"])))
    kept = docs.select(*(quoted(c) for c in keep)).schema
    own_fields = [T.StructField("n_tokens", T.LongType()), T.StructField("token_ids", T.ArrayType(T.IntegerType())), T.StructField("round_trip", T.BooleanType())]
    return restored(source.mapInArrow(_encoder(broadcast, keep), T.StructType([*kept, *own_fields])), names)


def decode(encoded: DataFrame, model: str = MODEL, column: str = "token_ids") -> DataFrame:
    """Adds ``decoded``, the text of ``token_ids``; null for null."""
    broadcast = encoded.sparkSession.sparkContext.broadcast(read_pieces(model))

    @F.pandas_udf("string")
    def text(ids):
        vocabulary = _loaded(broadcast)
        return ids.map(lambda x: None if x is None else vocabulary.decode(x))

    return encoded.withColumn("decoded", text(F.col(column)))
