"""Near-duplicate documents: b-bit MinHash signatures and a multi-index Hamming join.

1. A document's set are its distinct five-word shingles (as 64-bit hashes).  Each of SYMBOLS hash functions gives the
   minimum over the set, of which 16 bits are kept: a signature of 64 symbols.
2. Documents with equal sets form one class; only its smallest doc_id goes on.
3. Two sets of Jaccard 0.75 differ in 16 symbols on average.  Multi-index: the 64 symbols are split into 4 chunks of 3
   symbols, where no error is allowed, and 13 chunks of 4, where one is.  By the pigeonhole principle (4 * 1 + 13 * 2 =
   LIMIT + 1) every pair within LIMIT agrees in some chunk up to its allowed errors.  Errors are enumerated by leaving out
   each symbol in turn: 4 + 13 * 4 = 56 keys of three symbols (48 bits).  Pairs that share a key are tested up to REACH, so
   a pair at exactly 0.75 is lost if it shares none (3e-9) or lies beyond REACH = 36 (2.5e-8).
4. Groups of near copies may be very large, so pairs in a bucket are not all written out.  Each document has a hub: of
   the most crowded members of its buckets the most crowded one.  Each is compared with its hub on the full sets, which
   joins most of a group.  Shingles outside the hub that over HOT documents of the group have are taken to the hub's:
   together they are the group's common set C.  With D(x) the elements in which x and C differ, x and y are linked exactly
   if (n(x) + n(y)) / 7 >= |D(x)| + |D(y)| - 2 |D(x) & D(y)|, so the document with the most slack n / 7 - |D| is linked with
   every one that is linked with any without sharing an element of D.  The CENTRAL documents with most slack are compared
   with the whole group, one row a document.  What may be left are links between different components of a group.  Let c be
   the size of a document's intersection with C; x and y share min(c(x), c(y)) of it at most.  So a link either takes shingles
   outside of C as well (``sharing_pairs``, a join on the rarest of them), or c suffices alone (``full_pairs``, between
   documents outside the group's main component and the rest, dealt into parts).  Pairs of a bucket with different hubs,
   in different components and of fitting sizes are candidates as well.
5. Each link is confirmed on the full sets: 100 * intersection >= 75 * union.

Defined cases: null, empty and blank texts have the empty set, are linked with nothing and kept.  Rows that share a
doc_id are taken as one document in links.  A null doc_id is linked with nothing; its component_id is null and it is
kept.  An empty table gives an empty result.  A similarity of just 0.75 links.  Very long texts are read whole; a document's
set is held by one task.  Only doc_id and text are read, so other columns of any name do no harm.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from linkveil.llm import words as W
from linkveil.llm.components import components
from linkveil.llm.dropping import drop_keys
from linkveil.session import bounded_batches, durable

SHINGLE = 5
PERCENT = 75
SYMBOLS = 64
LANES = SYMBOLS // 4
LIMIT = 29
REACH = 36
HOT = 32
CENTRAL = 3
EXACT_CHUNKS, LOOSE_CHUNKS = 4, 13
SALTS = 32
PART = 4096
_MULTIPLIERS = np.random.default_rng(7).integers(1, 2**63, SYMBOLS, dtype=np.uint64) * W.U(2) + W.U(1)
SIGNATURE = [f"s{i}" for i in range(LANES)]


def shingle_sets(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingles of all documents of a slice, and where each document's begin."""
    words = W.Words(data, offsets)
    hashes, counts = words.hashes(), words.counts()
    n_docs = len(counts)
    keys, starts = W.windows(hashes, words.first, SHINGLE)
    of = np.searchsorted(words.first, starts, side="right") - 1
    short = np.flatnonzero((counts > 0) & (counts < SHINGLE))
    if len(short):  # the whole sequence is the one shingle
        whole = []
        for d in short.tolist():
            total = W.U(int(counts[d]))
            for h in hashes[words.first[d] : words.first[d + 1]]:
                total = np.uint64((int(total) * 0x9FB21C651E98DF25 + int(h)) & 0xFFFFFFFFFFFFFFFF)
            whole.append(total)
        keys, of = np.concatenate([keys, W.mix(np.array(whole, dtype=np.uint64))]), np.concatenate([of, short])
        order = np.argsort(of, kind="stable")
        keys, of = keys[order], of[order]
    begin = np.searchsorted(of, np.arange(n_docs + 1))
    for lo, hi in zip(begin[:-1].tolist(), begin[1:].tolist(), strict=True):
        keys[lo:hi].sort()
    fresh = np.ones(len(keys), dtype=bool)
    fresh[1:] = keys[1:] != keys[:-1]
    fresh[begin[:-1][begin[:-1] < len(keys)]] = True
    sizes = W.per_document(fresh, begin)
    return keys[fresh], np.concatenate(([0], np.cumsum(sizes)))


def signatures(keys: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each set that isn't empty: two 64-bit sums that stand for the set, and LANES words of four symbols."""
    at = begin[:-1][np.diff(begin) > 0]
    if not len(at):
        return np.zeros((0, 2), dtype=np.uint64), np.zeros((0, LANES), dtype=np.uint64)
    sums = np.stack([np.add.reduceat(keys, at), np.add.reduceat(W.mix(keys ^ W._BASE), at)], axis=1)
    lanes = np.zeros((len(at), LANES), dtype=np.uint64)
    for j in range(SYMBOLS):
        least = np.minimum.reduceat(keys * _MULTIPLIERS[j], at)
        lanes[:, j // 4] |= (W.mix(least) >> W.U(48)) << W.U(16 * (j % 4))
    return sums, lanes


@W.tidy
def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n = batch.num_rows
        size, sums, lanes = np.zeros(n, dtype=np.int64), np.zeros((n, 2), dtype=np.uint64), np.zeros((n, LANES), dtype=np.uint64)
        for lo, hi, data, offsets in W.slices(batch.column("text")):
            keys, begin = shingle_sets(data, offsets)
            size[lo:hi] = np.diff(begin)
            full = lo + np.flatnonzero(size[lo:hi])
            sums[full], lanes[full] = signatures(keys, begin)
        columns = [sums[:, 0], sums[:, 1], *(lanes[:, j] for j in range(LANES))]
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), pa.array(size), *(pa.array(np.ascontiguousarray(c).view(np.int64)) for c in columns)],
            names=["doc_id", "n_shingles", "h1", "h2", *SIGNATURE],
        )


def sign(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, h1, h2 and the signature of each row."""
    schema = "doc_id long, n_shingles long, h1 long, h2 long, " + ", ".join(f"{s} long" for s in SIGNATURE)
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_sign, schema)


@W.tidy
def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for first, end, data, offsets in W.slices(batch.column("text")):
            keys, begin = shingle_sets(data, offsets)
            raw = keys.tobytes()
            sets = [raw[8 * lo : 8 * hi] for lo, hi in zip(begin[:-1].tolist(), begin[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(first, end - first), pa.array(sets, pa.binary())], names=["id", "shingles"])


def chunk_keys() -> list[Column]:
    """The 56 keys of a signature: the number of the key and three symbols."""

    def symbol(j: int) -> Column:
        return F.shiftrightunsigned(F.col(SIGNATURE[j // 4]), 16 * (j % 4)).bitwiseAND(F.lit(0xFFFF))

    chosen, at = [], 0
    for _ in range(EXACT_CHUNKS):
        chosen.append((at, at + 1, at + 2))
        at += 3
    for _ in range(LOOSE_CHUNKS):
        chunk = range(at, at + 4)
        chosen += [tuple(x for x in chunk if x != left_out) for left_out in chunk]
        at += 4
    return [
        F.lit(k << 48).bitwiseOR(F.shiftleft(symbol(a), 32)).bitwiseOR(F.shiftleft(symbol(b), 16)).bitwiseOR(symbol(c))
        for k, (a, b, c) in enumerate(chosen)
    ]


def distance(left: str, right: str) -> Column:
    """Symbols in which two signatures differ: 16-bit lanes of the exclusive or that aren't zero."""
    total = F.lit(0)
    for s in SIGNATURE:
        x = F.col(f"{left}.{s}").bitwiseXOR(F.col(f"{right}.{s}"))
        for step in (8, 4, 2, 1):
            x = x.bitwiseOR(F.shiftrightunsigned(x, step))
        total = total + F.bit_count(x.bitwiseAND(F.lit(0x0001000100010001)))
    return total


def sizes_fit(a: Column, b: Column) -> Column:
    return (F.least(a, b) * 100 >= F.greatest(a, b) * PERCENT)


@W.tidy
def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        good = []
        for x, y in zip(batch.column("left_set"), batch.column("right_set"), strict=True):
            x, y = np.frombuffer(x.as_buffer(), dtype=np.uint64), np.frombuffer(y.as_buffer(), dtype=np.uint64)
            both = len(np.intersect1d(x, y, assume_unique=True))
            good.append(100 * both >= PERCENT * (len(x) + len(y) - both))
        yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))


def confirm(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (a, b) whose full sets are similar enough."""
    left = pairs.join(sets.withColumnsRenamed({"id": "a", "shingles": "left_set"}), "a")
    both = left.join(sets.withColumnsRenamed({"id": "b", "shingles": "right_set"}), "b")
    return both.select("a", "b", "left_set", "right_set").mapInArrow(_confirm, "a long, b long")


def classes(signed: DataFrame) -> DataFrame:
    """One row for each different set: its smallest doc_id as ``id``, the sums of the set, and the signature."""
    return signed.where("n_shingles > 0 AND doc_id IS NOT NULL").groupBy("h1", "h2", "n_shingles").agg(
        F.min("doc_id").alias("id"), *(F.first(s).alias(s) for s in SIGNATURE)
    )


def enough(common: Column, a: Column, b: Column) -> Column:
    """Whether sets of sizes a and b with so many elements in common are linked: Jaccard p / 100 means (100 + p) common >= p (a + b)."""
    return common * (100 + PERCENT) >= (a + b) * PERCENT


@W.tidy
def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n, n_hub, common, extra = [], [], [], []
        for x, h in zip(batch.column("own_set"), batch.column("hub_set"), strict=True):
            x, h = np.frombuffer(x.as_buffer(), dtype=np.uint64), np.frombuffer(h.as_buffer(), dtype=np.uint64)
            at = np.minimum(np.searchsorted(h, x), len(h) - 1)
            shared = h[at] == x
            n.append(len(x))
            n_hub.append(len(h))
            common.append(int(shared.sum()))
            extra.append(x[~shared].view(np.int64))
        yield pa.RecordBatch.from_arrays(
            [batch.column("id"), batch.column("hub"), batch.column("parts"), pa.array(n, pa.int64()), pa.array(n_hub, pa.int64()), pa.array(common, pa.int64()), pa.array(extra, pa.list_(pa.int64()))],
            names=["id", "hub", "parts", "n", "n_hub", "c", "extra"],
        )


def hubs(members: DataFrame) -> DataFrame:
    """(id, hub, parts) from (key, id, n): of the leaders of an id's buckets the one with most neighbours; ties to the smallest id.

    A group has fewer documents than its hub has neighbours, and there are parts by PART neighbours, SALTS at most."""
    crowd = members.groupBy("id").agg(F.sum("n").alias("crowd"))
    leaders = members.join(crowd, "id").groupBy("key").agg(F.max(F.struct("crowd", (-F.col("id")).alias("minus"))).alias("leader"))
    best = members.select("key", "id").join(leaders, "key").groupBy("id").agg(F.max("leader").alias("leader"))
    parts = F.least(F.lit(SALTS), 1 + F.floor(F.col("leader.crowd") / PART)).cast("int")
    return best.select("id", (-F.col("leader.minus")).alias("hub"), parts.alias("parts"))


def with_common_sets(compared: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(id, hub, parts, n, c, root) with c against the group's common set, and (hub, id, shingle, df) outside of it that two documents or more have.

    ``root`` is the hub for the documents that are linked with it."""
    each = compared.select("hub", "id", F.explode("extra").alias("shingle"))
    counts = each.groupBy("hub", "shingle").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    shared = durable(each.join(counts, ["hub", "shingle"]))
    hot = shared.where(F.col("df") > HOT).groupBy("id").agg(F.count(F.lit(1)).alias("hot"))
    root = F.when(enough(F.col("c"), F.col("n"), F.col("n_hub")), F.col("hub")).otherwise(F.col("id")).alias("root")
    sizes = compared.select("id", "hub", "parts", "n", "c", root).join(hot, "id", "left")
    sizes = sizes.select("id", "hub", "parts", "n", (F.col("c") + F.coalesce("hot", F.lit(0))).alias("c"), "root")
    return durable(sizes), shared.where(F.col("df") <= HOT)


def dealt(rows: DataFrame) -> DataFrame:
    """``rows`` with the part of their hub's group that they belong to, so that no large group meets in one task."""
    return rows.withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int"))


def repeated(rows: DataFrame) -> DataFrame:
    """``rows`` once for each part of a group."""
    return rows.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))


def central_pairs(placed: DataFrame) -> DataFrame:
    """(a, b): each document with the CENTRAL ones of its hub, unless both are linked with the hub."""
    order = Window.partitionBy("hub").orderBy(F.desc(7 * F.col("c") - 3 * F.col("n")), "id")
    best = placed.withColumn("place", F.row_number().over(order)).where(F.col("place") <= CENTRAL)
    best = repeated(best.select("hub", "parts", F.col("id").alias("a"), F.col("root").alias("a_root"))).drop("parts")
    return dealt(placed).join(best, ["hub", "part"]).where("root <> a_root").select("a", F.col("id").alias("b"))


def sharing_pairs(placed: DataFrame, shared: DataFrame) -> DataFrame:
    """Pairs (a, b) of one hub and of different components that shingles outside the common set may link.

    A partner of x shares at least 0.75 n(x) of its shingles, of them c(x) of the common set at most, so ``need`` or more of
    the ``own`` others.  Two sets with so many elements in common share one of the first own - need + 1 in any order that both
    follow; rare ones come first here.  Behind the last such element no more are shared than either has left."""
    order = Window.partitionBy("hub", "id").orderBy("df", "shingle")
    need = F.greatest(F.ceil(F.col("n") * PERCENT / 100) - F.col("c"), F.lit(1))
    rare = (
        shared.join(placed, ["hub", "id"])
        .withColumn("at", F.row_number().over(order))
        .withColumn("own", F.count(F.lit(1)).over(Window.partitionBy("hub", "id")))
        .where(F.col("at") <= F.col("own") - need + 1)
        .withColumn("left", F.col("own") - F.col("at"))
    )
    x, y = rare.alias("x"), rare.alias("y")
    same = (F.col("x.hub") == F.col("y.hub")) & (F.col("x.shingle") == F.col("y.shingle"))
    apart = (F.col("x.id") < F.col("y.id")) & (F.col("x.root") != F.col("y.root")) & sizes_fit(F.col("x.n"), F.col("y.n"))
    able = enough(F.least("x.own", "y.own") + F.least("x.c", "y.c"), F.col("x.n"), F.col("y.n"))
    met = x.join(y, same & apart & able).groupBy(F.col("x.id").alias("a"), F.col("y.id").alias("b")).agg(
        (F.count(F.lit(1)) + F.min(F.least("x.left", "y.left"))).alias("k"),
        F.first(F.least("x.c", "y.c")).alias("c"), F.first("x.n").alias("n"), F.first("y.n").alias("m"),
    )
    return met.where(enough(F.col("k") + F.col("c"), F.col("n"), F.col("m"))).select("a", "b")


def full_pairs(placed: DataFrame, nodes: DataFrame) -> DataFrame:
    """Pairs (a, b) of one hub and of different components that the common set alone may link: one is outside the group's main component."""
    joined = placed.groupBy("hub", "parts", "root").agg(F.min("n").alias("least_n"), F.count(F.lit(1)).alias("size"))
    group = joined.groupBy("hub", "parts").agg(F.min("least_n").alias("least_n"), F.max(F.struct("size", "root")).alias("main"))
    group = repeated(group.select("hub", "parts", "least_n", F.col("main.root").alias("main"))).drop("parts")
    full = dealt(placed).join(group, ["hub", "part"]).where(enough(F.col("c"), F.col("n"), F.col("least_n")))
    full = full.join(nodes.select("id", *SIGNATURE), "id")
    x, y = repeated(full.where("root <> main")).alias("x"), full.alias("y")
    apart = (F.col("x.root") != F.col("y.root")) & ((F.col("y.root") == F.col("y.main")) | (F.col("x.id") < F.col("y.id")))
    may = enough(F.least("x.c", "y.c"), F.col("x.n"), F.col("y.n")) & (distance("x", "y") <= REACH)
    alone = x.join(y, (F.col("x.hub") == F.col("y.hub")) & (F.col("x.part") == F.col("y.part")) & apart & may)
    return alone.select(F.col("x.id").alias("a"), F.col("y.id").alias("b"))


def links(nodes: DataFrame, docs: DataFrame) -> DataFrame:
    """Links (a, b) between classes of one component, enough of them to join all that are linked; each rests on confirmed ones."""
    keyed = nodes.select("id", F.explode(F.array(*chunk_keys())).alias("key"))
    buckets = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    members = durable(keyed.join(buckets, "key"))
    chosen = durable(hubs(members))

    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    wanted = chosen.select(F.col("id").alias("doc_id"))
    sets = durable(
        texts.join(wanted.hint("shuffle_hash"), "doc_id", "left_semi").mapInArrow(_sets, "id long, shingles binary")
    )
    own = chosen.where("id <> hub").join(sets.withColumnRenamed("shingles", "own_set"), "id")
    both = own.join(sets.withColumnsRenamed({"id": "hub", "shingles": "hub_set"}), "hub")
    compared = durable(
        both.select("id", "hub", "parts", "own_set", "hub_set").mapInArrow(_compare, "id long, hub long, parts int, n long, n_hub long, c long, extra array<long>")
    )
    first = compared.where(enough(F.col("c"), F.col("n"), F.col("n_hub"))).select(F.col("id").alias("a"), F.col("hub").alias("b"))
    sizes, shared = with_common_sets(compared)
    roots = components(first.unionAll(confirm(central_pairs(sizes), sets)))
    placed = durable(sizes.drop("root").join(roots, "id", "left").withColumn("root", F.coalesce("root", "id")))

    where = members.select("key", "id").join(chosen, "id").join(roots, "id", "left").withColumn("root", F.coalesce("root", "id"))
    spread = [f(c).alias(f"{f.__name__}_{c}") for c in ("root", "hub") for f in (F.min, F.max)]
    mixed = where.groupBy("key").agg(*spread).where("min_root <> max_root AND min_hub <> max_hub").select("key")
    rest = where.join(mixed, "key", "left_semi").join(nodes.drop("h1", "h2"), "id")
    x, y = rest.alias("x"), rest.alias("y")
    apart = (F.col("x.key") == F.col("y.key")) & (F.col("x.id") < F.col("y.id")) & (F.col("x.root") != F.col("y.root"))
    apart &= (F.col("x.hub") != F.col("y.hub")) & (F.col("x.hub") != F.col("y.id")) & (F.col("y.hub") != F.col("x.id"))
    near = (distance("x", "y") <= REACH) & sizes_fit(F.col("x.n_shingles"), F.col("y.n_shingles"))
    across = x.join(y, apart & near).select(F.col("x.id").alias("a"), F.col("y.id").alias("b"))
    pairs = across.unionAll(sharing_pairs(placed, shared)).unionAll(full_pairs(placed, nodes)).distinct()
    return roots.select(F.col("id").alias("a"), F.col("root").alias("b")).unionAll(confirm(pairs, sets))


def find(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id that links reach), kept (the document is that one)."""
    bounded_batches(docs.sparkSession)
    signed = durable(sign(docs))
    nodes = durable(classes(signed))
    roots = components(links(nodes, docs))
    salt = F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt")
    placed = nodes.select("h1", "h2", "n_shingles", "id").join(roots, "id", "left").select(
        "h1", "h2", "n_shingles", F.coalesce("root", "id").alias("root"), salt
    )
    rows = signed.select("doc_id", "n_shingles", "h1", "h2", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int").alias("salt"))
    joined = rows.join(placed, ["h1", "h2", "n_shingles", "salt"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("root", "doc_id"))
    return joined.select("doc_id", "n_shingles", component.alias("component_id")).withColumn(
        "kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True))
    )


def keep_one(docs: DataFrame) -> DataFrame:
    """One document of each component, with the columns of ``docs``."""
    return drop_keys(docs, "doc_id", find(docs).where("NOT kept").select("doc_id"))
