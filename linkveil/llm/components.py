"""Connected components of a graph of integer ids: alternating large-star and small-star steps, or one task if there are few edges."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkveil.session import durable

#: Edges up to which one task (16 bytes an edge) takes the place of steps, each of which shuffles several times.
TASK_EDGES = 200_000
#: Edges of a written file, about: rounds over small graphs don't write many small ones.
EDGES_A_FILE = 100_000


def _solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    parts = [(b.column("u").to_numpy(), b.column("v").to_numpy()) for b in batches if b.num_rows]
    if not parts:
        return
    u, v = (np.concatenate(x) for x in zip(*parts, strict=True))
    ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(ids))
    while True:
        before = root.copy()
        least = np.minimum(before[a], before[b])
        np.minimum.at(root, before[a], least)
        np.minimum.at(root, before[b], least)
        while (root[root] != root).any():
            root = root[root]
        if (root == before).all():
            break
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[root])], names=["id", "root"])


def components(edges: DataFrame) -> DataFrame:
    """(id, root): for each id on an edge of ``edges`` (a, b), the smallest id that it reaches.

    Up to TASK_EDGES edges, which are counted, go to one task.  Of more, a step only takes minima by vertex and joins them back, so a vertex with very many edges is never collected; each
    step is written to the shared checkpoint folder.  The number of steps grows with the logarithm of the longest path.
    """
    edges = durable(
        edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    )
    state = _state(edges)
    if state[0] <= TASK_EDGES:
        return durable(edges.coalesce(1).mapInArrow(_solve, "id long, root long"))
    while True:
        both = edges.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u")
        found = small.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionAll(least.select("u", F.col("m").alias("v"))).distinct()
        edges = durable(found.coalesce(1 + state[0] // EDGES_A_FILE))
        before, state = state, _state(edges)
        if state == before:
            break
    roots = edges.select(F.col("u").alias("id"), F.col("v").alias("root"))
    return roots.unionAll(edges.select(F.col("v").alias("id"), F.col("v").alias("root")).distinct())


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x")).first()
    return row["n"], row["x"]
