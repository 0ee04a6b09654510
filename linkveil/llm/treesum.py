"""Sums of numpy arrays over partitions, level by level, so that neither a task nor the driver sees many."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from linkveil.llm import words as W
from linkveil.session import durable

SCHEMA = "slot int, total binary"


def emit(totals: dict[int, np.ndarray]) -> pa.RecordBatch:
    """A row (slot, float64 bytes) for each array of a partition."""
    return pa.RecordBatch.from_arrays(
        [pa.array(list(totals), pa.int32()), pa.array([np.ascontiguousarray(v, dtype=np.float64).tobytes() for v in totals.values()], pa.binary())],
        names=["slot", "total"],
    )


@W.tidy
def _add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    totals: dict[int, np.ndarray] = {}
    for batch in batches:
        for slot, raw in zip(batch.column("slot").to_pylist(), batch.column("total"), strict=True):
            part = np.frombuffer(raw.as_buffer(), dtype=np.float64)
            if slot in totals:
                totals[slot] += part
            else:
                totals[slot] = part.copy()
    if totals:
        yield emit(totals)


def tree_sum(df: DataFrame, summarise: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], fan_in: int = 16) -> dict[int, np.ndarray]:
    """Sums by slot of what ``summarise`` emits, once for each partition of ``df``; at most ``fan_in`` rows a slot reach the driver."""
    level = durable(df.mapInArrow(summarise, SCHEMA))
    rows = level.count()
    slots = max(1, level.select("slot").distinct().count()) if rows > fan_in else 1
    while rows > fan_in * slots:
        level = durable(level.repartition(math.ceil(rows / slots / fan_in)).mapInArrow(_add, SCHEMA))
        rows = level.count()
    out: dict[int, np.ndarray] = {}
    for slot, raw in level.toLocalIterator():
        part = np.frombuffer(bytes(raw), dtype=np.float64)
        out[slot] = out[slot] + part if slot in out else part.copy()
    return out
