"""Dropping rows by their identity, with a broadcast only behind a check of its size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkveil.llm.columns import fresh, identity, quoted
from linkveil.session import durable

BROADCAST_ROWS = 500_000


def _anti(rows: DataFrame, found: dict, keys: DataFrame, limit: int) -> DataFrame:
    """``rows`` without those whose columns ``found`` are a row of ``keys``."""
    taken = rows.columns
    names = {c: fresh(f"__{c}", taken) for c in found}
    keys = durable(keys.select(*(F.col(c).alias(n) for c, n in names.items())).dropna().distinct())
    n = keys.count()
    if not n:
        return rows
    keys = F.broadcast(keys) if n <= limit else keys.hint("shuffle_hash")
    own = {c: fresh(f"__own_{c}", taken) for c in found}
    marked = rows.withColumns({own[c]: x for c, x in found.items()})
    same = [F.col(own[c]) == F.col(names[c]) for c in found]
    return marked.join(keys, same, "left_anti").select(*(quoted(c) for c in taken))


def drop_keys(rows: DataFrame, column: str, keys: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """``rows`` without those whose ``column`` is in the one column of ``keys``; null keys drop nothing.

    The keys are written and counted first.  Up to ``limit`` of them go to every task, so the rows aren't shuffled; more are
    joined by a shuffle of both sides.
    """
    return _anti(rows, {"key": quoted(column)}, keys.select(quoted(keys.columns[0]).alias("key")), limit)


def drop_documents(docs: DataFrame, gone: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """``docs`` without the documents whose identity (id, mark) is in ``gone``; see ``drop_keys``."""
    key, mark = identity()
    return _anti(docs, {"id": key, "mark": mark}, gone.select("id", "mark"), limit)
