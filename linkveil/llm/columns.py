"""Names of columns that may hold any character, and names that clash with none; the identity of a row."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Bits of a text's digest beside the id.
MARK_BITS = 20


def quoted(name: str) -> Column:
    """The column of that very name, whatever is in it."""
    return F.col("`" + name.replace("`", "``") + "`")


def fresh(name: str, taken: Iterable[str]) -> str:
    """``name`` with as many underscores in front as none of ``taken`` has (names are told apart without case)."""
    low = {t.lower() for t in taken}
    while name.lower() in low:
        name = "_" + name
    return name


def identity() -> tuple[Column, Column]:
    """A row's own (id, mark): its doc_id, or for a null one a hash of its text, and MARK_BITS of the text's digest.

    Rows that share a doc_id are told apart by their texts; rows of equal id and text are one document."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    digest = F.xxhash64(text)
    return F.coalesce(F.col("doc_id").cast("long"), digest), F.pmod(digest, F.lit(1 << MARK_BITS))


def plain(df: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """``df`` with names that every function takes (no dot, no backtick), and the new name of each column renamed."""
    names = {c: fresh(f"__column_{i}", df.columns) for i, c in enumerate(df.columns) if "." in c or "`" in c}
    return df.select(*(quoted(c).alias(names.get(c, c)) for c in df.columns)), names


def restored(df: DataFrame, names: dict[str, str]) -> DataFrame:
    """``df`` with the names from before ``plain``."""
    back = {new: old for old, new in names.items()}
    return df.select(*(quoted(c).alias(back.get(c, c)) for c in df.columns)) if names else df
