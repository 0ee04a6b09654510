"""Files that parties exchange, and the columns that each may hold."""

from __future__ import annotations

import uuid
from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkveil.session import checkpoint_dir
from linkveil.sources.registry import ATTRIBUTES

_FILTER = frozenset([f"w{i}" for i in range(16)] + ["ones"])
_SECRETS = frozenset({"key", "owner_key", "salt"})
#: Columns that a party must never hold.
PARTIES: dict[str, frozenset[str]] = {
    "owner": frozenset({"g", "p", "truth", "label", "human"}),
    "top_unit": frozenset({"attr", "pair_key", "entity_id", *ATTRIBUTES}) | _SECRETS,
    "lower_unit": frozenset({"keys", "w4", "w15", "entity_id"}) | _SECRETS,
    "evaluator": _SECRETS,
}


def allowed(columns: Sequence[str], party: str) -> bool:
    return not PARTIES[party] & set(columns)


def assert_party_view(df: DataFrame, party: str) -> DataFrame:
    """The table, if the party may hold all of its columns."""
    bad = sorted(PARTIES[party] & set(df.columns))
    if bad:
        raise ValueError(f"{party} must not hold {', '.join(bad)}")
    return df


def send(df: DataFrame, party: str, path: str, fmt: str = "parquet", partition_by: Sequence[str] = ()) -> None:
    """Writes a table for a party after the check of its columns."""
    writer = assert_party_view(df, party).write.format(fmt).mode("errorifexists")
    if fmt == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def receive(spark, path: str, schema, fmt: str = "parquet") -> DataFrame:
    reader = spark.read.format(fmt).schema(schema)
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def write_candidates(df: DataFrame, path: str) -> None:
    """Candidates by band of similarity (hundredths), sorted inside, so that a round's range reads few files and row groups."""
    df.withColumn("band", F.floor(F.col("sim") * 100).cast("int")).repartition("band").sortWithinPartitions("sim").write.partitionBy("band").parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int = 16) -> None:
    """A table bucketed by a key, for joins without a shuffle."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)


def round_trip(df: DataFrame, formats: Sequence[str] = ("parquet", "orc", "json", "csv")) -> DataFrame:
    """(format, rows, same): rows written and read again in each format, and how many of them are unchanged."""
    spark, folder, out = df.sparkSession, f"{checkpoint_dir(df.sparkSession)}/exchange-{uuid.uuid4().hex}", None
    for fmt in formats:
        send(df, "top_unit", f"{folder}/{fmt}", fmt)
        back = receive(spark, f"{folder}/{fmt}", df.schema, fmt)
        counts = back.agg(F.count(F.lit(1)).alias("rows")).crossJoin(back.intersect(df).agg(F.count(F.lit(1)).alias("same")))  # one row each
        row = counts.select(F.lit(fmt).alias("format"), "rows", "same")
        out = row if out is None else out.unionByName(row)
    return out
