"""Session helpers: lineage cuts that survive the loss of executors."""

from __future__ import annotations

import atexit
import gc
import re
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def checkpoint_dir(spark: SparkSession) -> str:
    """The folder all executors share, named by ``spark.checkpoint.dir``.

    Only under a local master a temporary local folder does instead, which goes with the process; on a cluster a session that
    names none is refused, as executors don't see each other's folders.
    """
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named:
            if not re.fullmatch(r"local(\[[^]]*\])?", context.master):
                raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
            named = tempfile.mkdtemp(prefix="linkveil-checkpoint-")
            atexit.register(shutil.rmtree, named, ignore_errors=True)
        context.setCheckpointDir(named)
    return context.getCheckpointDir()


def durable(df: DataFrame) -> DataFrame:
    """Writes ``df`` to the shared checkpoint folder and cuts its lineage there."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """Writes ``df`` as compressed columns to the shared checkpoint folder and reads it from there: a fraction of what ``durable`` takes.

    The files go with the process or with the folder."""
    spark = df.sparkSession
    path = f"{checkpoint_dir(spark)}/stored-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def released(spark: SparkSession) -> None:
    """Lets Spark's cleaner delete the shuffles that nothing refers to any more; else they stay until the driver's memory runs short."""
    gc.collect()
    spark._jvm.System.gc()


#: Rows up to which a table goes to every task of a join.
BROADCAST_ROWS = 200_000


def sent(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` for the small side of a join: sent to every task if it has at most ``limit`` rows, which is counted first, else left
    to a shuffle."""
    return F.broadcast(df) if df.select(F.lit(1)).limit(limit + 1).count() <= limit else df


def local_session(name: str = "linkveil", cores: str = "8", partitions: int = 8) -> SparkSession:
    """A local session for tests and for the bench."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName(name)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "6g")
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.cleaner.referenceTracking.cleanCheckpoints", "true")
        .getOrCreate()
    )


def bounded_batches(spark: SparkSession, rows: int = 2000) -> None:
    """At most ``rows`` rows in an Arrow batch from here on: with whole texts, batches of 10,000 rows take too much memory on both
    sides.  Plans read this setting when they run, so it can't be put back once a plan is handed out; every operator that reads
    texts sets it, so none depends on what ran before.  Sessions may change it at any time; a smaller value stays."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name, "10000")) <= rows:
        spark.conf.set(name, str(rows))
