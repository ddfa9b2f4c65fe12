"""Reading of tables, and intermediate tables in the folder that all machines share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder in ``spark.checkpoint.dir``; a folder of this machine only where the session names none, as in tests."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    global _own
    if _own is None:
        _own = tempfile.mkdtemp(prefix="uncertainseq-")
    return f"file://{_own}"


_own: str | None = None


#: Spark's own setting under which the shuffle files of an execution go when it ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def materialise(df: DataFrame, name: str, codec: str = "snappy") -> DataFrame:
    """Write ``df`` once to the shared folder and return the stored table: a cut of lineage that outlives lost executors.

    The shuffle files of the write go when it ends; ``discard`` deletes the table once what was made of it is stored.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.option("compression", codec).parquet(path)
    finally:
        spark.conf.set(CLEANUP, before)
    stored = spark.read.schema(df.schema).parquet(path)
    stored.stored_at = path
    return stored


def discard(*tables: DataFrame) -> None:
    """Delete stored tables that nothing unwritten reads any more."""
    for stored in tables:
        path = stored.sparkSession._jvm.org.apache.hadoop.fs.Path(stored.stored_at)
        path.getFileSystem(stored.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def text_of(column: str = "text") -> Column:
    """The text, empty where it is null."""
    return F.coalesce(F.col(column), F.lit(""))


def fresh(df: DataFrame, name: str) -> str:
    """``name``, with underscores added until ``df`` has no such column."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


#: Rows of at most a few dozen bytes that may be sent to every executor; larger tables are joined by a shuffle.
BROADCAST_ROWS = 1_000_000


def small_or_shuffled(stored: DataFrame, most: int = BROADCAST_ROWS) -> DataFrame:
    """A stored narrow table, marked for broadcast if a count shows that it is small; else as it is, for a shuffled join."""
    return F.broadcast(stored) if stored.count() <= most else stored
