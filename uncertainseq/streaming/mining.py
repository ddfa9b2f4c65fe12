"""Incremental miners over a stream of files: every micro-batch is an increment of whole new sequences."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from uncertainseq.functions.sequences import clean
from uncertainseq.operators.incremental import IncrementalMiner, StateStore
from uncertainseq.operators.mining import Database

#: The flat form of an increment; a stream's schema is stated, never inferred.
FLAT = "seq_id long, eid long, item_id int, p double"


def read_increments(spark: SparkSession, source_dir: str, files_per_batch: int | None = None) -> DataFrame:
    """A stream of Parquet files in ``source_dir``, in order of arrival, at most so many in a micro-batch."""
    reader = spark.readStream.schema(FLAT)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.parquet(source_dir)


def run_stream(
    miner: IncrementalMiner, increments: DataFrame, weights: dict[int, float], names: dict[int, str], checkpoint: str, store: StateStore | None = None, available_now: bool = True,
) -> StreamingQuery:
    """Start a query that hands every micro-batch to ``miner``; with ``available_now`` it ends when all present files are taken.

    A batch delivered twice counts once: the miner knows the batches it took, and with ``store`` so does a miner that
    starts anew, as its state is committed before Spark marks the batch done. An empty batch changes nothing. Rows of
    items without a weight, or without a positive probability, cannot be scored and are left out.
    """
    if store:
        store.restore(miner)
    known = increments.sparkSession.createDataFrame([(i,) for i in weights], "item_id int")

    def take(batch: DataFrame, batch_id: int) -> None:
        if batch_id in miner.batches:
            return
        flat = clean(batch.join(known, "item_id", "left_semi").withColumn("batch_id", F.lit(batch_id).cast("int"))).persist()
        try:
            if not flat.isEmpty():
                delta = Database(flat, weights, names)
                miner.update(delta, batch_id) if miner.batches else miner.start(delta, batch_id)
                delta.release()
                if store:
                    store.commit(miner)
        finally:
            flat.unpersist()

    writer = increments.writeStream.foreachBatch(take).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()
