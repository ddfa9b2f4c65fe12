"""Event streams: windows, replays, and the assembly of whole sessions with late rows set aside.

Events are rows (event_id, user_id, ts, ...). ``windowed`` and ``without_replays`` are Spark's own stateful operators; ``run_sessions``
keeps its open events as stored tables, so that what is late is known row by row, which a dropped row is not.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

EVENTS = "event_id long, user_id long, ts timestamp, event_type string"


def read_events(spark: SparkSession, source_dir: str, files_per_batch: int | None = None, schema: str = EVENTS) -> DataFrame:
    """A stream of Parquet files of events, at most so many files in a micro-batch."""
    reader = spark.readStream.schema(schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.parquet(source_dir)


def without_replays(events: DataFrame, delay: str) -> DataFrame:
    """The events, one of each event_id; state is kept for ``delay`` behind the latest event."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def windowed(events: DataFrame, width: str, slide: str | None = None, delay: str | None = None) -> DataFrame:
    """Events by user and window, tumbling without ``slide``: (user_id, start, end, n). A stream that has a watermark takes no second one."""
    span = F.window("ts", width, slide) if slide else F.window("ts", width)
    marked = events.withWatermark("ts", delay) if delay else events
    counts = marked.groupBy("user_id", span.alias("span")).agg(F.count("*").alias("n"))
    return counts.select("user_id", F.col("span.start").alias("start"), F.col("span.end").alias("end"), "n")


def session_numbers(events: DataFrame, gap: str) -> DataFrame:
    """``events`` with the start and the last time of their session: a user's events with less than ``gap`` between neighbours."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    fresh = F.coalesce((F.col("ts") >= F.lag("ts").over(order) + F.expr(f"interval {gap}")).cast("int"), F.lit(1))
    nth = events.withColumn("fresh", fresh).withColumn("nth", F.sum("fresh").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    whole = Window.partitionBy("user_id", "nth")
    return nth.withColumns({"start": F.min("ts").over(whole), "last": F.max("ts").over(whole)}).drop("fresh", "nth")


def assembled(events: DataFrame) -> DataFrame:
    """(user_id, start, last, events): a row a session, its events in order."""
    return events.groupBy("user_id", "start", "last").agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("events"))


class SessionTables:
    """Where ``run_sessions`` writes, a folder a micro-batch: sessions, late, open and marks.

    A batch delivered again overwrites its own folders, so it counts once. Readers take the batches that ``marks`` lists.
    """

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder.rstrip("/")

    def path(self, name: str, batch: int) -> str:
        return f"{self.folder}/{name}/batch={batch}"

    def marks(self, before: int | None = None) -> list[tuple[int, object]]:
        """(batch, latest event time until then) of the finished batches: a row a batch."""
        found = self._read("marks", "latest timestamp, batch int")
        rows = found.filter(F.col("batch") < before) if before is not None else found
        return sorted((r["batch"], r["latest"]) for r in rows.collect())

    def sessions(self) -> DataFrame:
        return self._read("sessions", "user_id long, start timestamp, last timestamp, events array<struct<ts timestamp, event_id long, event_type string>>, batch int")

    def late(self) -> DataFrame:
        return self._read("late", f"{EVENTS}, batch int")

    def _read(self, name: str, schema: str) -> DataFrame:
        jvm, spark = self.spark._jvm, self.spark
        place = jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}")
        if not place.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).exists(place):
            return spark.createDataFrame([], schema)
        return spark.read.schema(schema).parquet(f"{self.folder}/{name}")


def run_sessions(events: DataFrame, folder: str, checkpoint: str, gap: str, delay: str, available_now: bool = True) -> StreamingQuery:
    """Assemble whole sessions from a stream of events (``EVENTS``); see ``SessionTables`` for the results.

    The watermark of a batch is the latest event time of the batches before it less ``delay``. Events before it are late: they go
    to a table of their own, since their session may have been closed and scored. A session closes when the watermark, with this batch's
    events, passes its last event by ``gap``; open events wait in a table that is as large as what the watermark leaves open.
    An event_id that is open already is a replay and counts once. Events without user, id or time belong to no session and are late.
    """
    spark = events.sparkSession
    tables = SessionTables(spark, folder)

    def take(batch: DataFrame, batch_id: int) -> None:
        before = tables.marks(batch_id)
        known = batch.select("event_id", "user_id", "ts", "event_type").persist()
        try:
            whole = F.col("event_id").isNotNull() & F.col("user_id").isNotNull() & F.col("ts").isNotNull()
            in_time = whole
            if before and before[-1][1]:
                in_time &= F.col("ts") >= F.lit(before[-1][1]) - F.expr(f"interval {delay}")
            known.filter(~F.coalesce(in_time, F.lit(False))).write.mode("overwrite").parquet(tables.path("late", batch_id))
            waiting = known.filter(in_time)
            if before:
                waiting = waiting.unionByName(spark.read.schema(EVENTS).parquet(tables.path("open", before[-1][0])))
            latest = max([x for x in (known.filter(whole).agg(F.max("ts")).first()[0], before[-1][1] if before else None) if x], default=None)
            placed = session_numbers(waiting.dropDuplicates(["event_id"]), gap)
            done = F.lit(False) if latest is None else F.col("last") + F.expr(f"interval {gap}") <= F.lit(latest) - F.expr(f"interval {delay}")
            assembled(placed.filter(done)).write.mode("overwrite").parquet(tables.path("sessions", batch_id))
            placed.filter(~done).select("event_id", "user_id", "ts", "event_type").write.mode("overwrite").parquet(tables.path("open", batch_id))
            spark.createDataFrame([(latest,)], "latest timestamp").coalesce(1).write.mode("overwrite").parquet(tables.path("marks", batch_id))
        finally:
            known.unpersist()

    writer = events.writeStream.foreachBatch(take).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()
