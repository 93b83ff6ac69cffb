"""Tiles kept up to date from an event stream (ours): windows, late data, duplicates, sessions.

Results go to folders `batch_no=N` of the shared folder, one for each batch and written over when
a batch is run again, so a restarted stream gives each batch once and nothing gathers on the driver."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery

from ..durable import shared_dir

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType())])
MODES = ("append", "update", "complete")


def source(spark: SparkSession, path: str, glob: str = "*.parquet", files: int | None = None) -> DataFrame:
    """Events as a stream of Parquet files (`files` of them a batch at most), with the event time
    that watermarks need."""
    reader = spark.readStream.schema(EVENTS).option("pathGlobFilter", glob)
    reader = reader.option("maxFilesPerTrigger", files) if files else reader
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def tile_counts(events: DataFrame, width: str = "4 hours", slide: str | None = None, late: str = "2 hours") -> DataFrame:
    """user_id, window and its counts; rows later than the watermark are dropped."""
    win = F.window("ts", width, slide) if slide else F.window("ts", width)
    g = events.withWatermark("ts", late).groupBy("user_id", win.alias("w")).agg(F.count("*").alias("n"), F.sum(F.floor("value")).alias("v"))
    return g.select("user_id", F.col("w.start").alias("start"), "n", "v")


def session_strips(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    g = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return g.select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame, late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def followed(first: DataFrame, then: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Two streams of events: each of `first` with those of `then` the same user has up to `within` later.
    The bound on both times lets the state of either side go."""
    a = first.withWatermark("ts", late).select(F.col("user_id").alias("a_user"), F.col("event_id").alias("first_id"), F.col("ts").alias("a_ts"))
    b = then.withWatermark("ts", late).select(F.col("user_id").alias("b_user"), F.col("event_id").alias("then_id"), F.col("ts").alias("b_ts"))
    near = (F.col("a_user") == F.col("b_user")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, near).select(F.col("a_user").alias("user_id"), "first_id", "then_id")


def started(stream: DataFrame, path: str, mode: str = "append", every: str | None = None) -> StreamingQuery:
    """The stream's batches written to `path`: all there is for `every=None`, else one batch each
    `every` until stopped.  Started again on the same path, it goes on where it was."""
    if mode not in MODES:
        raise ValueError(f"mode is one of {MODES}")

    def put(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch_no={n}")

    trigger = {"processingTime": every} if every else {"availableNow": True}
    return stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{path}.state").trigger(**trigger).start()


def stored(spark: SparkSession, path: str, schema: T.StructType, mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    """What `started` wrote: all batches, the last one (complete), or each key's last row (update)."""
    try:
        rows = spark.read.schema(schema).parquet(path)
    except Exception as e:
        if "PATH_NOT_FOUND" not in str(e):
            raise
        return spark.createDataFrame([], schema)  # no batch yet
    names = schema.fieldNames()
    if "batch_no" not in rows.columns or mode == "append":
        return rows.select(*names)
    if mode == "complete":
        return rows.filter(F.col("batch_no") == rows.agg(F.max("batch_no")).first()[0]).select(*names)
    if not keys:
        raise ValueError("mode update needs the keys of a row")
    newest = F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc("batch_no")))
    return rows.withColumn("_newest", newest).filter("_newest = 1").select(*names)


def drained(stream: DataFrame, mode: str = "complete", keys: list[str] | None = None) -> DataFrame:
    """Run the stream over what there is and return its result table."""
    return drained_with_late(stream, mode, keys)[0]


def drained_with_late(stream: DataFrame, mode: str = "append", keys: list[str] | None = None) -> tuple[DataFrame, int]:
    """The result table, and how many rows came behind the watermark and were dropped.  Rows that
    share a group within a batch are counted as one, as they meet before the watermark is looked at."""
    path = f"{shared_dir(stream.sparkSession).rstrip('/')}/drained-{uuid.uuid4().hex}"
    q = started(stream, path, mode)
    q.awaitTermination()
    return stored(stream.sparkSession, path, stream.schema, mode, keys), late_rows(q)


def late_rows(q: StreamingQuery) -> int:
    """Rows dropped behind the watermark in the batches that the session still reports on
    (spark.sql.streaming.numRecentProgressUpdates, 100 by default)."""
    return sum(op["numRowsDroppedByWatermark"] for p in q.recentProgress for op in p["stateOperators"])
