"""Streams of cells into an index, and windows over event streams.

A micro-batch is appended by the batch path, so a stream ends with the same answers as a rebuild. The number of the last
batch taken is published with the index's version, in one file: a restarted stream may deliver a batch again, and it
changes nothing. Rows far behind time are appended like any other, as their chunks are rebuilt; none is dropped.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.append import append
from ..operators.tree import Index, read_index, shared_folder


class IndexedStream:
    """A named stream into a stored index; the streaming query calls take() for each micro-batch. What was taken is told
    by the index's newest version on disk, so a new object after a restart goes on where the last one ended."""

    def __init__(self, spark: SparkSession, path: str, name: str, to_cells: Callable[[DataFrame], DataFrame], on_collision: str = "max") -> None:
        self.spark, self.path, self.name, self.to_cells, self.on_collision = spark, path, name, to_cells, on_collision

    @property
    def index(self) -> Index:
        return read_index(self.spark, self.path)

    def take(self, rows: DataFrame, batch_id: int) -> None:
        append(self.index, self.to_cells(rows), on_collision=self.on_collision, batch=(self.name, batch_id))


def append_stream(stream: DataFrame, state: IndexedStream, checkpoint: str) -> IndexedStream:
    """Run the stream over what is there now."""
    q = stream.writeStream.foreachBatch(state.take).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return state


def event_stream(spark: SparkSession, path: str, like: DataFrame, files: int = 1) -> DataFrame:
    """Parquet files of events as a stream, with a proper timestamp so that watermarks are allowed."""
    rows = spark.readStream.schema(like.schema).option("maxFilesPerTrigger", files).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_latest(agg: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Run a streaming aggregate in complete mode to its end; each batch replaces a table under path by a new one, the
    last of which is read. The result stays in files, however large."""
    spark, last = agg.sparkSession, [-1]

    def put(rows: DataFrame, batch_id: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")
        last[0] = batch_id

    agg.writeStream.foreachBatch(put).outputMode("complete").option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(agg.schema).parquet(f"{path}/batch={last[0]}") if last[0] >= 0 else spark.createDataFrame([], agg.schema)


def tumbling(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", delay).groupBy(F.window("ts", "1 hour"), "user_id").agg(F.max("value").alias("vmax"), F.count("*").alias("n"))


def sliding(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", delay).groupBy(F.window("ts", "2 hours", "1 hour"), "user_id").agg(F.max("value").alias("vmax"), F.count("*").alias("n"))


def sessions(rows: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return rows.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"), F.max("value").alias("vmax"))


def chunk_bounds(stream: DataFrame, side: int = 16) -> DataFrame:
    """Running least and largest value and number of events of each block of users: the state that node bounds need."""
    return stream.groupBy(F.floor(F.col("user_id") / side).alias("block")).agg(F.min("value").alias("vmin"), F.max("value").alias("vmax"), F.count("*").alias("n"))


def deduplicated(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def run_to_files(rows: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Run a stream of rows to its end into Parquet files under path, and read them."""
    rows.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return rows.sparkSession.read.schema(rows.schema).parquet(path)


def standing_queries(stream: DataFrame, bands: DataFrame, most: int = 10_000) -> DataFrame:
    """Rows of the stream with every band(band, lo, hi, least) they fall into; more than `most` bands raise."""
    if bands.limit(most + 1).count() > most:
        raise ValueError(f"more than {most} standing queries")
    return stream.join(F.broadcast(bands), (F.col("user_id") >= F.col("lo")) & (F.col("user_id") < F.col("hi")) & (F.col("value") >= F.col("least")))


def fresh_folder(spark: SparkSession, tag: str) -> str:
    import uuid

    return f"{shared_folder(spark)}/{tag}-{uuid.uuid4().hex}"
