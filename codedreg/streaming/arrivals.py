"""Arrivals as a stream: epochs are tumbling windows, the watermark is the deadline.

Events stand for results that clients send: client = user_id mod 20, payload = value.  Delivery lags behind the event
time by a hashed delay.  Each stream has a batch twin with the same deadline rule, against which it is tested.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codedreg.operators import coding
from codedreg.sources.tables import EVENTS, read_stream
from codedreg.storage import ensure_checkpoint_dir

CLIENTS = 20


def updates(events: DataFrame) -> DataFrame:
    """event_id, client, ts (with time zone, as watermarks need), payload."""
    return events.select("event_id", F.pmod("user_id", F.lit(CLIENTS)).cast("int").alias("client"), F.col("ts").cast("timestamp").alias("ts"), F.col("value").alias("payload"))


def open_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return updates(read_stream(spark, sf_dir, "events", EVENTS))


def epoch_aggregate(rows: DataFrame, length: str, late: str) -> DataFrame:
    """start, client, n, payload of every epoch (tumbling window)."""
    windowed = rows.withWatermark("ts", late).groupBy(F.window("ts", length), "client")
    return windowed.agg(F.count("*").alias("n"), F.sum("payload").alias("payload")).select(F.col("window.start").alias("start"), "client", "n", "payload")


def sliding_aggregate(rows: DataFrame, length: str, step: str, late: str) -> DataFrame:
    windowed = rows.withWatermark("ts", late).groupBy(F.window("ts", length, step))
    return windowed.agg(F.count("*").alias("n"), F.sum("payload").alias("payload")).select(F.col("window.start").alias("start"), "n", "payload")


def sessions(rows: DataFrame, gap: str, late: str) -> DataFrame:
    """start, client, n of spells in which a client stays in touch."""
    windowed = rows.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "client")
    return windowed.agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), "client", "n")


def once_each(rows: DataFrame, late: str) -> DataFrame:
    """Retransmissions dropped while the watermark can tell."""
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def drain(stream: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Run over what is there into Parquet in the shared folder, and hand back the closed results as a table."""
    spark = stream.sparkSession
    path = f"{ensure_checkpoint_dir(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/log").outputMode("append")
    query = (writer.partitionBy(*by) if by else writer).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def _exists(spark: SparkSession, path: str) -> bool:
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(folder)


class ParameterServer:
    """Applies each batch of closed epochs to a state of fixed size, once, also over restarts.

    The state lies in the folder, a row of Parquet for each batch; a batch whose row is there changes nothing.
    """

    def __init__(self, spark: SparkSession, path: str, apply: Callable[[list[float], list], list[float]], start: list[float]):
        self.path, self.apply = path, apply
        self.done, self.state = -1, list(start)
        rows = self._rows(spark)
        if rows:
            self.done, self.state = max((r["batch"], list(r["state"])) for r in rows)

    def _rows(self, spark: SparkSession) -> list:
        if not _exists(spark, self.path):
            return []
        return spark.read.schema("batch long, state array<double>").parquet(self.path).collect()

    def __call__(self, frame: DataFrame, batch_id: int) -> None:
        if batch_id <= self.done:
            return
        # a row for each client and epoch that closed in this batch: bounded by the trigger's span, not by the data
        self.state = self.apply(self.state, frame.orderBy("start", "client").collect())
        spark = frame.sparkSession
        spark.createDataFrame([(batch_id, self.state)], "batch long, state array<double>").write.mode("append").parquet(self.path)
        self.done = batch_id


def serve(stream: DataFrame, server: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    query = stream.writeStream.foreachBatch(server).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()


class CompositeServer:
    """Keeps the composite table of the rows that have come: coding is linear, so each batch is coded alone and added."""

    def __init__(self, path: str, c: int, seed: int = 0):
        self.path, self.c, self.seed = path, c, seed

    def __call__(self, frame: DataFrame, batch_id: int) -> None:
        if not frame.isEmpty():
            # a folder for each batch: a batch that comes again writes the same rows over its own
            coding.compose(coding.encode_clients(frame, self.c, 0.0, self.seed)).write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")

    def table(self, spark: SparkSession) -> DataFrame:
        schema = "k int, x array<double>, y array<double>"
        if not _exists(spark, self.path):
            return spark.createDataFrame([], schema)
        return coding.compose(spark.read.schema(schema).parquet(f"{self.path}/batch=*"))


def in_delivery_order(rows: DataFrame, path: str, files: int, late_s: int = 3600) -> None:
    """Write updates as files in the order they are delivered: event time and a hashed delay below late_s; file i of `files` is
    the i-th stretch of delivery time."""
    seen = F.unix_timestamp("ts") + F.pmod(F.col("event_id") * 48271, F.lit(late_s))
    span = rows.agg(F.min(seen).alias("low"), F.max(seen).alias("high"))
    place = F.floor((seen - F.col("low")) * files / (F.col("high") - F.col("low") + 1)).cast("int")
    dealt = rows.crossJoin(F.broadcast(span)).withColumn("file", place).drop("low", "high")
    for i in range(files):
        dealt.where(F.col("file") == i).drop("file").coalesce(1).write.mode("append").parquet(path)


def closed_epochs(rows: DataFrame, length: str, late: str) -> DataFrame:
    """Batch twin of epoch_aggregate: epochs whose end the watermark has passed."""
    limit = rows.agg(F.max("ts").alias("top")).select((F.col("top") - F.expr(f"interval {late}")).alias("limit"))
    grouped = rows.groupBy(F.window("ts", length), "client").agg(F.count("*").alias("n"), F.sum("payload").alias("payload"))
    return grouped.crossJoin(F.broadcast(limit)).where("window.end <= limit").select(F.col("window.start").alias("start"), "client", "n", "payload")


def delivered_late(rows: DataFrame, length_s: int, late_s: int) -> DataFrame:
    """start, n, in_time: results by epoch, and those delivered (with a hashed delay of up to an hour) by its deadline."""
    delay = F.pmod(F.col("event_id") * 48271, F.lit(3600))
    second = F.unix_timestamp("ts")
    start = second - F.pmod(second, F.lit(length_s))
    in_time = second + delay <= start + F.lit(length_s + late_s)
    return rows.groupBy(start.alias("start")).agg(F.count("*").alias("n"), F.sum(in_time.cast("long")).alias("in_time"))
