"""Streaming over formula edits: first of each key within a watermark, windowed counts, idempotent sink."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType
from pyspark.sql.window import Window

from cellwright.functions import lexing


def read_edits(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Stream of files with columns workbook_id, sheet, ts, formula; the times become instants, as watermarks need."""
    schema = "event_id long, workbook_id long, ts timestamp, sheet string, formula string"
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def dedup_stream(edits: DataFrame, delay: str = "7 days") -> DataFrame:
    """One edit per workbook and sketch. State holds the keys within the watermark; later ones are dropped, so the result
    equals the batch result only where the delay covers the disorder."""
    keyed = lexing.with_sketch(edits).drop("tokens", "kinds")
    return keyed.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["workbook_id", "sketch_key"])


def edit_counts(edits: DataFrame, width: str = "1 day", delay: str = "7 days") -> DataFrame:
    """Edits and tokens of each sheet and window."""
    t = lexing.with_tokens(edits).withWatermark("ts", delay)
    return t.groupBy(F.window("ts", width), "sheet").agg(F.count(F.lit(1)).alias("edits"), F.sum(F.size("tokens")).alias("tokens"))


def shared_path(spark: SparkSession, name: str) -> str:
    """A new folder under spark.checkpoint.dir of the session; a folder of this machine only where that is unset, as in tests."""
    base = spark.conf.get("spark.checkpoint.dir", None) or f"file://{tempfile.gettempdir()}"
    return f"{base.rstrip('/')}/cellwright-{name}-{uuid.uuid4().hex[:12]}"


def run_to_table(stream: DataFrame, mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    """Drains the available input into Parquet in the shared folder, batch by batch; a batch that is run again replaces its
    own files, so each result counts once. update mode: rows replace earlier ones of equal keys."""
    path, checkpoint = shared_path(stream.sparkSession, "stream"), shared_path(stream.sparkSession, "stream-state")
    q = stream.writeStream.foreachBatch(idempotent_sink(path)).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    rows = stream.sparkSession.read.schema(StructType([*stream.schema.fields, StructField("epoch", LongType())])).parquet(path)
    if mode != "update":
        return rows.drop("epoch")
    rest = [c for c in stream.columns if c not in keys]
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "epoch").alias("last"))
    return last.select(*keys, *(F.col("last")[c].alias(c) for c in rest))


def late_edits(edits: DataFrame, delay: str, arrival: str = "event_id") -> DataFrame:
    """What a watermark of a workbook would drop, as a side output: edits that come, in the order of the column arrival, when
    a later one by at least the delay has been seen. event_id, workbook_id, late_hours."""
    before = Window.partitionBy("workbook_id").orderBy(arrival, "event_id").rowsBetween(Window.unboundedPreceding, -1)
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    late = edits.withColumn("late_hours", F.floor((F.max(us).over(before) - us) / 3_600_000_000).cast("long"))
    return late.where(F.col("late_hours") >= F.expr(f"cast(extract(DAY FROM interval '{delay}') as long) * 24")).select("event_id", "workbook_id", "late_hours")


def sessions(edits: DataFrame, gap: str) -> DataFrame:
    """Runs of edits of a workbook with pauses below the gap; works on streams, too, behind a watermark."""
    timed = edits.withColumn("ts", F.col("ts").cast("timestamp"))
    runs = timed.groupBy("workbook_id", F.session_window("ts", gap).alias("w")).agg(F.unix_micros(F.min("ts")).alias("first_us"), F.unix_micros(F.max("ts")).alias("last_us"), F.count(F.lit(1)).alias("edits"))
    return runs.drop("w")


def idempotent_sink(path: str):
    """For foreachBatch: a batch that is run again replaces its own folder."""

    def write(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return write


def latest_edits(edits: DataFrame, at: str) -> DataFrame:
    """As of a time: the last formula of each workbook and sheet."""
    seen = edits.where(F.col("ts") <= F.lit(at).cast("timestamp_ntz"))
    return seen.groupBy("workbook_id", "sheet").agg(F.max_by("formula", F.struct("ts", "event_id")).alias("formula"), F.count(F.lit(1)).alias("edits"))
