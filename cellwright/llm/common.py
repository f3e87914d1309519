"""Shared plumbing of the training-data operators: shared folder, written intermediate tables, packed arrays."""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir of the session, or one set here where it is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        jdir = spark.sparkContext._jsc.sc().getCheckpointDir()
        if jdir.isDefined():
            return jdir.get()
        found = f"file://{tempfile.mkdtemp(prefix='cellwright-')}"  # single-machine sessions only, such as tests
        spark.sparkContext.setCheckpointDir(found)
        return spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return found


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a table written to the shared folder: cuts lineage, and lost executors cost no recomputation of what came before."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_and_text(docs: DataFrame) -> DataFrame:
    """doc_id and whole text, null as empty; any other columns, whatever their names, are left behind."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))


def partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def ragged_index(starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """Flat indices of the runs [start, start + len), one after another."""
    total = int(lens.sum())
    if not total:
        return np.zeros(0, np.int64)
    ends = np.cumsum(lens)
    return np.arange(total, dtype=np.int64) + np.repeat(starts - (ends - lens), lens)


def mix64(h: np.ndarray) -> np.ndarray:
    """Finaliser that spreads the bits of unsigned 64-bit values."""
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(0x9E3779B97F4A7C15)
    h = h ^ (h >> np.uint64(29))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def _cuts(texts, max_bytes: int):
    """(start, end) of slices of an Arrow text array of about max_bytes each."""
    import pyarrow.compute as pc

    cum = np.cumsum(np.asarray(pc.fill_null(pc.binary_length(texts), 0), np.int64))
    at = 0
    while at < len(cum):
        end = max(at + 1, int(np.searchsorted(cum, (cum[at - 1] if at else 0) + max_bytes, side="right")))
        yield at, end
        at = end


def text_chunks(batch, max_bytes: int = 4_000_000):
    """Splits an Arrow batch with a column text into slices of about max_bytes of text."""
    for a, b in _cuts(batch.column("text"), max_bytes):
        yield batch.slice(a, b - a)


def text_slices(texts, max_bytes: int):
    """As text_chunks, of an array of texts."""
    for a, b in _cuts(texts, max_bytes):
        yield texts.slice(a, b - a)
