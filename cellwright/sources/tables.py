"""Sources and sinks around the methods: external candidates and benchmarks, bucketed corpora, training shards."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

CANDIDATES = T.StructType([T.StructField("system", T.StringType()), T.StructField("example_id", T.LongType()), T.StructField("rank", T.IntegerType()), T.StructField("candidate", T.StringType()), T.StructField("mean_logprob", T.DoubleType())])
BENCHMARK = T.StructType([T.StructField("example_id", T.LongType()), T.StructField("buggy", T.StringType()), T.StructField("intended", T.StringType())])


def external_candidates(spark: SparkSession, path: str, kind: str = "json") -> DataFrame:
    """Candidates produced elsewhere, as by a hosted model; the schema is given, never inferred."""
    return spark.read.schema(CANDIDATES).format(kind).load(path)


def external_benchmark(spark: SparkSession, path: str, kind: str = "json") -> DataFrame:
    return spark.read.schema(BENCHMARK).format(kind).load(path)


FORMULA = T.StructType([T.StructField("formula_id", T.LongType()), T.StructField("workbook_id", T.LongType()), T.StructField("sheet_no", T.IntegerType()), T.StructField("formula", T.StringType())])


def read_formulas(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """Formulas from Parquet, JSON lines, CSV, or text of one formula a line, which then have no ids. The schema is given."""
    if kind == "text":
        return spark.read.text(path).withColumnRenamed("value", "formula")
    reader = spark.read.schema(FORMULA).format(kind)
    return (reader.option("escape", '"').option("quote", '"') if kind == "csv" else reader).load(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, key: str = "workbook_id") -> None:
    """A corpus bucketed by workbook: deduplication per workbook then needs no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def write_shards(pairs: DataFrame, path: str, rows_per_file: int = 1_000_000) -> None:
    """Training pairs, a folder for each objective."""
    pairs.write.mode("overwrite").partitionBy("objective").option("maxRecordsPerFile", rows_per_file).parquet(path)
