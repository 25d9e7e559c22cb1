"""Readers that give STRINGS (string_id, text)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phrasework.operators.strings import strings


def read_strings(spark: SparkSession, path: str, id_col: str, text_col: str, fmt: str = "parquet", schema: str | None = None, prefix: str = "") -> DataFrame:
    """Two columns of a Parquet, ORC, JSON or CSV table; other columns are not read."""
    reader = spark.read.format(fmt)
    if schema:
        reader = reader.schema(schema)
    if fmt == "csv":
        reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    return strings(reader.load(path), id_col, text_col, prefix)


def read_whole_files(spark: SparkSession, path: str) -> DataFrame:
    """Each text file as one string, keyed by its path."""
    return spark.read.option("wholetext", True).text(path).select(F.col("_metadata.file_path").alias("string_id"), F.col("value").alias("text"))


def read_binary_files(spark: SparkSession, path: str) -> DataFrame:
    """Each file as one string of Latin-1 characters, one a byte, keyed by its path."""
    return spark.read.format("binaryFile").load(path).select(F.col("path").alias("string_id"), F.decode("content", "ISO-8859-1").alias("text"))
