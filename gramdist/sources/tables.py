"""Given tables, and strings from text, CSV, JSON and ORC files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_strings(spark: SparkSession, fmt: str, path: str, id_col: str = "id", text_col: str = "text") -> DataFrame:
    """(string_id, text) from parquet, orc, csv (with header), json, or text files (a file is a string)."""
    if fmt == "text":
        df = spark.read.text(path, wholetext=True).select(F.xxhash64(F.input_file_name()).alias(id_col), F.col("value").alias(text_col))
    elif fmt == "csv":
        df = spark.read.option("header", True).option("multiLine", True).option("escape", '"').csv(path)
    elif fmt == "json":
        df = spark.read.schema(f"`{id_col}` long, `{text_col}` string").json(path)
    else:
        df = spark.read.format(fmt).load(path)
    return df.select(F.col(id_col).cast("long").alias("string_id"), F.col(text_col).cast("string").alias("text"))


def write_slp(slps: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Grammars by codec; rows of one codec are spread by id so files stay even."""
    slps.repartition("codec", F.pmod("string_id", F.lit(16))).write.mode(mode).partitionBy("codec").parquet(path)


def read_slp(spark: SparkSession, path: str) -> DataFrame:
    from ..model import SLP

    return spark.read.schema(SLP).parquet(path)
