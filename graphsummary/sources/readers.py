"""Edge lists from files and columns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def parquet_edges(spark: SparkSession, path: str, src: str, dst: str, where: Column | None = None) -> DataFrame:
    """Two columns of a table; the filter and the choice of columns reach the scan."""
    df = spark.read.parquet(path)
    return (df.where(where) if where is not None else df).select(F.col(src).alias("src"), F.col(dst).alias("dst"))


def text_edges(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst, w) of a text edge list: ends parted by spaces, tabs or commas, an optional weight, comment lines with # or %."""
    line = F.trim("value")
    parts = F.split(line, r"[\s,;]+")
    rows = spark.read.text(path).where((line != "") & ~line.startswith("#") & ~line.startswith("%"))
    return rows.select(F.try_element_at(parts, F.lit(1)).try_cast("bigint").alias("src"), F.try_element_at(parts, F.lit(2)).try_cast("bigint").alias("dst"), F.coalesce(F.try_element_at(parts, F.lit(3)).try_cast("double"), F.lit(1.0)).alias("w")).where("src is not null and dst is not null")


def csv_edges(spark: SparkSession, path: str, sep: str = ",", comment: str = "#") -> DataFrame:
    return spark.read.csv(path, sep=sep, comment=comment, schema="src bigint, dst bigint, w double", ignoreLeadingWhiteSpace=True)


def json_edges(df: DataFrame, src: str, json: str, field: str) -> DataFrame:
    """(src, dst): a column and an integer field of a JSON column."""
    return df.select(F.col(src).alias("src"), F.from_json(json, f"{field} bigint")[field].alias("dst")).where("dst is not null")
