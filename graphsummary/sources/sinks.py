"""Results to files and tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_hierarchy(h: DataFrame, path: str) -> None:
    """Parquet, a folder for each round: reading one round reads no other."""
    h.write.mode("overwrite").partitionBy("round").parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str = "node", buckets: int = 16) -> None:
    """A table bucketed and sorted by its key: later joins on the key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def write_lines(rows: DataFrame, path: str) -> None:
    """(ord, line) rows as text in order."""
    rows.orderBy("ord", "line").select("line").coalesce(1).write.mode("overwrite").text(path)


def graphml(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(ord, line) of a GraphML document."""
    spark = nodes.sparkSession
    head = spark.createDataFrame([(0, '<graphml xmlns="http://graphml.graphdrawing.org/xmlns"><graph edgedefault="undirected">'), (3, "</graph></graphml>")], "ord int, line string")
    n = nodes.select(F.lit(1).alias("ord"), F.format_string('<node id="%d"/>', "node").alias("line"))
    e = edges.select(F.lit(2).alias("ord"), F.format_string('<edge source="%d" target="%d"/>', "src", "dst").alias("line"))
    return head.unionByName(n).unionByName(e)


def measure_only(df: DataFrame) -> None:
    """Run a plan whole without keeping its result."""
    df.write.format("noop").mode("overwrite").save()
