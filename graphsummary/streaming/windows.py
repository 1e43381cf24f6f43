"""Windows, dedup, joins and keyed state over edge streams; the batch forms of the windows are the same expressions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """events as a file stream, with a timestamp that a watermark accepts."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def edges_of_events(df: DataFrame, offset: int = 10_000_000) -> DataFrame:
    """(ts, src, dst): the user and the JSON key of every event."""
    return df.select(F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("src"), (F.get_json_object("props", "$.k").cast("bigint") + offset).alias("dst")).where("dst is not null")


def tumbling(edges: DataFrame, every: str = "1 day") -> DataFrame:
    w = F.window("ts", every)
    return edges.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.approx_count_distinct("src").alias("about_sources")).select(F.col("w.start").alias("start"), "n", "about_sources")


def sliding(edges: DataFrame, size: str = "1 day", step: str = "6 hours") -> DataFrame:
    return edges.groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(edges: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return edges.groupBy("src", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("src", F.col("w.start").alias("start"), "n")


def first_seen(edges: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each (src, dst) once within the watermark."""
    return edges.withWatermark("ts", late).dropDuplicatesWithinWatermark(["src", "dst"])


def with_labels(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """A stream joined with static labels."""
    return edges.join(assignment.toDF("src", "community"), "src", "left")


def answers(edges: DataFrame, late: str = "1 hour", within: str = "10 minutes") -> DataFrame:
    """Stream with stream: edges of the same destination that follow each other within an interval."""
    a = edges.select(F.col("ts").alias("ta"), F.col("src").alias("a"), F.col("dst").alias("da")).withWatermark("ta", late)
    b = edges.select(F.col("ts").alias("tb"), F.col("src").alias("b"), F.col("dst").alias("db")).withWatermark("tb", late)
    return a.join(b, (F.col("da") == F.col("db")) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr(f"interval {within}"))).where("a <> b")


def capped_nodes(edges: DataFrame, cap: int) -> DataFrame:
    """(node, deg, capped): the running degree of every node of a batch, kept as keyed state."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("node"))

    def run(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        deg = (state.get[0] if state.exists else 0) + sum(len(p) for p in parts)
        state.update((deg,))
        yield pd.DataFrame({"node": [key[0]], "deg": [deg], "capped": [deg > cap]})

    return ends.groupBy("node").applyInPandasWithState(run, "node bigint, deg bigint, capped boolean", "deg bigint", "update", GroupStateTimeout.NoTimeout)
