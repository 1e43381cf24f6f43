"""Walking the levels of a detection: members of a supernode, path of a node, assignment after a round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def rounds_of(h: DataFrame) -> list[int]:
    return sorted(r[0] for r in h.select("round").distinct().collect())  # as many as there are rounds


def level(h: DataFrame, round_: int) -> DataFrame:
    """(node, community) after a round; a node that a round does not name keeps its community."""
    out = None
    for r in [x for x in rounds_of(h) if x <= round_]:
        step = h.where(F.col("round") == r).select(F.col("child").alias("community"), F.col("parent").alias("__to"))
        out = step.select(F.col("community").alias("node"), F.col("__to").alias("community")) if out is None else out.join(step, "community", "left").select("node", F.coalesce("__to", "community").alias("community"))
    return out


def members(h: DataFrame, community: int, round_: int) -> DataFrame:
    return level(h, round_).where(F.col("community") == community).select("node")


def path(h: DataFrame) -> DataFrame:
    """(node, path): the communities of every node, round by round."""
    out = None
    for r in rounds_of(h):
        step = h.where(F.col("round") == r).select(F.col("child").alias("__at"), F.col("parent").alias("__to"))
        if out is None:
            out = step.select(F.col("__at").alias("node"), F.array("__to").alias("path"))
        else:
            top = F.element_at("path", -1)
            out = out.withColumn("__at", top).join(step, "__at", "left").select("node", F.concat("path", F.array(F.coalesce("__to", "__at"))).alias("path"))
    return out


def children(h: DataFrame, community: int, round_: int) -> DataFrame:
    """The communities of the round before that a supernode was made of."""
    return h.where((F.col("round") == round_) & (F.col("parent") == community)).select(F.col("child").alias("community"))
