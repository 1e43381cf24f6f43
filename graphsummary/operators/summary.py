"""Sizes of communities and the weighted supergraph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsummary.operators import measure, sketch


def exact_sizes(assignment: DataFrame, degrees: DataFrame) -> DataFrame:
    """(community, size, n_nodes): size is the sum of the members' degrees."""
    return assignment.join(degrees, "node", "left").groupBy("community").agg(F.sum(F.coalesce("deg", F.lit(0))).alias("size"), F.count("*").alias("n_nodes"))


def sizes(assignment: DataFrame, degrees: DataFrame, method: str = "sketch", size_by: str = "volume", edges: DataFrame | None = None, depth: int = 4, width: int = 16, seed: int | None = None) -> DataFrame:
    """(community, size). method='sketch' adds every node's weight at its community's cells and reads the least."""
    if size_by == "nodes":
        weights = assignment.withColumn("deg", F.lit(1).cast("bigint"))
    elif size_by == "volume":
        weights = assignment.join(degrees, "node", "left").withColumn("deg", F.coalesce("deg", F.lit(0)))
    else:
        if edges is None:
            raise ValueError("these sizes need the edges")
        split = measure.edge_split(edges, assignment)
        value = F.col("inner") if size_by == "inner_edges" else F.col("inner") + F.col("cross")
        every = assignment.select("community").distinct().join(split, "community", "left")
        weights = every.select("community", F.coalesce(value, F.lit(0)).alias("deg"))
    if method == "exact":
        return weights.groupBy("community").agg(F.sum("deg").alias("size"))
    made = sketch.build(weights, "community", "deg", depth, width, seed)
    return sketch.estimate(made, assignment.select("community").distinct(), "community", depth, width, seed).withColumnRenamed("est", "size")


def superedges(edges: DataFrame, assignment: DataFrame, weight: bool = True) -> DataFrame:
    """(src, dst, w): unordered pairs of different communities with the weight between them."""
    rows = measure.labelled(edges, assignment).where("cs <> cd")
    w = F.sum("w") if weight else F.count("*")
    return rows.groupBy(F.least("cs", "cd").alias("src"), F.greatest("cs", "cd").alias("dst")).agg(w.alias("w"))


def supergraph(edges: DataFrame, assignment: DataFrame, sizes_: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(supernodes(community, size, n_nodes), superedges(src, dst, w))."""
    members = assignment.groupBy("community").agg(F.count("*").alias("n_nodes"))
    return members.join(sizes_, "community", "left").select("community", F.coalesce("size", F.lit(0)).alias("size"), "n_nodes"), superedges(edges, assignment)
