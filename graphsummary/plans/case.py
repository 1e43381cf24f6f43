"""Drilling down: one community's own graph and its layout."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsummary.operators import layout
from graphsummary.operators.edges import nodes


def extract(edges: DataFrame, assignment: DataFrame, community: int) -> DataFrame:
    """The edges between a community's members."""
    inside = assignment.where(F.col("community") == community).select("node")
    return edges.join(inside.toDF("src"), "src", "left_semi").join(inside.toDF("dst"), "dst", "left_semi")


def largest(supernodes: DataFrame) -> int | None:
    row = supernodes.orderBy(F.desc("size"), "community").select("community").first()
    return row[0] if row else None


def relayout(edges: DataFrame, assignment: DataFrame, community: int, iterations: int = 100, **options) -> DataFrame:
    own = extract(edges, assignment, community)
    return layout.run(nodes(own), own, iterations, **options)[0]
