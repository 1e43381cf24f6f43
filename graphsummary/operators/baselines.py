"""What the summary is compared with: whole layouts, exact counters, other ways to shrink a graph."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsummary.operators import components as cc
from graphsummary.operators import layout, sketch
from graphsummary.operators.edges import arrival_hash, degrees, nodes
from graphsummary.operators.summary import exact_sizes, superedges
from graphsummary.sources.storage import store

__all__ = ["attribute_supergraph", "components", "degree_filter", "edge_sample", "exact_sizes", "hash_table_sizes", "label_propagation", "peel_densest", "whole_layout"]


def whole_layout(edges: DataFrame, iterations: int = 500, gravity: float = 1.0, repulsion: float = 80.0, **options) -> tuple[DataFrame, DataFrame]:
    """The force layout of every node: the only timed comparator."""
    return layout.run(nodes(edges), edges, iterations, gravity, repulsion, **options)


def hash_table_sizes(assignment: DataFrame, degrees_: DataFrame, width: int) -> DataFrame:
    """Counting with one hash function: a sketch of depth 1."""
    weights = assignment.join(degrees_, "node")
    made = sketch.build(weights, "community", "deg", 1, width)
    return sketch.estimate(made, assignment.select("community").distinct(), "community", 1, width).withColumnRenamed("est", "size")


def edge_sample(edges: DataFrame, percent: int, seed: int = 0) -> DataFrame:
    """Edges by a hash of their ends: the same ones on every run and engine."""
    return edges.where(F.pmod(arrival_hash(seed=seed), F.lit(100)) < percent)


def degree_filter(edges: DataFrame, least: int) -> DataFrame:
    """Edges between nodes of at least this degree."""
    strong = store(degrees(edges).where(F.col("deg") >= least).select("node"), "strong")
    return edges.join(strong.toDF("src"), "src", "left_semi").join(strong.toDF("dst"), "dst", "left_semi")


def peel_densest(edges: DataFrame, eps: float = 0.1, most_passes: int = 200) -> tuple[DataFrame, float]:
    """(nodes, average degree / 2) of a subgraph within a factor 2 + 2 eps of the densest: in every pass all nodes of
    degree up to 2 (1 + eps) times the density go; the best pass is kept. O(log n) passes."""
    now = store(edges.select("src", "dst"), "peel")
    best, best_nodes = -1.0, nodes(now)
    for _ in range(most_passes):
        deg = store(degrees(now), "degrees")
        t = deg.agg(F.count("*"), F.sum("deg")).first()
        if not t[0]:
            break
        density = t[1] / 2 / t[0]
        if density > best:
            best, best_nodes = density, deg.select("node")
        stay = store(deg.where(F.col("deg") > 2 * (1 + eps) * density).select("node"), "stay")
        now = store(now.join(stay.toDF("src"), "src", "left_semi").join(stay.toDF("dst"), "dst", "left_semi"), "peel")
    return best_nodes, max(best, 0.0)


def attribute_supergraph(edges: DataFrame, attribute: Column, nodes_: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nodes merged by an attribute instead of by detection: (assignment, superedges)."""
    a = nodes_.select("node", attribute.cast("bigint").alias("community"))
    return a, superedges(edges, a)


def components(edges: DataFrame) -> DataFrame:
    """(node, community): connected components, the coarsest result that labels moving along edges can reach."""
    return cc.components(edges).withColumnRenamed("component", "community")


def label_propagation(edges: DataFrame, rounds: int = 20) -> DataFrame:
    """(node, community): every node takes the most common label around it, of equally common ones the smallest."""
    both = store(edges.select("src", "dst").union(edges.select("dst", "src")).toDF("node", "other"), "around")
    now = store(nodes(edges).select("node", F.col("node").alias("community")), "labels")
    for _ in range(rounds):
        votes = both.join(now.toDF("other", "label"), "other").groupBy("node", "label").agg(F.count("*").alias("n"))
        top = votes.groupBy("node").agg((-F.max(F.struct("n", (-F.col("label")).alias("m")))["m"]).alias("community"))
        after = store(top, "labels")
        same = not after.join(now.toDF("node", "old"), "node").where("old <> community").limit(1).count()
        now = after
        if same:
            break
    return now
