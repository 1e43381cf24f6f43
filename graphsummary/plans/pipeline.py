"""The whole way from an edge list to a drawing: detect, size, merge, lay out, colour."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsummary.operators import draw, layout, measure, rounds, sketch, summary
from graphsummary.operators.edges import degrees
from graphsummary.params import Params
from graphsummary.sources.storage import store


@dataclass
class Summary:
    assignment: DataFrame  # node, community
    hierarchy: DataFrame  # round, cap, child, parent
    supernodes: DataFrame  # community, size, n_nodes
    superedges: DataFrame  # src, dst, w
    drawing: DataFrame  # node (the community), x, y, radius, band, hex, size
    trace: DataFrame  # of the layout
    metrics: dict

    def segments(self) -> DataFrame:
        return draw.segments(self.superedges, self.drawing)

    def svg(self) -> DataFrame:
        return draw.svg(self.drawing, self.segments())


def detect(edges: DataFrame, p: Params) -> rounds.Detection:
    return rounds.detect(edges, p.rounds, p.threshold, p.threshold_scale, p.schedule, p.factor, p.carry, p.admit, p.tie, p.stop_when_stable)


def merge(edges: DataFrame, found: rounds.Detection, p: Params) -> tuple[DataFrame, DataFrame, dict]:
    """(supernodes, superedges, figures of the sketch)."""
    m = edges.count()
    depth, width = (p.depth, p.width) if p.width else sketch.dims(m, p.width_fraction, p.depth, p.min_width)
    sizes = summary.sizes(found.assignment, degrees(edges), p.size_method, p.size_by, edges, depth, width)
    supernodes, superedges = summary.supergraph(edges, found.assignment, sizes)
    return store(supernodes, "supernodes"), store(superedges, "superedges"), {"m": m, "depth": depth, "width": width, "cells": depth * width}


def lay_out(supernodes: DataFrame, superedges: DataFrame, p: Params) -> tuple[DataFrame, DataFrame]:
    nodes = supernodes.select(F.col("community").alias("node"), F.greatest("size", F.lit(1)).alias("size"))
    return layout.run(nodes, superedges, p.iterations, p.gravity, p.repulsion, p.engine, p.stop_eps, p.seed, "size", p.gravity_mode, p.attraction, p.speed, p.tolerance)


def summarise(edges: DataFrame, params: Params | None = None, **options) -> Summary:
    """Everything for one graph. edges: seq, src, dst, w."""
    p = params or Params(**options)
    clock, times = time.perf_counter(), {}
    edges = store(edges, "edges")
    mark = lambda name, since: times.__setitem__(name, 1000 * (time.perf_counter() - since)) or time.perf_counter()
    begun = time.perf_counter()
    found = detect(edges, p)
    begun = mark("detection_ms", begun)
    supernodes, superedges, figures = merge(edges, found, p)
    times["supergraph_ms"] = 1000 * (time.perf_counter() - clock)
    begun = mark("merge_ms", begun)
    placed, trace = lay_out(supernodes, superedges, p)
    mark("layout_ms", begun)
    colours = draw.qualitative(supernodes, p.tail_share, p.bands)
    drawing = placed.select("node", "x", "y").join(draw.radius(supernodes), F.col("node") == F.col("community")).drop("community")
    drawing = store(drawing.join(colours.select(F.col("community").alias("node"), "band", "hex"), "node"), "drawing")
    times["total_ms"] = 1000 * (time.perf_counter() - clock)
    c = measure.counts(supernodes, superedges).first()
    return Summary(found.assignment, found.hierarchy, supernodes, superedges, drawing, trace, figures | times | {"cap": found.base, "rounds": len(found.metrics), "sn": c["sn"], "se": c["se"]})


def stylise(edges: DataFrame, params: Params | None = None, whole_iterations: int = 500, **options) -> DataFrame:
    """(node, x, y, community, band, hex): the layout of the whole graph in the colours of its communities."""
    p = params or Params(**options)
    edges = store(edges, "edges")
    found = detect(edges, p)
    supernodes, _, _ = merge(edges, found, p)
    from graphsummary.operators.baselines import whole_layout

    placed, _ = whole_layout(edges, whole_iterations, p.gravity, p.repulsion, engine=p.engine, seed=p.seed)
    return draw.stylise(placed, found.assignment, draw.qualitative(supernodes, p.tail_share, p.bands))
