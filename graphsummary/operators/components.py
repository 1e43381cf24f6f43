"""Connected components by randomised contraction.

Each round every node joins the one of its closed neighbourhood that a fresh hash puts first, and edges move to what their
ends have joined; in expectation a fixed share of the nodes goes away in each round, whatever the graph. Once at most FEW
edges are left, one task finishes them (its input is bounded by FEW, so it does not grow with the graph). Labels are put
together from the last round back. The label of a component is its smallest node.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsummary.sources.storage import discard, store

#: Edges that one task finishes.
FEW = 100_000


def _finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, up) of the components of all edges of one task: neighbours' smallest label, chains halved."""
    held = [x for x in batches if x.num_rows]
    if not held:
        return
    table = pa.Table.from_batches(held)
    ends = [x.combine_chunks() for x in table.columns]
    coded = pa.concat_arrays(ends).dictionary_encode()
    n, code = len(coded.dictionary), coded.indices.to_numpy()
    a, b = code[: table.num_rows], code[table.num_rows :]
    label = np.arange(n)
    while True:
        low = np.minimum(label[a], label[b])
        if (label[a] == label[b]).all():
            break
        for end in (label[a], label[b]):  # the roots take the smaller label
            np.minimum.at(label, end, low)
        while (label[label] != label).any():
            label = label[label]
    yield pa.RecordBatch.from_arrays([coded.dictionary, coded.dictionary.take(pa.array(label))], names=["node", "up"])


def components(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """(node, component) for every node of the edges; null ends and loops are left out."""
    a, b = F.col(src), F.col(dst)
    now = store(edges.where(a < b).select(a.alias("a"), b.alias("b")).union(edges.where(b < a).select(b, a)).distinct(), "links")
    kind, ups = now.schema["a"].dataType.simpleString(), []
    while now.limit(FEW + 1).count() > FEW:
        first = lambda x, k=len(ups): F.xxhash64(x, F.lit(k))
        best = now.union(now.select("b", "a")).groupBy("a").agg(F.min_by("b", first("b")).alias("b"))
        up = store(best.select(F.col("a").alias("node"), F.when(first("b") < first("a"), F.col("b")).otherwise(F.col("a")).alias("up")), "up")
        ends = now.join(up.toDF("a", "x"), "a").join(up.toDF("b", "y"), "b").where("x <> y")
        after = store(ends.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "links")
        discard(now)
        now, ups = after, [*ups, up]
    root = store(now.coalesce(1).mapInArrow(_finish, f"node {kind}, up {kind}"), "roots")
    for up in reversed(ups):
        below = store(up.join(root.toDF("up", "top"), "up", "left").select("node", F.coalesce("top", "up").alias("up")), "roots")
        discard(root)
        root = below
    least = root.groupBy("up").agg(F.min("node").alias("component"))
    return root.join(least, "up").select("node", F.least("node", "component").alias("component"))
