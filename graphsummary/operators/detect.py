"""Degree-capped stream detection: exact and parallel, sequential, sliced and bulk forms.

With both ends of every edge counted, a node's running degree after an edge is the edge's rank among the node's edges:
a window expression. So it is known without simulation which edges the cap admits and which end takes the other's
label. A label is only ever copied, so the labels form a forest of pointers over the admitted edges; pointer doubling
finds the roots.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphsummary.operators.edges import degrees, half_edges, nodes
from graphsummary.operators.order import RANGE, ranged
from graphsummary.sources.storage import discard, small, store

#: A node's edges that one task may rank.
HUB = 1 << 20


def _limit(cap: int, admit: str) -> int:
    if admit not in ("le", "lt"):
        raise ValueError("admit is 'le' or 'lt'")
    return cap if admit == "le" else cap - 1


def _hub_ranks(half: DataFrame, limit: int | None) -> DataFrame:
    """half with rank, for nodes of many edges: ranks inside ranges of (node, seq), added to what earlier ranges hold."""
    rows = ranged(half, [F.col("node"), F.col("seq")])
    before = Window.partitionBy("node").orderBy(RANGE).rowsBetween(Window.unboundedPreceding, -1)  # a row for each range
    per = rows.groupBy("node", RANGE).agg(F.count("*").alias("held"))
    per = per.select("node", RANGE, F.coalesce(F.sum("held").over(before), F.lit(0)).alias("__start"))
    if limit is not None:
        per = per.where(F.col("__start") < limit)
    own = F.row_number().over(Window.partitionBy("node", RANGE).orderBy("seq"))
    return rows.join(per, ["node", RANGE]).withColumn("rank", F.col("__start") + own).select("seq", "node", "side", "rank")


def ranked(edges: DataFrame, limit: int | None = None, offset: DataFrame | None = None, hub: int = HUB) -> DataFrame:
    """Half-edges with the running degree of their node. limit drops what no cap admits while it is shuffled; where it
    lets more than hub edges of a node through, nodes of more edges are ranked by ranges, over many tasks."""
    half = half_edges(edges)
    plain = lambda x: x.withColumn("rank", F.row_number().over(Window.partitionBy("node").orderBy("seq")).cast("bigint"))
    rows = None
    if limit is None or limit > hub:
        hubs = store(degrees(edges).where(F.col("deg") > hub).select("node"), "hubs")
        if not hubs.isEmpty():
            hubs = small(hubs)
            rest = plain(half.join(hubs, "node", "left_anti")).select("seq", "node", "side", "rank")
            rows = rest.unionByName(_hub_ranks(half.join(hubs, "node", "left_semi"), limit))
    rows = plain(half) if rows is None else rows
    if limit is not None:
        rows = rows.where(F.col("rank") <= limit)
    if offset is None:
        return rows.withColumn("deg", F.col("rank").cast("bigint"))
    carried = offset.select("node", F.col("deg").alias("__before"))
    rows = rows.join(carried, "node", "left").withColumn("deg", F.col("rank") + F.coalesce("__before", F.lit(0))).drop("__before")
    return rows if limit is None else rows.where(F.col("deg") <= limit)


def admitted(edges: DataFrame, cap: int, admit: str = "le", offset: DataFrame | None = None) -> DataFrame:
    """(seq, src, dst, src_deg, dst_deg) of the edges whose ends are both within the cap after counting the edge."""
    rows = ranked(edges, _limit(cap, admit), offset)
    at = lambda c, side: F.max(F.when(F.col("side") == side, F.col(c)))
    both = rows.groupBy("seq").agg(F.count("*").alias("ends"), at("node", 0).alias("src"), at("node", 1).alias("dst"), at("deg", 0).alias("src_deg"), at("deg", 1).alias("dst_deg"))
    return both.where("ends = 2").drop("ends")


def _source_joins(tie: str) -> Column:
    """True where the source takes the destination's label."""
    s, d = F.col("src_deg"), F.col("dst_deg")
    if tie == "source":
        return s <= d
    if tie == "hold":
        return s < d
    if tie == "lower_id":
        return (s < d) | (s == d) & (F.col("src") > F.col("dst"))
    raise ValueError("tie is 'source', 'hold' or 'lower_id'")


def copy_events(admitted_: DataFrame, tie: str = "source") -> DataFrame:
    """(seq, loser, winner): at seq the loser takes the winner's label."""
    rows = admitted_.where(F.col("src_deg") != F.col("dst_deg")) if tie == "hold" else admitted_
    joins = _source_joins(tie)
    return rows.select("seq", F.when(joins, F.col("src")).otherwise(F.col("dst")).alias("loser"), F.when(joins, F.col("dst")).otherwise(F.col("src")).alias("winner"))


def event_pointers(events: DataFrame) -> DataFrame:
    """(seq, loser, winner, ptr): ptr is the winner's latest earlier change of label, null if it had none."""
    ends = F.array(F.struct(F.col("loser").alias("node"), F.col("seq").alias("wrote")), F.struct(F.col("winner").alias("node"), F.lit(None).alias("wrote")))
    rows = events.select("seq", "loser", "winner", F.explode(ends).alias("e")).select("seq", "loser", "winner", "e.*")
    before = Window.partitionBy("node").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    return rows.withColumn("ptr", F.max("wrote").over(before)).where("wrote is null").select("seq", "loser", "winner", "ptr")


def _resolve(pointers: DataFrame, labels: DataFrame | None) -> DataFrame:
    """(seq, loser, label) by pointer doubling; an event without a pointer has the label that its winner started with."""
    if labels is None:
        start = pointers.withColumn("label", F.col("winner"))
    else:
        own = labels.select(F.col("node").alias("winner"), F.col("community").alias("__own"))
        start = pointers.join(own, "winner", "left").withColumn("label", F.coalesce("__own", "winner"))
    now = store(start.select("seq", "loser", "ptr", "label"), "events")
    while now.where("ptr is not null").limit(1).count():
        to = now.select(F.col("seq").alias("ptr"), F.col("ptr").alias("next"), F.col("label").alias("found"))
        after = now.join(to, "ptr", "left").select("seq", "loser", F.col("next").alias("ptr"), F.coalesce("found", "label").alias("label"))
        after = store(after, "events")
        discard(now)
        now = after
    return now


def stream(edges: DataFrame, cap: int, admit: str = "le", tie: str = "source", labels: DataFrame | None = None, offset: DataFrame | None = None, all_nodes: DataFrame | None = None) -> DataFrame:
    """(node, community): the sequential stream's labels, in parallel.

    labels (node, community) and offset (node, deg) carry the state of an earlier part of the stream.
    """
    events = _resolve(event_pointers(copy_events(admitted(edges, cap, admit, offset), tie)), labels)
    last = events.groupBy(F.col("loser").alias("node")).agg(F.max_by("label", "seq").alias("label"))
    every = all_nodes.select("node") if all_nodes is not None else nodes(edges)
    if labels is not None:
        every = every.union(labels.select("node")).distinct().join(labels.select("node", F.col("community").alias("__own")), "node", "left")
        return every.join(last, "node", "left").select("node", F.coalesce("label", "__own", "node").alias("community"))
    return every.join(last, "node", "left").select("node", F.coalesce("label", "node").alias("community"))


def loop(rows: Iterator[tuple[int, int]], cap: int, admit: str = "le", count: str = "every", tie: str = "source", label: dict | None = None, deg: dict | None = None) -> tuple[dict, dict]:
    """The sequential method over (src, dst) pairs in order; returns labels and counters.

    count: 'every' (both ends of each edge), 'admitted' (both ends of admitted edges), 'joiner' (only the end that joins).
    """
    label, deg, limit = {} if label is None else label, {} if deg is None else deg, _limit(cap, admit)
    for s, d in rows:
        label.setdefault(s, s)
        label.setdefault(d, d)
        ds, dd = deg.setdefault(s, 0), deg.setdefault(d, 0)
        if count == "every":
            deg[s], deg[d] = ds, dd = ds + 1, dd + 1
            if ds > limit or dd > limit:
                continue
        elif ds > limit or dd > limit:
            continue
        elif count == "admitted":
            deg[s], deg[d] = ds, dd = ds + 1, dd + 1
        if ds == dd and tie == "hold":
            continue
        joins = ds < dd or ds == dd and (tie == "source" or s > d)
        a, b = (s, d) if joins else (d, s)
        label[a] = label[b]
        if count == "joiner":
            deg[a] += 1
    return label, deg


def stream_loop(edges: DataFrame, cap: int, admit: str = "le", count: str = "every", tie: str = "source") -> DataFrame:
    """The sequential method in one task, with all labels in memory: the reference, and the counter variants."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        label, deg = {}, {}
        for part in parts:
            loop(zip(part["src"].tolist(), part["dst"].tolist(), strict=True), cap, admit, count, tie, label, deg)
        yield pd.DataFrame({"node": list(label.keys()), "community": list(label.values())}, dtype="int64")

    ordered = edges.select("seq", "src", "dst").repartition(1).sortWithinPartitions("seq")
    return ordered.mapInPandas(run, "node bigint, community bigint")


def stream_sliced(edges: DataFrame, cap: int, slices: int = 64, admit: str = "le", tie: str = "source", reconcile_cap: int | None = None) -> DataFrame:
    """Disjoint slices of the stream run side by side without seeing each other; then one pass over the links between
    nodes and the communities that the slices gave them settles the differences."""

    def run(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("seq")
        label, _ = loop(zip(part["src"].tolist(), part["dst"].tolist(), strict=True), cap, admit, "every", tie)
        return pd.DataFrame({"node": list(label.keys()), "label": list(label.values())}, dtype="int64")

    cut = edges.select("seq", "src", "dst").withColumn("slice", F.pmod(F.xxhash64("seq"), F.lit(slices)).cast("int"))
    given = cut.groupBy("slice").applyInPandas(run, "node bigint, label bigint").where("node <> label")
    links = given.groupBy(F.col("node").alias("src"), F.col("label").alias("dst")).agg(F.count("*").alias("w"))
    links = links.withColumn("seq", F.struct(-F.col("w"), F.xxhash64("src", "dst"), "src", "dst"))
    return stream(store(links, "links"), reconcile_cap or 4 * cap, admit, tie, all_nodes=nodes(edges))


def bulk(edges: DataFrame, cap: int, admit: str = "le") -> DataFrame:
    """All admitted edges act at once: every node follows its strongest admitted neighbour (highest degree, then
    smallest id) if that is stronger than itself; pointers are followed to the top."""
    deg = degrees(edges)
    both = admitted(edges, cap, admit).select("src", "dst")
    both = both.union(both.select("dst", "src").toDF("src", "dst"))
    strong = lambda n, d: F.struct(F.col(d).alias("deg"), (-F.col(n)).alias("minus"))
    seen = both.join(deg.toDF("src", "sd"), "src").join(deg.toDF("dst", "dd"), "dst").where(strong("dst", "dd") > strong("src", "sd"))
    up = seen.groupBy(F.col("src").alias("node")).agg((-F.max(strong("dst", "dd"))["minus"]).alias("up"))
    now = store(nodes(edges).join(up, "node", "left").select("node", F.coalesce("up", "node").alias("up")), "up")
    while True:
        to = now.toDF("up", "next")
        after = store(now.join(to, "up").select("node", F.col("next").alias("up"), (F.col("next") != F.col("up")).alias("moved")), "up")
        if not after.where("moved").limit(1).count():
            return after.select("node", F.col("up").alias("community"))
        now = after.drop("moved")
