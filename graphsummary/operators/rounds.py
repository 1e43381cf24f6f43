"""Detection in rounds with a growing cap, and what can be read off the rounds."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphsummary.operators import detect as detection
from graphsummary.operators import measure
from graphsummary.operators.edges import base_cap, degrees, nodes
from graphsummary.sources.storage import store

#: Caps beyond this admit every edge of any list that fits a count.
MOST = 1 << 62


@dataclass
class Detection:
    assignment: DataFrame  # node, community
    hierarchy: DataFrame  # round, cap, child, parent
    metrics: list[dict]  # one for each round: round, cap, sn, se, changed, q
    base: int


def caps(base: int, rounds: int, schedule: str = "power", factor: float = 2.0) -> list[int]:
    """The cap of each round; a base of 1 would never grow as a power and counts as 2 there."""
    if schedule == "power":
        return [min(MOST, max(base, 2) ** i) for i in range(1, rounds + 1)]
    if schedule == "geometric":
        return [min(MOST, int(base * factor**i)) for i in range(rounds)]
    if schedule == "constant":
        return [base] * rounds
    raise ValueError("schedule is 'power', 'geometric' or 'constant'")


def relabel(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """Edges between the communities of their ends, loops gone, repeats and arrival order kept."""
    a = assignment.toDF("src", "__s")
    b = assignment.toDF("dst", "__d")
    return edges.join(a, "src").join(b, "dst").where("__s <> __d").select("seq", F.col("__s").alias("src"), F.col("__d").alias("dst"), "w")


def detect(edges: DataFrame, rounds: int = 10, threshold: str | int = "mode", threshold_scale: int = 1, schedule: str = "power", factor: float = 2.0, carry: str = "contract",
           admit: str = "le", tie: str = "source", stop_when_stable: bool = True, with_q: bool = False, kernel: Callable[..., DataFrame] | None = None, cap_list: list[int] | None = None) -> Detection:
    """Repeat the stream detector. carry='contract' goes on with the communities as nodes and fresh counters;
    'labels' replays the original edges with labels and counters kept."""
    if carry not in ("contract", "labels"):
        raise ValueError("carry is 'contract' or 'labels'")
    base = base_cap(edges, threshold, threshold_scale) if cap_list is None else cap_list[0]
    plan = cap_list or caps(base, rounds, schedule, factor)
    kernel = kernel or detection.stream
    every = nodes(edges)
    total = store(every.select("node", F.col("node").alias("community")), "labels")
    now, levels, metrics, deg = edges, [], [], None
    for i, cap in enumerate(plan, 1):
        if carry == "contract":
            step = store(kernel(now, cap, admit=admit, tie=tie), "step")
            moved = step.where("node <> community")
            merged = total.join(step.toDF("community", "__to"), "community", "left").select("node", F.coalesce("__to", "community").alias("community"))
            level = step.select(F.lit(i).alias("round"), F.lit(cap).cast("bigint").alias("cap"), F.col("node").alias("child"), F.col("community").alias("parent"))
            changed = moved.count()
        else:
            deg = store(degrees(edges), "degrees") if deg is None else deg
            offset = deg.select("node", (F.col("deg") * (i - 1)).alias("deg"))
            merged = detection.stream(edges, cap, admit, tie, labels=total if i > 1 else None, offset=offset if i > 1 else None)
        merged = store(merged, "labels")
        if carry == "labels":
            both = total.toDF("node", "old").join(merged, "node")
            changed = both.where("old <> community").count()
            level = both.select(F.lit(i).alias("round"), F.lit(cap).cast("bigint").alias("cap"), F.col("old").alias("child"), F.col("community").alias("parent")).distinct()
        total = merged
        levels.append(level)
        after = store(relabel(now if carry == "contract" else edges, step if carry == "contract" else total), "edges")
        pairs = after.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
        row = {"round": i, "cap": cap, "sn": total.select("community").distinct().count(), "se": pairs.count(), "changed": changed}
        if with_q:
            row["q"] = measure.modularity(edges, total).first()[0]
        metrics.append(row)
        if carry == "contract":
            now = after
        if stop_when_stable and cap_list is None and (not changed or not row["se"]):
            break
    hierarchy = levels[0]
    for level in levels[1:]:
        hierarchy = hierarchy.unionByName(level)
    return Detection(total, hierarchy, metrics, base)


def sweep(edges: DataFrame, rounds: list[int], **options) -> list[dict]:
    """Independent runs, each from the start, one for every number of rounds."""
    return [detect(edges, rounds=k, stop_when_stable=False, **options).metrics[-1] | {"rounds": k} for k in rounds]


def metrics_frame(spark, metrics: list[dict]) -> DataFrame:
    rows = [(m["round"], int(m["cap"]), m["sn"], m["se"], m["changed"], m.get("q")) for m in metrics]
    return spark.createDataFrame(rows, "round int, cap bigint, sn bigint, se bigint, changed bigint, q double")


def converged(metrics: DataFrame) -> DataFrame:
    """(stable_round): the first round after which the number of communities stays."""
    last = metrics.withColumn("before", F.lag("sn").over(Window.orderBy("round"))).where("before is null or before <> sn")
    return last.agg(F.max("round").alias("stable_round"))


def best_round(metrics: DataFrame, by: str = "q") -> DataFrame:
    """(best_round, best): the earliest round with the highest value."""
    return metrics.agg((-F.max(F.struct(F.col(by), -F.col("round")))["col2"]).alias("best_round"), F.max(by).alias("best"))
