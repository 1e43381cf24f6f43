"""Force layout: one step as DataFrame kernels, and an iterated run in one task or over the cluster.

A layout has the columns node, x, y, mass, fx, fy, pfx, pfy; edges are src, dst, w. Forces: gravity towards the centre,
attraction along edges, repulsion between all nodes (exact, by a pyramid of grid cells, or by a tree whose crowded cells are
opened), each node's speed by its
swing, one global speed.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsummary.operators.opened import LEAF, TINY, pyramid_levels, repulsion_opened
from graphsummary.operators.sketch import PRIME
from graphsummary.sources.storage import discard, small, store

#: Fixed values of the hash that places nodes at the start.
PLACE = ((1103515245, 12345), (1664525013, 1013904223))
GROWTH = 1.5  # of the global speed, at most, in a step
#: The largest graph that one task lays out, and the largest for which it compares all pairs.
TASK_NODES, TASK_EDGES, ALL_PAIRS = 50_000, 2_000_000, 3_000
#: The largest graph whose places every worker holds (48 bytes a node), nodes in a block (a task), and the most blocks.
HELD_NODES, BLOCK_NODES, BLOCKS = 3_000_000, 16_384, 64
#: Near pairs for each node before leaves are made deeper, and the deepest level.
NEAR_PAIRS, DEEPEST = 150, 10
#: Pairs of a node and what pushes it that are made at once: few enough for the processor's cache.
PAIRS_AT_ONCE = 65_536
OUTER = 0.002


# ---------------------------------------------------------------- kernels
def init(nodes: DataFrame, seed: int = 0, shape: str = "disc", spread: float = 100.0, mass: str | None = None) -> DataFrame:
    """Positions from a hash of the node: no random generator, so any engine and any partitioning agrees."""
    def unit(a: int, b: int):
        x = F.pmod(F.pmod("node", F.lit(PRIME).cast("bigint")) * F.lit(a).cast("bigint") + F.lit(b + seed).cast("bigint"), F.lit(PRIME).cast("bigint"))
        return x / F.lit(float(PRIME))

    u, v = unit(*PLACE[0]), unit(*PLACE[1])
    r, t = F.sqrt(u) * spread, v * (2 * math.pi)
    x, y = (r * F.cos(t), r * F.sin(t)) if shape == "disc" else (u * spread, v * spread)
    zero = F.lit(0.0)
    return nodes.select("node", x.alias("x"), y.alias("y"), (F.col(mass).cast("double") if mass else F.lit(1.0)).alias("mass"), *[zero.alias(c) for c in ("fx", "fy", "pfx", "pfy")])


def gravity(layout: DataFrame, scale: float = 1.0, mode: str = "unit") -> DataFrame:
    """(node, fx, fy): a pull of the node's mass towards the origin; 'strong' grows with the distance."""
    d = F.sqrt(F.col("x") * F.col("x") + F.col("y") * F.col("y"))
    f = F.lit(-scale) * F.col("mass") if mode == "strong" else F.when(d > TINY, F.lit(-scale) * F.col("mass") / d).otherwise(F.lit(0.0))
    return layout.select("node", (f * F.col("x")).alias("fx"), (f * F.col("y")).alias("fy"))


def attraction(layout: DataFrame, edges: DataFrame, mode: str = "linear") -> DataFrame:
    """(node, fx, fy): every edge pulls both of its ends towards each other, by its weight."""
    at = layout.select("node", "x", "y")
    j = edges.join(at.toDF("src", "xs", "ys"), "src").join(at.toDF("dst", "xd", "yd"), "dst")
    j = j.select("src", "dst", F.col("w").cast("double").alias("w"), (F.col("xd") - F.col("xs")).alias("dx"), (F.col("yd") - F.col("ys")).alias("dy"))
    d = F.sqrt(F.col("dx") * F.col("dx") + F.col("dy") * F.col("dy"))
    f = {"linear": F.col("w"), "unit": F.when(d > TINY, F.col("w") / d).otherwise(F.lit(0.0)), "log": F.when(d > TINY, F.col("w") * F.log1p(d) / d).otherwise(F.lit(0.0))}[mode]
    j = j.withColumns({"px": f * F.col("dx"), "py": f * F.col("dy")})
    both = F.array(F.struct(F.col("src").alias("node"), F.col("px").alias("fx"), F.col("py").alias("fy")), F.struct(F.col("dst").alias("node"), (-F.col("px")).alias("fx"), (-F.col("py")).alias("fy")))
    return j.select(F.explode(both).alias("f")).select("f.*").groupBy("node").agg(F.sum("fx").alias("fx"), F.sum("fy").alias("fy"))


def _push(scale: float):
    """Force on (x, y, mass) from (ox, oy, omass): scale * m * om / d, away from it; nothing at the same point."""
    dx, dy = F.col("x") - F.col("ox"), F.col("y") - F.col("oy")
    d2 = dx * dx + dy * dy
    f = F.when(d2 > TINY, F.lit(scale) * F.col("mass") * F.col("omass") / d2).otherwise(F.lit(0.0))
    return F.sum(f * dx).alias("fx"), F.sum(f * dy).alias("fy")


def repulsion_exact(layout: DataFrame, scale: float = 80.0) -> DataFrame:
    """(node, fx, fy) over all pairs, for checking the pyramid on small layouts."""
    a = layout.select("node", "x", "y", "mass")
    return a.crossJoin(F.broadcast(a.toDF("other", "ox", "oy", "omass"))).where("node <> other").groupBy("node").agg(*_push(scale))


def repulsion_tree(layout: DataFrame, scale: float = 80.0, levels: int | None = None) -> DataFrame:
    """(node, fx, fy): exact between nodes of neighbouring leaf cells, cell by cell beyond.

    On each level a node meets the cells whose parents neighbour its own parent's cell and which do not neighbour its own
    cell: at most 27, found by an equi-join on the cell.
    """
    box = layout.agg(F.min("x"), F.max("x"), F.min("y"), F.max("y"), F.count("*")).first()
    x0, x1, y0, y1, n = box
    if not n:
        return layout.select("node", "fx", "fy")
    levels = levels or pyramid_levels(n)
    side = max(x1 - x0, y1 - y0, TINY) * (1 + 1e-9)
    top = 1 << levels
    leaf = lambda c, low: F.least(F.floor((F.col(c) - low) / side * top), F.lit(top - 1)).cast("bigint")
    at = store(layout.select("node", "x", "y", "mass", leaf("x", x0).alias("cx"), leaf("y", y0).alias("cy")), "leaves")
    far = F.array(*[F.struct(F.lit(i).cast("bigint").alias("i"), F.lit(j).cast("bigint").alias("j")) for i in range(-3, 4) for j in range(-3, 4) if max(abs(i), abs(j)) > 1])
    near = F.array(*[F.struct(F.lit(i).cast("bigint").alias("i"), F.lit(j).cast("bigint").alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
    level = F.explode(F.sequence(F.lit(2), F.lit(levels)))
    up = lambda c: F.floor(F.col(c) / F.pow(F.lit(2), F.lit(levels) - F.col("level"))).cast("bigint")
    on = at.select("node", "x", "y", "mass", "cx", "cy", level.alias("level")).withColumns({"cx": up("cx"), "cy": up("cy")})
    mid = lambda c: (F.sum(F.col(c) * F.col("mass")) / F.sum("mass")).alias(f"o{c}")
    cells = store(on.where("mass > 0").groupBy("level", "cx", "cy").agg(mid("x"), mid("y"), F.sum("mass").alias("omass")), "cells")
    half = lambda c: F.floor(F.col(c) / 2)
    meet = on.select("node", "x", "y", "mass", "level", "cx", "cy", F.explode(far).alias("o"))
    meet = meet.withColumns({"tx": F.col("cx") + F.col("o.i"), "ty": F.col("cy") + F.col("o.j")}).where((F.abs(half("tx") - half("cx")) <= 1) & (F.abs(half("ty") - half("cy")) <= 1))
    other = cells.toDF("level", "tx", "ty", "ox", "oy", "omass")
    by_cell = meet.select("node", "x", "y", "mass", "level", "tx", "ty").join(small(other), ["level", "tx", "ty"]).groupBy("node").agg(*_push(scale))
    close = at.select("node", "x", "y", "mass", F.explode(near).alias("o"), "cx", "cy").select("node", "x", "y", "mass", (F.col("cx") + F.col("o.i")).alias("tx"), (F.col("cy") + F.col("o.j")).alias("ty"))
    by_node = close.join(at.select(F.col("node").alias("other"), F.col("x").alias("ox"), F.col("y").alias("oy"), F.col("mass").alias("omass"), F.col("cx").alias("tx"), F.col("cy").alias("ty")), ["tx", "ty"]).where("node <> other").groupBy("node").agg(*_push(scale))
    return by_cell.union(by_node).groupBy("node").agg(F.sum("fx").alias("fx"), F.sum("fy").alias("fy"))


def add_forces(layout: DataFrame, *forces: DataFrame) -> DataFrame:
    """The layout with the sum of the forces as fx, fy, and what stood there as pfx, pfy."""
    total = forces[0]
    for f in forces[1:]:
        total = total.union(f)
    total = total.groupBy("node").agg(F.sum("fx").alias("gx"), F.sum("fy").alias("gy"))
    j = layout.join(total, "node", "left")
    return j.select("node", "x", "y", "mass", F.coalesce("gx", F.lit(0.0)).alias("fx"), F.coalesce("gy", F.lit(0.0)).alias("fy"), F.col("fx").alias("pfx"), F.col("fy").alias("pfy"))


def _size(sign: int):
    dx, dy = F.col("fx") + sign * F.col("pfx"), F.col("fy") + sign * F.col("pfy")
    return F.sqrt(dx * dx + dy * dy)


def totals(layout: DataFrame) -> DataFrame:
    """(swing, traction), weighted by mass."""
    return layout.agg(F.sum(F.col("mass") * _size(-1)).alias("swing"), F.sum(F.col("mass") * _size(1) / 2).alias("traction"))


def speeds(layout: DataFrame, global_speed: float = 1.0, rule: str = "published") -> DataFrame:
    """(node, swing, speed)."""
    g, s = F.lit(float(global_speed)), F.col("swing")
    v = g / (1 + F.sqrt(g + s)) if rule == "paper" else g / (1 + g * F.sqrt(s))
    return layout.select("node", _size(-1).alias("swing")).withColumn("speed", v)


def move(layout: DataFrame, speeds_: DataFrame) -> DataFrame:
    j = layout.join(speeds_.select("node", "speed"), "node")
    return j.select("node", (F.col("x") + F.col("speed") * F.col("fx")).alias("x"), (F.col("y") + F.col("speed") * F.col("fy")).alias("y"), "mass", "fx", "fy", "pfx", "pfy")


def next_speed(now: float, swing: float, traction: float, tolerance: float = 1.0) -> float:
    """Tolerance times traction over swing, growing by half at most."""
    wanted = tolerance * traction / swing if swing > TINY else now * GROWTH
    return min(wanted, now * GROWTH)


# ---------------------------------------------------------------- one task
def _cells(x: np.ndarray, y: np.ndarray, m: np.ndarray, scale: float) -> tuple[np.ndarray, np.ndarray]:
    """Pyramid repulsion over arrays, with the cells that blocks have."""
    g, fx, fy = _grids(x, y, m), np.empty(len(x)), np.empty(len(x))
    for lo in range(0, len(x), 8192):
        at = g["order"][lo : lo + 8192]
        fx[at], fy[at] = _push_block(g, lo, lo + len(at), scale)
    return fx, fy


def _pairs(x: np.ndarray, y: np.ndarray, m: np.ndarray, scale: float) -> tuple[np.ndarray, np.ndarray]:
    fx, fy = np.empty(len(x)), np.empty(len(x))
    for i in range(0, len(x), 512):
        s = slice(i, i + 512)
        dx, dy = x[s, None] - x, y[s, None] - y
        d2 = dx * dx + dy * dy
        f = np.where(d2 > TINY, scale * m[s, None] * m / np.maximum(d2, TINY), 0.0)
        fx[s], fy[s] = (f * dx).sum(1), (f * dy).sum(1)
    return fx, fy


def run_arrays(x, y, mass, src, dst, w, iterations: int, gravity_: float = 1.0, repulsion: float = 80.0, gravity_mode: str = "unit", attraction_: str = "linear", speed: str = "published", tolerance: float = 1.0, stop_eps: float | None = None, all_pairs: int = ALL_PAIRS):
    """The same step on arrays, repeated; returns x, y and the trace."""
    x, y, n = x.astype(float).copy(), y.astype(float).copy(), len(x)
    px, py, g, trace = np.zeros(n), np.zeros(n), 1.0, []
    for it in range(1, iterations + 1):
        fx, fy = (_pairs if n <= all_pairs else _cells)(x, y, mass, repulsion)
        d = np.hypot(x, y)
        pull = -gravity_ * mass * (1 if gravity_mode == "strong" else np.where(d > TINY, 1 / np.maximum(d, TINY), 0))
        fx, fy = fx + pull * x, fy + pull * y
        dx, dy = x[dst] - x[src], y[dst] - y[src]
        if attraction_ == "linear":
            f = w
        else:
            e = np.hypot(dx, dy)
            f = np.where(e > TINY, w * (np.log1p(e) if attraction_ == "log" else 1) / np.maximum(e, TINY), 0)
        fx += np.bincount(src, f * dx, n) - np.bincount(dst, f * dx, n)
        fy += np.bincount(src, f * dy, n) - np.bincount(dst, f * dy, n)
        swing = np.hypot(fx - px, fy - py)
        total, traction = (mass * swing).sum(), (mass * np.hypot(fx + px, fy + py) / 2).sum()
        g = next_speed(g, total, traction, tolerance) if it > 1 else g
        v = g / (1 + np.sqrt(g + swing)) if speed == "paper" else g / (1 + g * np.sqrt(swing))
        x, y, px, py = x + v * fx, y + v * fy, fx, fy
        most, across = float((v * np.hypot(fx, fy)).max(initial=0)), float(np.hypot(np.ptp(x), np.ptp(y))) if n else 0.0
        trace.append((it, most, across, float(total), float(traction), float(g)))
        if stop_eps is not None and most <= stop_eps * across:
            break
    return x, y, trace


# ---------------------------------------------------------------- blocks of nodes, places held by every worker
def _grids(x: np.ndarray, y: np.ndarray, m: np.ndarray) -> dict:
    """The nodes in the order of their leaf cells, where each cell starts, and mass and centre of the cells of all levels, each
    with two empty ones around, one level after the other. Where that leaves places crowded, the cells span all but the outermost OUTER of the nodes on
    each side, these lie in the outermost cells (whose centres stay true), and leaves go down to DEEPEST."""
    n, levels = len(x), pyramid_levels(len(x))
    low, side = (x.min(), y.min()), max(np.ptp(x), np.ptp(y), TINY) * (1 + 1e-9)
    spread = False
    while True:
        top = 1 << levels
        cx, cy = (np.clip(np.floor((v - v0) / side * top), 0, top - 1).astype(np.int64) for v, v0 in zip((x, y), low, strict=True))
        key = cx * top + cy
        held = np.pad(np.bincount(key, minlength=top * top).reshape(top, top), 1)
        about = sum(held[1 + i : 1 + i + top, 1 + j : 1 + j + top] for i in (-1, 0, 1) for j in (-1, 0, 1))
        if spread and levels >= DEEPEST or (held[1:-1, 1:-1] * about).sum() <= NEAR_PAIRS * n:
            break
        if not spread:
            ends = [np.quantile(v, (OUTER, 1 - OUTER)) for v in (x, y)]
            low, side, spread = (ends[0][0], ends[1][0]), max(*(e[1] - e[0] for e in ends), TINY) * (1 + 1e-9), True
        else:
            levels += 1
    order = np.argsort(key, kind="stable")
    sums, pyramid = [np.bincount(key, v, top * top).reshape(top, top) for v in (m, m * x, m * y)], []
    for _ in range(levels, 1, -1):
        mass = np.maximum(sums[0], TINY)
        pyramid.append([np.pad(v, 2).ravel() for v in (sums[0], sums[1] / mass, sums[2] / mass)])
        sums = [v.reshape(v.shape[0] // 2, 2, -1, 2).sum((1, 3)) for v in sums]
    first = np.concatenate([[0], np.cumsum(held[1:-1, 1:-1].ravel())])
    return {"levels": levels, "pyramid": [np.concatenate(v) for v in zip(*pyramid, strict=True)], "first": first, "key": key[order].astype(np.int32), "x": x[order], "y": y[order], "m": m[order], "order": order.astype(np.int32)}


def _far_steps() -> np.ndarray:
    """For a cell's parities in x and y: steps to the 27 cells whose parents neighbour its parent and which don't neighbour it."""
    reach = [range(-2 - odd, 4 - odd) for odd in (0, 1)]
    return np.array([[(i, j) for i in reach[p >> 1] for j in reach[p & 1] if max(abs(i), abs(j)) > 1] for p in range(4)])


_FAR = _far_steps()


def _sum_pushes(x: np.ndarray, y: np.ndarray, of: np.ndarray, om: np.ndarray, ox: np.ndarray, oy: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """What the masses in row of[i] give the node i in all."""
    dx, dy, f = (np.take(v, of, axis=0) for v in (ox, oy, om))
    dx -= x[:, None]
    dy -= y[:, None]
    d2 = dx * dx
    d2 += dy * dy
    d2[d2 <= TINY] = np.inf
    f /= d2
    return -np.vecdot(f, dx), -np.vecdot(f, dy)


def _push_block(g: dict, lo: int, hi: int, scale: float) -> tuple[np.ndarray, np.ndarray]:
    """Pyramid repulsion on the nodes lo to hi in the order of cells: of these cells, the ones that repulsion_tree meets. All nodes
    of a leaf cell meet the same ones, so they are looked up once for a leaf cell."""
    levels, x, y, m = g["levels"], g["x"][lo:hi], g["y"][lo:hi], g["m"][lo:hi]
    top = 1 << levels
    key = g["key"][lo:hi].astype(np.int64)
    new = np.concatenate([[True], key[1:] != key[:-1]])
    of, (cx, cy) = np.cumsum(new) - 1, np.divmod(key[new], top)
    fx, fy = np.zeros(hi - lo), np.zeros(hi - lo)

    far, begun = [], 0
    for level in range(levels, 1, -1):
        wide, ax, ay = (1 << level) + 4, cx >> (levels - level), cy >> (levels - level)
        steps = _FAR[..., 0] * wide + _FAR[..., 1]
        far.append((begun + (ax + 2) * wide + ay + 2)[:, None] + steps[(ax & 1) * 2 + (ay & 1)])
        begun += wide * wide
    far = np.concatenate(far, 1)
    rows = max(1, PAIRS_AT_ONCE // far.shape[1])
    for a in range(0, hi - lo, rows):
        s = slice(a, a + rows)
        c = far[of[s][0] : of[s][-1] + 1]
        fx[s], fy[s] = _sum_pushes(x[s], y[s], of[s] - of[a], *(v[c] for v in g["pyramid"]))

    tx = cx[:, None] + np.arange(-1, 2)
    ok, row = (tx >= 0) & (tx < top), np.clip(tx, 0, top - 1) * top
    start = g["first"][row + np.maximum(cy - 1, 0)[:, None]]
    ends = np.cumsum(np.where(ok, g["first"][row + np.minimum(cy + 1, top - 1)[:, None] + 1] - start, 0), 1)
    start[:, 1:] -= ends[:, :-1]
    order = np.argsort(-ends[of, 2], kind="stable")  # nodes of a cell stay together, and with those that meet about as many
    met, a = ends[of, 2][order], 0
    while a < hi - lo:
        s = order[a : a + max(1, PAIRS_AT_ONCE // met[a])]
        new = np.concatenate([[True], of[s][1:] != of[s][:-1]])
        c, k = of[s][new], np.arange(met[a])
        begin, end = start[c], ends[c]
        i = np.where(k < end[:, :1], begin[:, :1], np.where(k < end[:, 1:2], begin[:, 1:2], begin[:, 2:])) + k
        none = k >= end[:, 2:]
        i[none] = 0
        om = g["m"][i]
        om[none] = 0.0
        ux, uy = _sum_pushes(x[s], y[s], np.cumsum(new) - 1, om, g["x"][i], g["y"][i])
        fx[s] += ux
        fy[s] += uy
        a += len(s)
    return fx * scale * m, fy * scale * m


_FORCES = "at binary, fx binary, fy binary"


def _row(at: np.ndarray, fx: np.ndarray, fy: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([v.tobytes()], pa.binary()) for v in (at.astype(np.int32), fx, fy)], names=["at", "fx", "fy"])


def _run_blocks(start: DataFrame, links: DataFrame, iterations: int, gravity_: float, repulsion: float, gravity_mode: str, attraction_: str, speed: str, tolerance: float, stop_eps: float | None) -> tuple[DataFrame, DataFrame]:
    """The steps of run_arrays with the pyramid, its forces by blocks of nodes and of edges over the cluster. Places are sent
    to every worker for each step and forces come back to the driver: at most HELD_NODES nodes; edges stay where they are."""
    spark = start.sparkSession
    held = start.select("node", "x", "y", "mass").orderBy("node").toArrow()
    ids, x, y, mass = (held.column(c).to_numpy() for c in ("node", "x", "y", "mass"))
    n, given = len(ids), spark.sparkContext.broadcast(ids)

    def halves(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (np.searchsorted(given.value, batch.column(i).to_numpy()).astype(np.int32) for i in (0, 1))
            w = batch.column(2).to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([a, b])), pa.array(np.concatenate([b, a])), pa.array(np.concatenate([w, w]))], names=["own", "other", "w"])

    ends = links.select("src", "dst", "w").mapInArrow(halves, "own int, other int, w double").repartitionByRange("own").sortWithinPartitions("own")
    ends = store(ends, "ends")
    blocks = max(1, min(BLOCKS, n // BLOCK_NODES))
    px, py, g, trace = np.zeros(n), np.zeros(n), 1.0, []
    for it in range(1, iterations + 1):
        grids = _grids(x, y, mass)
        now = spark.sparkContext.broadcast((grids, x, y))

        def push(batches: Iterator[pa.RecordBatch], now=now) -> Iterator[pa.RecordBatch]:
            grids = now.value[0]
            for batch in batches:
                for block in batch.column(0).to_pylist():
                    for lo in range(n * block // blocks, n * (block + 1) // blocks, 8192):
                        hi = min(lo + 8192, n * (block + 1) // blocks)
                        yield _row(grids["order"][lo:hi], *_push_block(grids, lo, hi, repulsion))

        def pull(batches: Iterator[pa.RecordBatch], now=now) -> Iterator[pa.RecordBatch]:
            _, x, y = now.value
            for batch in batches:
                own, other, w = (batch.column(i).to_numpy() for i in range(3))
                dx, dy = x[other] - x[own], y[other] - y[own]
                if attraction_ != "linear":
                    e = np.hypot(dx, dy)
                    w = np.where(e > TINY, w * (np.log1p(e) if attraction_ == "log" else 1) / np.maximum(e, TINY), 0)
                at, of = np.unique(own, return_inverse=True)
                yield _row(at, np.bincount(of, w * dx, len(at)), np.bincount(of, w * dy, len(at)))

        forces = spark.range(0, blocks, 1, blocks).mapInArrow(push, _FORCES).union(ends.mapInArrow(pull, _FORCES)).toArrow()
        d = np.hypot(x, y)
        unit = -gravity_ * mass * (1 if gravity_mode == "strong" else np.where(d > TINY, 1 / np.maximum(d, TINY), 0))
        fx, fy = unit * x, unit * y
        for at, ux, uy in zip(*(forces.column(i).to_pylist() for i in range(3)), strict=True):
            i = np.frombuffer(at, np.int32)  # each node once
            fx[i] += np.frombuffer(ux)
            fy[i] += np.frombuffer(uy)
        now.destroy()
        swing = np.hypot(fx - px, fy - py)
        total, traction = (mass * swing).sum(), (mass * np.hypot(fx + px, fy + py) / 2).sum()
        g = next_speed(g, total, traction, tolerance) if it > 1 else g
        v = g / (1 + np.sqrt(g + swing)) if speed == "paper" else g / (1 + g * np.sqrt(swing))
        x, y, px, py = x + v * fx, y + v * fy, fx, fy
        most, across = float((v * np.hypot(fx, fy)).max(initial=0)), float(np.hypot(np.ptp(x), np.ptp(y)))
        trace.append((it, most, across, float(total), float(traction), float(g)))
        if stop_eps is not None and most <= stop_eps * across:
            break
    made = store(spark.createDataFrame(pa.table({"node": ids, "x": x, "y": y, "mass": mass})), "layout")
    given.destroy()
    discard(ends)
    return made, spark.createDataFrame(trace, TRACE)


TRACE = "iteration int, max_move double, diameter double, swing double, traction double, global_speed double"


def run(nodes: DataFrame, edges: DataFrame, iterations: int = 100, gravity_: float = 1.0, repulsion: float = 80.0, engine: str = "auto", stop_eps: float | None = None, seed: int = 0, mass: str | None = None,
        gravity_mode: str = "unit", attraction_: str = "linear", speed: str = "published", tolerance: float = 1.0, all_pairs: int = ALL_PAIRS, theta: float | None = None) -> tuple[DataFrame, DataFrame]:
    """(layout, trace). engine 'task' lays the whole graph out in one task with array kernels; its size is checked.
    engine 'blocks' shares the same steps out over the cluster, with the places of all nodes in every worker; its size is
    checked too. engine 'spark' keeps nodes and edges distributed and writes positions to shared storage every few steps; with theta,
    its repulsion opens cells by it, at every size."""
    if theta is not None and engine != "spark":
        raise ValueError("theta needs engine 'spark'")
    start = store(init(nodes, seed, mass=mass), "start")
    links = store(edges.select("src", "dst", F.col("w").cast("double").alias("w")), "links")
    n, m = start.count(), links.count()
    fits = n <= TASK_NODES and m <= TASK_EDGES
    if engine == "task" and not fits:
        raise ValueError(f"{n} nodes and {m} edges are too many for one task")
    if engine == "blocks" and not 0 < n <= HELD_NODES:
        raise ValueError(f"{n} nodes are not between 1 and {HELD_NODES}")
    spark = nodes.sparkSession
    if engine == "blocks" or engine == "auto" and not fits and n <= HELD_NODES:
        return _run_blocks(start, links, iterations, gravity_, repulsion, gravity_mode, attraction_, speed, tolerance, stop_eps)
    if engine != "spark" and fits:
        options = (iterations, gravity_, repulsion, gravity_mode, attraction_, speed, tolerance, stop_eps, all_pairs)

        def one(nodes_: pd.DataFrame, edges_: pd.DataFrame) -> pd.DataFrame:
            nodes_ = nodes_.sort_values("node").reset_index(drop=True)
            if not len(nodes_):
                return pd.DataFrame(columns=["node", "x", "y", "mass", "trace"])
            edges_ = edges_.sort_values(["src", "dst"])
            ids = nodes_["node"].to_numpy()
            src, dst = np.searchsorted(ids, edges_["src"].to_numpy()), np.searchsorted(ids, edges_["dst"].to_numpy())
            x, y, trace = run_arrays(nodes_["x"].to_numpy(), nodes_["y"].to_numpy(), nodes_["mass"].to_numpy(), src, dst, edges_["w"].to_numpy(), *options)
            out = pd.DataFrame({"node": ids, "x": x, "y": y, "mass": nodes_["mass"]})
            out["trace"] = None
            out.at[0, "trace"] = [list(map(float, t)) for t in trace]
            return out

        key = F.lit(1).alias("one")
        made = start.select(key, "node", "x", "y", "mass").groupBy("one").cogroup(links.select(key, "src", "dst", "w").groupBy("one")).applyInPandas(one, "node bigint, x double, y double, mass double, trace array<array<double>>")
        made = store(made, "layout")
        t = made.where("trace is not null").select(F.explode("trace").alias("t"))
        trace = t.select(*[F.col("t")[i].cast("int" if i == 0 else "double").alias(c.split()[0]) for i, c in enumerate(TRACE.split(", "))])
        return made.select("node", "x", "y", "mass"), trace
    now, g, rows = start, 1.0, []
    for it in range(1, iterations + 1):
        push = repulsion_opened(now, repulsion, theta) if theta is not None else repulsion_exact(now, repulsion) if n <= all_pairs else repulsion_tree(now, repulsion)
        forced = store(add_forces(now, gravity(now, gravity_, gravity_mode), attraction(now, links, attraction_), push), "forces")
        t = totals(forced).first()
        g = next_speed(g, t["swing"] or 0.0, t["traction"] or 0.0, tolerance) if it > 1 else g
        moved = store(move(forced, speeds(forced, g, speed)), "layout")
        step = moved.join(now.select("node", F.col("x").alias("ox"), F.col("y").alias("oy")), "node")
        s = step.agg(F.max(F.hypot(F.col("x") - F.col("ox"), F.col("y") - F.col("oy"))).alias("most"), F.hypot(F.max("x") - F.min("x"), F.max("y") - F.min("y")).alias("across")).first()
        rows.append((it, float(s["most"] or 0), float(s["across"] or 0), float(t["swing"] or 0), float(t["traction"] or 0), float(g)))
        for old in (now, forced):
            discard(old)
        now = moved
        if stop_eps is not None and rows[-1][1] <= stop_eps * rows[-1][2]:
            break
    return now.select("node", "x", "y", "mass"), spark.createDataFrame(rows, TRACE)


