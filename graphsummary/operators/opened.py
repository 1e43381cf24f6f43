"""Repulsion by a tree whose crowded cells are opened, in blocks of nodes that each get the part of the tree they can reach.

Nodes are dealt to blocks: the largest cells with few enough nodes. What lies above the blocks is a small tree that every
worker holds. A block asks each block that one of its nodes may open for its inner part, and is sent only the cells and
nodes that could be met from anywhere in the asking block. So a node's way down the tree is never written as rows.

A cell's code is 4 ** level plus its place on a space-filling order, so a cell's quarters follow each other and have the
codes 4 * code to 4 * code + 3.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsummary.sources.storage import discard, small, store

LEAF = 8  # nodes in a leaf cell, about
TINY = 1e-9
#: Nodes in a block; the most blocks wanted, beyond which blocks hold more nodes.
BLOCK, MOST_BLOCKS = 4096, 1 << 18
#: Cells that the driver counts at once, blocks that one task of a block answers, and pairs of a node and a cell made at once.
COUNTED, ANSWERED, MET = 1 << 20, 1024, 2_000_000
CELL = np.dtype([("code", "i8"), ("held", "i8"), ("x", "f8"), ("y", "f8"), ("mass", "f8"), ("listed", "i8")])
POINT = np.dtype([("x", "f8"), ("y", "f8"), ("mass", "f8")])


def pyramid_levels(n: int) -> int:
    return max(2, min(20, math.ceil(math.log(max(1, n / LEAF), 4))))


def _apart(c: Column) -> Column:
    """The bits of c, a zero before each."""
    for shift, mask in ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555)):
        c = c.bitwiseOR(F.shiftleft(c, shift)).bitwiseAND(F.lit(mask).cast("bigint"))
    return c


def _together(c: np.ndarray) -> np.ndarray:
    """Every other bit of c."""
    c = c & 0x5555555555555555
    for shift, mask in ((1, 0x3333333333333333), (2, 0x0F0F0F0F0F0F0F0F), (4, 0x00FF00FF00FF00FF), (8, 0x0000FFFF0000FFFF), (16, 0x00000000FFFFFFFF)):
        c = (c | c >> shift) & mask
    return c


def _level(code: np.ndarray) -> np.ndarray:
    return np.searchsorted(np.int64(1) << 2 * np.arange(32, dtype=np.int64), code, "right") - 1


def _spread(first: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For runs that start at first: which run, and which place, for every place in them."""
    own = np.repeat(np.arange(len(size)), size)
    return own, np.arange(len(own)) - np.repeat(np.cumsum(size) - size, size) + np.repeat(first, size)


@dataclass
class _Frame:
    """The square that holds all nodes, and when a cell is opened."""

    x0: float
    y0: float
    side: float
    most: float  # the largest coordinate, for what rounding may move
    deepest: int
    leaf: int
    theta: float

    def width(self, level: np.ndarray) -> np.ndarray:
        return self.side / np.exp2(level)

    def boxes(self, code: np.ndarray) -> tuple[np.ndarray, ...]:
        """Bounds of cells, with what rounding may move."""
        level = _level(code)
        place, wide, more = code - (np.int64(1) << 2 * level), self.width(level), 1e-12 * self.side + 1e-14 * self.most
        x, y = self.x0 + _together(place >> 1) * wide, self.y0 + _together(place) * wide
        return x - more, x + wide + more, y - more, y + wide + more

    def far_from_all(self, boxes: tuple[np.ndarray, ...], t: np.ndarray, level: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Whether cells around x, y are far for every place in the boxes t; those that could be near for rounding aren't."""
        low_x, high_x, low_y, high_y = (b[t] for b in boxes)
        away = np.hypot(np.maximum(np.maximum(low_x - x, x - high_x), 0), np.maximum(np.maximum(low_y - y, y - high_y), 0))
        return self.width(level) * (1 + 1e-9) < self.theta * away


@dataclass
class _Tree:
    """The blocks in order, and the cells from level 2 down to the blocks that hold mass."""

    cells: np.ndarray
    blocks: np.ndarray  # codes, in the order of their nodes
    units: np.ndarray  # the blocks' first units, and how many there are in all
    inner: np.ndarray = field(init=False)  # cells that are no blocks
    level: np.ndarray = field(init=False)

    def __post_init__(self) -> None:
        self.inner, self.level = ~np.isin(self.cells["code"], self.blocks), _level(self.cells["code"])

    def asks(self, frame: _Frame, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(block, asked block): the blocks whose cells may be opened from the blocks at."""
        code, boxes, level = self.cells["code"], frame.boxes(self.blocks[at]), self.level
        own_level = _level(self.blocks[at])
        top = np.flatnonzero(level == 2)
        t, c, out = np.repeat(np.arange(len(at)), len(top)), np.tile(top, len(at)), [(np.zeros(0, np.int64),) * 2]
        while len(t):
            around = (own_level[t] >= level[c]) & (self.blocks[at[t]] >> 2 * np.maximum(own_level[t] - level[c], 0) == code[c])
            near = around | ~frame.far_from_all(boxes, t, level[c], self.cells["x"][c], self.cells["y"][c])
            t, c = t[near], c[near]
            ends = ~self.inner[c]
            full = ends & ((level[c] < frame.deepest) | (self.cells["held"][c] <= frame.leaf))
            out.append((at[t[full]], code[c[full]]))
            t, c = t[~ends], c[~ends]
            first = np.searchsorted(code, code[c] * 4)
            own, c = _spread(first, np.searchsorted(code, code[c] * 4 + 4) - first)
            t = t[own]
        asking, asked = (np.concatenate(v) for v in zip(*out, strict=True))
        place = np.argsort(self.blocks)
        return asking, place[np.searchsorted(self.blocks[place], asked)]


def _tree(at: DataFrame, key: Column, total: int, deepest: int, block: int) -> _Tree:
    """Counted from the top: each pass counts the cells some levels below those that still hold more than a block."""
    level, open_, cells, blocks = 0, np.zeros(1, np.int64), [], []
    rows = at.withColumn("key", key)
    while len(open_):
        steps = int(math.log(COUNTED / len(open_), 4)) if COUNTED > len(open_) else 0
        below = min(deepest, level + max(2, min(steps, 2 + math.ceil(math.log(max(1.0, total / block), 4)))))
        cell = F.shiftright("key", 2 * (deepest - below))
        inside = rows if level == 0 else rows.join(small(at.sparkSession.createDataFrame([(int(k),) for k in open_], "up bigint")), F.shiftright("key", 2 * (deepest - level)) == F.col("up"), "left_semi")
        solid = F.greatest(F.col("mass"), F.lit(0.0))
        sums = inside.groupBy(cell.alias("cell")).agg(F.count("*").alias("n"), F.count_if(F.col("mass") > 0).alias("held"), F.sum(solid), F.sum(solid * F.col("x")), F.sum(solid * F.col("y"))).orderBy("cell").toArrow()
        own, *values = (sums.column(i).to_numpy() for i in range(6))
        for now in range(level + 1, below + 1):
            up, first = np.unique(own >> 2 * (below - now), return_index=True)
            n, held, mass, mx, my = (np.add.reduceat(v, first) for v in values)
            if now >= 2:
                made, some = np.zeros(len(up), CELL), held > 0
                made["code"], made["held"], made["mass"] = up + (np.int64(1) << 2 * now), held, mass
                made["x"], made["y"] = (np.divide(v, mass, out=np.zeros(len(up)), where=some) for v in (mx, my))
                cells.append(made[some])
            crowded = held > block if 2 <= now < deepest else np.full(len(up), now < 2)
            blocks.append(np.stack([up[~crowded] + (np.int64(1) << 2 * now), up[~crowded] << 2 * (deepest - now), n[~crowded]]))
            open_ = up[crowded]
            keep = np.isin(own >> 2 * (below - now), open_)
            own, values = own[keep], [v[keep] for v in values]
            if not len(open_):
                break
            total = int(held[crowded].max())
        level = below
    found = np.concatenate(blocks, axis=1)
    found = found[:, np.argsort(found[1])]
    cells = np.concatenate(cells) if cells else np.zeros(0, CELL)
    units = np.concatenate([[0], np.cumsum(np.maximum(1, -(-found[2] // block)))])
    return _Tree(cells[np.argsort(cells["code"])], found[0], units)


def _inner(code: int, key: np.ndarray, x: np.ndarray, y: np.ndarray, mass: np.ndarray, frame: _Frame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The cells of a block, from its own, over nodes in the order of key; each cell's first node and first quarter."""
    level = int(_level(np.array([code]))[0])
    at, made, first, below, total = np.arange(len(key)), [], [], [], 0
    while len(at):
        own = (key[at] >> 2 * (frame.deepest - level)) + (np.int64(1) << 2 * level)
        codes, start, held = np.unique(own, return_index=True, return_counts=True)
        cells = np.zeros(len(codes), CELL)
        m = np.add.reduceat(mass[at], start)
        cells["code"], cells["held"], cells["mass"] = codes, held, m
        cells["x"], cells["y"] = (np.add.reduceat(mass[at] * v[at], start) / m for v in (x, y))
        total += len(cells)
        made.append(cells)
        first.append(at[start])
        at = at[np.repeat((held > frame.leaf) & (level < frame.deepest), held)]
        level += 1
    cells = np.concatenate(made)
    below = np.searchsorted(cells["code"], cells["code"] * 4)
    return cells, np.concatenate(first), below


def _answers(code: int, nodes: pa.Table, asking: np.ndarray, tree: _Tree, frame: _Frame) -> Iterator[tuple[int, bytes, bytes]]:
    """(block, cells, nodes): what each of the asking blocks can meet inside a block."""
    key, x, y, mass = (nodes.column(c).to_numpy() for c in ("key", "x", "y", "mass"))
    order = np.lexsort((mass, y, x, key))
    key, x, y, mass = (v[order] for v in (key, x, y, mass))
    cells, first, below = _inner(code, key, x, y, mass, frame)
    level, boxes = _level(cells["code"]), frame.boxes(tree.blocks[asking])
    t, c, found = np.arange(len(asking)), np.zeros(len(asking), np.int64), []
    while len(t):
        near = ~frame.far_from_all(boxes, t, level[c], cells["x"][c], cells["y"][c])
        few = cells["held"][c] <= frame.leaf
        found.append((t, c, near & few))
        wide = near & ~few & (level[c] < frame.deepest)
        t, c = t[wide], c[wide]
        size = np.searchsorted(cells["code"], cells["code"][c] * 4 + 4) - below[c]
        own, c = _spread(below[c], size)
        t = t[own]
    t, c, listed = (np.concatenate(v) for v in zip(*found, strict=True))
    order = np.argsort(t, kind="stable")
    t, c, listed = t[order], c[order], listed[order]
    ends = np.searchsorted(t, np.arange(len(asking) + 1))
    for i, (a, b) in enumerate(zip(ends[:-1], ends[1:], strict=True)):
        sent = cells[c[a:b]]
        sent["listed"] = np.where(listed[a:b], sent["held"], 0)
        _, at = _spread(first[c[a:b]], sent["listed"])
        points = np.empty(len(at), POINT)
        points["x"], points["y"], points["mass"] = x[at], y[at], mass[at]
        yield int(asking[i]), sent.tobytes(), points.tobytes()


def _forces(key: np.ndarray, x: np.ndarray, y: np.ndarray, mass: np.ndarray, cells: np.ndarray, points: np.ndarray, top: np.ndarray, frame: _Frame) -> tuple[np.ndarray, np.ndarray]:
    """The pushes on a block's nodes, for a mass of 1: each goes down the cells sent and those above them."""
    shown = np.cumsum(cells["listed"]) - cells["listed"]
    every, shown = np.concatenate([cells, top]), np.concatenate([shown, np.zeros(len(top), np.int64)])
    code, at = np.unique(every["code"], return_index=True)  # a block's own cell as sent, before the one above
    every, shown, level = every[at], shown[at], _level(code)
    first, last = np.searchsorted(code, code * 4), np.searchsorted(code, code * 4 + 4)
    held, listed, ox, oy, om = (np.ascontiguousarray(every[c]) for c in ("held", "listed", "x", "y", "mass"))
    width, up, start = frame.width(level), 2 * (frame.deepest - level), np.flatnonzero(level == 2)
    crowded, last_level = held > frame.leaf, level == frame.deepest
    px, py, pm = (np.ascontiguousarray(points[c]) for c in ("x", "y", "mass"))
    own_code = key + (np.int64(1) << 2 * frame.deepest)
    n = len(x)
    fx, fy = np.zeros(n), np.zeros(n)
    some = max(1, min(1024, MET // max(1, len(code) + len(points))))
    for lo in range(0, n, some):
        hi = min(n, lo + some)

        def push(i, dx, dy, m, d2, lo=lo, hi=hi):
            f = np.where(d2 > TINY, m / np.maximum(d2, TINY), 0.0)
            fx[lo:hi] += np.bincount(i - lo, f * dx, hi - lo)
            fy[lo:hi] += np.bincount(i - lo, f * dy, hi - lo)

        i, c = np.repeat(np.arange(lo, hi), len(start)), np.tile(start, hi - lo)
        while len(i):
            dx, dy = x[i] - ox[c], y[i] - oy[c]
            own = own_code[i] >> up[c] == code[c]
            far = (width[c] < frame.theta * np.hypot(dx, dy)) & ~own
            k = np.flatnonzero(far)
            push(i[k], dx[k], dy[k], om[c[k]], dx[k] ** 2 + dy[k] ** 2)
            k = np.flatnonzero(~far)
            i, c, own = i[k], c[k], own[k]
            wide = crowded[c]
            stuck = wide & last_level[c]
            if stuck.any():  # as a point, without the node itself
                a, b, itself = i[stuck], c[stuck], np.where(own[stuck], np.maximum(mass[i[stuck]], 0), 0.0)
                rest = om[b] - itself
                ok = rest > TINY
                a, b, itself, rest = a[ok], b[ok], itself[ok], rest[ok]
                dx, dy = x[a] - (ox[b] * om[b] - x[a] * itself) / rest, y[a] - (oy[b] * om[b] - y[a] * itself) / rest
                push(a, dx, dy, rest, dx**2 + dy**2)
            a, b = i[~wide], c[~wide]
            if (listed[b] != held[b]).any():
                raise AssertionError("a cell is met that was not sent whole")
            own, p = _spread(shown[b], listed[b])
            a = a[own]
            dx, dy = x[a] - px[p], y[a] - py[p]
            push(a, dx, dy, pm[p], dx**2 + dy**2)
            wide &= ~stuck
            i, c = i[wide], c[wide]
            size = last[c] - first[c]
            if not size.all():
                raise AssertionError("a cell is opened that was not sent")
            own, c = _spread(first[c], size)
            i = i[own]
    return fx, fy


def repulsion_opened(layout: DataFrame, scale: float = 80.0, theta: float = 0.5, leaf: int = LEAF, deepest: int | None = None, block: int = BLOCK) -> DataFrame:
    """(node, fx, fy): every node descends a tree of cells and opens those that are wide for their distance.

    A cell narrower than theta times its centre's distance acts as one point; a cell of at most leaf nodes acts node by
    node; any other is opened into its quarters, so crowded places are divided further than empty ones. A crowded cell on
    the deepest level acts as one point without the node itself; down to that level theta 0 is exact, by all pairs of
    cells. With a positive theta, work for each node is bounded by theta and the depth, wherever the nodes lie. The result
    doesn't depend on block, the nodes of a block about; with theta 0 every block is sent all nodes.
    """
    spark = layout.sparkSession
    held = store(layout.select("node", "x", "y", F.coalesce(F.col("mass").cast("double"), F.lit(0.0)).alias("mass")), "places")
    x0, x1, y0, y1, n = held.agg(F.min("x"), F.max("x"), F.min("y"), F.max("y"), F.count("*")).first()
    if not n:
        return layout.select("node", "fx", "fy")
    deepest = deepest or min(30, pyramid_levels(n) + 16)
    if not 2 <= deepest <= 31:
        raise ValueError("the deepest level is one of 2 to 31")
    block = max(block, leaf, -(-n // MOST_BLOCKS))
    side = max(x1 - x0, y1 - y0, TINY) * (1 + 1e-9)
    frame = _Frame(x0, y0, side, max(map(abs, (x0, x1, y0, y1))), deepest, leaf, theta)
    place = lambda c, low: _apart(F.least(F.floor((F.col(c) - low) / side * (1 << deepest)), F.lit((1 << deepest) - 1)).cast("bigint"))
    key = F.shiftleft(place("x", x0), 1).bitwiseOR(place("y", y0))
    tree = _tree(held, key, n, deepest, block)
    sent = spark.sparkContext.broadcast(tree)
    first_keys = (tree.blocks - (np.int64(1) << 2 * _level(tree.blocks))) << 2 * (deepest - _level(tree.blocks))
    starts = spark.sparkContext.broadcast(first_keys)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        units = sent.value.units
        for batch in batches:
            own = np.searchsorted(starts.value, batch.column(4).to_numpy(), "right") - 1
            part = (batch.column(5).to_numpy().view(np.uint64) % (units[own + 1] - units[own]).astype(np.uint64)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(own), pa.array(units[own] + part)], names=["node", "x", "y", "mass", "key", "block", "unit"])

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.column(0).to_numpy()
            for lo in range(0, len(at), 256):
                asking, asked = sent.value.asks(frame, at[lo : lo + 256])
                yield pa.RecordBatch.from_arrays([pa.array(asked), pa.array(asking // ANSWERED), pa.array(asking)], names=["block", "part", "asking"])

    def answer(own: tuple[pa.Scalar, ...], nodes: pa.Table, asking: pa.Table) -> pa.Table:
        out: list[tuple[int, bytes, bytes]] = []
        tree = sent.value
        if nodes.num_rows:
            for t, cells, points in _answers(int(tree.blocks[own[0].as_py()]), nodes, np.sort(asking.column("asking").to_numpy()), tree, frame):
                out += [(unit, cells, points) for unit in range(tree.units[t], tree.units[t + 1])]
        return pa.table([pa.array([r[i] for r in out], kind) for i, kind in enumerate((pa.int64(), pa.binary(), pa.binary()))], names=["unit", "cells", "points"])

    def force(nodes: pa.Table, parts: pa.Table) -> pa.Table:
        key, x, y, mass = (nodes.column(c).to_numpy() for c in ("key", "x", "y", "mass"))
        cells, points = (np.frombuffer(b"".join(parts.column(c).to_pylist()), kind) for c, kind in (("cells", CELL), ("points", POINT)))
        order = np.argsort(key, kind="stable")  # nodes of a place go the same way
        fx, fy = np.empty(len(x)), np.empty(len(x))
        fx[order], fy[order] = _forces(key[order], x[order], y[order], mass[order], cells, points, sent.value.cells, frame)
        return pa.table([nodes.column("node"), pa.array(scale * mass * fx), pa.array(scale * mass * fy)], names=["node", "fx", "fy"])

    kind = held.schema["node"].dataType.simpleString()
    dealt = held.select("node", "x", "y", "mass", key.alias("key"), F.xxhash64("node").alias("hash")).mapInArrow(deal, f"node {kind}, x double, y double, mass double, key bigint, block bigint, unit bigint")
    tasks = lambda most: max(1, min(most, max(4 * spark.sparkContext.defaultParallelism, most // 16)))
    blocks, units = len(tree.blocks), int(tree.units[-1])
    asks = store(spark.range(0, blocks, 1, tasks(-(-blocks // 64))).mapInArrow(ask, "block bigint, part bigint, asking bigint"), "asks")
    asked = asks.select("block", "part").distinct().toDF("block", "piece")
    full = dealt.where("mass > 0").select("block", "x", "y", "mass", "key").join(small(asked), "block")
    full, asking = full.repartition(tasks(blocks), "block", "piece").groupBy("block", "piece"), asks.repartition(tasks(blocks), "block", "part").groupBy("block", "part")
    answers = full.cogroup(asking).applyInArrow(answer, "unit bigint, cells binary, points binary")
    parts = answers.repartition(tasks(units), "unit").groupBy("unit")
    made = dealt.select("unit", "node", "x", "y", "mass", "key").repartition(tasks(units), "unit").groupBy("unit").cogroup(parts).applyInArrow(force, f"node {kind}, fx double, fy double")
    made = store(made, "pushes")
    for old in (held, asks):
        discard(old)
    sent.destroy()
    starts.destroy()
    return made
