"""Count-min sketches in long format (row_no, cell, cnt): built by partial aggregation, merged by adding up."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsummary.sources.storage import BROADCAST_BYTES

PRIME = (1 << 31) - 1
#: The factors of the first four rows, as in the fixtures. Further rows and other seeds are drawn.
FACTORS = ((1103515245, 12345), (1664525013, 1013904223), (1597334677, 715136305), (950706376, 374761393))


def factors(depth: int, seed: int | None = None) -> list[tuple[int, int]]:
    """(a, b) of each row's affine hash; no a near 0 or the prime."""
    if seed is None and depth <= len(FACTORS):
        return list(FACTORS[:depth])
    rng = np.random.default_rng(seed or 0)
    drawn = [(int(rng.integers(PRIME // 8, PRIME - PRIME // 8)), int(rng.integers(0, PRIME))) for _ in range(depth)]
    return drawn if seed is not None else [*FACTORS, *drawn][:depth]


def cell(key: Column, a: int, b: int, width: int) -> Column:
    """((a * (key mod p) + b) mod p) mod width; the key is reduced first, so nothing overflows."""
    x = F.pmod(key, F.lit(PRIME).cast("bigint"))
    return F.pmod(F.pmod(x * F.lit(a).cast("bigint") + F.lit(b).cast("bigint"), F.lit(PRIME).cast("bigint")), F.lit(width).cast("bigint"))


def cells(key: Column, depth: int, width: int, seed: int | None = None) -> Column:
    return F.array(*[F.struct(F.lit(i + 1).alias("row_no"), cell(key, a, b, width).alias("cell")) for i, (a, b) in enumerate(factors(depth, seed))])


def dims(m: int, width_fraction: float = 1e-3, depth: int = 4, min_width: int = 16, most: int = 1 << 24) -> tuple[int, int]:
    """(depth, width): a share of the number of edges, odd, within bounds."""
    return depth, min(most, max(min_width, int(m * width_fraction))) | 1


def dims_for(eps: float, confidence: float) -> tuple[int, int]:
    """(depth, width) for errors within eps of the total with the given confidence."""
    return max(1, math.ceil(-math.log2(1 - confidence))), math.ceil(2 / eps) | 1


def bound(total: float, width: int, depth: int) -> dict:
    """Expected share that collides with a key, the error called large, and the bound on its chance."""
    return {"collision_share": total / width, "large_error": 2 * total / width, "chance": 2.0**-depth}


def build(df: DataFrame, key: str, weight: str | None = None, depth: int = 4, width: int = 16, seed: int | None = None) -> DataFrame:
    """(row_no, cell, cnt). Null keys count nothing."""
    w = F.col(weight) if weight else F.lit(1).cast("bigint")
    rows = df.where(F.col(key).isNotNull()).select(F.explode(cells(F.col(key), depth, width, seed)).alias("c"), w.alias("w"))
    return rows.groupBy("c.row_no", "c.cell").agg(F.sum("w").alias("cnt"))


def estimate(sketch: DataFrame, keys: DataFrame, key: str, depth: int = 4, width: int = 16, seed: int | None = None) -> DataFrame:
    """(key, est): the least of the key's cells. The sketch is broadcast if its cells have a bound that allows it."""
    held = F.broadcast(sketch) if depth * width * 40 <= BROADCAST_BYTES else sketch
    rows = keys.select(F.col(key), F.explode(cells(F.col(key), depth, width, seed)).alias("c")).select(key, "c.*")
    return rows.join(held, ["row_no", "cell"], "left").groupBy(key).agg(F.min(F.coalesce("cnt", F.lit(0))).alias("est"))


def column_min(sketch: DataFrame, depth: int) -> DataFrame:
    """(cell, least): the smallest entry of each column over all rows; an absent entry is 0."""
    per = sketch.groupBy("cell").agg(F.min("cnt").alias("least"), F.count("*").alias("rows"))
    return per.select("cell", F.when(F.col("rows") < depth, F.lit(0).cast("bigint")).otherwise(F.col("least")).alias("least"))


def merge(*sketches: DataFrame) -> DataFrame:
    out = sketches[0]
    for s in sketches[1:]:
        out = out.unionByName(s)
    return out.groupBy("row_no", "cell").agg(F.sum("cnt").alias("cnt"))


def sketch_loop(df: DataFrame, key: str, weight: str, depth: int = 4, width: int = 16, seed: int | None = None) -> DataFrame:
    """The same matrix, filled by one task key by key: the sequential baseline."""
    import pandas as pd

    rows = factors(depth, seed)

    def run(parts):
        m = np.zeros((depth, width), np.int64)
        for part in parts:
            for x, w in zip(part["k"].tolist(), part["w"].tolist(), strict=True):
                for i, (a, b) in enumerate(rows):
                    m[i, (a * (x % PRIME) + b) % PRIME % width] += w
        r, c = np.nonzero(m)
        yield pd.DataFrame({"row_no": (r + 1).astype("int32"), "cell": c, "cnt": m[r, c]})

    return df.select(F.col(key).alias("k"), F.col(weight).alias("w")).repartition(1).mapInPandas(run, "row_no int, cell bigint, cnt bigint")
