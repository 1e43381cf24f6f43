"""Radii, colour classes, drawings as rows, SVG text and tiles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.operators.order import numbered, running, tile
from graphsummary.sources.storage import store

# fixed values: colour names from small to large communities, with the hex values of a qualitative scheme
PALETTE = (
    ("brown", "#b15928"), ("light purple", "#cab2d6"), ("purple", "#6a3d9a"), ("light orange", "#fdbf6f"), ("orange", "#ff7f00"), ("light red", "#fb9a99"),
    ("red", "#e31a1c"), ("light green", "#b2df8a"), ("green", "#33a02c"), ("light blue", "#a6cee3"), ("blue", "#1f78b4"),
)
BANDS = len(PALETTE) - 1
GREY = "#999999"


def palette(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(i, n, h) for i, (n, h) in enumerate(PALETTE)], "band int, name string, hex string")


def radius(supernodes: DataFrame, scale: float = 1.0, size: str = "size") -> DataFrame:
    """Areas in proportion to sizes."""
    return supernodes.withColumn("radius", F.lit(float(scale)) * F.sqrt(F.col(size).cast("double")))


def qualitative(sizes: DataFrame, tail_share: float = 0.5, bands: str = "equal_count", key: str = "community", size: str = "size") -> DataFrame:
    """(key, size, band, name, hex). Band 0 is the tail: the smallest communities as long as their sizes sum to at most
    tail_share of all (the one that crosses it is not in). The rest are cut into ten bands from small to large."""
    run = store(running(sizes.select(key, size), [F.col(size), F.col(key)], run=F.col(size).cast("bigint"), number=F.lit(1).cast("bigint")), "run")
    total = run.agg(F.max("run")).first()[0] or 0
    run = run.withColumn("tail", F.col("run") <= tail_share * total)
    in_tail = run.where("tail").agg(F.count("*").alias("n"), F.coalesce(F.max("run"), F.lit(0)).alias("size")).first()
    rest = run.where("not tail").agg(F.count("*").alias("n"), F.min(F.log2(F.col(size).cast("double"))).alias("low"), F.max(F.log2(F.col(size).cast("double"))).alias("high")).first()
    if bands == "equal_count":
        band = tile(F.col("number") - in_tail["n"], F.lit(rest["n"]), BANDS)
    elif bands == "equal_weight":  # the tail comes first in the same order
        band = F.least(F.floor(F.lit(BANDS) * (F.col("run") - in_tail["size"] - F.col(size)) / F.lit(max(total - in_tail["size"], 1))) + 1, F.lit(BANDS))
    elif rest["n"] and rest["high"] > rest["low"]:
        band = F.least(F.floor(F.lit(BANDS) * (F.log2(F.col(size).cast("double")) - rest["low"]) / (rest["high"] - rest["low"])) + 1, F.lit(BANDS))
    else:
        band = F.lit(1)
    made = run.withColumn("band", F.when(F.col("tail"), F.lit(0)).otherwise(band).cast("int"))
    return made.join(F.broadcast(palette(sizes.sparkSession)), "band").select(key, size, "band", "name", "hex")


def sequential(sizes: DataFrame, steps: int = 9, key: str = "community", size: str = "size") -> DataFrame:
    """(key, size, shade, hex): shade 1 is the lightest, the largest communities get the darkest."""
    rows = store(numbered(sizes.select(key, size), [F.col(size), F.col(key)], "number"), "numbered")
    shade = tile(F.col("number"), F.lit(rows.count()), steps).cast("int")
    level = (F.lit(230) - F.floor((F.col("shade") - 1) * 210 / max(1, steps - 1))).cast("int")
    hex_ = F.concat(F.lit("#"), *[F.lpad(F.lower(F.hex(level)), 2, "0")] * 2, F.lit("ff"))
    return rows.select(key, size, shade.alias("shade")).withColumn("hex", hex_)


def stylise(layout: DataFrame, assignment: DataFrame, colours: DataFrame) -> DataFrame:
    """(node, x, y, community, band, hex): every node of a whole layout in the colour of its community."""
    return layout.select("node", "x", "y").join(assignment, "node", "left").join(colours.select("community", "band", "hex"), "community", "left").select("node", "x", "y", "community", "band", F.coalesce("hex", F.lit(GREY)).alias("hex"))


def plain(layout: DataFrame) -> DataFrame:
    """(node, x, y, hex): the grey layout."""
    return layout.select("node", "x", "y", F.lit(GREY).alias("hex"))


def segments(edges: DataFrame, layout: DataFrame, colour: Column | None = None) -> DataFrame:
    """(x1, y1, x2, y2, w, color)."""
    a, b = layout.select("node", "x", "y").toDF("src", "x1", "y1"), layout.select("node", "x", "y").toDF("dst", "x2", "y2")
    return edges.join(a, "src").join(b, "dst").select("x1", "y1", "x2", "y2", "w", (colour if colour is not None else F.lit(GREY)).alias("color"))


def svg(discs: DataFrame, lines: DataFrame | None = None, radius_column: str | None = "radius") -> DataFrame:
    """(ord, line): the rows of an SVG document, edges below nodes; write them sorted as text."""
    size = discs.agg(F.min("x").alias("x0"), F.min("y").alias("y0"), F.max("x").alias("x1"), F.max("y").alias("y1"), F.count("*").alias("n"))
    head = size.select(F.lit(0).alias("ord"), F.format_string('<svg xmlns="http://www.w3.org/2000/svg" viewBox="%.3f %.3f %.3f %.3f">', *[F.coalesce(c, F.lit(0.0)) for c in (F.col("x0") - 5, F.col("y0") - 5, F.col("x1") - F.col("x0") + 10, F.col("y1") - F.col("y0") + 10)]).alias("line"))
    r = F.col(radius_column) if radius_column else F.lit(1.0)
    body = discs.select(F.lit(2).alias("ord"), F.format_string('<circle cx="%.3f" cy="%.3f" r="%.3f" fill="%s"/>', F.col("x"), F.col("y"), r, F.col("hex")).alias("line"))
    out = head.unionByName(body)
    if lines is not None:
        out = out.unionByName(lines.select(F.lit(1).alias("ord"), F.format_string('<line x1="%.3f" y1="%.3f" x2="%.3f" y2="%.3f" stroke="%s"/>', "x1", "y1", "x2", "y2", "color").alias("line")))
    return out.unionByName(size.select(F.lit(3).alias("ord"), F.lit("</svg>").alias("line")))


def tiles(drawing: DataFrame, zoom: int) -> DataFrame:
    """(zoom, tx, ty, n, hex): nodes on a square grid of 2^zoom tiles a side, with the most common colour of each."""
    box = drawing.agg(F.min("x").alias("x0"), F.max("x").alias("x1"), F.min("y").alias("y0"), F.max("y").alias("y1"))
    side = box.select(F.greatest(F.col("x1") - F.col("x0"), F.col("y1") - F.col("y0"), F.lit(1e-9)).alias("s")).scalar()
    n = 1 << zoom
    at = lambda c, low: F.least(F.floor((F.col(c) - box.select(low).scalar()) / side * n), F.lit(n - 1)).cast("bigint")
    return drawing.groupBy(F.lit(zoom).alias("zoom"), at("x", "x0").alias("tx"), at("y", "y0").alias("ty")).agg(F.count("*").alias("n"), F.mode("hex", True).alias("hex"))


def morton(cx: Column, cy: Column, bits: int = 16) -> Column:
    """Interleaved bits of two cell numbers."""
    one = F.lit(1).cast("bigint")
    out = F.lit(0).cast("bigint")
    for i in range(bits):
        for v, at in ((cx, 2 * i), (cy, 2 * i + 1)):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(v.cast("bigint"), i).bitwiseAND(one), at))
    return out
