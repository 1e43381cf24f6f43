"""Edge lists: canonical form, arrival order, degrees and the base cap.

An edge list has the columns seq, src, dst, w. seq orders the stream: a dense number, dealt by ranges of the order so that
no task sees all rows, or a composite key (hash, src, dst), which needs no pass of its own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsummary.operators.order import numbered

#: Fixed values of the arrival hash; the same expression stands in the SQL forms.
ARRIVAL_A, ARRIVAL_B, ARRIVAL_MOD = 7919, 104729, 1000003


def canonical(df: DataFrame, src: str = "src", dst: str = "dst", weight: str | None = None, seq: str | None = None, directed: bool = False, loops: str = "drop", repeats: str = "distinct") -> DataFrame:
    """Edges without null ends. loops: 'drop', 'keep'. repeats: 'distinct' (w 1), 'sum' (weights add), 'keep'."""
    s, d = F.col(src).cast("bigint"), F.col(dst).cast("bigint")
    a, b = (s, d) if directed else (F.least(s, d), F.greatest(s, d))
    w = F.col(weight) if weight else F.lit(1).cast("bigint")
    kept = df.where(s.isNotNull() & d.isNotNull())
    if loops == "drop":
        kept = kept.where(s != d)
    columns = [a.alias("src"), b.alias("dst"), w.alias("w")] + ([F.col(seq).alias("seq")] if seq else [])
    out = kept.select(*columns)
    if repeats == "keep":
        return out
    first = [F.min("seq").alias("seq")] if seq else []
    if repeats == "distinct":
        out = out.groupBy("src", "dst").agg(F.lit(1).cast("bigint").alias("w"), *first) if seq else out.select("src", "dst").distinct().withColumn("w", F.lit(1).cast("bigint"))
        return out
    return out.groupBy("src", "dst").agg(F.sum("w").alias("w"), *first)


def arrival_hash(src: str = "src", dst: str = "dst", seed: int = 0) -> Column:
    """Looks shuffled, equal in every engine; ends are reduced first, so no product overflows."""
    a, b = (F.pmod(F.col(c), F.lit(ARRIVAL_MOD)) for c in (src, dst))
    return F.pmod(a * F.lit(ARRIVAL_A) + b * F.lit(ARRIVAL_B) + F.lit(seed), F.lit(ARRIVAL_MOD))


def with_arrival(edges: DataFrame, order: str = "hash", seed: int = 0, dense: bool = True, by: str | None = None) -> DataFrame:
    """Add seq. order: 'hash' (seeded shuffle), 'time' or 'given' (the column named by). dense=False keeps a composite key, which needs no pass
    of its own; a dense number comes from ranges of the order, in parallel."""
    keys = [arrival_hash(seed=seed), F.col("src"), F.col("dst")] if order == "hash" else [F.col(by), F.col("src"), F.col("dst")]
    if dense:
        return numbered(edges, keys, "seq")
    return edges.withColumn("seq", F.struct(*[k.alias(f"k{i}") for i, k in enumerate(keys)]))


def half_edges(edges: DataFrame) -> DataFrame:
    """(seq, node, side): two rows for each edge; side 0 is the source."""
    ends = F.array(F.struct(F.col("src").alias("node"), F.lit(0).alias("side")), F.struct(F.col("dst").alias("node"), F.lit(1).alias("side")))
    return edges.select("seq", F.explode(ends).alias("end")).select("seq", "end.node", "end.side")


def degrees(edges: DataFrame, weighted: bool = False) -> DataFrame:
    """(node, deg); a loop counts twice."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("node"), *(["w"] if weighted else []))
    return ends.groupBy("node").agg((F.sum("w") if weighted else F.count("*")).alias("deg"))


def directed_degrees(edges: DataFrame) -> DataFrame:
    """(node, deg_out, deg_in)."""
    ends = F.array(F.struct(F.col("src").alias("node"), F.lit(1).alias("o")), F.struct(F.col("dst").alias("node"), F.lit(0).alias("o")))
    rows = edges.select(F.explode(ends).alias("e")).select("e.*")
    return rows.groupBy("node").agg(F.sum("o").cast("bigint").alias("deg_out"), F.sum(1 - F.col("o")).cast("bigint").alias("deg_in"))


def degree_histogram(degrees_: DataFrame) -> DataFrame:
    return degrees_.groupBy("deg").agg(F.count("*").alias("n"))


def cap_frame(edges: DataFrame, rule: str = "mode", scale: int = 1) -> DataFrame:
    """One row (cap): the most common degree (of equally common ones the smallest) or the average, times scale."""
    if rule == "mode":
        top = degree_histogram(degrees(edges)).orderBy(F.desc("n"), "deg").limit(1)
        return top.select((F.col("deg") * scale).alias("cap"))
    d = degrees(edges)
    return d.agg(F.floor(F.sum("deg") / F.greatest(F.count("*"), F.lit(1))).alias("c")).select((F.col("c") * scale).alias("cap"))


def base_cap(edges: DataFrame, rule: str | int = "mode", scale: int = 1) -> int:
    """The cap as a number on the driver; 1 for an empty edge list."""
    if not isinstance(rule, str):
        return int(rule) * scale
    row = cap_frame(edges, rule, scale).first()
    return max(1, int(row[0])) if row and row[0] is not None else 1


def nodes(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct()


def id_dictionary(df: DataFrame, column: str) -> DataFrame:
    """(value, id) for the distinct strings of a column: a 64-bit hash, checked to be free of collisions."""
    found = df.select(F.col(column).alias("value")).where("value is not null").distinct().withColumn("id", F.xxhash64("value"))
    clash = found.groupBy("id").agg(F.count("*").alias("n")).where("n > 1").limit(1).count()
    if clash:
        raise ValueError("two strings share a hash; give numeric ids instead")
    return found


def shift(side: str, offset: int) -> Column:
    """Ids of a bipartite graph's second side, moved by a constant."""
    return F.col(side) + F.lit(offset)
