"""Global order without a window over everything: rows are dealt to ranges of the order, ranges are summed, and each row
adds what lies before its range. Only one row for each range is ordered in one task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphsummary.sources.storage import store

RANGE = "__range"


def ranged(df: DataFrame, keys: list[Column]) -> DataFrame:
    """df, stored, with the number of the range of the order in which each row lies. Ties in all keys share a range."""
    named = df.withColumns({f"__k{i}": k for i, k in enumerate(keys)})
    names = [f"__k{i}" for i in range(len(keys))]
    return store(named.repartitionByRange(*names).withColumn(RANGE, F.spark_partition_id()), "ranged")


def within(keys: list[Column]):
    """The order inside a range; keys are the ones given to ranged."""
    return Window.partitionBy(RANGE).orderBy(*[f"__k{i}" for i in range(len(keys))])


def plain(df: DataFrame) -> DataFrame:
    return df.drop(RANGE, *[c for c in df.columns if c.startswith("__k")])


def running(df: DataFrame, keys: list[Column], **sums: Column) -> DataFrame:
    """df with the running sum of each given expression, this row included; ties take the order of their rows."""
    rows = ranged(df.withColumns({f"__v_{n}": v for n, v in sums.items()}), keys)
    per = rows.groupBy(RANGE).agg(*[F.sum(f"__v_{n}").alias(n) for n in sums])
    before = Window.orderBy(RANGE).rowsBetween(Window.unboundedPreceding, -1)  # one row for each range
    start = per.select(RANGE, *[F.coalesce(F.sum(n).over(before), F.lit(0)).alias(f"__s_{n}") for n in sums])
    so_far = within(keys).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    made = rows.withColumns({n: F.sum(f"__v_{n}").over(so_far) for n in sums}).join(F.broadcast(start), RANGE)
    made = made.withColumns({n: F.col(n) + F.col(f"__s_{n}") for n in sums})
    return plain(made.drop(*[f"__{x}_{n}" for n in sums for x in "vs"]))


def numbered(df: DataFrame, keys: list[Column], name: str) -> DataFrame:
    """df with its row number in the order, from 1."""
    return running(df, keys, **{name: F.lit(1).cast("bigint")})


def with_next(df: DataFrame, keys: list[Column], column: str, name: str) -> DataFrame:
    """df with the column's value of the next row in the order, null for the last."""
    rows = ranged(df, keys)
    first = rows.groupBy(RANGE).agg(F.min_by(column, F.struct(*[f"__k{i}" for i in range(len(keys))])).alias("__first"))
    after = first.select(RANGE, F.lead("__first").over(Window.orderBy(RANGE)).alias("__after"))  # one row for each range
    made = rows.withColumns({name: F.lead(column).over(within(keys)), "__last": F.lead(F.lit(True)).over(within(keys)).isNull()}).join(F.broadcast(after), RANGE)
    return plain(made.withColumn(name, F.when(F.col("__last"), F.col("__after")).otherwise(F.col(name))).drop("__last", "__after"))


def tile(number: Column, total: Column, tiles: int) -> Column:
    """The tile of a row of this number among total rows, as ntile deals them: the first tiles hold one row more."""
    low, more = F.floor(total / tiles), total % tiles
    wide = more * (low + 1)
    return F.when(number <= wide, F.floor((number - 1) / (low + 1)) + 1).otherwise(more + F.floor((number - wide - 1) / F.greatest(low, F.lit(1))) + 1)
