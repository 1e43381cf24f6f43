"""SQL functions, an aggregate and a table function for use in SQL text."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from graphsummary.operators.sketch import PRIME, factors

CELL = "create or replace temporary function affine_cell(x bigint, a bigint, b bigint, c bigint) returns bigint return pmod(pmod(a * pmod(x, {p}) + b, {p}), c)"


def cms_agg(keys: pd.Series, weights: pd.Series) -> np.ndarray:
    """A count-min matrix of depth 4 and width 257 as one flat array: an aggregate over groups that fit a task."""
    m = np.zeros((4, 257), np.int64)
    x = keys.to_numpy(np.int64) % PRIME
    for i, (a, b) in enumerate(factors(4)):
        np.add.at(m[i], (a * x + b) % PRIME % 257, weights.to_numpy(np.int64))
    return m.ravel()


class SketchCells:
    def eval(self, key: int, depth: int, width: int):
        if key is not None:
            for i, (a, b) in enumerate(factors(depth)):
                yield i + 1, (a * (key % PRIME) + b) % PRIME % width


def register(spark: SparkSession) -> None:
    """affine_cell stays in generated code; cms_agg and sketch_cells run in Python workers."""
    spark.sql(CELL.format(p=PRIME))
    spark.udf.register("cms_agg", pandas_udf(cms_agg, "array<bigint>"))
    spark.udtf.register("sketch_cells", udtf(SketchCells, returnType="row_no int, cell bigint"))


def builtin_sketch(df, key: str, eps: float = 0.01, confidence: float = 0.95, seed: int = 7):
    """The built-in count-min aggregate, as a binary for export."""
    return df.agg(F.count_min_sketch(F.col(key), F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))
