"""Functions for SQL and DataFrames beside the built-in ones: Arrow-batched scalars, aggregates and a table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def dot(x: pd.Series, y: pd.Series) -> pd.Series:
    """Scalar product of two arrays of one length; null where one is null or lengths differ."""
    pairs = zip(x, y, strict=True)
    return pd.Series([float(np.dot(a, b)) if a is not None and b is not None and len(a) == len(b) else None for a, b in pairs], dtype="float64")


@F.pandas_udf(T.DoubleType())
def frobenius(v: pd.Series) -> float:
    """Root of the sum of squares of a column; 0 without rows."""
    x = v.dropna().to_numpy(np.float64)
    return float(np.sqrt(np.dot(x, x)))


@F.udtf(returnType=T.StructType([T.StructField("i", T.LongType()), T.StructField("j", T.LongType()), T.StructField("v", T.DoubleType())]))
class RowCells:
    """row_cells(i, row): a matrix row, given as an array, as its cells that aren't zero."""

    def eval(self, i: int, row: list):
        for j, v in enumerate(row or []):
            if v:
                yield i, j, float(v)


def register(spark: SparkSession) -> None:
    """dot, frobenius and row_cells for SQL."""
    spark.udf.register("dot", dot)
    spark.udf.register("frobenius", frobenius)
    spark.udtf.register("row_cells", RowCells)
