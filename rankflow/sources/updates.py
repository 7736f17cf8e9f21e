"""Changes of a matrix as factors (L, R) in COO form, batches of row changes, and a deterministic Zipf stream of rows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.coo import SCHEMA, Coo

UPDATE_SCHEMA = "seq long, i long, j long, v double"


def _thin(spark: SparkSession, cells: list[tuple[int, int, float]], rows: int, cols: int) -> Coo:
    return Coo(spark.createDataFrame(cells, SCHEMA), rows, cols, len(cells))


def cell(spark: SparkSession, i: int, j: int, d: float, rows: int, cols: int) -> tuple[Coo, Coo]:
    return _thin(spark, [(i, 0, 1.0)], rows, 1), _thin(spark, [(j, 0, d)], cols, 1)


def row(spark: SparkSession, i: int, change: dict[int, float], rows: int, cols: int) -> tuple[Coo, Coo]:
    return _thin(spark, [(i, 0, 1.0)], rows, 1), _thin(spark, [(j, 0, v) for j, v in change.items()], cols, 1)


def col(spark: SparkSession, j: int, change: dict[int, float], rows: int, cols: int) -> tuple[Coo, Coo]:
    return _thin(spark, [(i, 0, v) for i, v in change.items()], rows, 1), _thin(spark, [(j, 0, 1.0)], cols, 1)


def every_row(spark: SparkSession, change: dict[int, float], rows: int, cols: int) -> tuple[Coo, Coo]:
    """The same vector is added to all rows."""
    ones = spark.range(rows).select(F.col("id").alias("i"), F.lit(0).cast("long").alias("j"), F.lit(1.0).alias("v"))
    return Coo(ones, rows, 1), _thin(spark, [(j, 0, v) for j, v in change.items()], cols, 1)


def every_col(spark: SparkSession, change: dict[int, float], rows: int, cols: int) -> tuple[Coo, Coo]:
    right, left = every_row(spark, change, cols, rows)
    return left, right


def rank_k(parts: list[tuple[Coo, Coo]]) -> tuple[Coo, Coo]:
    from ..operators.coo import hstack

    return hstack([a for a, _ in parts]), hstack([b for _, b in parts])


def range_lookup(points: DataFrame, x: str, upto: np.ndarray, name: str) -> DataFrame:
    """points with ``name``: the first k with x <= upto[k] (rising sums, the last one at least any x).

    A range join by buckets: an interval between two sums is entered under every bucket of x that it touches, a point under its
    own, and the two meet by equality. Intervals are at most as many as sums and buckets together."""
    buckets = max(1, len(upto))
    low = np.concatenate(([-np.inf], upto[:-1]))
    some = np.flatnonzero(low < upto)  # sums that don't rise hold no point
    at = lambda v: np.clip(np.floor(v * buckets), 0, buckets - 1).astype(np.int64)
    spark = points.sparkSession
    first, last = at(np.maximum(low[some], 0.0)), at(upto[some])
    spans = spark.createDataFrame(pa.table({"_k": some, "_lo": low[some], "_hi": upto[some], "_a": first, "_b": last}))
    spans = spans.select("_k", "_lo", "_hi", F.explode(F.sequence("_a", "_b")).alias("_bucket"))
    own = F.least(F.greatest(F.floor(F.col(x) * buckets), F.lit(0)), F.lit(buckets - 1))
    met = points.withColumn("_bucket", own).join(spans, "_bucket").filter((F.col("_lo") < F.col(x)) & (F.col(x) <= F.col("_hi")))
    return met.select(*points.columns, F.col("_k").alias(name))


def zipf_rows(df: DataFrame, unit: str, n: int, factor: float, name: str = "i") -> DataFrame:
    """df with a row 0 to n-1 from its number in (0, 1): inverse of the Zipf distribution over n ranks."""
    weight = 1.0 / np.arange(1, n + 1) ** factor
    upto = np.cumsum(weight) / weight.sum()
    upto[-1] = max(1.0, upto[-1])
    return range_lookup(df, unit, upto, name)


def zipf_updates(events: DataFrame, n: int, factor: float, size: int | None = 1000, width: int = 5) -> DataFrame:
    """Events as row changes (seq, i, j, v): a Zipf row, a fixed pattern of columns with small integers. size: the workload's
    batch, the first so many events; None: all events."""
    picked = (events if size is None else events.filter(F.col("event_id") < size)).select(F.col("event_id").alias("seq"))
    picked = zipf_rows(picked.withColumn("u", (F.pmod(F.col("seq") * 7919 + 13, F.lit(10_007)) + 0.5) / 10_007.0), "u", n, factor)
    return picked.select("seq", "i", F.explode(F.sequence(F.lit(0), F.lit(width - 1))).alias("k")).select("seq", "i", ((F.col("i") * 3 + F.col("k") * 5) % n).alias("j"), (F.col("k") + 1).cast("double").alias("v"))


MOST_RANK = 100_000


class TooWide(ValueError):
    """A batch that changes more rows than factors are good for; send it as a full change."""


def compact(updates: DataFrame, rows: int, cols: int, most: int = MOST_RANK) -> tuple[Coo, Coo, int]:
    """(L, R, rank): changes of one row are added, so the rank is the number of distinct rows, which is checked before the rows
    are numbered on the driver."""
    sums = updates.groupBy("i", "j").agg(F.sum("v").alias("v")).filter("v <> 0")
    touched = sorted(r[0] for r in sums.select("i").distinct().limit(most + 1).collect())
    if len(touched) > most:
        raise TooWide(f"more than {most} changed rows")
    spark = updates.sparkSession
    number = spark.createDataFrame(list(zip(touched, range(len(touched)), strict=True)), "i long, c long")
    left = number.select("i", F.col("c").alias("j"), F.lit(1.0).alias("v"))
    right = sums.join(F.broadcast(number), "i").select(F.col("j").alias("i"), F.col("c").alias("j"), "v")
    return Coo(left, rows, len(touched), len(touched)), Coo(right, cols, len(touched)), len(touched)


def dense(updates: DataFrame, rows: int, cols: int) -> Coo:
    """A full change: cells added by place, as one matrix."""
    return Coo(updates.groupBy("i", "j").agg(F.sum("v").alias("v")).filter("v <> 0"), rows, cols)
