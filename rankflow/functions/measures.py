"""Measures of a refresh: time, speed-up, memory, filled cells, communication, error."""

from __future__ import annotations

import time
from collections.abc import Callable
from statistics import mean, pstdev

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.coo import Coo


def refresh(f: Callable[[], object], runs: int = 3) -> tuple[float, float]:
    """(mean, deviation) of wall seconds."""
    took = []
    for _ in range(runs):
        t = time.perf_counter()
        f()
        took.append(time.perf_counter() - t)
    return mean(took), pstdev(took)


def speedup(reeval: float, incr: float) -> float:
    return reeval / incr


def memory(n: int, matrices: int) -> float:
    """GiB of so many n x n matrices of doubles."""
    return 8.0 * n * n * matrices / 2**30


def speedup_per_memory(reeval: float, incr: float, memory_reeval: float, memory_incr: float) -> float:
    return (reeval / incr) / (memory_incr / memory_reeval)


def fill(m: Coo) -> int:
    """Changed cells of a change."""
    return m.df.filter("v <> 0").count()


def communication(n: int, rank: int, steps: int) -> int:
    """Bytes of factors sent and gathered by incremental squarings: rank doubles each step."""
    return sum(2 * 8 * n * rank * 2**s for s in range(steps))


def moved(spark: SparkSession, f: Callable[[], object]) -> dict[str, int]:
    """Bytes that the stages of f wrote to and read from shuffles, and sent to the driver, by Spark's status store."""
    store = spark.sparkContext._jsc.sc().statusStore()

    def stages() -> dict[tuple[int, int], tuple[int, int, int]]:
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
        got = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
        each = [got.apply(k) for k in range(got.size())]
        return {(s.stageId(), s.attemptId()): (s.shuffleWriteBytes(), s.shuffleReadBytes(), s.resultSize()) for s in each}

    before = stages()
    f()
    new = [v for k, v in stages().items() if k not in before]
    return dict(zip(("shuffle_written", "shuffle_read", "to_driver"), (sum(c) for c in zip(*new, strict=True)) if new else (0, 0, 0), strict=True))


def difference(a: Coo, b: Coo) -> DataFrame:
    x, y = a.df.select("i", "j", F.col("v").alias("x")), b.df.select("i", "j", F.col("v").alias("y"))
    return x.join(y, ["i", "j"], "full_outer").select("i", "j", F.coalesce("x", F.lit(0.0)).alias("x"), F.coalesce("y", F.lit(0.0)).alias("y"))


def max_abs_err(a: Coo, b: Coo) -> float:
    return difference(a, b).agg(F.coalesce(F.max(F.abs(F.col("x") - F.col("y"))), F.lit(0.0))).first()[0]


def rel_err(a: Coo, b: Coo) -> float:
    return difference(a, b).agg(F.coalesce(F.sqrt(F.sum((F.col("x") - F.col("y")) ** 2)) / F.sqrt(F.sum(F.col("y") ** 2)), F.lit(0.0))).first()[0]
