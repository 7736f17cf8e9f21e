"""Matrices and updates made from the given tables, as COO frames."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.coo import SCHEMA, Coo, Tall, cut, packed, small_batches, unpacked

NATIONS = 25
TALL = 1 << 50  # declared height of matrices whose row ids are only unique
PAIRS = 1 << 22  # pairs of suppliers that a task counts at once
BLOCK = 64  # suppliers whose pairs are packed together


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def crosstab(df: DataFrame, i: Column, j: Column, v: Column, rows: int, cols: int) -> Coo:
    """Aggregate v by (i, j)."""
    cells = df.groupBy(i.cast("long").alias("i"), j.cast("long").alias("j")).agg(v.cast("double").alias("v"))
    return Coo(cells.filter("v <> 0"), rows, cols)


def from_rows(df: DataFrame, row_id: str, columns: list[str], rows: int = TALL) -> Coo:
    """One row of df is one matrix row; columns in order. Nulls count as zeros. df is kept behind the matrix, so it should be
    cheap to read again (a table, or a checkpoint), with ids that stay the same."""
    cells = df.select(F.col(row_id).cast("long").alias("i"), F.posexplode(F.array(*[F.col(c).cast("double") for c in columns])).alias("j", "v"))
    cells = cells.select("i", F.col("j").cast("long").alias("j"), (F.col("v") + 0.0).alias("v")).filter("v <> 0")
    return Coo(cells, rows, len(columns), tall=Tall(df, row_id, tuple(columns)))


def from_array_column(df: DataFrame, row_id: str, column: str, cols: int, rows: int = TALL) -> Coo:
    """One row of df is one matrix row, its cells an array."""
    wide = df.select(row_id, *[F.get(F.col(column), F.lit(k)).cast("double").alias(f"_{k}") for k in range(cols)])
    return from_rows(wide, row_id, [f"_{k}" for k in range(cols)], rows)


def to_wide(m: Coo, names: list[str]) -> DataFrame:
    """Rows with one column for each matrix column."""
    return m.df.groupBy("i").agg(*[F.coalesce(F.sum(F.when(F.col("j") == k, F.col("v"))), F.lit(0.0)).alias(n) for k, n in enumerate(names)])


def flows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines with the nations of customer (i) and supplier (j). Small tables are left to Spark's own size check."""
    t = lambda n: table(spark, sf_dir, n)
    lines = t("lineitem").select("l_orderkey", "l_suppkey", "l_partkey", "l_quantity", "l_shipdate")
    orders, customers, suppliers = t("orders").select("o_orderkey", "o_custkey"), t("customer").select("c_custkey", F.col("c_nationkey").alias("i")), t("supplier").select("s_suppkey", F.col("s_nationkey").alias("j"))
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey).join(customers, F.col("o_custkey") == F.col("c_custkey")).join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))


def nation_flow(spark: SparkSession, sf_dir: str) -> Coo:
    return crosstab(flows(spark, sf_dir), F.col("i"), F.col("j"), F.count("*"), NATIONS, NATIONS)


def ranked(m: Coo) -> DataFrame:
    return m.df.withColumn("rn", F.row_number().over(Window.partitionBy("i").orderBy(F.desc("v"), "j")))


def nation_top(spark: SparkSession, sf_dir: str, row: int | None = None) -> tuple[Coo, Coo, Coo]:
    """(A, L, R): each nation's three first suppliers; the change puts the fourth in the place of the third in ``row``."""
    r = Coo(cut(nation_flow(spark, sf_dir).df), NATIONS, NATIONS)
    r = cut(ranked(r))
    a = Coo(r.filter("rn <= 3").select("i", "j", F.lit(1.0).alias("v")), NATIONS, NATIONS)
    row = 3 if row is None else row
    return a, *row_change(r, row)


def row_change(r: DataFrame, row: int) -> tuple[Coo, Coo]:
    """e_row and (new row - old row)."""
    left = r.sparkSession.createDataFrame([(row, 0, 1.0)], "i long, j long, v double")
    right = r.filter((F.col("i") == row) & F.col("rn").isin(3, 4)).select(F.col("j").alias("i"), F.lit(0).cast("long").alias("j"), F.when(F.col("rn") == 4, 1.0).otherwise(-1.0).alias("v"))
    return Coo(left, NATIONS, 1), Coo(right, NATIONS, 1)


def nation_stochastic(spark: SparkSession, sf_dir: str) -> Coo:
    from ..operators.coo import row_normalize

    return row_normalize(nation_flow(spark, sf_dir))


def nation_start(spark: SparkSession, sf_dir: str, p: int) -> tuple[Coo, Coo]:
    """(T0, B): quantity and lines by (supplier nation, part mod p)."""
    f = flows(spark, sf_dir)
    j = F.col("l_partkey") % p
    return crosstab(f, F.col("j"), j, F.sum("l_quantity"), NATIONS, p), crosstab(f, F.col("j"), j, F.count("*"), NATIONS, p)


def suppliers_top(spark: SparkSession, sf_dir: str) -> Coo:
    """Each supplier's three first co-suppliers of orders."""
    small_batches(spark)
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").cast("long").alias("o"), F.col("l_suppkey").cast("long").alias("s")).dropna()
    n = table(spark, sf_dir, "supplier").count()
    pairs = lines.repartition("o").sortWithinPartitions("o", "s").mapInArrow(_pairs_of_orders, "b long, n long, data binary")
    return Coo(pairs.repartition("b").sortWithinPartitions("b").mapInArrow(_first_three, SCHEMA), n, n)


def _counted(i: np.ndarray, j: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sums of v by (i, j), in order."""
    order = np.lexsort((j, i))
    i, j, v = i[order], j[order], v[order]
    first = np.flatnonzero(np.concatenate([[True], (i[1:] != i[:-1]) | (j[1:] != j[:-1])]))
    return i[first], j[first], np.add.reduceat(v, first)


def _pairs_of_orders(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From lines (o, s) sorted by both: pairs of different suppliers of an order with the number of pairs of their lines, counted
    and packed by blocks of the first supplier. At most about PAIRS pairs are held at once, also of one order."""
    held, many = [], 0

    def send():
        i, j, v = _counted(*(np.concatenate(c) for c in zip(*held, strict=True)))
        block = i // BLOCK
        ends = [*np.flatnonzero(block[1:] != block[:-1]) + 1, len(i)]
        spans = list(zip([0, *ends[:-1]], ends, strict=True))
        rows = [packed(i[a:z], j[a:z], v[a:z]) for a, z in spans]
        for k in range(0, len(rows), 1000):
            part = spans[k : k + 1000]
            yield pa.RecordBatch.from_arrays([pa.array([int(block[a]) for a, _ in part], pa.int64()), pa.array([int(z - a) for a, z in part], pa.int64()), pa.array(rows[k : k + 1000], pa.binary())], ["b", "n", "data"])

    def orders(o, s):
        nonlocal held, many
        o, s, lines = _counted(o, s, np.ones(len(o), np.int64))
        _, begin, of, size = np.unique(o, return_index=True, return_inverse=True, return_counts=True)
        partners = size[of]
        upto, a = np.cumsum(partners), 0
        while a < len(o):
            z = max(a + 1, int(np.searchsorted(upto, PAIRS - many + (upto[a - 1] if a else 0), "right")))
            x = np.repeat(np.arange(a, z), partners[a:z])
            y = np.arange(len(x)) - np.repeat(upto[a:z] - partners[a:z] - (upto[a - 1] if a else 0), partners[a:z]) + begin[of[x]]
            x, y = x[x != y], y[x != y]
            if len(x):
                held.append((s[x], s[y], lines[x] * lines[y]))
                many += len(x)
            if many >= PAIRS // 2:
                yield from send()
                held, many = [], 0
            a = z

    rest = np.zeros(0, np.int64), np.zeros(0, np.int64)
    for batch in batches:
        o, s = (np.concatenate([old, batch.column(c).to_numpy()]) for old, c in zip(rest, "os", strict=True))
        last = int(np.searchsorted(o, o[-1])) if len(o) else 0
        rest = o[last:], s[last:]
        if last:
            yield from orders(o[:last], s[:last])
    if len(rest[0]):
        yield from orders(*rest)
    if held:
        yield from send()


def _first_three(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From packed pairs sorted by block: the three partners of a supplier with most pairs, the least number first among equals."""
    block, held, many = None, [], 0

    def top():
        i, j, v = _counted(*(np.concatenate(c) for c in zip(*held, strict=True)))
        order = np.lexsort((j, -v, i))
        i, j = i[order], j[order]
        start = np.flatnonzero(np.concatenate([[True], i[1:] != i[:-1]]))
        rank = np.arange(len(i)) - np.repeat(start, np.diff([*start, len(i)]))
        keep = rank < 3
        return pa.RecordBatch.from_arrays([pa.array(i[keep]), pa.array(j[keep]), pa.array(np.ones(keep.sum()))], ["i", "j", "v"])

    for batch in batches:
        for b, n, data in zip(*(batch.column(c).to_pylist() for c in ("b", "n", "data")), strict=True):
            if b != block:
                if held:
                    yield top()
                block, held, many = b, [], 0
            held.append(unpacked(data, n, np.int64, np.int64, np.int64))
            many += n
            if many > PAIRS:
                held = [_counted(*(np.concatenate(c) for c in zip(*held, strict=True)))]
                many = 0
    if held:
        yield top()


def folded(spark: SparkSession, sf_dir: str, n: int) -> Coo:
    """n x n: quantities of lines by folded keys, rows over their sums."""
    from ..operators.coo import row_normalize

    lines = table(spark, sf_dir, "lineitem")
    return row_normalize(crosstab(lines, F.col("l_partkey") % n, (31 * F.col("l_orderkey") + F.col("l_suppkey")) % n, F.sum("l_quantity"), n, n))


def line_regression(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[str], list[str]]:
    """(rows with id, X columns, Y columns): price in thousands on quantity, discount and tax. Ids are unique only."""
    lines = table(spark, sf_dir, "lineitem").select(F.lit(1.0).alias("one"), F.col("l_quantity").alias("q"), (F.col("l_discount") * 100).alias("d"), (F.col("l_tax") * 100).alias("t"), (F.col("l_extendedprice") / 1000).alias("y"), "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
    return cut(lines.withColumn("id", F.monotonically_increasing_id())), ["one", "q", "d", "t"], ["y"]


def document_regression(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", F.lit(1.0).alias("one"), (F.log(F.col("n_chars") + 1.0) / 10).alias("size"), (F.col("lang") == "en").cast("double").alias("english"))
    labels = table(spark, sf_dir, "labels").select("doc_id", F.col("quality").cast("double").alias("quality"), F.col("toxic").cast("double").alias("toxic"))
    return cut(docs.join(labels, "doc_id"))


def event_transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(a, b, n): event type, the same user's next, how often."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, sf_dir, "events").select("event_type", F.lead("event_type").over(order).alias("b"))
    return e.filter("b is not null").groupBy(F.col("event_type").alias("a"), "b").agg(F.count("*").alias("n"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, path): distinct links of pages."""
    pages = table(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("path"))
    return pages.distinct()
