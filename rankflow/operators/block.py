"""Dense matrices in row panels, each a block of float64 in Arrow binary; and the same matrix in column panels if wanted.

Thin operands within ``LIMIT_BYTES`` are sent to the panels, and matrix @ thin stays local to them: no shuffle. With column
panels thin' products with the transpose are local too; without, panels give partial sums, added up on executors. Matrix @
matrix works on square tiles of a bounded size: a task multiplies one tile of either side, and partial tiles are added a few at
a time, so that no task holds more than a handful of tiles whatever the matrix's size.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .coo import Coo, cut

LIMIT_BYTES = 256 << 20
PANEL_BYTES = 16 << 20
TILE_BYTES = 32 << 20
FAN = 4  # partial results that one task adds up
SCHEMA = "p int, at long, n int, m int, data binary"


@dataclass(frozen=True)
class Block:
    """panels: (p, at, n, m, data): rows at to at + n. columns: the transpose in row panels, or None (single layout)."""

    panels: DataFrame
    rows: int
    cols: int
    columns: DataFrame | None = None

    @property
    def height(self) -> int:
        return panel_height(self.cols)


def panel_height(cols: int) -> int:
    return max(1, PANEL_BYTES // (8 * max(1, cols)))


def _matrix(n: int, m: int, data: bytes) -> np.ndarray:
    return np.frombuffer(data, np.float64).reshape(n, m)


def _rows(batch: pa.RecordBatch):
    return zip(*(batch.column(c).to_pylist() for c in ("p", "at", "n", "m", "data")), strict=True)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [()] * 5, kinds, strict=True)], ["p", "at", "n", "m", "data"])


def _panels(coo: DataFrame, rows: int, cols: int) -> DataFrame:
    h = panel_height(cols)

    def build(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        p = key[0].as_py()
        n = min(h, rows - p * h)
        x = np.zeros((n, cols))
        ok = table.column("v").is_valid().to_numpy()
        np.add.at(x, (table.column("i").to_numpy()[ok] - p * h, table.column("j").to_numpy()[ok]), table.column("v").to_numpy()[ok])
        return pa.Table.from_batches([_batch([(p, p * h, n, cols, x.tobytes())])])

    spark = coo.sparkSession
    empty = spark.range(-(-rows // h)).select((F.col("id") * h).alias("i"), F.lit(0).cast("long").alias("j"), F.lit(None).cast("double").alias("v"))
    cells = coo.select("i", "j", "v").unionByName(empty).withColumn("p", F.floor(F.col("i") / h).cast("int"))
    return cells.groupBy("p").applyInArrow(build, SCHEMA)


def from_coo(a: Coo, dual: bool = True) -> Block:
    """The input is shuffled once for each layout."""
    columns = cut(_panels(a.df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), a.cols, a.rows)) if dual else None
    return Block(cut(_panels(a.df, a.rows, a.cols)), a.rows, a.cols, columns)


def to_coo(a: Block) -> Coo:
    def cells(batches):
        for b in batches:
            for _, at, n, m, data in _rows(b):
                x = _matrix(n, m, data)
                i, j = np.nonzero(x)
                yield pa.RecordBatch.from_arrays([pa.array(i + at), pa.array(j), pa.array(x[i, j])], ["i", "j", "v"])

    return Coo(a.panels.mapInArrow(cells, "i long, j long, v double"), a.rows, a.cols)


def _gathered(panels: DataFrame, rows: int, cols: int) -> np.ndarray:
    """A thin result on the driver; its size is checked first."""
    if 8 * rows * cols > LIMIT_BYTES:
        raise MemoryError(f"{rows} x {cols} is more than the driver takes; use the COO back end")
    out = np.zeros((rows, cols))
    for r in panels.collect():
        out[r.at : r.at + r.n] += _matrix(r.n, r.m, r.data)
    return out


def mul_thin(a: Block, x: np.ndarray) -> np.ndarray:
    """a @ x: one broadcast of x, one gathering of the result."""
    return _gathered(_times(a.panels, x), a.rows, x.shape[1])


def _times(panels: DataFrame, x: np.ndarray) -> DataFrame:
    if x.nbytes > LIMIT_BYTES:
        raise MemoryError("the thin operand is over the limit; use the COO back end")
    sent = panels.sparkSession.sparkContext.broadcast(np.ascontiguousarray(x))

    def run(batches):
        for b in batches:
            yield _batch([(p, at, n, sent.value.shape[1], (_matrix(n, m, d) @ sent.value).tobytes()) for p, at, n, m, d in _rows(b)])

    return panels.mapInArrow(run, SCHEMA)


def tmul_thin(a: Block, x: np.ndarray) -> np.ndarray:
    """a.T @ x: local with column panels; else a partial sum from each panel, added on the way to the driver."""
    if a.columns is not None:
        return _gathered(_times(a.columns, x), a.cols, x.shape[1])
    if max(x.nbytes, 8 * a.cols * x.shape[1]) > LIMIT_BYTES:
        raise MemoryError("the thin operand is over the limit; use the COO back end")
    sent = a.panels.sparkSession.sparkContext.broadcast(np.ascontiguousarray(x))
    cols = a.cols

    def run(batches):
        total, first = None, 0
        for b in batches:
            for p, at, n, m, d in _rows(b):
                part = _matrix(n, m, d).T @ sent.value[at : at + n]
                total, first = (part, p) if total is None else (total + part, first)
        if total is not None:
            yield _batch([(first, 0, cols, total.shape[1], total.tobytes())])

    def added(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        total = sum(_matrix(n, m, d) for n, m, d in zip(*(t.column(c).to_pylist() for c in ("n", "m", "data")), strict=True))
        return pa.Table.from_batches([_batch([(key[0].as_py(), 0, total.shape[0], total.shape[1], total.tobytes())])])

    parts, many = a.panels.mapInArrow(run, SCHEMA), a.panels.rdd.getNumPartitions()
    while many > 4 * FAN:  # a tree of sums, so that the driver gets a few partial results only
        many = -(-many // FAN)
        parts = parts.withColumn("p", F.pmod("p", F.lit(many)).cast("int")).groupBy("p").applyInArrow(added, SCHEMA)
    return _gathered(parts, a.cols, x.shape[1])


def add_outer(a: Block, left: np.ndarray, right: np.ndarray) -> Block:
    """a + left @ right.T: factors are broadcast, each panel adds its rows; both layouts."""

    def plus(panels: DataFrame, x: np.ndarray, y: np.ndarray) -> DataFrame:
        sent = panels.sparkSession.sparkContext.broadcast((np.ascontiguousarray(x), np.ascontiguousarray(y.T)))

        def run(batches):
            u, v = sent.value
            for b in batches:
                yield _batch([(p, at, n, m, (_matrix(n, m, d) + u[at : at + n] @ v).tobytes()) for p, at, n, m, d in _rows(b)])

        return cut(panels.mapInArrow(run, SCHEMA))

    if max(left.nbytes, right.nbytes) > LIMIT_BYTES:
        raise MemoryError("the factors are over the limit; use the COO back end")
    return Block(plus(a.panels, left, right), a.rows, a.cols, None if a.columns is None else plus(a.columns, right, left))


def combine(a: Block, b: Block, c: float = 1.0) -> Block:
    """a + c * b, panel by panel."""

    def run(batches):
        for x in batches:
            cols = [x.column(k).to_pylist() for k in ("p", "at", "n", "m", "data", "other")]
            yield _batch([(p, at, n, m, (_matrix(n, m, d) + c * _matrix(n, m, e)).tobytes()) for p, at, n, m, d, e in zip(*cols, strict=True)])

    def both(x: DataFrame, y: DataFrame) -> DataFrame:
        return cut(x.join(y.select("p", F.col("data").alias("other")), "p").mapInArrow(run, SCHEMA))

    return Block(both(a.panels, b.panels), a.rows, a.cols, None if a.columns is None or b.columns is None else both(a.columns, b.columns))


def scaled(c: float, a: Block) -> Block:
    def run(batches):
        for b in batches:
            yield _batch([(p, at, n, m, (c * _matrix(n, m, d)).tobytes()) for p, at, n, m, d in _rows(b)])

    return Block(a.panels.mapInArrow(run, SCHEMA), a.rows, a.cols, None if a.columns is None else a.columns.mapInArrow(run, SCHEMA))


def transpose(a: Block) -> Block:
    if a.columns is None:
        return from_coo(Coo(to_coo(a).df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), a.cols, a.rows))
    return Block(a.columns, a.cols, a.rows, a.panels)


def identity(spark: SparkSession, n: int) -> Block:
    h = panel_height(n)

    def run(batches):
        for b in batches:
            rows = []
            for p in b.column(0).to_pylist():
                size = min(h, n - p * h)
                rows.append((p, p * h, size, n, np.eye(size, n, p * h).tobytes()))
            yield _batch(rows)

    panels = spark.range(-(-n // h)).mapInArrow(run, SCHEMA)
    return Block(panels, n, n, panels)


def _tiles(batches, tile: int):
    """Row panels cut at the borders of the tiles: a's get (bi, bk), b's (bk, bj)."""
    names, kinds = ["r", "c", "at", "n", "m", "data"], (pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
    for x in batches:
        for _, at, n, m, d in _rows(x):
            z, out = _matrix(n, m, d), []
            for r in range(at // tile, (at + n - 1) // tile + 1):
                lo, hi = max(at, r * tile), min(at + n, (r + 1) * tile)
                for c in range(-(-m // tile)):
                    part = z[lo - at : hi - at, c * tile : (c + 1) * tile]
                    out.append((r, c, lo - r * tile, hi - lo, part.shape[1], np.ascontiguousarray(part).tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names)


def matmul_grid(a: Block, b: Block, grid: int | None = None, dual: bool = True) -> Block:
    """a @ b over tiles: (bi, bk) of a meets (bk, bj) of b in one task, and the partial tiles are added over bk by a tree.

    grid: tiles along the longest side; more are taken where a tile would pass ``TILE_BYTES``."""
    rows, inner, cols = a.rows, a.cols, b.cols
    tile = max(1, min(-(-max(rows, inner, cols) // (grid or 1)), int((TILE_BYTES / 8) ** 0.5)))
    high, deep, wide = (-(-s // tile) for s in (rows, inner, cols))
    cut_up = "r int, c int, at long, n int, m int, data binary"

    def spread(panels: DataFrame, side: str, copies: int) -> DataFrame:
        pieces = panels.mapInArrow(lambda batches: _tiles(batches, tile), cut_up)
        other = F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("o")
        pieces = pieces.select("*", other)
        bi, bj, bk = ("r", "o", "c") if side == "a" else ("o", "c", "r")
        return pieces.select(F.col(bi).alias("bi"), F.col(bj).alias("bj"), F.col(bk).alias("bk"), F.lit(side).alias("side"), "at", "n", "m", "data")

    def product(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        bi, bj, bk = (k.as_py() for k in key)
        got = {"a": [], "b": []}
        for side, at, n, m, d in zip(*(t.column(c).to_pylist() for c in ("side", "at", "n", "m", "data")), strict=True):
            got[side].append((at, _matrix(n, m, d)))
        if not got["a"] or not got["b"]:
            return pa.Table.from_batches([_tile_batch([])])
        x, y = (np.vstack([z for _, z in sorted(got[s], key=lambda q: q[0])]) for s in "ab")
        z = x @ y
        return pa.Table.from_batches([_tile_batch([(bi, bj, bk, z.shape[0], z.shape[1], z.tobytes())])])

    def added(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        total = sum(_matrix(n, m, d) for n, m, d in zip(*(t.column(c).to_pylist() for c in ("n", "m", "data")), strict=True))
        return pa.Table.from_batches([_tile_batch([(*(k.as_py() for k in key), total.shape[0], total.shape[1], total.tobytes())])])

    partial = "bi int, bj int, bk int, n int, m int, data binary"
    tiles = spread(a.panels, "a", wide).unionByName(spread(b.panels, "b", high)).groupBy("bi", "bj", "bk").applyInArrow(product, partial)
    while deep > 1:
        deep = -(-deep // FAN)
        tiles = tiles.withColumn("bk", F.floor(F.col("bk") / FAN).cast("int")).groupBy("bi", "bj", "bk").applyInArrow(added, partial)
    tiles = cut(tiles)

    def panels_of(turned: bool) -> DataFrame:
        n, m = (cols, rows) if turned else (rows, cols)
        size = panel_height(m)

        def pieces(batches):
            for x in batches:
                for bi, bj, tn, tm, d in zip(*(x.column(c).to_pylist() for c in ("bi", "bj", "n", "m", "data")), strict=True):
                    z, at, left, out = _matrix(tn, tm, d), bi * tile, bj * tile, []
                    if turned:
                        z, at, left = z.T, left, at
                    for q in range(at // size, (at + z.shape[0] - 1) // size + 1):
                        lo, hi = max(at, q * size), min(at + z.shape[0], (q + 1) * size)
                        out.append((q, (lo << 32) + left, hi - lo, z.shape[1], np.ascontiguousarray(z[lo - at : hi - at]).tobytes()))
                    yield _batch(out)

        def assemble(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
            q = key[0].as_py()
            x = np.zeros((min(size, n - q * size), m))
            for code, k, w_, d in zip(*(t.column(c).to_pylist() for c in ("at", "n", "m", "data")), strict=True):
                lo, left = code >> 32, code & 0xFFFFFFFF
                x[lo - q * size : lo - q * size + k, left : left + w_] = _matrix(k, w_, d)
            return pa.Table.from_batches([_batch([(q, q * size, x.shape[0], m, x.tobytes())])])

        return cut(tiles.mapInArrow(pieces, SCHEMA).groupBy("p").applyInArrow(assemble, SCHEMA))

    return Block(panels_of(False), rows, cols, panels_of(True) if dual else None)


def _tile_batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [()] * 6, kinds, strict=True)], ["bi", "bj", "bk", "n", "m", "data"])
