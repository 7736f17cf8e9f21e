"""Matrix operators as plans over COO frames (i long, j long, v double): joins and sums that Catalyst plans itself.

A missing row is a zero. Only an operand whose size is within ``BROADCAST_BYTES`` is broadcast, by its number of cells where
that is known and by its declared shape otherwise; beyond it the join is left to Spark (shuffled, skew split by AQE).

A large matrix that changes by thin factors keeps them in a log beside its cells: products with thin operands read the log, so
a refresh moves nothing of the matrix; the log is added up once its rank is over ``LOG_RANK``. A tall matrix made from the
columns of a table keeps that table, and its products over the rows are summed by partition in one pass.

A product on tiles is kept as packed tiles (a few bytes a cell), which a later product or the log's sum takes as they are; its
cells are read out of them.
"""

from __future__ import annotations

import os
import tempfile
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BROADCAST_BYTES = 64 << 20
LOCAL_BYTES = 1 << 20  # a settled matrix of at most so many bytes is kept in the plan itself
LOG_RANK = 64
TILE = 512
GROUP = 8  # tiles along a side of what one task of a product on tiles sums up
BATCH_BYTES = 8 << 20
PRODUCTS = 1 << 24  # products of cells from which a product of settled matrices works on tiles
TALL_COLS = 1024  # columns up to which products over the rows are summed by partition
CELL = 24
SCHEMA = "i long, j long, v double"
TILES = "p long, q long, n long, data binary"
WHOLE = "decimal(38,0)"


@dataclass(frozen=True)
class Tall:
    """The table behind a tall matrix: a row of ``df`` is a matrix row, its columns in order."""

    df: DataFrame
    row_id: str
    columns: tuple[str, ...]


@dataclass(frozen=True)
class Coo:
    """base + sum of L @ R.T over the log. cells: an upper bound of base's cells, if known. tiles: base as packed tiles, if it is
    made from them."""

    base: DataFrame
    rows: int
    cols: int
    cells: int | None = None
    log: tuple[tuple[Coo, Coo], ...] = ()
    tall: Tall | None = None
    tiles: DataFrame | None = None

    @property
    def bytes(self) -> int:
        return CELL * (self.rows * self.cols if self.cells is None or self.log else min(self.cells, self.rows * self.cols))

    @property
    def df(self) -> DataFrame:
        """All cells, with the log added up."""
        if not self.log:
            return self.base
        if self.tiles is not None:
            return _logged_tiles(self).base
        left, right = self.stacked
        return _sum(self.base, mul(left, transpose(right)).df)

    @property
    def stacked(self) -> tuple[Coo, Coo]:
        """The log as one pair of factors."""
        return hstack([left for left, _ in self.log]), hstack([right for _, right in self.log])

    @property
    def rank(self) -> int:
        return sum(left.cols for left, _ in self.log)


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a local folder only where that is unset and all runs in one process."""
    sc = spark.sparkContext
    where = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not where:
        if not sc.master.startswith("local[") and sc.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        where = os.path.join(tempfile.gettempdir(), "rankflow-checkpoints")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(where)
    return where


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the session's shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def settle(m: Coo) -> Coo:
    """m computed: small ones become rows of the plan (their size is checked), large ones a checkpoint; a log stays a log."""
    if m.log:
        known = lambda x: x if x.cells is not None else settle(x)  # noqa: E731  # factors are settled once, when they come
        return replace(m, log=tuple((known(a), known(b)) for a, b in m.log))
    if m.bytes <= LOCAL_BYTES:
        t = m.df.select("i", "j", "v").toArrow()
        spark = m.base.sparkSession
        schema = f"i long, j long, v {m.base.schema['v'].dataType.simpleString()}"
        return Coo(spark.createDataFrame(t if t.num_rows else [], schema), m.rows, m.cols, t.num_rows)
    if m.tiles is not None:
        tiles = cut(m.tiles)
        return _from_tiles(tiles, m.rows, m.cols, tiles.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])
    df = cut(m.df)
    return Coo(df, m.rows, m.cols, df.count())


def _sum(x: DataFrame, y: DataFrame) -> DataFrame:
    return x.unionByName(y).groupBy("i", "j").agg(F.sum("v").alias("v")).filter("v <> 0")


def clean(df: DataFrame, rows: int, cols: int) -> Coo:
    """COO from any (i, j, v): cells of one place are added, -0.0 and zeros go. Null, NaN or infinite cells are an error."""
    bad = F.col("i").isNull() | F.col("j").isNull() | F.col("v").isNull() | F.isnan(F.col("v").cast("double")) | (F.abs(F.col("v").cast("double")) == float("inf")) | (F.col("i") < 0) | (F.col("i") >= rows) | (F.col("j") < 0) | (F.col("j") >= cols)
    checked = df.select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), F.when(bad, F.raise_error(F.lit("a cell is null, not finite or out of range")).cast("double")).otherwise(F.col("v").cast("double")).alias("v"))
    return Coo(checked.groupBy("i", "j").agg((F.sum("v") + 0.0).alias("v")).filter("v <> 0"), rows, cols)


def integers(m: Coo) -> Coo:
    """m with cells as whole numbers of 38 digits, which sums and products keep exactly; a broken number or one beyond is an error."""
    if m.base.schema["v"].dataType.simpleString() == WHOLE:
        return m
    v = F.when(F.col("v") == F.floor("v"), F.col("v").cast(WHOLE)).otherwise(F.raise_error(F.lit("a cell is not a whole number")).cast(WHOLE))
    return Coo(m.df.select("i", "j", v.alias("v")), m.rows, m.cols, m.cells)


def _hint(m: Coo, df: DataFrame) -> DataFrame:
    return F.broadcast(df) if m.bytes <= BROADCAST_BYTES else df


def mul(a: Coo, b: Coo) -> Coo:
    """a @ b: join on the inner index, sum by cell. With a thin b a's log is read as it is."""
    if a.log and b.cols <= LOG_RANK:
        left, right = a.stacked
        return add(mul(replace(a, log=()), b), mul(left, mul(transpose(right), b)))
    if b.log and a.rows <= LOG_RANK:
        return transpose(mul(transpose(b), transpose(a)))
    if _dense_enough(a, b):
        return _mul_tiles(a, b)
    x, y = a.df.select("i", F.col("j").alias("k"), F.col("v").alias("x")), b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("y"))
    if max(a.bytes, b.bytes) <= LOCAL_BYTES:  # one task and no shuffle; what lies before their own last sums stays as it is
        x, y = x.coalesce(1), y.coalesce(1)
    x, y = (x, _hint(b, y)) if b.bytes <= a.bytes else (_hint(a, x), y)
    return Coo(x.join(y, "k").groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("v")).filter("v <> 0"), a.rows, b.cols)


def _dense_enough(a: Coo, b: Coo) -> bool:
    """Whether a @ b, of settled matrices of doubles, has many more products of cells than tiles to build for them."""
    if a.log or b.log or a.cells is None or b.cells is None or a.cells * b.cells / a.cols < PRODUCTS or any(m.base.schema["v"].dataType.simpleString() != "double" for m in (a, b)):
        return False
    at = lambda c: F.floor(F.col(c) / TILE)
    of = lambda m: m.tiles.select("p", "q") if m.tiles is not None else m.base.select(at("i").alias("p"), at("j").alias("q")).distinct()
    left, right = of(a).groupBy(F.col("q").alias("k")).agg(F.count("*").alias("n")), of(b).groupBy(F.col("p").alias("k")).agg(F.count("*").alias("m"))
    pairs = left.join(right, "k").agg(F.sum(F.col("n") * F.col("m"))).first()[0] or 0
    return a.cells * b.cells / a.cols >= 64 * TILE * pairs


def packed(*columns: np.ndarray) -> bytes:
    """Columns of 8-byte numbers in little room: whole ones by their steps, each byte's place by itself, compressed."""
    steps = [np.diff(c, prepend=c.dtype.type(0)) if c.dtype.kind == "i" else c for c in columns]
    return pa.compress(b"".join(np.ascontiguousarray(c).view(np.uint8).reshape(-1, 8).T.tobytes() for c in steps), "zstd", asbytes=True)


def unpacked(data: bytes, n: int, *kinds: type) -> list[np.ndarray]:
    """The columns of ``packed``, n numbers each."""
    raw = np.frombuffer(pa.decompress(data, 8 * n * len(kinds), "zstd", asbytes=True), np.uint8).reshape(len(kinds), 8, n)
    columns = [np.ascontiguousarray(c.T).view(kind).ravel() for c, kind in zip(raw, kinds, strict=True)]
    return [np.cumsum(c) if c.dtype.kind == "i" else c for c in columns]


def small_batches(spark: SparkSession) -> None:
    """Arrow batches of packed cells hold BATCH_BYTES at most (a setting of the running session; the default is 64 MB)."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    size = spark.conf.get(key).rstrip("b")
    if not size.isdigit() or int(size) > BATCH_BYTES:
        spark.conf.set(key, str(BATCH_BYTES))


def _strips(m: Coo, key: str, name: str, width: int) -> DataFrame:
    """(key, n<name>, name): the cells of TILE rows packed, by place (row within them times width, plus column) and value."""

    def pack(t: pa.Table) -> pa.Table:
        at, v = t.column("at").to_numpy(), t.column("v").to_numpy()
        order = np.argsort(at)
        return pa.table([t.column(key)[:1], pa.array([t.num_rows], pa.int64()), pa.array([packed(at[order], v[order])])], names=[key, f"n{name}", name])

    cells = m.base.select(F.floor(F.col("i") / TILE).alias(key), (F.col("i") % TILE * width + F.col("j")).alias("at"), "v")
    return cells.groupBy(key).applyInArrow(pack, f"{key} long, n{name} long, {name} binary")


def _tiles(m: Coo) -> DataFrame:
    """(p, q, n, data): square tiles, their cells packed by place (TILE times the row within it, plus the column) and value."""
    small_batches(m.base.sparkSession)
    if m.tiles is not None:
        return m.tiles

    def pack(t: pa.Table) -> pa.Table:
        at, v = t.column("at").to_numpy(), t.column("v").to_numpy()
        order = np.argsort(at)
        return pa.table([t.column("p")[:1], t.column("q")[:1], pa.array([t.num_rows], pa.int64()), pa.array([packed(at[order], v[order])])], names=["p", "q", "n", "data"])

    cells = m.base.select(F.floor(F.col("i") / TILE).alias("p"), F.floor(F.col("j") / TILE).alias("q"), (F.col("i") % TILE * TILE + F.col("j") % TILE).alias("at"), "v")
    return cut(cells.groupBy("p", "q").applyInArrow(pack, TILES))


def _from_tiles(tiles: DataFrame, rows: int, cols: int, cells: int | None = None) -> Coo:
    def run(batches):
        for batch in batches:
            for p, q, n, data in zip(*(batch.column(c).to_pylist() for c in ("p", "q", "n", "data")), strict=True):
                at, v = unpacked(data, n, np.int64, np.float64)
                yield pa.RecordBatch.from_arrays([pa.array(p * TILE + at // TILE), pa.array(q * TILE + at % TILE), pa.array(v)], ["i", "j", "v"])

    return Coo(tiles.mapInArrow(run, SCHEMA), rows, cols, cells, tiles=tiles)


def _dense(n: int, data: bytes, width: int) -> np.ndarray:
    out = np.zeros(TILE * width)
    at, v = unpacked(data, n, np.int64, np.float64)
    out[at] = v
    return out.reshape(TILE, width)


def _tile(p: int, q: int, x: np.ndarray) -> pa.RecordBatch | None:
    at = np.flatnonzero(x)
    return pa.RecordBatch.from_arrays([pa.array([p]), pa.array([q]), pa.array([len(at)]), pa.array([packed(at, x.ravel()[at])], pa.binary())], ["p", "q", "n", "data"]) if len(at) else None


def _mul_tiles(a: Coo, b: Coo) -> Coo:
    """a @ b by tiles. A task sums up a square of ``GROUP`` x ``GROUP`` tiles of the result, to which the tiles of a's rows and b's
    columns are sent packed; no partial sums are. It holds that square and the left tiles with one inner number, whatever the
    matrices' size; of two tiles only rows and columns with cells are multiplied."""
    x = _tiles(a)
    y = x if b is a else _tiles(b)
    count = lambda n: -(-min(n, 1 << 40) // TILE)
    side = max(1, min(GROUP, max(count(a.rows), count(b.cols)) // 6))
    x = x.select(F.floor(F.col("p") / side).alias("gp"), F.col("q").alias("k"), F.lit(0).alias("side"), F.col("p").alias("at"), "n", "data")
    y = y.select(F.floor(F.col("q") / side).alias("gq"), F.col("p").alias("k"), F.lit(1).alias("side"), F.col("q").alias("at"), "n", "data")
    meet = x.select("gp", "k").distinct().join(y.select("gq", "k").distinct(), "k")
    groups = -(-count(a.rows) // side) * -(-count(b.cols) // side)
    meet = F.broadcast(meet) if CELL * groups * count(a.cols) <= BROADCAST_BYTES else meet
    both = x.join(meet, ["gp", "k"]).unionByName(y.join(meet, ["gq", "k"]))
    both = both.repartition(min(groups, 1000), "gp", "gq").sortWithinPartitions("gp", "gq", "k", "side", "at")

    def run(batches):
        group, inner, left, out = None, None, {}, {}
        for batch in batches:
            for gp, gq, k, which, at, n, data in zip(*(batch.column(c).to_pylist() for c in ("gp", "gq", "k", "side", "at", "n", "data")), strict=True):
                if (gp, gq) != group:
                    yield from filter(None, (_tile(*place, sums) for place, sums in out.items()))
                    group, inner, out = (gp, gq), None, {}
                if k != inner:
                    inner, left = k, {}
                m = _dense(n, data, TILE)
                if which == 0:
                    left[at] = m, np.flatnonzero(m.any(1)), m.any(0)
                    continue
                has, cols = m.any(1), np.flatnonzero(m.any(0))
                for p, (x, rows, filled) in left.items():
                    common = np.flatnonzero(has & filled)
                    if len(common):
                        sums = out.setdefault((p, at), np.zeros((TILE, TILE)))
                        sums[np.ix_(rows, cols)] += x[np.ix_(rows, common)] @ m[np.ix_(common, cols)]
        yield from filter(None, (_tile(*place, sums) for place, sums in out.items()))

    return _from_tiles(both.mapInArrow(run, TILES), a.rows, b.cols)


def _logged_tiles(m: Coo) -> Coo:
    """m's tiles with its log added up. The factors go to the tiles; small ones are broadcast, so that no tile moves."""
    small_batches(m.base.sparkSession)
    left, right = (settle(x) for x in m.stacked)
    width = left.cols
    x, y = cut(_strips(left, "p", "l", width)), cut(_strips(right, "q", "r", width))
    new = x.select("p").crossJoin(y.select("q")).join(m.tiles.select("p", "q"), ["p", "q"], "left_anti")
    tiles = m.tiles.unionByName(new.select("p", "q", F.lit(0).cast("long").alias("n"), F.lit(None).cast("binary").alias("data")))
    tiles = tiles.join(_hint(left, x), "p", "left").join(_hint(right, y), "q", "left").select("p", "q", "n", "data", "nl", "l", "nr", "r")

    def run(batches):
        for batch in batches:
            for p, q, n, data, nl, x, nr, y in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if x is None or y is None:
                    yield pa.RecordBatch.from_arrays([pa.array([p]), pa.array([q]), pa.array([n]), pa.array([data], pa.binary())], ["p", "q", "n", "data"])
                    continue
                out = np.zeros((TILE, TILE)) if data is None else _dense(n, data, TILE)
                out += _dense(nl, x, width) @ _dense(nr, y, width).T
                if (done := _tile(p, q, out)) is not None:
                    yield done

    return _from_tiles(tiles.mapInArrow(run, TILES), m.rows, m.cols)


def tmul(a: Coo, b: Coo) -> Coo:
    """a.T @ b without a transposed copy; over the rows of one table where both sides come from it."""
    if a.tall is not None and b.tall is not None and a.tall.df is b.tall.df and a.cols + b.cols <= TALL_COLS:
        return gram(a, b)
    return mul(transpose(a), b)


def transpose(a: Coo) -> Coo:
    return Coo(a.base.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), a.cols, a.rows, a.cells, tuple((right, left) for left, right in a.log))


def add(a: Coo, b: Coo, sign: float = 1.0) -> Coo:
    df = a.df.unionByName(b.df.withColumn("v", F.col("v") * sign) if sign != 1.0 else b.df)
    df = df.coalesce(1) if max(a.bytes, b.bytes) <= LOCAL_BYTES else df
    return Coo(df.groupBy("i", "j").agg(F.sum("v").alias("v")).filter("v <> 0"), a.rows, a.cols)


def scale(c: float, a: Coo) -> Coo:
    return Coo(a.df.withColumn("v", F.col("v") * float(c)).filter("v <> 0"), a.rows, a.cols)


def identity(spark: SparkSession, n: int) -> Coo:
    return Coo(spark.range(n).select(F.col("id").alias("i"), F.col("id").alias("j"), F.lit(1.0).alias("v")), n, n)


def hstack(parts: list[Coo]) -> Coo:
    at, df = 0, None
    for p in parts:
        q = p.df.withColumn("j", F.col("j") + at)
        df, at = q if df is None else df.unionByName(q), at + p.cols
    known = all(p.cells is not None and not p.log for p in parts)
    return Coo(df, parts[0].rows, at, sum(p.cells for p in parts) if known else None)


def vstack(parts: list[Coo]) -> Coo:
    return transpose(hstack([transpose(p) for p in parts]))


def piece(a: Coo, rows: tuple[int, int], cols: tuple[int, int]) -> Coo:
    df = a.df.filter(F.col("i").between(rows[0], rows[1] - 1) & F.col("j").between(cols[0], cols[1] - 1))
    return Coo(df.select((F.col("i") - rows[0]).alias("i"), (F.col("j") - cols[0]).alias("j"), "v"), rows[1] - rows[0], cols[1] - cols[0])


def add_outer(m: Coo, left: Coo, right: Coo) -> Coo:
    """m + left @ right.T. A large m takes the factors into its log, and is only rewritten once that is full."""
    if m.bytes <= BROADCAST_BYTES:
        return add(m, mul(left, transpose(right)))
    logged = replace(m, log=(*m.log, (left, right)))
    if logged.rank <= LOG_RANK:
        return logged
    return settle(Coo(logged.df, m.rows, m.cols) if logged.tiles is None else _logged_tiles(logged))


def row_normalize(a: Coo) -> Coo:
    """Rows over their sums; empty rows stay empty."""
    s = a.df.groupBy("i").agg(F.sum("v").alias("s"))
    return Coo(a.df.join(s, "i").filter("s <> 0").select("i", "j", (F.col("v") / F.col("s")).alias("v")), a.rows, a.cols)


def col_normalize(a: Coo) -> Coo:
    return transpose(row_normalize(transpose(a)))


def diag(a: Coo) -> Coo:
    return Coo(a.df.filter("i = j"), a.rows, a.cols)


def trace(a: Coo) -> float:
    return a.df.filter("i = j").agg(F.coalesce(F.sum("v"), F.lit(0.0))).first()[0]


def norm(a: Coo) -> float:
    return a.df.agg(F.sqrt(F.coalesce(F.sum(F.col("v") * F.col("v")), F.lit(0.0)))).first()[0]


def gram(a: Coo, b: Coo | None = None) -> Coo:
    """a.T @ b (b = a if none). From one table: partial products by partition, then one sum of a.cols x b.cols cells; logs enter
    as thin products. Otherwise cells of one row meet, and sums combine before the shuffle."""
    b = b or a
    if a.tall is not None and b.tall is not None and a.tall.df is b.tall.df and a.cols + b.cols <= TALL_COLS:
        out = _partial_products(a.tall, b.tall)
        x, y = replace(a, log=(), tall=None), replace(b, log=(), tall=None)
        p, q = a.stacked if a.log else (None, None)
        u, v = b.stacked if b.log else (None, None)
        if a.log:
            out = add(out, mul(q, mul(transpose(p), y)))
        if b.log:
            out = add(out, mul(mul(transpose(x), u), transpose(v)))
        if a.log and b.log:
            out = add(out, mul(mul(q, mul(transpose(p), u)), transpose(v)))
        return out
    x, y = a.df.select(F.col("i").alias("k"), F.col("j").alias("i"), F.col("v").alias("x")), b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("y"))
    return Coo(x.join(y, "k").groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("v")).filter("v <> 0"), a.cols, b.cols)


def _partial_products(a: Tall, b: Tall) -> Coo:
    n, m, same = len(a.columns), len(b.columns), a.columns == b.columns

    def run(batches):
        total = np.zeros((n, m))
        for batch in batches:
            columns = [c.fill_null(0.0).to_numpy(zero_copy_only=False) for c in batch.columns]
            x = np.stack(columns[:n], 1)
            total += x.T @ (x if same else np.stack(columns[n:], 1))
        i, j = np.nonzero(total)
        if len(i):
            yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(total[i, j])], ["i", "j", "v"])

    columns = [F.col(c).cast("double").alias(f"x{k}") for k, c in enumerate((*a.columns, *(() if same else b.columns)))]
    parts = a.df.select(*columns).mapInArrow(run, SCHEMA)
    return Coo(parts.groupBy("i", "j").agg(F.sum("v").alias("v")).filter("v <> 0"), n, m)


def to_numpy(a: Coo, max_cells: int = 1 << 24) -> np.ndarray:
    if a.rows * a.cols > max_cells:
        raise MemoryError(f"{a.rows} x {a.cols} cells are more than {max_cells}")
    out = np.zeros((a.rows, a.cols))
    t = a.df.select("i", "j", "v").toArrow()
    np.add.at(out, (t["i"].to_numpy(), t["j"].to_numpy()), t["v"].to_numpy())
    return out


def from_numpy(spark: SparkSession, x: np.ndarray) -> Coo:
    i, j = np.nonzero(x)
    t = pa.table({"i": i.astype(np.int64), "j": j.astype(np.int64), "v": x[i, j].astype(np.float64)})
    return Coo(spark.createDataFrame(t, schema=SCHEMA) if len(i) else spark.createDataFrame([], SCHEMA), *x.shape, len(i))
