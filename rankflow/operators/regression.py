"""Least squares and gradient descent as programs over X and Y, and other applications of the iterative forms."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..plans.ir import Ident, Program, Ref, Scale, Stmt
from . import coo
from .coo import Coo
from .models import View, general_program

TALL = 1 << 50  # hashes of nodes are numbers under it


def ols_program(m: int, n: int, p: int, ridge: float = 0.0) -> Program:
    """Z = X'X (+ ridge), W = inverse, C = X'Y kept as a view of its own, beta = W C."""
    x, y = Ref("X"), Ref("Y")
    z = x.T @ x
    return Program({"X": (m, n), "Y": (m, p)}, (Stmt("Z", z + Scale(ridge, Ident(n)) if ridge else z), Stmt("W", Ref("Z").inv()), Stmt("C", x.T @ y), Stmt("beta", Ref("W") @ Ref("C"))), ("beta",), ("X", "Y"))


def ols(backend, x: Coo, y: Coo, strategy: str = "incr", ridge: float = 0.0, **how) -> View:
    return View(backend, ols_program(x.rows, x.cols, y.cols, ridge), {"X": x, "Y": y}, strategy, **how)


def append(view: View, row: int, x: Coo, y: Coo) -> None:
    """A new observation: row ``row`` of X and Y, zero so far, becomes x' and y' (one column each). Both change at once."""
    left = Coo(x.df.sparkSession.createDataFrame([(row, 0, 1.0)], coo.SCHEMA), view.program.inputs["X"][0], 1, 1)
    view.apply({"X": (left, x), "Y": (left, y)})


def gd_program(m: int, n: int, p: int, k: int, eta: float, model: str = "lin", s: int | None = None, hybrid: bool = False) -> Program:
    """T <- T - eta X'(X T - Y): A = I - eta X'X, B = eta X'Y in front of the general form."""
    g = general_program(n, p, k, model, s, True, hybrid)
    x, y = Ref("X"), Ref("Y")
    first = (Stmt("A", Ident(n) - Scale(eta, x.T @ x)), Stmt("B", Scale(eta, x.T @ y)))
    return Program({"X": (m, n), "Y": (m, p), "T0": (n, p)}, first + g.stmts, g.outputs, ("X", "Y"))


def gd_regression(backend, x: Coo, y: Coo, k: int, eta: float, model: str = "lin", strategy: str = "hybrid", s: int | None = None) -> View:
    spark = x.df.sparkSession
    t0 = Coo(spark.createDataFrame([], coo.SCHEMA), x.cols, y.cols)
    return View(backend, gd_program(x.rows, x.cols, y.cols, k, eta, model, s, strategy == "hybrid"), {"X": x, "Y": y, "T0": t0}, strategy)


def pagerank(backend, edges: Coo, k: int, damping: float = 0.85, strategy: str = "hybrid") -> View:
    """edges: cell (i, j) for a link from j to i. Mass of dangling nodes is not spread; T0 and B are uniform."""
    from .models import iterate

    n, spark = edges.rows, edges.df.sparkSession
    q = coo.col_normalize(Coo(edges.df.select("i", "j", F.lit(1.0).alias("v")).distinct(), n, n))

    def uniform(v: float) -> Coo:
        return Coo(spark.range(n).select(F.col("id").alias("i"), F.lit(0).cast("long").alias("j"), F.lit(v).alias("v")), n, 1)

    return iterate(backend, coo.scale(damping, q), uniform((1 - damping) / n), uniform(1.0 / n), k, "lin", strategy)


def pagerank_graph(backend, edges, k: int, damping: float = 0.85, strategy: str = "hybrid"):
    """(node, rank) for links (src, dst) between nodes of any type. Nodes are numbered by a hash, so no sort of them is needed;
    two nodes of one hash are an error. A node without links out keeps its mass to itself, as in ``pagerank``."""
    from .models import iterate

    edges = coo.cut(edges.select("src", "dst").filter("src is not null and dst is not null").distinct())
    number = lambda c: F.pmod(F.xxhash64(c), F.lit(TALL))
    nodes = coo.cut(edges.select(F.col("src").alias("node")).union(edges.select("dst")).distinct().withColumn("i", number("node")))
    n, numbers = nodes.agg(F.count("*"), F.count_distinct("i")).first()
    if n != numbers:
        raise ValueError("two nodes have one hash")
    out = edges.groupBy("src").agg(F.count("*").alias("d"))
    links = edges.join(out, "src").select(number("dst").alias("i"), number("src").alias("j"), (F.lit(damping) / F.col("d")).alias("v"))
    column = lambda v: Coo(nodes.select("i", F.lit(0).cast("long").alias("j"), F.lit(v).alias("v")), TALL, 1, n)
    if not n:
        return nodes.select("node", F.lit(0.0).alias("rank"))
    a = Coo(coo.cut(links), TALL, TALL, edges.count())
    view = iterate(backend, a, column((1 - damping) / n), column(1.0 / n), k, "lin", strategy)
    return nodes.join(view.frame(), "i", "left").select("node", F.coalesce("v", F.lit(0.0)).alias("rank"))


def markov(backend, q: Coo, k: int, strategy: str = "incr") -> View:
    from .models import powers

    return powers(backend, q, k, "exp", strategy)


def reach(backend, edges: Coo, k: int, strategy: str = "incr") -> View:
    """Sums of powers; a cell over 0 means reachable in under k hops."""
    from .models import power_sums

    return power_sums(backend, edges, k, "exp" if not k & (k - 1) else "lin", strategy)


def expm_program(n: int, k: int) -> Program:
    """Truncated series of the matrix exponential: E_k = sum of A^i / i! for i to k."""
    stmts = [Stmt("M1", Ref("A")), Stmt("E1", Ident(n) + Ref("A"))]
    for i in range(2, k + 1):
        stmts += [Stmt(f"M{i}", Scale(1.0 / i, Ref("A") @ Ref(f"M{i - 1}"))), Stmt(f"E{i}", Ref(f"E{i - 1}") + Ref(f"M{i}"))]
    return Program({"A": (n, n)}, tuple(stmts), (f"E{k}",), ("A",))


def expm_series(backend, a: Coo, k: int, strategy: str = "incr") -> View:
    return View(backend, expm_program(a.rows, k), {"A": a}, strategy)


def jacobi(backend, m: Coo, b: Coo, k: int, strategy: str = "hybrid") -> View:
    """x <- D^-1 (b - (M - D) x), from 0."""
    from .models import iterate

    d = coo.diag(m).df.select("i", (1.0 / F.col("v")).alias("w"))
    a = Coo(m.df.filter("i <> j").join(d, "i").select("i", "j", (-F.col("v") * F.col("w")).alias("v")), m.rows, m.cols)
    rhs = Coo(b.df.join(d, "i").select("i", "j", (F.col("v") * F.col("w")).alias("v")), b.rows, b.cols)
    t0 = Coo(b.df.sparkSession.createDataFrame([], coo.SCHEMA), b.rows, b.cols)
    return iterate(backend, a, rhs, t0, k, "lin", strategy)


def power_iteration(backend, a: Coo, k: int, strategy: str = "hybrid") -> View:
    """A^k times ones; scale at the end. The ratio of two steps nears the dominant eigenvalue."""
    from .models import iterate

    ones = Coo(a.df.sparkSession.range(a.rows).select(F.col("id").alias("i"), F.lit(0).cast("long").alias("j"), F.lit(1.0).alias("v")), a.rows, 1)
    return iterate(backend, a, None, ones, k, "lin", strategy)
