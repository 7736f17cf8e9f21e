"""One interface over NumPy on the driver (small), COO plans, and block panels. Programs run on any of them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..plans.compile import Trigger
from ..plans.ir import Add, Expr, HStack, Ident, Inv, MatMul, Program, Ref, Scale, Transpose, refs
from . import block, coo

LOCAL_CELLS = 4096 * 4096


class Local:
    """Arrays on the driver, for matrices of at most LOCAL_CELLS cells."""

    def __init__(self, spark: SparkSession | None = None):
        self.spark = spark

    def load(self, m: coo.Coo) -> np.ndarray:
        return coo.to_numpy(m, LOCAL_CELLS)

    thin = load

    def coo(self, x: np.ndarray) -> coo.Coo:
        return coo.from_numpy(self.spark, x)

    def shape(self, x):
        return x.shape

    def mul(self, x, y):
        return x @ y

    def tmul(self, x, y):
        return x.T @ y

    def transpose(self, x):
        return x.T

    def add(self, x, y):
        return x + y

    def scale(self, c, x):
        return c * x

    def eye(self, n):
        return np.eye(n)

    def inv(self, x):
        from .inverse import checked

        return checked(x)

    def hstack(self, parts):
        return np.concatenate(parts, axis=1)

    def add_outer(self, m, left, right):
        return m + left @ right.T

    def settle(self, x):
        return x


class CooBackend:
    """Every matrix and factor is a COO frame; settled ones are checkpointed."""

    def __init__(self, spark: SparkSession):
        self.spark = spark

    def load(self, m: coo.Coo) -> coo.Coo:
        return m if m.tall is not None else coo.settle(m)

    def thin(self, m: coo.Coo) -> coo.Coo:
        return coo.settle(m)

    def coo(self, x: coo.Coo) -> coo.Coo:
        return x

    def shape(self, x):
        return x.rows, x.cols

    def mul(self, x, y):
        return coo.mul(x, y)

    def tmul(self, x, y):
        return coo.tmul(x, y)

    def transpose(self, x):
        return coo.transpose(x)

    def add(self, x, y):
        return coo.add(x, y)

    def scale(self, c, x):
        return coo.scale(c, x)

    def eye(self, n):
        return coo.identity(self.spark, n)

    def inv(self, x):
        from .inverse import invert

        return invert(x)

    def hstack(self, parts):
        return coo.hstack(parts)

    def add_outer(self, m, left, right):
        return coo.add_outer(m, left, right)

    def settle(self, x):
        return coo.settle(x)


class IntegerBackend(CooBackend):
    """COO frames of whole numbers, exact up to 38 digits (doubles are up to 2^53, about 16). Programs without inverses."""

    def load(self, m: coo.Coo) -> coo.Coo:
        return coo.settle(coo.integers(m))

    thin = load

    def eye(self, n):
        return coo.integers(coo.identity(self.spark, n))

    def scale(self, c, x):
        if c != int(c):
            raise ValueError(f"{c} is not a whole number")
        return coo.Coo(x.df.withColumn("v", (coo.F.col("v") * coo.F.lit(int(c)).cast(coo.WHOLE)).cast(coo.WHOLE)).filter("v <> 0"), x.rows, x.cols)


class BlockBackend:
    """Large matrices in panels, thin ones (at most ``thin_cols`` columns, within the size limit) as arrays on the driver."""

    def __init__(self, spark: SparkSession, dual: bool = True, grid: int | None = 2, thin_cols: int = 4096):
        self.spark, self.dual, self.grid, self.thin_cols = spark, dual, grid, thin_cols

    def load(self, m: coo.Coo):
        return block.from_coo(m, self.dual)

    def thin(self, m: coo.Coo) -> np.ndarray:
        return coo.to_numpy(m, block.LIMIT_BYTES // 8)

    def coo(self, x) -> coo.Coo:
        return coo.from_numpy(self.spark, x) if isinstance(x, np.ndarray) else block.to_coo(x)

    def shape(self, x):
        return x.shape if isinstance(x, np.ndarray) else (x.rows, x.cols)

    def _panels(self, x):
        return self.load(coo.from_numpy(self.spark, x)) if isinstance(x, np.ndarray) else x

    def mul(self, x, y):
        if isinstance(x, np.ndarray) and isinstance(y, np.ndarray):
            return x @ y
        if isinstance(y, np.ndarray):
            return block.mul_thin(x, y)
        if isinstance(x, np.ndarray):
            return block.tmul_thin(y, x.T).T
        return block.matmul_grid(x, y, self.grid, self.dual)

    def tmul(self, x, y):
        if isinstance(x, np.ndarray) and isinstance(y, np.ndarray):
            return x.T @ y
        if isinstance(y, np.ndarray):
            return block.tmul_thin(x, y)
        return self.mul(self.transpose(x), y)

    def transpose(self, x):
        return x.T if isinstance(x, np.ndarray) else block.transpose(x)

    def add(self, x, y):
        if isinstance(x, np.ndarray) and isinstance(y, np.ndarray):
            return x + y
        return block.combine(self._panels(x), self._panels(y))

    def scale(self, c, x):
        return c * x if isinstance(x, np.ndarray) else block.scaled(c, x)

    def eye(self, n):
        return np.eye(n) if n <= 64 else block.identity(self.spark, n)

    def inv(self, x):
        from .inverse import checked, invert

        if isinstance(x, np.ndarray):
            return checked(x)

        return self.load(invert(block.to_coo(x)))

    def hstack(self, parts):
        return np.hstack([p if isinstance(p, np.ndarray) else coo.to_numpy(block.to_coo(p)) for p in parts])

    def add_outer(self, m, left, right):
        return m + left @ right.T if isinstance(m, np.ndarray) else block.add_outer(m, left, right)

    def settle(self, x):
        return x


def backend(spark: SparkSession, name: str):
    return {"local": Local, "coo": CooBackend, "block": BlockBackend}[name](spark)


def evaluate(b, e: Expr, env: dict, memo: dict | None = None):
    memo = {} if memo is None else memo
    if e in memo:
        return memo[e]
    match e:
        case Ref(name):
            return env[name]
        case Ident(n):
            out = b.eye(n)
        case Add(x, y):
            out = b.add(evaluate(b, x, env, memo), evaluate(b, y, env, memo))
        case Scale(c, x):
            out = b.scale(c, evaluate(b, x, env, memo))
        case MatMul(Transpose(x), y):
            out = b.tmul(evaluate(b, x, env, memo), evaluate(b, y, env, memo))
        case MatMul(x, y):
            out = b.mul(evaluate(b, x, env, memo), evaluate(b, y, env, memo))
        case Transpose(x):
            out = b.transpose(evaluate(b, x, env, memo))
        case Inv(x):
            out = b.inv(evaluate(b, x, env, memo))
        case HStack(parts):
            out = b.hstack([evaluate(b, p, env, memo) for p in parts])
        case _:
            raise TypeError(e)
    memo[e] = out
    return out


def run_program(b, program: Program, env: dict, lean: bool = False) -> dict:
    """env with all views, computed in order (re-evaluation). Each view is settled, so plans stay short. lean: only inputs and
    outputs stay; a matrix between them goes after its last use, as re-evaluation needs no older step."""
    env = dict(env)
    last = {name: k for k, s in enumerate(program.stmts) for name in refs(s.expr)}
    for k, s in enumerate(program.stmts):
        env[s.target] = b.settle(evaluate(b, s.expr, env))
        if lean:
            for name in [n for n in env if last.get(n, -1) <= k and n not in program.inputs and n not in program.outputs and n in program.shapes]:
                del env[name]
    return env


def run_trigger(b, trigger: Trigger, env: dict, factors: dict[str, tuple]) -> dict:
    """New views after changes (input -> (L, R)). All factors are computed from old values before any view is changed; the
    old env stays as it was, so a failure on the way leaves it whole."""
    work: dict = dict(env)
    for name, (left, right) in factors.items():
        work[f"d{name}.L"], work[f"d{name}.R"] = left, right
    steps, views = trigger.steps
    for op, constant, operands, result in steps:
        got = [work[k] for k in operands]
        if op == "hstack":
            work[result] = b.hstack(got)
        elif constant is not None:
            work[result] = getattr(b, op)(constant, *got)
        else:
            work[result] = getattr(b, op)(*got)
    new = dict(env)
    for view, change in views.items():
        if isinstance(change, tuple):
            out = env[view]
            for left, right in change:
                out = b.add_outer(out, work[left], work[right])
        else:
            out = b.add(env[view], work[change])
        new[view] = b.settle(out)
    return new


def frame(b, x) -> DataFrame:
    return b.coo(x).df.select("i", "j", "v")
