"""Orders of time and space of the strategies, counted operations with constants, and the choice of a strategy."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .compile import Dense, Trigger, compile_program
from .ir import Add, Expr, HStack, Inv, MatMul, Program, Scale, Shapes, Transpose, shape
from .rewrite import chain_order

PROBLEMS, MODELS, STRATEGIES = ("powers", "sums", "general"), ("lin", "exp", "skip"), ("reeval", "incr", "hybrid")


def _check(model: str, k: int, s: int | None) -> None:
    if model not in MODELS:
        raise ValueError(f"no model {model}")
    if model == "exp" and k & (k - 1):
        raise ValueError("the exponential model takes powers of two")
    if model == "skip" and (not s or s & (s - 1) or k % s):
        raise ValueError("skip takes a power of two that divides k")


def time(problem: str, model: str, strategy: str, n: float, k: int, p: float = 1, s: int | None = None, gamma: float = 3.0, r: float = 1) -> float:
    """Order of the work of one refresh after a change of A of rank r."""
    _check(model, k, s)
    steps = {"lin": k, "exp": math.log2(k), "skip": math.log2(s or 1) + k / (s or 1)}[model]
    if problem in ("powers", "sums"):
        if strategy == "reeval":
            return n**gamma * steps
        if strategy == "incr":
            return r * n * n * {"lin": k * k, "exp": k, "skip": k * k / (s or 1)}[model]
    elif strategy == "reeval":
        return {"lin": p * n * n * k, "exp": (n**gamma + p * n * n) * steps, "skip": n**gamma * math.log2(s or 1) + p * n * n * steps}[model]
    elif strategy == "incr":
        return r * (n * n + n * p) * {"lin": k * k, "exp": k, "skip": k * k / (s or 1)}[model]
    elif strategy == "hybrid":
        return p * n * n * steps + {"lin": 0, "exp": r * n * n * k, "skip": r * n * n * (s or 1)}[model]
    raise ValueError(f"no {strategy} for {problem}")


def space(problem: str, model: str, strategy: str, n: float, k: int, p: float = 1, s: int | None = None) -> float:
    _check(model, k, s)
    steps = {"lin": k, "exp": math.log2(k), "skip": math.log2(s or 1) + k / (s or 1)}[model]
    if problem in ("powers", "sums"):
        return n * n if strategy == "reeval" else n * n * steps
    if strategy == "reeval":
        return n * n + n * p
    return {"lin": n * n + k * n * p, "exp": (n * n + n * p) * math.log2(k), "skip": (n * n + n * p) * math.log2(s or 1) + n * p * k / (s or 1)}[model]


def ols_time(strategy: str, n: float, m: float, p: float, gamma: float = 3.0) -> float:
    """Least squares of m rows, n columns and p responses: inverse and coefficients."""
    if strategy == "reeval":
        return n**gamma + m * n * n + m * n * p + n * n * min(m, p)
    return n * n + m * n + n * n + m * p + n * p + m * n


def expression_cost(e: Expr, known: Shapes, gamma: float = 3.0) -> float:
    """Multiplications and additions of e in its best order: products by shape, square ones of one size by n**gamma, inverses so too."""
    match e:
        case MatMul(x, y):
            (n, k), (_, m) = shape(x, known), shape(y, known)
            own = float(n) ** gamma if n == k == m else float(n) * k * m
            return expression_cost(x, known, gamma) + expression_cost(y, known, gamma) + own
        case Add(x, y):
            n, m = shape(x, known)
            return expression_cost(x, known, gamma) + expression_cost(y, known, gamma) + float(n) * m
        case Scale(_, x) | Transpose(x):
            return expression_cost(x, known, gamma)
        case Inv(x):
            return expression_cost(x, known, gamma) + float(shape(x, known)[0]) ** gamma
        case HStack(parts):
            return sum(expression_cost(p, known, gamma) for p in parts)
    return 0.0


def reevaluation_cost(program: Program, gamma: float = 3.0) -> float:
    return sum(expression_cost(chain_order(s.expr, program.shapes), program.shapes, gamma) for s in program.stmts)


def trigger_cost(program: Program, trigger: Trigger, ranks: dict[str, int], gamma: float = 3.0) -> float:
    """The trigger's factors and the additions of its changes to the views."""
    known = dict(program.shapes)
    for name in trigger.inputs:
        rows, cols = program.inputs[name]
        known |= {f"d{name}.L": (rows, ranks[name]), f"d{name}.R": (cols, ranks[name])}
    total = 0.0
    for target, e in trigger.assigns:
        known[target] = shape(e, known)
        total += expression_cost(e, known, gamma)
    for view, change in trigger.updates.items():
        n, m = program.shapes[view]
        total += float(n) * m * (1 if isinstance(change, Dense) else sum(shape(a, known)[1] for a, _ in change))
    return total


def program_cost(program: Program, ranks: dict[str, int] | None = None, gamma: float = 3.0) -> dict[str, float]:
    """Cost of each input's trigger, and their sum under ``total``: what one change of every dynamic input costs."""
    ranks = ranks or dict.fromkeys(program.dynamic, 1)
    out = {n: trigger_cost(program, t, ranks, gamma) for n, t in compile_program(program, ranks).items()}
    return out | {"total": sum(out.values())}


def cheapest(program: Program, ranks: dict[str, int] | None = None, gamma: float = 3.0) -> str:
    """Between re-evaluation and incremental by the cost of one change of every dynamic input."""
    ranks = ranks or dict.fromkeys(program.dynamic, 1)
    return "incr" if program_cost(program, ranks, gamma)["total"] < len(ranks) * reevaluation_cost(program, gamma) else "reeval"


def memory_matrices(strategy: str, k: int = 16) -> int:
    """n x n matrices held for A^k by squarings: three when re-evaluating, else every view in two layouts."""
    return 3 if strategy == "reeval" else 2 * (int(math.log2(k)) + 1)


def flops(problem: str, model: str, strategy: str, n: float, k: int, p: float = 1, s: int | None = None, r: float = 1) -> float:
    """Multiplications and additions with constants; agrees with ``time`` in order."""
    if strategy == "incr" and model == "exp" and problem == "powers":
        return 8 * n * n * k * r
    return 2 * time(problem, model, strategy, n, k, p, s, 3.0, r)


@dataclass(frozen=True)
class Choice:
    strategy: str
    model: str
    s: int | None
    cost: float
    why: str


def choose(problem: str, n: float, k: int, p: float = 1, gamma: float = 3.0, r: float = 1, memory: float = math.inf, job: float = 0.0, flop: float = 1.0, byte: float = 0.0) -> Choice:
    """Least flop * work + byte * moved + job * steps among the models and strategies whose space fits in memory (in cells)."""
    best = None
    for strategy in STRATEGIES:
        if strategy == "hybrid" and problem != "general":
            continue
        for model in MODELS:
            if model == "exp" and k & (k - 1):
                continue
            for s in [2**e for e in range(1, int(math.log2(k)) + 1) if k % 2**e == 0] if model == "skip" else [None]:
                if space(problem, model, strategy, n, k, p, s) > memory:
                    continue
                rank = n if strategy == "reeval" else min(n, r * k)
                steps = {"lin": k, "exp": math.log2(max(k, 1)), "skip": math.log2(s or 1) + k / (s or 1)}[model]
                work = time(problem, model, strategy, n, k, p, s, gamma, r)
                cost = flop * work + byte * 8 * n * (p if strategy == "hybrid" else rank) * steps + job * steps
                if best is None or cost < best.cost:
                    best = Choice(strategy, model, s, cost, f"{strategy} {model}{s or ''}: {work:.3g} operations in {steps:g} steps")
    if best is None:
        raise MemoryError("no strategy fits")
    return best


def table(spark: SparkSession, n: float, k: int, p: float, s: int, gamma: float = 3.0) -> DataFrame:
    """Every cell of time and space."""
    rows = []
    for problem in PROBLEMS:
        for strategy in STRATEGIES:
            for model in MODELS:
                if strategy == "hybrid" and problem != "general":
                    continue
                q = s if model == "skip" else None
                rows.append((problem, model, strategy, float(time(problem, model, strategy, n, k, p, q, gamma)), float(space(problem, model, strategy, n, k, p, q))))
    return spark.createDataFrame(rows, "problem string, model string, strategy string, time double, space double")
