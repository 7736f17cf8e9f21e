"""Iterative programs (powers, sums of powers, T <- A T + B) under the linear, exponential and skip models, and a view that
keeps one fresh by re-evaluation, by factored changes, by whole-matrix changes, or by the hybrid of both."""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from ..plans import cost
from ..plans.compile import compile_program
from ..plans.ir import Expr, Ident, Program, Ref, Stmt
from ..plans.rewrite import choose_aux
from . import backends
from .coo import Coo
from .inverse import Singular

STRATEGIES = ("reeval", "incr", "dense_delta", "hybrid")


def steps(k: int, model: str, s: int | None = None) -> list[tuple[int, int, int]]:
    """(i, a, b) for i after 1: the result of step i comes from those of a and b = i - a."""
    if k < 1:
        raise ValueError("at least one step")
    if model == "lin":
        return [(i, 1, i - 1) for i in range(2, k + 1)]
    top = k if model == "exp" else s
    if model not in ("exp", "skip") or not top or top & (top - 1) or k % top:
        raise ValueError("exponential steps need a power of two; skip one that divides the number of steps")
    out, i = [], 2
    while i <= top:
        out.append((i, i // 2, i // 2))
        i *= 2
    return out + [(i, top, i - top) for i in range(2 * top, k + 1, top)]


def _p(i: int) -> Ref:
    return Ref("A") if i == 1 else Ref(f"P{i}")


def powers_program(n: int, k: int, model: str = "exp", s: int | None = None) -> Program:
    return Program({"A": (n, n)}, tuple(Stmt(f"P{i}", _p(a) @ _p(b)) for i, a, b in steps(k, model, s)), (f"P{k}" if k > 1 else "A",), ("A",))


def sums_program(n: int, k: int, model: str = "exp", s: int | None = None) -> Program:
    """S_k = I + A + ... + A^(k-1)."""
    stmts, plan = [Stmt("S1", Ident(n))], steps(k, model, s)
    needed = {a for _, a, _ in plan}
    for i, a, b in plan:
        if model != "lin" and i in needed:
            stmts.append(Stmt(f"P{i}", _p(a) @ _p(b)))
        stmts.append(Stmt(f"S{i}", _p(a) @ Ref(f"S{b}") + Ref(f"S{a}")))
    return Program({"A": (n, n)}, tuple(stmts), (f"S{k}",), ("A",))


def general_program(n: int, p: int, k: int, model: str = "lin", s: int | None = None, with_b: bool = True, hybrid: bool = False) -> Program:
    """T_i = A T_(i-1) + B from T0."""
    t = lambda i: Ref(f"T{i}")
    b_of = (lambda e: e + Ref("B")) if with_b else (lambda e: e)
    stmts: list[Stmt] = [Stmt("T1", b_of(Ref("A") @ t(0)), hybrid)]
    plan = steps(k, model, s)
    needed = {a for _, a, _ in plan} if model != "lin" else set()
    if with_b and model != "lin":
        stmts.append(Stmt("S1", Ident(n)))
    for i, a, b in plan:
        if i in needed:
            stmts.append(Stmt(f"P{i}", _p(a) @ _p(b)))
            if with_b:
                stmts.append(Stmt(f"S{i}", _p(a) @ Ref(f"S{b}") + Ref(f"S{a}")))
        e: Expr = _p(a) @ t(b)
        if with_b:
            e = e + (Ref("B") if model == "lin" or a == 1 else Ref(f"S{a}") @ Ref("B"))
        stmts.append(Stmt(f"T{i}", e, hybrid))
    inputs = {"A": (n, n), "T0": (n, p)} | ({"B": (n, p)} if with_b else {})
    return Program(inputs, tuple(stmts), (f"T{k}",), tuple(inputs))


@dataclass(frozen=True)
class RefreshReport:
    ms: float
    ranks: dict[str, int]
    bytes: int
    version: int


class View:
    """A program's views, preloaded. ``apply`` brings them up to date after a change of an input."""

    def __init__(self, backend, program: Program, inputs: dict[str, Coo], strategy: str = "incr", merge: bool = True, stack: bool = True, chain: bool = False, aux: bool = False, lean: bool = False, factor: bool = False):
        """aux: products inside statements become views of their own first. chain, factor: see ``compile_program``. lean: a view that is
        re-evaluated holds only inputs and outputs between refreshes, since it needs no older step."""
        if strategy not in (*STRATEGIES, "auto"):
            raise ValueError(f"no strategy {strategy}")
        if strategy == "auto":
            strategy = cost.cheapest(program)
        program = choose_aux(program) if aux else program
        self.backend, self.program, self.strategy, self.merge, self.stack, self.chain, self.factor = backend, program, strategy, merge, stack, chain, factor
        self._triggers: dict = {}
        self.lean = lean and strategy == "reeval"
        self.fallbacks = 0  # refreshes that met a singular small system and computed the views anew
        given = {k: backend.load(v) for k, v in inputs.items()}
        for name, want in program.inputs.items():
            if backend.shape(given[name]) != tuple(want):
                raise ValueError(f"{name} is {backend.shape(given[name])}, declared {want}")
        self.env = backends.run_program(backend, program, given, lean=self.lean)
        self.version, self.ranks = 0, {}

    def apply(self, name: str | dict, left: Coo | None = None, right: Coo | None = None) -> RefreshReport:
        """One input's change left @ right.T, or {input: (left, right)} for several at once. Arrays are taken as the back end's thin
        factors."""
        changes = name if isinstance(name, dict) else {name: (left, right)}
        began, b = time.perf_counter(), self.backend
        ranks = {k: a.shape[1] if isinstance(a, np.ndarray) else a.cols for k, (a, _) in changes.items()}
        for k in ranks:
            if k not in self.program.dynamic:
                raise ValueError(f"{k} is static")
        thin = lambda x: x if isinstance(x, np.ndarray) else b.thin(x)
        factors = {k: (thin(a), thin(c)) for k, (a, c) in changes.items()}
        if self.strategy == "reeval":
            self._again(factors)
        else:
            trigger = self._trigger(ranks)
            try:
                self.env = backends.run_trigger(b, trigger, self.env, factors)
                self.ranks = trigger.ranks
            except Singular:  # the change has no inverse on the way, though the changed matrix may have one
                self.fallbacks += 1
                self._again(factors)
        self.version += 1
        return RefreshReport(1000 * (time.perf_counter() - began), dict(self.ranks), self.view_bytes(), self.version)

    def _trigger(self, ranks: dict[str, int]):
        """Compiled once for each combination of inputs and ranks."""
        key = tuple(sorted(ranks.items()))
        if key not in self._triggers:
            compiled = compile_program(self.program, ranks, self.merge, self.stack, self.strategy == "dense_delta", together=True, chain=self.chain, factor=self.factor)
            self._triggers[key] = next(iter(compiled.values()))
        return self._triggers[key]

    def _again(self, factors: dict[str, tuple]) -> None:
        """Re-evaluation: changed inputs, then every statement."""
        b, base = self.backend, {k: self.env[k] for k in self.program.inputs}
        for k, (left, right) in factors.items():
            base[k] = b.settle(b.add_outer(base[k], left, right))
        self.env = backends.run_program(b, self.program, base, lean=self.lean)

    def apply_full(self, name: str, change: Coo) -> RefreshReport:
        """A change without thin factors: added to the input, and everything after it computed again."""
        began, b = time.perf_counter(), self.backend
        self.restore({name: b.coo(b.add(self.env[name], b.load(change)))})
        return RefreshReport(1000 * (time.perf_counter() - began), {}, self.view_bytes(), self.version)

    def apply_batch(self, name: str, updates: DataFrame, most: float = 0.25) -> RefreshReport:
        """Cell changes (i, j, v): by factors while their rank is under that share of the smaller side, else as a full change."""
        from ..sources.updates import TooWide, compact, dense

        rows, cols = self.program.inputs[name]
        try:
            left, right, rank = compact(updates, rows, cols, max(1, int(min(most * min(rows, cols), 100_000))))
        except TooWide:
            return self.apply_full(name, dense(updates, rows, cols))
        return self.apply(name, left, right) if rank else RefreshReport(0.0, {}, self.view_bytes(), self.version)

    def restore(self, inputs: dict[str, Coo]) -> None:
        """Puts inputs in place of the present ones and computes all views again."""
        b = self.backend
        base = {k: b.load(inputs[k]) if k in inputs else self.env[k] for k in self.program.inputs}
        self.env = backends.run_program(b, self.program, base, lean=self.lean)
        self.version += 1

    def view_bytes(self, copies: int = 1) -> int:
        """Bytes of the matrices that the view holds between refreshes, as dense doubles."""
        return sum(8 * n * m * copies for name, (n, m) in self.program.shapes.items() if name in self.env)

    def frame(self, name: str | None = None) -> DataFrame:
        return backends.frame(self.backend, self.env[name or self.program.outputs[0]])

    def step(self, prefix: str, i: int) -> DataFrame:
        return self.frame("A" if prefix == "P" and i == 1 else f"{prefix}{i}")


def powers(backend, a: Coo, k: int, model: str = "exp", strategy: str = "incr", s: int | None = None, **how) -> View:
    return View(backend, powers_program(a.rows, k, model, s), {"A": a}, strategy, **how)


def power_sums(backend, a: Coo, k: int, model: str = "exp", strategy: str = "incr", s: int | None = None, **how) -> View:
    return View(backend, sums_program(a.rows, k, model, s), {"A": a}, strategy, **how)


def iterate(backend, a: Coo, b: Coo | None, t0: Coo, k: int, model: str = "lin", strategy: str = "hybrid", s: int | None = None, **how) -> View:
    program = general_program(a.rows, t0.cols, k, model, s, b is not None, strategy == "hybrid")
    return View(backend, program, {"A": a, "T0": t0} | ({"B": b} if b is not None else {}), strategy, **how)


def extend_steps(view: View, more: int) -> DataFrame:
    """T after ``more`` further steps from the last one, by re-evaluation."""
    b, env = view.backend, view.env
    t = env[view.program.outputs[0]]
    for _ in range(more):
        t = b.mul(env["A"], t)
        t = b.settle(b.add(t, env["B"]) if "B" in env else t)
    return backends.frame(b, t)
