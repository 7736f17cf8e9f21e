"""Matrix expressions, statements and programs. Expressions are immutable, compare by structure, and overload operators."""

from __future__ import annotations

from dataclasses import dataclass, field


class ShapeError(ValueError):
    """Operands that don't fit."""


@dataclass(frozen=True)
class Expr:
    def __add__(self, o: Expr) -> Expr:
        return Add(self, o)

    def __sub__(self, o: Expr) -> Expr:
        return Add(self, Scale(-1.0, o))

    def __matmul__(self, o: Expr) -> Expr:
        return MatMul(self, o)

    def __rmul__(self, c: float) -> Expr:
        return Scale(float(c), self)

    def __neg__(self) -> Expr:
        return Scale(-1.0, self)

    @property
    def T(self) -> Expr:  # noqa: N802
        return self.x if isinstance(self, Transpose) else Transpose(self)

    def inv(self) -> Expr:
        return Inv(self)


@dataclass(frozen=True)
class Ref(Expr):
    name: str


@dataclass(frozen=True)
class Ident(Expr):
    n: int


@dataclass(frozen=True)
class Add(Expr):
    x: Expr
    y: Expr


@dataclass(frozen=True)
class Scale(Expr):
    c: float
    x: Expr


@dataclass(frozen=True)
class MatMul(Expr):
    x: Expr
    y: Expr


@dataclass(frozen=True)
class Transpose(Expr):
    x: Expr


@dataclass(frozen=True)
class Inv(Expr):
    x: Expr


@dataclass(frozen=True)
class HStack(Expr):
    parts: tuple[Expr, ...]


Shapes = dict[str, tuple[int, int]]


def shape(e: Expr, known: Shapes) -> tuple[int, int]:
    match e:
        case Ref(name):
            if name not in known:
                raise ShapeError(f"unknown matrix {name}")
            return known[name]
        case Ident(n):
            return n, n
        case Add(x, y):
            a, b = shape(x, known), shape(y, known)
            if a != b:
                raise ShapeError(f"sum of {a} and {b}")
            return a
        case Scale(_, x):
            return shape(x, known)
        case MatMul(x, y):
            (n, k), (q, m) = shape(x, known), shape(y, known)
            if k != q:
                raise ShapeError(f"product of {(n, k)} and {(q, m)}")
            return n, m
        case Transpose(x):
            n, m = shape(x, known)
            return m, n
        case Inv(x):
            n, m = shape(x, known)
            if n != m:
                raise ShapeError(f"inverse of {(n, m)}")
            return n, m
        case HStack(parts):
            each = [shape(p, known) for p in parts]
            if len({n for n, _ in each}) != 1:
                raise ShapeError(f"columns of {each}")
            return each[0][0], sum(m for _, m in each)
    raise TypeError(e)


def refs(e: Expr) -> set[str]:
    match e:
        case Ref(name):
            return {name}
        case Ident(_):
            return set()
        case Add(x, y) | MatMul(x, y):
            return refs(x) | refs(y)
        case Scale(_, x) | Transpose(x) | Inv(x):
            return refs(x)
        case HStack(parts):
            return set().union(*map(refs, parts))
    raise TypeError(e)


@dataclass(frozen=True)
class Stmt:
    target: str
    expr: Expr
    dense: bool = False  # keep this view's change as one matrix rather than two thin factors


@dataclass(frozen=True)
class Program:
    """inputs: name -> (rows, cols); statements in order; outputs: names a user reads; dynamic: inputs that may change."""

    inputs: Shapes
    stmts: tuple[Stmt, ...]
    outputs: tuple[str, ...] = ()
    dynamic: tuple[str, ...] = ()
    shapes: Shapes = field(default_factory=dict)

    def __post_init__(self):
        known = dict(self.inputs)
        for name, (n, m) in known.items():
            if n < 0 or m < 0:
                raise ShapeError(f"{name} has shape {(n, m)}")
        for s in self.stmts:
            if s.target in known:
                raise ValueError(f"{s.target} is assigned twice")
            known[s.target] = shape(s.expr, known)
        for name in (*self.outputs, *self.dynamic):
            if name not in known:
                raise ShapeError(f"unknown matrix {name}")
        for name in self.dynamic:
            if name not in self.inputs:
                raise ValueError(f"{name} isn't an input")
        object.__setattr__(self, "shapes", known)
