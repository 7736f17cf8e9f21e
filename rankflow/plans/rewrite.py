"""Rewrites on expressions: sums of monomials, order of product chains by shape, shared subexpressions, copies."""

from __future__ import annotations

from .ir import Add, Expr, HStack, Ident, Inv, MatMul, Program, Ref, Scale, Shapes, Stmt, Transpose, refs, shape


def rebuild(e: Expr, f) -> Expr:
    """e with f applied to its operands."""
    match e:
        case Add(x, y):
            return Add(f(x), f(y))
        case MatMul(x, y):
            return MatMul(f(x), f(y))
        case Scale(c, x):
            return Scale(c, f(x))
        case Transpose(x):
            return Transpose(f(x))
        case Inv(x):
            return Inv(f(x))
        case HStack(parts):
            return HStack(tuple(map(f, parts)))
    return e


def monomials(e: Expr) -> list[tuple[float, tuple[Expr, ...]]]:
    """e as a sum of (coefficient, factors); transposes are pushed to the factors."""
    match e:
        case Add(x, y):
            return monomials(x) + monomials(y)
        case Scale(c, x):
            return [(c * k, fs) for k, fs in monomials(x)]
        case MatMul(x, y):
            return [(a * b, (*f, *g)) for a, f in monomials(x) for b, g in monomials(y)]
        case Transpose(x) if isinstance(x, (Add, Scale, MatMul, Transpose)):
            return [(k, tuple(g.T for g in reversed(fs))) for k, fs in monomials(x)]
    return [(1.0, (e,))]


def expand(e: Expr) -> Expr:
    """Sum of monomials, equal ones gathered."""
    total: dict[tuple[Expr, ...], float] = {}
    for c, fs in monomials(e):
        fs = tuple(f for f in fs if not isinstance(f, Ident)) or fs[:1]
        total[fs] = total.get(fs, 0.0) + c
    terms = []
    for fs, c in total.items():
        m = fs[0]
        for g in fs[1:]:
            m = m @ g
        if c:
            terms.append(m if c == 1.0 else Scale(c, m))
    if not terms:
        return Scale(0.0, e)
    out = terms[0]
    for t in terms[1:]:
        out = out + t
    return out


def _factors(e: Expr) -> list[Expr]:
    return _factors(e.x) + _factors(e.y) if isinstance(e, MatMul) else [e]


def chain_order(e: Expr, known: Shapes) -> Expr:
    """Every product chain in the association of least multiplications, which keeps thin operands thin."""
    fs = [rebuild(f, lambda x: chain_order(x, known)) for f in _factors(e)]
    if len(fs) == 1:
        return fs[0]
    d = [shape(fs[0], known)[0], *(shape(f, known)[1] for f in fs)]
    best: dict[tuple[int, int], tuple[float, int]] = {(k, k): (0.0, k) for k in range(len(fs))}
    for span in range(1, len(fs)):
        for a in range(len(fs) - span):
            b = a + span
            best[a, b] = min((best[a, c][0] + best[c + 1, b][0] + float(d[a]) * d[c + 1] * d[b + 1], c) for c in range(a, b))

    def build(a: int, b: int) -> Expr:
        return fs[a] if a == b else MatMul(build(a, best[a, b][1]), build(best[a, b][1] + 1, b))

    return build(0, len(fs) - 1)


def chain_cost(e: Expr, known: Shapes) -> float:
    """Multiplications of e as written."""
    match e:
        case MatMul(x, y):
            (n, k), (_, m) = shape(x, known), shape(y, known)
            return chain_cost(x, known) + chain_cost(y, known) + float(n) * k * m
        case Add(x, y):
            return chain_cost(x, known) + chain_cost(y, known)
        case Scale(_, x) | Transpose(x) | Inv(x):
            return chain_cost(x, known)
        case HStack(parts):
            return sum(chain_cost(p, known) for p in parts)
    return 0.0


def cse(stmts: list[tuple[str, Expr]], least: int = 2) -> list[tuple[str, Expr]]:
    """Products that occur at least so often become assignments of their own, before their first use."""
    count: dict[Expr, int] = {}

    def visit(e: Expr) -> None:
        if isinstance(e, (MatMul, Inv)):
            count[e] = count.get(e, 0) + 1
            if count[e] > 1:
                return
        rebuild(e, lambda x: visit(x) or x)

    for _, e in stmts:
        visit(e)
    names: dict[Expr, str] = {}
    out: list[tuple[str, Expr]] = []

    def use(e: Expr) -> Expr:
        if count.get(e, 0) >= least and isinstance(e, (MatMul, Inv)):
            if e not in names:
                inner = rebuild(e, use)
                names[e] = f"_t{len(names)}"
                out.append((names[e], inner))
            return Ref(names[e])
        return rebuild(e, use)

    for target, e in stmts:
        e = use(e)
        out.append((target, e))
    return out


def copy_prop(stmts: list[tuple[str, Expr]], keep: set[str]) -> list[tuple[str, Expr]]:
    """Assignments that only rename are dropped and their uses renamed, except for names in keep."""
    name: dict[str, Expr] = {}
    out = []

    def use(e: Expr) -> Expr:
        return name.get(e.name, e) if isinstance(e, Ref) else rebuild(e, use)

    for target, e in stmts:
        e = use(e)
        if isinstance(e, Ref) and target not in keep:
            name[target] = e
        else:
            out.append((target, e))
    return out


def choose_aux(program: Program) -> Program:
    """Products and inverses that a statement reads more than once, or inside an inverse, become views of their own."""
    stmts: list[Stmt] = []
    taken = set(program.shapes)
    for s in program.stmts:
        count = 0

        def lift(e: Expr, top: bool, s=s) -> Expr:
            nonlocal count
            e = rebuild(e, lambda x: lift(x, False))
            if not top and isinstance(e, (MatMul, Inv)) and len(refs(e)):
                for t in stmts:
                    if t.expr == e:
                        return Ref(t.target)
                name = f"{s.target}_{count}"
                while name in taken:
                    count += 1
                    name = f"{s.target}_{count}"
                taken.add(name)
                stmts.append(Stmt(name, e))
                return Ref(name)
            return e

        stmts.append(Stmt(s.target, lift(s.expr, True), s.dense))
    return Program(program.inputs, tuple(stmts), program.outputs, program.dynamic)
