"""Derivation of changes and compilation of one trigger for each input that may change.

A change is a tuple of blocks (L, R), standing for the sum of L @ R.T, or one matrix (``Dense``) where a view's change is
wanted whole. Rules keep products thin: a factor only ever meets a matrix as matrix @ factor.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from .ir import Add, Expr, HStack, Ident, Inv, MatMul, Program, Ref, Scale, Shapes, Transpose, refs, shape
from .rewrite import chain_order, copy_prop, cse, expand


@dataclass(frozen=True)
class Dense:
    expr: Expr


Blocks = tuple[tuple[Expr, Expr], ...]
Change = Blocks | Dense


def merge_common(blocks: Blocks) -> Blocks:
    """Blocks of one right factor become one (left factors added), then blocks of one left factor. By form, not by value."""
    for same, other in ((1, 0), (0, 1)):
        found: dict[Expr, Expr] = {}
        for b in blocks:
            found[b[same]] = found[b[same]] + b[other] if b[same] in found else b[other]
        blocks = tuple((o, s) if same else (s, o) for s, o in found.items())
    return blocks


def dense_of(change: Change) -> Expr | None:
    if isinstance(change, Dense):
        return change.expr
    out = None
    for left, right in change:
        term = left @ right.T
        out = term if out is None else out + term
    return out


def change_of(e: Expr, changes: dict[str, Change], merge: bool = True, view: Expr | None = None, widths: Shapes | None = None) -> Change:
    """Change of e when the named matrices change at once. view: the stored value of e, which the rule for inverses needs; with
    widths (shapes of all names) it takes the blocks of the change one after another, else all at once."""
    if not refs(e) & changes.keys():
        return ()
    match e:
        case Ref(name):
            return changes[name]
        case Scale(c, x):
            d = change_of(x, changes, merge)
            return Dense(Scale(c, d.expr)) if isinstance(d, Dense) else tuple((Scale(c, a), b) for a, b in d)
        case Transpose(x):
            d = change_of(x, changes, merge)
            return Dense(d.expr.T) if isinstance(d, Dense) else tuple((b, a) for a, b in d)
        case Add(x, y):
            p, q = change_of(x, changes, merge), change_of(y, changes, merge)
            if isinstance(p, Dense) or isinstance(q, Dense):
                p, q = dense_of(p), dense_of(q)
                return Dense(p if q is None else q if p is None else p + q)
            return merge_common(p + q) if merge else p + q
        case MatMul(x, y):
            p, q = change_of(x, changes, merge), change_of(y, changes, merge)
            if isinstance(p, Dense) or isinstance(q, Dense):
                return _dense_product(x, y, p, q)
            if not merge:
                cross = tuple((a @ (b.T @ u), v) for u, v in q for a, b in p)
                return tuple((a, y.T @ b) for a, b in p) + tuple((x @ u, v) for u, v in q) + cross
            out = []
            for u, v in q:
                left = x @ u
                for a, b in p:
                    left = left + a @ (b.T @ u)
                out.append((left, v))
            return merge_common(tuple((a, y.T @ b) for a, b in p) + tuple(out))
        case Inv(x):
            d = change_of(x, changes, merge)
            if view is None or isinstance(d, Dense):
                raise ValueError("an inverse must be a view of its own, and its matrix change by thin factors")
            out: Blocks = ()
            for left, right in d if widths is not None else (_stacked(d),):
                seen, back = view @ left, view.T @ right
                for a, b in out:  # the inverse as the blocks before have left it
                    seen, back = seen + a @ (b.T @ left), back + b @ (a.T @ right)
                eye = Ident(-1 if widths is None else shape(right, widths)[1])
                out += ((-(seen @ Inv(eye + right.T @ seen)), back),)
            return out
        case HStack(parts):
            raise ValueError(f"no rule for columns side by side: {len(parts)}")
    raise TypeError(e)


def _dense_product(x: Expr, y: Expr, p: Change, q: Change) -> Dense:
    terms = []
    if isinstance(q, Dense):
        terms.append(x @ q.expr)
    elif q:
        terms += [(x @ u) @ v.T for u, v in q]
    if isinstance(p, Dense):
        terms.append(p.expr @ y)
        if q:
            terms.append(p.expr @ dense_of(q))
    else:
        for a, b in p:
            terms.append(a @ (b.T @ y))
            if isinstance(q, Dense):
                terms.append(a @ (b.T @ q.expr))
            else:
                terms += [(a @ (b.T @ u)) @ v.T for u, v in q]
    out = terms[0]
    for t in terms[1:]:
        out = out + t
    return Dense(out)


def _stacked(blocks: Blocks) -> tuple[Expr, Expr]:
    if len(blocks) == 1:
        return blocks[0]
    return HStack(tuple(a for a, _ in blocks)), HStack(tuple(b for _, b in blocks))


@dataclass(frozen=True)
class Trigger:
    """assigns: factors, computed from old values in order; updates: view -> its change, added once all are known."""

    inputs: tuple[str, ...]
    assigns: tuple[tuple[str, Expr], ...]
    updates: dict[str, Change] = field(default_factory=dict)
    ranks: dict[str, int] = field(default_factory=dict)
    blocks: dict[str, int] = field(default_factory=dict)

    @cached_property
    def steps(self) -> tuple[list[tuple], dict]:
        """(operations, views): each expression once, as (operation, constant, operands, result), in order; and each view's change by
        its operands. Names are matrices, numbers are results on the way."""
        out: list[tuple] = []
        seen: dict[Expr, int] = {}

        def put(e: Expr) -> str | int:
            if isinstance(e, Ref):
                return e.name
            if e not in seen:
                match e:
                    case Ident(n):
                        op = ("eye", n, ())
                    case Add(x, y):
                        op = ("add", None, (put(x), put(y)))
                    case Scale(c, x):
                        op = ("scale", c, (put(x),))
                    case MatMul(Transpose(x), y):
                        op = ("tmul", None, (put(x), put(y)))
                    case MatMul(x, y):
                        op = ("mul", None, (put(x), put(y)))
                    case Transpose(x):
                        op = ("transpose", None, (put(x),))
                    case Inv(x):
                        op = ("inv", None, (put(x),))
                    case HStack(parts):
                        op = ("hstack", None, tuple(put(p) for p in parts))
                    case _:
                        raise TypeError(e)
                seen[e] = len(seen)
                out.append((*op, seen[e]))
            return seen[e]

        for target, e in self.assigns:
            out.append(("settle", None, (put(e),), target))
        return out, {v: put(c.expr) if isinstance(c, Dense) else tuple((put(a), put(b)) for a, b in c) for v, c in self.updates.items()}

    def explain(self) -> str:
        return "\n".join([f"on {', '.join(self.inputs)}:", *(f"  {t} := {text(e)}" for t, e in self.assigns), *(f"  {v} += {' + '.join(f'{text(a)} {text(b)}^T' for a, b in c) if not isinstance(c, Dense) else text(c.expr)}" for v, c in self.updates.items())])


def text(e: Expr) -> str:
    match e:
        case Ref(name):
            return name
        case Ident(n):
            return f"eye({n})" if n >= 0 else "eye"
        case Add(x, y):
            return f"({text(x)} + {text(y)})"
        case Scale(c, x):
            return f"{c:g} * {text(x)}"
        case MatMul(x, y):
            return f"({text(x)} @ {text(y)})"
        case Transpose(x):
            return f"{text(x)}'"
        case Inv(x):
            return f"inv({text(x)})"
        case HStack(parts):
            return f"[{', '.join(map(text, parts))}]"
    raise TypeError(e)


def _sized(e: Expr, n: int) -> Expr:
    from .rewrite import rebuild

    return Ident(n) if isinstance(e, Ident) and e.n < 0 else rebuild(e, lambda x: _sized(x, n))


def compile_program(program: Program, ranks: dict[str, int], merge: bool = True, stack: bool = True, dense: bool = False, together: bool = False, chain: bool = False, factor: bool = False) -> dict[str, Trigger]:
    """A trigger for each input in ranks (name -> rank of its change), or one for all of them if together.

    merge: gather blocks with a factor in common. stack: each view's factors become one pair; without it blocks keep their own
    names, so that factors can be recognised across statements. dense: changes as whole matrices (what factors avoid). chain: the
    change of an inverse block by block rather than by one small system. factor: statements are first written as sums of products."""
    for name in ranks:
        if name not in program.dynamic:
            raise ValueError(f"{name} is static")
    out = {}
    for names in [tuple(ranks)] if together else [(n,) for n in ranks]:
        known: Shapes = dict(program.shapes)
        changes: dict[str, Change] = {}
        for n in names:
            rows, cols = program.inputs[n]
            known |= {f"d{n}.L": (rows, ranks[n]), f"d{n}.R": (cols, ranks[n])}
            changes[n] = Dense(Ref(f"d{n}.L") @ Ref(f"d{n}.R").T) if dense else ((Ref(f"d{n}.L"), Ref(f"d{n}.R")),)
        assigns: list[tuple[str, Expr]] = []
        widths, counts = {}, {}

        def put(name: str, e: Expr, known=known, assigns=assigns) -> Expr:
            if isinstance(e, Ref):
                return e
            e = chain_order(e, known)
            known[name] = shape(e, known)
            assigns.append((name, e))
            return Ref(name)

        updates: dict[str, Change] = dict(changes)
        for s in program.stmts:
            e = expand(s.expr) if factor and not isinstance(s.expr, Inv) else s.expr
            d = change_of(e, changes, merge, Ref(s.target), known if chain else None) if isinstance(e, Inv) and not dense else _whole_inverse(e, s.target, changes) if isinstance(e, Inv) else change_of(e, changes, merge)
            if d == ():
                continue
            if isinstance(d, tuple) and s.dense:
                d = Dense(dense_of(d))
            if isinstance(d, Dense):
                new: Change = Dense(put(f"d{s.target}", d.expr))
                widths[s.target] = min(known[s.target])
            else:
                d = tuple((_sized(a, _width(d, known)), b) for a, b in d)
                counts[s.target] = len(d)
                if stack:
                    d = (_stacked(d),)
                tag = (lambda k: "") if stack else str
                new = tuple((put(f"d{s.target}.L{tag(k)}", a), put(f"d{s.target}.R{tag(k)}", b)) for k, (a, b) in enumerate(d))
                widths[s.target] = sum(shape(a, known)[1] for a, _ in new)
            changes[s.target] = updates[s.target] = new
        used = {r for c in updates.values() for e in ([c.expr] if isinstance(c, Dense) else [x for b in c for x in b]) for r in refs(e)}
        trigger = Trigger(names, tuple(copy_prop(cse(assigns), used)), updates, widths, counts)
        out["+".join(names)] = trigger
    return out


def _width(blocks: Blocks, known: Shapes) -> int:
    """Columns of the right factors together: the size of the identity in the rule for inverses."""
    return sum(shape(b, known)[1] for _, b in blocks)


def _whole_inverse(e: Inv, target: str, changes: dict[str, Change]) -> Change:
    """New inverse less the old one: as costly as starting again."""
    d = dense_of(change_of(e.x, changes))
    return () if d is None else Dense(Inv(e.x + d) - Ref(target))
