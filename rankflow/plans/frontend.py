"""Text front end.

    program := (decl | stmt | loop)*      decl := ("input" | "dynamic") NAME "(" INT "," INT ")"
    stmt := ["out"] NAME "=" expr         loop := "repeat" INT "as" NAME "{" stmt* "}"
    expr := + and - of terms; term := * (scalar) and @ of factors; factor: name, number, -f, (e), inv(e), eye(n), f'

In a loop ``NAME[i]`` names the view of step i and ``NAME[i-1]`` the one before; loops are unrolled.
"""

from __future__ import annotations

import re

from .ir import Expr, Ident, Program, Ref, Scale, Stmt

_TOKEN = re.compile(r"\s*(?:#[^\n]*\s*)*(?:(\d+\.?\d*(?:[eE][+-]?\d+)?)|([A-Za-z_]\w*)|([-+*@()=,{}\[\]']))")


def sym(name: str) -> Ref:
    """A named matrix to build expressions with."""
    return Ref(name)


class _Parser:
    def __init__(self, source: str):
        self.tokens, at = [], 0
        source = source.rstrip()
        while at < len(source):
            m = _TOKEN.match(source, at)
            if not m:
                if source[at:].strip().startswith("#") or not source[at:].strip():
                    break
                raise SyntaxError(f"unexpected {source[at : at + 20]!r}")
            self.tokens.append(m[1] or m[2] or m[3])
            at = m.end()
        self.at, self.step = 0, {}
        self.inputs, self.stmts, self.outputs, self.dynamic = {}, [], [], []

    def peek(self) -> str | None:
        return self.tokens[self.at] if self.at < len(self.tokens) else None

    def take(self, want: str | None = None) -> str:
        t = self.peek()
        if t is None or want is not None and t != want:
            raise SyntaxError(f"expected {want or 'more'}, found {t}")
        self.at += 1
        return t

    def program(self) -> Program:
        while self.peek() is not None:
            if self.peek() in ("input", "dynamic"):
                kind, name = self.take(), self.take()
                self.take("(")
                rows = int(self.take())
                self.take(",")
                self.inputs[name] = (rows, int(self.take()))
                self.take(")")
                if kind == "dynamic":
                    self.dynamic.append(name)
            elif self.peek() == "repeat":
                self.loop()
            else:
                self.stmt()
        return Program(self.inputs, tuple(self.stmts), tuple(self.outputs), tuple(self.dynamic))

    def loop(self) -> None:
        self.take("repeat")
        n, _, name = int(self.take()), self.take("as"), self.take()
        self.take("{")
        start = self.at
        for k in range(1, n + 1):
            self.at, self.step[name] = start, k
            while self.peek() != "}":
                self.stmt()
        self.take("}")
        del self.step[name]

    def name(self) -> str:
        name = self.take()
        if self.peek() == "[":
            self.take("[")
            t = self.take()
            k = self.step[t] if t in self.step else int(t)
            while self.peek() in ("+", "-"):
                k += (1 if self.take() == "+" else -1) * int(self.take())
            self.take("]")
            name = f"{name}_{k}"
        return name

    def stmt(self) -> None:
        out = self.peek() == "out" and bool(self.take())
        target = self.name()
        self.take("=")
        self.stmts.append(Stmt(target, self.expr()))
        if out:
            self.outputs.append(target)

    def expr(self) -> Expr:
        e = self.term()
        while self.peek() in ("+", "-"):
            e = e + self.term() if self.take() == "+" else e - self.term()
        return e

    def term(self) -> Expr:
        e = self.factor()
        while self.peek() in ("*", "@"):
            op, f = self.take(), self.factor()
            if op == "*" and isinstance(e, float):
                e = e * f if isinstance(f, float) else Scale(e, f)
            elif op == "*" and isinstance(f, float):
                e = Scale(f, e)
            elif op == "@" and not isinstance(e, float) and not isinstance(f, float):
                e = e @ f
            else:
                raise SyntaxError("* takes a number, @ two matrices")
        return e

    def factor(self):
        t = self.peek()
        if t == "-":
            self.take()
            f = self.factor()
            return -f if isinstance(f, float) else Scale(-1.0, f)
        if t == "(":
            self.take()
            e = self.expr()
            self.take(")")
        elif t == "inv":
            self.take()
            self.take("(")
            e = self.expr().inv()
            self.take(")")
        elif t == "eye":
            self.take()
            self.take("(")
            e = Ident(int(self.take()))
            self.take(")")
        elif t is not None and t[0].isdigit():
            return float(self.take())
        else:
            e = Ref(self.name())
        while self.peek() == "'":
            self.take()
            e = e.T
        return e


def parse(source: str) -> Program:
    return _Parser(source).program()
