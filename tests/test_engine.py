"""Language, derivation, compilation and the iterative models, against re-evaluation and worked examples."""

import itertools

import numpy as np
import pytest

from rankflow.functions import measures
from rankflow.operators import backends, block, coo, inverse, models, regression
from rankflow.plans import compile as comp
from rankflow.plans import cost, frontend, ir, rewrite
from rankflow.sources import updates

N, P, K = 12, 5, 16


class Thin:
    """A factor as the local back end loads it."""

    def __init__(self, x):
        self.x, self.rows, self.cols = x, *x.shape


class Arrays(backends.Local):
    def load(self, m):
        return m.x

    thin = load


def g(*shape, seed=0):
    return np.random.default_rng(seed).standard_normal(shape) / (2 * shape[0] ** 0.5)


def direct(program, env):
    return backends.run_program(Arrays(), program, env)


MODELS = [("lin", None), ("exp", None), ("skip", 4), ("skip", 1), ("skip", 16)]


@pytest.mark.parametrize("strategy", ["incr", "dense_delta", "reeval"])
@pytest.mark.parametrize(("model", "s"), MODELS)
@pytest.mark.parametrize("make", [models.powers_program, models.sums_program])
def test_powers_and_sums(make, model, s, strategy):
    program = make(N, K, model, s)
    a, left, right = g(N, N), g(N, 2, seed=1), g(N, 2, seed=2)
    v = models.View(Arrays(), program, {"A": Thin(a)}, strategy)
    want = direct(program, {"A": a + left @ right.T})
    v.apply("A", Thin(left), Thin(right))
    for name, x in want.items():
        assert np.allclose(v.env[name], x, atol=1e-12), name
    truth = np.linalg.matrix_power(a + left @ right.T, K) if make is models.powers_program else sum(np.linalg.matrix_power(a + left @ right.T, i) for i in range(K))
    assert np.allclose(v.env[program.outputs[0]], truth)


@pytest.mark.parametrize("strategy", ["incr", "hybrid", "dense_delta"])
@pytest.mark.parametrize(("model", "s"), MODELS)
@pytest.mark.parametrize("with_b", [True, False])
@pytest.mark.parametrize("which", ["A", "T0", "B"])
def test_general_form(which, with_b, model, s, strategy):
    if which == "B" and not with_b:
        return
    program = models.general_program(N, P, K, model, s, with_b, strategy == "hybrid")
    env = {"A": g(N, N), "T0": g(N, P, seed=3)} | ({"B": g(N, P, seed=4)} if with_b else {})
    v = models.View(Arrays(), program, {k: Thin(x) for k, x in env.items()}, strategy)
    left, right = g(N, 1, seed=5), g(env[which].shape[1], 1, seed=6)
    v.apply(which, Thin(left), Thin(right))
    env[which] = env[which] + left @ right.T
    want = direct(program, env)
    t = env["T0"]
    for _ in range(K):
        t = env["A"] @ t + env.get("B", 0)
    assert np.allclose(v.env[f"T{K}"], t) and all(np.allclose(v.env[n], x) for n, x in want.items())


def ranks(program, name="A", **how):
    return comp.compile_program(program, {name: 1}, **how)[name].ranks


def test_stacked_ranks():
    chain = frontend.parse("dynamic A(9, 9)  B = A @ A  C = B @ B  out D = C @ C")
    assert list(ranks(chain).values()) == [2, 4, 8]
    assert list(ranks(chain, merge=False).values()) == [3, 9, 27]
    for model, s in MODELS:
        assert ranks(models.powers_program(N, K, model, s))[f"P{K}"] == 16
        got = ranks(models.sums_program(N, K, model, s))[f"S{K}"]
        assert got == (21 if s == 4 else 15)  # blocks within stacked factors aren't told apart
        assert ranks(models.sums_program(N, K, model, s), stack=False)[f"S{K}"] == 15
    assert ranks(models.general_program(N, P, K, "lin"))["T16"] == 16
    assert ranks(models.general_program(N, P, K, "exp"))["T16"] == 27
    assert ranks(models.general_program(N, P, K, "skip", 4))["T16"] == 26
    assert [ranks(models.general_program(N, P, K, "exp"), stack=False)[f"T{i}"] for i in (1, 2, 4, 8, 16)] == [1, 2, 4, 9, 20]
    for model, s in MODELS:
        assert ranks(models.general_program(N, P, K, model, s), "B")["T16"] == 1 == ranks(models.general_program(N, P, K, model, s), "T0")["T16"]


def test_unstacked_and_unmerged_triggers_agree():
    program = models.general_program(N, P, 8, "exp")
    env = {"A": g(N, N), "T0": g(N, P, seed=3), "B": g(N, P, seed=4)}
    left, right = g(N, 1, seed=5), g(N, 1, seed=6)
    want = direct(program, env | {"A": env["A"] + left @ right.T})["T8"]
    for how in ({"stack": False}, {"merge": False}, {"merge": False, "stack": False}):
        v = models.View(Arrays(), program, {k: Thin(x) for k, x in env.items()}, "incr", **how)
        v.apply("A", Thin(left), Thin(right))
        assert np.allclose(v.env["T8"], want)


def test_worked_example():
    a = np.array([[1.0, 2.0], [0.0, 1.0]])
    v = models.View(Arrays(), models.powers_program(2, 4), {"A": Thin(a)})
    assert v.env["P4"].tolist() == [[1, 8], [0, 1]]
    v.apply("A", Thin(np.array([[0.0], [1.0]])), Thin(np.array([[1.0], [0.0]])))
    assert v.env["P4"].tolist() == [[17, 24], [12, 17]]


@pytest.mark.parametrize("seed", range(6))
def test_delta_rules_and_order_of_changes(seed):
    r = np.random.default_rng(seed)
    env = {n: r.integers(-3, 4, (4, 4)).astype(float) for n in "XYZ"}
    x, y, z = (ir.Ref(n) for n in "XYZ")
    e = [x @ y @ z, x @ y + 3 * z, (x - y.T) @ x, x @ x @ x, (x + y) @ (y - z), 2 * (x.T @ y)][seed]
    d = {n: (r.integers(-2, 3, (4, 2)).astype(float), r.integers(-2, 3, (4, 2)).astype(float)) for n in "XYZ"}
    program = ir.Program({n: (4, 4) for n in "XYZ"}, (ir.Stmt("E", e),), ("E",), tuple("XYZ"))
    new = {n: env[n] + d[n][0] @ d[n][1].T for n in "XYZ"}
    want = direct(program, new)["E"]
    once = models.View(Arrays(), program, {n: Thin(m) for n, m in env.items()})
    once.apply({n: (Thin(a), Thin(b)) for n, (a, b) in d.items()})
    assert (once.env["E"] == want).all()
    for order in itertools.permutations("XYZ"):
        v = models.View(Arrays(), program, {n: Thin(m) for n, m in env.items()})
        for n in order:
            v.apply(n, Thin(d[n][0]), Thin(d[n][1]))
        assert (v.env["E"] == want).all()


def test_expand_and_chain_order_and_cse():
    known = {"A": (50, 50), "B": (50, 50), "u": (50, 1)}
    a, b, u = ir.Ref("A"), ir.Ref("B"), ir.Ref("u")
    best = rewrite.chain_order((a @ b) @ u, known)
    assert best == a @ (b @ u) and rewrite.chain_cost(best, known) == 5000
    e = (a + b) @ (a - b) @ u
    env = {"A": g(50, 50), "B": g(50, 50, seed=1), "u": g(50, 1, seed=2)}
    assert np.allclose(backends.evaluate(Arrays(), rewrite.expand(e), env), backends.evaluate(Arrays(), e, env))
    out = rewrite.cse([("x", (a @ b) @ u), ("y", (a @ b) @ a)])
    assert sum(x == a @ b for _, x in out) == 1
    p = ir.Program({"X": (9, 3), "Y": (9, 1)}, (ir.Stmt("beta", (ir.Ref("X").T @ ir.Ref("X")).inv() @ (ir.Ref("X").T @ ir.Ref("Y"))),), ("beta",), ("X",))
    aux = rewrite.choose_aux(p)
    assert len(aux.stmts) == 4 and isinstance(aux.stmts[1].expr, ir.Inv)
    v = models.View(Arrays(), aux, {"X": Thin(g(9, 3)), "Y": Thin(g(9, 1))})
    v.apply("X", Thin(g(9, 1, seed=8)), Thin(g(3, 1, seed=9)))
    assert np.allclose(v.env["beta"], direct(aux, {"X": g(9, 3) + g(9, 1, seed=8) @ g(3, 1, seed=9).T, "Y": g(9, 1)})["beta"])


def test_parser():
    p = frontend.parse("# powers\ndynamic A(4,4) input B(4,2)\nT[0] = 1 * B\nrepeat 3 as i { T[i] = A @ T[i-1] + 2 * B }\nout Z = inv(A' @ A + eye(4)) @ T[3] - -1 * B")
    assert p.outputs == ("Z",) and p.shapes["Z"] == (4, 2) and len(p.stmts) == 5
    for bad in ("x = ", "A = B @ C", "dynamic A(2,3) B = A @ A", "dynamic A(2,2) A = A", "dynamic A(2,2) B = A $ A", "dynamic A(2,2) B = 2 @ A"):
        with pytest.raises((SyntaxError, ValueError)):
            frontend.parse(bad)


def test_validation():
    with pytest.raises(ValueError):
        models.powers_program(4, 12, "exp")
    with pytest.raises(ValueError):
        models.powers_program(4, 16, "skip", 3)
    v = models.View(Arrays(), frontend.parse("input B(2,2) dynamic A(2,2) out C = A @ B"), {"A": Thin(np.eye(2)), "B": Thin(np.eye(2))})
    with pytest.raises(ValueError, match="static"):
        v.apply("B", Thin(np.ones((2, 1))), Thin(np.ones((2, 1))))
    assert models.View(Arrays(), models.powers_program(1, 1), {"A": Thin(np.ones((1, 1)))}).program.outputs == ("A",)
    before = {k: x.copy() for k, x in v.env.items()}
    with pytest.raises(Exception):  # noqa: B017
        v.apply("A", Thin(np.ones((3, 1))), Thin(np.ones((3, 1))))
    assert all((v.env[k] == x).all() for k, x in before.items())


def test_inverse_changes():
    w = np.eye(2)
    e1 = np.array([[1.0], [0.0]])
    a, b = inverse.rank1(w, e1, e1)
    assert np.allclose(w + a @ b.T, np.diag([0.5, 1]))
    left, right = np.hstack([-e1, e1]), np.hstack([e1, e1])
    a, b = inverse.rank_k(w, left, right)
    assert np.allclose(w + a @ b.T, w)
    with pytest.raises(inverse.Singular):
        inverse.guarded(w, w - e1 @ e1.T, -e1, e1)
    r = np.random.default_rng(0)
    z = r.standard_normal((30, 30)) + 6 * np.eye(30)
    u, v = r.standard_normal((30, 3)), r.standard_normal((30, 3))
    w = np.linalg.inv(z)
    for f in (inverse.rank_k, inverse.block):
        a, b = f(w, u, v)
        assert inverse.residual(w + a @ b.T, z + u @ v.T) < 1e-9
    c = np.linalg.cholesky(z @ z.T)
    assert np.allclose(inverse.cholesky_rank1(c, u[:, 0]) @ inverse.cholesky_rank1(c, u[:, 0]).T, z @ z.T + np.outer(u[:, 0], u[:, 0]))
    a, b = inverse.compact(np.hstack([u, u]), np.hstack([v, v]))
    assert a.shape[1] == 3 and np.allclose(a @ b.T, 2 * u @ v.T)


def test_ols_and_gradient_descent():
    x, y = g(40, 4), g(40, 2, seed=1)
    for strategy in ("incr", "dense_delta", "reeval"):
        v = regression.ols(Arrays(), Thin(x), Thin(y), strategy)
        left, right = g(40, 2, seed=2), g(4, 2, seed=3)
        v.apply("X", Thin(left), Thin(right))
        x2 = x + left @ right.T
        assert np.allclose(v.env["beta"], np.linalg.lstsq(x2, y, rcond=None)[0])
        v.apply("Y", Thin(g(40, 1, seed=4)), Thin(g(2, 1, seed=5)))
        assert np.allclose(v.env["beta"], np.linalg.lstsq(x2, y + g(40, 1, seed=4) @ g(2, 1, seed=5).T, rcond=None)[0])
    for strategy, (model, s) in itertools.product(("incr", "hybrid", "reeval"), MODELS):
        program = regression.gd_program(40, 4, 2, 16, 0.5, model, s, strategy == "hybrid")
        v = models.View(Arrays(), program, {"X": Thin(x), "Y": Thin(y), "T0": Thin(np.zeros((4, 2)))}, strategy)
        v.apply("X", Thin(left), Thin(right))
        t = np.zeros((4, 2))
        for _ in range(16):
            t = t - 0.5 * x2.T @ (x2 @ t - y)
        assert np.allclose(v.env["T16"], t)


def test_drift_over_a_long_stream():
    z = np.eye(6) * 3
    w, r = np.linalg.inv(z), np.random.default_rng(1)
    for _ in range(500):
        u, v = r.standard_normal((6, 1)) * 0.1, r.standard_normal((6, 1)) * 0.1
        a, b = inverse.rank1(w, u, v)
        w, z = w + a @ b.T, z + u @ v.T
    assert inverse.residual(w, z) < 1e-8


def test_cost_tables():
    assert cost.memory_matrices("reeval") == 3 and cost.memory_matrices("incr") == 10
    assert measures.memory(20_000, 3) == pytest.approx(8.94, abs=0.01) and measures.memory(50_000, 10) == pytest.approx(186.26, abs=0.01)
    assert measures.speedup_per_memory(1328.7, 24.9, 55.9, 186.3) == pytest.approx(16.0, abs=0.05)
    assert cost.choose("powers", 10_000, 16).strategy == "incr" and cost.choose("powers", 10_000, 16).model == "exp"
    assert cost.choose("general", 10_000, 16, p=1).strategy in ("hybrid", "reeval")
    assert cost.choose("powers", 1000, 16, r=1000).strategy == "reeval"
    with pytest.raises(MemoryError):
        cost.choose("powers", 100, 16, memory=10)
    for n in (100, 1000):
        assert cost.time("powers", "exp", "incr", n, 16) < cost.time("powers", "exp", "reeval", n, 16)


@pytest.fixture(scope="module")
def cells(spark):
    r = np.random.default_rng(7)
    return r.integers(-2, 3, (9, 9)).astype(float)


def test_back_ends_agree(spark, cells):
    left, right = np.eye(9)[:, [2]], np.arange(9.0)[:, None] % 3 - 1
    want = np.linalg.matrix_power(cells + left @ right.T, 4)
    for name in ("local", "coo", "block"):
        for strategy in ("incr", "reeval"):
            b = backends.backend(spark, name)
            v = models.powers(b, coo.from_numpy(spark, cells), 4, "exp", strategy)
            v.apply("A", coo.from_numpy(spark, left), coo.from_numpy(spark, right))
            assert (coo.to_numpy(b.coo(v.env["P4"])) == want).all(), (name, strategy)


def test_block_operators(spark, cells, monkeypatch):
    monkeypatch.setattr(block, "PANEL_BYTES", 9 * 8 * 2)
    a = block.from_coo(coo.from_numpy(spark, cells))
    single = block.from_coo(coo.from_numpy(spark, cells), dual=False)
    x = np.arange(18.0).reshape(9, 2)
    for m in (a, single):
        assert (block.mul_thin(m, x) == cells @ x).all() and (block.tmul_thin(m, x) == cells.T @ x).all()
    for grid in (1, 2, 4):
        got = block.matmul_grid(a, a, grid)
        assert (coo.to_numpy(block.to_coo(got)) == cells @ cells).all() and (coo.to_numpy(block.to_coo(block.transpose(got))) == (cells @ cells).T).all()
    assert (coo.to_numpy(block.to_coo(block.add_outer(a, x, x))) == cells + x @ x.T).all()


def test_coo_operators(spark, cells):
    a = coo.from_numpy(spark, cells)
    for got, want in ((coo.transpose(a), cells.T), (coo.add(a, a), 2 * cells), (coo.scale(3, a), 3 * cells), (coo.gram(a), cells.T @ cells), (coo.identity(spark, 9), np.eye(9)), (coo.vstack([a, a]), np.vstack([cells, cells])), (coo.piece(a, (2, 5), (1, 9)), cells[2:5, 1:9])):
        assert (coo.to_numpy(got) == want).all()
    assert coo.trace(a) == np.trace(cells) and coo.norm(a) == pytest.approx(np.linalg.norm(cells))
    z = cells + 12 * np.eye(9)
    assert np.allclose(coo.to_numpy(inverse.invert(coo.from_numpy(spark, z), local_side=4)), np.linalg.inv(z))
    with pytest.raises(inverse.Singular):
        inverse.invert(coo.from_numpy(spark, np.zeros((3, 3))))
    bad = spark.createDataFrame([(0, 0, float("nan"))], coo.SCHEMA)
    with pytest.raises(Exception, match="not finite"):
        coo.clean(bad, 2, 2).df.collect()
    twice = spark.createDataFrame([(0, 0, 1.0), (0, 0, -1.0), (1, 1, -0.0), (1, 0, 2.0)], coo.SCHEMA)
    assert coo.clean(twice, 2, 2).df.count() == 1


def test_update_shapes(spark):
    for (left, right), want in (
        (updates.cell(spark, 1, 2, 5.0, 3, 3), [[0, 0, 0], [0, 0, 5], [0, 0, 0]]),
        (updates.row(spark, 0, {0: 1.0, 2: 2.0}, 3, 3), [[1, 0, 2], [0, 0, 0], [0, 0, 0]]),
        (updates.col(spark, 1, {0: 1.0, 2: 2.0}, 3, 3), [[0, 1, 0], [0, 0, 0], [0, 2, 0]]),
        (updates.every_row(spark, {1: 4.0}, 3, 3), [[0, 4, 0]] * 3),
        (updates.every_col(spark, {1: 4.0}, 3, 3), [[0, 0, 0], [4, 4, 4], [0, 0, 0]]),
        (updates.rank_k([updates.cell(spark, 0, 0, 1.0, 3, 3), updates.cell(spark, 2, 2, 1.0, 3, 3)]), [[1, 0, 0], [0, 0, 0], [0, 0, 1]]),
    ):
        assert (coo.to_numpy(coo.mul(left, coo.transpose(right))) == np.array(want)).all()


def test_batches_equal_single_updates(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet")
    for factor, least, most in ((5.0, 1, 8), (0.0, 20, 64)):
        u = updates.zipf_updates(events, 64, factor, 200)
        left, right, rank = updates.compact(u, 64, 64)
        assert least <= rank <= most
        total = np.zeros((64, 64))
        for r in u.collect():
            total[r.i, r.j] += r.v
        assert (coo.to_numpy(coo.mul(left, coo.transpose(right))) == total).all()
