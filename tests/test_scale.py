"""What the engine does at sizes over its limits, with the limits made small; plans; restarts; the facade."""

import os
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from rankflow import workload_queries
from rankflow.engine import Engine
from rankflow.operators import backends, block, coo, inverse, models, regression
from rankflow.plans import compile as comp
from rankflow.plans import cost, frontend
from rankflow.sources import fixtures, updates
from rankflow.streaming import refresh
from rankflow.streaming.store import ViewStore


def plan_of(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def executed(df):
    return df._jdf.queryExecution().executedPlan().toString()


def random(n, m, seed=0):
    return np.random.default_rng(seed).standard_normal((n, m))


@pytest.mark.parametrize("factor", [0.0, 1.0, 2.0, 5.0])
def test_zipf_rows_beyond_any_table(spark, factor):
    n = 10_000
    df = spark.range(20_000).withColumn("u", (F.col("id") + 0.5) / 20_000)
    got = np.array([r.i for r in updates.zipf_rows(df, "u", n, factor).orderBy("id").collect()])
    upto = np.cumsum(1.0 / np.arange(1, n + 1) ** factor)
    want = np.searchsorted(upto / upto[-1], (np.arange(20_000) + 0.5) / 20_000)
    assert len(got) == 20_000 and np.mean(got == np.minimum(want, n - 1)) > 0.999
    if factor == 0.0:
        assert got.max() > 9_990 and (got > 4096).mean() > 0.58 and np.bincount(got).max() <= 3


def test_a_large_matrix_takes_changes_into_its_log(spark, monkeypatch):
    monkeypatch.setattr(coo, "BROADCAST_BYTES", 2000)
    monkeypatch.setattr(coo, "LOCAL_BYTES", 0)
    x = random(30, 30)
    m = coo.from_numpy(spark, x)
    m = coo.Coo(coo.cut(m.df), 30, 30)
    for k in range(4):
        left, right = random(30, 1, k), random(30, 1, 10 + k)
        x = x + left @ right.T
        m = coo.add_outer(m, coo.from_numpy(spark, left), coo.from_numpy(spark, right))
    assert len(m.log) == 4 and m.rank == 4
    # The refresh itself adds nothing to the plan of the cells.
    assert "Aggregate" not in plan_of(m.base) and "Exchange" not in executed(m.base)
    thin = random(30, 2, 99)
    assert np.allclose(coo.to_numpy(coo.mul(m, coo.from_numpy(spark, thin))), x @ thin)
    assert np.allclose(coo.to_numpy(coo.tmul(m, coo.from_numpy(spark, thin))), x.T @ thin) and np.allclose(coo.to_numpy(m), x)
    monkeypatch.setattr(coo, "LOG_RANK", 4)
    m = coo.add_outer(m, coo.from_numpy(spark, thin[:, :1]), coo.from_numpy(spark, thin[:, 1:]))
    assert not m.log and np.allclose(coo.to_numpy(m), x + thin[:, :1] @ thin[:, 1:].T)


@pytest.mark.parametrize("backend", ["coo", "block"])
def test_views_with_logs_agree_with_recomputation(spark, monkeypatch, backend):
    monkeypatch.setattr(coo, "BROADCAST_BYTES", 0)
    a = random(20, 20) / 9
    view = models.powers(backends.backend(spark, backend), coo.from_numpy(spark, a), 4, "exp", "incr")
    for k in range(3):
        left, right = random(20, 1, k), random(20, 1, 7 + k) / 9
        a = a + left @ right.T
        view.apply("A", coo.from_numpy(spark, left), coo.from_numpy(spark, right))
    got = np.zeros((20, 20))
    for r in view.frame().collect():
        got[r.i, r.j] += r.v
    assert np.allclose(got, np.linalg.matrix_power(a, 4))


def test_products_over_rows_need_no_join(spark):
    x, y = random(200, 5), random(200, 2, 1)
    x[3, 2] = 0
    df = spark.createDataFrame([(k, *map(float, r), *map(float, s)) for k, (r, s) in enumerate(zip(x, y, strict=True))], "id long, a double, b double, c double, d double, e double, y double, z double")
    mx, my = fixtures.from_rows(df, "id", list("abcde")), fixtures.from_rows(df, "id", ["y", "z"])
    for got, want in ((coo.gram(mx), x.T @ x), (coo.tmul(mx, my), x.T @ y)):
        assert np.allclose(coo.to_numpy(got), want) and "Join" not in plan_of(got.df)
    left, right = updates.row(spark, 7, {1: 2.0, 4: -1.0}, fixtures.TALL, 5)
    changed = coo.add_outer(mx, left, right)
    x[7, 1] += 2
    x[7, 4] -= 1
    assert changed.log and np.allclose(coo.to_numpy(coo.gram(changed)), x.T @ x) and np.allclose(coo.to_numpy(coo.tmul(changed, my)), x.T @ y)
    # A changed row is looked up by a broadcast of its id: the rows themselves aren't shuffled for the join.
    looked = coo.tmul(mx, coo.settle(left)).df
    assert "SortMergeJoin" not in executed(looked) and "BroadcastHashJoin" in executed(looked)


def test_nulls_count_as_zeros_in_both_forms(spark):
    df = spark.createDataFrame([(0, 1.0, None), (1, None, 2.0), (2, 3.0, 4.0)], "id long, a double, b double")
    m = fixtures.from_rows(df, "id", ["a", "b"])
    want = np.array([[10.0, 12.0], [12.0, 20.0]])
    assert (coo.to_numpy(coo.gram(m)) == want).all() and (coo.to_numpy(coo.gram(coo.Coo(m.df, m.rows, 2))) == want).all()


@pytest.mark.parametrize("chain", [False, True])
@pytest.mark.parametrize("strategy", ["incr", "reeval", "dense_delta", "auto"])
def test_least_squares_by_every_strategy(spark, strategy, chain):
    x, y = random(60, 3), random(60, 1, 1)
    df = spark.createDataFrame([(k, *map(float, r), float(s[0])) for k, (r, s) in enumerate(zip(x, y, strict=True))], "id long, a double, b double, c double, y double")
    view = regression.ols(backends.CooBackend(spark), fixtures.from_rows(df, "id", list("abc")), fixtures.from_rows(df, "id", ["y"]), strategy, chain=chain)
    for k in (4, 9):
        view.apply("X", *updates.row(spark, k, {0: 1.0, 2: 0.5}, fixtures.TALL, 3))
        x[k] += [1.0, 0.0, 0.5]
    view.apply("Y", *updates.cell(spark, 5, 0, 2.0, fixtures.TALL, 1))
    y[5] += 2
    got = {r.i: r.v for r in view.frame().collect()}
    assert np.allclose([got[k] for k in range(3)], np.linalg.lstsq(x, y, rcond=None)[0].ravel())


def test_singular_small_system_falls_back(spark):
    """Z + L R' is regular although the small system of the inverse's change isn't well."""
    program = frontend.parse("dynamic Z(2, 2)  out W = inv(Z)")
    view = models.View(backends.Local(spark), program, {"Z": coo.from_numpy(spark, np.diag([1.0, 1.0]))}, "incr")
    with pytest.raises(inverse.Singular):
        view.apply("Z", coo.from_numpy(spark, np.array([[1.0], [0.0]])), coo.from_numpy(spark, np.array([[-1.0], [0.0]])))
    assert (view.env["Z"] == np.eye(2)).all() and view.fallbacks == 1  # the old state stays
    view.apply("Z", coo.from_numpy(spark, np.array([[0.0], [1.0]])), coo.from_numpy(spark, np.array([[1.0], [2.0]])))
    assert np.allclose(view.env["W"], np.linalg.inv([[1.0, 0.0], [1.0, 3.0]]))


@pytest.mark.parametrize("grid", [1, 3, 4, 10])
def test_tiled_product(spark, monkeypatch, grid):
    monkeypatch.setattr(block, "PANEL_BYTES", 8 * 23 * 3)
    x, y = random(23, 17), random(17, 11, 1)
    a, b = (block.from_coo(coo.from_numpy(spark, m)) for m in (x, y))
    got = block.matmul_grid(a, b, grid)
    assert np.allclose(coo.to_numpy(block.to_coo(got)), x @ y)
    assert np.allclose(coo.to_numpy(block.to_coo(block.transpose(got))), (x @ y).T)


def test_tiles_are_bounded_in_bytes(spark, monkeypatch):
    monkeypatch.setattr(block, "TILE_BYTES", 8 * 5 * 5)
    x = random(19, 19)
    a = block.from_coo(coo.from_numpy(spark, x))
    assert np.allclose(coo.to_numpy(block.to_coo(block.matmul_grid(a, a, None))), x @ x)


def test_single_layout_adds_partial_sums_in_a_tree(spark, monkeypatch):
    monkeypatch.setattr(block, "PANEL_BYTES", 8 * 9)
    monkeypatch.setattr(block, "FAN", 2)
    x, thin = random(40, 9), random(40, 2, 1)
    a = block.from_coo(coo.from_numpy(spark, x), dual=False)
    a = block.Block(a.panels.repartition(20), 40, 9, None)
    assert np.allclose(block.tmul_thin(a, thin), x.T @ thin)


def test_a_wide_batch_is_a_full_change(spark):
    x = random(12, 12)
    view = models.powers(backends.CooBackend(spark), coo.from_numpy(spark, x), 2, "exp", "incr")
    cells = [(i, j, float(i - j)) for i in range(12) for j in range(12) if i != j]
    view.apply_batch("A", spark.createDataFrame(cells, coo.SCHEMA))
    for i, j, v in cells:
        x[i, j] += v
    assert np.allclose(coo.to_numpy(view.env["P2"]), x @ x)
    with pytest.raises(updates.TooWide):
        updates.compact(spark.createDataFrame(cells, coo.SCHEMA), 12, 12, 3)
    view.apply_batch("A", spark.createDataFrame([(1, 1, 0.5), (1, 2, 0.5)], coo.SCHEMA))
    x[1, 1:3] += 0.5
    assert np.allclose(coo.to_numpy(view.env["P2"]), x @ x) and view.ranks["P2"] == 2


def test_a_restarted_refresher_loses_and_repeats_nothing(spark, tmp_path):
    batches = [[(0, 1, 2.0), (2, 0, 1.0)], [(1, 1, 3.0)], [(0, 1, -1.0), (3, 3, 4.0)], [(2, 2, 1.0)]]
    a = np.zeros((4, 4))
    for b in batches:
        for i, j, v in b:
            a[i, j] += v
    frame = lambda b: spark.createDataFrame(b, coo.SCHEMA)
    store = lambda: ViewStore(spark, str(tmp_path / "views"))
    empty = lambda: models.powers(backends.CooBackend(spark), coo.Coo(spark.createDataFrame([], coo.SCHEMA), 4, 4), 2)
    first = refresh.Refresher(empty(), "A", store())
    first(frame(batches[0]), 0)
    first(frame(batches[1]), 1)
    # Batch 2 was committed, then the process was lost before its view changed; the stream sends it again.
    left, right, _ = updates.compact(frame(batches[2]), 4, 4)
    store().add("A", left, right, batch=2)
    second = refresh.Refresher(empty(), "A", store())
    assert second.done == 2
    for k in (1, 2, 3, 3):
        second(frame(batches[k]), k)
    assert np.allclose(coo.to_numpy(second.view.env["A"]), a) and np.allclose(coo.to_numpy(second.view.env["P2"]), a @ a)


def test_costs_of_programs_add_up_and_choose():
    program = regression.ols_program(1000, 20, 1)
    each = cost.program_cost(program)
    assert each["total"] == each["X"] + each["Y"] and each["X"] > each["Y"]
    assert cost.cheapest(program) == "incr" and cost.cheapest(models.general_program(500, 1, 16, "lin", None, False)) == "reeval"
    one, two = (comp.compile_program(program, {"X": r})["X"] for r in (1, 2))
    assert cost.trigger_cost(program, one, {"X": 1}) < cost.trigger_cost(program, two, {"X": 2})


def test_engine_facade(spark, tmp_path):
    x = random(6, 6)
    engine = Engine(spark, "coo", str(tmp_path / "store"))
    engine.matrix("A", coo.from_numpy(spark, x).df, 6, 6)
    engine.view("p", "dynamic A(6, 6)  B = A @ A  out C = B @ B")
    engine.update("p", "A", spark.createDataFrame([(2, 3, 1.5)], coo.SCHEMA))
    x[2, 3] += 1.5
    want = np.linalg.matrix_power(x, 4)
    assert np.isclose(engine.sql("SELECT sum(v) AS s FROM p_C").first().s, want.sum())
    assert np.isclose(engine.sql("SELECT frobenius(v) AS s FROM p_C").first().s, np.linalg.norm(want))
    assert "operations" in engine.explain("p")
    cells = engine.sql("SELECT c.* FROM (SELECT 5L AS i, array(0.0D, 2.5D) AS r) t, LATERAL row_cells(t.i, t.r) c").collect()
    assert [(c.i, c.j, c.v) for c in cells] == [(5, 1, 2.5)]
    assert engine.sql("SELECT dot(array(1.0D, 2.0D), array(3.0D, 4.0D)) AS d").first().d == 11.0


def test_pagerank_of_a_graph_by_names(spark):
    links = [("a", "b"), ("b", "c"), ("c", "a"), ("a", "c"), ("d", "a"), ("a", "b"), (None, "a")]
    got = {r.node: r.rank for r in regression.pagerank_graph(backends.CooBackend(spark), spark.createDataFrame(links, "src string, dst string"), 6).collect()}
    rank, names = dict.fromkeys("abcd", 0.25), {s for s in links if None not in s}
    for _ in range(6):
        rank = {n: 0.0375 + sum(0.85 * rank[s] / sum(1 for x in names if x[0] == s) for s, d in names if d == n) for n in "abcd"}
    assert got == pytest.approx(rank)


def test_batches_in_turn_come_from_one_pass(spark):
    """Every batch in order, rows of one batch added up, also where sequence numbers have gaps."""
    rows = [(k * 3, k % 5, (k * 7) % 6, 1.0 + k % 2) for k in range(400)]
    got = list(workload_queries._in_batches(spark.createDataFrame(rows, "seq long, i long, j long, v double"), 100, 6))
    want = np.zeros((12, 6, 6))
    for seq, i, j, v in rows:
        want[seq // 100, i, j] += v
    assert len(got) == 12 and all((left @ right.T == w).all() and left.shape[1] == 5 for (left, right), w in zip(got, want, strict=True))


def test_single_updates_have_no_limit(spark):
    """More than 100,000 updates one by one; cells of one update are added."""
    n = 100_003
    cells = spark.range(n).select(F.col("id").alias("seq"), (F.col("id") % 4).alias("i"), F.explode(F.expr("array(1L, 3L, 3L)")).alias("j"), (F.col("id") + 1.0).alias("v"))
    k = 0
    for k, (left, right) in enumerate(workload_queries._by_row_change(cells, 4), 1):
        if k % 10_000 == 1 or k == n:
            assert left[:, 0].tolist() == [float(r == (k - 1) % 4) for r in range(4)] and right[:, 0].tolist() == [0.0, k, 0.0, 2.0 * k]
    assert k == n


def test_equal_expressions_of_a_trigger_run_once():
    steps, views = comp.compile_program(frontend.parse("dynamic A(4, 4)  B = A @ A  out C = B @ B"), {"A": 1})["A"].steps
    done = [s[:3] for s in steps if s[0] != "settle"]
    assert len(done) == len(set(done)) and set(views) == {"A", "B", "C"}


def test_a_heavy_product_works_on_tiles(spark, monkeypatch):
    """Settled matrices of doubles with many products of cells; empty tiles and rows, and cells that cancel; scattered ones stay joins."""
    monkeypatch.setattr(coo, "TILE", 4)
    monkeypatch.setattr(coo, "PRODUCTS", 100)
    g = np.random.default_rng(4)
    x, y = g.integers(-3, 4, (21, 30)) * 1.0, g.integers(-3, 4, (30, 13)) * 1.0
    x[:, 8:12], x[5], y[:, 4:8] = 0.0, 0.0, 0.0
    a, b = coo.from_numpy(spark, x), coo.from_numpy(spark, y)
    assert not coo._dense_enough(a, b)  # few products for each pair of tiles
    monkeypatch.setattr(coo, "_dense_enough", lambda *_: True)
    got = coo.mul(a, b)
    assert (coo.to_numpy(got) == x @ y).all() and got.df.filter("v = 0").count() == 0


def test_views_on_tiles_stay_packed(spark, monkeypatch):
    """Products of products, changes in the log, a log added up when it is full; tiles, rows and columns without cells."""
    monkeypatch.setattr(coo, "TILE", 4)
    monkeypatch.setattr(coo, "GROUP", 2)
    monkeypatch.setattr(coo, "LOCAL_BYTES", 0)
    monkeypatch.setattr(coo, "BROADCAST_BYTES", 600)
    monkeypatch.setattr(coo, "LOG_RANK", 9)
    monkeypatch.setattr(coo, "_dense_enough", lambda a, b: None not in (a.cells, b.cells) and not a.log and not b.log and min(a.rows, a.cols, b.cols) > 9)
    g = np.random.default_rng(5)
    x = g.integers(-2, 3, (26, 26)) * 1.0
    x[8:12], x[:, 4:8], x[:, 17] = 0.0, 0.0, 0.0
    view = models.powers(backends.CooBackend(spark), coo.from_numpy(spark, x), 4, "exp", "incr")
    assert view.env["P4"].tiles is not None
    for k, (i, j) in enumerate([(9, 5), (25, 17), (0, 1)]):
        view.apply("A", *updates.cell(spark, i, j, 1.0 + k, 26, 26))
        x[i, j] += 1.0 + k
        assert view.env["P4"].tiles is not None
        assert (coo.to_numpy(view.env["P4"]) == np.linalg.matrix_power(x, 4)).all() and view.frame().filter("v = 0").count() == 0
    assert (coo.to_numpy(coo.transpose(view.env["P4"])) == np.linalg.matrix_power(x, 4).T).all()


def test_a_large_product_takes_little_disk(spark, monkeypatch):
    """A few bytes a cell in the shared folder, and its log is added up without moving it."""
    monkeypatch.setattr(coo, "BROADCAST_BYTES", 1 << 20)
    g = np.random.default_rng(6)
    x = (g.random((700, 700)) < 0.5) * 1.0
    a = coo.Coo(coo.cut(coo.from_numpy(spark, x).df), 700, 700, int(x.sum()))
    product = coo.mul(a, a)
    folder = spark.sparkContext.getCheckpointDir().removeprefix("file:")
    disk = lambda: sum(os.path.getsize(os.path.join(d, f)) for d, _, files in os.walk(folder) for f in files)
    before = disk()
    m = coo.settle(product)
    assert m.cells == 490_000 and disk() - before < 5 * m.cells
    m = coo.add_outer(m, *updates.cell(spark, 3, 699, -2.0, 700, 700))
    assert m.log and "Exchange hashpartitioning(i" not in executed(m.df)
    x = x @ x
    x[3, 699] -= 2.0
    assert (coo.to_numpy(m) == x).all()


@pytest.mark.parametrize("pairs", [5, 1 << 22])
def test_first_co_suppliers_by_counts(spark, monkeypatch, tmp_path, pairs):
    """Against a plain count; lines without a key, orders of one supplier, an order larger than what a task counts at once."""
    monkeypatch.setattr(fixtures, "PAIRS", pairs)
    monkeypatch.setattr(fixtures, "BLOCK", 3)
    g = np.random.default_rng(7)
    lines = [(int(o), int(s)) for o, s in zip(g.integers(0, 60, 200), g.integers(0, 20, 200), strict=True)]
    lines += [(70, k % 20) for k in range(50)] + [(71, 4), (71, 4)]
    spark.createDataFrame([*lines, (None, 3), (5, None)], "l_orderkey long, l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.range(20).select(F.col("id").alias("s_suppkey")).write.parquet(f"{tmp_path}/supplier.parquet")
    count = Counter((s, t) for o, s in lines for p, t in lines if o == p and s != t)
    want = sorted((i, j, 1.0) for i in range(20) for j in sorted((j for k, j in count if k == i), key=lambda j, i=i: (-count[i, j], j))[:3])
    got = fixtures.suppliers_top(spark, str(tmp_path))
    assert sorted(map(tuple, got.df.collect())) == want and (got.rows, got.cols) == (20, 20)
    # The pairs of an order's lines are counted and packed where the order is, and not sent one by one.
    assert "Join" not in executed(got.df)


def test_powers_of_whole_numbers_are_exact(spark):
    """Beyond 2^53 and 2^63, where doubles round and longs overflow; small results stay longs; broken numbers are an error."""
    x = np.array([[123_456, 98_765, 0], [1, 0, 777_777], [54_321, 2, 3]])
    exact = x.astype(object)
    b = backends.IntegerBackend(spark)
    rows = lambda df: sorted((r.i, r.j, int(r.v)) for r in df.collect())
    cells = lambda m: sorted((i, j, v) for (i, j), v in np.ndenumerate(m) if v)
    step = regression.power_iteration(b, coo.from_numpy(spark, x * 1.0), 4).frame()
    got = workload_queries.whole(step)
    assert rows(got) == cells(exact @ exact @ exact @ exact @ np.ones((3, 1), object)) and got.schema["v"].dataType.simpleString() == "decimal(38,0)"
    view = models.powers(b, coo.from_numpy(spark, x * 1.0), 4, "exp", "incr")
    view.apply_batch("A", coo.transpose(coo.from_numpy(spark, x * 1.0)).df)
    full = exact + exact.T
    assert rows(workload_queries.whole(view.frame())) == cells(full @ full @ full @ full)
    assert workload_queries.whole(view.frame("A")).schema["v"].dataType.simpleString() == "bigint"
    with pytest.raises(Exception, match="not a whole number"):
        b.load(coo.from_numpy(spark, x + 0.5))
