"""Streams, the view store, and a few registered queries against their SQL."""

import duckdb
import numpy as np
import pytest

from rankflow.operators import backends, coo, models
from rankflow.sources import fixtures, updates
from rankflow.streaming import refresh
from rankflow.streaming.store import ViewStore
from rankflow.workload_queries import ORACLE_SQL, QUERIES


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in "nation customer supplier orders lineitem events documents embeddings pages labels".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", ["pow16_incr_exp", "sums16_incr_lin", "gen16_hybrid_skip4", "ols_incr_li", "inv_rank2", "batch_zipf_1", "a4_cell", "stream_pow", "stream_session", "op_asof", "cost_time"])
def test_query_matches_sql(spark, duck, sf, name):
    df = QUERIES[name](spark, sf)
    cur = duck.execute(ORACLE_SQL[name])
    cols = [c[0] for c in cur.description]
    assert sorted(cols) == sorted(df.columns)
    assert sorted(map(repr, (tuple(r) for r in df.select(*cols).collect()))) == sorted(map(repr, cur.fetchall()))


def test_every_query_has_sql():
    assert set(QUERIES) == set(ORACLE_SQL)


def test_replayed_batches_change_nothing(spark):
    view = models.powers(backends.Local(spark), coo.Coo(spark.createDataFrame([], coo.SCHEMA), 4, 4), 2)
    sink = refresh.Refresher(view, "A")
    first = spark.createDataFrame([(0, 1, 2.0), (0, 1, 1.0), (3, 2, 1.0)], coo.SCHEMA)
    for batch_id in (0, 0, 1, 1):
        sink(first, batch_id)
    a = np.zeros((4, 4))
    a[0, 1], a[3, 2] = 6, 2
    assert (view.env["A"] == a).all() and (view.env["P2"] == a @ a).all() and sink.ranks == [2, 2]


def test_view_store_versions_log_and_fold(spark, tmp_path):
    store = ViewStore(spark, str(tmp_path), max_rank=2)
    m = np.arange(9.0).reshape(3, 3)
    store.put("V", coo.from_numpy(spark, m))
    for k in range(4):
        left, right = updates.cell(spark, k % 3, 1, float(k + 1), 3, 3)
        version = store.add("V", left, right, source=f"batch {k}")
        assert store.add("V", left, right, source=f"batch {k}") == version  # applied once
        m[k % 3, 1] += k + 1
        assert (coo.to_numpy(store.get("V")) == m).all() and store.rank("V") <= 2
    x = coo.from_numpy(spark, np.ones((3, 1)))
    assert (coo.to_numpy(store.times("V", x)) == m @ np.ones((3, 1))).all() and store.version("V") == 4


def test_streams_take_the_newest_value(spark, tmp_path):
    rows = [(1, 0, 0, 1.0, "2024-01-01 00:00:00"), (2, 0, 0, 9.0, "2024-01-01 02:00:00"), (3, 0, 0, 5.0, "2024-01-01 01:00:00"), (2, 0, 0, 9.0, "2024-01-01 02:00:00")]
    spark.createDataFrame(rows, "seq long, i long, j long, v double, t string").selectExpr("seq", "i", "j", "v", "cast(t as timestamp) event_time").write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("seq long, i long, j long, v double, event_time timestamp").parquet(str(tmp_path / "in"))
    got = refresh.to_table(refresh.latest_rows(stream), str(tmp_path / "s"), "complete").collect()
    assert [(r.i, r.v) for r in got] == [(0, 9.0)]


@pytest.mark.parametrize("name", ["choice_table", "compact_ranks", "cost_program", "cost_space", "cost_time", "mem_ratio", "op_identity", "rank_table"])
def test_figures_come_from_a_table(spark, duck, sf, name, monkeypatch):
    """Equal to SQL over the table, which Spark reads, so that other rows give other figures."""
    read = []
    monkeypatch.setattr(fixtures, "table", lambda s, d, t, f=fixtures.table: read.append(t) or f(s, d, t))
    test_query_matches_sql(spark, duck, sf, name)
    assert read and ORACLE_SQL[name].lower().count(read[0])
