"""Round trips, applications against brute force, and streams against tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tilemul.apps import graphs, learning
from tilemul.grid import GridSpec
from tilemul.matrix import Matrix
from tilemul.operators import layout, products
from tilemul.sources import io, tables
from tilemul.streaming import deltas

GOLDEN = [(0, 0, 1), (0, 2, 2), (1, 1, 3), (2, 2, 4), (2, 3, 5), (3, 0, 6)]


def matrix(spark, cells, n, kind="long"):
    return Matrix(spark.createDataFrame(cells, f"i long, j long, v {kind}"), n, n)


def cells(m):
    return {(r.i, r.j): r.v for r in m.df.collect()}


def test_round_trips(spark, tmp_path):
    a = matrix(spark, GOLDEN, 4)
    io.write_coo(a, str(tmp_path / "coo"))
    back = io.read_coo(spark, str(tmp_path / "coo"))
    assert cells(back) == cells(a) and (back.rows, back.cols) == (4, 4)
    io.write_tiles(layout.to_tiles(a, 2, 2), str(tmp_path / "tiles"))
    t = io.read_tiles(spark, str(tmp_path / "tiles"))
    assert cells(layout.from_tiles(t)) == cells(a)
    assert "PartitionFilters: [isnotnull(ti" in t.get(1, 1)._jdf.queryExecution().executedPlan().toString()
    io.write_mtx(a, str(tmp_path / "mtx"))
    assert cells(io.read_mtx(spark, str(tmp_path / "mtx"))) == cells(a)
    for fmt in ("csv", "json", "orc", "parquet"):
        io.write_edges(a, str(tmp_path / fmt), fmt)
        assert {(r.i, r.j): int(r.v) for r in io.read_edges(spark, str(tmp_path / fmt), fmt).collect()} == cells(a)


def test_symmetric_pattern_text(spark, tmp_path):
    (tmp_path / "s").mkdir()
    (tmp_path / "s" / "a.mtx").write_text("%%MatrixMarket matrix coordinate pattern symmetric\n% note\n3 3 3\n2 1\n3 3\n3 1\n")
    a = io.read_mtx(spark, str(tmp_path / "s"))
    assert set(cells(a)) == {(1, 0), (0, 1), (2, 2), (2, 0), (0, 2)} and a.rows == 3


def test_bucketed_operand(spark):
    a = matrix(spark, GOLDEN, 4)
    g = GridSpec.regular(4, 4, 4, 2, 2, 1)
    io.save_stationary(a, "stationary_a", g)
    try:
        got = io.stationary_product(spark, "stationary_a", a, 4, g)
        assert cells(got) == cells(products.plain(a, a))
    finally:
        spark.sql("drop table stationary_a")


def random_graph(n=14, seed=3):
    rng = np.random.default_rng(seed)
    x = (rng.random((n, n)) < 0.25).astype(int)
    np.fill_diagonal(x, 0)
    return x


def of_array(spark, x, kind="long"):
    return matrix(spark, [(int(i), int(j), x[i, j].item()) for i, j in zip(*np.nonzero(x))], len(x), kind)


def test_graph_counts(spark):
    x = random_graph()
    a = of_array(spark, x)
    u = ((x + x.T) > 0).astype(int)
    assert graphs.triangles(a).first()[0] == np.trace(u @ u @ u) // 6
    assert graphs.closed_walks(a, 3).first()[0] == np.trace(x @ x @ x)
    assert graphs.has_cycle(a, 3) == bool(np.trace(x @ x @ x))
    implied = (x @ x > 0) & (x > 0)
    assert {tuple(r) for r in graphs.transitive_reduction(a).collect()} == set(zip(*map(lambda v: v.tolist(), np.nonzero((x > 0) & ~implied))))


def test_pagerank_against_numpy(spark):
    x = random_graph(10, 5).astype(float)
    x[3] = 0  # a node without successors
    a = of_array(spark, x, "double")
    p = np.divide(x, x.sum(1, keepdims=True), out=np.zeros_like(x), where=x.sum(1, keepdims=True) > 0)
    v = e = np.eye(10)[:, :3]
    for _ in range(8):
        m = p.T @ v
        v = 0.85 * m + e * (1 - 0.85 * m.sum(0))
    seeds = spark.range(3).select(F.col("id").alias("seed"), F.col("id").alias("node"))
    got = np.zeros((10, 3))
    for (i, j), w in cells(graphs.pagerank(a, seeds, rounds=8)).items():
        got[i, j] = w
    assert np.allclose(got, v)


def test_betweenness_against_brute_force(spark):
    x = random_graph(9, 8)
    n = len(x)
    score = np.zeros(n)
    for s in range(n):
        dist, paths, order = {s: 0}, {s: 1.0}, [s]
        for u in order:
            for w in np.flatnonzero(x[u]).tolist():
                if w not in dist:
                    dist[w] = dist[u] + 1
                    order.append(w)
                    paths[w] = 0.0
                if dist[w] == dist[u] + 1:
                    paths[w] += paths[u]
        gain = dict.fromkeys(order, 0.0)
        for w in reversed(order):
            for u in order:
                if x[u, w] and dist[w] == dist[u] + 1:
                    gain[u] += paths[u] / paths[w] * (1 + gain[w])
            if w != s:
                score[w] += gain[w]
    got = np.zeros(n)
    for r in graphs.betweenness(of_array(spark, x), spark.range(n)).collect():
        got[r.node] = r.score
    assert np.allclose(got, score)


def test_markov_clusters(spark):
    x = np.zeros((6, 6), int)
    x[:3, :3] = x[3:, 3:] = 1
    np.fill_diagonal(x, 0)
    found = {r.node: r.cluster for r in graphs.markov_clusters(of_array(spark, x), rounds=8).collect()}
    assert len({found[i] for i in range(3)}) == 1 and len(set(found.values())) == 2


def test_subspace_and_nmf_and_gnn(spark):
    rng = np.random.default_rng(0)
    x = rng.integers(0, 4, (12, 12)).astype(float)
    x = x + x.T
    a = of_array(spark, x, "double")
    values, q = learning.subspace(a, 2, rounds=60)
    want = np.linalg.eigvalsh(x)
    assert values[0] == pytest.approx(want[np.argmax(np.abs(want))], rel=1e-4)
    v, w = rng.random((12, 3)), rng.random((12, 3))
    mv, mw = (Matrix(learning.dense_to_matrix(spark, z).df, 12, 3) for z in (v, w))
    before = np.linalg.norm(x - v @ w.T)
    w1, h1 = learning.nmf_update(a, mv, mw, rounds=2)
    dense = lambda m: np.array([[cells(m)[i, j] for j in range(3)] for i in range(12)])
    assert np.linalg.norm(x - dense(w1) @ dense(h1).T) < before
    feats = rng.random((12, 4))
    w0 = rng.random((4, 2)) - 0.5
    hat = (x != 0).astype(float) + np.eye(12)
    d = hat.sum(1)
    out = (hat / np.sqrt(d)[:, None] / np.sqrt(d)[None]) @ feats @ w0
    got = learning.propagate(a, Matrix(learning.dense_to_matrix(spark, feats).df, 12, 4), [w0])
    assert all(np.isclose(out[i, j], val) for (i, j), val in cells(got).items())


def test_late_rows_and_restart(spark, sf, tmp_path):
    events = tables.table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    days = events.withColumn("d", F.dayofmonth("ts"))
    b = tables.grid_b(spark, 5, 2)
    folder = tmp_path / "in"
    order = [(1, 3), (3, 6), (20, 32), (6, 20)]  # days 6 to 19 come after days 20 to 31: late
    for n, (lo, hi) in enumerate(order):
        days.where((F.col("d") >= lo) & (F.col("d") < hi)).drop("d").coalesce(1).write.mode("append").parquet(str(folder))
        got = deltas.run(deltas.delta_product(deltas.source(spark, str(folder)), b), "append", folder=str(tmp_path / "run"))
        if n == 1:
            got.count()  # a restart from the checkpoint read only the new file
    assert got.count() > 0
    starts = {r[0].day for r in got.select("start").distinct().collect()}
    assert not starts & set(range(7, 19))


def test_entry_has_no_reference_to_data_on_import():
    import __spark_entry__ as e

    assert "sd_c" in e.queries() and set(e.oracle_sql()) <= set(e.queries())


def test_betweenness_follows_long_paths(spark):
    n = 35
    chain = spark.range(n - 1).select(F.col("id").alias("i"), (F.col("id") + 1).alias("j"), F.lit(1).cast("long").alias("v"))
    found = {r.node: r.score for r in graphs.betweenness(Matrix(chain, n, n), spark.range(1)).collect()}
    assert all(found[k] == n - 1 - k for k in range(1, n - 1))


def test_terms_are_numbered_over_many_ranges(spark, sf, monkeypatch):
    whole = {(r.i, r.j): r.v for r in tables.doc_term(spark, sf).df.collect()}
    monkeypatch.setattr(tables, "TOKENS_PER_RANGE", 500)
    a = tables.doc_term(spark, sf)
    assert {(r.i, r.j): r.v for r in a.df.collect()} == whole
    texts = {r.doc_id: r.text for r in tables.table(spark, sf, "documents").collect()}
    terms = sorted({t for x in texts.values() for t in x.lower().split(" ") if t}, key=lambda t: t.encode())
    assert a.cols == len(terms) and sum(whole.values()) == sum(len([t for t in x.lower().split(" ") if t]) for x in texts.values())
