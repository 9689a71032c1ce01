"""SQL surface, functions, baselines and measured runs."""

import numpy as np

from tilemul import sqlapi
from tilemul.grid import GridSpec
from tilemul.matrix import Matrix
from tilemul.operators import baselines, products, runs
from tilemul.sources import tables

GOLDEN = [(0, 0, 1), (0, 2, 2), (1, 1, 3), (2, 2, 4), (2, 3, 5), (3, 0, 6)]


def cells(df):
    return {(r.i, r.j): r.v for r in df.collect()}


def golden(spark):
    return Matrix(spark.createDataFrame(GOLDEN, "i long, j long, v long"), 4, 4)


def test_statements_and_functions(spark, sf):
    dims = sqlapi.register(spark, sf)
    assert dims["user_event"][1] == 5
    a = tables.user_follow(spark, sf)
    want = cells(products.plain(a, a).df)
    for strategy in ("plain", "c", "a", "b", "merge"):
        assert cells(spark.sql(sqlapi.multiply_sql("user_follow", "user_follow", strategy))) == want
    assert spark.sql("select * from work_cube(2, 3, 4)").count() == 24
    rows = spark.sql("select * from untile(array(0L, 2L, 2L), array(0L, 1L), array(4D, 5D))").collect()
    assert [tuple(r) for r in rows] == [(0, 0, 4.0), (0, 1, 5.0)]
    got = spark.sql("select vector_sum(x) s from values (array(1D, 2D)), (array(3D, 4D)) t(x)").first().s
    assert got == [4.0, 6.0]
    assert spark.sql("select csr_row_dot(array(0L, 2L), array(2D, 3D), array(1D, 9D, 5D)) d").first().d == 17.0


def test_barrier_lockstep_and_baselines(spark):
    a = golden(spark)
    want = cells(products.plain(a, a).df)
    steps = baselines.lockstep_barrier(a, a, GridSpec.regular(4, 4, 4, 2, 2, 2))
    assert {r.step for r in steps.collect()} == {0, 1}
    assert cells(products.salted_sum(steps.select("i", "j", "v"))) == want
    assert cells(baselines.single_worker(a, a).df) == want
    assert cells(baselines.block_matrix(a, a, 2).df) == {p: float(v) for p, v in want.items()}


def test_measured_scaling_and_event_log(spark, tmp_path):
    a = golden(spark)
    table = runs.strong_scaling(spark, lambda p: products.layout_1d(a, a, p).df, [1, 2])
    assert [r.p for r in table.orderBy("p").collect()] == [1, 2] and table.where("p = 1").first().speedup == 1.0
    line = (
        '{"Event":"SparkListenerTaskEnd","Stage ID":3,"Task Info":{"Launch Time":1000,"Finish Time":%d},"Task Metrics":'
        '{"Executor CPU Time":1000000000,"Executor Run Time":5,"Disk Bytes Spilled":7,"Peak Execution Memory":9,'
        '"Shuffle Read Metrics":{"Fetch Wait Time":100,"Remote Bytes Read":1,"Local Bytes Read":2},"Shuffle Write Metrics":{"Shuffle Bytes Written":11}}}'
    )
    (tmp_path / "log").write_text("\n".join([line % 2000, line % 4000, '{"Event":"SparkListenerStageCompleted"}']))
    row = runs.shuffle_stats(runs.task_log(spark, str(tmp_path / "log"))).first()
    assert (row.tasks, row.shuffle_bytes, row.spilled_bytes) == (2, 22, 14)
    assert np.isclose(row.comp, 1.0) and np.isclose(row.comm, 0.1) and np.isclose(row.load_imb, 1.0) and np.isclose(row["skew"], 1.5)


def test_figure_like_orderings(spark):
    """Staged imbalance is never below end-to-end; permuting helps; the offset raises it here."""
    from tilemul.operators import work

    a = tables.rmat(spark, 11)
    g = GridSpec.regular(a.rows, a.cols, a.cols, 8, 8, 8)
    measure = lambda u: (
        work.flop_imbalance(u, g).first().imbalance,
        work.stage_imbalance(u, g, offset=False).first().ratio_of_sums,
        work.stage_imbalance(u, g, offset=True).first().ratio_of_sums,
    )
    raw = measure(work.unit_mults(a, a, g))
    mixed = measure(work.unit_mults(products.permute(a, 1, 2), products.permute(a, 2, 3), g))
    for end, staged, offset in (raw, mixed):
        assert staged >= end - 1e-9 and offset >= end - 1e-9
    assert mixed[0] < raw[0] and mixed[2] > mixed[0]
