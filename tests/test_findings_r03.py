"""Findings of round 3: what moves and what is held, beside right results."""

import numpy as np
import pytest

from tilemul import catalogue
from tilemul.apps import graphs
from tilemul.matrix import Matrix
from tilemul.operators import panels, products
from tilemul.sources import tables


def entries(m):
    return {(r.i, r.j): r.v for r in m.df.collect()}


def test_packed_entries_take_less_than_two_bytes(spark):
    cells = [(i, j, 1) for i in range(256) for j in range(256) if (i * 7 + j * j) % 5 == 0]
    a = Matrix(spark.createDataFrame(cells, "i long, j long, v long"), 256, 256)
    pieces = panels.packed(a, 256, 256)
    binary = [c for c, kind in pieces.dtypes if kind == "binary"]
    assert sum(len(r[c]) for r in pieces.collect() for c in binary) < 2 * len(cells)  # four bytes each before


def test_pairs_of_an_order_are_not_shuffled(spark, sf):
    plan = tables.copurchase(spark, sf).df._jdf.queryExecution().executedPlan().toString()
    assert "HashAggregate" not in plan and "SortMergeJoin" not in plan


def test_pairs_are_counted_in_small_steps(spark, sf, monkeypatch):
    lines = {(r.l_orderkey, r.l_partkey) for r in tables.table(spark, sf, "lineitem").select("l_orderkey", "l_partkey").collect()}
    orders, want = {}, {}
    for o, p in lines:
        orders.setdefault(o, []).append(p)
    for held in orders.values():
        for x in held:
            for y in held:
                if x != y:
                    want[x, y] = want.get((x, y), 0) + 1
    assert entries(tables.copurchase(spark, sf)) == want
    sizes, parts = np.array([3, 1, 2]), np.array([5, 6, 7, 8, 9, 4])
    for step in (1, 4, 1 << 20):
        monkeypatch.setattr(tables, "PAIRS_AT_ONCE", step)
        i, j = (np.concatenate(x).tolist() for x in zip(*tables._pairs_of(sizes, parts)))
        assert list(zip(i, j)) == [(x, y) for s in ((5, 6, 7), (8,), (9, 4)) for x in s for y in s]


@pytest.mark.parametrize("most", [1, 2, 70, 70_000])
def test_strips_with_values_of_any_size(spark, most, monkeypatch):
    monkeypatch.setattr(panels, "STRIPS", 2)  # strips of several tiles
    cells = [(i, j, 1 + (i * j) % most) for i in range(90) for j in range(90) if (i + 3 * j) % 4 == 0]
    a = Matrix(spark.createDataFrame(cells, "i long, j long, v long"), 90, 90)
    want = entries(products.plain(a, a))
    assert entries(panels.by_panels(a, a, side=16)) == want
    mask = a.where("i % 7 = 3")
    kept = entries(mask)
    assert entries(panels.by_panels(a, a, mask=mask, side=16)) == {k: v for k, v in want.items() if k in kept}


def test_triangles_count_an_edge_once_and_do_not_shuffle_edges(spark, sf):
    edges = [(0, 1), (1, 0), (1, 2), (2, 0), (2, 3), (3, 3), (3, 1), (1, 3)]
    a = Matrix(spark.createDataFrame([(i, j, 1) for i, j in edges], "i long, j long, v long"), 4, 4)
    assert graphs.triangles(a).first()[0] == 2
    seen, packed = [], panels.packed

    def watched(m, *sides):
        seen.append(m.df._jdf.queryExecution().executedPlan().toString())
        return packed(m, *sides)

    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(panels, "packed", watched)
        catalogue.QUERIES["triangles"](spark, sf)
    assert seen and all("HashAggregate" not in plan for plan in seen)


def test_block_matrices_of_wide_extents_have_few_partitions(spark):
    from tilemul.operators import baselines

    n = 70_000
    a = Matrix(spark.createDataFrame([(0, n - 1, 2), (n - 1, 5, 3)], "i long, j long, v long"), n, n)
    out = baselines.block_matrix(a, a, 64).df
    assert out.rdd.getNumPartitions() <= 1024  # 4,096 before


def test_pairs_keep_parts_that_the_part_table_lacks(spark, tmp_path):
    spark.createDataFrame([(0,), (1,)], "p_partkey long").write.parquet(f"{tmp_path}/part.parquet")
    lines = [(7, 0), (7, 5000), (7, 5000), (8, 1), (8, 0), (9, 1)]
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    a = tables.copurchase(spark, str(tmp_path))
    assert entries(a) == {(0, 5000): 1, (5000, 0): 1, (0, 1): 1, (1, 0): 1}
    sums = {r.j: (r.entries, r.total) for r in catalogue.QUERIES["ss_copurchase"](spark, str(tmp_path)).collect()}
    assert sums == {0: (1, 2), 1: (2, 2), 5000: (2, 2)}
