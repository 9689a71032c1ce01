"""What the findings of round 2 showed, as small cases."""

import duckdb
import numpy as np
import pandas as pd
import pytest

from pyspark.sql import functions as F

from tilemul import catalogue
from tilemul.grid import GridSpec
from tilemul.matrix import Matrix
from tilemul.operators import layout, products
from tilemul.sources import tables


def both(spark, d, name, names):
    """Rows of a query and of its SQL over the Parquet files of a folder, sorted."""
    got = catalogue.QUERIES[name](spark, str(d))
    con = duckdb.connect()
    for table in names:
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{d}/{table}.parquet'")
    want = con.execute(catalogue.ORACLES[name])
    assert got.columns == [c[0] for c in want.description]
    return sorted(tuple(r) for r in got.collect()), sorted(want.fetchall())


@pytest.mark.parametrize("name", ["stream_delta_tumbling", "stream_delta_sliding", "stream_running"])
def test_update_mode_has_the_columns_of_its_result(spark, sf, name):
    got, want = both(spark, sf, name, ["events"])
    assert got == want


def test_heaviest_tile_beyond_a_thousand_columns_of_tiles(spark, tmp_path):
    parts = [0, 900_000, 900_001]  # one entry in tile 0, two in tile 1500: 1000 - 0 against 2000 - 1500
    lines = pd.DataFrame({"l_orderkey": [1, 1, 1], "l_partkey": parts, "l_quantity": [1.0, 1.0, 1.0]})
    lines.to_parquet(tmp_path / "lineitem.parquet")
    pd.DataFrame({"o_orderkey": [1]}).to_parquet(tmp_path / "orders.parquet")
    pd.DataFrame({"p_partkey": parts}).to_parquet(tmp_path / "part.parquet")
    got, want = both(spark, tmp_path, "heaviest_tile", ["lineitem", "orders", "part"])
    assert got == want and got[0][1] == 0


GIVEN = ["customer", "supplier", "part", "orders", "lineitem", "events"]


@pytest.mark.parametrize(
    "name",
    ["ai_models", "comm_model", "fetch_collisions", "fetch_collisions_no_offset", "first_fetch_local", "flop_imbalance", "grid_b", "imbalance_vs_p", "owner_map", "permutation_bijection"],
)
def test_measures_are_taken_of_given_tables(spark, sf, name):
    assert any(f" {table}" in catalogue.ORACLES[name] for table in GIVEN)
    got, want = both(spark, sf, name, GIVEN)
    assert got == want


def test_breakdown_follows_the_events(spark, sf, tmp_path):
    pd.read_parquet(f"{sf}/events.parquet").head(200).to_parquet(tmp_path / "events.parquet", coerce_timestamps="us")
    few, all_of = (sum(r.comp for r in catalogue.QUERIES["breakdown"](spark, str(d)).collect()) for d in (tmp_path, sf))
    assert few < all_of


def test_rows_against_a_rule_equal_the_plain_product_and_move_no_part_of_c(spark):
    from tilemul.matrix import Matrix
    from tilemul.operators import products
    from tilemul.session import settings
    from tilemul.sources import tables

    cells = [(i, (7 * i * n + n) % 50, i + n) for i in range(9) for n in range(1 + 4 * (i % 4))]
    a = Matrix.of(spark.createDataFrame(cells, "i long, j long, v long"), 9, 50, combine=True)
    b = tables.grid_b(spark, 50, 37)
    with settings(spark, spark__sql__execution__arrow__maxRecordsPerBatch="3"):
        got = {(r.i, r.j): r.v for r in products.by_rows(a, b).df.collect()}
    assert got == {(r.i, r.j): r.v for r in products.plain(a, b).df.collect()}
    assert a.scale(2).rule is None and b.transpose().rule is None
    for name in ("sd_n128", "sd_n512", "sd_supp_part_n512"):
        plan = catalogue.QUERIES[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
        assert "Join" not in plan


def test_complete_mode_leaves_nothing_on_the_driver(spark, sf):
    tables_before = {t.name for t in spark.catalog.listTables()}
    got, want = both(spark, sf, "stream_session", ["events"])
    assert got == want
    assert {t.name for t in spark.catalog.listTables()} == tables_before  # no table in the driver's memory


def test_tiles_take_no_more_room_than_their_entries(spark, monkeypatch):
    monkeypatch.setattr(layout, "AT_ONCE", 3)
    rows = [(4000 * t + 7 * e, 600 * (t % 3) + e, t + e + 1) for t in range(40) for e in range(1 + t % 5)] + [(i, 0, 1) for i in range(3000)]
    rows = sorted({(i, j): v for i, j, v in rows}.items())
    rows = [(i, j, v) for (i, j), v in rows]
    a = Matrix(spark.createDataFrame(rows, "i long, j long, v long").repartition(3), 160_000, 1800)
    t = layout.to_tiles(a, 4000, 600)
    held = t.df.selectExpr("ti", "size(row_ptr) AS n", "size(vals) AS entries", "row_idx IS NULL AS whole").collect()
    assert all(r.n <= 2 * r.entries + 1 for r in held) and {r.whole for r in held} == {True, False}
    assert sorted(tuple(r) for r in layout.from_tiles(t).df.collect()) == rows
    new = t.get(1, 1).withColumn("vals", F.transform("vals", lambda v: v * 10))
    got = sorted(tuple(r) for r in layout.from_tiles(t.replace(new)).df.collect())
    assert got == [(i, j, v * 10 if i // 4000 == 1 and j // 600 == 1 else v) for i, j, v in rows] and got != rows


def test_replace_tiles_equals_its_sql(spark, sf):
    got, want = both(spark, sf, "replace_tiles", GIVEN)
    assert got == want


def test_tile_products_are_expanded_a_run_of_rows_at_a_time(spark, monkeypatch):
    """No pair of tiles is expanded whole, and inner tiles of a dense B are bounded."""
    assert catalogue._bounded_grid(Matrix(None, 9_000_000, 1_200_000), Matrix(None, 1_200_000, 8), 4, 4).tile_k * 8 <= catalogue.TILE_PLACES
    rows = [(i, k, i + k + 1) for i in range(40) for k in range(12) if (i * k) % 3 == 0 and i % 7]
    a = Matrix(spark.createDataFrame(rows, "i long, j long, v long"), 40, 12)
    b = Matrix(spark.createDataFrame([(k, j, 5 * k - j) for k in range(12) for j in range(3)], "i long, j long, v long"), 12, 3)
    want = {}
    for i, k, v in rows:
        for j in range(3):
            want[i, j] = want.get((i, j), 0) + v * (5 * k - j)
    got = {(r.i, r.j): r.v for r in layout.tile_product(layout.to_tiles(a, 40, 12), layout.to_tiles(b, 12, 3)).df.collect()}
    assert got == want
    made = layout.kernels.pack(*(np.array(x) for x in zip(*rows)), 40, 12)
    dense = layout.kernels.pack(np.repeat(np.arange(12), 3), np.tile(np.arange(3), 12), np.ones(36, int), 12, 3)
    monkeypatch.setattr(layout, "PRODUCTS", 20)
    slabs = list(layout._slabs(made, dense))
    assert len(slabs) > 5 and sum(len(s.vals) for _, s in slabs) == len(rows)
    assert all(3 * len(s.vals) <= 20 or s.rows == 1 for _, s in slabs)
    parts = [(first, *layout.kernels.csr_csr(s, dense)) for first, s in slabs]
    whole = layout.kernels.csr_csr(made, dense)
    assert np.array_equal(np.concatenate([r + first for first, r, _, _ in parts]), whole[0])
    assert np.array_equal(np.concatenate([v for *_, v in parts]), whole[2])


@pytest.mark.parametrize("cols, gn, slots", [(8, 4, 32), (5, 2, 3), (1, 1, 7)])
def test_balanced_does_not_move_a_dense_operand_by_rule(spark, monkeypatch, cols, gn, slots):
    rng = np.random.default_rng(4)
    places = {(int(i), int(k)) for i, k in zip(rng.integers(0, 60, 500), rng.integers(0, 90, 500) ** 2 // 90)}  # uneven tiles
    rows = [(i, k, (i * k) % 11 - 5) for i, k in sorted(places)]
    a = Matrix(spark.createDataFrame(rows, "i long, j long, v long"), 60, 90)
    b = tables.grid_b(spark, 90, cols)
    want = {}
    for i, k, v in rows:
        for j in range(cols):
            want[i, j] = want.get((i, j), 0) + v * ((31 * k + 17 * j) % 97 - 48)
    grid = GridSpec.regular(60, 90, cols, 4, 4, gn)

    def moved(*_):
        raise AssertionError("B was moved")

    monkeypatch.setattr(products, "_right", moved)
    got = products.balanced(a, b, grid, slots).df.collect()
    assert {(r.i, r.j): r.v for r in got} == want and len(got) == len(want)
