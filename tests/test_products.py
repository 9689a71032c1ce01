"""Every strategy gives the same product, on a hand-checked example and on random shapes."""

import random

import pytest
from pyspark.sql import functions as F

from tilemul.grid import GridSpec
from tilemul.matrix import Matrix, identity
from tilemul.operators import layout, products, stealing, work
from tilemul.plans import planner, verify

GOLDEN = [(0, 0, 1), (0, 2, 2), (1, 1, 3), (2, 2, 4), (2, 3, 5), (3, 0, 6)]
DENSE = [(r, c, v) for r, row in enumerate([(1, 2), (3, 4), (5, 6), (7, 8)]) for c, v in enumerate(row)]


def matrix(spark, cells, rows, cols):
    return Matrix(spark.createDataFrame(cells, "i long, j long, v long"), rows, cols)


def cells(m):
    return {(r.i, r.j): r.v for r in m.df.collect()}


def reference(a, b, times=lambda x, y: x * y, plus=lambda x, y: x + y):
    out = {}
    for (i, k), x in a.items():
        for (k2, j), y in b.items():
            if k == k2:
                v = times(x, y)
                out[i, j] = plus(out[i, j], v) if (i, j) in out else v
    return out


def test_golden_dense(spark):
    a, b = matrix(spark, GOLDEN, 4, 4), matrix(spark, DENSE, 4, 2)
    want = {(0, 0): 11, (0, 1): 14, (1, 0): 9, (1, 1): 12, (2, 0): 55, (2, 1): 64, (3, 0): 6, (3, 1): 12}
    for strategy in ("plain", "c", "a", "b", "1d", "3d", "lockstep-c", "lockstep-a", "lockstep-b", "auto"):
        assert cells(planner.multiply(a, b, strategy, GridSpec.regular(4, 4, 2, 2, 2, 2), workers=4)) == want, strategy


def test_golden_square_and_measures(spark):
    a = matrix(spark, GOLDEN, 4, 4)
    g = GridSpec.regular(4, 4, 4, 2, 2, 2)
    square = cells(products.stationary_c(a, a, g))
    assert square == {(0, 0): 1, (0, 2): 10, (0, 3): 10, (1, 1): 9, (2, 0): 30, (2, 2): 16, (2, 3): 20, (3, 0): 6, (3, 2): 12}
    assert work.flops(a, a).first().mults == 10
    one = work.compression_factor(a, a).first()
    assert (one.mults, one.nnz) == (10, 9) and one.cf == pytest.approx(10 / 9)
    assert work.nnz_imbalance(a, 2, 2).first().imbalance == pytest.approx(4 / 3)
    units = work.unit_mults(a, a, g)
    assert {(r.ti, r.tj, r.tk): r.mults for r in units.collect()} == {
        (0, 0, 0): 2, (0, 1, 0): 1, (0, 1, 1): 2, (1, 0, 0): 1, (1, 0, 1): 1, (1, 1, 0): 1, (1, 1, 1): 2,
    }
    assert work.flop_imbalance(units, g).first().imbalance == pytest.approx(1.2)
    assert work.stage_imbalance(units, g, offset=False).first().ratio_of_sums == pytest.approx(1.6)
    offset = work.stage_imbalance(units, g, offset=True).first()
    assert offset.ratio_of_sums == pytest.approx(1.6) and offset.mean_of_ratios == pytest.approx(5 / 3)


def test_golden_tile(spark):
    t = layout.to_tiles(matrix(spark, GOLDEN, 4, 4), 2, 2)
    row = t.get(1, 1).first()
    assert (row.row_ptr, row.col_idx, row.vals) == ([0, 2, 2], [0, 1], [4, 5])
    assert t.get_async(1, 1).result().vals == [4, 5]
    assert cells(layout.from_tiles(t)) == {(i, j): v for i, j, v in GOLDEN}


@pytest.mark.parametrize("ring,times,plus", [
    ("plus_times", lambda x, y: x * y, lambda x, y: x + y),
    ("min_plus", lambda x, y: x + y, min),
    ("max_min", min, max),
    ("or_and", lambda x, y: int(x != 0 and y != 0), max),
    ("plus_pair", lambda x, y: 1, lambda x, y: x + y),
])
def test_strategies_agree_on_ragged_shapes(spark, ring, times, plus):
    rng = random.Random(ring)
    m, k, n = 7, 5, 3
    a = {(rng.randrange(m), rng.randrange(k)): rng.randint(-3, 3) for _ in range(16)}
    b = {(rng.randrange(k), rng.randrange(n)): rng.randint(-3, 3) for _ in range(9)}
    left = matrix(spark, [(*p, v) for p, v in a.items()], m, k)
    right = matrix(spark, [(*p, v) for p, v in b.items()], k, n)
    want = reference(a, b, times, plus)
    for shape in ((2, 3, 2), (1, 1, 1), (9, 2, 4)):  # more tiles than rows among them
        g = GridSpec.regular(m, k, n, *shape)
        for run in (products.stationary_c, products.stationary_a, products.stationary_b, products.layout_3d):
            assert cells(run(left, right, g, ring=ring)) == want, (run.__name__, shape)
        tiled = layout.tile_product(layout.to_tiles(left, g.tile_m, g.tile_k), layout.to_tiles(right, g.tile_k, g.tile_n), ring)
        assert cells(tiled) == want, shape


def test_edges(spark):
    empty, b = matrix(spark, [], 4, 4), matrix(spark, DENSE, 4, 2)
    g = GridSpec.regular(4, 4, 2, 2, 2, 2)
    for run in (products.stationary_c, products.stationary_a, products.stationary_b):
        assert cells(run(empty, b, g)) == {}
    a = matrix(spark, GOLDEN, 4, 4)
    assert cells(products.plain(a, identity(spark, 4))) == {(i, j): v for i, j, v in GOLDEN}
    with pytest.raises(ValueError):
        products.plain(a, matrix(spark, [], 3, 2))
    with pytest.raises(ValueError):
        products.lockstep(a, b, GridSpec.regular(4, 4, 2, 2, 2, 1))
    with pytest.raises(ValueError):
        matrix(spark, [(0, 0, 1), (0, 0, 2)], 1, 1).validate()
    with pytest.raises(ValueError):
        matrix(spark, [(None, 0, 1)], 1, 1).validate()
    cancel = matrix(spark, [(0, 0, 1), (0, 1, -1)], 1, 2)
    ones = matrix(spark, [(0, 0, 1), (1, 0, 1)], 2, 1)
    assert cells(products.plain(cancel, ones)) == {(0, 0): 0}  # a reached place stays


def test_algebra(spark):
    a, b = matrix(spark, GOLDEN, 4, 4), matrix(spark, [(0, 1, 2), (3, 3, 1), (2, 0, 5)], 4, 4)
    ab = products.plain(a, b)
    assert cells(ab.transpose()) == cells(products.plain(b.transpose(), a.transpose()))
    both = products.plain(a, a.add(b)).drop_zeros()
    assert cells(both) == cells(products.plain(a, a).add(ab).drop_zeros())
    back = products.unpermute(products.plain(products.permute(a, 1, 2), products.permute(b, 2, 3)), 1, 3)
    assert cells(back) == cells(ab)


def test_exchanges(spark, sf):
    from tilemul.sources import tables

    a = tables.order_part(spark, sf)
    a = a.with_df(spark.createDataFrame(a.df.collect(), a.df.schema))
    b = tables.grid_b(spark, a.cols, 4)
    g = GridSpec.regular(a.rows, a.cols, 4, 2, 2, 2)
    verify.assert_exchanges(products.stationary_c(a, b, g).df, 2)
    verify.assert_exchanges(products.stationary_a(a, b, g, small_b=True).df, 2)
    verify.assert_no_cross(products.stationary_c(a, b, g).df)


def test_claims_keep_the_product(spark):
    a = matrix(spark, GOLDEN, 4, 4)
    g = GridSpec.regular(4, 4, 4, 2, 2, 2)
    units = work.work_units(a, a, g)
    for stationary in "ca":
        for policy in ("none", "random", "locality", "lockstep"):
            claims, summary = stealing.simulate(units.toPandas(), g, stationary, policy, seed=4)
            again, _ = stealing.simulate(units.toPandas(), g, stationary, policy, seed=4)
            assert claims.equals(again)
            table = stealing.claims_table(spark, claims)
            check = stealing.check_claims(units, table).first()
            assert (check.units, check.claims, check.most, check.missing) == (8, 8, 1, 0)
            assert cells(products.with_claims(a, a, g, table)) == cells(products.plain(a, a))


def test_stealing_orderings(spark):
    from dataclasses import replace

    from tilemul.sources import tables

    a = tables.rmat(spark, 9)
    g = GridSpec.regular(a.rows, a.cols, a.cols, 8, 8, 8, 4, 4)
    units = work.work_units(a, a, g).toPandas()
    free = stealing.CostParams(flop_rate=1e6, bw_net=1e18, bw_node=1e18, latency=0.0)
    span = {p: stealing.simulate(units, g, "a", p, free, 1)[1]["makespan"] for p in stealing.POLICIES}
    assert span["random"] <= span["none"] + 1e-9 and span["locality"] <= span["none"] + 1e-9
    assert span["none"] <= span["lockstep"] + 1e-9
    dear = replace(free, bw_net=1e5, bw_node=1e6)
    runs = {p: stealing.simulate(units, g, "a", p, dear, 1) for p in ("random", "locality")}
    for p, (claims, _) in runs.items():
        stolen = claims[claims.stolen]
        most = 3 if p == "random" else 2
        assert (stolen.remote_tiles <= most).all()


def test_schedule_offset_is_a_latin_square(spark):
    from tilemul.grid import schedule

    for n in (2, 3, 4):
        g = GridSpec.regular(n, n, n, n, n, n)
        for stationary in "cab":
            worst = work.fetch_collisions(schedule(spark, g, stationary)).agg({"most_a": "max", "most_b": "max"}).first()
            assert max(worst) == 1
        none = work.fetch_collisions(schedule(spark, g, "c", offset=False)).agg({"most_a": "max"}).first()
        assert none[0] == n


def test_planner(spark):
    p = planner.choose_strategy
    big_a = planner.Stats(62_500_000, 62_500_000, 3_400_000_000)
    picks = [p(big_a, planner.Stats(62_500_000, n, 62_500_000 * n), 24).stationary for n in (16, 32, 128, 512)]
    assert picks == sorted(picks) and picks[0] == "a" and picks[-1] == "c"  # one crossover
    assert "stationary" in p(big_a, big_a, 16, 10**9).explain()
    with pytest.raises(ValueError):
        planner.multiply(identity(spark, 2), identity(spark, 2), "sideways")


def test_roofline_golden(spark):
    from tilemul.operators import roofline

    rows = [(17_500_000, 17_500_000, n, 5_200_000_000, 24) for n in (128, 256, 512)]
    df = roofline.with_sparse_dense(roofline.parameters(spark, rows, "m long, k long, n long, nnz long, p long"))
    got = {r.n: (round(r.ai_net, 3), round(r.ai_local, 3)) for r in df.collect()}
    assert got == {128: (5.338, 4.539), 256: (9.078, 6.987), 512: (13.974, 9.566)}
    roofs = [r.net_roof / 1e9 for r in roofline.roofline(df).orderBy("n").collect()]
    assert [round(x, 1) for x in roofs] == [20.4, 34.8, 53.5]


def test_put_replace_renew(spark):
    import numpy as np

    t = layout.to_tiles(matrix(spark, GOLDEN, 4, 4), 2, 2)
    g = GridSpec.regular(4, 4, 4, 2, 2, 2)
    new = layout.put_block(t, 0, 1, np.array([[7, 8]]), row0=1)
    assert cells(layout.from_tiles(new))[1, 2] == 7 and cells(layout.from_tiles(new))[0, 2] == 2
    with pytest.raises(PermissionError):
        t.replace(t.get(1, 1), rank=0, grid=g)
    assert t.mine(3, g).count() == 1
    assert cells(layout.from_tiles(t.renew())) == cells(layout.from_tiles(t))


def test_balanced_parts_are_even_and_keep_the_product(spark, monkeypatch):
    from tilemul.sources import tables

    a = tables.rmat(spark, 8)
    hub = spark.range(256).select(F.lit(3).cast("long").alias("i"), F.col("id").alias("j"), F.lit(1).cast("long").alias("v"))
    a = a.add(a.with_df(hub)).add(a.with_df(hub.select(F.col("j").alias("i"), F.col("i").alias("j"), "v")))  # a dense row and column
    want = cells(products.plain(a, a))
    g = GridSpec.regular(a.rows, a.cols, a.cols, 4, 4, 4)
    slots = 16
    units = work.unit_mults(a, a, g)
    plan = work.rebalance(units, slots)
    rows = plan.orderBy("ti", "tk", "tj").collect()
    before = 0
    for r in rows:  # running totals in order, heavy units cut
        assert r.before == before and r.pieces == max(1, -(-r.mults * slots * 4 // r.total))
        before += r.mults
    assert before == rows[0].total and max(r.pieces for r in rows) > 1
    loads = work.part_loads(plan, slots).collect()
    assert len(loads) == slots and sum(r.mults for r in loads) == before
    by_tile = max(r.s for r in units.groupBy("ti", "tj").agg(F.sum("mults").alias("s")).collect())
    assert max(r.mults for r in loads) < 1.5 * before / slots < by_tile
    assert cells(products.balanced(a, a, g, slots)) == want
    monkeypatch.setattr(work, "CHUNK", 1)
    monkeypatch.setattr(products, "BROADCAST_UNITS", 0)
    assert cells(products.balanced(a, a, g, 3)) == want
    assert cells(products.balanced(a.where(F.lit(False)), a, g, 3)) == {}


def test_task_times_of_a_real_run(tmp_path):
    """An event log of a skewed square: tiles by owner against the plan of even parts."""
    import subprocess
    import sys

    code = f"""
from pyspark.sql import SparkSession
s = (SparkSession.builder.master('local[2]').config('spark.ui.enabled', 'false').config('spark.sql.shuffle.partitions', '16')
     .config('spark.sql.adaptive.coalescePartitions.enabled', 'false')
     .config('spark.eventLog.enabled', 'true').config('spark.eventLog.compress', 'false').config('spark.eventLog.dir', {str(tmp_path)!r}).config('spark.eventLog.rolling.enabled', 'false').getOrCreate())
s.sparkContext.setCheckpointDir({str(tmp_path / 'c')!r})
from tilemul.grid import GridSpec
from tilemul.operators import products
from tilemul.session import materialise
from tilemul.sources import tables
a = tables.rmat(s, 13)
a = a.with_df(materialise(a.df))
g = GridSpec.regular(a.rows, a.cols, a.cols, 4, 4, 4)
for name in ('', 'measured'):  # the first runs compile code
    for kind, c in (('tiles', products.stationary_c(a, a, g)), ('even', products.balanced(a, a, g, 16))):
        s.sparkContext.setJobGroup(name and kind, kind)
        c.df.write.format('noop').mode('overwrite').save()
s.stop()
"""
    subprocess.run([sys.executable, "-c", code], check=True, timeout=500, capture_output=True)
    import json

    log = next(p for p in tmp_path.iterdir() if p.is_file())
    group, times = {}, {}
    for line in log.read_text().splitlines():
        e = json.loads(line)
        if e["Event"] == "SparkListenerJobStart":
            group.update({n: e["Properties"].get("spark.jobGroup.id") for n in e["Stage IDs"]})
        elif e["Event"] == "SparkListenerTaskEnd":
            times.setdefault((group[e["Stage ID"]], e["Stage ID"]), []).append(e["Task Metrics"]["Executor CPU Time"])
    longest = {}
    for (name, _), some in times.items():  # the stage of the join is the one with most task time
        if name and sum(some) > sum(longest.get(name, [0])):
            longest[name] = sorted(some)
    skew = {name: some[-1] / some[len(some) // 2] for name, some in longest.items()}
    assert skew["even"] <= 2.5 and skew["even"] < skew["tiles"], skew


def test_offset_tiles_and_lockstep_of_all_operands(spark):
    a, b = matrix(spark, GOLDEN, 4, 4), matrix(spark, GOLDEN, 4, 4).transpose()
    want = cells(products.plain(a, b))
    for grid in (GridSpec.regular(4, 4, 4, 2, 2, 2), GridSpec.regular(4, 4, 4, 2, 4, 2), GridSpec.regular(4, 4, 4, 1, 1, 1)):
        left, right = layout.to_tiles(a, grid.tile_m, grid.tile_k), layout.to_tiles(b, grid.tile_k, grid.tile_n)
        for offset in (True, False):
            assert cells(layout.tile_product_c(left, right, grid, offset=offset)) == want
        for stationary in "cab":
            assert cells(products.lockstep(a, b, grid, stationary)) == want


@pytest.mark.parametrize("size", [1, 2, 3, 16, 17, 100, 1000, 4097])
def test_permutations_are_bijections_that_scatter(spark, size):
    for seed in (1, 2):
        x = [r.x for r in spark.range(size).select(products.permuted_index("id", size, seed).alias("x")).collect()]
        assert sorted(x) == list(range(size))
        if size >= 100:  # no diagonal stays one
            steps = {(q - p) % size for p, q in zip(x, x[1:])}
            assert len(steps) > size // 4


def test_workers_follow_the_data():
    small, large = planner.Stats(1000, 1000, 5000), planner.Stats(10**8, 10**8, 10**10)
    assert planner.choose_workers(small, small) == planner.LEAST_WORKERS
    many = planner.choose_workers(large, large)
    assert many * planner.ENTRIES_PER_WORKER >= 2 * 10**10 and round(many**0.5) ** 2 == many
    assert planner.choose_workers(large, large) <= planner.MOST_WORKERS
