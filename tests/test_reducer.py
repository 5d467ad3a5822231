import numpy as np
import pandas as pd
import pytest
from lossgrid.operators import allocate as A
from lossgrid.operators import groups as G
from lossgrid.operators.diffs import min_neighbour_diff, neighbour_diffs
from lossgrid.operators.local import ArrayGrid
from lossgrid.operators.reduce import reduce_grid
from lossgrid.plans.spec import Axis, GridSpec, ReduceConfig
from pyspark.sql import functions as F

F1 = [[10, 10, 20, 20], [10, 10, 20, 22], [30, 30, 30, 40]]


def frame(values):
    rows = [(r, c, 1, float(v)) for r, line in enumerate(values) for c, v in enumerate(line) if v is not None]
    return pd.DataFrame(rows, columns=["row", "col", "load", "a"])


def table(spark, values):
    return spark.createDataFrame(frame(values), "row int, col int, load long, a double")


def arrays(values, cols=None):
    pdf = frame(values)
    return ArrayGrid(pdf, ["a"], {"a": float(pdf["a"].abs().max()) or 1.0}, cols or max(map(len, values)))


def tiled(blocks, cells):
    seen = set()
    for b in blocks.itertuples():
        for r in range(b.r0, b.r1 + 1):
            for c in range(b.c0, b.c1 + 1):
                assert (r, c) not in seen
                seen.add((r, c))
    return seen == set(cells)


def test_worked_grid():
    g = arrays(F1)
    one = g.merge(0.0, "mean_abs", "chain")
    assert len(one) == 6 and one.loss() == 0
    two = one.merge(0.05, "mean_abs", "chain")
    assert len(two) == 4
    assert two.loss() == pytest.approx(0.011931818, abs=1e-8)
    assert two.loss("mode") == pytest.approx(0.007575757, abs=1e-8)


def test_loss_is_not_monotone():
    g = arrays([[1, 100, 20]])
    pair = g._joined(np.array([0, 0, 1]))
    assert pair.loss() == pytest.approx(16.665)

    fresh = arrays([[1, 100, 20]])
    assert fresh._joined(np.array([0, 0, 0])).loss() == pytest.approx(13.648889, abs=1e-6)


@pytest.mark.parametrize("guard", ["chain", "range", "bin"])
@pytest.mark.parametrize("metric", ["mean_abs", "max_abs", "sum_abs", "l2"])
def test_tables_equal_arrays(spark, guard, metric):
    rng = np.random.default_rng(5)
    values = rng.integers(1, 6, (7, 9)).tolist()
    values[2][3] = values[5][5] = None
    g = arrays(values).merge(0.25, metric, guard).merge(0.4, metric, guard)
    t = G.cells_as_blocks(table(spark, values), ["a"])
    scale = {"a": 5.0}
    for delta in (0.25, 0.4):
        t = G.run_merge(t, ["a"], scale, delta, metric, guard)
    got = sorted(map(tuple, t.select("r0", "r1", "c0", "c1", "n_cells").collect()))
    want = sorted((*map(int, b[[0, 1, 2, 3]]), int(n)) for b, n in zip(g.box, g.n, strict=True))
    assert got == want


def test_range_guard_bounds_every_group():
    rng = np.random.default_rng(1)
    g = arrays(rng.random((20, 20)).tolist()).merge(0.2, "mean_abs", "range")
    assert ((g.hi - g.lo) / g.scale <= 0.2 + 1e-9).all() and len(g) < 400


def test_scan_and_pairs_tile_the_grid(spark):
    values = np.random.default_rng(2).integers(1, 5, (9, 8)).tolist()
    cells = [(r, c) for r in range(9) for c in range(8)]
    scanned = G.scan_groups(table(spark, values), ["a"], {"a": 4.0}, 0.25, tile=4).toPandas()
    assert tiled(scanned, cells) and ((scanned["a__hi"] - scanned["a__lo"]) / 4 <= 0.25).all()
    matched = G.pair_match(G.cells_as_blocks(table(spark, values), ["a"]), ["a"], {"a": 4.0}, 0.25)
    local = arrays(values)
    local.scale = np.array([4.0])
    want = sorted(tuple(map(int, b)) for b in local.match(0.25, "mean_abs").box)
    assert sorted(map(tuple, matched.select("r0", "r1", "c0", "c1").collect())) == want


@pytest.mark.parametrize("kw", [{}, {"guard": "chain"}, {"guard": "bin"}, {"extractor": "scan"}, {"extractor": "pair_match"}, {"schedule": "distinct"}, {"schedule": "min_remaining"}, {"schedule": "bisect"}, {"lookahead": 3}, {"axis_order": "alternate"}, {"restart": True}])
def test_walk_invariants(spark, kw):
    values = np.random.default_rng(3).gamma(4, 10, (8, 9)).round(1).tolist()
    cfg = ReduceConfig(thetas=(0.0, 0.05, 0.2), steps=30, **kw)
    out = reduce_grid(table(spark, values), ["a"], 9, cfg)
    sizes = []
    for theta, r in out.items():
        blocks, cells = r.blocks.toPandas(), r.cells.toPandas()
        assert tiled(blocks, zip(cells["row"], cells["col"], strict=True))
        assert r.ifl <= theta + 1e-12
        assert (blocks["a"] * blocks["n_cells"]).sum() == pytest.approx(cells["a"].sum())
        sizes.append(r.n_blocks)
    assert sizes == sorted(sizes, reverse=True)


def test_engines_agree_on_the_walk(spark):
    values = np.random.default_rng(4).integers(1, 9, (6, 6)).tolist()
    cfg = ReduceConfig(thetas=(0.1,), guard="chain", steps=6)
    a, b = (reduce_grid(table(spark, values), ["a"], 6, cfg, engine)[0.1] for engine in ("local", "tables"))
    pick = ["block_id", "n_cells", "load"]
    assert sorted(map(tuple, a.blocks.select(*pick).collect())) == sorted(map(tuple, b.blocks.select(*pick).collect()))
    assert a.ifl == pytest.approx(b.ifl)


@pytest.mark.parametrize("schedule", ["distinct", "min_remaining"])
def test_steps_do_not_end_the_walk(spark, schedule):
    values = np.random.default_rng(8).integers(1, 400, (8, 8)).tolist()
    few, many = (reduce_grid(table(spark, values), ["a"], 8, ReduceConfig(thetas=(0.3,), schedule=schedule, steps=n))[0.3] for n in (2, 10_000))
    assert len(few.trace) == len(many.trace) > 2 and few.trace[-1]["ifl"] > 0.3
    assert few.n_blocks == many.n_blocks < 64


def test_literal_stop_ends_at_the_first_pass(spark):
    values = np.random.default_rng(6).integers(1, 9, (8, 8)).tolist()
    r = reduce_grid(table(spark, values), ["a"], 8, ReduceConfig(thetas=(0.3,), stop="first_within"))[0.3]
    assert len(r.trace) == 1


@pytest.mark.parametrize("values", [[[5]], [[1, 2, 3]], [[1], [2], [3]], [[7, 7], [7, 7]], [[0, 0], [0, 0]], [[-3, -3], [2, 0]], [[None, 1], [1, None]]])
def test_edge_grids(spark, values):
    r = reduce_grid(table(spark, values), ["a"], 3, ReduceConfig(thetas=(0.1,)))[0.1]
    assert r.blocks.agg(F.sum("n_cells")).first()[0] == r.n_cells
    assert r.ifl <= 0.1


def test_empty_grid(spark):
    r = reduce_grid(spark.createDataFrame([], "row int, col int, load long, a double"), ["a"], 3, ReduceConfig())[0.05]
    assert r.n_blocks == 0 and r.blocks.count() == 0


def test_zero_policies(spark):
    grid = table(spark, [[0, 2]])
    cells = A.cell_map(spark.createDataFrame([(0, 0, 0, 1)], "r0 int, r1 int, c0 int, c1 int"), 2)
    reps = A.allocate(grid, cells, ["a"])
    got = {p: A.information_loss(grid, cells, reps, ["a"], p, 0.5).first()[0] for p in ("skip", "drop_cell", "epsilon")}
    assert got == {"skip": 0.25, "drop_cell": 0.5, "epsilon": pytest.approx((1 / 0.5 + 0.5) / 2)}
    with pytest.raises(Exception, match="undefined"):
        A.information_loss(grid, cells, reps, ["a"], "error").collect()


def test_missing_cells_break_lines(spark):
    d = neighbour_diffs(table(spark, [[1, None, 2, 4]]), ["a"], suffix="")
    assert [tuple(r) for r in d.collect()] == [(0, 2, "h", 2.0)]
    assert min_neighbour_diff(d).first()[0] == 2.0


def test_options_are_checked():
    for bad in ({"thetas": (-1,)}, {"guard": "x"}, {"schedule": "x"}, {"allocation": "x"}, {"steps": 0}):
        with pytest.raises(ValueError):
            ReduceConfig(**bad)
    with pytest.raises(ValueError):
        Axis.width(F.lit(1), 0, 1, 0)
    with pytest.raises(ValueError):
        GridSpec(Axis.width(F.lit(1), 0, 1, 2), Axis.width(F.lit(1), 0, 1, 2), {})


def test_quantile_edges_are_exact(spark):
    from lossgrid.operators.grid import _edges

    df = spark.range(300_007).select((F.col("id") * 7919 % 300_007).alias("v")).selectExpr("CASE WHEN v < 300000 THEN v END AS v")
    assert _edges(df, Axis.quantile(F.col("v"), 8)) == [37_500.0 * k - 1 for k in range(1, 8)]
    few = spark.createDataFrame([(3.0,), (1.0,), (1.0,), (None,), (2.0,)], "v double")
    assert _edges(few, Axis.quantile(F.col("v"), 2)) == [1.0] and _edges(few, Axis.quantile(F.col("v"), 4)) == [1.0, 1.0, 2.0]
    assert _edges(few.where("v > 9"), Axis.quantile(F.col("v"), 4)) == []


@pytest.mark.parametrize("kw", [{}, {"metric": "max_abs"}, {"metric": "l2", "zero_policy": "drop_cell"}, {"metric": "sum_abs", "axis_order": "alternate"}, {"zero_policy": "epsilon", "epsilon": 0.5}])
@pytest.mark.parametrize("schedule", ["distinct", "min_remaining"])
def test_live_walk_equals_whole_passes(schedule, kw):
    from lossgrid.operators import reduce as R

    rng = np.random.default_rng(11)
    rows = [(r, c, 1, float(rng.gamma(4, 10).__round__(1)), float(rng.integers(0, 6))) for r in range(15) for c in range(14) if rng.random() > 0.05]
    pdf = pd.DataFrame(rows, columns=["row", "col", "load", "a", "b"])
    grid = ArrayGrid(pdf, ["a", "b"], {"a": float(pdf["a"].max()), "b": 5.0}, 14)
    cfg = ReduceConfig(thetas=(0.05, 0.3, 0.6), schedule=schedule, **kw)
    assert R._Live.fits(cfg)
    live = R._Live(R.LiveWalk(grid, cfg.metric, cfg.zero_policy, cfg.epsilon), cfg)
    raw = sorted(set(grid.gaps(cfg.metric)))
    found = []
    for start in (R._Arrays(grid, cfg), live):
        steps = R._deltas(start, None, cfg) if schedule == "min_remaining" else iter_deltas(raw)
        found.append(R._walk(start, None, cfg, steps))
    (whole, t1), (alive, t2) = found
    assert [t["n_blocks"] for t in t1] == [t["n_blocks"] for t in t2] and np.allclose([(t["delta"], t["ifl"]) for t in t1], [(t["delta"], t["ifl"]) for t in t2], atol=1e-11)
    for theta in cfg.thetas:
        a, b = whole[theta][0].grid, alive[theta][0].walk.grid(alive[theta][0].joins)
        assert sorted(map(tuple, a.box)) == sorted(map(tuple, b.box)) and a.loss("average", cfg.zero_policy, cfg.epsilon) == pytest.approx(whole[theta][1])
        assert b.loss("average", cfg.zero_policy, cfg.epsilon) == pytest.approx(alive[theta][1])
    assert whole[0.6][0].grid.n.max() > 2


def iter_deltas(raw):
    for delta in raw:
        yield delta


def test_plan_has_one_exchange_for_each_axis(spark, tmp_path):
    path = str(tmp_path / "b")
    G.cells_as_blocks(table(spark, F1), ["a"]).write.parquet(path)
    plan = G.run_merge(spark.read.parquet(path), ["a"], {"a": 40.0}, 0.05)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 2
    assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_slices_do_not_merge(spark):
    from pyspark.sql import functions as F

    cells = spark.range(32).select((F.col("id") % 4).cast("int").alias("row"), (F.floor(F.col("id") / 4) % 4).cast("int").alias("col"), F.floor(F.col("id") / 16).cast("int").alias("slice"), F.lit(1).cast("long").alias("load"), F.lit(5.0).alias("v"))
    for engine in ("local", "tables"):
        found = reduce_grid(cells, ["v"], 4, ReduceConfig(thetas=(0.1,), guard="chain", schedule="fixed", fixed=0.0), engine)[0.1]
        blocks = sorted(tuple(r) for r in found.blocks.select("slice", "r0", "r1", "c0", "c1", "n_cells").collect())
        assert blocks == [(0, 0, 3, 0, 3, 16), (1, 0, 3, 0, 3, 16)] and found.ifl == 0
        assert found.cells.select("row", "col", "slice").distinct().count() == 32
    apart = cells.withColumn("v", F.when(F.col("col") < 2, 5.0).otherwise(9.0))
    found = reduce_grid(apart, ["v"], 4, ReduceConfig(thetas=(0.1,), schedule="fixed", fixed=0.01))[0.1]
    from lossgrid.operators import graph as G

    edges = G.build_graph(found.blocks, found.cells, ["v"]).edges
    assert found.n_blocks == 4 and edges.count() == 4  # two blocks in each slice, joined within it only


def test_reduction_that_slows():
    from types import SimpleNamespace

    from lossgrid.operators.reduce import diminishing

    found = {t: SimpleNamespace(reduction=r) for t, r in ((0.1, 30.0), (0.05, 20.0), (0.15, 45.0))}
    assert [(t, g, s) for t, _, g, s in diminishing(found)] == [(0.05, 20.0, True), (0.1, 10.0, True), (0.15, 15.0, False)]


def test_trace_is_a_table(spark):
    from pyspark.sql import functions as F

    grid = spark.range(36).select((F.col("id") % 6).cast("int").alias("row"), F.floor(F.col("id") / 6).cast("int").alias("col"), F.lit(1).cast("long").alias("load"), (F.col("id") % 5 + 1).cast("double").alias("v"))
    found = reduce_grid(grid, ["v"], 6, ReduceConfig(thetas=(0.2,)))[0.2]
    rows = found.trace_table(spark).orderBy("pass").collect()
    assert len(rows) == len(found.trace) and rows[0]["n_before"] == 36 and all(r["n_blocks"] <= r["n_before"] and r["pairs"] == 2 * (r["n_before"] - 1) for r in rows)
