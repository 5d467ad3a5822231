"""Contract: names, schemas, and agreement with SQL on the smallest tables."""

import duckdb
import pytest
from lossgrid.plans import checked
from lossgrid.plans import queries as exact
from lossgrid.plans import registry, relational, studies

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
PICK = ["grid_lineitem", "diffs_l2", "merge_two_pass", "alloc_mode", "ifl_skip", "graph_edges_border", "objective_soft", "edge_cut_rate_zorder", "paper_gain_table", "op_as_of", "op_range_join"]
PICK += list(checked.QUERIES) + ["graph_from_orders", "w7_sample_events"]


def test_names():
    names = set(registry.queries())
    assert set(registry.oracle_sql()) <= names and len(names) > 100
    assert names <= set(entry.queries())
    every = [*exact.QUERIES, *relational.QUERIES, *checked.QUERIES, *studies.QUERIES]
    assert len(every) == len(set(every))


def test_entry(spark):
    assert entry.entry(spark).count() > 0


@pytest.mark.parametrize("name", PICK)
def test_sql_agrees(spark, name):
    sf = "/root/testdata/sf0.01"
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want = con.sql(registry.oracle_sql()[name]).df()
    got = registry.queries()[name](spark, sf).toPandas()
    cols = sorted(want.columns)
    assert cols == sorted(got.columns)
    rows = [sorted(map(repr, d[cols].astype(object).where(d[cols].notna(), None).itertuples(index=False, name=None))) for d in (got, want)]
    assert rows[0] == rows[1]


def test_whole_tables(spark):
    sf = "/root/testdata/sf0.001"
    orders, items = (spark.read.parquet(f"{sf}/{t}.parquet").toPandas() for t in ("orders", "lineitem"))
    of = dict(zip(orders["o_orderkey"], orders["o_custkey"], strict=True))
    pairs = {(2 * int(of[o]), 2 * int(p) + 1) for o, p in zip(items["l_orderkey"], items["l_partkey"], strict=True) if o in of}
    edges = registry.queries()["graph_from_orders"](spark, sf).collect()
    assert len(edges) == 2 * len(pairs) and {(r["src"], r["dst"]) for r in edges} == pairs | {(b, a) for a, b in pairs}
    days = {int(k): (d.strftime("%Y-%m-01"), d.year, d.isoweekday()) for k, d in zip(orders["o_orderkey"], orders["o_orderdate"], strict=True)}
    got = registry.queries()["op_dates"](spark, sf).collect()
    assert len(got) == len(orders) and {r["o_orderkey"]: (r["m"], r["y"], r["d"]) for r in got} == days
    want = sorted((int(r.l_orderkey), int(r.l_linenumber), k, float(v)) for r in items.itertuples() for k, v in (("discount", r.l_discount), ("tax", r.l_tax)))
    assert sorted((r["l_orderkey"], r["l_linenumber"], r["k"], float(r["v"])) for r in registry.queries()["op_unpivot"](spark, sf).collect()) == want


def test_gains_come_from_the_events(spark):
    small, large = (tuple(registry.queries()["paper_gain_table"](spark, f"/root/testdata/sf{n}").first()) for n in ("0.001", "0.01"))
    assert small != large and None not in small + large


@pytest.mark.parametrize("name", ["stream_incremental_grid", "stream_tag"])
def test_streams_equal_batches(spark, sf, name):
    from lossgrid.operators.grid import gridify
    from lossgrid.plans.checked import stream_spec
    from lossgrid.sources.io import load

    out = registry.queries()[name](spark, sf).toPandas()
    grid = gridify(load(spark, sf, "events"), stream_spec()).toPandas()
    assert out["load" if name == "stream_incremental_grid" else "n"].sum() == grid["load"].sum()
    if name == "stream_incremental_grid":
        both = out.merge(grid, on=["row", "col"])
        assert len(both) == len(grid) and (both["total"] / both["load_x"] - both["val"]).abs().max() < 1e-9


def test_late_rows_and_drift(spark, sf, tmp_path):
    from lossgrid.plans.checked import stream_spec
    from lossgrid.sources.io import load
    from lossgrid.streaming import stream as ST
    from pyspark.sql import functions as F

    df = load(spark, sf, "events").orderBy("ts")
    n = df.count()
    pdf = df.toPandas()
    for k in range(4):
        spark.createDataFrame(pdf.iloc[k * n // 4 : (k + 1) * n // 4], df.schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    events = ST.source(spark, str(tmp_path / "in"), df.schema)
    ST.run_to_end(ST.window_counts(events, stream_spec(), "ts", "1 day", "1 day"), "late_test", "append", str(tmp_path / "c1"))
    closed = spark.table("late_test").agg(F.sum("load")).first()[0]
    assert 0 < closed < n
    ST.run_to_end(ST.dedup(events, "event_id", "ts", "30 days").select("event_id"), "dedup_test", "append", str(tmp_path / "c2"))
    assert spark.table("dedup_test").count() == n
    parts = events.select((F.col("user_id") % 3).cast("int").alias("part"), "value")
    ST.run_to_end(ST.monitor(parts), "monitor_test", "update", str(tmp_path / "c3"))
    assert spark.table("monitor_test").groupBy("part").agg(F.max("batches")).count() == 3


def test_stream_state_outlives_its_object(spark, sf, tmp_path):
    """A second run from the same checkpoint and folder goes on with the sums of the first."""
    from lossgrid.operators.grid import gridify
    from lossgrid.plans.checked import stream_spec
    from lossgrid.sources.io import load
    from lossgrid.streaming import stream as ST

    df = load(spark, sf, "events")
    halves = df.randomSplit([0.5, 0.5], 3)
    state = None
    for k, half in enumerate(halves):
        half.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        state = ST.IncrementalGrid(spark, stream_spec(), "value", str(tmp_path / "state"))
        assert (state.state is None) == (k == 0)
        ST.run_to_end(ST.source(spark, str(tmp_path / "in"), df.schema), state, "append", str(tmp_path / "check"))
    grid = gridify(df, stream_spec())
    assert state.state.agg({"load": "sum"}).first()[0] == df.count() and state.state.count() == grid.count()
    reps = grid.selectExpr("row", "col", "val as value")
    assert state.drift(reps).first()[0] < 1e-9 and state.refreshed(reps, 0.05, 10) is None
    fresh = state.refreshed(reps.selectExpr("row", "col", "value * 2 as value"), 0.05, 10)
    assert fresh.count() == grid.count() and state.drift(fresh).first()[0] <= 0.06


def test_late_rows_are_counted(spark, sf, tmp_path):
    from lossgrid.plans.checked import stream_spec
    from lossgrid.sources.io import load
    from lossgrid.streaming import stream as ST

    df = load(spark, sf, "events").orderBy("ts")
    pdf, n = df.toPandas(), df.count()
    for part in (pdf.iloc[n // 2 :], pdf.iloc[n // 2 :], pdf.iloc[: n // 2]):  # the first half of the month comes last
        spark.createDataFrame(part, df.schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    import os
    import time

    files = sorted((f for f in os.listdir(tmp_path / "in") if f.endswith(".parquet")), key=lambda f: os.path.getmtime(tmp_path / "in" / f))
    for k, f in enumerate(files):  # the source takes files by their time
        os.utime(tmp_path / "in" / f, (time.time() - 100 + 10 * k,) * 2)
    events = ST.source(spark, str(tmp_path / "in"), df.schema)
    seen = ST.run_to_end(ST.window_counts(events, stream_spec(), "ts", "1 day", "1 hour"), "late_counted", "append", str(tmp_path / "c"))
    assert seen["rows"] == n + n - n // 2 and seen["late"] > 0
    whole = ST.run_to_end(ST.source(spark, str(tmp_path / "in"), df.schema).groupBy("event_type").count(), "whole_counts", "complete", str(tmp_path / "c2"))
    assert whole["late"] == 0 and spark.table("whole_counts").agg({"count": "sum"}).first()[0] == seen["rows"]


def test_unknown_cells_go_to_the_nearest(spark):
    from lossgrid.streaming import stream as ST

    known = spark.createDataFrame([(0, 0, 5), (0, 4, 7), (3, 2, 9)], "row int, col int, part int")
    got = {(r["row"], r["col"]): r["part"] for r in ST.filled(known, 5, 5).collect()}
    assert len(got) == 25 and None not in got.values()
    assert [got[0, c] for c in range(5)] == [5, 5, 5, 7, 7] and set(got[3, c] for c in range(5)) == {9}
    assert got[1, 0] == 5 and got[4, 4] == 9 and got[2, 1] == 9
