"""Queries that SQL can repeat, each beside its DuckDB text.

Doubles are rounded to 6 digits on both sides.  The texts hold for the shapes of sf0.01.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import curves, trajectory
from ..operators import allocate as A
from ..operators import diffs as D
from ..operators import graph as G
from ..operators import groups as R
from ..operators.grid import densify, gridify, normalize, scales
from ..sources.io import load, sample_exact
from ..sources.scratch import Scratch
from .spec import Axis, GridSpec
from .workloads import price_surface, workload

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

ROWS = COLS = 30
DELTA = 0.05
PARTS = 4


def add(name: str, sql: str):
    def keep(f):
        QUERIES[name] = f
        SQL[name] = sql
        return f

    return keep


def rounded(df: DataFrame) -> DataFrame:
    """Doubles to 6 digits (and no negative zero), counts as bigint."""
    out = []
    for name, kind in df.dtypes:
        c = F.col(f"`{name}`")
        out.append((F.round(c, 6) + F.lit(0.0)).alias(name) if kind == "double" else c.cast("long").alias(name) if kind == "int" else c)
    return df.select(*out)


def _axis(x: str, lo: str, hi: str, bins: int) -> str:
    return f"CAST(greatest(0, least({bins - 1}, floor((CAST({x} AS DOUBLE) - {lo}) * {bins} / ({hi} - {lo})))) AS BIGINT)"


_US = "(epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01 00:00:00'))"
_E = f"""
g AS (SELECT {_axis("user_id", "0.0", "(SELECT CAST(max(user_id) + 1 AS DOUBLE) FROM events)", ROWS)} AS r,
             {_axis(_US, "0.0", "2592000000000.0", COLS)} AS c,
             count(*) AS load, CAST(count(*) AS DOUBLE) AS cnt, avg(value) AS val
      FROM events GROUP BY 1, 2),
s AS (SELECT max(abs(cnt)) AS mc, max(abs(val)) AS mv FROM g)"""


def events_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workload(spark, sf_dir, "E", (ROWS, COLS)).grid()


# ---------------------------------------------------------------- grids


@add("grid_events", f'WITH {_E} SELECT r AS "row", c AS col, load, round(cnt, 6) AS cnt, round(val, 6) AS val FROM g')
def _(spark, sf_dir):
    return rounded(events_grid(spark, sf_dir))


@add(
    "grid_lineitem",
    f"""SELECT {_axis("l_partkey", "0.0", "(SELECT CAST(max(l_partkey) + 1 AS DOUBLE) FROM lineitem)", 40)} AS "row",
               {_axis("date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE))", "0.0", "2500.0", 85)} AS col,
               count(*) AS load, CAST(count(*) AS DOUBLE) AS cnt, round(avg(l_extendedprice), 6) AS price, round(avg(l_quantity), 6) AS quantity
        FROM lineitem GROUP BY 1, 2""",
)
def _(spark, sf_dir):
    return rounded(workload(spark, sf_dir, "H", (40, 85)).grid())


@add(
    "grid_orders",
    f"""WITH n AS (SELECT n_nationkey, row_number() OVER (ORDER BY n_regionkey, n_nationkey) - 1 AS place FROM nation)
        SELECT place AS "row", {_axis("(year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1", "0.0", "80.0", 80)} AS col,
               count(*) AS load, CAST(count(*) AS DOUBLE) AS cnt, round(avg(o_totalprice), 6) AS price
        FROM orders JOIN customer ON o_custkey = c_custkey JOIN n ON c_nationkey = n_nationkey GROUP BY 1, 2""",
)
def _(spark, sf_dir):
    return rounded(workload(spark, sf_dir, "P2", (25, 80)).grid())


@add(
    "grid_documents",
    f"""SELECT CAST(regexp_extract(source, '([0-9]+)$', 1) AS BIGINT) AS "row",
               {_axis("d.doc_id", "0.0", "(SELECT CAST(max(doc_id) + 1 AS DOUBLE) FROM documents)", 5)} AS col,
               count(*) AS load, CAST(count(*) AS DOUBLE) AS cnt, round(avg(ln(1 + n_chars)), 6) AS size, round(avg(coalesce(toxic, 0)), 6) AS toxic
        FROM documents d LEFT JOIN labels USING (doc_id) GROUP BY 1, 2""",
)
def _(spark, sf_dir):
    return rounded(workload(spark, sf_dir, "P", (20, 5)).grid())


@add(
    "grid_conversations",
    f"""SELECT {_axis("conv_id", "0.0", "(SELECT CAST(max(conv_id) + 1 AS DOUBLE) FROM conversations)", 30)} AS "row",
               greatest(0, least(7, turn)) AS col, count(*) AS load, CAST(count(*) AS DOUBLE) AS cnt, round(avg(length(text)), 6) AS size
        FROM conversations GROUP BY 1, 2""",
)
def _(spark, sf_dir):
    return rounded(workload(spark, sf_dir, "C", (30, 8)).grid())


@add(
    "grid_slices",
    f"""SELECT {_axis("user_id", "0.0", "200.0", 10)} AS "row", {_axis(_US, "0.0", "2592000000000.0", 10)} AS col,
               list_position(['click', 'login', 'purchase', 'search', 'view'], event_type) - 1 AS slice,
               count(*) AS load, round(avg(value), 6) AS val
        FROM events WHERE list_position(['click', 'login', 'purchase', 'search', 'view'], event_type) > 0 GROUP BY 1, 2, 3""",
)
def _(spark, sf_dir):
    at = F.expr("timestampdiff(MICROSECOND, timestamp_ntz'2024-01-01 00:00:00', ts)")
    spec = GridSpec(Axis.width(F.col("user_id"), 0, 200, 10), Axis.width(at, 0, 30 * 86400 * 1e6, 10), {"val": F.avg("value")}, slice=Axis.category(F.col("event_type"), ["click", "login", "purchase", "search", "view"]))
    return rounded(gridify(load(spark, sf_dir, "events", ["user_id", "ts", "value", "event_type"]), spec))


@add("price_surface", "SELECT p_partkey // 50 AS \"row\", p_partkey % 50 AS col, count(*) AS load, round(avg(p_retailprice), 6) AS price FROM part GROUP BY 1, 2")
def _(spark, sf_dir):
    return rounded(price_surface(spark, sf_dir, 50))


@add(
    "densify_events",
    f"""WITH {_E}, a AS (SELECT r, c FROM range({ROWS}) x(r), range({COLS}) y(c))
        SELECT a.r AS "row", a.c AS col, coalesce(load, 0) AS load, round(coalesce(cnt, 0), 6) AS cnt, round(coalesce(val, 0), 6) AS val
        FROM a LEFT JOIN g ON a.r = g.r AND a.c = g.c""",
)
def _(spark, sf_dir):
    return rounded(densify(events_grid(spark, sf_dir), ROWS, COLS).select("row", "col", "load", "cnt", "val"))


for _how, _x in {"max": "{a} / (SELECT max(abs({a})) FROM g)", "minmax": "({a} - (SELECT min({a}) FROM g)) / (SELECT max({a}) - min({a}) FROM g)", "zscore": "({a} - (SELECT avg({a}) FROM g)) / (SELECT stddev_pop({a}) FROM g)"}.items():

    def _f(spark, sf_dir, how=_how):
        return rounded(normalize(events_grid(spark, sf_dir), ["cnt", "val"], how).select("row", "col", "cnt__n", "val__n"))

    add(f"normalize_{_how}", f'WITH {_E} SELECT r AS "row", c AS col, round({_x.format(a="cnt")}, 6) + 0.0 AS cnt__n, round({_x.format(a="val")}, 6) + 0.0 AS val__n FROM g')(_f)


# ---------------------------------------------------------------- differences

_METRIC = {"mean_abs": "(gc + gv) / 2", "sum_abs": "gc + gv", "max_abs": "greatest(gc, gv)", "l2": "sqrt(gc * gc + gv * gv)"}
_PAIRS = {"h": ("g.r = o.r AND o.c = g.c + 1"), "v": ("g.c = o.c AND o.r = g.r + 1"), "d": ("o.r = g.r + 1 AND o.c = g.c + 1"), "a": ("o.r = g.r + 1 AND o.c = g.c - 1")}


def _diff_sql(metric: str, axes: str = "hv") -> str:
    parts = [f"SELECT g.r, g.c, '{k}' AS axis, abs(g.cnt / mc - o.cnt / mc) AS gc, abs(g.val / mv - o.val / mv) AS gv FROM g JOIN g o ON {_PAIRS[k]} CROSS JOIN s" for k in axes]
    return f"{_E}, p AS ({' UNION ALL '.join(parts)}), d AS (SELECT r, c, axis, round({_METRIC[metric]}, 12) AS diff FROM p)"


def events_diffs(spark, sf_dir, metric="mean_abs", neigh="rook") -> DataFrame:
    return D.neighbour_diffs(normalize(events_grid(spark, sf_dir), ["cnt", "val"], "max"), ["cnt", "val"], metric, neigh)


for _m in _METRIC:

    def _f(spark, sf_dir, m=_m):
        return rounded(events_diffs(spark, sf_dir, m))

    add(f"diffs_{_m}", f'WITH {_diff_sql(_m)} SELECT r AS "row", c AS col, axis, round(diff, 6) AS diff FROM d')(_f)


@add("diffs_queen", f'WITH {_diff_sql("mean_abs", "hvda")} SELECT r AS "row", c AS col, axis, round(diff, 6) AS diff FROM d')
def _(spark, sf_dir):
    return rounded(events_diffs(spark, sf_dir, neigh="queen"))


@add("min_diff", f"WITH {_diff_sql('mean_abs')} SELECT round(min(diff), 6) AS delta FROM d")
def _(spark, sf_dir):
    return rounded(D.min_neighbour_diff(events_diffs(spark, sf_dir)))


@add("min_diff_above", f"WITH {_diff_sql('mean_abs')} SELECT round(min(diff), 6) AS delta FROM d WHERE diff > 0.1")
def _(spark, sf_dir):
    return rounded(D.min_neighbour_diff(events_diffs(spark, sf_dir), 0.1))


@add(
    "min_diff_per_cell",
    f"""WITH {_diff_sql("mean_abs")}, e AS (SELECT r, c, diff FROM d UNION ALL SELECT r + CAST(axis = 'v' AS INT), c + CAST(axis = 'h' AS INT), diff FROM d)
        SELECT r AS "row", c AS col, round(min(diff), 6) AS delta FROM e GROUP BY 1, 2""",
)
def _(spark, sf_dir):
    return rounded(D.min_diff_per_cell(events_diffs(spark, sf_dir)))


@add("diff_quantiles", f"WITH {_diff_sql('mean_abs')} SELECT round(quantile_cont(diff, 0.1), 6) AS q10, round(quantile_cont(diff, 0.25), 6) AS q25, round(quantile_cont(diff, 0.5), 6) AS q50 FROM d")
def _(spark, sf_dir):
    return rounded(events_diffs(spark, sf_dir).agg(F.percentile("diff", 0.1).alias("q10"), F.percentile("diff", 0.25).alias("q25"), F.percentile("diff", 0.5).alias("q50")))


# ---------------------------------------------------------------- merging

_START = "b0 AS (SELECT r AS r0, r AS r1, c AS c0, c AS c1, 1 AS n, load, cnt AS sc, val AS sv, cnt AS lc, cnt AS hc, val AS lv, val AS hv FROM g)"


def _pass_sql(k: int, axis: str, delta: float = DELTA, guard: str = "chain", shift: float = 0.0) -> str:
    a0, a1, b0, b1 = ("r0", "r1", "c0", "c1") if axis == "h" else ("c0", "c1", "r0", "r1")
    gap = "round((abs(sc / n / mc - lag(sc / n / mc) OVER w) + abs(sv / n / mv - lag(sv / n / mv) OVER w)) / 2.0, 12)"
    extra = ""
    if guard == "bin":
        for x, m in (("c", "mc"), ("v", "mv")):
            lo, hi = (f"floor(({s}{x} / {m} + {shift}) / {delta})" for s in "lh")
            extra += f" AND {lo} = {hi} AND lag({lo}) OVER w = {lo} AND lag({hi}) OVER w = {lo}"
    return f"""
f{k} AS (SELECT b{k}.*, CASE WHEN {b0} = lag({b1}) OVER w + 1 AND {gap} <= {delta}{extra} THEN 0 ELSE 1 END AS nw
         FROM b{k} CROSS JOIN s WINDOW w AS (PARTITION BY {a0}, {a1} ORDER BY {b0})),
q{k} AS (SELECT *, sum(nw) OVER (PARTITION BY {a0}, {a1} ORDER BY {b0} ROWS UNBOUNDED PRECEDING) AS run FROM f{k}),
b{k + 1} AS (SELECT min(r0) AS r0, max(r1) AS r1, min(c0) AS c0, max(c1) AS c1, sum(n) AS n, sum(load) AS load, sum(sc) AS sc, sum(sv) AS sv,
             min(lc) AS lc, max(hc) AS hc, min(lv) AS lv, max(hv) AS hv FROM q{k} GROUP BY {a0}, {a1}, run)"""


def _merged_sql(axes: str, delta: float = DELTA, guard: str = "chain") -> str:
    return f"{_E}, {_START}, " + ", ".join(_pass_sql(k, axis, delta, guard) for k, axis in enumerate(axes))


def _blocks_out(k: int) -> str:
    return f"SELECT r0, r1, c0, c1, CAST(n AS BIGINT) AS n_cells, CAST(load AS BIGINT) AS load, round(sc / n, 6) AS cnt, round(sv / n, 6) AS val FROM b{k}"


def merged(spark, sf_dir, axes: str, delta: float = DELTA, guard: str = "chain") -> DataFrame:
    grid = events_grid(spark, sf_dir)
    scale = {a: d for a, (_, d) in scales(grid, ["cnt", "val"]).items()}
    return R.run_merge(R.cells_as_blocks(grid, ["cnt", "val"]), ["cnt", "val"], scale, delta, "mean_abs", guard, axes)


def _shown(blocks: DataFrame) -> DataFrame:
    return rounded(blocks.select("r0", "r1", "c0", "c1", "n_cells", "load", (F.col("cnt__sum") / F.col("n_cells")).alias("cnt"), (F.col("val__sum") / F.col("n_cells")).alias("val")))


for _name, _axes in {"merge_h_pass": "h", "merge_hv_pass": "hv", "merge_two_pass": "hvhv"}.items():

    def _f(spark, sf_dir, axes=_axes):
        return _shown(merged(spark, sf_dir, axes))

    add(_name, f"WITH {_merged_sql(_axes)} {_blocks_out(len(_axes))}")(_f)


@add("merge_bin_guard", f"WITH {_merged_sql('hv', 0.1, 'bin')} {_blocks_out(2)}")
def _(spark, sf_dir):
    return _shown(merged(spark, sf_dir, "hv", 0.1, "bin"))


_MAP = f"WITH {_merged_sql('hv')}, m AS (SELECT r0 * {COLS} + c0 AS block_id, g.* FROM b2 JOIN g ON g.r BETWEEN r0 AND r1 AND g.c BETWEEN c0 AND c1)"


def merged_map(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    grid = events_grid(spark, sf_dir)
    return grid, A.cell_map(merged(spark, sf_dir, "hv"), COLS)


@add("expand_blocks", f'{_MAP} SELECT r AS "row", c AS col, block_id FROM m')
def _(spark, sf_dir):
    return rounded(merged_map(spark, sf_dir)[1])


_ALLOC = {
    "average": "SELECT block_id, round(avg(cnt), 6) AS cnt, round(avg(val), 6) AS val FROM m GROUP BY 1",
    "median": "SELECT block_id, round(median(cnt), 6) AS cnt, round(median(val), 6) AS val FROM m GROUP BY 1",
    "load_weighted": "SELECT block_id, round(sum(cnt * load) / sum(load), 6) AS cnt, round(sum(val * load) / sum(load), 6) AS val FROM m GROUP BY 1",
    "mode": """SELECT x.block_id, x.v AS cnt, y.v AS val FROM
        (SELECT block_id, v FROM (SELECT block_id, round(cnt, 0) AS v, row_number() OVER (PARTITION BY block_id ORDER BY count(*) DESC, round(cnt, 0)) AS k FROM m GROUP BY 1, 2) WHERE k = 1) x
        JOIN (SELECT block_id, v FROM (SELECT block_id, round(val, 0) AS v, row_number() OVER (PARTITION BY block_id ORDER BY count(*) DESC, round(val, 0)) AS k FROM m GROUP BY 1, 2) WHERE k = 1) y USING (block_id)""",
}
for _how, _x in _ALLOC.items():

    def _f(spark, sf_dir, how=_how):
        return rounded(A.allocate(*merged_map(spark, sf_dir), ["cnt", "val"], how, 0 if how == "mode" else None))

    add(f"alloc_{_how}", f"{_MAP} {_x}")(_f)

_LOSS = f"{_MAP}, a AS (SELECT block_id, avg(cnt) AS ac, avg(val) AS av FROM m GROUP BY 1), t AS (SELECT m.*, abs(cnt - ac) AS ec, abs(val - av) AS ev FROM m JOIN a USING (block_id))"
_IFL = {
    "skip": "SELECT round(sum(CASE WHEN cnt <> 0 THEN ec / abs(cnt) ELSE 0 END) / count(*) + sum(CASE WHEN val <> 0 THEN ev / abs(val) ELSE 0 END) / count(*), 6) AS ifl FROM t",
    "drop_cell": "SELECT round(sum(ec / abs(cnt)) / count(*) + sum(ev / abs(val)) / count(*), 6) AS ifl FROM t WHERE cnt <> 0 AND val <> 0",
    "epsilon": "SELECT round(sum(ec / greatest(abs(cnt), 1)) / count(*) + sum(ev / greatest(abs(val), 1)) / count(*), 6) AS ifl FROM t",
}


def _loss(spark, sf_dir, policy: str = "skip", **kw) -> DataFrame:
    grid, cells = merged_map(spark, sf_dir)
    return A.information_loss(grid, cells, A.allocate(grid, cells, ["cnt", "val"]), ["cnt", "val"], policy, 1.0, **kw)


for _how, _x in _IFL.items():

    def _f(spark, sf_dir, how=_how):
        return rounded(_loss(spark, sf_dir, how))

    add(f"ifl_{_how}", f"{_LOSS} {_x}")(_f)


@add("ifl_by_attribute", f"{_LOSS} SELECT round(sum(ec / abs(cnt)) / count(*) + sum(CASE WHEN val <> 0 THEN ev / abs(val) ELSE 0 END) / count(*), 6) AS ifl, round(sum(ec / abs(cnt)) / count(*), 6) AS ifl_cnt, round(sum(CASE WHEN val <> 0 THEN ev / abs(val) ELSE 0 END) / count(*), 6) AS ifl_val FROM t")
def _(spark, sf_dir):
    return rounded(_loss(spark, sf_dir, per_attribute=True))


@add("ifl_by_block", f"{_LOSS} SELECT block_id, count(*) AS n_cells, round(sum(ec / abs(cnt) + CASE WHEN val <> 0 THEN ev / abs(val) ELSE 0 END), 6) AS loss FROM t GROUP BY 1")
def _(spark, sf_dir):
    grid, cells = merged_map(spark, sf_dir)
    return rounded(A.loss_by_block(grid, cells, A.allocate(grid, cells, ["cnt", "val"]), ["cnt", "val"]))


@add("size_reduction", f"WITH {_merged_sql('hv')} SELECT count(*) AS n_blocks, (SELECT count(*) FROM g) AS n_cells, round(100 * (1 - count(*) / (SELECT count(*) FROM g)), 6) AS reduction FROM b2")
def _(spark, sf_dir):
    return rounded(A.size_reduction(merged(spark, sf_dir, "hv"), events_grid(spark, sf_dir).count()))


# ---------------------------------------------------------------- graphs

_BORDER = f"""{_MAP},
p AS (SELECT x.block_id AS u, y.block_id AS v FROM m x JOIN m y ON (x.r = y.r AND y.c = x.c + 1) OR (x.c = y.c AND y.r = x.r + 1) WHERE x.block_id <> y.block_id),
e1 AS (SELECT least(u, v) AS a, greatest(u, v) AS b, count(*) AS sides FROM p GROUP BY 1, 2),
e AS (SELECT a AS src, b AS dst, sides FROM e1 UNION ALL SELECT b, a, sides FROM e1)"""


def events_graph(spark, sf_dir, weight="unit", neigh="rook") -> G.Graph:
    grid, cells = merged_map(spark, sf_dir)
    blocks = A.with_ids(merged(spark, sf_dir, "hv"), COLS).select("block_id", "r0", "r1", "c0", "c1", "n_cells", "load", (F.col("cnt__sum") / F.col("n_cells")).alias("cnt"), (F.col("val__sum") / F.col("n_cells")).alias("val"))
    scale = {a: d for a, (_, d) in scales(grid, ["cnt", "val"]).items()}
    return G.build_graph(blocks, cells, ["cnt", "val"], weight, neigh, scale)


@add("graph_edges_unit", f"{_BORDER} SELECT src, dst, 1.0::DOUBLE AS w FROM e")
def _(spark, sf_dir):
    return rounded(events_graph(spark, sf_dir).edges)


@add("graph_edges_border", f"{_BORDER} SELECT src, dst, CAST(sides AS DOUBLE) AS w FROM e")
def _(spark, sf_dir):
    return rounded(events_graph(spark, sf_dir, "border").edges)


@add("graph_edges_similarity", f"{_BORDER}, a AS (SELECT block_id, avg(cnt) AS ac, avg(val) AS av FROM m GROUP BY 1) SELECT src, dst, round(exp(-(abs(x.ac - y.ac) / mc + abs(x.av - y.av) / mv) / 2), 6) AS w FROM e JOIN a x ON x.block_id = src JOIN a y ON y.block_id = dst CROSS JOIN s")
def _(spark, sf_dir):
    return rounded(events_graph(spark, sf_dir, "similarity").edges)


@add("graph_edges_load", f"{_BORDER}, a AS (SELECT block_id, sum(load) AS l FROM m GROUP BY 1) SELECT src, dst, round(ln(1 + x.l) + ln(1 + y.l), 6) AS w FROM e JOIN a x ON x.block_id = src JOIN a y ON y.block_id = dst")
def _(spark, sf_dir):
    return rounded(events_graph(spark, sf_dir, "load").edges)


@add("graph_degrees", f"{_BORDER} SELECT src AS id, CAST(count(*) AS DOUBLE) AS deg FROM e GROUP BY 1")
def _(spark, sf_dir):
    return rounded(G.degrees(events_graph(spark, sf_dir).edges))


@add("graph_from_orders", """WITH p AS (SELECT DISTINCT 2 * o_custkey AS a, 2 * l_partkey + 1 AS b FROM orders JOIN lineitem ON l_orderkey = o_orderkey)
SELECT a AS src, b AS dst, 1.0::DOUBLE AS w FROM p UNION ALL SELECT b, a, 1.0::DOUBLE FROM p""")
def _(spark, sf_dir):
    """Every customer (even ids) beside every part (odd ids) of their orders."""
    orders, items = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]), load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"])
    pairs = orders.join(items, F.col("o_orderkey") == F.col("l_orderkey")).select((F.col("o_custkey") * 2).alias("src"), (F.col("l_partkey") * 2 + 1).alias("dst"))
    return rounded(G.Graph.from_edges(pairs).edges)


def _striped(graph: G.Graph) -> DataFrame:
    return graph.nodes.select("id", (F.floor(F.col("id") / COLS) % PARTS).cast("int").alias("part"))


_CUT = f"{_BORDER}, l AS (SELECT DISTINCT block_id AS id, (block_id // {COLS}) % {PARTS} AS part FROM m), j AS (SELECT e.*, x.part AS p, y.part AS q FROM e JOIN l x ON x.id = src JOIN l y ON y.id = dst)"


@add("ncut_stripe", f"{_CUT} SELECT round(sum(k), 6) AS ncut FROM (SELECT p, sum(CASE WHEN p <> q THEN 1.0 ELSE 0 END) / count(*) AS k FROM j GROUP BY 1)")
def _(spark, sf_dir):
    graph = events_graph(spark, sf_dir)
    return rounded(G.ncut(graph, _striped(graph)))


@add("ncut_terms", f"{_CUT} SELECT p AS part, CAST(sum(CASE WHEN p <> q THEN 1 ELSE 0 END) AS DOUBLE) AS cut, CAST(count(*) AS DOUBLE) AS vol, round(sum(CASE WHEN p <> q THEN 1.0 ELSE 0 END) / count(*), 6) AS ratio FROM j GROUP BY 1")
def _(spark, sf_dir):
    graph = events_graph(spark, sf_dir)
    return rounded(G.ncut_terms(graph, _striped(graph)))


def _soft(graph: G.Graph) -> DataFrame:
    """A soft assignment by formula: shares 1 + (id * (k + 1)) mod 7."""
    share = [F.lit(1.0) + F.pmod(F.col("id") * (k + 1), F.lit(7)) for k in range(PARTS)]
    total = sum(share[1:], share[0])
    return graph.nodes.select("id", F.array(*[s / total for s in share]).alias("prob"))


_SOFT = f"""{_BORDER}, a AS (SELECT block_id AS id, sum(load) AS load FROM m GROUP BY 1), dg AS (SELECT src AS id, count(*) AS deg FROM e GROUP BY 1),
k AS (SELECT CAST(range AS BIGINT) AS k FROM range({PARTS})),
y0 AS (SELECT id, load, k, 1.0 + (id * (k + 1)) % 7 AS sh FROM a CROSS JOIN k),
y AS (SELECT id, load, k, sh / sum(sh) OVER (PARTITION BY id) AS y FROM y0),
n AS (SELECT k, sum(y) AS s, sum(y * coalesce(deg, 0)) AS vol, sum(y * load) AS load FROM y LEFT JOIN dg USING (id) GROUP BY 1),
i AS (SELECT x.k, sum(x.y * z.y) AS inner_ FROM e JOIN y x ON x.id = src JOIN y z ON z.id = dst AND z.k = x.k GROUP BY 1),
u AS (SELECT n.*, inner_ FROM n JOIN i USING (k)),
b AS (SELECT sum((load - t) * (load - t)) AS raw, max(t) AS t FROM (SELECT load, avg(load) OVER () AS t FROM u))"""


def _sums(spark, sf_dir) -> DataFrame:
    graph = events_graph(spark, sf_dir)
    return G.soft_sums(graph, _soft(graph))


@add("soft_sums", f'{_SOFT} SELECT k, round(s, 6) AS s, round(vol, 6) AS vol, round(load, 6) AS load, round(inner_, 6) AS "inner" FROM u')
def _(spark, sf_dir):
    return rounded(_sums(spark, sf_dir))


@add("expected_ncut_cut", f"{_SOFT} SELECT round(sum((vol - inner_) / vol), 6) AS expected_ncut FROM u")
def _(spark, sf_dir):
    return rounded(G.expected_ncut(_sums(spark, sf_dir), "cut"))


@add("expected_ncut_printed", f"{_SOFT} SELECT round(sum((s * s - inner_) / vol), 6) AS expected_ncut FROM u")
def _(spark, sf_dir):
    return rounded(G.expected_ncut(_sums(spark, sf_dir), "printed"))


@add("balance_penalty", f"{_SOFT} SELECT round(raw / (t * t), 6) AS balance FROM b")
def _(spark, sf_dir):
    return rounded(G.balance_penalty(_sums(spark, sf_dir)))


@add("balance_penalty_raw", f"{_SOFT} SELECT round(raw, 2) AS balance FROM b")
def _(spark, sf_dir):
    return G.balance_penalty(_sums(spark, sf_dir), "raw").select(F.round("balance", 2).alias("balance"))


@add("objective_soft", f"{_SOFT} SELECT round(x, 6) AS expected_ncut, round(raw / (t * t), 6) AS balance, round(x + 0.5 * raw / (t * t), 6) AS objective FROM b, (SELECT sum((vol - inner_) / vol) AS x FROM u)")
def _(spark, sf_dir):
    return rounded(G.objective(_sums(spark, sf_dir), alpha=0.5))


@add("harden_soft", f"{_SOFT} SELECT id, min(k) AS part FROM (SELECT id, k, y, max(y) OVER (PARTITION BY id) AS top FROM y) WHERE y = top GROUP BY 1")
def _(spark, sf_dir):
    return rounded(G.harden(_soft(events_graph(spark, sf_dir))))


# ---------------------------------------------------------------- partitions of cells and measures

_Z = " + ".join(f"((c >> {k}) & 1) * {1 << (2 * k)} + ((r >> {k}) & 1) * {1 << (2 * k + 1)}" for k in range(6))
_PART = {
    "hash": f"((r * {COLS} + c) * 2654435761 % 4294967296) % {PARTS}",
    "stripe": f"r % {PARTS}",
    "zorder": f"least({PARTS - 1}, floor(coalesce(sum(load) OVER (ORDER BY {_Z} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * {PARTS} / sum(load) OVER ()))",
}


def parted(spark, sf_dir, how: str) -> DataFrame:
    cells = events_grid(spark, sf_dir).select("row", "col", "load")
    return {"hash": lambda: curves.hash_parts(cells, PARTS, COLS), "stripe": lambda: curves.stripe_parts(cells, PARTS), "zorder": lambda: curves.zorder_parts(cells, PARTS)}[how]()


def _part_sql(how: str) -> str:
    return f"WITH {_E}, t AS (SELECT r, c, load, CAST({_PART[how]} AS BIGINT) AS part FROM g)"


_ROOK = "p AS (SELECT x.part = y.part AS same, CAST(x.load * y.load AS DOUBLE) AS ll FROM t x JOIN t y ON (x.r = y.r AND y.c = x.c + 1) OR (x.c = y.c AND y.r = x.r + 1))"
for _how in _PART:

    def _f(spark, sf_dir, how=_how):
        return rounded(parted(spark, sf_dir, how).select("row", "col", "load", "part"))

    add(f"parts_{_how}", f'{_part_sql(_how)} SELECT r AS "row", c AS col, load, part FROM t')(_f)

    def _f(spark, sf_dir, how=_how):
        cells = parted(spark, sf_dir, how)
        raw = cells.select("row", "col", (F.col("row").cast("long") * COLS + F.col("col")).alias("block_id"))
        edges = G.both_ways(G.borders(raw).select("a", "b", F.lit(1.0).alias("w")))
        return rounded(G.edge_cut_rate(edges, cells.select((F.col("row").cast("long") * COLS + F.col("col")).alias("id"), "part")))

    add(f"edge_cut_rate_{_how}", f"{_part_sql(_how)}, {_ROOK} SELECT round(avg(CASE WHEN same THEN 0.0 ELSE 1.0 END), 6) AS edge_cut_rate FROM p")(_f)

    def _f(spark, sf_dir, how=_how):
        return rounded(G.proximity(parted(spark, sf_dir, how)))

    add(f"proximity_rook_{_how}", f"{_part_sql(_how)}, {_ROOK} SELECT round(100 * avg(CASE WHEN same THEN 1.0 ELSE 0.0 END), 6) AS proximity FROM p")(_f)


@add("proximity_load", f"{_part_sql('zorder')}, {_ROOK} SELECT round(100 * sum(CASE WHEN same THEN ll ELSE 0 END) / sum(ll), 6) AS proximity FROM p")
def _(spark, sf_dir):
    return rounded(G.proximity(parted(spark, sf_dir, "zorder"), weight="load"))


@add("proximity_queen", f"{_part_sql('zorder')}, p AS (SELECT x.part = y.part AS same FROM t x JOIN t y ON (x.r < y.r OR (x.r = y.r AND x.c < y.c)) AND greatest(abs(x.r - y.r), abs(x.c - y.c)) <= 1) SELECT round(100 * avg(CASE WHEN same THEN 1.0 ELSE 0.0 END), 6) AS proximity FROM p")
def _(spark, sf_dir):
    return rounded(G.proximity(parted(spark, sf_dir, "zorder"), neigh="queen"))


@add("proximity_radius2", f"{_part_sql('zorder')}, p AS (SELECT x.part = y.part AS same, 1.0 / greatest(abs(x.r - y.r), abs(x.c - y.c)) AS w FROM t x JOIN t y ON (x.r < y.r OR (x.r = y.r AND x.c < y.c)) AND greatest(abs(x.r - y.r), abs(x.c - y.c)) <= 2) SELECT round(100 * sum(CASE WHEN same THEN w ELSE 0 END) / sum(w), 6) AS proximity FROM p")
def _(spark, sf_dir):
    return rounded(G.proximity(parted(spark, sf_dir, "zorder"), 2, "distance"))


_LOADS = f"{_part_sql('stripe')}, l AS (SELECT k, coalesce(sum(load), 0) AS load FROM range({PARTS}) x(k) LEFT JOIN t ON part = k GROUP BY 1), v AS (SELECT load / avg(load) OVER () AS rel FROM l)"
for _how, _x in {"max": "max(rel) - 1", "mean_abs": "avg(abs(rel - 1))", "cv": "sqrt(avg((rel - 1) * (rel - 1)))"}.items():

    def _f(spark, sf_dir, how=_how):
        return rounded(G.imbalance(parted(spark, sf_dir, "stripe"), PARTS, how))

    add(f"imbalance_{_how}", f"{_LOADS} SELECT round(100 * ({_x}), 6) AS imbalance FROM v")(_f)


@add("traj_segments", f"""WITH p AS (SELECT user_id, epoch_us(ts) AS t, CAST(user_id AS DOUBLE) AS x, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY epoch_us(ts)) <= 43200000000 THEN 0 ELSE 1 END AS nw FROM events),
q AS (SELECT *, sum(nw) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS segment FROM p)
SELECT user_id, CAST(segment AS BIGINT) AS segment, min(t) - epoch_us(TIMESTAMP '2024-01-01') AS since, count(*) AS n FROM q GROUP BY 1, 2""")
def _(spark, sf_dir):
    segs = trajectory.segments(load(spark, sf_dir, "events", ["user_id", "ts"]), "user_id", "ts", F.col("user_id"), 43200)
    zero = F.expr("unix_micros(cast(timestamp_ntz'2024-01-01 00:00:00' as timestamp))")
    return segs.select("user_id", "segment", (F.col("start") - zero).alias("since"), "n")


@add("w7_sample_events", "SELECT event_id, user_id, event_type, round(value, 6) AS value FROM events ORDER BY (event_id * 2654435761) % 4294967296, event_id LIMIT 100000")
def _(spark, sf_dir):
    return rounded(sample_exact(load(spark, sf_dir, "events", ["event_id", "user_id", "event_type", "value"]), 100_000, F.col("event_id")))


@add("sample_events", "SELECT event_id FROM events ORDER BY (event_id * 2654435761) % 4294967296, event_id LIMIT 100000")
def _(spark, sf_dir):
    return sample_exact(load(spark, sf_dir, "events", ["event_id"]), 100_000, F.col("event_id"))


_BY_TYPE = f"""g AS (SELECT event_type, {_axis("user_id", "0.0", "(SELECT CAST(max(user_id) + 1 AS DOUBLE) FROM events)", ROWS)} AS r, {_axis(_US, "0.0", "2592000000000.0", COLS)} AS c, count(*) AS load
      FROM events WHERE event_type IS NOT NULL GROUP BY 1, 2, 3),
t AS (SELECT event_type, r, c, r % {PARTS} AS stripe, least({PARTS - 1}, floor(coalesce(sum(load) OVER (PARTITION BY event_type ORDER BY {_Z} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * {PARTS} / sum(load) OVER (PARTITION BY event_type))) AS z FROM g),
p AS (SELECT x.event_type, CASE WHEN x.z = y.z THEN 1.0 ELSE 0.0 END AS z, CASE WHEN x.stripe = y.stripe THEN 1.0 ELSE 0.0 END AS stripe FROM t x JOIN t y ON x.event_type = y.event_type AND ((x.r = y.r AND y.c = x.c + 1) OR (x.c = y.c AND y.r = x.r + 1))),
d AS (SELECT event_type, 100 * avg(z) AS p, 100 * avg(stripe) AS base FROM p GROUP BY 1)"""


@add("paper_gain_table", f"WITH {_BY_TYPE} SELECT round(avg(100 * (p / base - 1)), 6) AS gain_percent, round(avg(p - base), 6) AS gain_points FROM d")
def _(spark, sf_dir):
    """Gain in proximity of parts along the Z-order over stripes; every type of event is a dataset."""
    events = load(spark, sf_dir, "events", ["user_id", "ts", "value", "event_type"])
    types = sorted(r[0] for r in events.where("event_type IS NOT NULL").select("event_type").distinct().collect())
    spec = replace(workload(spark, sf_dir, "E", (ROWS, COLS)).spec, slice=Axis.category(F.col("event_type"), types))
    grid = Scratch(spark, "types").save(gridify(events, spec).select("slice", "row", "col", "load"), "grid")
    rows = []
    for k in range(len(types)):
        cells = grid.where(F.col("slice") == k).drop("slice")
        found = [G.proximity(parts).withColumnRenamed("proximity", name) for name, parts in (("p", curves.zorder_parts(cells, PARTS)), ("base", curves.stripe_parts(cells, PARTS)))]
        rows.append(found[0].crossJoin(found[1]))
    table = reduce(DataFrame.union, rows) if rows else spark.createDataFrame([], "p double, base double")
    return rounded(G.relative_gain(table))
