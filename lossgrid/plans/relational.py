"""Relational operators around the methods, each beside its DuckDB text."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import scalar as S
from ..operators import joins as J
from ..sources.io import load, text_attributes
from .queries import COLS, PARTS, _E, _blocks_out, _merged_sql, _part_sql, events_grid, merged, parted, rounded

QUERIES: dict = {}
SQL: dict[str, str] = {}


def add(name: str, sql: str):
    def keep(f):
        QUERIES[f"op_{name}"] = f
        SQL[f"op_{name}"] = sql
        return f

    return keep


@add("projection", "SELECT event_id, CAST(floor(value / 10) AS BIGINT) AS value_bin, CASE WHEN value >= 100 THEN 'high' WHEN value >= 20 THEN 'middle' ELSE 'low' END AS level, round(sqrt(value) + ln(1 + value), 6) AS mixed FROM events")
def _(spark, sf_dir):
    level = F.when(F.col("value") >= 100, "high").when(F.col("value") >= 20, "middle").otherwise("low")
    return rounded(load(spark, sf_dir, "events").select("event_id", F.floor(F.col("value") / 10).cast("long").alias("value_bin"), level.alias("level"), (F.sqrt("value") + F.log1p("value")).alias("mixed")))


@add("filter_box", "SELECT event_id, user_id FROM events WHERE user_id BETWEEN 10 AND 60 AND ts >= TIMESTAMP '2024-01-05' AND ts < TIMESTAMP '2024-01-09' AND event_type IN ('click', 'view')")
def _(spark, sf_dir):
    df = load(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type"])
    time = (F.col("ts") >= F.expr("timestamp_ntz'2024-01-05 00:00:00'")) & (F.col("ts") < F.expr("timestamp_ntz'2024-01-09 00:00:00'"))
    return df.where(F.col("user_id").between(10, 60) & time & F.col("event_type").isin("click", "view")).select("event_id", "user_id")


@add("filter_null_safe", "SELECT d.doc_id, quality FROM documents d LEFT JOIN labels USING (doc_id) WHERE quality IS NOT DISTINCT FROM NULL AND source LIKE 'src1%'")
def _(spark, sf_dir):
    df = load(spark, sf_dir, "documents", ["doc_id", "source"]).join(load(spark, sf_dir, "labels", ["doc_id", "quality"]), "doc_id", "left")
    return df.where(F.col("quality").eqNullSafe(F.lit(None)) & F.col("source").like("src1%")).select("doc_id", "quality")


_ITEMS = 'SELECT p_brand, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1'
for _hint in ("broadcast", "merge", "shuffle_hash"):

    def _f(spark, sf_dir, hint=_hint):
        items = load(spark, sf_dir, "lineitem", ["l_partkey", "l_quantity"])
        part = load(spark, sf_dir, "part", ["p_partkey", "p_brand"]).hint(hint)
        return items.join(part, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))

    add(f"join_{_hint}", _ITEMS)(_f)


@add("join_salted", "SELECT o_custkey, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def _(spark, sf_dir):
    orders = load(spark, sf_dir, "orders", ["o_custkey"])
    return J.salted(orders, load(spark, sf_dir, "customer", ["c_custkey"]).withColumnRenamed("c_custkey", "o_custkey"), "o_custkey", 4).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))


@add("semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 400000)")
def _(spark, sf_dir):
    big = load(spark, sf_dir, "orders", ["o_custkey", "o_totalprice"]).where("o_totalprice > 400000")
    return load(spark, sf_dir, "customer", ["c_custkey"]).join(big, F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@add("anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def _(spark, sf_dir):
    return load(spark, sf_dir, "documents", ["doc_id"]).join(load(spark, sf_dir, "labels", ["doc_id"]), "doc_id", "left_anti")


@add("anti_empty_cells", f'WITH {_E} SELECT a.r AS "row", b.c AS col FROM range(30) a(r), range(30) b(c) WHERE NOT EXISTS (SELECT 1 FROM g WHERE g.r = a.r AND g.c = b.c)')
def _(spark, sf_dir):
    every = spark.range(30).select(F.col("id").alias("row"), F.explode(F.sequence(F.lit(0), F.lit(29))).alias("col"))
    return rounded(every.join(events_grid(spark, sf_dir), ["row", "col"], "left_anti"))


@add("outer_left", "SELECT d.doc_id, coalesce(toxic, -1) AS toxic FROM documents d LEFT JOIN labels USING (doc_id)")
def _(spark, sf_dir):
    both = load(spark, sf_dir, "documents", ["doc_id"]).join(load(spark, sf_dir, "labels", ["doc_id", "toxic"]), "doc_id", "left")
    return both.select("doc_id", F.coalesce("toxic", F.lit(-1)).alias("toxic"))


@add("outer_full", f"""{_part_sql("stripe")}, x AS (SELECT r, c, load FROM t WHERE part = 0), y AS (SELECT r, c, load FROM t WHERE r < 10)
SELECT coalesce(x.r, y.r) AS "row", coalesce(x.c, y.c) AS col, coalesce(x.load, 0) AS a, coalesce(y.load, 0) AS b FROM x FULL JOIN y ON x.r = y.r AND x.c = y.c""")
def _(spark, sf_dir):
    t = parted(spark, sf_dir, "stripe")
    x, y = t.where("part = 0").select("row", "col", F.col("load").alias("a")), t.where("row < 10").select("row", "col", F.col("load").alias("b"))
    return rounded(x.join(y, ["row", "col"], "full").fillna(0, ["a", "b"]))


@add("range_join", f"WITH {_merged_sql('hv')} SELECT r AS \"row\", c AS col, r0 * {COLS} + c0 AS block_id FROM g JOIN b2 ON g.r BETWEEN r0 AND r1 AND g.c BETWEEN c0 AND c1")
def _(spark, sf_dir):
    found = J.in_blocks(events_grid(spark, sf_dir).select("row", "col"), merged(spark, sf_dir, "hv").select("r0", "r1", "c0", "c1"), 8)
    return rounded(found.select("row", "col", (F.col("r0").cast("long") * COLS + F.col("c0")).alias("block_id")))


@add("as_of", """SELECT v.event_id, p.value FROM (SELECT event_id, user_id, ts FROM events WHERE event_type = 'view') v
ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) p ON v.user_id = p.user_id AND v.ts >= p.ts""")
def _(spark, sf_dir):
    df = load(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type", "value"])
    views = df.where("event_type = 'view'").select("event_id", "user_id", "ts")
    buys = df.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return J.as_of(views, buys, "user_id", "ts", "value").select("event_id", "value")


@add("distinct_agg", f"WITH {_E} SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT CAST(ts AS DATE)) AS days FROM events GROUP BY 1")
def _(spark, sf_dir):
    return load(spark, sf_dir, "events", ["event_type", "user_id", "ts"]).groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct(F.to_date("ts")).alias("days"))


_P2 = "orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"


def _orders(spark, sf_dir) -> DataFrame:
    o = load(spark, sf_dir, "orders", ["o_custkey", "o_orderdate", "o_totalprice", "o_orderstatus"])
    c, n = load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]), load(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).withColumn("y", F.year("o_orderdate").cast("long"))


for _kind in ("rollup", "cube"):

    def _f(spark, sf_dir, kind=_kind):
        return getattr(_orders(spark, sf_dir), kind)("n_regionkey", "y").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"), F.grouping_id().alias("level")).select("n_regionkey", "y", "n", "total", "level")

    add(_kind, f"SELECT n_regionkey, year(o_orderdate) AS y, count(*) AS n, round(sum(o_totalprice), 2) AS total, grouping_id(n_regionkey, year(o_orderdate)) AS level FROM {_P2} GROUP BY {_kind}(n_regionkey, year(o_orderdate))")(_f)


@add("grouping_sets", f"SELECT n_regionkey, o_orderstatus, count(*) AS n FROM {_P2} GROUP BY GROUPING SETS ((n_regionkey), (o_orderstatus), ())")
def _(spark, sf_dir):
    _orders(spark, sf_dir).createOrReplaceTempView("lg_orders")
    return spark.sql("SELECT n_regionkey, o_orderstatus, count(*) AS n FROM lg_orders GROUP BY GROUPING SETS ((n_regionkey), (o_orderstatus), ())")


@add("pivot", f"SELECT n_regionkey, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM {_P2} GROUP BY 1")
def _(spark, sf_dir):
    out = _orders(spark, sf_dir).groupBy("n_regionkey").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).fillna(0)
    return out.select("n_regionkey", F.col("F").alias("f"), F.col("O").alias("o"), F.col("P").alias("p"))


@add("unpivot", "SELECT l_orderkey, l_linenumber, l_quantity AS q, k, v FROM (SELECT *, 'discount' AS k, l_discount AS v FROM lineitem UNION ALL SELECT *, 'tax' AS k, l_tax AS v FROM lineitem)")
def _(spark, sf_dir):
    items = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_tax"])
    named = items.select("l_orderkey", "l_linenumber", F.col("l_quantity").alias("q"), F.col("l_discount").alias("discount"), F.col("l_tax").alias("tax"))
    return named.unpivot(["l_orderkey", "l_linenumber", "q"], ["discount", "tax"], "k", "v")


@add("rank_windows", f"""{_part_sql("zorder")} SELECT r AS "row", c AS col, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd
FROM t WINDOW w AS (PARTITION BY part ORDER BY load DESC, r, c), v AS (PARTITION BY part ORDER BY load DESC)""")
def _(spark, sf_dir):
    w = Window.partitionBy("part").orderBy(F.col("load").desc(), "row", "col")
    v = Window.partitionBy("part").orderBy(F.col("load").desc())
    t = parted(spark, sf_dir, "zorder")
    return rounded(t.select("row", "col", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"), F.percent_rank().over(v).alias("pr"), F.cume_dist().over(v).alias("cd")))


@add("value_windows", f"""WITH {_E} SELECT r AS "row", c AS col, coalesce(lag(load) OVER w, -1) AS before, coalesce(lead(load) OVER w, -1) AS after, first_value(load) OVER w AS first_, last_value(load) OVER (PARTITION BY r ORDER BY c ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_, coalesce(nth_value(load, 3) OVER (PARTITION BY r ORDER BY c ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), -1) AS third FROM g WINDOW w AS (PARTITION BY r ORDER BY c)""")
def _(spark, sf_dir):
    w = Window.partitionBy("row").orderBy("col")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    g = events_grid(spark, sf_dir)
    return rounded(g.select("row", "col", F.coalesce(F.lag("load").over(w), F.lit(-1)).alias("before"), F.coalesce(F.lead("load").over(w), F.lit(-1)).alias("after"), F.first("load").over(w).alias("first_"), F.last("load").over(whole).alias("last_"), F.coalesce(F.nth_value("load", 3).over(whole), F.lit(-1)).alias("third")))


@add("frames", f"""WITH {_E} SELECT r AS "row", c AS col, CAST(sum(load) OVER (PARTITION BY r ORDER BY c ROWS UNBOUNDED PRECEDING) AS BIGINT) AS upto, round(avg(val) OVER (PARTITION BY r ORDER BY c ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 6) AS smooth, CAST(sum(load) OVER (PARTITION BY r ORDER BY c RANGE BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS recent FROM g""")
def _(spark, sf_dir):
    w = Window.partitionBy("row").orderBy("col")
    g = events_grid(spark, sf_dir)
    return rounded(g.select("row", "col", F.sum("load").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("upto"), F.avg("val").over(w.rowsBetween(-1, 1)).alias("smooth"), F.sum("load").over(w.rangeBetween(-2, 0)).alias("recent")))


@add("top_k", f'WITH {_E} SELECT r AS "row", c AS col, load FROM g ORDER BY load DESC, r, c LIMIT 20')
def _(spark, sf_dir):
    return rounded(events_grid(spark, sf_dir).select("row", "col", "load").orderBy(F.col("load").desc(), "row", "col").limit(20))


@add("top_k_per_part", f'{_part_sql("hash")} SELECT part, r AS "row", c AS col, load FROM (SELECT *, row_number() OVER (PARTITION BY part ORDER BY load DESC, r, c) AS k FROM t) WHERE k <= 3')
def _(spark, sf_dir):
    w = Window.partitionBy("part").orderBy(F.col("load").desc(), "row", "col")
    return rounded(parted(spark, sf_dir, "hash").withColumn("k", F.row_number().over(w)).where("k <= 3").select("part", "row", "col", "load"))


for _name, _op in {"union_all": "unionByName", "intersect": "intersect", "except": "exceptAll"}.items():

    def _f(spark, sf_dir, op=_op):
        t = parted(spark, sf_dir, "stripe")
        return rounded(getattr(t.where("part < 2").select("row", "col"), op)(t.where("part in (1, 3)").select("row", "col")))

    add(f"set_{_name}", f'{_part_sql("stripe")} SELECT r AS "row", c AS col FROM t WHERE part < 2 {dict(union_all="UNION ALL", intersect="INTERSECT").get(_name, "EXCEPT ALL")} SELECT r, c FROM t WHERE part IN (1, 3)')(_f)


@add("approx_distinct_error", "SELECT true AS within")
def _(spark, sf_dir):
    """HyperLogLog sketches of each type, merged, stay within 5 % of the exact count."""
    df = load(spark, sf_dir, "events", ["event_type", "event_id"])
    parts = df.groupBy("event_type").agg(F.hll_sketch_agg("event_id", F.lit(12)).alias("s"))
    est = parts.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("est")).join(df.agg(F.count_distinct("event_id").alias("n")))
    return est.select((F.abs(F.col("est") - F.col("n")) <= 0.05 * F.col("n")).alias("within"))


@add("approx_quantile_error", "SELECT true AS within")
def _(spark, sf_dir):
    df = load(spark, sf_dir, "events", ["value"])
    both = df.agg(F.percentile_approx("value", 0.5, 10000).alias("a"), F.percentile("value", 0.49).alias("lo"), F.percentile("value", 0.51).alias("hi"))
    return both.select(F.col("a").between(F.col("lo"), F.col("hi")).alias("within"))


@add("dedup_posts", "SELECT min(doc_id) AS doc_id, md5(text) AS digest, count(*) AS n FROM documents GROUP BY 2")
def _(spark, sf_dir):
    return load(spark, sf_dir, "documents", ["doc_id", "text"]).groupBy(F.md5(F.col("text").cast("binary")).alias("digest")).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("n")).select("doc_id", "digest", "n")


@add("json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, '{\"k\":' || CAST(json_extract(props, '$.k') AS VARCHAR) || '}' AS again FROM events")
def _(spark, sf_dir):
    df = load(spark, sf_dir, "events", ["event_id", "props"])
    return df.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.to_json(F.from_json("props", "k int")).alias("again"))


@add("dates", "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(isodow(o_orderdate) AS BIGINT) AS d, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS since FROM orders")
def _(spark, sf_dir):
    df = load(spark, sf_dir, "orders", ["o_orderkey", "o_orderdate"])
    return df.select("o_orderkey", F.date_format(F.trunc("o_orderdate", "month"), "yyyy-MM-dd").alias("m"), F.year("o_orderdate").cast("long").alias("y"), (F.weekday("o_orderdate") + 1).cast("long").alias("d"), F.datediff("o_orderdate", F.lit("1995-01-01")).cast("long").alias("since"))


@add("windows_tumbling", "SELECT event_type, CAST(epoch(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2024-01-01')) - epoch(TIMESTAMP '2024-01-01') AS BIGINT) // 3600 AS hour_, count(*) AS n FROM events GROUP BY 1, 2")
def _(spark, sf_dir):
    hour = F.expr("timestampdiff(HOUR, timestamp_ntz'2024-01-01 00:00:00', w.start)")
    return load(spark, sf_dir, "events", ["event_type", "ts"]).groupBy("event_type", F.window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("event_type", hour.alias("hour_"), "n")


@add("sessions", """WITH p AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS nw FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
q AS (SELECT user_id, sum(nw) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM p) SELECT user_id, count(DISTINCT k) AS sessions, count(*) AS n FROM q GROUP BY 1""")
def _(spark, sf_dir):
    per = load(spark, sf_dir, "events", ["user_id", "ts"]).groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n"))
    return per.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("n"))


@add("text_attributes", r"""SELECT conv_id, turn, CAST(length(text) AS BIGINT) AS n_chars, CAST(len(regexp_extract_all(text, '\S+')) AS BIGINT) AS n_words, CAST(len(regexp_extract_all(text, '[.!?]+')) AS BIGINT) AS n_sentences,
round(length(regexp_replace(text, '[^A-Za-z]', '', 'g')) / length(text), 6) AS letter_share FROM conversations""")
def _(spark, sf_dir):
    out = text_attributes(load(spark, sf_dir, "conversations"))
    return rounded(out.select("conv_id", "turn", F.col("n_chars_").alias("n_chars"), "n_words", "n_sentences", "letter_share"))


@add("page_hosts", "SELECT lower(regexp_extract(url, '^[a-zA-Z][a-zA-Z0-9+.-]*://([^/:?#]+)', 1)) AS host, count(*) AS n FROM pages GROUP BY 1")
def _(spark, sf_dir):
    return load(spark, sf_dir, "pages", ["url"]).groupBy(S.host_of(F.col("url")).alias("host")).agg(F.count(F.lit(1)).alias("n"))


@add("arrays", "SELECT vec_id, len(embedding) AS dim, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm2, list_position(embedding, list_max(embedding)) - 1 AS top FROM embeddings")
def _(spark, sf_dir):
    v = F.col("embedding")
    norm2 = F.aggregate(v, F.lit(0.0), lambda acc, x: acc + x.cast("double") * x.cast("double"))
    return load(spark, sf_dir, "embeddings").select("vec_id", F.size(v).cast("long").alias("dim"), F.round(norm2, 4).alias("norm2"), (F.array_position(v, F.array_max(v)) - 1).alias("top"))


@add("sql_functions", f'WITH {_E} SELECT r * {COLS} + c AS id, round(abs(val - 50) / abs(val), 6) AS err, {" + ".join(f"((c >> {k}) & 1) * {1 << (2 * k)} + ((r >> {k}) & 1) * {1 << (2 * k + 1)}" for k in range(6))} AS z FROM g WHERE val <> 0')
def _(spark, sf_dir):
    S.register(spark)
    events_grid(spark, sf_dir).createOrReplaceTempView("lg_grid")
    return rounded(spark.sql(f"SELECT lg_cell_id(row, col, {COLS}) AS id, lg_rel_err(val, 50D) AS err, lg_zorder(row, col) AS z FROM lg_grid WHERE val <> 0"))


@add("table_function", f'WITH {_merged_sql("hv")} SELECT r AS "row", c AS col, r0, c0 FROM b2 JOIN g ON g.r BETWEEN r0 AND r1 AND g.c BETWEEN c0 AND c1 WHERE n > 3')
def _(spark, sf_dir):
    S.register(spark)
    merged(spark, sf_dir, "hv").createOrReplaceTempView("lg_blocks")
    return rounded(spark.sql("SELECT c.row, c.col, b.r0, b.c0 FROM lg_blocks b, LATERAL lg_cells_of(b.r0, b.r1, b.c0, b.c1) c WHERE b.n_cells > 3"))


@add("block_overlap", f"WITH {_merged_sql('hv')} SELECT r0, c0, (least(r1, 12) - greatest(r0, 5) + 1) * (least(c1, 20) - greatest(c0, 8) + 1) AS shared FROM b2 WHERE r0 <= 12 AND r1 >= 5 AND c0 <= 20 AND c1 >= 8")
def _(spark, sf_dir):
    b = merged(spark, sf_dir, "hv")
    shared = S.overlap(F.col("r0"), F.col("r1"), F.col("c0"), F.col("c1"), (5, 12, 8, 20))
    return rounded(b.select("r0", "c0", shared.cast("long").alias("shared")).where("shared > 0"))


@add("tag_records", f"WITH {_merged_sql('hv')} SELECT event_id, r0 * {COLS} + c0 AS block_id FROM (SELECT event_id, CAST(greatest(0, least(29, floor(CAST(user_id AS DOUBLE) * 30 / (SELECT CAST(max(user_id) + 1 AS DOUBLE) FROM events)))) AS BIGINT) AS r, CAST(greatest(0, least(29, floor(CAST((epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01 00:00:00')) AS DOUBLE) * 30 / 2592000000000.0))) AS BIGINT) AS c FROM events) e JOIN b2 ON e.r BETWEEN r0 AND r1 AND e.c BETWEEN c0 AND c1")
def _(spark, sf_dir):
    from ..operators.allocate import cell_map
    from ..operators.reduce import tag_records
    from .workloads import workload

    w = workload(spark, sf_dir, "E", (30, 30))
    records = load(spark, sf_dir, "events", ["event_id", "user_id", "ts"])
    return tag_records(records, w.spec, cell_map(merged(spark, sf_dir, "hv"), COLS)).select("event_id", "block_id")


del _blocks_out, PARTS
