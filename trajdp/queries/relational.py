"""Registered queries: the general operators around the methods, with their SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .. import sql as surface_sql
from ..operators import histogram, relational
from ..sources import trajectories
from . import sqltext as S
from .histograms import rects, steps_of

QUERIES, SQL = {}, {}


def add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def read(s, d, t):
    return s.read.parquet(f"{d}/{t}.parquet")


def steps_sql(src: str = "li") -> str:
    return S.steps(src, 4 if src != "em" else 5)


K = "(props::JSON->>'$.k')::INTEGER"


def filters_and_joins() -> None:
    ev = lambda s, d: read(s, d, "events").withColumn("k", F.get_json_object("props", "$.k").cast("int"))
    add("r_filter_bbox", lambda s, d: ev(s, d).where(F.col("k").between(20, 39) & (F.col("value") < 64)).select("event_id", "user_id", "k"), f"SELECT event_id, user_id, {K} AS k FROM events WHERE {K} BETWEEN 20 AND 39 AND value < 64")
    add("r_filter_predicates", lambda s, d: ev(s, d).where(F.col("event_type").rlike("^(click|view)$") & ~F.col("user_id").isin(1, 2, 3) & F.col("value").isNotNull() & ~F.col("k").eqNullSafe(7)).select("event_id", "event_type"),
        f"SELECT event_id, event_type FROM events WHERE regexp_matches(event_type, '^(click|view)$') AND user_id NOT IN (1, 2, 3) AND value IS NOT NULL AND {K} IS DISTINCT FROM 7")
    add("r_project_struct", lambda s, d: read(s, d, "orders").select("o_orderkey", F.struct(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).alias("at")).select("o_orderkey", "at.y", "at.m"),
        "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m FROM orders")
    segment = "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"
    for name, hint in (("broadcast", "broadcast"), ("shuffle_hash", "shuffle_hash"), ("sort_merge", "merge")):
        add(f"r_join_{name}", lambda s, d, hint=hint: read(s, d, "orders").join(read(s, d, "customer").hint(hint), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), segment)
    rng = steps_sql() + f", {S.rectangles(16, 200)} SELECT qid, count(*) AS n FROM queries JOIN steps ON row BETWEEN r1 AND r2 AND col BETWEEN c1 AND c2 GROUP BY qid"
    inside = lambda: F.col("row").between(F.col("r1"), F.col("r2")) & F.col("col").between(F.col("c1"), F.col("c2"))
    add("r_join_range", lambda s, d: steps_of(s, d, "li").join(F.broadcast(rects(s, "li")), inside()).groupBy("qid").agg(F.count(F.lit(1)).alias("n")), rng)
    add("r_join_range_binned", lambda s, d: relational.range_binned(steps_of(s, d, "li"), rects(s, "li"), 4).groupBy("qid").agg(F.count(F.lit(1)).alias("n")), rng)
    probes = lambda s, d: read(s, d, "events").where("event_type = 'purchase'").select("user_id", F.col("ts").alias("at"), F.col("event_id").alias("probe"))
    known = lambda s, d: ev(s, d).where("event_type = 'view'").select("user_id", "ts", "k")
    add("r_join_asof", lambda s, d: relational.as_of(probes(s, d), known(s, d), "user_id", "at", "ts", "k").select("probe", "user_id", "k"),
        f"SELECT p.event_id AS probe, p.user_id, v.k FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, {K} AS k FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
    spans = lambda s, d: read(s, d, "events").groupBy("user_id", F.to_date("ts").alias("day")).agg(F.min("ts").alias("a"), F.max("ts").alias("b"))
    add("r_join_interval", lambda s, d: relational.overlapping(spans(s, d), "user_id", "a", "b"),
        "WITH s AS (SELECT user_id, ts::DATE AS day, min(ts) AS a, max(ts) AS b FROM events GROUP BY ALL) SELECT x.user_id AS user_id, y.user_id AS other, count(*) AS n FROM s x JOIN s y ON x.user_id < y.user_id AND x.a <= y.b AND y.a <= x.b GROUP BY ALL")
    add("r_join_semi", lambda s, d: read(s, d, "orders").join(read(s, d, "customer").where("c_acctbal > 5000"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 5000)")
    add("r_join_anti", lambda s, d: read(s, d, "customer").join(read(s, d, "orders").where("o_totalprice > 400000"), F.col("o_custkey") == F.col("c_custkey"), "left_anti").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 400000)")
    big = lambda s, d: read(s, d, "orders").where("o_totalprice > 450000").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    add("r_join_left", lambda s, d: read(s, d, "customer").join(big(s, d), F.col("o_custkey") == F.col("c_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).cast("long").alias("n")),
        "SELECT c_custkey, coalesce(n, 0)::BIGINT AS n FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders WHERE o_totalprice > 450000 GROUP BY o_custkey) ON o_custkey = c_custkey")
    add("r_join_full", lambda s, d: relational.histogram_difference(histogram.build(steps_of(s, d, "li")), histogram.build(steps_of(s, d, "or"))),
        steps_sql() + f", {S.hist()}, other AS ({S.steps('or', 4)}, {S.hist()} SELECT * FROM hist) SELECT coalesce(a.comp, b.comp) AS comp, coalesce(a.row, b.row) AS row, coalesce(a.col, b.col) AS col, coalesce(a.cnt, 0) - coalesce(b.cnt, 0) AS diff FROM hist a FULL JOIN other b ON a.comp = b.comp AND a.row = b.row AND a.col = b.col")
    add("r_join_cross", lambda s, d: read(s, d, "region").crossJoin(read(s, d, "nation").agg(F.count(F.lit(1)).alias("nations"))).select("r_name", "nations"), "SELECT r_name, nations FROM region CROSS JOIN (SELECT count(*) AS nations FROM nation)")
    add("r_join_self", lambda s, d: (lambda h: h.alias("a").join(h.alias("b"), (F.col("a.row") == F.col("b.row")) & (F.col("a.col") + 1 == F.col("b.col"))).select(F.col("a.row").alias("row"), F.col("a.col").alias("col"), (F.col("b.cnt") - F.col("a.cnt")).alias("step")))(histogram.build(steps_of(s, d, "li")).where("comp = 'F'")),
        steps_sql() + f", {S.hist()} SELECT a.row, a.col, b.cnt - a.cnt AS step FROM hist a JOIN hist b ON a.comp = 'F' AND b.comp = 'F' AND a.row = b.row AND a.col + 1 = b.col")


def aggregates() -> None:
    li = lambda s, d: read(s, d, "lineitem")
    add("r_agg_partial", lambda s, d: steps_of(s, d, "li").groupBy("row").agg(F.count(F.lit(1)).alias("n"), F.sum("col").alias("cols")), steps_sql() + " SELECT row, count(*) AS n, sum(col)::BIGINT AS cols FROM steps GROUP BY row")
    add("r_agg_distinct", lambda s, d: steps_of(s, d, "li").groupBy("row").agg(F.countDistinct("traj_id").alias("n")), steps_sql() + " SELECT row, count(DISTINCT traj_id) AS n FROM steps GROUP BY row")
    add("r_agg_stats", lambda s, d: li(s, d).groupBy("l_linenumber").agg(F.round(F.avg("l_quantity"), 6).alias("mean"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.sum(F.when(F.col("l_quantity") > 25, 1).otherwise(0)).alias("high")),
        "SELECT l_linenumber, round(avg(l_quantity), 6) AS mean, round(stddev_samp(l_quantity), 6) AS sd, sum((l_quantity > 25)::INTEGER)::BIGINT AS high FROM lineitem GROUP BY l_linenumber")
    add("r_agg_min_max_by", lambda s, d: read(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest")),
        "SELECT o_custkey, arg_max(o_orderkey, row(o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, row(o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY o_custkey")
    add("r_agg_collect", lambda s, d: steps_of(s, d, "or").groupBy("traj_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("step", "row", "col"))), lambda x: F.concat(x["row"].cast("string"), F.lit(":"), x["col"].cast("string"))), " ").alias("walk")),
        steps_sql("or") + " SELECT traj_id, string_agg(row || ':' || col, ' ' ORDER BY step) AS walk FROM steps GROUP BY traj_id")
    nation = lambda s, d: read(s, d, "orders").join(read(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    frm = "FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"
    add("r_rollup", lambda s, d: nation(s, d).rollup("n_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")), f"SELECT n_name, c_mktsegment, count(*) AS n {frm} GROUP BY ROLLUP (n_name, c_mktsegment)")
    add("r_cube", lambda s, d: nation(s, d).cube("n_regionkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")), f"SELECT n_regionkey, c_mktsegment, count(*) AS n {frm} GROUP BY CUBE (n_regionkey, c_mktsegment)")

    def sets(s, d):
        nation(s, d).createOrReplaceTempView("trajdp_orders_by_nation")
        return s.sql("SELECT n_regionkey, c_mktsegment, count(*) AS n FROM trajdp_orders_by_nation GROUP BY GROUPING SETS ((n_regionkey), (c_mktsegment), ())")

    add("r_grouping_sets", sets, f"SELECT n_regionkey, c_mktsegment, count(*) AS n {frm} GROUP BY GROUPING SETS ((n_regionkey), (c_mktsegment), ())")
    types = ["click", "error", "purchase", "signup", "view"]
    pivoted = ", ".join(f"count(*) FILTER (event_type = '{t}') AS {t}" for t in types)
    pivot = lambda s, d: read(s, d, "events").groupBy("user_id").pivot("event_type", types).agg(F.count(F.lit(1))).na.fill(0)
    add("r_pivot", pivot, f"SELECT user_id, {pivoted} FROM events GROUP BY user_id")
    add("r_unpivot", lambda s, d: pivot(s, d).unpivot(["user_id"], types, "event_type", "n"), f"UNPIVOT (SELECT user_id, {pivoted} FROM events GROUP BY user_id) ON {', '.join(types)} INTO NAME event_type VALUE n")


def windows_and_sets() -> None:
    faces = lambda s, d: histogram.build(steps_of(s, d, "li")).where("comp = 'F'")
    h = steps_sql() + f", {S.hist()}, f AS (SELECT row, col, cnt FROM hist WHERE comp = 'F')"
    over = lambda *o: Window.partitionBy("row").orderBy(*o)
    add("r_rank", lambda s, d: faces(s, d).select("row", "col", F.row_number().over(over(F.desc("cnt"), "col")).alias("rn"), F.rank().over(over(F.desc("cnt"))).alias("rk"), F.dense_rank().over(over(F.desc("cnt"))).alias("dr")),
        h + " SELECT row, col, row_number() OVER (PARTITION BY row ORDER BY cnt DESC, col) AS rn, rank() OVER (PARTITION BY row ORDER BY cnt DESC) AS rk, dense_rank() OVER (PARTITION BY row ORDER BY cnt DESC) AS dr FROM f")
    add("r_ntile", lambda s, d: faces(s, d).select("row", "col", F.ntile(4).over(over("cnt", "col")).alias("q")), h + " SELECT row, col, ntile(4) OVER (PARTITION BY row ORDER BY cnt, col) AS q FROM f")
    add("r_lag_lead", lambda s, d: faces(s, d).select("row", "col", F.lag("cnt").over(over("col")).alias("before"), F.lead("cnt", 1, 0.0).over(over("col")).alias("after"), F.first("cnt").over(over("col")).alias("first")),
        h + " SELECT row, col, lag(cnt) OVER w AS before, lead(cnt, 1, 0.0::DOUBLE) OVER w AS after, first_value(cnt) OVER w AS first FROM f WINDOW w AS (PARTITION BY row ORDER BY col)")
    add("r_cume_dist", lambda s, d: faces(s, d).select("row", "col", F.round(F.cume_dist().over(over("cnt")), 6).alias("cd"), F.round(F.percent_rank().over(over("cnt")), 6).alias("pr")),
        h + " SELECT row, col, round(cume_dist() OVER w, 6) AS cd, round(percent_rank() OVER w, 6) AS pr FROM f WINDOW w AS (PARTITION BY row ORDER BY cnt)")
    add("r_frame_rows", lambda s, d: faces(s, d).select("row", "col", F.round(F.avg("cnt").over(over("col").rowsBetween(-2, 2)), 6).alias("mean")), h + " SELECT row, col, round(avg(cnt) OVER (PARTITION BY row ORDER BY col ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 6) AS mean FROM f")
    add("r_frame_range", lambda s, d: read(s, d, "events").select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-86400, 0)).alias("n")),
        "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
    add("r_topk", lambda s, d: faces(s, d).orderBy(F.desc("cnt"), "row", "col").limit(10), h + " SELECT row, col, 'F' AS comp, cnt FROM f ORDER BY cnt DESC, row, col LIMIT 10")
    add("r_topk_group", lambda s, d: faces(s, d).withColumn("k", F.row_number().over(over(F.desc("cnt"), "col"))).where("k <= 3").select("row", "col", "k"), h + " SELECT row, col, k FROM (SELECT row, col, row_number() OVER (PARTITION BY row ORDER BY cnt DESC, col) AS k FROM f) WHERE k <= 3")
    half = lambda s, d, odd: read(s, d, "events").where(F.col("event_id") % 2 == odd).select(F.get_json_object("props", "$.k").cast("int").alias("k"), "event_type")
    a, b = (f"SELECT {K} AS k, event_type FROM events WHERE event_id % 2 = {x}" for x in (0, 1))
    for name, op, sql in (("union", "unionByName", "UNION ALL"), ("intersect", "intersect", "INTERSECT"), ("except", "subtract", "EXCEPT"), ("intersect_all", "intersectAll", "INTERSECT ALL"), ("except_all", "exceptAll", "EXCEPT ALL")):
        add(f"r_{name}", lambda s, d, op=op: getattr(half(s, d, 0), op)(half(s, d, 1)), f"({a}) {sql} ({b})")
    add("r_dedup", lambda s, d: steps_of(s, d, "em").dropDuplicates(["traj_id", "row", "col"]).select("traj_id", "row", "col"), steps_sql("em") + " SELECT DISTINCT traj_id, row, col FROM steps")


def functions() -> None:
    ev = lambda s, d: read(s, d, "events")
    add("r_string", lambda s, d: ev(s, d).select("event_id", F.upper("event_type").alias("u"), F.concat_ws("-", F.lpad(F.col("user_id").cast("string"), 6, "0"), F.substring("event_type", 1, 3)).alias("c"), F.regexp_extract("props", "([0-9]+)", 1).alias("n"), F.length("props").alias("l"), F.md5(F.col("event_id").cast("string")).alias("h")),
        "SELECT event_id, upper(event_type) AS u, lpad(user_id::VARCHAR, 6, '0') || '-' || substr(event_type, 1, 3) AS c, regexp_extract(props, '([0-9]+)', 1) AS n, length(props)::INTEGER AS l, md5(event_id::VARCHAR) AS h FROM events")
    add("r_datetime", lambda s, d: ev(s, d).select("event_id", F.to_date(F.date_trunc("month", "ts")).alias("m"), F.unix_timestamp("ts").alias("u"), F.hour("ts").alias("h"), F.dayofweek("ts").alias("w"), F.datediff("ts", F.lit("2020-01-01")).alias("d")),
        "SELECT event_id, date_trunc('month', ts)::DATE AS m, floor(epoch(ts))::BIGINT AS u, hour(ts)::INTEGER AS h, (dayofweek(ts) + 1)::INTEGER AS w, date_diff('day', DATE '2020-01-01', ts::DATE)::INTEGER AS d FROM events")
    add("r_math", lambda s, d: ev(s, d).select("event_id", F.round(F.log(F.col("value") + 1), 6).alias("l"), F.floor("value").alias("f"), F.shiftright(F.col("user_id"), 2).alias("s"), F.col("user_id").bitwiseAND(F.lit(7)).alias("b"), F.round(F.pow(F.col("value") / 100, 2.0), 6).alias("p")),
        "SELECT event_id, round(ln(value + 1), 6) AS l, floor(value)::BIGINT AS f, user_id >> 2 AS s, user_id & 7 AS b, round(pow(value / 100, 2), 6) AS p FROM events")
    arr = lambda s, d: read(s, d, "embeddings").select("vec_id", F.transform(F.slice("embedding", 1, 8), lambda x: F.floor(x.cast("double") * 100).cast("int")).alias("a"))
    adb = "SELECT vec_id, list_transform(embedding[1:8], lambda x: floor(x::DOUBLE * 100)::INTEGER) AS a FROM embeddings"
    add("r_array", lambda s, d: arr(s, d).select("vec_id", F.size(F.filter("a", lambda x: x > 0)).alias("up"), F.aggregate("a", F.lit(0), lambda p, x: p + x).alias("total"), F.size(F.array_distinct("a")).alias("kinds"), F.exists("a", lambda x: x > 20).alias("far"), F.array_max(F.zip_with("a", F.slice("a", 2, 7), lambda x, y: F.abs(x - y))).alias("jump")),
        f"SELECT vec_id, len(list_filter(a, lambda x: x > 0))::INTEGER AS up, list_sum(a)::INTEGER AS total, len(list_distinct(a))::INTEGER AS kinds, len(list_filter(a, lambda x: x > 20)) > 0 AS far, list_max(list_transform(range(1, 8), lambda i: abs(a[i] - a[i + 1])))::INTEGER AS jump FROM ({adb})")
    add("r_map", lambda s, d: steps_of(s, d, "cv").groupBy("traj_id", "row").agg(F.count(F.lit(1)).alias("n")).groupBy("traj_id").agg(F.map_from_entries(F.collect_list(F.struct("row", "n"))).alias("m")).select("traj_id", F.size("m").alias("rows"), F.array_max(F.map_keys("m")).alias("top"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("n")),
        steps_sql("cv") + " SELECT traj_id, count(DISTINCT row)::INTEGER AS rows, max(row) AS top, count(*) AS n FROM steps GROUP BY traj_id")
    add("r_json", lambda s, d: ev(s, d).select("event_id", F.from_json("props", "k int").alias("p")).select("event_id", "p.k", F.to_json("p").alias("j")), f"SELECT event_id, {K} AS k, '{{\"k\":' || {K} || '}}' AS j FROM events")
    add("r_scalar_subquery", lambda s, d: sql(s, d, "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 1.9 * avg(o_totalprice) FROM orders)"), "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 1.9 * avg(o_totalprice) FROM orders)")
    ex = "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 450000)"
    add("r_exists", lambda s, d: sql(s, d, ex), ex)
    cte = "WITH big AS (SELECT o_custkey, max(o_totalprice) AS p FROM orders GROUP BY o_custkey), rich AS (SELECT * FROM big WHERE p > 400000) SELECT c_mktsegment, count(*) AS n FROM rich JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"
    add("r_cte", lambda s, d: sql(s, d, cte), cte)
    add("r_udf", lambda s, d: relational.hilbert_twin(s.range(256).select((F.col("id") / 16).cast("int").alias("row"), (F.col("id") % 16).cast("int").alias("col")), 4), f"WITH RECURSIVE {_curve(4)} SELECT row, col, pos FROM curve")
    add("r_udaf", lambda s, d: relational.deviation_by(histogram.build(steps_of(s, d, "li")).where("comp = 'F'"), "row", "cnt").withColumn("dev", F.round("dev", 6)), steps_sql() + f", {S.hist()}, f AS (SELECT row, cnt, avg(cnt) OVER (PARTITION BY row) AS m FROM hist WHERE comp = 'F') SELECT row, round(sum(abs(cnt - m)), 6) AS dev FROM f GROUP BY row")
    add("r_udtf", lambda s, d: relational.segment_table(s, [(0.5, 0.5, 3.5, 0.5), (0.5, 0.5, 0.5, 2.5)]), "SELECT * FROM (VALUES (0, 0, 0, 0), (0, 1, 0, 1), (0, 2, 0, 2), (0, 3, 0, 3), (1, 0, 0, 0), (1, 1, 1, 0), (1, 2, 2, 0)) t(seg, k, row, col)")
    add("r_map_in_arrow", lambda s, d: relational.arrow_cells(trajectories.points(s, d, "li"), trajectories.box(s, d, "li", 4)), f"WITH {S.points('li')}, {S.gridded('li', 4)} SELECT traj_id, row, col FROM cells0")
    ancestors = "SELECT c.row, c.col, a.level, a.br, a.bc FROM (SELECT CAST(id DIV 8 AS INT) AS row, CAST(id % 8 AS INT) AS col FROM range(64)) c, LATERAL quad_ancestors(c.row, c.col, 3) a"
    add("r_udtf_ancestors", lambda s, d: (s.udtf.register("quad_ancestors", relational.QuadAncestors), s.sql(ancestors))[1],
        "SELECT r::INTEGER AS row, c::INTEGER AS col, l::INTEGER AS level, (r >> (3 - l))::INTEGER AS br, (c >> (3 - l))::INTEGER AS bc FROM (SELECT unnest(range(8)) AS r), (SELECT unnest(range(8)) AS c), (SELECT unnest(range(4)) AS l)")

    def surface(s, d):
        surface_sql.register(s, d, "cv", 4, 50, "keep")
        return s.sql("SELECT qid, range_count(r1, r2, c1, c2) AS ans, hilbert_index(r1, c1, 4) AS pos FROM queries")

    add("r_sql_surface", surface, S.steps("cv", 4).replace("WITH RECURSIVE ", f"WITH RECURSIVE {_curve(4)}, ") + f", {S.hist()}, {S.rectangles(16, 50)}, {S.answers()} SELECT qid, ans, pos FROM answers JOIN queries USING (qid) JOIN curve ON row = r1 AND col = c1")
    add("r_sample_hash", lambda s, d: steps_of(s, d, "li").where(relational.hash_fraction("traj_id", 11) < 0.1).select("traj_id", "step"), steps_sql() + f" SELECT traj_id, step FROM steps WHERE {S.uniform(11, 'rows', 'traj_id')} < 0.1")
    add("r_sample_by", lambda s, d: ev(s, d).sampleBy("event_type", {"view": 0.5, "click": 0.1}, seed=3).groupBy("event_type").count())


def _curve(res: int) -> str:
    from .privacy import hilbert_sql

    return hilbert_sql(res)


def sql(s, d, text: str):
    for t in ("orders", "customer"):
        read(s, d, t).createOrReplaceTempView(t)
    return s.sql(text)


filters_and_joins()
aggregates()
windows_and_sets()
functions()
