"""Registered queries: points, steps, histograms and answers, with their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import answering, histogram, mechanisms, walks, workload
from ..sources import trajectories
from . import sqltext as S

RES = {"li": 4, "em": 5, "ev": 4, "or": 4, "cv": 4}
M = 200
QUERIES, SQL = {}, {}


def steps_of(spark, d: str, src: str, loops: str = "keep", res: int | None = None):
    grid = trajectories.box(spark, d, src, res or RES[src])
    return walks.walk_steps(trajectories.points(spark, d, src), grid, policy=loops)


def rects(spark, src: str, m: int = M):
    return workload.random_rectangles(spark, 1 << RES[src], m)


def rounded(df, *cols: str, digits: int = 6):
    return df.withColumns({c: F.round(c, digits) for c in cols})


def add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def register() -> None:
    hist_cols, step_cols = "comp, row, col, cnt", "traj_id, step, row, col"
    for src in RES:
        res, side = RES[src], 1 << RES[src]
        grid = lambda s, d, src=src: trajectories.box(s, d, src, RES[src])
        pts = lambda s, d, src=src: trajectories.points(s, d, src)
        add(f"m_src_{src}", lambda s, d, pts=pts: rounded(pts(s, d), "x", "y"), f"WITH {S.points(src)} SELECT traj_id, seq, round(x, 6) AS x, round(y, 6) AS y FROM points")
        add(f"m_grid_{src}", lambda s, d, pts=pts, grid=grid: walks.assign(pts(s, d), grid(s, d)), f"WITH {S.points(src)}, {S.gridded(src, res)} SELECT {step_cols} FROM cells0")
        add(f"m_collapse_{src}", lambda s, d, pts=pts, grid=grid: walks.collapse(walks.assign(pts(s, d), grid(s, d))),
            f"WITH {S.points(src)}, {S.gridded(src, res)}, {S.collapsed()} SELECT {step_cols} FROM cells1")
        add(f"m_fill_staircase_{src}", lambda s, d, src=src: steps_of(s, d, src), S.steps(src, res) + f" SELECT {step_cols} FROM steps")
        add(f"m_length_{src}", lambda s, d, src=src: walks.length(steps_of(s, d, src)), S.steps(src, res) + " SELECT traj_id, count(*) AS k FROM steps GROUP BY traj_id")
        for mode in ("visits", "distinct"):
            add(f"m_hist_{mode}_{src}", lambda s, d, src=src, mode=mode: histogram.build(steps_of(s, d, src), mode), S.steps(src, res) + f", {S.hist(mode)} SELECT {hist_cols} FROM hist")
        exact = S.steps(src, res) + f", {S.rectangles(side, M)} SELECT qid, count(DISTINCT traj_id)::DOUBLE AS ans FROM queries LEFT JOIN steps ON row BETWEEN r1 AND r2 AND col BETWEEN c1 AND c2 GROUP BY qid"
        add(f"q_exact_{src}", lambda s, d, src=src: answering.exact(steps_of(s, d, src), rects(s, src)), exact)
        direct = S.steps(src, res) + f", {S.hist()}, {S.rectangles(side, M)}, {S.answers()} SELECT qid, ans FROM answers"
        add(f"q_hist_{src}", lambda s, d, src=src: answering.from_hist(histogram.build(steps_of(s, d, src)), rects(s, src)), direct)
        add(f"q_prefix_{src}", lambda s, d, src=src: answering.from_prefix(answering.prefix(histogram.build(steps_of(s, d, src)), 1 << RES[src]), rects(s, src)), direct)

    add("m_sample_li", lambda s, d: trajectories.sample(trajectories.points(s, d, "li"), 500, 7),
        f"WITH {S.points('li')}, chosen AS (SELECT traj_id FROM (SELECT DISTINCT traj_id FROM points) ORDER BY {S.uniform(7, 'sample', 'traj_id')}, traj_id LIMIT 500) SELECT traj_id, seq, x, y FROM points WHERE traj_id IN (SELECT traj_id FROM chosen)")
    add("m_fill_drop_ev", lambda s, d: walks.fill(walks.collapse(walks.assign(trajectories.points(s, d, "ev"), trajectories.box(s, d, "ev", 4))), "drop"),
        f"""WITH {S.points('ev')}, {S.gridded('ev', 4)}, {S.collapsed()},
gaps AS (SELECT *, coalesce((abs(row - lag(row) OVER w) + abs(col - lag(col) OVER w) <> 1)::INTEGER, 0) AS g FROM cells1 WINDOW w AS (PARTITION BY traj_id ORDER BY step)),
pieces AS (SELECT traj_id * 1000 + sum(g) OVER (PARTITION BY traj_id ORDER BY step) AS piece, step, row, col FROM gaps)
SELECT piece::BIGINT AS traj_id, row_number() OVER (PARTITION BY piece ORDER BY step) - 1 AS step, row, col FROM pieces""")
    add("m_fill_segment_em", lambda s, d: walks.fill_segments(trajectories.points(s, d, "em"), trajectories.box(s, d, "em", 5)))
    add("m_generate", lambda s, d: trajectories.generate_for(s.read.parquet(f"{d}/events.parquet").select(F.col("user_id").alias("traj_id")).distinct(), 10, 4.0, 7))
    for src in ("ev", "em"):
        add(f"m_loop_erase_{src}", lambda s, d, src=src: steps_of(s, d, src, "erase"), S.steps(src, RES[src], "erase") + f" SELECT {step_cols} FROM steps")
    add("m_hist_invlen_li", lambda s, d: rounded(histogram.build(steps_of(s, d, "li"), weight="inv_len"), "cnt"),
        S.steps("li", 4) + f", {S.shares(16)} SELECT 'F' AS comp, row, col, round(cnt, 6) AS cnt FROM shares WHERE cnt > 0")
    add("m_hist_dense_em", lambda s, d: histogram.densify(histogram.build(steps_of(s, d, "em")), 32), S.steps("em", 5) + f", {S.hist()}, {S.dense(32)} SELECT {hist_cols} FROM full_hist")
    add("m_cells_em", lambda s, d: histogram.cells(histogram.build(steps_of(s, d, "em"))),
        S.steps("em", 5) + f""", {S.hist()}, {S.dense(32)}, c AS (SELECT g.row, g.col, f.cnt AS f, coalesce(l.cnt, 0) AS e_left, coalesce(r.cnt, 0) AS e_right, coalesce(u.cnt, 0) AS e_up, coalesce(b.cnt, 0) AS e_down
FROM grid g JOIN full_hist f ON f.comp = 'F' AND f.row = g.row AND f.col = g.col
LEFT JOIN full_hist l ON l.comp = 'V' AND l.row = g.row AND l.col = g.col - 1 LEFT JOIN full_hist r ON r.comp = 'V' AND r.row = g.row AND r.col = g.col
LEFT JOIN full_hist u ON u.comp = 'H' AND u.row = g.row - 1 AND u.col = g.col LEFT JOIN full_hist b ON b.comp = 'H' AND b.row = g.row AND b.col = g.col)
SELECT * FROM c WHERE f + e_left + e_right + e_up + e_down > 0""")
    add("m_res_em", lambda s, d: histogram.at_resolution(trajectories.points(s, d, "em"), trajectories.box(s, d, "em", 5), 2, policy="keep"), S.steps("em", 3) + f", {S.hist()} SELECT {hist_cols} FROM hist")
    viol = f", {S.hist()}, ends AS (SELECT e.comp, e.row, e.col, e.cnt, least(coalesce(a.cnt, 0), coalesce(b.cnt, 0)) AS low FROM hist e LEFT JOIN hist a ON a.comp = 'F' AND a.row = e.row AND a.col = e.col LEFT JOIN hist b ON b.comp = 'F' AND b.row = e.row + (e.comp = 'H')::INTEGER AND b.col = e.col + (e.comp = 'V')::INTEGER WHERE e.comp <> 'F') SELECT comp, row, col, cnt, low, cnt - low AS excess FROM ends WHERE cnt > low"
    add("m_violations_ev", lambda s, d: histogram.violations(histogram.build(steps_of(s, d, "ev"))), S.steps("ev", 4) + viol)

    def nested(s):
        q = rects(s, "em")
        return q.select("qid", ((F.col("r1") + F.col("r2")) / 2).cast("int").alias("r1"), F.col("r2"), F.col("c1"), ((F.col("c1") + F.col("c2")) / 2).cast("int").alias("c2"),
                        F.col("r1").alias("o_r1"), F.col("r2").alias("o_r2"), F.col("c1").alias("o_c1"), F.col("c2").alias("o_c2"))

    add("m_monotone_em", lambda s, d: answering.monotone_violations(histogram.build(steps_of(s, d, "em")), nested(s)),
        S.steps("em", 5) + f", {S.hist()}, {S.rectangles(32, M)}, inner_q AS (SELECT qid, (r1 + r2) // 2 AS r1, r2, c1, (c1 + c2) // 2 AS c2 FROM queries), {S.answers()}, {S.answers(name='small', queries='inner_q')} SELECT qid, s.ans AS \"inner\", a.ans AS \"outer\" FROM small s JOIN answers a USING (qid) WHERE s.ans > a.ans + 1e-9")
    one = "(SELECT min(traj_id) FROM points)"
    first = lambda s, d: trajectories.points(s, d, "li").agg(F.min("traj_id"), F.max("traj_id")).first()
    for how, sql in (
        ("remove", f"SELECT * FROM points WHERE traj_id <> {one}"), ("add", f"SELECT * FROM points UNION ALL SELECT -1 - traj_id, seq, x, y FROM points WHERE traj_id = {one}"),
        ("change", f"SELECT * FROM points WHERE traj_id <> {one} UNION ALL SELECT {one}, seq, x, y FROM points WHERE traj_id = (SELECT max(traj_id) FROM points)")):
        add(f"m_neighbour_{how}_li", lambda s, d, how=how: mechanisms.neighbour(trajectories.points(s, d, "li"), how, *first(s, d)), f"WITH {S.points('li')} {sql}")
    add("q_approx_li", lambda s, d: answering.exact(steps_of(s, d, "li"), rects(s, "li"), approx=True))
    add("q_segments_ev", lambda s, d: answering.segments(steps_of(s, d, "ev"), rects(s, "ev")),
        S.steps("ev", 4) + f""", {S.rectangles(16, M)}, met AS (SELECT qid, traj_id, step, step - row_number() OVER (PARTITION BY qid, traj_id ORDER BY step) AS g FROM queries JOIN steps ON row BETWEEN r1 AND r2 AND col BETWEEN c1 AND c2)
SELECT q.qid, count(DISTINCT (traj_id, g)) FILTER (traj_id IS NOT NULL)::DOUBLE AS ans FROM queries q LEFT JOIN met USING (qid) GROUP BY q.qid""")
    add("q_faces_only_li", lambda s, d: answering.faces_only(histogram.build(steps_of(s, d, "li")), rects(s, "li")), S.steps("li", 4) + f", {S.hist()}, {S.rectangles(16, M)}, {S.answers(faces=True)} SELECT qid, ans FROM answers")
    add("q_gen_sorted", lambda s, d: rects(s, "em"), f"WITH {S.rectangles(32, M)} SELECT * FROM queries")
    total = 32 * 33 // 2
    pair = lambda k: f"floor({S.uniform(7, k, 'qid')} * {total})::BIGINT"
    hi = lambda j: f"floor((sqrt(8.0 * {j} + 1) - 1) / 2)::INTEGER"
    add("q_gen_pairs", lambda s, d: workload.random_rectangles(s, 32, M, method="pairs"),
        f"WITH j AS (SELECT qid, {pair('pr')} AS a, {pair('pc')} AS b FROM (SELECT unnest(range({M})) AS qid)), h AS (SELECT *, {hi('a')} AS r2, {hi('b')} AS c2 FROM j) SELECT qid, (a - r2 * (r2 + 1) // 2)::INTEGER AS r1, r2, (b - c2 * (c2 + 1) // 2)::INTEGER AS c1, c2 FROM h")
    add("q_coverage", lambda s, d: workload.coverage(rects(s, "em"), 32),
        f"WITH {S.rectangles(32, M)} SELECT r::INTEGER AS row, c::INTEGER AS col, count(qid) AS hits FROM (SELECT unnest(range(32)) AS r), (SELECT unnest(range(32)) AS c) LEFT JOIN queries ON r BETWEEN r1 AND r2 AND c BETWEEN c1 AND c2 GROUP BY ALL")
    add("q_overlap_pairs", lambda s, d: workload.overlaps(rects(s, "em"), rects(s, "em")),
        f"WITH {S.rectangles(32, M)} SELECT * FROM (SELECT a.qid, b.qid AS qid2, greatest(0, least(a.r2, b.r2) - greatest(a.r1, b.r1) + 1)::BIGINT * greatest(0, least(a.c2, b.c2) - greatest(a.c1, b.c1) + 1) AS cells FROM queries a JOIN queries b ON a.qid < b.qid) WHERE cells > 0")
    add("q_sensitivity_or", lambda s, d: mechanisms.query_sensitivity(steps_of(s, d, "or", "erase"), rects(s, "or")),
        S.steps("or", 4, "erase") + f""", {S.rectangles(16, M)}, met AS (SELECT qid, traj_id, step - row_number() OVER (PARTITION BY qid, traj_id ORDER BY step) AS g FROM queries JOIN steps ON row BETWEEN r1 AND r2 AND col BETWEEN c1 AND c2),
runs AS (SELECT qid, traj_id, count(DISTINCT g) AS n FROM met GROUP BY ALL) SELECT q.qid, coalesce(max(n), 0)::BIGINT AS most FROM queries q LEFT JOIN runs USING (qid) GROUP BY q.qid""")


register()
