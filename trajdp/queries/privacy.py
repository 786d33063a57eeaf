"""Registered queries: mechanisms, partitioning, synthesis, baselines, measures and experiments, with their SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from ..functions import curves, noise
from ..operators import answering, histogram, measures, mechanisms, quadtree, regions, walks, workload
from ..plans import baselines, estimator, experiments, frames, release, repair
from ..plans.dense import DenseHist, collected, framed, partitioned, query_array
from ..sources import trajectories
from ..storage import kept
from . import sqltext as S
from .histograms import M, RES, rects, rounded, steps_of

QUERIES, SQL = {}, {}
PART = quadtree.PartitionParams(eps1=0.5, eps2=0.5, threshold="stddev", seed=7)
PER_LEVEL = quadtree.PartitionParams(eps1=2.0, eps2=0.5, threshold="stddev", scope="per_level", seed=7)
FRESH = quadtree.PartitionParams(eps1=2.0, eps2=0.5, threshold="stddev", parent_noise="fresh", seed=7)
QUIET = quadtree.PartitionParams(threshold=5.0, noise=False)
MEAN_LENGTH = 16.0
ROUND = {"eps3": 1.0, "eps4": 1.0, "seed": 7}


def add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def shares_of(s, d, src, steps=None):
    steps = steps_of(s, d, src) if steps is None else steps
    side = 1 << RES[src]
    return histogram.densify(histogram.build(steps, weight="inv_len"), side).where("comp = 'F'").select("row", "col", "cnt")


def nodes_of(s, d, src):
    return quadtree.nodes(shares_of(s, d, src), RES[src])


def alg1(s, d, src, p):
    """Leaves with densities; the walks, read three times, are kept."""
    steps = kept(steps_of(s, d, src))
    n = steps.select("traj_id").distinct().count()
    return quadtree.partition(histogram.build(steps), shares_of(s, d, src, steps), n, RES[src], p)


def count_of(s, d, src) -> int:
    return steps_of(s, d, src).select("traj_id").distinct().count()


# --- SQL of step 1

def nodes_sql(res: int, of: str = "shares") -> str:
    return f"""lv AS MATERIALIZED (SELECT level::INTEGER AS level, (row >> ({res} - level))::INTEGER AS br, (col >> ({res} - level))::INTEGER AS bc, cnt FROM {of}, (SELECT unnest(range({res + 1})) AS level)),
tot AS (SELECT level, br, bc, count(*) AS size, sum(cnt) AS total FROM lv GROUP BY level, br, bc),
nodes AS MATERIALIZED (SELECT level, br, bc, any_value(size) AS size, any_value(total) AS total, sum(abs(cnt - total / size)) AS cost FROM lv JOIN tot USING (level, br, bc) GROUP BY level, br, bc)"""


def split_sql(p: quadtree.PartitionParams, res: int) -> str:
    noisy = parent = "cost"
    if p.noise:
        eps = p.eps1 / (res + 1) if p.scope == "per_level" else p.eps1
        scale = p.sensitivity / (eps if p.parent_noise == "reuse" else eps / 2)
        noisy = parent = f"cost + {S.laplace(S.uniform(p.seed, 'cost', 'level', 'br', 'bc'), scale)}"
        if p.parent_noise == "fresh":
            parent = f"cost + {S.laplace(S.uniform(p.seed, 'parent', 'level', 'br', 'bc'), scale)}"
    return f"""noisy AS MATERIALIZED (SELECT *, {noisy} AS noisy_cost, {parent} AS parent_cost FROM nodes),
kids AS (SELECT level - 1 AS level, br // 2 AS br, bc // 2 AS bc, avg(noisy_cost) AS below FROM noisy WHERE level > 0 GROUP BY ALL),
flags AS MATERIALIZED (SELECT n.*, coalesce(parent_cost - below > {quadtree.threshold(p)!r}, false) AS split FROM noisy n LEFT JOIN kids USING (level, br, bc))"""


def leaves_sql(res: int) -> str:
    return f"""tree AS (SELECT level, br, bc, size, total, split FROM flags WHERE level = 0
  UNION ALL SELECT f.level, f.br, f.bc, f.size, f.total, f.split FROM tree t JOIN flags f ON t.split AND f.level = t.level + 1 AND f.br // 2 = t.br AND f.bc // 2 = t.bc),
leaves AS MATERIALIZED (SELECT (((1::BIGINT << (2 * level)) - 1) // 3 + br * (1::BIGINT << level) + bc)::BIGINT AS pid, level, br, bc, (br * (1 << ({res} - level)))::INTEGER AS r1, ((br + 1) * (1 << ({res} - level)) - 1)::INTEGER AS r2,
  (bc * (1 << ({res} - level)))::INTEGER AS c1, ((bc + 1) * (1 << ({res} - level)) - 1)::INTEGER AS c2, size, total FROM tree WHERE NOT split)"""


N_SQL = "(SELECT count(DISTINCT traj_id) FROM steps)"


def density_sql(p: quadtree.PartitionParams, how: str = "range") -> str:
    parts = ["leaf_q AS (SELECT pid AS qid, r1, r2, c1, c2 FROM leaves)", S.answers(name="leaf_n", queries="leaf_q", faces=how != "range")]
    b = f"ans / {N_SQL}"
    if p.noise:
        b = f"greatest(0, {b} + {S.laplace(S.uniform(p.seed, 'density', 'pid'), f'{1 / p.eps2!r} / {N_SQL}')})"
    return ", ".join(parts) + f", regions AS MATERIALIZED (SELECT leaves.*, {b} AS b FROM leaves JOIN leaf_n ON leaf_n.qid = pid)"


def step1_sql(src: str, p: quadtree.PartitionParams, how: str = "range") -> str:
    res = RES[src]
    return ", ".join([S.steps(src, res), S.hist(), S.shares(1 << res), nodes_sql(res), split_sql(p, res), leaves_sql(res), density_sql(p, how)])


# --- SQL of step 2

def start_sql(side: int) -> str:
    edges = 2 * side * (side - 1)
    return f"""slots0 AS (SELECT 'F' AS comp, r::INTEGER AS row, c::INTEGER AS col FROM (SELECT unnest(range({side})) AS r), (SELECT unnest(range({side})) AS c)),
slots1 AS (SELECT * FROM slots0 UNION ALL SELECT 'V', row, col FROM slots0 WHERE col < {side - 1} UNION ALL SELECT 'H', row, col FROM slots0 WHERE row < {side - 1}),
est0 AS MATERIALIZED (SELECT comp, row, col, CASE WHEN comp = 'F' THEN {N_SQL} * {MEAN_LENGTH} / {side * side} ELSE {N_SQL} * {MEAN_LENGTH - 1} / {edges} END::DOUBLE AS cnt FROM slots1)"""


def owners_sql() -> str:
    """CTE own(comp, row, col, pa, pb): regions of a component's cells."""
    at = lambda a, r, c: f"JOIN regions {a} ON {r} BETWEEN {a}.r1 AND {a}.r2 AND {c} BETWEEN {a}.c1 AND {a}.c2"
    return f"own AS MATERIALIZED (SELECT comp, row, col, a.pid AS pa, b.pid AS pb FROM slots1 {at('a', 'row', 'col')} {at('b', 'row + (comp = chr(72))::INTEGER', 'col + (comp = chr(86))::INTEGER')})"


def round_sql(i: int, rounds: int, update: str = "region", how: str = "face") -> str:
    """CTEs from est{i} to est{i+1}."""
    e3, e4, seed = ROUND["eps3"] / rounds, rounds / ROUND["eps4"], ROUND["seed"]
    pick = f"""{S.answers(f'est{i}', f'guess{i}')},
score{i} AS MATERIALIZED (SELECT q.*, abs(t.ans - g.ans) AS score, t.ans - g.ans AS err FROM queries q JOIN answers t USING (qid) JOIN guess{i} g USING (qid)),
pick{i} AS MATERIALIZED (SELECT qid, r1, r2, c1, c2, score, err + {S.laplace(S.uniform(seed, f'lm{i}', 'qid'), e4)} AS werr FROM score{i} ORDER BY score * {e3 / 2!r} + {S.gumbel(S.uniform(seed, f'em{i}', 'qid'))} DESC, qid LIMIT 1)"""
    if update == "classic":
        new = f"""new{i} AS MATERIALIZED (SELECT comp, row, col, cnt * CASE WHEN row BETWEEN r1 AND r2 - (comp = 'H')::INTEGER AND col BETWEEN c1 AND c2 - (comp = 'V')::INTEGER
  THEN exp(werr / (2 * {N_SQL})) ELSE 1 END AS cnt FROM est{i}, pick{i})"""
    else:
        new = f"""fac{i} AS MATERIALIZED (SELECT pid, g.r1 <= p.r2 AND g.r2 >= p.r1 AND g.c1 <= p.c2 AND g.c2 >= p.c1 AS hit, CASE WHEN g.r1 <= p.r2 AND g.r2 >= p.r1 AND g.c1 <= p.c2 AND g.c2 >= p.c1
  THEN exp(werr * b / (2 * {N_SQL})) ELSE 1 END AS f FROM regions g, pick{i} p),
new{i} AS MATERIALIZED (SELECT comp, row, col, cnt * CASE WHEN pa = pb THEN x.f WHEN x.hit AND y.hit THEN least(x.f, y.f) ELSE 1 END AS cnt FROM est{i} JOIN own USING (comp, row, col) JOIN fac{i} x ON x.pid = pa JOIN fac{i} y ON y.pid = pb)"""
    f = lambda t: f"(SELECT sum(cnt) FROM {t}{i} WHERE comp = 'F')"
    e = lambda t: f"(SELECT sum(cnt) FROM {t}{i} WHERE comp <> 'F')"
    scale = {"face": f"{f('est')} / {f('new')}", "answer": f"{N_SQL} / ({f('new')} - {e('new')})", "mass": f"CASE WHEN comp = 'F' THEN {f('est')} / {f('new')} ELSE {e('est')} / {e('new')} END", "none": "1"}[how]
    return f"{pick},\n{new},\nest{i + 1} AS MATERIALIZED (SELECT comp, row, col, cnt * ({scale}) AS cnt FROM new{i})"


def step2_sql(rounds: int, of: int, update: str = "region", how: str = "face", used: str = "true") -> str:
    """CTEs up to est{rounds}; used: which rectangles the rounds choose from."""
    q = S.rectangles(32, M).replace("queries AS MATERIALIZED", "every_q AS MATERIALIZED") + f", queries AS MATERIALIZED (SELECT * FROM every_q WHERE {used})"
    base = [step1_sql("em", PART), q, S.answers(), start_sql(32), owners_sql()]
    return ",\n".join(base + [round_sql(i, of, update, how) for i in range(rounds)])


class Setting:
    """The driver's side of a synthesis on the skewed walks."""

    def __init__(self, s, d, used: str = "true"):
        self.spark, self.steps = s, kept(steps_of(s, d, "em"))
        self.table = kept(histogram.densify(histogram.build(self.steps), 32))
        self.truth, self.n = collected(self.table, 32), float(self.steps.select("traj_id").distinct().count())
        self.every = rects(s, "em")
        self.queries = self.every.where(used)
        self.qids, self.q = query_array(self.queries)
        self.parts = quadtree.partition(self.table, shares_of(s, d, "em", self.steps), int(self.n), 5, PART)
        self.regions = self.parts.toPandas().sort_values("pid").reset_index(drop=True)
        self.mass = self.n * MEAN_LENGTH

    def run(self, rounds: int, **options) -> estimator.Synthesis:
        p = estimator.SynthParams(rounds=rounds, **({"repair": "none"} | ROUND | options))
        return estimator.run(self.truth, self.qids, self.q, self.regions, self.n, self.mass, p)

    def frames(self, rounds: int, **options):
        """The same over frames: the histogram and the trace."""
        p = estimator.SynthParams(rounds=rounds, **({"repair": "none"} | ROUND | options))
        return frames.run(self.table, self.queries, self.parts, 32, self.n, self.mass, p)

    def frame(self, hist: DenseHist):
        return rounded(framed(self.spark, hist), "cnt")


def scored(s, d):
    x = Setting(s, d)
    start = estimator.initial(32, x.n, x.mass)
    scores = np.abs(x.truth.answers(x.q) - start.answers(x.q))
    return s.createDataFrame(pd.DataFrame({"qid": x.qids, "score": scores}), "qid long, score double")


def halved(hist):
    """The histogram with cells 8..20 and edges strictly between them halved: edges on their border break."""
    box = hist.withColumns({k: F.lit(v) for k, v in (("r1", 8), ("r2", 20), ("c1", 8), ("c2", 20))})
    return box.select("comp", "row", "col", F.when(answering.in_component(), F.col("cnt") / 2).otherwise(F.col("cnt")).alias("cnt"))


HALVED = """halved AS MATERIALIZED (SELECT comp, row, col, CASE WHEN row BETWEEN 8 AND 20 - (comp = 'H')::INTEGER AND col BETWEEN 8 AND 20 - (comp = 'V')::INTEGER THEN cnt / 2 ELSE cnt END AS cnt FROM full_hist),
ends AS MATERIALIZED (SELECT e.comp, e.row, e.col, e.cnt, a.row AS fr, a.col AS fc, a.cnt AS face FROM halved e JOIN halved a ON a.comp = 'F' AND ((a.row = e.row AND a.col = e.col) OR (a.row = e.row + (e.comp = 'H')::INTEGER AND a.col = e.col + (e.comp = 'V')::INTEGER)) WHERE e.comp <> 'F'),
star AS MATERIALIZED (SELECT f.row, f.col, greatest(f.cnt, coalesce(list_sort(list(x.cnt) FILTER (x.cnt > x.face), 'DESC')[2], 0)) AS cnt FROM halved f LEFT JOIN ends x ON x.fr = f.row AND x.fc = f.col WHERE f.comp = 'F' GROUP BY f.row, f.col, f.cnt),
fixed AS MATERIALIZED (SELECT 'F' AS comp, row, col, cnt FROM star UNION ALL SELECT x.comp, x.row, x.col, least(any_value(x.cnt), min(s.cnt)) FROM ends x JOIN star s ON s.row = x.fr AND s.col = x.fc GROUP BY x.comp, x.row, x.col)"""


def tables() -> None:
    """Mechanisms on their own."""
    ids = lambda s: s.range(1000).select(F.col("id").alias("key"))
    u = S.uniform(7, "t", "key")
    keys = "FROM (SELECT unnest(range(1000)) AS key)"
    users = lambda s, d: s.read.parquet(f"{d}/events.parquet").select(F.col("user_id").alias("key")).distinct()
    each = "FROM (SELECT DISTINCT user_id AS key FROM events)"
    add("m_uniform", lambda s, d: ids(s).withColumn("value", F.round(noise.uniform(7, "t", "key"), 9)), f"SELECT key, round({u}, 9) AS value {keys}")
    add("m_laplace", lambda s, d: users(s, d).withColumn("value", F.round(noise.laplace(noise.uniform(7, "t", "key"), 2.0), 6)), f"SELECT key, round({S.laplace(u, 2.0)}, 6) AS value {each}")
    add("m_gumbel", lambda s, d: users(s, d).withColumn("value", F.round(noise.gumbel(noise.uniform(7, "t", "key")), 6)), f"SELECT key, round({S.gumbel(u)}, 6) AS value {each}")
    v = S.uniform(7, "t2", "key")
    add("m_geometric", lambda s, d: users(s, d).withColumn("value", noise.geometric(noise.uniform(7, "t", "key"), noise.uniform(7, "t2", "key"), 2.0)),
        f"SELECT key, (floor(-2.0 * ln({u})) - floor(-2.0 * ln({v})))::BIGINT AS value {each}")
    add("m_secure_shape", lambda s, d: noise.secure(users(s, d)).agg(F.count("u").alias("n"), F.min(F.col("u") > 0).alias("above"), F.min(F.col("u") < 1).alias("below")), "SELECT count(DISTINCT user_id) AS n, true AS above, true AS below FROM events")
    true = S.steps("li", 4) + f", {S.hist()}, {S.rectangles(16, M)}, {S.answers()}"
    ans = lambda s, d: answering.from_hist(histogram.build(steps_of(s, d, "li")), rects(s, "li"))
    add("m_lm_li", lambda s, d: rounded(mechanisms.laplace(ans(s, d), 0.1, seed=7), "ans"), true + f" SELECT qid, round(ans + {S.laplace(S.uniform(7, 'lm', 'qid'), 10.0)}, 6) AS ans FROM answers")
    score = lambda s, d: ans(s, d).withColumnRenamed("ans", "score")
    add("m_em_select_li", lambda s, d: mechanisms.exponential(score(s, d), 0.01, seed=7), true + f" SELECT qid, ans AS score FROM answers ORDER BY ans * 0.005 + {S.gumbel(S.uniform(7, 'em', 'qid'))} DESC, qid LIMIT 1")
    add("m_em_probs_li", lambda s, d: rounded(mechanisms.exponential_probs(score(s, d), 0.001), "prob", digits=9),
        true + ", e AS (SELECT qid, exp((ans - (SELECT max(ans) FROM answers)) * 0.0005) AS e FROM answers) SELECT qid, round(e / (SELECT sum(e) FROM e), 9) AS prob FROM e")
    add("m_budget_split", lambda s, d: mechanisms.split_budgets(s.read.parquet(f"{d}/events.parquet").groupBy(F.col("user_id").alias("key")).agg(F.max("value").alias("eps"))),
        "SELECT key, unnest(['cost', 'density', 'choice', 'answer']) AS part, eps * 0.25::DOUBLE AS eps FROM (SELECT user_id AS key, max(value) AS eps FROM events GROUP BY user_id)")

    def ledger(s, d):
        """Events as a log of what was spent: views on disjoint data, all others one after the other."""
        kind = F.when(F.col("event_type") == "view", "parallel").otherwise("sequential")
        log = s.read.parquet(f"{d}/events.parquet").select(F.col("event_type").alias("stage"), (F.floor("value") / 1024).cast("double").alias("eps"), kind.alias("composition"))
        return rounded(mechanisms.ledger_totals(log), "eps")

    add("m_ledger", ledger, "SELECT event_type AS stage, round(CASE WHEN event_type = 'view' THEN max(floor(value) / 1024) ELSE sum(floor(value) / 1024) END, 6) AS eps FROM events GROUP BY event_type")


def pruning_sql(charge: float) -> list[str]:
    """CTEs best5 to best0: the least cost and charges of a pruning below each node, from the leaves up."""
    out = [f"best5 AS MATERIALIZED (SELECT level, br, bc, cost + {charge!r} AS best, false AS split FROM nodes WHERE level = 5)"]
    for k in range(4, -1, -1):
        below = f"SELECT br // 2 AS br, bc // 2 AS bc, sum(best) AS below FROM best{k + 1} GROUP BY ALL"
        out.append(f"best{k} AS MATERIALIZED (SELECT n.level, n.br, n.bc, least(cost + {charge!r}, below) AS best, below < cost + {charge!r} - 1e-9 AS split FROM nodes n JOIN ({below}) USING (br, bc) WHERE n.level = {k})")
    return out


def step_one() -> None:
    for src in ("li", "em"):
        res = RES[src]
        base = S.steps(src, res) + f", {S.hist()}, {S.shares(1 << res)}, {nodes_sql(res)}"
        add(f"p_nodes_{src}", lambda s, d, src=src: rounded(nodes_of(s, d, src), "total", "cost"), base + " SELECT level, br, bc, size, round(total, 6) AS total, round(cost, 6) AS cost FROM nodes")
        add(f"p_cost_{src}", lambda s, d, src=src: rounded(quadtree.cost(shares_of(s, d, src), quadtree.cell_region(regions.uniform(s, RES[src], 2))), "cost"),
            base + " SELECT (br * 4 + bc)::BIGINT AS pid, round(cost, 6) AS cost FROM nodes WHERE level = 2")
        add(f"p_alg1_{src}", lambda s, d, src=src: rounded(alg1(s, d, src, PART), "b").drop("total"),
            step1_sql(src, PART) + " SELECT pid, level, br, bc, r1, r2, c1, c2, size, round(b, 6) AS b FROM regions")
    base = S.steps("em", 5) + f", {S.hist()}, {S.shares(32)}, {nodes_sql(5)}"
    add("p_uniform_em", lambda s, d: quadtree.uniform_regions(shares_of(s, d, "em"), quadtree.cell_region(regions.uniform(s, 5, 4))), base + " SELECT (br * 16 + bc)::BIGINT AS pid, cost <= 1e-9 AS is_uniform FROM nodes WHERE level = 4")
    noisy = lambda s, d, p=PART: quadtree.noisy(nodes_of(s, d, "em"), p, 5)
    add("p_noisy_em", lambda s, d: rounded(noisy(s, d), "noisy_cost").select("level", "br", "bc", "noisy_cost"), base + f", {split_sql(PART, 5)} SELECT level, br, bc, round(noisy_cost, 6) AS noisy_cost FROM noisy")
    add("p_split_em", lambda s, d: quadtree.split_flags(noisy(s, d), PART).select("level", "br", "bc", "split"), base + f", {split_sql(PART, 5)} SELECT level, br, bc, split FROM flags")
    exact = base + f", {split_sql(QUIET, 5)}, {leaves_sql(5)}"
    exact_leaves = lambda s, d: quadtree.leaves(quadtree.split_flags(noisy(s, d, QUIET), QUIET), 5)
    add("p_leaves_exact_em", lambda s, d: exact_leaves(s, d).drop("total"), exact + " SELECT pid, level, br, bc, r1, r2, c1, c2, size FROM leaves")
    add("p_alg1_perlevel_em", lambda s, d: rounded(alg1(s, d, "em", PER_LEVEL), "b").drop("total"),
        step1_sql("em", PER_LEVEL) + " SELECT pid, level, br, bc, r1, r2, c1, c2, size, round(b, 6) AS b FROM regions")
    add("p_alg1_fresh_em", lambda s, d: rounded(alg1(s, d, "em", FRESH), "b").drop("total"),
        step1_sql("em", FRESH) + " SELECT pid, level, br, bc, r1, r2, c1, c2, size, round(b, 6) AS b FROM regions")

    def over_arrays(s, d):
        steps = kept(steps_of(s, d, "em"))
        hist, shares = collected(histogram.densify(histogram.build(steps), 32), 32), collected(shares_of(s, d, "em", steps).selectExpr("'F' AS comp", "*"), 32).f
        got = partitioned(hist, shares, steps.select("traj_id").distinct().count(), PART).drop(columns="total")
        return rounded(s.createDataFrame(got, "pid long, level int, br int, bc int, r1 int, r2 int, c1 int, c2 int, size long, b double"), "b")

    add("p_alg1_arrays_em", over_arrays, step1_sql("em", PART) + " SELECT pid, level, br, bc, r1, r2, c1, c2, size, round(b, 6) AS b FROM regions")
    # best pruning in SQL: a node is kept if nothing below or above it is cheaper, level by level
    levels = pruning_sql(2.0)
    every = " UNION ALL ".join(f"SELECT * FROM best{k}" for k in range(6))
    add("p_best_pruning_em", lambda s, d: rounded(regions.best_pruning(nodes_of(s, d, "em"), 5, 2.0), "cost"),
        base + ", " + ", ".join(levels) + f", allbest AS MATERIALIZED ({every}), down AS (SELECT * FROM allbest WHERE level = 0 UNION ALL SELECT b.* FROM down t JOIN allbest b ON t.split AND b.level = t.level + 1 AND b.br // 2 = t.br AND b.bc // 2 = t.bc) SELECT n.level, n.br, n.bc, n.size, round(n.cost, 6) AS cost FROM down JOIN nodes n USING (level, br, bc) WHERE NOT split")

    def tiny(s, d):
        cells = np.zeros((3, 4))
        for r in shares_of(s, d, "em").collect():
            cells[min(2, r["row"] * 3 // 32), r["col"] // 8] += r["cnt"]
        total, boxes = regions.exhaustive(cells, 5.0)
        return s.createDataFrame([(i, *b, total) for i, b in enumerate(sorted(boxes))], "pid long, r1 int, r2 int, c1 int, c2 int, total double")

    add("p_exhaustive", tiny)
    faces = lambda s, d: histogram.densify(histogram.build(steps_of(s, d, "em")), 32).where("comp = 'F'").select("row", "col", "cnt")
    fsql = S.steps("em", 5) + f", {S.hist()}, {S.dense(32)}, faces AS MATERIALIZED (SELECT row, col, cnt FROM full_hist WHERE comp = 'F'), kd0 AS (SELECT 0::BIGINT AS pid, 0 AS r1, 31 AS r2, 0 AS c1, 31 AS c2)"
    for k in range(4):
        ax, lo, hi = ("row", "r1", "r2") if k % 2 == 0 else ("col", "c1", "c2")
        other = "c1, c2" if k % 2 == 0 else "r1, r2"
        fsql += f""", run{k} AS (SELECT pid, {ax} AS line, sum(s) OVER (PARTITION BY pid ORDER BY {ax}) AS run, sum(s) OVER (PARTITION BY pid) AS whole FROM (SELECT pid, {ax}, sum(cnt) AS s FROM faces JOIN kd{k} ON row BETWEEN r1 AND r2 AND col BETWEEN c1 AND c2 GROUP BY pid, {ax})),
cut{k} AS (SELECT k.*, least(coalesce((SELECT min(line) FROM run{k} r WHERE r.pid = k.pid AND 2 * run >= whole), {lo}), {hi} - 1) AS cut FROM kd{k} k),
kd{k + 1} AS MATERIALIZED (SELECT pid * 2 AS pid, {lo}, CASE WHEN {lo} < {hi} THEN cut ELSE {hi} END AS {hi}, {other} FROM cut{k} UNION ALL SELECT pid * 2 + 1, cut + 1, {hi}, {other} FROM cut{k} WHERE {lo} < {hi})"""
    add("p_kdtree_em", lambda s, d: regions.kdtree(faces(s, d), 32, 4), fsql + " SELECT pid, r1::INTEGER AS r1, r2::INTEGER AS r2, c1::INTEGER AS c1, c2::INTEGER AS c2 FROM kd4")
    add("p_rtree_em", lambda s, d: regions.packed_boxes(faces(s, d), 4),
        S.steps("em", 5) + f", {S.hist()}, a AS (SELECT *, ntile(4) OVER (ORDER BY col, row) AS a FROM hist WHERE comp = 'F'), b AS (SELECT *, ntile(4) OVER (PARTITION BY a ORDER BY row, col) AS b FROM a) SELECT ((a - 1) * 4 + b - 1)::BIGINT AS pid, min(row) AS r1, max(row) AS r2, min(col) AS c1, max(col) AS c2, count(*) AS cells FROM b GROUP BY a, b")
    add("p_uniform_grid_em", lambda s, d: regions.uniform(s, 5, 2), "SELECT (r * 4 + c)::BIGINT AS pid, (r * 8)::INTEGER AS r1, (r * 8 + 7)::INTEGER AS r2, (c * 8)::INTEGER AS c1, (c * 8 + 7)::INTEGER AS c2 FROM (SELECT unnest(range(4)) AS r), (SELECT unnest(range(4)) AS c)")
    add("p_cover_check_em", lambda s, d: quadtree.check_cover(exact_leaves(s, d), 32), exact + ", g AS (SELECT unnest(range(32)) AS r), h AS (SELECT unnest(range(32)) AS c) SELECT r::INTEGER AS row, c::INTEGER AS col, count(pid) AS times FROM g CROSS JOIN h LEFT JOIN leaves ON r BETWEEN r1 AND r2 AND c BETWEEN c1 AND c2 GROUP BY r, c HAVING count(pid) <> 1")
    for how in ("faces", "range"):
        add(f"p_density_{how}_em", lambda s, d, how=how: rounded(quadtree.density(exact_leaves(s, d), count_of(s, d, "em"), quadtree.counted(histogram.build(steps_of(s, d, "em")), exact_leaves(s, d), how)), "b").select("pid", "size", "b"),
            exact + f", {density_sql(QUIET, how)} SELECT pid, size, round(b, 6) AS b FROM regions")
    add("p_density_invlen_em", lambda s, d: rounded(quadtree.density(exact_leaves(s, d), count_of(s, d, "em"), exact_leaves(s, d).select("pid", F.col("total").alias("count"))), "b").select("pid", "size", "b"),
        exact + f" SELECT pid, size, round(total / {N_SQL}, 6) AS b FROM leaves")
    loud = quadtree.PartitionParams(eps2=0.5, seed=7)
    add("p_density_noisy_em", lambda s, d: rounded(quadtree.noisy_density(quadtree.density(exact_leaves(s, d), count_of(s, d, "em"), quadtree.counted(histogram.build(steps_of(s, d, "em")), exact_leaves(s, d))), count_of(s, d, "em"), loud), "b").select("pid", "b"),
        exact + f", {density_sql(loud)} SELECT pid, round(b, 6) AS b FROM regions")
    rules = [("variance", 0.025), ("stddev", 0.025), ("variance", 0.25), ("stddev", 0.25)]
    add("p_delta_rules", lambda s, d: rounded(s.createDataFrame([(r, e, float(quadtree.threshold(quadtree.PartitionParams(eps1=e, threshold=r)))) for r, e in rules], "rule string, eps1 double, delta double"), "delta"),
        "SELECT rule, eps1::DOUBLE AS eps1, round(CASE rule WHEN 'variance' THEN 4 / (eps1 * eps1) ELSE sqrt(2.5) * 2 / eps1 END, 6) AS delta FROM (VALUES ('variance', 0.025::DOUBLE), ('stddev', 0.025), ('variance', 0.25), ('stddev', 0.25)) t(rule, eps1)")

    def sensitivity(s, d):
        """most: the largest change of the whole grid's cost when one trajectory goes, by counts and by shares."""
        steps = kept(steps_of(s, d, "cv", "erase"))
        return rounded(mechanisms.cost_sensitivity(steps, 16, "raw").union(mechanisms.cost_sensitivity(steps, 16)), "most", "bound")

    one = """SELECT '{m}' AS weight, round(max(abs(after - base)), 6) AS most, round(2 * max(mass), 6) AS bound FROM (
  SELECT traj_id, any_value(mass) AS mass, sum(abs(cnt - coalesce(w, 0) - (mean - mass / 256))) AS after, any_value(base) AS base FROM ids_{m} CROSS JOIN tot_{m} LEFT JOIN own_{m} USING (traj_id, row, col) CROSS JOIN base_{m} GROUP BY traj_id)"""
    ctes = "".join(f""", own_{m} AS MATERIALIZED (SELECT traj_id, row, col, {w} AS w FROM k), ids_{m} AS (SELECT traj_id, sum(w) AS mass FROM own_{m} GROUP BY ALL),
tot_{m} AS MATERIALIZED (SELECT r::INTEGER AS row, c::INTEGER AS col, coalesce(sum(w), 0) AS cnt FROM (SELECT unnest(range(16)) AS r) CROSS JOIN (SELECT unnest(range(16)) AS c) LEFT JOIN own_{m} o ON o.row = r AND o.col = c GROUP BY ALL),
base_{m} AS (SELECT sum(abs(cnt - mean)) AS base, any_value(mean) AS mean FROM tot_{m}, (SELECT sum(cnt) / 256 AS mean FROM tot_{m}))""" for m, w in (("raw", "1.0::DOUBLE"), ("inv_len", "1.0::DOUBLE / n")))
    add("p_cost_sensitivity_cv", sensitivity, S.steps("cv", 4, "erase") + ", k AS (SELECT *, count(*) OVER (PARTITION BY traj_id) AS n FROM (SELECT DISTINCT traj_id, row, col FROM steps))" + ctes + " " + " UNION ALL ".join(one.format(m=m) for m in ("raw", "inv_len")))
    add("p_cost_sensitivity_change_cv", lambda s, d: rounded(mechanisms.change_sensitivity(steps_of(s, d, "cv", "erase"), 16), "most", "bound"),
        S.steps("cv", 4, "erase") + ", k AS (SELECT *, count(*) OVER (PARTITION BY traj_id) AS n FROM (SELECT DISTINCT traj_id, row, col FROM steps))" + ctes + """,
succ AS (SELECT traj_id, lead(traj_id) OVER (ORDER BY traj_id) AS other FROM ids_inv_len), pairs AS (SELECT * FROM succ WHERE other IS NOT NULL),
after AS (SELECT p.traj_id, sum(abs(t.cnt - coalesce(a.w, 0) + coalesce(b.w, 0) - mean)) AS after FROM pairs p CROSS JOIN tot_inv_len t LEFT JOIN own_inv_len a ON a.traj_id = p.traj_id AND a.row = t.row AND a.col = t.col
  LEFT JOIN own_inv_len b ON b.traj_id = p.other AND b.row = t.row AND b.col = t.col CROSS JOIN base_inv_len GROUP BY p.traj_id)
SELECT 'change' AS neighbours, round(max(abs(after - base)), 6) AS most, 4.0::DOUBLE AS bound FROM after, base_inv_len""")
    add("p_bound", lambda s, d: rounded(s.createDataFrame([(float(n), float(estimator.partition_bound(n, 0.05, 0.1, 100.0))) for n in (1000, 100000)], "n double, bound double"), "bound", digits=3),
        "SELECT n::DOUBLE AS n, round(100 + 16 * n * ln(n / 0.05) / 0.1, 3) AS bound FROM (VALUES (1000.0::DOUBLE), (100000.0)) t(n)")
    add("p_stats_em", lambda s, d: quadtree.stats(exact_leaves(s, d), 5),
        exact + ", a AS (SELECT count(*) AS n, max(level) AS h, max(size) AS l, min(size) AS m FROM leaves) SELECT unnest(['leaves', 'height', 'largest', 'smallest', 'work']) AS metric, unnest([n, h, l, m, 6144])::DOUBLE AS value FROM a")


def step_two() -> None:
    hist = " SELECT comp, row, col, round(cnt, 6) AS cnt FROM "
    base = step2_sql(0, 1)
    add("s_initial", lambda s, d: (lambda x: x.frame(estimator.initial(32, x.n, x.mass)))(Setting(s, d)), base + hist + "est0")
    add("s_scores_em", lambda s, d: rounded(scored(s, d), "score"), step2_sql(1, 1) + " SELECT qid, round(score, 6) AS score FROM score0")
    add("s_select_em", lambda s, d: rounded(mechanisms.exponential(scored(s, d), ROUND["eps3"], seed=7, stream="em0"), "score"), step2_sql(1, 1) + " SELECT qid, round(score, 6) AS score FROM pick0")
    add("s_measure_em", lambda s, d: (lambda x: rounded(s.createDataFrame([(t["qid"], t["werr"]) for t in x.run(1).trace], "qid long, werr double"), "werr"))(Setting(s, d)), step2_sql(1, 1) + " SELECT qid, round(werr, 6) AS werr FROM pick0")
    add("s_update_classic_em", lambda s, d: (lambda x: x.frame(x.run(1, update="classic", normalise="none").hist))(Setting(s, d)), step2_sql(1, 1, "classic", "none") + hist + "est1")
    add("s_update_region_em", lambda s, d: (lambda x: x.frame(x.run(1, normalise="none").hist))(Setting(s, d)), step2_sql(1, 1, "region", "none") + hist + "est1")
    for how in ("face", "answer", "mass"):
        add(f"s_normalise_{how}_em", lambda s, d, how=how: (lambda x: x.frame(x.run(1, normalise=how).hist))(Setting(s, d)), step2_sql(1, 1, "region", how) + hist + "est1")
    for t in (1, 3):
        add(f"s_alg2_t{t}_em", lambda s, d, t=t: (lambda x: x.frame(x.run(t).hist))(Setting(s, d)), step2_sql(t, t) + hist + f"est{t}")

    def logweight(s, d):
        x = Setting(s, d)
        p = estimator.SynthParams(rounds=3, repair="none", **ROUND)
        return x.frame(estimator.run_logweight(x.truth, x.qids, x.q, x.regions, x.n, x.mass, p).hist)

    add("s_logweight_t3_em", logweight, step2_sql(3, 3) + hist + "est3")
    over = lambda name, sql, rounds, **o: add(name, lambda s, d: rounded(Setting(s, d).frames(rounds, **o)[0], "cnt"), sql + hist + f"est{rounds}")
    add("s_frame_initial", lambda s, d: (lambda x: rounded(frames.initial(s, 32, x.n, x.mass), "cnt"))(Setting(s, d)), base + hist + "est0")
    add("s_frame_scores_em", lambda s, d: (lambda x: rounded(frames.scores(answering.plan(x.table, x.queries, 32)[1], answering.plan(frames.initial(s, 32, x.n, x.mass), x.queries, 32)[1]), "score").select("qid", "score"))(Setting(s, d)),
        step2_sql(1, 1) + " SELECT qid, round(score, 6) AS score FROM score0")
    add("s_frame_measure_em", lambda s, d: (lambda x: rounded(s.createDataFrame([(t["qid"], t["werr"]) for t in x.frames(1)[1]], "qid long, werr double"), "werr"))(Setting(s, d)), step2_sql(1, 1) + " SELECT qid, round(werr, 6) AS werr FROM pick0")
    over("s_frame_update_classic_em", step2_sql(1, 1, "classic", "none"), 1, update="classic", normalise="none")
    over("s_frame_update_region_em", step2_sql(1, 1, "region", "none"), 1, normalise="none")
    for how in ("face", "answer", "mass"):
        over(f"s_frame_normalise_{how}_em", step2_sql(1, 1, "region", how), 1, normalise=how)
    over("s_frame_alg2_t3_em", step2_sql(3, 3), 3)
    broken = lambda s, d: halved(histogram.densify(histogram.build(steps_of(s, d, "em")), 32))
    bad = S.steps("em", 5) + f", {S.hist()}, {S.dense(32)}, {HALVED}"
    add("s_gate_em", lambda s, d: histogram.violations(broken(s, d)).limit(1).agg((F.count(F.lit(1)) > 0).alias("needed")), bad + " SELECT count(*) > 0 AS needed FROM ends WHERE cnt > face")
    add("s_repair_star_em", lambda s, d: repair.star_frame(broken(s, d)), bad + " SELECT comp, row, col, cnt FROM fixed")
    add("s_repair_greedy_lower_em", lambda s, d: repair.greedy_frame(broken(s, d)), bad + ", low AS (SELECT comp, row, col, min(face) AS low FROM ends GROUP BY ALL) SELECT comp, row, col, least(cnt, coalesce(low, cnt)) AS cnt FROM halved LEFT JOIN low USING (comp, row, col)")
    add("s_repair_greedy_raise_em", lambda s, d: repair.greedy_frame(broken(s, d), "raise"), bad + ", high AS (SELECT 'F' AS comp, fr AS row, fc AS col, max(cnt) AS high FROM ends GROUP BY ALL) SELECT comp, row, col, greatest(cnt, coalesce(high, cnt)) AS cnt FROM halved LEFT JOIN high USING (comp, row, col)")
    add("s_repair_optimal_em", lambda s, d: framed(s, repair.optimal(collected(broken(s, d), 32)).hist))

    def cost(s, d):
        got = repair.optimal(collected(broken(s, d), 32))
        return rounded(s.createDataFrame([(got.moved, got.matched, bool(got.certified))], "moved double, matched double, certified boolean"), "moved", "matched")

    add("s_repair_cost_em", cost, bad + " SELECT round(sum(abs(h.cnt - f.cnt)), 6) AS moved, round(sum(abs(h.cnt - f.cnt)), 6) AS matched, true AS certified FROM halved h JOIN fixed f USING (comp, row, col)")

    def frame_cost(s, d):
        fixed, moves = repair.optimal_frame(kept(broken(s, d)), 32)
        got = moves.agg(F.sum(F.abs("change")).alias("moved"), F.sum("matched").alias("matched"))
        return rounded(got.withColumn("certified", F.lit(histogram.violations(fixed).isEmpty()) & (F.abs(F.col("moved") - F.col("matched")) < 1e-6)), "moved", "matched")

    add("s_frame_repair_cost_em", frame_cost, SQL["s_repair_cost_em"])
    add("s_frame_repair_optimal_em", lambda s, d: repair.optimal_frame(kept(broken(s, d)), 32)[0])

    def full(s, d):
        p = release.ReleaseParams(eps=2.0, partition=quadtree.PartitionParams(threshold="stddev"), mean_length=MEAN_LENGTH, seed=7)
        return release.released(trajectories.points(s, d, "em"), rects(s, "em"), trajectories.box(s, d, "em", 5), p)

    add("s_release_em", lambda s, d: full(s, d).frame())

    def secure(s, d):
        """Two releases with the operating system's noise: whether they differ, spend their budget and are consistent."""
        p = release.ReleaseParams(eps=2.0, partition=quadtree.PartitionParams(threshold="stddev"), mean_length=MEAN_LENGTH, synth=estimator.SynthParams(rounds=3))
        points, grid = kept(trajectories.points(s, d, "em")), trajectories.box(s, d, "em", 4)
        a, b = (release.released(points, rects(s, "cv"), grid, p) for _ in range(2))
        differ = a.frame().join(b.frame().withColumnRenamed("cnt", "other"), ["comp", "row", "col"]).agg((F.max(F.abs(F.col("cnt") - F.col("other"))) > 0).alias("differ"))
        return differ.withColumn("spent", F.lit(round(a.ledger.total(), 6))).withColumn("violated", F.lit(histogram.violations(a.frame()).count()).cast("long"))

    add("s_release_secure_em", secure, "SELECT true AS differ, 2.0::DOUBLE AS spent, 0::BIGINT AS violated")
    bounded = S.steps("em", 5, "erase") + f""", {S.rectangles(32, M)},
moved AS (SELECT *, sign(lead(row) OVER w - row) AS dr, sign(lead(col) OVER w - col) AS dc FROM steps WINDOW w AS (PARTITION BY traj_id ORDER BY step)),
told AS (SELECT *, last_value(nullif(dr, 0) IGNORE NULLS) OVER w AS pr, last_value(nullif(dc, 0) IGNORE NULLS) OVER w AS pc FROM moved WINDOW w AS (PARTITION BY traj_id ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
turns AS (SELECT *, coalesce(sum(coalesce((dr * pr < 0)::INTEGER, 0) + coalesce((dc * pc < 0)::INTEGER, 0)) OVER (PARTITION BY traj_id ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS t FROM told),
met AS (SELECT qid, traj_id, step - row_number() OVER (PARTITION BY qid, traj_id ORDER BY step) AS g FROM queries JOIN turns ON t < 4 AND row BETWEEN r1 AND r2 AND col BETWEEN c1 AND c2),
runs AS (SELECT qid, traj_id, count(DISTINCT g) AS n FROM met GROUP BY ALL) SELECT max(n)::BIGINT AS most, 4::BIGINT AS charged FROM runs"""
    add("s_release_sensitivity_em", lambda s, d: mechanisms.query_sensitivity(walks.bounded_runs(steps_of(s, d, "em", "erase"), 4), rects(s, "em")).agg(F.max("most").alias("most"), F.lit(4).cast("long").alias("charged")), bounded)
    add("m_bounded_runs_em", lambda s, d: walks.bounded_runs(steps_of(s, d, "em", "erase"), 4), bounded.split("met AS")[0].rstrip().rstrip(",") + " SELECT traj_id, step, row, col FROM turns WHERE t < 4")
    add("s_release_ledger_em", lambda s, d: rounded(mechanisms.ledger_totals(full(s, d).ledger.frame(s)), "eps"), "SELECT unnest(['cost', 'density', 'choice', 'answer']) AS stage, 0.5::DOUBLE AS eps")
    add("s_serve_em", lambda s, d: answering.from_prefix(answering.prefix(full(s, d).frame(), 32), rects(s, "em")))
    cases = [(1000, 65536, 10, 16000, 0.1), (1000, 65536, 20, 8000, 0.01)]
    add("s_bound", lambda s, d: rounded(s.createDataFrame([(float(n), float(t), float(estimator.answer_bound(n, h, t, q, e)), float(min(n, estimator.answer_bound(n, h, t, q, e)))) for n, h, t, q, e in cases], "n double, rounds double, bound double, capped double"), "bound", digits=3),
        "SELECT n, t AS rounds, round(b, 3) AS bound, least(n, b) AS capped FROM (SELECT n, t, 2 * n * sqrt(ln(h) / t) + 10 * t * ln(q) / e AS b FROM (VALUES (1000.0::DOUBLE, 65536.0::DOUBLE, 10.0::DOUBLE, 16000.0::DOUBLE, 0.1::DOUBLE), (1000.0, 65536.0, 20.0, 8000.0, 0.01)) t(n, h, t, q, e))")
    add("s_min_iterations", lambda s, d: rounded(s.createDataFrame([(int(h), float(estimator.least_rounds(h))) for h in (1024, 65536)], "components long, rounds double"), "rounds"), "SELECT h::BIGINT AS components, round(4 * ln(h), 6) AS rounds FROM (VALUES (1024), (65536)) t(h)")


def hilbert_sql(res: int) -> str:
    """CTE curve(row, col, pos): four turned copies of the curve a level below."""
    return f"""growing(k, r, c, pos) AS (SELECT 0, 0, 0, 0::BIGINT UNION ALL
  SELECT k + 1, CASE q WHEN 0 THEN c WHEN 3 THEN (1 << k) - 1 - c ELSE r + (1 << k) END, CASE q WHEN 0 THEN r WHEN 1 THEN c WHEN 2 THEN c + (1 << k) ELSE (2 << k) - 1 - r END, q * (1::BIGINT << (2 * k)) + pos
  FROM growing, (SELECT unnest(range(4)) AS q) WHERE k < {res}),
curve AS MATERIALIZED (SELECT r::INTEGER AS row, c::INTEGER AS col, pos FROM growing WHERE k = {res})"""


def others() -> None:
    curve = f"WITH RECURSIVE {hilbert_sql(5)}"
    placed = lambda s, d: walks.assign(trajectories.points(s, d, "or"), trajectories.box(s, d, "or", 5))
    at = f"{S.points('or')}, {S.gridded('or', 5)}"
    add("b_hilbert_encode", lambda s, d: curves.hilbert_index(placed(s, d), 5), f"{curve}, {at} SELECT traj_id, step, row, col, pos FROM cells0 JOIN curve USING (row, col)")
    places = lambda s, d: s.read.parquet(f"{d}/orders.parquet").select(F.col("o_orderkey").alias("key"), F.pmod("o_orderkey", F.lit(1024)).alias("pos"))
    add("b_hilbert_decode", lambda s, d: curves.hilbert_cell(places(s, d), 5), curve + " SELECT o_orderkey AS key, row, col, pos FROM orders JOIN curve ON pos = o_orderkey % 1024")
    bits = " + ".join(f"((col >> {k}) & 1) * {1 << (2 * k)} + ((row >> {k}) & 1) * {1 << (2 * k + 1)}" for k in range(5))
    add("b_morton", lambda s, d: placed(s, d).withColumn("pos", curves.morton_index(F.col("row"), F.col("col"), 5)), f"WITH {at} SELECT traj_id, step, row, col, ({bits})::BIGINT AS pos FROM cells0")
    em = S.steps("em", 5) + f", {S.hist()}, {S.dense(32)}, {hilbert_sql(5)}"
    dense = lambda s, d: histogram.densify(histogram.build(steps_of(s, d, "em")), 32)
    add("b_unroll_em", lambda s, d: baselines.unrolled(dense(s, d), 5), em + " SELECT pos, cnt FROM full_hist JOIN curve USING (row, col) WHERE comp = 'F'")
    add("b_query_runs", lambda s, d: baselines.query_runs(workload.rectangles_of(s.read.parquet(f"{d}/events.parquet").select(F.col("user_id").alias("qid")).distinct(), 32), 5),
        f"WITH RECURSIVE {hilbert_sql(5)}, {S.rectangles(32, 50).replace('SELECT unnest(range(50)) AS qid', 'SELECT DISTINCT user_id AS qid FROM events')}, p AS (SELECT qid, pos - row_number() OVER (PARTITION BY qid ORDER BY pos) AS g, pos FROM queries JOIN curve ON row BETWEEN r1 AND r2 AND col BETWEEN c1 AND c2) SELECT qid, min(pos) AS lo, max(pos) AS hi FROM p GROUP BY qid, g")
    true = S.steps("em", 5) + f", {S.hist()}, {S.dense(32)}, {S.rectangles(32, M)}, {S.answers()}"
    add("b_flat_queries_em", lambda s, d: rounded(baselines.flat_queries(answering.from_hist(dense(s, d), rects(s, "em")), 0.5, M, 7), "ans"), true + f" SELECT qid, round(ans + {S.laplace(S.uniform(7, 'flat', 'qid'), M / 0.5)}, 6) AS ans FROM answers")
    key = "CASE comp WHEN 'F' THEN 0 WHEN 'V' THEN 1 ELSE 2 END * 1024 + row * 32 + col"
    for name, scope, scale in (("b_flat_cells_em", "sequential", "(SELECT max(n) FROM (SELECT count(*) AS n FROM steps GROUP BY traj_id)) / 0.5"), ("b_flat_parallel_em", "parallel", "1 / 0.5")):
        add(name, lambda s, d, scope=scope: rounded(baselines.flat_cells(dense(s, d), 0.5, baselines.longest(steps_of(s, d, "em")), 32, 7, scope), "cnt"), true + f" SELECT comp, row, col, round(cnt + {S.laplace(S.uniform(7, 'cells', key), scale)}, 6) AS cnt FROM full_hist")

    def mw(s, d):
        x = Setting(s, d)
        out = baselines.mw1d(x.truth.f[baselines.hilbert_order(5)], baselines.Runs(x.q, 5), x.n, x.mass, 2.0, 2, 7, qids=x.qids)
        return rounded(s.createDataFrame([(i, float(v)) for i, v in enumerate(out)], "pos long, cnt double"), "cnt")

    flat = [S.steps("em", 5), S.hist(), S.dense(32), S.rectangles(32, M), hilbert_sql(5), S.answers("full_hist", "truth", faces=True), f"w0 AS MATERIALIZED (SELECT 'F' AS comp, row, col, pos, ({N_SQL} * {MEAN_LENGTH} / 1024)::DOUBLE AS cnt FROM curve)"]
    for i in range(2):
        flat += [S.answers(f"w{i}", f"wa{i}"), f"wp{i} AS MATERIALIZED (SELECT q.*, t.ans + {S.laplace(S.uniform(7, f'lm{i}', 'qid'), 2.0)} - g.ans AS e FROM queries q JOIN truth t USING (qid) JOIN wa{i} g USING (qid) ORDER BY abs(t.ans - g.ans) * 0.25 + {S.gumbel(S.uniform(7, f'em{i}', 'qid'))} DESC, qid LIMIT 1)",
                 f"wn{i} AS MATERIALIZED (SELECT comp, row, col, pos, cnt * CASE WHEN row BETWEEN r1 AND r2 AND col BETWEEN c1 AND c2 THEN exp(e / (2 * {N_SQL})) ELSE 1 END AS cnt FROM w{i}, wp{i})",
                 f"w{i + 1} AS MATERIALIZED (SELECT comp, row, col, pos, cnt * {N_SQL} * {MEAN_LENGTH} / (SELECT sum(cnt) FROM wn{i}) AS cnt FROM wn{i})"]
    add("b_mw1_t2_em", mw, ",\n".join(flat) + " SELECT pos, round(cnt, 6) AS cnt FROM w2")

    def vector(s, d):
        x = Setting(s, d)
        return x, x.truth.f[baselines.hilbert_order(5)]

    add("b_bucketize_em", lambda s, d: s.createDataFrame(baselines.bucketize(vector(s, d)[1], 0.5, seed=7), "start long, length long"))
    add("b_bucket_release_em", lambda s, d: s.createDataFrame([(i, float(v)) for i, v in enumerate(baselines.bucket_release(vector(s, d)[1], 1.0, seed=7))], "pos long, cnt double"))
    add("b_bucket_expand_em", lambda s, d: s.createDataFrame([(i, float(v)) for i, v in enumerate(baselines.bucket_expand([(k * 64, 64) for k in range(16)], vector(s, d)[1].reshape(16, 64).sum(axis=1)))], "pos long, cnt double"),
        em + " SELECT pos, sum(cnt) OVER (PARTITION BY pos // 64) / 64 AS cnt FROM full_hist JOIN curve USING (row, col) WHERE comp = 'F'")
    greedy = [step1_sql("em", PART), S.rectangles(32, M), S.answers(), start_sql(32), owners_sql()]

    def greedy_round(i: int) -> str:
        text = round_sql(i, 2, "classic", "face").replace(f"est{i + 1} AS", f"raw{i} AS")
        return text + f""", low{i} AS (SELECT e.comp, e.row, e.col, min(a.cnt) AS low FROM raw{i} e JOIN raw{i} a ON a.comp = 'F' AND ((a.row = e.row AND a.col = e.col) OR (a.row = e.row + (e.comp = 'H')::INTEGER AND a.col = e.col + (e.comp = 'V')::INTEGER)) WHERE e.comp <> 'F' GROUP BY ALL),
est{i + 1} AS MATERIALIZED (SELECT comp, row, col, least(cnt, coalesce(low, cnt)) AS cnt FROM raw{i} LEFT JOIN low{i} USING (comp, row, col))"""

    add("b_greedy_t2_em", lambda s, d: (lambda x: x.frame(baselines.greedy_consistent(x.truth, x.qids, x.q, x.n, x.mass, 2.0, 2, 7).hist))(Setting(s, d)), ",\n".join(greedy + [greedy_round(0), greedy_round(1)]) + " SELECT comp, row, col, round(cnt, 6) AS cnt FROM est2")
    add("b_uniform", lambda s, d: (lambda x: x.frame(estimator.initial(32, x.n, x.mass)))(Setting(s, d)), step2_sql(0, 1) + " SELECT comp, row, col, round(cnt, 6) AS cnt FROM est0")


def accuracy() -> None:
    """Measures of the noisy cells against the true histogram."""
    dense = lambda s, d: histogram.densify(histogram.build(steps_of(s, d, "em")), 32)
    noisy = lambda s, d: baselines.flat_cells(dense(s, d), 5.0, 1.0, 32, 7, "parallel")
    pair = lambda s, d: (answering.from_hist(dense(s, d), rects(s, "em")), answering.from_hist(noisy(s, d), rects(s, "em")))
    key = "CASE comp WHEN 'F' THEN 0 WHEN 'V' THEN 1 ELSE 2 END * 1024 + row * 32 + col"
    base = S.steps("em", 5) + f", {S.hist()}, {S.dense(32)}, {S.rectangles(32, M)}, est AS MATERIALIZED (SELECT comp, row, col, cnt + {S.laplace(S.uniform(7, 'cells', key), 0.2)} AS cnt FROM full_hist), {S.answers()}, {S.answers('est', 'guess')}, e AS (SELECT qid, abs(a.ans - g.ans) AS err, a.ans FROM answers a JOIN guess g USING (qid))"
    for name, metric, sql in (("e_avg_l1", "avg_l1", "avg(err)"), ("e_max", "max", "max(err)"), ("e_relative", "relative", "avg(err / greatest(ans, 1))")):
        add(name, lambda s, d, metric=metric: rounded(measures.summary(*pair(s, d)).where(F.col("metric") == metric), "value", digits=5), base + f" SELECT '{metric}' AS metric, round({sql}, 5) AS value FROM e")
    add("e_std", lambda s, d: rounded(measures.summary(*pair(s, d)).where("metric like 'std%'"), "value", digits=5), base + " SELECT 'std_pop' AS metric, round(stddev_pop(err), 5) AS value FROM e UNION ALL SELECT 'std_samp', round(stddev_samp(err), 5) FROM e")
    add("e_kld", lambda s, d: rounded(measures.divergence(dense(s, d), noisy(s, d), float(count_of(s, d, "em"))), "value"), base + f" SELECT round(sum(CASE WHEN f.cnt > 0 THEN f.cnt * ln(f.cnt / greatest(g.cnt, 0.001)) ELSE 0 END) / {N_SQL}, 6) AS value FROM full_hist f JOIN est g USING (comp, row, col) WHERE comp = 'F'")
    add("e_kld_normalised", lambda s, d: rounded(measures.divergence(dense(s, d), noisy(s, d), 1.0, normalise=True), "value"),
        base + ", m AS (SELECT f.cnt AS c, greatest(g.cnt, 0.001) AS g FROM full_hist f JOIN est g USING (comp, row, col) WHERE comp = 'F'), t AS (SELECT sum(c) AS sc, sum(g) AS sg FROM m) SELECT round(sum(CASE WHEN c > 0 THEN c / sc * ln((c / sc) / (g / sg)) ELSE 0 END), 6) AS value FROM m, t")

    def against_truth(x, ans, mechanism: str):
        return measures.summary(answering.from_hist(x.table, x.every), ans).where("metric = 'avg_l1'").withColumn("mechanism", F.lit(mechanism))

    def ratio(s, d):
        """The proposed mechanism after three rounds against naive noise on the answers and the uniform start."""
        x = Setting(s, d)
        own = against_truth(x, answering.from_hist(x.frame(x.run(3).hist), x.every), "PM")
        flat = against_truth(x, baselines.flat_queries(answering.from_hist(x.table, x.every), 2.0, M, 7), "BL-FLAT")
        start = against_truth(x, answering.from_hist(x.frame(estimator.initial(32, x.n, x.mass)), x.every), "B-UNI")
        return rounded(measures.improvement(own.unionByName(flat).unionByName(start)), "ratio", digits=4)

    add("e_ratio", ratio, step2_sql(3, 3) + f""", {S.answers('est3', 'guess3')}, pm AS (SELECT avg(abs(a.ans - g.ans)) AS e FROM answers a JOIN guess3 g USING (qid))
SELECT 'avg_l1' AS metric, 'BL-FLAT' AS mechanism, round((SELECT avg(abs({S.laplace(S.uniform(7, 'flat', 'qid'), M / 2.0)})) FROM answers) / e, 4) AS ratio FROM pm
UNION ALL SELECT 'avg_l1', 'B-UNI', round((SELECT avg(abs(a.ans - g.ans)) FROM answers a JOIN guess0 g USING (qid)) / e, 4) FROM pm""")

    def arbitrary(s, d):
        """Errors of the proposed mechanism on rectangles that it was not given, that it never chose, and that it chose."""
        x = Setting(s, d, "qid % 5 <> 0")
        got = x.run(3)
        errors = measures.errors(answering.from_hist(x.table, x.every), answering.from_hist(x.frame(got.hist), x.every))
        chosen = F.col("qid").isin(*[t["qid"] for t in got.trace])
        kind = F.when(F.col("qid") % 5 == 0, "not given").when(chosen, "chosen").otherwise("never chosen")
        return rounded(errors.groupBy(kind.alias("queries")).agg(F.avg("err").alias("value")), "value", digits=4)

    add("e_arbitrary_pm", arbitrary, step2_sql(3, 3, used="qid % 5 <> 0") + f""", {S.answers(name='all_true', queries='every_q')}, {S.answers('est3', 'all_guess', queries='every_q')},
picked AS (SELECT qid FROM pick0 UNION SELECT qid FROM pick1 UNION SELECT qid FROM pick2)
SELECT CASE WHEN qid % 5 = 0 THEN 'not given' WHEN qid IN (SELECT qid FROM picked) THEN 'chosen' ELSE 'never chosen' END AS queries, round(avg(abs(t.ans - g.ans)), 4) AS value FROM all_true t JOIN all_guess g USING (qid) GROUP BY 1""")
    add("e_held_out", lambda s, d: rounded(measures.held_out(*pair(s, d), rects(s, "em").where("qid % 5 <> 0")), "value", digits=5), base + " SELECT round(avg(err), 5) AS value FROM e WHERE qid % 5 = 0")
    add("e_inconsistency", lambda s, d: rounded(measures.inconsistency(noisy(s, d), histogram.violations(noisy(s, d)), pair(s, d)[1]), "value", digits=5),
        base + """, low AS (SELECT x.comp, x.row, x.col, any_value(x.cnt) AS cnt, min(a.cnt) AS low FROM est x JOIN est a ON a.comp = 'F' AND ((a.row = x.row AND a.col = x.col) OR (a.row = x.row + (x.comp = 'H')::INTEGER AND a.col = x.col + (x.comp = 'V')::INTEGER)) WHERE x.comp <> 'F' GROUP BY ALL)
SELECT unnest(['violated', 'share', 'excess', 'negative']) AS metric, round(unnest([v, v / n, x, (SELECT count(*) FROM guess WHERE ans < -1e-9)]), 5)::DOUBLE AS value FROM (SELECT count(*) FILTER (cnt > low + 1e-9)::DOUBLE AS v, count(*) AS n, coalesce(sum(cnt - low) FILTER (cnt > low + 1e-9), 0) AS x FROM low)""")
    add("e_snr", lambda s, d: rounded(measures.signal_to_noise(alg1(s, d, "em", PART), count_of(s, d, "em"), 0.5), "snr"),
        step1_sql("em", PART) + f" SELECT pid, round(b * {N_SQL} * 0.5, 6) AS snr FROM regions")

    def gap(s, d):
        """Costs with a charge for each region: of the private leaves, of the best pruning of the tree, and its bound."""
        nodes, charge = kept(nodes_of(s, d, "em")), 2.0
        root = regions.pruned_costs(nodes, 5, charge).where("level = 0").select(F.col("best"))
        own = quadtree.leaves(quadtree.split_flags(quadtree.noisy(nodes, PART, 5), PART), 5).join(nodes.select("level", "br", "bc", "cost"), ["level", "br", "bc"])
        own = own.agg(F.sum(F.col("cost") + charge).alias("own"), F.count(F.lit(1)).alias("regions"))
        n = count_of(s, d, "em")
        both = own.join(F.broadcast(root)).withColumn("bound", F.col("best") + float(estimator.partition_bound(n, 0.05, 1.0, 0.0)))
        return rounded(both.select("own", "regions", "best", "bound", (F.col("own") <= F.col("bound")).alias("holds")), "own", "best", "bound", digits=3)

    add("e_partition_gap", gap, step1_sql("em", PART) + ", " + ", ".join(pruning_sql(2.0)) + f""", g AS (SELECT sum(cost + 2.0) AS own, count(*) AS regions, (SELECT best FROM best0) AS best FROM leaves JOIN nodes USING (level, br, bc))
SELECT round(own, 3) AS own, regions, round(best, 3) AS best, round(best + 16 * {N_SQL} * ln({N_SQL} / 0.05), 3) AS bound, own <= best + 16 * {N_SQL} * ln({N_SQL} / 0.05) AS holds FROM g""")

    def work(s, d):
        """The repairs of a synthesis that keeps the sums of faces and of edges apart, and so breaks edges all over."""
        got = Setting(s, d).run(5, normalise="mass", repair="optimal")
        return s.createDataFrame([(t["iter"], t["violated"], t["components"], t["largest"], t["repaired_l1"], bool(t["certified"])) for t in got.trace],
                                 "iter int, violated int, components int, largest int, repaired_l1 double, certified boolean")

    add("e_repair_work", work)

    def ops(s, d):
        """What three rounds did, counted in the trace and the tree, beside the orders of the printed costs."""
        x = Setting(s, d)
        got = estimator.cost_summary(x.run(3).trace)
        visits = quadtree.by_level(shares_of(s, d, "em", x.steps), 5).count()
        cells = float(x.truth.f.size)
        rows = [("step1_visits", float(visits), float(cells * np.log2(cells))), ("scored", got["scored"], 3 * cells * len(x.q)), ("touched", got["touched"], 3 * cells)]
        return rounded(s.createDataFrame(rows, "metric string, counted double, printed double"), "printed")

    hits = " UNION ALL ".join(f"SELECT sum(size) AS k FROM fac{i} JOIN regions USING (pid) WHERE f <> 1" for i in range(3))
    add("e_ops", ops, step2_sql(3, 3) + f""" SELECT 'step1_visits' AS metric, (SELECT count(*) FROM lv)::DOUBLE AS counted, round((SELECT count(*) FROM shares) * log2((SELECT count(*) FROM shares)), 6)::DOUBLE AS printed
UNION ALL SELECT 'scored', (SELECT count(*) FROM score0)::DOUBLE + (SELECT count(*) FROM score1) + (SELECT count(*) FROM score2), (3 * (SELECT count(*) FROM shares) * (SELECT count(*) FROM queries))::DOUBLE
UNION ALL SELECT 'touched', coalesce((SELECT sum(k) FROM ({hits})), 0)::DOUBLE, (3 * (SELECT count(*) FROM shares))::DOUBLE""")

    def trace_cost(s, d):
        got = estimator.cost_summary(Setting(s, d).run(5, normalise="mass", repair="optimal").trace)
        return s.createDataFrame([(k, float(v)) for k, v in got.items()], "metric string, value double")

    add("s_cost_em", trace_cost)

    def audit(s, d):
        """The largest log ratio between outputs of the Laplace mechanism on two neighbouring histograms, over 40,000 seeded runs each."""
        q = rects(s, "cv", 1)
        points = kept(trajectories.points(s, d, "cv"))
        one = points.agg(F.min("traj_id")).first()[0]
        grid = trajectories.box(s, d, "cv", 4)
        values = [answering.from_hist(histogram.build(walks.walk_steps(x, grid)), q).first()["ans"] for x in (points, mechanisms.neighbour(points, "remove", one))]
        draw = lambda value, run: value + float(noise.laplace_value(noise.uniform_value(7, "audit", run), 1.0))
        ratio = mechanisms.audit(draw, *values, 40_000, 0.5)
        return s.createDataFrame([(abs(values[0] - values[1]), ratio <= 1.35)], "apart double, within boolean")

    add("m_audit_cv", audit)


def workloads() -> None:
    add("w_dist", experiments.distribution)
    add("w_std", experiments.deviation)
    add("w_queryset", experiments.query_set)
    add("w_resolution", experiments.resolution)
    add("w_kld", experiments.utility)
    add("w_time", experiments.timing)
    add("w_budget", experiments.budgets)
    add("w_iterations", experiments.best_rounds)
    add("w_ablation", experiments.ablations)
    add("w_best", experiments.best_ratio)
    add("w_noise_em", lambda s, d: rounded(regions.uniform(s, 5, 2).join(quadtree.counted(histogram.build(steps_of(s, d, "em")), regions.uniform(s, 5, 2)), "pid").select("pid", (F.col("count") * 0.025).alias("snr")), "snr"),
        S.steps("em", 5) + f", {S.hist()}, queries AS (SELECT (r * 4 + c)::BIGINT AS qid, r * 8 AS r1, r * 8 + 7 AS r2, c * 8 AS c1, c * 8 + 7 AS c2 FROM (SELECT unnest(range(4)) AS r), (SELECT unnest(range(4)) AS c)), {S.answers()} SELECT qid AS pid, round(ans * 0.025, 6) AS snr FROM answers")

    def walk(s, rows):
        return s.createDataFrame([(t, i, r, c) for t, cells in enumerate(rows) for i, (r, c) in enumerate(cells)], "traj_id long, step long, row int, col int")

    def example1(s, d):
        """Four trajectories over a 4 x 4 grid and seven regions, with the densities of the worked example."""
        steps = walk(s, [[(0, 0)], [(1, 1), (2, 1), (2, 2)], [(0, 2), (1, 2), (2, 2)], [(3, 2), (3, 3), (2, 3)]])
        boxes = s.createDataFrame([(1, 0, 1, 0, 1), (2, 0, 0, 2, 3), (3, 1, 1, 2, 3), (4, 2, 3, 0, 1), (6, 3, 3, 2, 2), (7, 3, 3, 3, 3), (5, 2, 2, 2, 3)], "pid long, r1 int, r2 int, c1 int, c2 int")
        return quadtree.density(boxes, 4, quadtree.counted(histogram.build(steps), boxes)).select("pid", "b")

    add("w_example1", example1, "SELECT * FROM (VALUES (1::BIGINT, 0.5::DOUBLE), (2, 0.25), (3, 0.25), (4, 0.25), (5, 0.75), (6, 0.25), (7, 0.25)) t(pid, b)")

    def example2(s, d):
        steps = walk(s, [[(0, 0), (0, 1)], [(1, 2), (1, 3), (2, 3), (3, 3), (3, 2)]])
        q = s.createDataFrame([(1, 0, 3, 2, 2), (2, 0, 0, 0, 1)], "qid long, r1 int, r2 int, c1 int, c2 int")
        exact = answering.exact(steps, q).withColumnRenamed("ans", "distinct")
        return answering.from_hist(histogram.build(steps), q).join(exact, "qid")

    add("w_example2", example2, "SELECT * FROM (VALUES (1::BIGINT, 2.0::DOUBLE, 1.0::DOUBLE), (2, 1.0, 1.0)) t(qid, ans, \"distinct\")")

    def example4(s, d):
        f, v, h = np.full((3, 3), 4.0), np.full((3, 2), 3.0), np.full((2, 3), 3.0)
        f[0:2, 0:2] = 2
        v[0:2, 0], h[0, 0:2] = 1.5, 1.5
        return histogram.violations(framed(s, DenseHist(f, v, h)))

    add("w_example4", example4, "SELECT * FROM (VALUES ('V', 0, 1, 3.0::DOUBLE, 2.0::DOUBLE, 1.0::DOUBLE), ('V', 1, 1, 3, 2, 1), ('H', 1, 0, 3, 2, 1), ('H', 1, 1, 3, 2, 1)) t(comp, row, col, cnt, low, excess)")


tables()
step_one()
step_two()
others()
accuracy()
workloads()
