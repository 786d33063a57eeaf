"""Building blocks of the SQL twins, written for DuckDB and apart from the DataFrame code."""

from __future__ import annotations

BOX = {"em": (-2, 2, -2, 2), "ev": (0, 100, 0, 256), "evu": (0, 100, 0, 256), "or": (0, 2405, 0, 500000), "cv": (0, 16, 0, 16)}
NUMBER = "(row_number() OVER (PARTITION BY traj_id ORDER BY {}) - 1)"


def points(src: str) -> str:
    """CTE points(traj_id, seq, x, y)."""
    if src in ("ev", "evu"):
        traj = "user_id * 100000 + date_diff('day', DATE '1970-01-01', ts::DATE)" if src == "ev" else "user_id"
        return f"points AS (SELECT traj_id, {NUMBER.format('ts, event_id')} AS seq, x, y FROM (SELECT ({traj})::BIGINT AS traj_id, ts, event_id, (props::JSON->>'$.k')::DOUBLE AS x, value::DOUBLE AS y FROM events))"
    if src == "em":
        return """points AS (SELECT traj_id, seq, sum(dx) OVER w AS x, sum(dy) OVER w AS y FROM (
  SELECT vec_id::BIGINT AS traj_id, i::BIGINT AS seq, embedding[2 * i + 1]::DOUBLE AS dx, embedding[2 * i + 2]::DOUBLE AS dy FROM embeddings, (SELECT unnest(range(32)) AS i))
  WINDOW w AS (PARTITION BY traj_id ORDER BY seq ROWS UNBOUNDED PRECEDING))"""
    if src == "li":
        return f"points AS (SELECT traj_id, {NUMBER.format('l_linenumber, l_partkey, l_suppkey, l_quantity')} AS seq, l_partkey::DOUBLE AS x, (l_quantity - 1)::DOUBLE AS y FROM (SELECT l_orderkey::BIGINT AS traj_id, * FROM lineitem))"
    if src == "or":
        return f"points AS (SELECT traj_id, {NUMBER.format('o_orderdate, o_orderkey')} AS seq, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::DOUBLE AS x, o_totalprice::DOUBLE AS y FROM (SELECT o_custkey::BIGINT AS traj_id, * FROM orders))"
    return f"points AS (SELECT traj_id, {NUMBER.format('turn, y')} AS seq, turn::DOUBLE AS x, y FROM (SELECT conv_id::BIGINT AS traj_id, turn, floor(log2(coalesce(length(text), 0) + 1)) AS y FROM conversations))"


def gridded(src: str, res: int) -> str:
    """CTE cells0(traj_id, step, row, col): each point's cell, clamped."""
    side = 1 << res
    if src == "li":
        x = f"floor(x / (SELECT max(p_partkey) + 1 FROM part)::DOUBLE * {side})"
        y = f"floor(y / 50.0::DOUBLE * {side})"
    else:
        x0, x1, y0, y1 = BOX[src]
        x, y = f"floor((x - {x0}) / {x1 - x0}::DOUBLE * {side})", f"floor((y - {y0}) / {y1 - y0}::DOUBLE * {side})"
    clamp = lambda v: f"least(greatest({v}, 0), {side - 1})::INTEGER"
    return f"cells0 AS (SELECT traj_id, seq AS step, {clamp(y)} AS row, {clamp(x)} AS col FROM points WHERE x IS NOT NULL AND y IS NOT NULL)"


def collapsed(of: str = "cells0") -> str:
    return f"""cells1 AS (SELECT traj_id, row_number() OVER (PARTITION BY traj_id ORDER BY step) - 1 AS step, row, col FROM (
  SELECT *, lag(row) OVER w AS pr, lag(col) OVER w AS pc FROM {of} WINDOW w AS (PARTITION BY traj_id ORDER BY step)) WHERE pr IS NULL OR pr <> row OR pc <> col)"""


def staircase() -> str:
    """CTE cells2: hops filled along the row first. Each hop's cells are listed from both of its ends."""
    return """hops AS (SELECT *, lead(row) OVER w AS nr, lead(col) OVER w AS nc FROM cells1 WINDOW w AS (PARTITION BY traj_id ORDER BY step)),
across AS (SELECT traj_id, step, abs(c - col) AS k, row, c::INTEGER AS col FROM (SELECT *, unnest(CASE WHEN nc IS NULL THEN [col] WHEN nc >= col THEN range(col, nc + 1) ELSE range(nc, col + 1) END) AS c FROM hops)),
upward AS (SELECT traj_id, step, abs(nc - col) + abs(r - row) AS k, r::INTEGER AS row, nc AS col FROM (SELECT *, unnest(CASE WHEN nr > row THEN range(row + 1, nr + 1) WHEN nr < row THEN range(nr, row) ELSE [] END) AS r FROM hops WHERE nr IS NOT NULL)),
listed AS (SELECT a.traj_id, a.step, k, a.row, a.col FROM (SELECT * FROM across UNION ALL SELECT * FROM upward) a JOIN hops h ON h.traj_id = a.traj_id AND h.step = a.step WHERE h.nr IS NULL OR a.row <> h.nr OR a.col <> h.nc),
cells2 AS (SELECT traj_id, row_number() OVER (PARTITION BY traj_id ORDER BY step, k) - 1 AS step, row, col FROM listed)"""


def erased() -> str:
    """CTE cells3: loops taken out, by following each cell's last visit."""
    return """visits AS MATERIALIZED (SELECT traj_id, step, row, col, max(step) OVER (PARTITION BY traj_id, row, col) AS last FROM cells2),
walk(traj_id, step, row, col, last, k) AS (
  SELECT traj_id, step, row, col, last, 0 FROM visits WHERE step = 0
  UNION ALL SELECT v.traj_id, v.step, v.row, v.col, v.last, k + 1 FROM walk w JOIN visits v ON v.traj_id = w.traj_id AND v.step = w.last + 1),
cells3 AS (SELECT traj_id, k::BIGINT AS step, row, col FROM walk)"""


def steps(src: str, res: int, loops: str = "keep") -> str:
    """WITH RECURSIVE ... up to steps(traj_id, step, row, col)."""
    parts = [points(src), gridded(src, res), collapsed(), staircase()]
    if loops == "erase":
        parts.append(erased())
    parts.append(f"steps AS MATERIALIZED (SELECT * FROM {'cells3' if loops == 'erase' else 'cells2'})")
    return "WITH RECURSIVE " + ",\n".join(parts)


def crossed() -> str:
    return """crossings AS (SELECT traj_id, step, CASE WHEN row = nr THEN 'V' ELSE 'H' END AS comp, least(row, nr) AS row, least(col, nc) AS col FROM (
  SELECT *, lead(row) OVER w AS nr, lead(col) OVER w AS nc FROM steps WINDOW w AS (PARTITION BY traj_id ORDER BY step)) WHERE abs(nr - row) + abs(nc - col) = 1)"""


def hist(mode: str = "visits") -> str:
    """CTE hist(comp, row, col, cnt) after steps."""
    word = "DISTINCT " if mode == "distinct" else ""
    return crossed() + f""",
hist AS MATERIALIZED (SELECT comp, row, col, count(*)::DOUBLE AS cnt FROM (SELECT {word}* FROM (SELECT traj_id, 'F' AS comp, row, col{'' if word else ', step'} FROM steps UNION ALL SELECT traj_id, comp, row, col{'' if word else ', step'} FROM crossings)) GROUP BY comp, row, col)"""


def shares(side: int) -> str:
    """CTE shares(row, col, cnt): every cell, each trajectory adding one in all."""
    return f"""visited AS (SELECT DISTINCT traj_id, row, col FROM steps),
part_of AS (SELECT row, col, sum(1.0::DOUBLE / k) AS cnt FROM (SELECT *, count(*) OVER (PARTITION BY traj_id) AS k FROM visited) GROUP BY row, col),
shares AS MATERIALIZED (SELECT r::INTEGER AS row, c::INTEGER AS col, coalesce(cnt, 0) AS cnt FROM (SELECT unnest(range({side})) AS r), (SELECT unnest(range({side})) AS c) LEFT JOIN part_of ON part_of.row = r AND part_of.col = c)"""


def dense(side: int) -> str:
    """CTE full_hist: all components, zeros included."""
    return f"""grid AS (SELECT r::INTEGER AS row, c::INTEGER AS col FROM (SELECT unnest(range({side})) AS r), (SELECT unnest(range({side})) AS c)),
slots AS (SELECT 'F' AS comp, row, col FROM grid UNION ALL SELECT 'V', row, col FROM grid WHERE col < {side - 1} UNION ALL SELECT 'H', row, col FROM grid WHERE row < {side - 1}),
full_hist AS MATERIALIZED (SELECT comp, row, col, coalesce(cnt, 0)::DOUBLE AS cnt FROM slots LEFT JOIN hist USING (comp, row, col))"""


def uniform(seed: int, stream: str, *keys: str) -> str:
    tail = "".join(f" || '|' || ({k})::VARCHAR" for k in keys)
    return f"((('0x' || substr(md5('{seed}|{stream}'{tail}), 1, 13))::BIGINT + 0.5) / {1 << 52}::DOUBLE)"


def laplace(u: str, scale: str | float) -> str:
    return f"(-({scale})::DOUBLE * sign({u} - 0.5) * ln(1 - 2 * abs({u} - 0.5)))"


def gumbel(u: str) -> str:
    return f"(-ln(-ln({u})))"


def rectangles(side: int, m: int, seed: int = 7) -> str:
    """CTE queries(qid, r1, r2, c1, c2), two sorted uniform cells an axis."""
    draw = lambda k: f"floor({uniform(seed, k, 'qid')} * {side})::INTEGER"
    return f"""draws AS (SELECT qid, {draw('a')} AS a, {draw('b')} AS b, {draw('c')} AS c, {draw('d')} AS d FROM (SELECT unnest(range({m})) AS qid)),
queries AS MATERIALIZED (SELECT qid, least(a, b) AS r1, greatest(a, b) AS r2, least(c, d) AS c1, greatest(c, d) AS c2 FROM draws)"""


def answers(of: str = "hist", name: str = "answers", faces: bool = False, queries: str = "queries") -> str:
    """CTE name(qid, ans): faces minus edges inside, by a range join."""
    more = " AND comp = 'F'" if faces else ""
    return f"""{name} AS MATERIALIZED (SELECT q.qid, coalesce(sum(CASE WHEN comp = 'F' THEN cnt ELSE -cnt END), 0)::DOUBLE AS ans FROM {queries} q LEFT JOIN {of} h
  ON row BETWEEN r1 AND r2 - (comp = 'H')::INTEGER AND col BETWEEN c1 AND c2 - (comp = 'V')::INTEGER{more} GROUP BY q.qid)"""
