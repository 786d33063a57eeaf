"""Registered queries of the streaming operators; batch twins have SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..streaming import live

CELL = "least(greatest(floor(value / 256.0 * 16), 0), 15)::INTEGER AS row, least(greatest(floor((props::JSON->>'$.k')::DOUBLE / 100.0 * 16), 0), 15)::INTEGER AS col"


def events(s, d):
    return s.read.parquet(f"{d}/events.parquet")


def run(s, d, plan, mode: str = "append", behind=None, extra=None):
    """Streams the events as four files in the order of time, one a micro-batch; ``behind``: a condition on rows that come after all others."""
    rows = events(s, d)
    late = None if behind is None else rows.where(F.expr(behind))
    rows = rows if behind is None else rows.where(~F.expr(behind))
    return live.drained(plan(live.source(s, live.feed(rows if extra is None else rows.unionByName(extra(rows)), 4, late))), mode)


def counted(e):
    return e.groupBy("comp", "row", "col").agg(F.count(F.lit(1)).alias("cnt"))


DELAYED = "event_id % 50 = 0"


def dropped(s, d):
    """delayed, dropped: rows that came behind all others, and how many of them found their window closed."""
    rows = events(s, d)
    seen = run(s, d, lambda e: live.tumbling(live.cells(e)), "append", DELAYED).agg(F.sum("cnt").alias("seen"))
    last = rows.where(~F.expr(DELAYED)).agg(F.max("ts").alias("last"))
    ended = F.date_trunc("day", "ts") + F.expr("interval 1 day") <= F.col("last") - F.expr("interval 1 hour")
    counts = rows.join(F.broadcast(last)).where(ended).agg(F.count(F.lit(1)).alias("every"), F.sum(F.expr(DELAYED).cast("int")).alias("delayed"))
    return counts.join(F.broadcast(seen)).select("delayed", (F.col("every") - F.col("seen")).alias("dropped"))


QUERIES = {
    "t_tumbling": lambda s, d: live.tumbling(live.cells(events(s, d))),
    "t_sliding": lambda s, d: live.sliding(live.cells(events(s, d))),
    "t_session": lambda s, d: live.sessions(live.cells(events(s, d))),
    "t_tumbling_stream": lambda s, d: run(s, d, lambda e: live.tumbling(live.cells(e)), "complete"),
    "t_sliding_stream": lambda s, d: run(s, d, lambda e: live.sliding(live.cells(e)), "complete"),
    "t_session_stream": lambda s, d: run(s, d, lambda e: live.sessions(live.cells(e)), "complete"),
    "t_stateful_crossings": lambda s, d: counted(run(s, d, lambda e: live.crossings(live.cells(e)))),
    "t_stateful_timeout": lambda s, d: counted(run(s, d, lambda e: live.crossings(live.cells(e), "12 hours"))),
    "t_dedup": lambda s, d: run(s, d, lambda e: live.deduplicated(e).select("event_id", "user_id"), extra=lambda e: e.where("event_id % 7 = 0")),
    "t_late": lambda s, d: run(s, d, lambda e: live.tumbling(live.cells(e)), "append", DELAYED),
    "t_late_count": dropped,
    "t_static_join": lambda s, d: run(s, d, lambda e: live.with_customers(e, s.read.parquet(f"{d}/customer.parquet"))),
    "t_interval_join": lambda s, d: live.clicks_to_purchases(events(s, d)),
    "t_interval_join_stream": lambda s, d: run(s, d, live.clicks_to_purchases),
    "t_release": lambda s, d: live.released_windows(live.tumbling(live.cells(events(s, d))), 1.0, 30, seed=7)[0].withColumn("cnt", F.round("cnt", 6)),
}
DAY = f"SELECT date_trunc('day', ts) AS start, {CELL} FROM events"
HOPS = """WITH p AS (SELECT user_id, {cell}, ts, event_id FROM events), h AS (SELECT *, lead(row) OVER w AS r2, lead(col) OVER w AS c2, lead(ts) OVER w - ts AS gap FROM p WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
k AS (SELECT * FROM h WHERE {kept}), x AS (SELECT 'V' AS comp, row, unnest(range(least(col, c2), greatest(col, c2)))::INTEGER AS col FROM k UNION ALL SELECT 'H', unnest(range(least(row, r2), greatest(row, r2)))::INTEGER, c2 FROM k) SELECT comp, row, col, count(*) AS cnt FROM x GROUP BY ALL"""
CLOSED = "start + INTERVAL 1 DAY <= (SELECT max(ts) FROM events WHERE event_id % 50 <> 0) - INTERVAL 1 HOUR"
SQL = {
    "t_tumbling": f"SELECT start, row, col, count(*) AS cnt FROM ({DAY}) GROUP BY ALL",
    "t_tumbling_stream": f"SELECT start, row, col, count(*) AS cnt FROM ({DAY}) GROUP BY ALL",
    "t_sliding": f"SELECT start - to_days(i) AS start, row, count(*) AS cnt FROM ({DAY}), (SELECT unnest([0, 1])::INTEGER AS i) GROUP BY ALL",
    "t_session": """WITH g AS (SELECT user_id, ts, coalesce((ts - lag(ts) OVER w >= INTERVAL 6 HOUR)::INTEGER, 1) AS n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(n) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS cnt FROM s GROUP BY user_id, k""",
    "t_stateful_crossings": HOPS.format(cell=CELL, kept="true"),
    "t_stateful_timeout": HOPS.format(cell=CELL, kept="gap <= INTERVAL 12 HOUR"),
    "t_late": f"SELECT start, row, col, count(*) AS cnt FROM (SELECT date_trunc('day', ts) AS start, {CELL} FROM events WHERE event_id % 50 <> 0) WHERE {CLOSED} GROUP BY ALL",
    "t_late_count": f"SELECT count(*) AS delayed, count(*) AS dropped FROM (SELECT date_trunc('day', ts) AS start FROM events WHERE event_id % 50 = 0) WHERE {CLOSED}",
    "t_dedup": "SELECT event_id, user_id FROM events",
    "t_static_join": "SELECT event_id, user_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey",
    "t_interval_join": "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.event_type = 'click' AND b.event_type = 'purchase' AND a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 2 DAY",
}
SQL |= {f"{k}_stream": SQL[k] for k in ("t_sliding", "t_session", "t_interval_join")}
