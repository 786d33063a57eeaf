"""Registered queries over whole tables: rows that a filter on ids would lose."""

import functools
import itertools
from datetime import datetime, timedelta

import numpy as np
import pandas as pd
import pytest

from trajdp import queries
from trajdp.operators import histogram, relational, sums
from trajdp.plans import experiments
from trajdp.sources import trajectories
from trajdp.storage import kept

WALK_SUMS = sums.walk_sums
PREPARED = experiments.prepared


def test_interval_join_covers_all_users(spark, tmp_path):
    users = [3, 40, 41, 700, 1499]
    start = datetime(2024, 1, 1)
    rows = [(u, start + timedelta(days=d, minutes=7 * u % 600 + m)) for u in users for d in range(3) for m in (0, 90 + 20 * d)]
    frame = pd.DataFrame(rows, columns=["user_id", "ts"])
    spark.createDataFrame(frame).write.parquet(f"{tmp_path}/events.parquet")
    spans = frame.groupby(["user_id", frame["ts"].dt.date])["ts"].agg(["min", "max"])
    per_user = {u: list(spans.loc[u].itertuples(index=False)) for u in users}
    want = {}
    for u, v in itertools.combinations(users, 2):
        n = sum(x[0] <= y[1] and y[0] <= x[1] for x in per_user[u] for y in per_user[v])
        if n:
            want[u, v] = n
    assert any(u > 40 for u, _ in want)
    found = queries.queries()["r_join_interval"](spark, str(tmp_path)).collect()
    assert {(r["user_id"], r["other"]): r["n"] for r in found} == want


def test_distinct_histogram_over_chunks_and_far_cells(spark):
    """Walks that reach over chunks, go back and forth, jump, and lie at negative cells; no hash of all walks and components in the plan."""
    rng = np.random.default_rng(3)
    rows, want = [], {}
    for t in range(12):
        r, c = rng.integers(-3, 3, 2).tolist()
        own = set()
        for step in range(0 if t == 5 else rng.integers(1, 60)):
            if step:
                dr, dc = [(0, 1), (0, -1), (1, 0), (-1, 0), (0, 0), (2, 1)][rng.integers(6)]
                if abs(dr) + abs(dc) == 1:
                    own.add(("V" if dc else "H", min(r, r + dr), min(c, c + dc)))
                r, c = r + dr, c + dc
            own.add(("F", r, c))
            rows.append((t * 10**12, step, r, c))
        for k in own:
            want[k] = want.get(k, 0) + 1
    steps = spark.createDataFrame(rows[::-1], "traj_id long, step long, row int, col int")
    for chunk in (1, 7, 1 << 19):
        got = sums.distinct_counts(steps, chunk)
        assert {(r["comp"], r["row"], r["col"]): r["cnt"] for r in got.collect()} == want
    plan = histogram.build(steps, "distinct")._jdf.queryExecution().executedPlan().toString()
    assert "keys=[traj_id" not in plan
    assert histogram.build(steps.limit(0), "distinct").count() == 0


@pytest.mark.parametrize("source", ["em", "cv", "or"])
def test_experiment_case_from_one_pass(spark, data, source, monkeypatch):
    """The sums of an experiment are those of its frames, without a frame of all steps."""
    points, grid = trajectories.points(spark, data, source), trajectories.box(spark, data, source, 5)
    points = points.unionByName(spark.createDataFrame([(-5, 0, None, 1.0)], "traj_id long, seq long, x double, y double"))
    monkeypatch.setattr(experiments, "MOST_STEPS", 0)
    want = experiments.case_of(points, source, grid, 10)
    monkeypatch.setattr(experiments, "MOST_STEPS", 1 << 22)
    monkeypatch.setattr(experiments, "prepared", None)
    for chunk in (1, None):
        monkeypatch.setattr(sums, "walk_sums", functools.partial(WALK_SUMS, chunk=chunk))
        got = experiments.case_of(points, source, grid, 10)
        assert (got.n, got.longest) == (want.n, want.longest)
        assert all(np.array_equal(a, b) for a, b in zip(got.truth.parts(), want.truth.parts()))
        assert np.allclose(got.shares, want.shares, atol=1e-9)
    empty = experiments.case_of(points.limit(0), source, grid, 10)
    assert empty.n == 0 and empty.truth.f.sum() == 0


def plain_steps(points):
    """A walk's cells with staircases, and without loops, one by one."""
    points = [p for i, p in enumerate(points) if not i or p != points[i - 1]]
    steps = points[:1]
    for r, c in points[1:]:
        row, col = steps[-1]
        steps += [(row, x) for x in (range(col + 1, c + 1) if c > col else range(col - 1, c - 1, -1))]
        steps += [(x, c) for x in (range(row + 1, r + 1) if r > row else range(row - 1, r - 1, -1))]
    last, own, i = {x: k for k, x in enumerate(steps)}, [], 0
    while i < len(steps):
        own.append(steps[i])
        i = last[steps[i]] + 1
    return steps, own


@pytest.mark.parametrize("side", [1, 2, 5, 16])
def test_walks_go_on_from_stretch_to_stretch(side, monkeypatch):
    """Steps and kept steps of walks that are looked at few or many at a time."""
    rng = np.random.default_rng(side)
    walks = [[tuple(x) for x in rng.integers(0, side, (rng.integers(1, 14), 2)).tolist()] for _ in range(40)]
    number, cells = np.repeat(np.arange(40), [len(w) for w in walks]), np.array([x for w in walks for x in w])
    for span, table in ((1, 1), (30, 3 * side**2), (1 << 17, 1 << 14)):
        monkeypatch.setattr(sums, "SPAN", span)
        monkeypatch.setattr(sums, "TABLE", table)
        got, last = ([], []), np.empty(max(table, side**2), np.int32)
        for code, lengths in sums.staircases(number, cells[:, 0], cells[:, 1], side):
            for out, (x, n) in zip(got, ((code, lengths), sums.without_loops(code, lengths, last))):
                out += [[(int(k) % side**2 // side, int(k) % side) for k in part] for part in np.split(x, np.cumsum(n)[:-1])]
        assert list(zip(*got)) == [plain_steps(w) for w in walks]


def test_experiment_case_reads_its_points_once(spark, monkeypatch):
    """One pass over the points, with a walk of more points than a task took before; a walk too long for arrays goes through frames."""
    rng = np.random.default_rng(5)
    rows = [(t, k, *x) for t, n in ((1, 9), (2, 9000), (3, 30)) for k, x in enumerate(rng.random((n, 2)).tolist())]
    frame = kept(spark.createDataFrame(rows, "traj_id long, seq long, x double, y double"))
    read = spark.sparkContext.accumulator(0)

    def counted(batches):
        for batch in batches:
            read.add(len(batch))
            yield batch

    points, grid = frame.mapInPandas(counted, frame.schema), trajectories.GridSpec(0, 1, 0, 1, 8)
    with monkeypatch.context() as patch:
        patch.setattr(experiments, "prepared", None)
        got = experiments.case_of(points, "gen", grid, 10)
    assert read.value == len(rows)
    cells = [[(int(y * 256), int(x * 256)) for t, _, x, y in rows if t == k] for k in (1, 2, 3)]
    walks = [plain_steps(w)[1] for w in cells]
    assert (got.n, got.longest, got.truth.f.sum()) == (3, max(map(len, walks)), sum(map(len, walks)))
    assert np.array_equal(np.argwhere(got.truth.f), sorted(set(sum(walks, []))))
    small = trajectories.GridSpec(0, 1, 0, 1, 3)
    few, want = frame.where("traj_id <> 2"), experiments.case_of(frame.where("traj_id <> 2"), "gen", small, 10)
    monkeypatch.setattr(experiments, "MOST_STEPS", 80)
    framed = []
    monkeypatch.setattr(experiments, "prepared", lambda *a: framed.append(1) or PREPARED(*a))
    got = experiments.case_of(few, "gen", small, 10)
    assert framed and (got.n, got.longest) == (want.n, want.longest)
    assert all(np.array_equal(a, b) for a, b in zip(got.truth.parts(), want.truth.parts()))


@pytest.mark.parametrize("block", [2, 5, 4096])
def test_overlaps_counted_without_a_join(spark, block):
    """Spans over several days, more than one a day and keys of texts; no join makes a row for each pair and day."""
    rng = np.random.default_rng(5)
    start = datetime(2024, 2, 27)
    spans = []
    for _ in range(90):
        a = start + timedelta(hours=int(rng.integers(0, 120)))
        spans.append((f"k{rng.integers(14)}", a, a + timedelta(minutes=int(rng.choice([0, 50, 600, 4000])))))
    spans += [(None, start, start), ("k1", None, start), ("k2", start, None)]
    want = {}
    for (k, a, b), (m, c, d) in itertools.product(spans[:90], repeat=2):
        if k < m and a <= d and c <= b:
            want[k, m] = want.get((k, m), 0) + 1
    frame = spark.createDataFrame(spans, "key string, a timestamp, b timestamp")
    got = relational.overlapping(frame, "key", "a", "b", block)
    assert {(r["key"], r["other"]): r["n"] for r in got.collect()} == want
    assert "Join" not in got._jdf.queryExecution().executedPlan().toString()
