"""Worked examples, certificates, invariants and limits of the methods."""

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from trajdp.functions import noise
from trajdp.operators import answering, histogram, mechanisms, quadtree, regions, walks, workload
from trajdp.plans import baselines, estimator, experiments, release, repair
from trajdp.plans.dense import DenseHist, box_sums, collected, framed, partitioned
from trajdp.sources import trajectories


def steps(spark, cells):
    return spark.createDataFrame([(t, i, r, c) for t, w in enumerate(cells) for i, (r, c) in enumerate(w)], "traj_id long, step long, row int, col int")


def rect(spark, *boxes):
    return spark.createDataFrame([(i, *b) for i, b in enumerate(boxes)], "qid long, r1 int, r2 int, c1 int, c2 int")


def counts(df):
    return {(r["comp"], r["row"], r["col"]): r["cnt"] for r in df.collect()}


def test_diagonal_hop_goes_along_the_row_first(spark):
    got = counts(histogram.build(walks.fill(steps(spark, [[(0, 0), (1, 1)]]))))
    assert got == {("F", 0, 0): 1, ("F", 0, 1): 1, ("F", 1, 1): 1, ("V", 0, 0): 1, ("H", 0, 1): 1}


def test_there_and_back(spark):
    s = steps(spark, [[(0, 0), (0, 1), (0, 0)]])
    assert counts(histogram.build(s)) == {("F", 0, 0): 2, ("F", 0, 1): 1, ("V", 0, 0): 2}
    assert counts(histogram.build(s, "distinct")) == {("F", 0, 0): 1, ("F", 0, 1): 1, ("V", 0, 0): 1}
    assert counts(histogram.build(walks.erase_loops(s))) == {("F", 0, 0): 1}


def test_whole_space_counts_trajectories(spark, data):
    grid = trajectories.box(spark, data, "em", 4)
    s = walks.walk_steps(trajectories.points(spark, data, "em"), grid)
    hist = histogram.build(s)
    n = s.select("traj_id").distinct().count()
    assert answering.from_hist(hist, rect(spark, (0, 15, 0, 15))).first()["ans"] == n
    assert histogram.violations(hist).count() == 0
    q = workload.random_rectangles(spark, 16, 40)
    direct = {r["qid"]: r["ans"] for r in answering.from_hist(hist, q).collect()}
    assert direct == {r["qid"]: r["ans"] for r in answering.from_prefix(answering.prefix(hist, 16), q).collect()}
    assert direct == {r["qid"]: r["ans"] for r in answering.segments(s, q).collect()}
    dense = collected(hist, 16)
    rows = q.orderBy("qid").toPandas()
    assert list(dense.answers(rows[["r1", "r2", "c1", "c2"]].to_numpy())) == [direct[i] for i in rows["qid"]]


@pytest.mark.parametrize("parts", [1, 4, 17])
def test_partitioning_does_not_matter(spark, data, parts):
    grid = trajectories.box(spark, data, "cv", 4)
    p = trajectories.points(spark, data, "cv").repartition(parts)
    got = counts(histogram.build(walks.walk_steps(p, grid)))
    assert got == counts(histogram.build(walks.walk_steps(trajectories.points(spark, data, "cv"), grid)))


def test_edges_of_walks(spark):
    one = steps(spark, [[(1, 1)]])
    assert counts(histogram.build(walks.walk_steps(one.select("traj_id", "step", "row", "col").selectExpr("traj_id", "step as seq", "col + 0.5D as x", "row + 0.5D as y"), trajectories.GridSpec(0, 2, 0, 2, 1)))) == {("F", 1, 1): 1}
    none = one.where("false")
    assert histogram.build(none).count() == 0 and answering.from_hist(histogram.build(none), rect(spark, (0, 1, 0, 1))).first()["ans"] == 0
    pts = spark.createDataFrame([(1, 0, -5.0, 0.5), (1, 1, None, 0.5), (1, 2, 9.0, 0.5)], "traj_id long, seq long, x double, y double")
    box = trajectories.GridSpec(0, 4, 0, 4, 2)
    assert [(r["row"], r["col"]) for r in walks.assign(pts, box).orderBy("step").collect()] == [(0, 0), (0, 3)]
    assert walks.assign(pts, trajectories.GridSpec(0, 4, 0, 4, 2, "drop")).count() == 0


def test_segment_cells_are_connected():
    for x, y, x2, y2 in ((0.5, 0.5, 3.2, 2.7), (3.9, 3.9, 0.1, 0.2), (1.5, 0.1, 1.5, 3.9)):
        cells = walks.segment_cells(x, y, x2, y2)
        assert cells[0] == (int(y), int(x)) and cells[-1] == (int(y2), int(x2))
        assert all(abs(a - c) + abs(b - d) == 1 for (a, b), (c, d) in itertools.pairwise(cells))


def test_costs_of_blocks(spark):
    faces = spark.createDataFrame([(0, 0, 2.0), (0, 1, 2.0), (1, 0, 2.0), (1, 1, 2.0), (0, 2, 0.0), (0, 3, 0.0), (1, 2, 0.0), (1, 3, 8.0)], "row int, col int, cnt double")
    boxes = spark.createDataFrame([(1, 0, 1, 0, 1), (2, 0, 1, 2, 3)], "pid long, r1 int, r2 int, c1 int, c2 int")
    assert {r["pid"]: r["cost"] for r in quadtree.cost(faces, quadtree.cell_region(boxes)).collect()} == {1: 0.0, 2: 12.0}


def recursive(cells, noisy, limit, res, level=0, br=0, bc=0):
    """The descent from the root, one node at a time."""
    here = noisy[level, br, bc]
    if level == res:
        return {(level, br, bc)}
    kids = [(level + 1, 2 * br + i, 2 * bc + j) for i in (0, 1) for j in (0, 1)]
    if here - sum(noisy[k] for k in kids) / 4 <= limit:
        return {(level, br, bc)}
    return set().union(*(recursive(cells, noisy, limit, res, *k) for k in kids))


def test_quadtree_equals_descent_and_covers(spark):
    rng = np.random.default_rng(1)
    cells = rng.integers(0, 30, (8, 8)) * (rng.random((8, 8)) < 0.4)
    faces = spark.createDataFrame([(r, c, float(cells[r, c])) for r in range(8) for c in range(8)], "row int, col int, cnt double")
    for p in (quadtree.PartitionParams(eps1=1.0, threshold="stddev", seed=7), quadtree.PartitionParams(noise=False, threshold=10.0)):
        table = quadtree.noisy(quadtree.nodes(faces, 3), p, 3)
        noisy = {(r["level"], r["br"], r["bc"]): r["noisy_cost"] for r in table.collect()}
        found = quadtree.leaves(quadtree.split_flags(table, p), 3)
        assert {(r["level"], r["br"], r["bc"]) for r in found.collect()} == recursive(cells, noisy, quadtree.threshold(p), 3)
        assert quadtree.check_cover(found, 8).count() == 0
    flat = faces.selectExpr("row", "col", "3.0D as cnt")
    p = quadtree.PartitionParams(noise=False, threshold=0.0)
    assert quadtree.leaves(quadtree.split_flags(quadtree.noisy(quadtree.nodes(flat, 3), p, 3), p), 3).count() == 1
    pruned = regions.best_pruning(quadtree.nodes(faces, 3), 3, 4.0).toPandas()
    own = quadtree.leaves(quadtree.split_flags(quadtree.noisy(quadtree.nodes(faces, 3), p, 3), p), 3).join(quadtree.nodes(faces, 3).select("level", "br", "bc", "cost"), ["level", "br", "bc"]).toPandas()
    assert pruned["cost"].sum() + 4 * len(pruned) <= own["cost"].sum() + 4 * len(own) + 1e-9


def test_thresholds_and_bounds():
    assert quadtree.threshold(quadtree.PartitionParams(eps1=0.025)) == pytest.approx(6400)
    assert estimator.answer_bound(1000, 65536, 10, 16000, 0.1) == pytest.approx(11786.56, abs=0.01)
    assert estimator.least_rounds(65536) == pytest.approx(44.36, abs=0.01)


def test_budget():
    assert mechanisms.split_budget(1.0) == (0.25,) * 4
    with pytest.raises(ValueError):
        mechanisms.split_budget(1.0, (0.5, 0.5, 0.5, 0.5))
    book = mechanisms.Ledger(1.0)
    book.spend("cost", 0.5, 2.0, composition="parallel")
    book.spend("cost", 0.5, 2.0, composition="parallel")
    book.spend("answer", 0.5, 1.0)
    assert book.total() == pytest.approx(1.0)
    with pytest.raises(ValueError):
        book.spend("answer", 0.1, 1.0)


def test_selection_probabilities(spark):
    scored = spark.createDataFrame([(0, 0.0), (1, 2 * math.log(3) / 0.5)], "qid long, score double")
    assert [round(r["prob"], 9) for r in mechanisms.exponential_probs(scored, 0.5).orderBy("qid").collect()] == [0.25, 0.75]


def test_noise_moments_and_audit(spark):
    u = np.array([noise.uniform_value(3, "x", i) for i in range(20000)])
    x = noise.laplace_value(u, 2.0)
    assert abs(x.mean()) < 0.1 and abs(x.var() - 8) < 0.6
    got = [r["u"] for r in spark.range(5).select(noise.uniform(3, "x", "id").alias("u")).collect()]
    assert np.allclose(got, u[:5], rtol=0, atol=0)
    draw = lambda value, run: value + float(noise.laplace_value(noise.uniform_value(5, "a", run), 1.0))
    assert mechanisms.audit(draw, 10.0, 11.0, 20000, 0.5) < 1.0 + 0.35


def test_repair_is_optimal_on_small_grids():
    rng = np.random.default_rng(2)
    for _ in range(60):
        h = DenseHist(rng.integers(0, 4, (2, 2)).astype(float), rng.integers(0, 5, (2, 1)).astype(float), rng.integers(0, 5, (1, 2)).astype(float))
        got, best = repair.optimal(h), math.inf
        for values in itertools.product(range(5), repeat=4):
            f = np.array(values, float).reshape(2, 2)
            best = min(best, np.abs(f - h.f).sum() + np.maximum(h.v - np.minimum(f[:, :-1], f[:, 1:]), 0).sum() + np.maximum(h.h - np.minimum(f[:-1], f[1:]), 0).sum())
        assert got.certified and got.moved == pytest.approx(best)


@pytest.mark.parametrize("face, edges, cost, lowered", [(1.0, 2.0, 1.0, 4.0), (2.0, None, 3.0, 3.0)])
def test_star_repairs(spark, face, edges, cost, lowered):
    h = DenseHist.zeros(3)
    h.f[:] = 6.0
    h.f[1, 1] = face
    if edges:
        h.v[1], h.h[:, 1] = edges, edges
    else:
        h.v[1, 0] = 5.0
    assert repair.optimal(h).moved == pytest.approx(cost)
    moved = lambda g: sum(np.abs(a - b).sum() for a, b in zip(g.parts(), h.parts()))
    assert moved(repair.greedy(h)) == pytest.approx(lowered)
    assert moved(collected(repair.star_frame(framed(spark, h)), 3)) == pytest.approx(cost)


def test_consistent_need_not_be_monotone():
    h = DenseHist(np.ones((2, 2)), np.ones((2, 1)), np.ones((1, 2)))
    assert h.violated() == 0
    assert list(h.answers(np.array([[0, 1, 0, 1], [0, 0, 0, 0]]))) == [0.0, 1.0]


def test_box_sums():
    x = np.arange(12.0).reshape(3, 4)
    assert box_sums(x, np.array([0]), np.array([1]), np.array([1]), np.array([2]))[0] == x[:2, 1:3].sum()
    assert box_sums(x, np.array([1]), np.array([0]), np.array([0]), np.array([3]))[0] == 0


def setting(rng):
    truth = DenseHist.zeros(8)
    truth.f[:] = rng.integers(5, 40, (8, 8))
    truth.v[:], truth.h[:] = np.minimum(truth.f[:, :-1], truth.f[:, 1:]) / 2, np.minimum(truth.f[:-1], truth.f[1:]) / 2
    q = np.sort(rng.integers(0, 8, (60, 2, 2)), axis=2).reshape(60, 4)
    n = float(truth.f.sum() - truth.v.sum() - truth.h.sum())
    return truth, np.arange(60), q, n


def test_synthesis_without_noise_improves_and_backends_agree():
    import pandas as pd

    truth, qids, q, n = setting(np.random.default_rng(4))
    parts = pd.DataFrame([(r, r + 3, c, c + 3, truth.f[r : r + 4, c : c + 4].sum() / n) for r in (0, 4) for c in (0, 4)], columns=["r1", "r2", "c1", "c2", "b"])
    p = estimator.SynthParams(rounds=6, noise=False, repair="none")
    a = estimator.run(truth, qids, q, parts, n, float(truth.f.sum()), p).hist
    b = estimator.run_logweight(truth, qids, q, parts, n, float(truth.f.sum()), p).hist
    for x, y in zip(a.parts(), b.parts()):
        assert np.allclose(x, y)
    start = estimator.initial(8, n, float(truth.f.sum()))
    err = lambda h: np.abs(truth.answers(q) - h.answers(q)).mean()
    fixed = estimator.run(truth, qids, q, parts, n, float(truth.f.sum()), estimator.SynthParams(rounds=6, noise=False))
    assert fixed.hist.violated() == 0 and err(fixed.hist) < err(start)
    none = estimator.run(truth, qids, q, parts, n, float(truth.f.sum()), estimator.SynthParams(rounds=0))
    assert np.allclose(none.hist.f, start.f)


def test_one_region_and_a_kept_sum_never_move():
    truth, qids, q, n = setting(np.random.default_rng(5))
    got = estimator.run(truth, qids, q, None, n, float(truth.f.sum()), estimator.SynthParams(rounds=3, noise=False)).hist
    assert np.allclose(got.f, truth.f.sum() / 64)


def test_baselines():
    r, c = baselines.hilbert_order(3)
    assert len({*zip(r, c)}) == 64 and (np.abs(np.diff(r)) + np.abs(np.diff(c)) == 1).all()
    vec = np.array([5.0, 5, 5, 5, 0, 9, 1, 1])
    tiles = baselines.bucketize(vec, 1.0, charge=0.5, noisy=False)
    assert sum(k for _, k in tiles) == 8 and tiles[0] == (0, 4)
    assert np.allclose(baselines.bucket_estimate(np.array([20.0, 9, 2]), 1.0, noisy=False), [20, 9, 2])
    noisy = baselines.bucket_estimate(np.array([20.0, 9, 2, 4]), 1.0)
    assert len(noisy) == 4
    assert np.allclose(baselines.bucket_release(vec, 1e9), vec, atol=1e-3)


def released(spark, data, **options):
    grid = trajectories.box(spark, data, "cv", 3)
    p = release.ReleaseParams(**({"eps": 1.0, "synth": estimator.SynthParams(rounds=2)} | options))
    return release.released(trajectories.points(spark, data, "cv"), workload.random_rectangles(spark, 8, 20), grid, p)


def test_release_spends_its_budget_and_leaks_nothing(spark, data):
    got = released(spark, data)
    assert got.ledger.total() == pytest.approx(1.0)
    assert {r[3] for r in got.ledger.rows if r[0] != "cost"} == {4.0}  # answers are charged the runs that walks are bounded to
    frame = got.frame()
    assert histogram.violations(frame).count() == 0
    assert sorted(frame.columns) == ["cnt", "col", "comp", "row"] and release.leak_free(frame)


def test_releases_differ_unless_seeded(spark, data):
    split = {"eps": 40.0, "partition": quadtree.PartitionParams(threshold=1.0)}  # a single region would keep its sum, and so never move
    a, b = (counts(released(spark, data, **split).frame()) for _ in range(2))
    assert a.keys() == b.keys() and max(abs(a[k] - b[k]) for k in a) > 1e-6
    a, b = (counts(released(spark, data, seed=3, **split).frame()) for _ in range(2))
    assert a == b


def test_release_over_frames_equals_the_one_over_arrays(spark, data):
    a, b = (counts(released(spark, data, seed=3, backend=k).frame()) for k in ("dense", "frame"))
    assert a.keys() == b.keys() and max(abs(a[k] - b[k]) for k in a) < 1e-6


def naive_erased(cells):
    out = []
    for c in cells:
        out = out[: out.index(c) + 1] if c in out else [*out, c]
    return out


def wander(rng, n, side):
    r, c = rng.integers(0, side, 2)
    out = [(int(r), int(c))]
    while len(out) < n:
        dr, dc = [(0, 1), (1, 0), (0, -1), (-1, 0)][rng.integers(4)]
        if 0 <= r + dr < side and 0 <= c + dc < side:
            r, c = r + dr, c + dc
            out.append((int(r), int(c)))
    return out


@pytest.mark.parametrize("most", [1, 2, 5])
def test_bounded_walks_meet_rectangles_in_few_runs(spark, most):
    rng = np.random.default_rng(most)
    s = steps(spark, [wander(rng, 60, 6) for _ in range(12)])
    boxes = [(r1, r2, c1, c2) for r1 in range(0, 6, 2) for r2 in range(r1, 6, 2) for c1 in range(0, 6, 2) for c2 in range(c1, 6, 2)]
    top = mechanisms.query_sensitivity(walks.bounded_runs(s, most), rect(spark, *boxes)).toPandas()["most"].max()
    assert 1 <= top <= most < mechanisms.query_sensitivity(s, rect(spark, *boxes)).toPandas()["most"].max()


def test_loop_erasure_equals_its_definition(spark):
    rng = np.random.default_rng(9)
    cells = [wander(rng, int(n), 5) for n in rng.integers(1, 80, 30)]
    got = walks.erase_loops(steps(spark, cells)).toPandas().sort_values(["traj_id", "step"])
    for t, part in got.groupby("traj_id"):
        assert part["step"].tolist() == list(range(len(part)))
        assert list(zip(part["row"], part["col"])) == naive_erased(cells[t])


@pytest.mark.parametrize("parent_noise", ["reuse", "fresh"])
def test_partition_over_arrays_equals_the_one_over_frames(spark, data, parent_noise):
    s = walks.walk_steps(trajectories.points(spark, data, "em"), trajectories.box(spark, data, "em", 4))
    hist = histogram.densify(histogram.build(s), 16)
    shares = histogram.densify(histogram.build(s, weight="inv_len"), 16).where("comp = 'F'")
    p = quadtree.PartitionParams(eps1=1.0, eps2=1.0, threshold="stddev", parent_noise=parent_noise, seed=5)
    n = s.select("traj_id").distinct().count()
    a = quadtree.partition(hist, shares.select("row", "col", "cnt"), n, 4, p).toPandas().sort_values("pid").reset_index(drop=True)
    b = partitioned(collected(hist, 16), collected(shares, 16).f, n, p).sort_values("pid").reset_index(drop=True)
    assert len(a) > 4 and a["pid"].tolist() == b["pid"].tolist()
    for k in ("r1", "r2", "c1", "c2", "size", "b", "total"):
        assert np.allclose(a[k], b[k]), k
    assert all(noise.draws(None).uniforms("x", np.arange(3)) != noise.draws(None).uniforms("x", np.arange(3)))


def broken_hist(rng, side=4):
    return DenseHist(rng.integers(0, 4, (side, side)).astype(float), rng.integers(0, 5, (side, side - 1)).astype(float), rng.integers(0, 5, (side - 1, side)).astype(float))


def test_components_cost_as_much_as_the_whole(spark):
    rng = np.random.default_rng(12)
    for k in range(30):
        h = broken_hist(rng) if k % 2 else DenseHist(rng.integers(2, 9, (4, 4)).astype(float), rng.integers(0, 5, (4, 3)).astype(float), rng.integers(0, 5, (3, 4)).astype(float))
        got = repair.optimal(h)
        edge, face, weight = [], [], []
        for kind, (edges, a, b) in enumerate(repair.incidences(h)):
            for r, c in zip(*np.nonzero(edges > -1)):
                for f in (a[r, c], b[r, c]):
                    if edges[r, c] > h.f.ravel()[f]:
                        edge.append(kind * 100 + r * 10 + c), face.append(f), weight.append(edges[r, c] - h.f.ravel()[f])
        whole = repair.component_moves(np.array(edge), np.array(face), np.array(weight))[2] if edge else 0.0
        assert got.certified and got.moved == pytest.approx(whole)
        if k < 2:
            fixed, moves = repair.optimal_frame(framed(spark, h), 4)
            out = collected(fixed, 4)
            assert out.violated() == 0 and sum(np.abs(x - y).sum() for x, y in zip(out.parts(), h.parts())) == pytest.approx(got.moved)
            assert moves.select("component").distinct().count() == got.components


def test_curve_runs_equal_rectangles():
    rng = np.random.default_rng(6)
    for res in (0, 1, 4):
        q = np.sort(rng.integers(0, 1 << res, (200, 2, 2)), axis=2).reshape(200, 4)
        runs, vec = baselines.Runs(q, res), rng.random(1 << 2 * res)
        grid = baselines.rolled(vec, res)
        assert np.allclose(runs.answers(vec), box_sums(grid, *q.T))
        r, c = baselines.hilbert_order(res)
        inside = (r >= q[:, :1]) & (r <= q[:, 1:2]) & (c >= q[:, 2:3]) & (c <= q[:, 3:4])
        assert all((runs.mask(k) == inside[k]).all() for k in range(50)) and np.allclose(runs.coverage(), inside.sum(axis=0))


def test_densities_and_answers_agree_on_every_way(spark, data):
    s = walks.walk_steps(trajectories.points(spark, data, "em"), trajectories.box(spark, data, "em", 4))
    hist, q = histogram.build(s), workload.random_rectangles(spark, 16, 100)
    few = {r["qid"]: r["ans"] for r in answering.every_query(q, answering.located(s.select("traj_id", "row", "col").distinct(), q, 1000).groupBy("qid").agg(F.countDistinct("traj_id").alias("ans"))).collect()}
    assert few == {r["qid"]: r["ans"] for r in answering.exact(s, q).collect()}
    blocks = regions.uniform(spark, 4, 2)
    own = answering.from_hist(hist, blocks.withColumnRenamed("pid", "qid"))
    assert {r["pid"]: r["count"] for r in quadtree.counted(hist, blocks).collect()} == {r["qid"]: r["ans"] for r in own.collect()}


def test_experiments_report_means_and_deviations(spark, data):
    got = experiments.distribution(spark, data, ("em",), (100,), (0.5,), 4, 200, 2, (3, 4)).toPandas()
    assert set(got["mechanism"]) == set(experiments.MECHANISMS) and set(got["metric"]) == {"avg_l1", "avg_l1_dev", "avg_l1_sequence", "avg_l1_sequence_dev"}
    assert (got["run"] == 2).all() and (got["value"] >= 0).all() and got.groupby("mechanism").size().eq(4).all()
    case = experiments.prepared_case(spark, data, "em", 4, 200, 100)
    a, b = (case.estimate("BL-FLAT", 0.5, noise.Simulated(k), 0)[1] for k in (1, 2))
    assert not np.allclose(a.f, case.truth.f) and not np.allclose(a.f, b.f)  # the histogram is noisy too


def test_a_grid_beyond_the_driver_goes_over_frames(spark, data, monkeypatch):
    monkeypatch.setattr(release, "MOST", 10)
    monkeypatch.setattr(release, "collected", None)
    got = released(spark, data, seed=1)
    assert histogram.violations(got.frame()).count() == 0 and [t["iter"] for t in got.trace] == [0, 1]


def test_scan_reads_only_what_is_needed(spark, data):
    plan = walks.assign(trajectories.points(spark, data, "li"), trajectories.GridSpec(0, 201, 0, 50, 4))._jdf.queryExecution().executedPlan().toString()
    assert "l_extendedprice" not in plan and "l_shipdate" not in plan
