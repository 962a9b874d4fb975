"""The kernel against plain numpy, its invariants and limits, and planted groups."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from sessionlens.operators import clustering as C
from sessionlens.operators import features, measures


def table(spark, x, soft=None, hard=None):
    n = len(x)
    soft = np.ones(n) if soft is None else soft
    hard = np.ones(n) if hard is None else hard
    rows = [([int(i) for i in np.flatnonzero(r)], [float(v) for v in r[r != 0]], 1.0, float(s), float(h), 1.0) for r, s, h in zip(x, soft, hard, strict=True)]
    return spark.createDataFrame(rows, "idx array<int>, val array<double>, mult double, soft double, hard double, none double")


def plain(x, v, w, q, steps, update="objective"):
    trace = []
    for _ in range(steps):
        d = ((x[:, None, :] - v[None]) ** 2).sum(2)
        u = C.membership(d, q)
        trace.append((w[:, None] * u**q * d).sum())
        m = u**q * (w if update == "objective" else np.ones_like(w))[:, None]
        v = (m.T @ x) / m.sum(0)[:, None]
    return v, trace


@pytest.fixture(scope="module")
def cloud():
    rng = np.random.default_rng(1)
    return (rng.random((120, 6)) < 0.4) * rng.integers(1, 4, (120, 6)).astype(float), rng.random(120), rng.random((3, 6))


@pytest.mark.parametrize("q", [1.3, 2.0, 3.0])
@pytest.mark.parametrize("update", ["objective", "as_printed"])
def test_kernel_is_plain_numpy(spark, cloud, q, update):
    x, w, v = cloud
    run = C.iterate(table(spark, x, w), [C.Run(v.copy(), q, "soft", update)], 6, 0.0, 3)[0]
    want, trace = plain(x, v, w, q, 3, update)
    assert run.centres == pytest.approx(want) and run.trace == pytest.approx(trace)
    d = ((x[:, None, :] - want[None]) ** 2).sum(2)
    u = C.membership(d, q)
    assert run.j == pytest.approx((w[:, None] * u**q * d).sum())
    z = (np.maximum(d, 1e-300) ** (-1 / (q - 1))).sum(1)
    assert run.j == pytest.approx((w * z ** (1 - q)).sum())  # the objective at its own memberships
    sep = min(((want[i] - want[j]) ** 2).sum() for i in range(3) for j in range(i))
    assert run.validity == pytest.approx((u**2 * d).sum() / (120 * sep))


def test_sparse_and_dense_sums_agree(spark, cloud, monkeypatch):
    x, w, v = cloud
    a = C.gather_sums(table(spark, x, w), [C.Run(v.copy())], 6)[0]
    idx = [np.flatnonzero(r) for r in x]
    s = C._Sparse(np.concatenate(idx), np.concatenate([r[r != 0] for r in x]), np.repeat(np.arange(len(x)), [len(i) for i in idx]), len(x))
    b = C._sums(s, (x * x).sum(1), C.Run(v.copy()), np.ones(len(x)), w, 6)
    assert a == pytest.approx(b)


def test_objective_falls_and_weights_only_lower_it(spark, cloud):
    x, w, v = cloud
    soft, none, printed, hard = C.iterate(table(spark, x, w, (w > 0.5) * 1.0), [C.Run(v.copy(), 1.5, "soft"), C.Run(v.copy(), 1.5, "none"), C.Run(v.copy(), 1.5, "soft", "as_printed"), C.Run(v.copy(), 1.5, "hard")], 6, 1e-6, 25)
    for r in (soft, none, hard):
        assert all(b <= a + 1e-9 for a, b in zip(r.trace, r.trace[1:], strict=False))
    assert all(p <= n + 1e-9 for p, n in zip(printed.trace, none.trace, strict=False))
    assert printed.centres == pytest.approx(none.centres)  # as printed, weights never move the centres
    assert soft.trace[0] <= none.trace[0] and hard.points == (w > 0.5).sum() and soft.points == 120


def test_exponent_near_one_is_kmeans(spark, cloud):
    x, w, v = cloud
    crisp, *fuzzy = C.iterate(table(spark, x, w), [C.Run(v.copy(), q) for q in (1.0, 1.5, 1.1, 1.01, 1.001)], 6, 0.0, 1)
    gaps = [np.abs(f.centres - crisp.centres).max() for f in fuzzy]
    assert gaps == sorted(gaps, reverse=True) and gaps[-1] < 1e-2
    assert C.iterate(table(spark, x, w), [C.Run(v.copy(), 1.0)], 6, 1e-7, 60)[0].converged


def test_kmeans_is_the_library_one(spark, cloud):
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.linalg import Vectors

    x, w, v = cloud
    ours = C.kmeans(table(spark, x, w), 3, 6, "none", v.copy())
    d = ((x[:, None, :] - ours.centres[None]) ** 2).sum(2)
    df = spark.createDataFrame([(Vectors.dense(r.tolist()),) for r in x], ["features"])
    theirs = KMeans(k=3, seed=1, maxIter=50).fit(df)
    assert ours.j == pytest.approx(d.min(1).sum()) and ours.j <= 1.35 * theirs.summary.trainingCost


def test_points_on_centres_and_ties():
    v = np.array([[0.0, 0.0], [1.0, 0.0], [1.0, 0.0]])
    u = C.membership(C.distances(np.array([[0.0, 0.0], [1.0, 0.0], [0.5, 0.0]]), v), 2.0)
    assert u[0].tolist() == [1, 0, 0] and u[1].tolist() == [0, 0.5, 0.5] and u[2] == pytest.approx([1 / 3] * 3)
    assert C.membership(np.array([[1.0, 1.0]]), 1.0).tolist() == [[1.0, 0.0]]


def test_duplicated_sessions_leave_centres(spark, cloud):
    x, w, v = cloud
    once = C.iterate(table(spark, x, w), [C.Run(v.copy())], 6, 0.0, 4)[0]
    twice = C.iterate(table(spark, np.vstack([x, x]), np.append(w, w)), [C.Run(v.copy())], 6, 0.0, 4)[0]
    assert twice.centres == pytest.approx(once.centres) and twice.j == pytest.approx(2 * once.j) and twice.validity == pytest.approx(once.validity)
    sessions = spark.createDataFrame([([0, 1], [1.0, 1.0], 2), ([0, 1], [1.0, 1.0], 2), ([2], [1.0], 1)], "idx array<int>, val array<double>, n_urls int")
    p = {tuple(r["idx"]): (r["mult"], round(r["soft"], 9), r["hard"]) for r in features.weighted_points(sessions).collect()}
    assert p == {(0, 1): (2.0, 0.4, 2.0), (2,): (1.0, 0.0, 0.0)}


def test_one_cluster_is_the_weighted_mean(spark, cloud):
    x, w, v = cloud
    run = C.iterate(table(spark, x, w), [C.Run(v[:1].copy())], 6, 0.0, 2)[0]
    assert run.centres[0] == pytest.approx((w[:, None] * x).sum(0) / w.sum()) and np.isnan(run.validity)


def test_planted_groups_are_found(spark):
    rng = np.random.default_rng(7)
    rows, labels = [], []
    for g in range(3):
        for _ in range(60):
            r = np.zeros(15)
            r[5 * g + rng.choice(5, 4, replace=False)] = 1
            rows.append(r)
            labels.append(g)
    for _ in range(40):  # sessions of one page
        r = np.zeros(15)
        r[rng.integers(15)] = 1
        rows.append(r)
        labels.append(-1)
    x = np.array(rows)
    w = np.clip((x.sum(1) - 1) / 5, 0, 1)
    points = table(spark, x, w, (w > 0) * 1.0)
    run = C.fcm(points, 3, 15, 1.3)
    got = C.memberships(points.withColumn("label", F.lit(0)), run.centres, 1.3)
    u = C.membership(C.distances(x, run.centres), 1.3).argmax(1)
    assert all(len(set(u[np.array(labels) == g])) == 1 for g in range(3)) and len(set(u[:180])) == 3
    assert C.check_partition(got).first()["bad_rows"] == 0
    sweep = C.sweep_table(spark, C.sweep(points, [2, 3, 4, 5], 15, 1.3))
    assert {r["best_c"] for r in C.select_c(sweep).collect()} == {3}
    assert C.overlap_profile(got, 0.5).where("clusters = 1").first()["sessions"] >= 180
    assert C.assign(got, "threshold", 0.9).count() <= 220
    top = {r["cluster"]: r["url_id"] // 5 for r in C.describe_clusters(run.centres, spark, top=1).collect()}
    assert sorted(top.values()) == [0, 1, 2]


def test_coinciding_centres_are_flagged(spark, cloud):
    x, w, v = cloud
    same = C.Run(np.vstack([v[:1], v[:1]]))
    assert same.degenerate() and not C.Run(v).degenerate()
    t = spark.createDataFrame([("a", 2, "soft", 2.0, 1, True, 1.0, 1.0, 0.0, 0.0, True), ("b", 3, "soft", 2.0, 1, True, 1.0, 1.0, 5.0, 1.0, False)], "run string, c int, weighting string, q double, iterations int, converged boolean, j double, j_per_weight double, s double, sep_min double, degenerate boolean")
    assert C.select_c(t).first()["best_c"] == 3


def test_purity_and_functions(spark):
    from sessionlens.functions.registry import register

    df = spark.createDataFrame([(0, "a"), (0, "a"), (0, "b"), (1, "b")], "cluster int, label string")
    assert measures.purity(df).first()["purity"] == 0.75
    register(spark)
    assert spark.sql("SELECT ramp_weight(3, 1, 6), step_weight(3, 4), session_starts(array(0D, 5D, 11D, 12D), 10D)").first()[:] == (0.4, 0.0, [0.0, 11.0])
    assert spark.sql("SELECT * FROM walk_session(array(4, 5), array(1D, 3D))").collect()[0][:] == (0, 4, 2.0)
