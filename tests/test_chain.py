"""The chain from raw lines to clusters, the seams between its steps, and the bounds of the clustering passes."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from conftest import SMALL
from sessionlens.operators import cleaning, clustering, features, sessionize
from sessionlens.plans import stage, workloads
from sessionlens.sources import logs
from sessionlens.streaming import live


def test_numbers_do_not_hang_on_exchange_reuse(spark):
    rows = spark.range(30_000).select(F.concat(F.lit("/p"), F.col("id").cast("string")).alias("url"), F.timestamp_micros(F.col("id") * 7919 % 30_011).alias("ts"), F.col("id").alias("seq"))
    before = spark.conf.get("spark.sql.exchange.reuse")
    spark.conf.set("spark.sql.exchange.reuse", "false")
    try:
        for order in ("sorted", "first_seen"):
            got = [r["n"] for r in cleaning.dictionary(rows, "url", "n", order).orderBy("url").collect()]
            assert sorted(got) == list(range(1, 30_001)) and (order != "sorted" or got == sorted(got))
    finally:
        spark.conf.set("spark.sql.exchange.reuse", before)


def test_records_without_url_are_counted_and_go(spark):
    rows = [(1, "10.0.0.1", "UA", "http://a/x"), (2, "10.0.0.1", "UA", None), (3, "10.0.0.2", "crawler", "http://a/y"), (4, "10.0.0.2", "UA", "http://a/z.GIF?q=1"), (5, "10.0.0.3", None, "http://a/x?q=2")]
    log = spark.createDataFrame(rows, "seq long, client_ip string, user_agent string, url string").withColumns({"ts": F.timestamp_micros("seq"), "elapsed_ms": F.lit(1), "bytes": F.lit(2)})
    assert {r["seq"] for r in cleaning.drop_embedded(log.withColumn("url", cleaning.strip_query("url"))).collect()} == {1, 2, 3, 5}
    assert {r["seq"] for r in cleaning.clean(log)[0].collect()} == {1, 5}
    report = cleaning.cleaning_report(log).first()
    assert (report["raw"], report["no_url"], report["cleaned"]) == (5, 1, 2)
    assert {r["seq"] for r in cleaning.drop_robots_like(log, "^crawl").collect()} == {1, 2, 4, 5}


def test_from_clean_log_to_clusters_with_defaults(spark):
    cleaned, urls = cleaning.clean(logs.weblog(spark, SMALL))
    users = cleaning.identify_users(cleaned, "ip_agent", "ip_alias", "ua_alias")
    sessions = sessionize.sessionize(users, "gap", sessionize.DAY, user="user_key")
    kept, numbers, n = features.number_urls(features.prune_support(features.prune_urls(sessions)))
    assert sorted(r["number"] for r in numbers.collect()) == list(range(n))
    items = features.profile_items(kept, user="user_key")
    for scale in ("none", "l2", "max", "log1p"):
        vectors = features.vectorize(items, "frequency", scale, user="user_key")
        assert vectors.agg(F.max(F.array_max("idx"))).first()[0] == n - 1
    run = clustering.fcm(stage.settle(features.weighted_points(vectors)), 3, n, 1.1, max_iter=5)
    assert run.centres.shape == (3, n) and np.isfinite(run.j)
    named = clustering.describe_clusters(run.centres, spark, numbers.join(urls, "url_id").select(F.col("number").cast("int").alias("url_id"), "url"), 2)
    assert named.where("url is null").count() == 0 and named.count() == 6


def test_duration_sessions_are_a_loop_over_each_user(spark):
    rng = np.random.default_rng(4)
    rows = [(int(u), int(t), i) for i, (u, t) in enumerate(zip(rng.integers(0, 6, 900), rng.integers(0, 4000, 900), strict=True))]
    df = spark.createDataFrame(rows, "user_id long, us long, seq long").withColumn("ts", F.timestamp_micros("us"))
    got = {r["seq"]: r["session_no"] for r in sessionize.duration_numbers(df, 37).collect()}
    want, last = {}, {}
    for u, t, i in sorted(rows):
        begin, no = last.get(u, (None, 0))
        if begin is None or t - begin > 37:
            begin, no = t, no + 1
        last[u], want[i] = (begin, no), no
    assert got == want
    counted = {(r["rule"], r["beta_us"]): r["sessions"] for r in sessionize.compare_heuristics(df, [5, 37, 90]).collect()}
    assert counted["duration", 37] == sum(no for _, no in last.values()) and counted["gap", 90] <= counted["gap", 37] <= counted["gap", 5]
    for beta in (5, 37, 90):
        assert counted["gap", beta] == sessionize.gap_numbers(df, beta).select("user_id", "session_no").distinct().count()
        assert counted["duration", beta] == sessionize.duration_numbers(df, beta).select("user_id", "session_no").distinct().count()
    assert sessionize.duration_numbers(df.where("false"), 37).count() == 0


def test_passes_keep_to_the_budget_and_sums_are_the_same(spark):
    rng = np.random.default_rng(2)
    rows = [([int(k) for k in np.sort(rng.choice(300, 6, False))], [1.0] * 6, 1.0, float(rng.random()), 1.0) for _ in range(400)]
    points = stage.settle(spark.createDataFrame(rows, "idx array<int>, val array<double>, mult double, soft double, none double").repartition(20))
    runs = [clustering.Run(rng.random((c, 300)), 1.5, w) for c in (2, 5, 9) for w in ("soft", "none")]
    whole = clustering.gather_sums(points, runs, 300)
    parts = clustering.gather_sums(points, runs, 300, budget=8 * 9 * 301)
    assert len(clustering.shards(runs, 300, 8 * 9 * 301)) > 1 and all(np.allclose(a, b) for a, b in zip(whole, parts, strict=True))
    before = clustering.BLOCK, clustering.DIRECT
    clustering.BLOCK, clustering.DIRECT = 256, 0
    try:
        assert all(np.allclose(a, b) for a, b in zip(whole, clustering.gather_sums(points, runs, 300), strict=True))
    finally:
        clustering.BLOCK, clustering.DIRECT = before
    with pytest.raises(ValueError, match="budget"):
        clustering.shards(runs, 300, 1000)
    with pytest.raises(ValueError, match="criterion"):
        clustering.iterate(points, runs, 300, criterion="U")


def test_many_coordinates_fit_the_budget(spark):
    import resource

    wide, rng = 200_000, np.random.default_rng(3)
    rows = [([int(k) for k in np.sort(rng.choice(wide, 5, False))], [1.0] * 5, 1.0, 1.0) for _ in range(120)]
    points = stage.settle(spark.createDataFrame(rows, "idx array<int>, val array<double>, mult double, none double").coalesce(1))
    before = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
    centres = np.zeros((60, wide))
    for j in range(60):
        centres[j, rows[j][0]] = 1.0
    runs = clustering.iterate(points, [clustering.Run(centres.copy(), 1.2, "none") for _ in range(2)], wide, max_iter=1)
    assert all(np.isfinite(r.j) for r in runs) and np.allclose(runs[0].centres, runs[1].centres)
    assert (resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - before) / 1024 < 1800


def test_j_stops_as_well(spark):
    points, width = workloads.chain_points(spark, SMALL)
    run = clustering.iterate(points, [clustering.Run(clustering.starts(points, 2, width), 1.2)], width, 1e-3, 50, "J")[0]
    assert run.converged and run.iterations < 50
    for how in ("hash", "first", "farthest"):
        x = clustering.starts(points, 3, width, how)
        assert (x == clustering.starts(points.repartition(3), 3, width, how)).all() and clustering.distances(x, x)[np.triu_indices(3, 1)].min() > 0


def test_weighted_sweep_over_many_counts_and_best_c(spark):
    table = workloads.chain_sweep(spark, SMALL, range(4, 10), max_iter=6)
    rows = table.collect()
    assert {(r["c"], r["weighting"]) for r in rows} == {(c, w) for c in range(4, 10) for w in ("soft", "none")}
    best = {r["weighting"]: r["best_c"] for r in clustering.select_c(table).collect()}
    for w, c in best.items():
        assert c == min((r["s"], r["c"]) for r in rows if r["weighting"] == w and not r["degenerate"])[1]


def test_streams_are_cleaned_and_followed(spark, tmp_path):
    follow = live.Drift(np.eye(2, 4), 2.0, 0.5)
    batch = spark.createDataFrame([([0], [1.0]), ([1, 2], [1.0, 1.0])], "idx array<int>, val array<double>")
    want, mass = live.drift(np.eye(2, 4), np.zeros(2), np.array([[1.0, 0, 0, 0], [0, 1, 1, 0]]), np.ones(2), 2.0, 0.5)
    follow(batch, 0)
    assert np.allclose(follow.centres, want) and np.allclose(follow.mass, mass) and follow.batches == 1
    logs.write_histories(logs.events_requests(spark, SMALL), "histories_test", 4)
    assert spark.table("histories_test").count() == 1000


def test_no_folder_of_one_machine_on_a_cluster():
    class Conf:
        def get(self, *_):
            return None

    class Spark:
        conf = Conf()
        sparkContext = type("C", (), {"master": "spark://x:7077", "applicationId": "a"})()

    with pytest.raises(RuntimeError, match="checkpoint"):
        stage.shared(Spark(), "x")


def test_few_points_keep_every_core_busy_in_a_pass(spark):
    """A small table of points was one file, so each of the 41 passes of the sweep ran in one task."""
    points, _ = workloads.chain_points(spark, SMALL)
    assert points.rdd.getNumPartitions() >= int(spark.conf.get("spark.sql.shuffle.partitions")) > 1


@pytest.mark.parametrize("q", [1.0, 1.03, 2.0])
def test_sums_by_clusters_are_those_by_points(q):
    rng = np.random.default_rng(4)
    x = (rng.random((300, 12)) < 0.3).astype(float)
    v = np.concatenate([x[:3], x[:1], rng.random((4, 12))])  # centres on points, two of them equal
    mult, w = rng.integers(1, 5, 300).astype(float), np.where(rng.random(300) < 0.2, 0.0, rng.random(300))
    d = clustering.distances(x, v)
    u = clustering.membership(d, q)
    uq = u**q if q > 1 else u
    for kind, count in (("soft", mult), ("hard", w)):
        for update, by in (("objective", w), ("as_printed", count)):
            m = uq * by[:, None]
            want = np.concatenate([m.sum(0), (m.T @ x).ravel(), [(w[:, None] * uq * d).sum(), (count[:, None] * u * u * d).sum(), (w[:, None] * u * u * d).sum(), w.sum(), count.sum()]])
            assert clustering._sums(x, (x * x).sum(1), clustering.Run(v.copy(), q, kind, update), mult, w, 12) == pytest.approx(want)
