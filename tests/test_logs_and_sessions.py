"""Worked examples: log lines, cleaning, users, and both session rules."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from sessionlens.operators import cleaning, features, measures, sessionize
from sessionlens.sources.logs import fuse_logs, parse_log, render_log, write_stage_text

MIN = sessionize.MINUTE
# fixed values: five requests (time, address, agent, elapsed, bytes, URL)
CHAIN = [
    ("2008-06-01 01:48:05", "IP1", "UA1", 741, 10858, "/1"), ("2008-06-01 01:48:06", "IP1", "UA1", 1735, 19247, "/2"), ("2008-06-01 01:48:08", "IP2", "UA2", 239, 209, "/1"),
    ("2008-06-01 01:48:09", "IP1", "UA3", 674, 156, "/3"), ("2008-06-01 01:48:13", "IP2", "UA2", 680, 179, "/4"),
]


@pytest.fixture
def chain(spark):
    rows = [(*r, i) for i, r in enumerate(CHAIN)]
    return spark.createDataFrame(rows, "ts string, client_ip string, user_agent string, elapsed_ms long, bytes long, url string, seq long").withColumn("ts", F.to_timestamp("ts"))


def requests(spark, micros, user=1):
    rows = [(user, t, i, i) for i, t in enumerate(micros)]
    return spark.createDataFrame(rows, "user_id long, us long, seq long, url_id int").withColumn("ts", F.timestamp_micros("us"))


def numbers(df):
    return [r["session_no"] for r in df.orderBy("user_id", "ts", "seq", "session_no").collect()]


def test_line_is_parsed_and_zone_is_a_matter_of_showing(spark, tmp_path):
    lines = ["1212265085.247 741 192.168.23.62 TCP_MISS/200 10858 GET - DEFAULT_PARENT/192.168.20.1 - Mozilla/5.0", "1212265085.247 741 192.168.23.62 TCP_MISS/200 10858 GET http://a.b/c?d=1 joe DIRECT/1.2.3.4 text/html Mozilla/5.0 (X)", "nonsense", None]
    good, bad = parse_log(spark.createDataFrame([(x,) for x in lines], "value string"))
    rows = good.orderBy("url").collect()
    assert [r["url"] for r in rows] == [None, "http://a.b/c?d=1"] and bad.count() == 2
    assert rows[0]["login"] is None and rows[1]["login"] == "joe" and rows[1]["user_agent"] == "Mozilla/5.0 (X)" and rows[0]["user_agent"] == "Mozilla/5.0"
    assert rows[0]["elapsed_ms"] == 741 and rows[0]["status"] == 200 and rows[0]["bytes"] == 10858
    for zone, want in (("UTC", "20080531201805"), ("Asia/Kolkata", "20080601014805")):
        write_stage_text(good.select("ts"), str(tmp_path / zone[:3]), zone)
        assert {r[0] for r in spark.read.text(str(tmp_path / zone[:3])).collect()} == {want}
    again = parse_log(render_log(good.where("url is not null")))[0]
    assert again.select("ts", "url", "login").collect() == good.where("url is not null").select("ts", "url", "login").collect()


def test_users_are_address_and_agent_in_time_order(chain):
    users = cleaning.user_histories(cleaning.identify_users(chain))
    assert [(r["user_key"], r["pos"], r["url"]) for r in users.orderBy("user_key", "pos").collect()] == [("IP1|UA1", 1, "/1"), ("IP1|UA1", 2, "/2"), ("IP1|UA3", 1, "/3"), ("IP2|UA2", 1, "/1"), ("IP2|UA2", 2, "/4")]
    assert cleaning.identify_users(chain, "ip").select("user_key").distinct().count() == 2
    nested = cleaning.user_histories(cleaning.identify_users(chain), nested=True).orderBy("user_key").first()
    assert [x["url"] for x in nested["requests"]] == ["/1", "/2"]


@pytest.mark.parametrize("order", ["sorted", "first_seen", "hash"])
def test_dictionary_is_one_to_one(chain, order):
    coded, d = cleaning.encode(chain, "url", "url_id", order)
    assert d.count() == 4 == d.select("url_id").distinct().count()
    assert coded.join(d.withColumnRenamed("url_id", "n"), "url").where("url_id <> n").count() == 0
    if order != "hash":
        assert [r["url_id"] for r in d.orderBy("url_id").collect()] == [1, 2, 3, 4]


def test_suffix_is_seen_behind_a_query(spark):
    urls = spark.createDataFrame([(u,) for u in ("/a.gif?x=1", "/b.JPG", "/c.map", "/d.html?y=a.gif", "/e#f.gif", None)], "url string")
    left = cleaning.drop_embedded(urls.withColumn("url", cleaning.strip_query("url")))
    assert sorted(r[0] for r in left.where("url is not null").collect()) == ["/d.html", "/e"]
    assert cleaning.drop_embedded(urls).where("url like '/a.gif%'").count() == 1


def test_robots_by_list_and_by_table(spark, chain):
    agents = spark.createDataFrame([("UA2",)], "agent string")
    assert cleaning.drop_robots(chain, ["UA2"]).count() == cleaning.drop_robots(chain, agents).count() == 3
    assert {(r["client_ip"], r["urls"]) for r in cleaning.robot_suspects(chain, 0.5).collect()} == {("IP1", 2), ("IP2", 2)}


def test_clocks_are_corrected(chain):
    both = fuse_logs([chain, chain], [0, 2500])
    assert both.count() == 10 and both.agg(F.max("ts")).first()[0] == dt.datetime(2008, 6, 1, 1, 48, 15, 500000)


def test_limit_is_inclusive_and_the_rules_differ(spark):
    beta = 30 * MIN
    edge = requests(spark, [0, beta, beta + 1, 2 * beta, 3 * beta + 2])
    assert numbers(sessionize.gap_numbers(edge, beta)) == [1, 1, 1, 1, 2]
    assert numbers(sessionize.duration_numbers(edge, beta)) == [1, 1, 2, 2, 3]
    assert numbers(sessionize.sessionize(requests(spark, [5]), "duration", beta)) == [1]
    assert numbers(sessionize.gap_numbers(requests(spark, [7, 7]), beta)) == [1, 1]


def test_duration_fold_is_a_plain_loop(spark):
    import random

    rnd = random.Random(5)
    rows, want = [], {}
    for user in range(12):
        t, at = 0, []
        for _ in range(rnd.randint(0, 40)):
            t += rnd.choice([0, 1, 5, 9, 10, 11, 30])
            at.append(t)
        first = no = None
        for i, t in enumerate(at):
            if first is None or t - first > 10:
                first, no = t, (no or 0) + 1
            want[user, i] = no
            rows.append((user, t, i, i))
    df = spark.createDataFrame(rows, "user_id long, us long, seq long, url_id int").withColumn("ts", F.timestamp_micros("us"))
    got = {(r["user_id"], r["seq"]): r["session_no"] for r in sessionize.duration_numbers(df, 10).collect()}
    assert got == want
    counts = {(r["rule"]): r["sessions"] for r in sessionize.compare_heuristics(df, [10]).collect()}
    assert counts["duration"] >= counts["gap"]


def test_soft_limit_shares_a_request(spark):
    got = sessionize.sessionize_soft(requests(spark, [0, 10, 25, 60]), 10, 10).orderBy("us", "session_no").select("us", "session_no", "mu").collect()
    assert [(r[0], r[1], round(r[2], 3)) for r in got] == [(0, 1, 1.0), (10, 1, 1.0), (25, 1, 0.5), (25, 2, 0.5), (60, 3, 1.0)]


def test_weights_of_sizes(spark):
    sizes = spark.range(9).select(F.col("id").alias("n"))
    w = [r[0] for r in sizes.orderBy("n").select(features.ramp_weight(F.col("n"), 1, 6)).collect()]
    assert w == pytest.approx([0, 0, 0.2, 0.4, 0.6, 0.8, 1, 1, 1])
    assert [r[0] for r in sizes.orderBy("n").select(features.ramp_weight(F.col("n"), 3, 3)).collect()] == [0.0] * 4 + [1.0] * 5
    assert [r[0] for r in sizes.orderBy("n").select(features.step_weight(F.col("n"), 3, False)).collect()] == [0.0] * 4 + [1.0] * 5
    with pytest.raises(ValueError):
        features.ramp_weight(F.col("n"), 4, 3)


def test_page_time_and_scales(spark):
    s = requests(spark, [0, 2_000_000, 5_000_000]).withColumn("url_id", F.col("url_id") % 2).withColumns({"session_no": F.lit(1), "bytes": F.lit(3), "elapsed_ms": F.lit(1500)})
    dwell = lambda last: {r["url_id"]: r["dwell_s"] for r in features.profile_items(s, last, session="session_no").collect()}
    assert dwell("zero") == {0: 2.0, 1: 3.0} and dwell("mean") == {0: 4.5, 1: 3.0} and dwell("elapsed") == {0: 3.5, 1: 3.0}
    items = features.profile_items(s, session="session_no")
    l2 = [r[0] for r in items.orderBy("url_id").select(features.value("frequency", "l2", "session_no")).collect()]
    assert l2 == pytest.approx([2 / 5**0.5, 1 / 5**0.5])
    p = features.profile_sessions(s, session="session_no").first()
    assert (p["n_urls"], p["n_requests"], p["items"][0]["freq"]) == (2, 3, 2)
    assert features.prune_urls(s, 2).count() == 2 and features.prune_support(s, 2, session="session_no").count() == 0
    kept = {r["treatment"]: (r["sessions"], r["urls"]) for r in measures.retention_report(items, min_urls=3).collect()}
    assert kept["none"] == (1, 2) and kept["hard"] == (0, 0) and kept["soft"] == (1, 2)
