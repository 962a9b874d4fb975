"""The registered queries of the library and the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .operators import cleaning, clustering, features, measures, relational, sessionize
from .plans import workloads
from .plans.stage import settle, shared
from .sources.logs import events_requests, fuse_logs, order_requests, parse_log, read_delimited, read_log_text, render_log, table, weblog, write_by_date
from .streaming import live

MIN30, DAY = 30 * sessionize.MINUTE, sessionize.DAY
BETAS = (MIN30, 6 * sessionize.HOUR, 12 * sessionize.HOUR, DAY)
_Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    """Registers a query under its function's name, with its SQL if there is any."""

    def put(f: Callable[[SparkSession, str], DataFrame]) -> Callable:
        _Q[f.__name__] = f
        if sql:
            _SQL[f.__name__] = sql
        return f

    return put


def queries() -> dict:
    return dict(_Q) | relational.queries()


def oracle_sql() -> dict[str, str]:
    return dict(_SQL) | relational.oracle_sql()


# ---- shared SQL
LOG = """raw AS (
  SELECT e.ts, CAST(round(e.value * 10) AS BIGINT) AS elapsed_ms,
    '10.0.' || ((user_id // 2) // 256) || '.' || ((user_id // 2) % 256) AS client_ip,
    CASE WHEN user_id % 17 = 0 THEN 'crawler' ELSE 'UA' || (user_id % 3) END AS user_agent,
    CASE WHEN event_type = 'error' THEN 500 ELSE 200 END AS status, CAST(round(e.value * 100) AS BIGINT) AS bytes,
    CASE WHEN event_type IN ('signup', 'purchase') THEN 'POST' ELSE 'GET' END AS method, r.seq, r.url
  FROM events e JOIN pages p ON CAST(json_extract_string(e.props, '$.k') AS BIGINT) % (SELECT count(*) FROM pages) = p.page_id,
  LATERAL (SELECT e.event_id * 2 AS seq, p.url AS url UNION ALL SELECT e.event_id * 2 + 1, rtrim(regexp_replace(p.url, '[?#].*$', ''), '/') || '.GIF?v=' || e.event_id WHERE e.event_id % 5 = 0) r
), stripped AS (SELECT *, regexp_replace(url, '[?#].*$', '') AS plain FROM raw),
cleaned AS (SELECT * FROM stripped WHERE lower(regexp_extract(plain, '\\.([A-Za-z0-9]+)$', 1)) NOT IN ('gif', 'jpeg', 'jpg', 'map') AND user_agent <> 'crawler')"""
REQ = "req AS (SELECT user_id, ts, event_id AS seq, CAST(json_extract_string(props, '$.k') AS INT) AS url_id, CAST(round(value * 100) AS BIGINT) AS bytes, event_type FROM events)"
LOG_COLUMNS = ["ts", "elapsed_ms", "client_ip", "user_agent", "status", "bytes", "method", "seq", "url"]


def gap_sql(beta: int, req: str = REQ, name: str = "sess") -> str:
    return f"""{req}, lagged AS (SELECT *, epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, seq) AS pause FROM req),
{name} AS (SELECT *, CAST(sum(CASE WHEN pause IS NULL OR pause > {beta} THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, seq ROWS UNBOUNDED PRECEDING) AS INT) AS session_no FROM lagged)"""


def duration_sql(beta: int, req: str = REQ) -> str:
    return f"""{req}, numbered AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, seq) AS n FROM req),
walk AS (
  SELECT user_id, seq, n, epoch_us(ts) AS began, 1 AS session_no FROM numbered WHERE n = 1 UNION ALL
  SELECT b.user_id, b.seq, b.n, CASE WHEN epoch_us(b.ts) - w.began > {beta} THEN epoch_us(b.ts) ELSE w.began END, w.session_no + CASE WHEN epoch_us(b.ts) - w.began > {beta} THEN 1 ELSE 0 END
  FROM walk w JOIN numbered b ON b.user_id = w.user_id AND b.n = w.n + 1
), sess AS (SELECT r.*, w.session_no FROM req r JOIN walk w ON r.user_id = w.user_id AND r.seq = w.seq)"""


ITEMS = "items AS (SELECT user_id, session_no, url_id, count(*) AS freq, CAST(sum(bytes) AS BIGINT) AS bytes FROM sess GROUP BY ALL), sizes AS (SELECT user_id, session_no, CAST(sum(freq) AS BIGINT) AS n_requests, count(*) AS n_urls FROM items GROUP BY ALL)"
RAMP = "CASE WHEN n_urls <= 1 THEN 0.0 WHEN n_urls >= 6 THEN 1.0 ELSE CAST(n_urls - 1 AS DOUBLE) / 5 END"
DAYS = gap_sql(DAY)


def _sessions(spark: SparkSession, sf_dir: str, beta: int = DAY, rule: str = "gap") -> DataFrame:
    return workloads.event_sessions(spark, sf_dir, beta, rule)


def _sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.session_sizes(_sessions(spark, sf_dir))


# ---- logs and cleaning
@query(f"WITH {LOG} SELECT ts, elapsed_ms, client_ip, user_agent, status, bytes, method, seq, url FROM raw")
def log_build(spark, sf_dir):
    return weblog(spark, sf_dir).select(*LOG_COLUMNS)


@query(f"WITH {LOG} SELECT ts, elapsed_ms, client_ip, user_agent, status, bytes, method, url FROM raw")
def log_parse(spark, sf_dir):
    """The log written as text lines and parsed again."""
    return parse_log(render_log(weblog(spark, sf_dir).withColumns({"cache_result": F.lit("TCP_MISS"), "origin": F.lit("DIRECT/10.9.9.9")})))[0].select(*[c for c in LOG_COLUMNS if c != "seq"])


@query(f"WITH {LOG} SELECT seq, plain AS url FROM stripped")
def clean_strip_query(spark, sf_dir):
    return weblog(spark, sf_dir).select("seq", cleaning.strip_query("url").alias("url"))


@query(f"WITH {LOG} SELECT seq, plain AS url FROM stripped WHERE lower(regexp_extract(plain, '\\.([A-Za-z0-9]+)$', 1)) NOT IN ('gif', 'jpeg', 'jpg', 'map')")
def clean_suffix(spark, sf_dir):
    return cleaning.drop_embedded(weblog(spark, sf_dir).withColumn("url", cleaning.strip_query("url"))).select("seq", "url")


@query(f"WITH {LOG} SELECT seq, client_ip FROM raw WHERE user_agent <> 'crawler'")
def clean_robots(spark, sf_dir):
    agents = spark.createDataFrame([("crawler",)], "agent string")
    return cleaning.drop_robots(weblog(spark, sf_dir), agents).select("seq", "client_ip")


@query(f"WITH {LOG}, d AS (SELECT plain, row_number() OVER (ORDER BY plain) AS url_id FROM (SELECT DISTINCT plain FROM cleaned)) SELECT ts, sha256(concat('alias', chr(0), client_ip)) AS ip_alias, sha256(user_agent) AS ua_alias, elapsed_ms, bytes, url_id, seq FROM cleaned JOIN d USING (plain)")
def clean_full(spark, sf_dir):
    return cleaning.clean(weblog(spark, sf_dir), order="sorted")[0]


@query(f"WITH {LOG} SELECT (SELECT count(*) FROM raw) AS raw, (SELECT count(*) FROM raw WHERE url IS NULL) AS no_url, count(*) AS cleaned, count(DISTINCT client_ip || '|' || user_agent) AS users, (SELECT count(*) FROM (SELECT plain FROM cleaned GROUP BY 1 HAVING count(*) >= 5)) AS site_urls, count(DISTINCT plain) AS urls FROM cleaned")
def cleaning_report(spark, sf_dir):
    return workloads.cleaning(spark, sf_dir)


@query("SELECT event_id, ts + to_milliseconds((user_id % 3) * 1500) AS ts, user_id FROM events")
def fuse_three_logs(spark, sf_dir):
    """Three servers' logs with clocks that are off by 0, 1.5 and 3 seconds."""
    e = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id")
    return fuse_logs([e.where(F.col("user_id") % 3 == i) for i in range(3)], [0, 1500, 3000])


@query(f"WITH {LOG} SELECT plain AS url, row_number() OVER (ORDER BY min((ts, seq))) AS url_id FROM cleaned GROUP BY plain")
def url_dictionary(spark, sf_dir):
    log = weblog(spark, sf_dir).withColumn("url", cleaning.strip_query("url"))
    return cleaning.dictionary(cleaning.drop_robots(cleaning.drop_embedded(log)), "url", "url_id", "first_seen")


@query(f"WITH {LOG} SELECT DISTINCT client_ip, sha256(concat('k', chr(0), client_ip)) AS ip_alias FROM raw")
def pseudonym(spark, sf_dir):
    return cleaning.pseudonymize(weblog(spark, sf_dir), "k").select("client_ip", "ip_alias").distinct()


def _users(policy: str):
    return lambda spark, sf_dir: cleaning.identify_users(cleaning.drop_robots(cleaning.drop_embedded(weblog(spark, sf_dir).withColumn("url", cleaning.strip_query("url")))).withColumn("login", F.expr("case when user_agent = 'UA1' then concat('login-', client_ip) end")), policy).groupBy("user_key").agg(F.count("*").alias("requests"))


_LOGIN = "CASE WHEN user_agent = 'UA1' THEN 'login-' || client_ip END"  # by a rule: the tables have no logins
for _name, _key in (("users_ip", "client_ip"), ("users_ip_agent", "client_ip || '|' || user_agent"), ("users_login", _LOGIN), ("users_auto", f"coalesce({_LOGIN}, client_ip || '|' || user_agent)")):
    _Q[_name] = _users(_name.removeprefix("users_"))
    _SQL[_name] = f"WITH {LOG} SELECT {_key} AS user_key, count(*) AS requests FROM cleaned GROUP BY 1"


@query(f"WITH {LOG} SELECT seq, user_agent FROM raw WHERE NOT regexp_matches(user_agent, '^(crawl|UA2)')")
def clean_robots_like(spark, sf_dir):
    return cleaning.drop_robots_like(weblog(spark, sf_dir), "^(crawl|UA2)").select("seq", "user_agent")


@query(f"WITH {LOG} SELECT seq, plain AS url FROM stripped WHERE lower(regexp_extract(plain, '\\.([A-Za-z0-9]+)$', 1)) NOT IN ('gif', 'jpeg', 'jpg', 'map', {', '.join(repr(x) for x in cleaning.MORE_SUFFIXES)})")
def clean_suffix_more(spark, sf_dir):
    """Styles, scripts and sounds too."""
    return cleaning.drop_embedded(weblog(spark, sf_dir).withColumn("url", cleaning.strip_query("url")), [*cleaning.SUFFIXES, *cleaning.MORE_SUFFIXES]).select("seq", "url")


@query(f"WITH {LOG} SELECT ts, elapsed_ms, client_ip, user_agent, status, bytes, method, url FROM raw")
def log_text_files(spark, sf_dir):
    """The log written as text files, read by the text reader and parsed."""
    path = shared(spark, "log-text")
    render_log(weblog(spark, sf_dir).withColumns({"cache_result": F.lit("TCP_MISS"), "origin": F.lit("DIRECT/10.9.9.9")})).write.text(path)
    return parse_log(read_log_text(spark, path))[0].select(*[c for c in LOG_COLUMNS if c != "seq"])


@query("SELECT event_id, user_id, value, event_id % 7 = 0 AS bad FROM events")
def csv_with_bad_rows(spark, sf_dir):
    """Every seventh line has a word where a number belongs; it is kept aside, not lost."""
    path = shared(spark, "csv")
    e = table(spark, sf_dir, "events").select("event_id", "user_id", F.when(F.col("event_id") % 7 == 0, F.concat(F.lit("x"), F.col("value").cast("string"))).otherwise(F.col("value").cast("string")).alias("value"))
    e.write.option("header", True).csv(path)
    got = read_delimited(spark, path, T.StructType().add("event_id", "long").add("user_id", "long").add("value", "double"))
    return got.select("event_id", "user_id", F.coalesce("value", F.expr("try_cast(substr(element_at(split(_bad, ','), 3), 2) as double)")).alias("value"), F.col("_bad").isNotNull().alias("bad"))


@query("SELECT CAST(ts AS DATE) AS date, count(*) AS requests FROM events GROUP BY 1")
def log_by_date(spark, sf_dir):
    """Requests written by date and read back by partition."""
    path = shared(spark, "by-date")
    write_by_date(events_requests(spark, sf_dir), path)
    return spark.read.parquet(path).groupBy("date").agg(F.count("*").alias("requests"))


@query(f"WITH {LOG}, n AS (SELECT count(DISTINCT plain) AS site_urls FROM stripped) SELECT client_ip, user_agent, count(DISTINCT plain) AS urls, any_value(site_urls) AS site_urls FROM stripped, n GROUP BY 1, 2 HAVING count(DISTINCT plain) >= any_value(site_urls) * 0.2")
def robot_suspects(spark, sf_dir):
    return cleaning.robot_suspects(weblog(spark, sf_dir).withColumn("url", cleaning.strip_query("url")), 0.2)


@query(f"WITH {LOG} SELECT client_ip || '|' || user_agent AS user_key, seq, row_number() OVER (PARTITION BY client_ip || '|' || user_agent ORDER BY ts, seq) AS pos FROM cleaned")
def user_histories(spark, sf_dir):
    log = cleaning.drop_robots(cleaning.drop_embedded(weblog(spark, sf_dir).withColumn("url", cleaning.strip_query("url"))))
    return cleaning.user_histories(cleaning.identify_users(log)).select("user_key", "seq", "pos")


# ---- sessions
def _numbered(rule: str, beta: int):
    return lambda spark, sf_dir: _sessions(spark, sf_dir, beta, rule).select("user_id", "seq", "session_no")


for _rule, _sql in (("gap", gap_sql), ("duration", duration_sql)):
    for _label, _beta in (("30m", MIN30), ("24h", DAY)):
        _Q[f"sess_{_rule}_{_label}"] = _numbered(_rule, _beta)
        _SQL[f"sess_{_rule}_{_label}"] = f"WITH {'RECURSIVE ' if _rule == 'duration' else ''}{_sql(_beta)} SELECT user_id, seq, session_no FROM sess"


def _compare_sql() -> str:
    parts = []
    for i, beta in enumerate(BETAS):
        for rule, sql in (("gap", gap_sql), ("duration", duration_sql)):
            body = f"WITH {'RECURSIVE ' if rule == 'duration' else ''}{sql(beta)} SELECT count(DISTINCT (user_id, session_no)) FROM sess"
            parts.append(f"SELECT '{rule}' AS rule, CAST({beta} AS BIGINT) AS beta_us, ({body}) AS sessions")
    return " UNION ALL ".join(parts)


@query(_compare_sql())
def sess_compare(spark, sf_dir):
    return sessionize.compare_heuristics(events_requests(spark, sf_dir), BETAS)


@query(f"WITH RECURSIVE {duration_sql(DAY)}, g AS ({f'WITH {DAYS} SELECT user_id, seq, session_no AS gap_no FROM sess'}) SELECT user_id, gap_no, count(DISTINCT session_no) AS parts, count(*) AS requests FROM sess JOIN g USING (user_id, seq) GROUP BY 1, 2")
def sess_refinement(spark, sf_dir):
    """Total-duration sessions lie inside page-stay sessions: how many in each."""
    both = sessionize.gap_numbers(_sessions(spark, sf_dir, DAY, "duration"), DAY, out="gap_no")
    return both.groupBy("user_id", "gap_no").agg(F.countDistinct("session_no").alias("parts"), F.count("*").alias("requests"))


_ORDERS = "req AS (SELECT o_custkey AS user_id, o_orderdate AS ts, o_orderkey AS seq FROM orders)"


@query(f"WITH RECURSIVE {duration_sql(90 * DAY, _ORDERS)} SELECT user_id, seq, session_no FROM sess")
def sess_orders_duration_90d(spark, sf_dir):
    return sessionize.duration_numbers(order_requests(spark, sf_dir), 90 * DAY).select("user_id", "seq", "session_no")


@query(f"WITH {gap_sql(90 * DAY, _ORDERS)} SELECT user_id, seq, session_no FROM sess")
def sess_orders_90d(spark, sf_dir):
    return sessionize.gap_numbers(order_requests(spark, sf_dir), 90 * DAY).select("user_id", "seq", "session_no")


@query(f"WITH {DAYS}, {ITEMS} SELECT count(*) AS sessions, min(n_requests) AS min_requests, max(n_requests) AS max_requests, avg(n_requests) AS mean_requests, min(n_urls) AS min_urls, max(n_urls) AS max_urls, avg(n_urls) AS mean_urls FROM sizes")
def sess_stats(spark, sf_dir):
    return measures.session_report(_sizes(spark, sf_dir))


@query(f"WITH {DAYS}, {ITEMS} SELECT user_id, session_no, url_id, freq, bytes FROM items")
def sess_profile(spark, sf_dir):
    s = features.profile_sessions(_sessions(spark, sf_dir), session="session_no")
    return s.select("user_id", "session_no", F.explode("items").alias("i")).select("user_id", "session_no", "i.url_id", "i.freq", "i.bytes")


@query(f"""WITH {gap_sql(6 * sessionize.HOUR)}, over AS (SELECT *, coalesce(pause, 0) - {6 * sessionize.HOUR} AS o FROM sess),
m AS (SELECT *, CASE WHEN pause IS NOT NULL AND o > 0 AND o < {2 * sessionize.HOUR} THEN 1 - o / {2.0 * sessionize.HOUR} ELSE 0.0 END AS share FROM over)
SELECT user_id, seq, session_no, round(CAST(1 - share AS DOUBLE), 9) AS mu FROM m UNION ALL SELECT user_id, seq, session_no - 1, round(CAST(share AS DOUBLE), 9) FROM m WHERE share > 0""")
def sess_soft(spark, sf_dir):
    soft = sessionize.sessionize_soft(events_requests(spark, sf_dir), 6 * sessionize.HOUR, 2 * sessionize.HOUR)
    return soft.select("user_id", "seq", "session_no", F.round("mu", 9).alias("mu"))


# ---- filters, features, weights
@query(f"WITH {REQ} SELECT accesses, count(*) AS urls FROM (SELECT event_type, url_id, count(*) AS accesses FROM req GROUP BY 1, 2) GROUP BY 1")
def url_access_hist(spark, sf_dir):
    return measures.histogram(events_requests(spark, sf_dir), ["event_type", "url_id"])


@query(f"WITH {REQ}, n AS (SELECT event_type, url_id, count(*) AS n FROM req GROUP BY 1, 2) SELECT count(*) AS urls, avg(CASE WHEN n = 1 THEN 1.0 ELSE 0 END) AS once, avg(CASE WHEN n = 2 THEN 1.0 ELSE 0 END) AS twice, avg(CASE WHEN n >= 3 THEN 1.0 ELSE 0 END) AS more, max(n) AS max_accesses, avg(n) AS mean_accesses FROM n")
def url_access_report(spark, sf_dir):
    return measures.access_report(events_requests(spark, sf_dir), ["event_type", "url_id"])


@query("WITH w AS (SELECT word FROM (SELECT unnest(regexp_split_to_array(lower(trim(text, ' ')), '[ \\t\\n\\x0b\\f\\r]+')) AS word FROM documents) WHERE word <> '') SELECT accesses, count(*) AS urls FROM (SELECT word, count(*) AS accesses FROM w GROUP BY 1) GROUP BY 1")
def word_access_hist(spark, sf_dir):
    """The long tail: words of documents as URLs."""
    w = table(spark, sf_dir, "documents").select(F.explode(F.split(F.lower(F.trim("text")), r"\s+")).alias("word")).where("word <> ''")
    return measures.histogram(w, ["word"])


@query("WITH w AS (SELECT word FROM (SELECT unnest(regexp_split_to_array(lower(trim(text, ' ')), '[ \\t\\n\\x0b\\f\\r]+')) AS word FROM documents) WHERE word <> ''), n AS (SELECT word, count(*) AS n FROM w GROUP BY 1) SELECT l AS min_access, (SELECT count(*) FROM n) AS urls_before, count(*) AS urls, CAST(sum(n) AS BIGINT) AS requests FROM n, (SELECT unnest([1, 2, 5]) AS l) WHERE n >= l GROUP BY 1")
def prune_long_tail(spark, sf_dir):
    """Words of documents as URLs: how many are left, and how many requests of them, at each limit on accesses."""
    w = table(spark, sf_dir, "documents").select(F.explode(F.split(F.lower(F.trim("text")), r"\s+")).alias("url_id")).where("url_id <> ''")
    n, out = w.select("url_id").distinct().count(), None
    for limit in (1, 2, 5):
        kept = features.prune_urls(w, limit).groupBy("url_id").agg(F.count("*").alias("n")).agg(F.count("*").alias("urls"), F.sum("n").alias("requests"))
        row = kept.select(F.lit(limit).alias("min_access"), F.lit(n).cast("long").alias("urls_before"), "urls", "requests")
        out = row if out is None else out.unionByName(row)
    return out


@query(f"WITH {DAYS} SELECT support, count(*) AS urls FROM (SELECT url_id, count(DISTINCT (user_id, session_no)) AS support FROM sess GROUP BY 1) GROUP BY 1")
def url_support_hist(spark, sf_dir):
    return measures.support_histogram(_sessions(spark, sf_dir), ["user_id", "session_no"])


@query(f"WITH {DAYS}, {ITEMS} SELECT n_urls, count(*) AS sessions FROM sizes GROUP BY 1")
def sess_size_hist(spark, sf_dir):
    return measures.size_histogram(_sizes(spark, sf_dir))


@query(f"WITH {REQ}, k AS (SELECT url_id FROM req GROUP BY 1 HAVING count(*) >= 95) SELECT seq, url_id FROM req WHERE url_id IN (SELECT url_id FROM k)")
def prune_access(spark, sf_dir):
    return features.prune_urls(events_requests(spark, sf_dir), 95).select("seq", "url_id")


@query(f"WITH {DAYS}, k AS (SELECT url_id FROM sess GROUP BY 1 HAVING count(DISTINCT (user_id, session_no)) >= 90) SELECT seq, url_id FROM sess WHERE url_id IN (SELECT url_id FROM k)")
def prune_support(spark, sf_dir):
    return features.prune_support(_sessions(spark, sf_dir), 90).select("seq", "url_id")


@query(f"WITH {DAYS}, k AS (SELECT url_id FROM sess GROUP BY 1 HAVING count(DISTINCT (user_id, session_no)) >= 90), left_over AS (SELECT user_id, session_no, count(DISTINCT url_id) AS n_urls FROM sess WHERE url_id IN (SELECT url_id FROM k) GROUP BY 1, 2) SELECT n_urls, {RAMP} AS weight, count(*) AS sessions, ({RAMP}) * count(*) AS total FROM left_over GROUP BY 1")
def weights_after_filter(spark, sf_dir):
    """Sizes are counted again after URLs of low support are gone."""
    return measures.weight_table(measures.session_sizes(features.prune_support(_sessions(spark, sf_dir), 90)))


def _feature(weight: str, scale: str = "none"):
    def run(spark, sf_dir):
        items = features.profile_items(_sessions(spark, sf_dir), session="session_no")
        return items.select("user_id", "session_no", "url_id", F.round(features.value(weight, scale, "session_no"), 6).alias("x"))

    return run


_DWELL = f"WITH {DAYS}, t AS (SELECT *, coalesce((lead(epoch_us(ts)) OVER (PARTITION BY user_id, session_no ORDER BY ts, seq) - epoch_us(ts)) / 1e6, 0) AS stay FROM sess)"
for _name, _weight, _scale, _text in (
    ("feat_binary", "binary", "none", f"WITH {DAYS}, {ITEMS} SELECT user_id, session_no, url_id, 1.0::DOUBLE AS x FROM items"),
    ("feat_freq", "frequency", "none", f"WITH {DAYS}, {ITEMS} SELECT user_id, session_no, url_id, freq::DOUBLE AS x FROM items"),
    ("feat_bytes", "bytes", "none", f"WITH {DAYS}, {ITEMS} SELECT user_id, session_no, url_id, bytes::DOUBLE AS x FROM items"),
    ("feat_dwell", "dwell", "none", f"{_DWELL} SELECT user_id, session_no, url_id, round(sum(stay), 6) AS x FROM t GROUP BY 1, 2, 3"),
    ("feat_bytes_log", "bytes", "log1p", f"WITH {DAYS}, {ITEMS} SELECT user_id, session_no, url_id, round(ln(1 + bytes::DOUBLE), 6) AS x FROM items"),
    ("feat_freq_l2", "frequency", "l2", f"WITH {DAYS}, {ITEMS} SELECT user_id, session_no, url_id, round(freq / sqrt(sum((freq * freq)::DOUBLE) OVER (PARTITION BY user_id, session_no)), 6) AS x FROM items"),
    ("feat_bytes_max", "bytes", "max", f"WITH {DAYS}, {ITEMS} SELECT user_id, session_no, url_id, round(coalesce(bytes::DOUBLE / nullif(max(abs(bytes)) OVER (PARTITION BY user_id, session_no), 0), 0), 6) AS x FROM items"),
):
    _Q[_name], _SQL[_name] = _feature(_weight, _scale), _text


@query(f"WITH {DAYS}, {ITEMS} SELECT user_id, session_no, n_urls, {RAMP} AS w FROM sizes")
def weights_ramp(spark, sf_dir):
    return _sizes(spark, sf_dir).select("user_id", "session_no", "n_urls", features.ramp_weight(F.col("n_urls")).alias("w"))


@query(f"WITH {DAYS}, {ITEMS} SELECT user_id, session_no, n_urls, CASE WHEN n_urls >= 3 THEN 1.0::DOUBLE ELSE 0.0 END AS w FROM sizes")
def weights_step(spark, sf_dir):
    return _sizes(spark, sf_dir).select("user_id", "session_no", "n_urls", features.step_weight(F.col("n_urls"), 3).alias("w"))


@query(f"WITH {DAYS}, {ITEMS} SELECT n_urls, {RAMP} AS weight, count(*) AS sessions, ({RAMP}) * count(*) AS total FROM sizes GROUP BY 1")
def weights_table(spark, sf_dir):
    return measures.weight_table(_sizes(spark, sf_dir))


@query(f"""WITH {DAYS}, {ITEMS}, w AS (SELECT items.*, n_urls, unnest([('none', 1.0), ('hard', CASE WHEN n_urls >= 2 THEN 1.0 ELSE 0 END), ('soft', {RAMP})]) AS t FROM items JOIN sizes USING (user_id, session_no)),
k AS (SELECT t[1] AS treatment, t[2]::DOUBLE AS w, * FROM w WHERE t[2] > 0)
SELECT treatment, count(DISTINCT (user_id, session_no)) AS sessions, CAST(sum(freq) AS BIGINT) AS requests, count(DISTINCT url_id) AS urls, round(sum(w / n_urls), 6) AS weight FROM k GROUP BY 1""")
def retention(spark, sf_dir):
    items = features.profile_items(_sessions(spark, sf_dir), session="session_no")
    return measures.retention_report(items).withColumn("weight", F.round("weight", 6))


@query(f"WITH {REQ} SELECT url_id, count(*) AS accesses, CASE WHEN count(*) <= 90 THEN 0.0 WHEN count(*) >= 110 THEN 1.0 ELSE (count(*) - 90) / 20.0::DOUBLE END AS weight FROM req GROUP BY 1")
def url_soft_weight(spark, sf_dir):
    return features.url_weights(events_requests(spark, sf_dir), 90, 110)


# ---- clustering: the kernel against SQL, from four fixed sessions of ten URLs
WIDTH, CLUSTERS = 10, 4
_TEN = gap_sql(DAY, REQ.replace("'$.k') AS INT) AS url_id", "'$.k') AS INT) % 10 AS url_id"))
#: What a session counts under each treatment.
MASS = {"soft": RAMP, "hard": "CASE WHEN n_urls >= 2 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END", "none": "1.0::DOUBLE"}


def points_sql(weighting: str = "soft", clusters: int = CLUSTERS) -> str:
    return f"""{_TEN}, {ITEMS}, pts AS (SELECT i.user_id, i.session_no, url_id, 1.0::DOUBLE AS x, n_urls, {MASS[weighting]} AS w FROM items i JOIN sizes USING (user_id, session_no)),
ses AS (SELECT DISTINCT user_id, session_no, n_urls, w FROM pts),
pick AS (SELECT url_id, user_id, session_no FROM (SELECT *, row_number() OVER (PARTITION BY url_id ORDER BY user_id, session_no) AS r FROM pts WHERE n_urls <= 5) WHERE r = 1 AND url_id < {clusters}),
v0 AS (SELECT g.j, u.k, CASE WHEN p.url_id IS NULL THEN 0.0::DOUBLE ELSE 1.0::DOUBLE END + CASE WHEN u.k = g.j THEN 0.5::DOUBLE ELSE 0.0::DOUBLE END AS v
  FROM range({clusters}) g(j), range({WIDTH}) u(k) LEFT JOIN (SELECT pick.url_id AS j, pts.url_id FROM pick JOIN pts USING (user_id, session_no)) p ON p.j = g.j AND p.url_id = u.k)"""


def step_sql(i: int, update: str = "objective", crisp: bool = False) -> str:
    """Distances, shares and new centres of one step, from v{i} to v{i+1}; q is 2, or 1 for crisp."""
    share = "CASE WHEN row_number() OVER (PARTITION BY user_id, session_no ORDER BY d, j) = 1 THEN 1.0 ELSE 0.0 END" if crisp else "(1 / d) / sum(1 / d) OVER (PARTITION BY user_id, session_no)"
    mass = ("u" if crisp else "u * u") + (" * w" if update == "objective" else "")
    return f"""d{i} AS (SELECT s.user_id, s.session_no, s.w, c.j, s.n_urls + c.v2 - 2 * coalesce(t.dot, 0) AS d FROM ses s CROSS JOIN (SELECT j, sum(v * v) AS v2 FROM v{i} GROUP BY 1) c
  LEFT JOIN (SELECT user_id, session_no, j, sum(x * v) AS dot FROM pts JOIN v{i} ON url_id = k GROUP BY 1, 2, 3) t ON t.user_id = s.user_id AND t.session_no = s.session_no AND t.j = c.j),
u{i} AS (SELECT *, {share} AS u FROM d{i}),
v{i + 1} AS (SELECT o.j, o.k, CASE WHEN a.m > 0 THEN coalesce(b.b, 0) / a.m ELSE o.v END AS v FROM v{i} o LEFT JOIN (SELECT j, sum({mass}) AS m FROM u{i} GROUP BY 1) a ON a.j = o.j
  LEFT JOIN (SELECT j, url_id, sum({mass} * x) AS b FROM u{i} JOIN (SELECT user_id, session_no, url_id, x FROM pts) USING (user_id, session_no) GROUP BY 1, 2) b ON b.j = o.j AND b.url_id = o.k)"""


def _steps(n: int, weighting: str = "soft", clusters: int = CLUSTERS, **how) -> str:
    return ", ".join([points_sql(weighting, clusters), *(step_sql(i, **how) for i in range(n))])


def _start(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, np.ndarray]:
    """The points, and as centres the first session (of five URLs at most) of each of the first URLs, with 0.5 more there."""
    vectors = settle(features.vectorize(features.profile_items(workloads.event_sessions(spark, sf_dir, urls=WIDTH), session="session_no").withColumn("session_id", F.struct("user_id", "session_no"))), "vectors")
    first = vectors.where("n_urls <= 5").select("session_id", "idx", F.explode("idx").alias("k")).where(F.col("k") < CLUSTERS).groupBy("k").agg(F.min_by("idx", "session_id").alias("idx")).orderBy("k").collect()
    v = np.zeros((CLUSTERS, WIDTH))
    for r in first:
        v[r["k"], r["idx"]] = 1.0
    v[range(CLUSTERS), range(CLUSTERS)] += 0.5
    return vectors, v


def _iterated(spark: SparkSession, sf_dir: str, n: int, **how) -> tuple[DataFrame, clustering.Run]:
    vectors, v = _start(spark, sf_dir)
    points = settle(features.weighted_points(vectors), "points")
    return vectors, clustering.iterate(points, [clustering.Run(v, **how)], WIDTH, 0.0, n)[0]


def _centres(spark: SparkSession, run: clustering.Run) -> DataFrame:
    return spark.createDataFrame([(j, k, round(float(x), 6)) for j, row in enumerate(run.centres) for k, x in enumerate(row)], "j long, k long, v double")


def _moved(n: int, **how):
    return lambda spark, sf_dir: _centres(spark, _iterated(spark, sf_dir, n, **how)[1])


for _name, _n, _how, _sqlhow in (
    ("kmeans_step", 1, {"q": 1.0, "weighting": "soft"}, {"crisp": True}),
    ("kmeans_3iter", 3, {"q": 1.0, "weighting": "soft"}, {"crisp": True}),
    ("fcm_center_update", 1, {}, {}),
    ("fcm_center_as_printed", 1, {"update": "as_printed"}, {"update": "as_printed"}),
    ("fcm_3iter", 3, {}, {}),
    ("fcm_3iter_none", 3, {"weighting": "none"}, {"weighting": "none"}),
    ("fcm_3iter_hard", 3, {"weighting": "hard"}, {"weighting": "hard"}),
    ("kmeans_3iter_none", 3, {"q": 1.0, "weighting": "none"}, {"crisp": True, "weighting": "none"}),
):
    _Q[_name] = _moved(_n, **_how)
    _SQL[_name] = f"WITH {_steps(_n, **_sqlhow)} SELECT j, k, round(v, 6) AS v FROM v{_n}"


@query(f"WITH {_steps(1)} SELECT user_id, session_no, j, round(u, 6) AS u FROM u0")
def fcm_membership(spark, sf_dir):
    vectors, v = _start(spark, sf_dir)
    u = clustering.memberships(vectors, v, 2.0)
    return u.select("session_id.user_id", "session_id.session_no", F.posexplode("u").alias("j", "u")).select("user_id", "session_no", F.col("j").cast("long").alias("j"), F.round("u", 6).alias("u"))


@query(f"WITH {_steps(3)} SELECT round(sum(w * u * u * d), 4) AS j, round(sum(w * u * u * d) / (SELECT sum(w) FROM ses), 6) AS j_per_weight FROM u2")
def fcm_j(spark, sf_dir):
    run = _iterated(spark, sf_dir, 2)[1]
    return spark.createDataFrame([(round(run.j, 4), round(run.j / run.mass, 6))], "j double, j_per_weight double")


@query(f"WITH {_steps(3)}, sep AS (SELECT min(s) AS s FROM (SELECT sum((a.v - b.v) * (a.v - b.v)) AS s FROM v2 a JOIN v2 b ON a.k = b.k AND a.j < b.j GROUP BY a.j, b.j)) SELECT round(sum(u * u * d) / (SELECT count(*) FROM ses) / (SELECT s FROM sep), 4) AS s, round((SELECT s FROM sep), 6) AS sep_min FROM u2")
def fcm_validity(spark, sf_dir):
    run = _iterated(spark, sf_dir, 2)[1]
    return spark.createDataFrame([(round(run.validity, 4), round(run.separation, 6))], "s double, sep_min double")


_SEP = "sep AS (SELECT min(s) AS s FROM (SELECT sum((a.v - b.v) * (a.v - b.v)) AS s FROM v2 a JOIN v2 b ON a.k = b.k AND a.j < b.j GROUP BY a.j, b.j))"


@query(f"WITH {_steps(3, 'hard')}, {_SEP} SELECT round(sum(w * u * u * d) / (SELECT sum(w) FROM ses) / (SELECT s FROM sep), 4) AS s, (SELECT sum(w) FROM ses) AS sessions FROM u2")
def fcm_validity_hard(spark, sf_dir):
    """Under hard removal the removed sessions are no points."""
    run = _iterated(spark, sf_dir, 2, weighting="hard")[1]
    return spark.createDataFrame([(round(run.validity, 4), run.points)], "s double, sessions double")


@query(f"WITH {_steps(3)}, {_SEP} SELECT round(sum(w * u * u * d) / (SELECT sum(w) FROM ses) / (SELECT s FROM sep), 4) AS s FROM u2")
def fcm_validity_weighted(spark, sf_dir):
    run = _iterated(spark, sf_dir, 2)[1]
    return spark.createDataFrame([(round(run.weighted_validity, 4),)], "s double")


def _sweep_sql() -> str:
    parts = []
    for c in (2, 3, 4):
        for weighting in MASS:
            mass = "w" if weighting == "hard" else "1"  # whom S counts
            parts.append(f"""SELECT * FROM (WITH {_steps(3, weighting, c)}, {_SEP} SELECT {c} AS c, '{weighting}' AS weighting, round(sum(w * u * u * d), 4) AS j, round(sum(w * u * u * d) / (SELECT sum(w) FROM ses), 6) AS j_per_weight,
  round(sum({mass} * u * u * d) / (SELECT sum({mass}) FROM ses) / (SELECT s FROM sep), 4) AS s FROM u2)""")
    return " UNION ALL ".join(parts)


def _fixed_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors, v = _start(spark, sf_dir)
    points = settle(features.weighted_points(vectors), "points")
    runs = clustering.iterate(points, [clustering.Run(v[:c].copy(), 2.0, w) for c in (2, 3, 4) for w in MASS], WIDTH, 0.0, 2)
    return clustering.sweep_table(spark, runs)


@query(_sweep_sql())
def fcm_sweep_fixed(spark, sf_dir):
    """J, J for each unit of weight and S of the three treatments for 2 to 4 clusters, two steps from fixed starts, in shared passes."""
    return _fixed_sweep(spark, sf_dir).select("c", "weighting", F.round("j", 4).alias("j"), F.round("j_per_weight", 6).alias("j_per_weight"), F.round("s", 4).alias("s"))


@query(f"SELECT weighting, arg_min(c, s) AS best_c, min(s) AS s FROM ({_sweep_sql()}) GROUP BY 1")
def fcm_select_fixed(spark, sf_dir):
    return clustering.select_c(_fixed_sweep(spark, sf_dir)).withColumn("s", F.round("s", 4))


@query(f"WITH {_TEN}, {ITEMS} SELECT count(*) AS rows, 0::BIGINT AS bad_rows, 0::BIGINT AS bad_columns FROM sizes")
def fcm_partition_check(spark, sf_dir):
    vectors, run = _iterated(spark, sf_dir, 3)
    return clustering.check_partition(clustering.memberships(vectors, run.centres, 2.0))


@query(f"WITH {_steps(1)} SELECT clusters, count(*) AS sessions FROM (SELECT count(*) FILTER (u >= 0.25) AS clusters FROM u0 GROUP BY user_id, session_no) GROUP BY 1")
def fcm_overlap(spark, sf_dir):
    vectors, v = _start(spark, sf_dir)
    return clustering.overlap_profile(clustering.memberships(vectors, v, 2.0)).withColumn("clusters", F.col("clusters").cast("long"))


@query(f"WITH {_steps(1)} SELECT user_id, session_no, j AS cluster FROM (SELECT *, row_number() OVER (PARTITION BY user_id, session_no ORDER BY round(u, 9) DESC, j) AS r FROM u0) WHERE r = 1")
def fcm_assign(spark, sf_dir):
    vectors, v = _start(spark, sf_dir)
    u = clustering.memberships(vectors, v, 2.0)
    u = u.withColumn("u", F.transform("u", lambda x: F.round(x, 9)))
    return clustering.assign(u).select("session_id.user_id", "session_id.session_no", F.col("cluster").cast("long").alias("cluster"))


# ---- the whole chain
_SHARE = "0.95::DOUBLE"
CHAIN = f"""{LOG}, who AS (SELECT sha256(concat('alias', chr(0), client_ip)) || '|' || sha256(user_agent) AS user_id, ts, seq, plain AS url_id FROM cleaned),
often AS (SELECT url_id FROM who GROUP BY 1 HAVING count(*) >= {_SHARE} * (SELECT count(*)::DOUBLE / count(DISTINCT url_id) FROM who)),
{gap_sql(DAY, 'req AS (SELECT * FROM who WHERE url_id IN (SELECT url_id FROM often))')},
support AS (SELECT url_id, count(DISTINCT (user_id, session_no)) AS n FROM sess GROUP BY 1),
supported AS (SELECT * FROM sess WHERE url_id IN (SELECT url_id FROM support WHERE n >= {_SHARE} * (SELECT avg(n) FROM support)))"""


@query(
    f"WITH {CHAIN} SELECT 'raw' AS step, count(*) AS requests, count(DISTINCT url) AS urls, count(DISTINCT client_ip || '|' || user_agent) AS users, NULL::BIGINT AS sessions FROM raw UNION ALL "
    + " UNION ALL ".join(f"SELECT '{step}', count(*), count(DISTINCT url_id), count(DISTINCT user_id), {sessions} FROM {name}" for step, name, sessions in (("cleaned", "who", "NULL"), ("accessed", "req", "NULL"), ("sessions", "sess", "count(DISTINCT (user_id, session_no))"), ("supported", "supported", "count(DISTINCT (user_id, session_no))")))
)
def chain_report(spark, sf_dir):
    return workloads.chain_report(spark, sf_dir)


@query(f"WITH {CHAIN}, items AS (SELECT user_id, session_no, url_id, count(*) AS freq FROM supported GROUP BY ALL), sizes AS (SELECT user_id, session_no, count(*) AS n_urls FROM items GROUP BY ALL) SELECT user_id AS user_key, session_no, url_id AS url, freq, n_urls, {RAMP} AS w FROM items JOIN sizes USING (user_id, session_no)")
def chain_vectors(spark, sf_dir):
    return workloads.chain_vectors(spark, sf_dir)


# ---- experiments without SQL
for _f in (workloads.cluster_summary, workloads.chain_sweep, workloads.chain_best_c, workloads.document_sweep, workloads.count_sweep, workloads.full_sweep, workloads.run_stats, workloads.hard_and_soft, workloads.crisp_and_fuzzy, workloads.language_purity, workloads.basket_clusters, workloads.dense_points):
    _Q[_f.__name__] = _f


@query()
def fcm_select_c(spark, sf_dir):
    """The count of least validity index for each weighting, with documents as sessions."""
    return clustering.select_c(workloads.count_sweep(spark, sf_dir, range(3, 7), source="documents", max_iter=15))


# ---- streams, run over all there is and flushed
def _stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return live.requests_stream(spark, live.staged(spark, sf_dir))


@query("SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS hits FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    return live.run_to_table(live.tumbling(_stream(spark, sf_dir))).where("event_type <> 'flush'")


@query("SELECT start, event_type, count(*) AS hits FROM (SELECT event_type, unnest([time_bucket(INTERVAL 15 MINUTE, ts) - to_minutes(15 * i) FOR i IN range(4)]) AS start FROM events) GROUP BY 1, 2")
def stream_sliding(spark, sf_dir):
    return live.run_to_table(live.tumbling(_stream(spark, sf_dir), "1 hour", "15 minutes")).where("event_type <> 'flush'")


@query(f"WITH {gap_sql(MIN30)} SELECT user_id, min(ts) AS start, count(*) AS requests FROM sess GROUP BY user_id, session_no")
def stream_session_gap(spark, sf_dir):
    return live.run_to_table(live.gap_sessions(_stream(spark, sf_dir))).where("user_id >= 0")


@query(f"WITH RECURSIVE {duration_sql(MIN30)} SELECT user_id, min(ts) AS start, count(*) AS requests FROM sess GROUP BY user_id, session_no")
def stream_session_duration(spark, sf_dir):
    return live.run_to_table(live.duration_sessions(_stream(spark, sf_dir), MIN30)).where("user_id >= 0")


@query(f"WITH {gap_sql(MIN30)} SELECT user_id, min(ts) AS start, count(DISTINCT url_id)::INT AS n_urls, CASE WHEN count(DISTINCT url_id) <= 1 THEN 0.0 ELSE least(1.0, (count(DISTINCT url_id) - 1) / 5.0::DOUBLE) END AS weight FROM sess GROUP BY user_id, session_no")
def stream_session_weights(spark, sf_dir):
    return live.run_to_table(live.weigh_sessions(_stream(spark, sf_dir))).where("user_id >= 0")


@query(f"WITH {REQ} SELECT user_id, ts, seq, url_id FROM req")
def stream_dedup(spark, sf_dir):
    """Every file is read twice; each request comes out once."""
    folder = live.staged(spark, sf_dir, flush=False)
    table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", "props").write.mode("append").parquet(folder)
    return live.run_to_table(live.deduplicated(live.requests_stream(spark, folder, watermark="60 days")).select("user_id", "ts", "seq", "url_id"))


@query("SELECT p.user_id, v.ts AS view_ts, p.ts AS buy_ts FROM events p JOIN events v ON p.user_id = v.user_id AND p.event_type = 'purchase' AND v.event_type = 'view' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 DAY")
def stream_buy_after_view(spark, sf_dir):
    folder = live.staged(spark, sf_dir)
    return live.run_to_table(live.purchases_after_views(live.requests_stream(spark, folder), live.requests_stream(spark, folder)))


@query(f"WITH {LOG} SELECT ts, seq, plain AS url, client_ip, user_agent FROM cleaned")
def stream_clean(spark, sf_dir):
    """The raw log cleaned as it arrives."""
    folder = shared(spark, "raw-log")
    log = weblog(spark, sf_dir)
    log.write.parquet(folder)
    stream = spark.readStream.schema(log.schema).parquet(folder)
    return live.run_to_table(live.cleaned(stream).select("ts", "seq", "url", "client_ip", "user_agent"))


@query("SELECT e.event_id AS seq, CAST(json_extract_string(e.props, '$.k') AS INT) AS url_id, p.url FROM events e LEFT JOIN pages p ON CAST(json_extract_string(e.props, '$.k') AS INT) = p.page_id")
def stream_named(spark, sf_dir):
    """A stream joined with the table of URL names."""
    urls = table(spark, sf_dir, "pages").select(F.col("page_id").cast("int").alias("url_id"), "url")
    folder = live.staged(spark, sf_dir, flush=False)
    return live.run_to_table(live.named(live.requests_stream(spark, folder).select("seq", "url_id"), urls))


_FIXED = np.array([[1.0 if k % 4 == j else 0.0 for k in range(100)] for j in range(4)]) * 0.2
_SCORED = f"""WITH {gap_sql(MIN30)}, s AS (SELECT user_id, min(ts) AS start, list_distinct(list(url_id)) AS u FROM sess GROUP BY user_id, session_no),
d AS (SELECT user_id, start, j, len(u) + 25 * 0.04 - 2 * 0.2 * len(list_filter(u, lambda k: k % 4 = j)) AS d FROM s, range(4) r(j))
SELECT user_id, start, j, round((1 / d) / sum(1 / d) OVER (PARTITION BY user_id, start), 6) AS u FROM d"""


@query(_SCORED)
def stream_scores(spark, sf_dir):
    """Sessions that close are scored by four fixed centres."""
    closed = live.run_to_table(live.session_vectors(_stream(spark, sf_dir), 100)).where("user_id >= 0")
    return live.scored(closed, _FIXED, 2.0).select("user_id", "start", F.posexplode("u").alias("j", "u")).select("user_id", "start", F.col("j").cast("long").alias("j"), F.round("u", 6).alias("u"))


@query()
def stream_drift(spark, sf_dir):
    """j, mass, moved: how far the centres went while the stream passed."""
    follow = live.Drift(_FIXED, 1.2)
    live.run_batches(live.session_vectors(_stream(spark, sf_dir), 100).where("user_id >= 0"), follow)
    rows = [(j, float(follow.mass[j]), float(np.abs(follow.centres[j] - _FIXED[j]).max())) for j in range(len(_FIXED))]
    return spark.createDataFrame(rows, "j int, mass double, moved double")


@query("SELECT 1::BIGINT AS late")
def stream_late(spark, sf_dir):
    """A row a year behind the others comes in a file of its own after them, and is counted as late."""
    folder = live.staged(spark, sf_dir, flush=False)
    first = live.tumbling(live.requests_stream(spark, folder, per_trigger=1))
    state = shared(spark, "late")

    def run() -> list[dict]:
        q = first.writeStream.foreachBatch(lambda b, n: b.write.format("noop").mode("overwrite").save()).outputMode("append").option("checkpointLocation", state).trigger(availableNow=True).start()
        q.awaitTermination()
        return live.progress_of(q)

    run()
    late = table(spark, sf_dir, "events").limit(1).select("event_id", F.lit("2023-01-01 00:00:00").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", "value", "props")
    late.coalesce(1).write.mode("append").parquet(folder)
    return spark.createDataFrame([(live.late_rows(run()),)], "late long")
