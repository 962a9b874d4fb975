"""Relational operators around the methods, each with an example on the given tables and its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.logs import events_requests, table

_Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}
K = "CAST(json_extract_string(props, '$.k') AS INT)"


def rel(sql: str | None = None):
    def put(f: Callable[[SparkSession, str], DataFrame]) -> Callable:
        _Q[f.__name__] = f
        if sql:
            _SQL[f.__name__] = sql
        return f

    return put


def queries() -> dict:
    return dict(_Q)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)


# ---- operators of their own
def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, carry: list[str], tie: str) -> DataFrame:
    """Each left row with the latest right row of the same key at or before its time: the rows are united and the last right
    row is carried forward in one sort by key, without comparing pairs."""
    both = left.select(by, at, tie, F.lit(True).alias("_left"), *(F.lit(None).cast(dict(right.dtypes)[c]).alias(f"_{c}") for c in carry)).unionByName(
        right.select(by, at, tie, F.lit(False).alias("_left"), *(F.col(c).alias(f"_{c}") for c in carry))
    )
    w = Window.partitionBy(by).orderBy(at, "_left", tie).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    packed = F.last(F.when(~F.col("_left"), F.struct(*(F.col(f"_{c}").alias(c) for c in carry))), ignorenulls=True).over(w)
    return both.withColumn("_r", packed).where("_left").select(by, at, tie, *(F.col(f"_r.{c}").alias(f"last_{c}") for c in carry))


def interval_join(points: DataFrame, spans: DataFrame, by: str, at: str, start: str, end: str) -> DataFrame:
    """Points inside spans of the same key, both ends included: a join on the key with a range condition."""
    s = spans.withColumnRenamed(by, "_by")
    return points.join(s, (F.col(by) == F.col("_by")) & (F.col(at) >= F.col(start)) & (F.col(at) <= F.col(end))).drop("_by")


def top_per_group(df: DataFrame, by: list[str], order: list, k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("rank") <= k)


def sample_by_hash(df: DataFrame, key: str, share: float, seed: int = 1) -> DataFrame:
    """The same rows in every run: those whose key hashes below the share."""
    return df.where(F.pmod(F.xxhash64(key, F.lit(seed)), F.lit(1 << 20)) < int(share * (1 << 20)))


def sequential_patterns(sessions: DataFrame, support: float = 0.1, longest: int = 3) -> DataFrame:
    """sequence, freq of pages that sessions visit in order. sessions: pages, an array of arrays."""
    from pyspark.ml.fpm import PrefixSpan

    return PrefixSpan(minSupport=support, maxPatternLength=longest, sequenceCol="pages").findFrequentSequentialPatterns(sessions)


def association_rules(baskets: DataFrame, support: float = 0.02, confidence: float = 0.2) -> DataFrame:
    """Rules between pages of a session. baskets: items, an array without repeats."""
    from pyspark.ml.fpm import FPGrowth

    return FPGrowth(itemsCol="items", minSupport=support, minConfidence=confidence).fit(baskets).associationRules


# ---- examples
@rel("SELECT event_id, value FROM events WHERE value BETWEEN 10 AND 50 AND event_type IN ('view', 'purchase') AND user_id IS NOT DISTINCT FROM 3")
def project_filter(spark, sf_dir):
    return table(spark, sf_dir, "events").where(F.col("value").between(10, 50) & F.col("event_type").isin("view", "purchase") & F.col("user_id").eqNullSafe(3)).select("event_id", "value")


@rel("SELECT l_orderkey, p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2")
def join_inner_hash(spark, sf_dir):
    lines, part = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "part").select("p_partkey", "p_brand")
    return lines.join(part.hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).groupBy("l_orderkey", "p_brand").agg(F.count("*").alias("n"))


@rel("SELECT o_custkey, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_sort_merge(spark, sf_dir):
    return table(spark, sf_dir, "orders").join(table(spark, sf_dir, "lineitem").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey").agg(F.count("*").alias("lines"))


@rel("SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(spark, sf_dir):
    n = table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # fixed tables
    return table(spark, sf_dir, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")


@rel("SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left(spark, sf_dir):
    return table(spark, sf_dir, "customer").join(table(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@rel("SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, quality FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def join_full(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "full")


@rel(f"SELECT event_id FROM events WHERE {K} IN (SELECT {K} FROM events WHERE event_type = 'purchase' GROUP BY 1 HAVING count(*) > 20)")
def join_semi(spark, sf_dir):
    e = table(spark, sf_dir, "events").withColumn("k", F.get_json_object("props", "$.k"))
    kept = e.where("event_type = 'purchase'").groupBy("k").agg(F.count("*").alias("n")).where("n > 20")
    return e.join(kept, "k", "left_semi").select("event_id")


@rel("SELECT doc_id FROM documents WHERE NOT EXISTS (SELECT 1 FROM benchmark b WHERE b.text = documents.text)")
def join_anti(spark, sf_dir):
    d, b = table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark").select(F.col("text").alias("t"))
    return d.join(b, d["text"] == b["t"], "left_anti").select("doc_id")


_BANDS = [("small", 0, 2), ("middle", 3, 5), ("large", 6, 1 << 30)]


@rel(f"SELECT o_orderkey, name FROM (SELECT l_orderkey AS o_orderkey, count(*) AS n FROM lineitem GROUP BY 1) JOIN (VALUES {', '.join(map(str, _BANDS))}) b(name, lo, hi) ON n BETWEEN lo AND hi")
def join_theta(spark, sf_dir):
    bands = spark.createDataFrame(_BANDS, "name string, lo long, hi long")  # a row for each band
    n = table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.count("*").alias("n"))
    return n.join(F.broadcast(bands), (F.col("n") >= F.col("lo")) & (F.col("n") <= F.col("hi"))).select("o_orderkey", "name")


@rel("WITH s AS (SELECT user_id, date_trunc('day', ts) AS d, min(ts) AS a, max(ts) AS b FROM events WHERE event_type = 'view' GROUP BY 1, 2) SELECT e.event_id, s.a FROM events e JOIN s ON e.user_id = s.user_id AND e.ts BETWEEN s.a AND s.b")
def join_interval(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    spans = e.where("event_type = 'view'").groupBy("user_id", F.date_trunc("day", "ts").alias("d")).agg(F.min("ts").alias("a"), F.max("ts").alias("b"))
    return interval_join(e.select("event_id", "user_id", "ts"), spans, "user_id", "ts", "a", "b").select("event_id", "a")


@rel("SELECT p.event_id, v.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def join_asof(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    out = asof_join(e.where("event_type = 'purchase'"), e.where("event_type = 'view'"), "user_id", "ts", ["event_id"], "event_id")
    return out.select("event_id", F.col("last_event_id").alias("last_view"))


@rel("SELECT user_id, count(*) AS n, round(sum(value), 4) AS total, count(DISTINCT event_type) AS kinds, arg_max(event_type, (ts, event_id)) AS last_kind, bool_or(event_type = 'error') AS failed, round(stddev_samp(value), 6) AS sd, list_sort(array_agg(DISTINCT event_type)) AS seen FROM events GROUP BY 1")
def agg_basic(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id").agg(
        F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"), F.countDistinct("event_type").alias("kinds"), F.max_by("event_type", F.struct("ts", "event_id")).alias("last_kind"),
        F.bool_or(F.col("event_type") == "error").alias("failed"), F.round(F.stddev("value"), 6).alias("sd"), F.sort_array(F.collect_set("event_type")).alias("seen"),
    )


@rel()
def agg_approx(spark, sf_dir):
    """Users a day and the median value, both with bounded error."""
    return table(spark, sf_dir, "events").groupBy(F.to_date("ts").alias("day")).agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", 0.5, 1000).alias("median"))


@rel("SELECT CAST(ts AS DATE) AS day, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY GROUPING SETS ((CAST(ts AS DATE), event_type), (event_type), ())")
def grouping_sets(spark, sf_dir):
    table(spark, sf_dir, "events").select(F.to_date("ts").alias("day"), "event_type", "value").createOrReplaceTempView("_event_days")
    return spark.sql("SELECT day, event_type, count(*) AS n, round(sum(value), 4) AS total FROM _event_days GROUP BY GROUPING SETS ((day, event_type), (event_type), ())")


@rel("SELECT r_name, n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def rollup(spark, sf_dir):
    return join_broadcast(spark, sf_dir).rollup("r_name", "n_name").agg(F.count("*").alias("customers"))


@rel("SELECT event_type, user_id % 3 AS part, count(*) AS n FROM events GROUP BY CUBE (event_type, user_id % 3)")
def cube(spark, sf_dir):
    return table(spark, sf_dir, "events").withColumn("part", F.col("user_id") % 3).cube("event_type", "part").agg(F.count("*").alias("n"))


_KINDS = ["click", "error", "purchase", "signup", "view"]


@rel("SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{k}') AS {k}" for k in _KINDS) + " FROM events GROUP BY 1")
def pivot(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", _KINDS).count().na.fill(0)


@rel("SELECT user_id, k, n, row_number() OVER (PARTITION BY user_id ORDER BY n DESC, k) AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY user_id ORDER BY n DESC, k) AS q, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd FROM (SELECT user_id, " + K + " AS k, count(*) AS n FROM events GROUP BY 1, 2) WINDOW w AS (PARTITION BY user_id ORDER BY n DESC)")
def win_rank(spark, sf_dir):
    n = events_requests(spark, sf_dir).groupBy("user_id", F.col("url_id").alias("k")).agg(F.count("*").alias("n"))
    w, strict = Window.partitionBy("user_id").orderBy(F.desc("n")), Window.partitionBy("user_id").orderBy(F.desc("n"), "k")
    return n.select("user_id", "k", "n", F.row_number().over(strict).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(strict).alias("q"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@rel("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after2, first_value(event_id) OVER w AS first, last_value(event_id) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last, nth_value(event_id, 3) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS third FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_offset(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after2"), F.first("event_id").over(w).alias("first"), F.last("event_id").over(whole).alias("last"), F.nth_value("event_id", 3).over(whole).alias("third"))


@rel("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS running, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM events")
def win_frames(spark, sf_dir):
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    hour = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    e = table(spark, sf_dir, "events").withColumn("s", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000))
    return e.select("event_id", F.count("*").over(rows).alias("running"), F.count("*").over(hour).alias("last_hour"))


@rel(f"SELECT {K} AS url_id, count(*) AS n FROM events GROUP BY 1 ORDER BY n DESC, url_id LIMIT 10")
def topk_urls(spark, sf_dir):
    return events_requests(spark, sf_dir).groupBy("url_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "url_id").limit(10)


@rel(f"SELECT event_type, url_id, n, rank FROM (SELECT event_type, {K} AS url_id, count(*) AS n, row_number() OVER (PARTITION BY event_type ORDER BY count(*) DESC, {K}) AS rank FROM events GROUP BY 1, 2) WHERE rank <= 3")
def topk_per_group(spark, sf_dir):
    n = events_requests(spark, sf_dir).groupBy("event_type", "url_id").agg(F.count("*").alias("n"))
    return top_per_group(n, ["event_type"], [F.desc("n"), "url_id"], 3)


@rel("SELECT user_id, 'both' AS part FROM (SELECT user_id FROM events WHERE day(ts) <= 15 INTERSECT SELECT user_id FROM events WHERE day(ts) > 15) UNION ALL SELECT user_id, 'first' FROM (SELECT user_id FROM events WHERE day(ts) <= 15 EXCEPT SELECT user_id FROM events WHERE day(ts) > 15)")
def setops(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    a, b = e.where(F.dayofmonth("ts") <= 15).select("user_id"), e.where(F.dayofmonth("ts") > 15).select("user_id")
    return a.intersect(b).withColumn("part", F.lit("both")).unionByName(a.subtract(b).withColumn("part", F.lit("first")))


@rel("SELECT conv_id, turn, i - 1 AS pos, w[i] AS word FROM (SELECT conv_id, turn, w, unnest(range(1, len(w) + 1)) AS i FROM (SELECT conv_id, turn, string_split(text, ' ') AS w FROM conversations))")
def generate(spark, sf_dir):
    return table(spark, sf_dir, "conversations").select("conv_id", "turn", F.posexplode(F.split("text", " ")).alias("pos", "word")).withColumn("pos", F.col("pos").cast("long"))


@rel("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k, json_array_length('[1,2]') AS two FROM events")
def json_props(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.json_array_length(F.lit("[1,2]")).cast("long").alias("two"))


@rel("SELECT event_id, upper(event_type) AS up, length(event_type) AS n, event_type[1:3] AS head, event_type || '-' || user_id AS joined, replace(event_type, 'e', '_') AS swapped, sha256(event_type) AS digest, regexp_replace(event_type, '[aeiou]', '', 'g') AS bare FROM events")
def string_fns(spark, sf_dir):
    t = F.col("event_type")
    return table(spark, sf_dir, "events").select("event_id", F.upper(t).alias("up"), F.length(t).cast("long").alias("n"), F.substring(t, 1, 3).alias("head"), F.concat_ws("-", t, F.col("user_id").cast("string")).alias("joined"), F.replace(t, F.lit("e"), F.lit("_")).alias("swapped"), F.sha2(t, 256).alias("digest"), F.regexp_replace(t, "[aeiou]", "").alias("bare"))


@rel("SELECT event_id, CAST(date_trunc('month', ts) AS DATE) AS month, dayofweek(ts) + 1 AS dow, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS days, strftime(ts, '%Y%m%d%H%M%S') AS stamp, CAST(ts + INTERVAL 36 HOUR AS DATE) AS later FROM events")
def date_fns(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.to_date(F.date_trunc("month", "ts")).alias("month"), F.dayofweek("ts").cast("long").alias("dow"), F.datediff(F.to_date("ts"), F.lit("2024-01-01")).cast("long").alias("days"), F.date_format("ts", "yyyyMMddHHmmss").alias("stamp"), F.to_date(F.col("ts") + F.expr("INTERVAL 36 HOUR")).alias("later"))


@rel("SELECT user_id, list_sort(ks) AS ks, list_sum(list_transform(ks, lambda x: x * 2)) AS doubled, len(list_filter(ks, lambda x: x >= 50)) AS high, list_max(ks) AS most FROM (SELECT user_id, array_agg(DISTINCT " + K + ") AS ks FROM events GROUP BY 1)")
def array_fns(spark, sf_dir):
    a = events_requests(spark, sf_dir).groupBy("user_id").agg(F.sort_array(F.collect_set("url_id")).alias("ks"))
    return a.select("user_id", "ks", F.aggregate(F.transform("ks", lambda x: x * 2), F.lit(0).cast("long"), lambda s, x: s + x).alias("doubled"), F.size(F.filter("ks", lambda x: x >= 50)).cast("long").alias("high"), F.array_max("ks").alias("most"))


@rel("SELECT user_id, count(*) AS keys, CAST(max(n) AS BIGINT) AS top, coalesce(max(n) FILTER (event_type = 'view'), 0) AS views FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1")
def map_fns(spark, sf_dir):
    m = table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.size(F.map_keys("m")).cast("long").alias("keys"), F.array_max(F.map_values("m")).alias("top"), F.coalesce(F.try_element_at("m", F.lit("view")), F.lit(0)).alias("views"))


@rel("SELECT event_id, round(sqrt(value), 6) AS root, round(ln(1 + value), 6) AS log, round(pow(value, 2), 4) AS square, greatest(value, 10.0::DOUBLE) AS most, least(value, 10.0::DOUBLE) AS least, value / nullif(user_id % 3, 0) AS ratio, CAST(floor(value) AS BIGINT) AS down FROM events")
def math_fns(spark, sf_dir):
    v = F.col("value")
    return table(spark, sf_dir, "events").select("event_id", F.round(F.sqrt(v), 6).alias("root"), F.round(F.log1p(v), 6).alias("log"), F.round(F.pow(v, 2), 4).alias("square"), F.greatest(v, F.lit(10.0)).alias("most"), F.least(v, F.lit(10.0)).alias("least"), F.try_divide(v, F.col("user_id") % 3).alias("ratio"), F.floor(v).alias("down"))


@rel("SELECT d.doc_id, coalesce(quality, -1) AS quality, nullif(toxic, 0) AS toxic, CASE WHEN quality IS NULL THEN 'unknown' WHEN quality = 1 THEN 'good' ELSE 'poor' END AS grade, quality IS NOT DISTINCT FROM toxic AS same FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def null_fns(spark, sf_dir):
    j = table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    grade = F.when(F.col("quality").isNull(), "unknown").when(F.col("quality") == 1, "good").otherwise("poor")
    return j.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.nullif(F.col("toxic"), F.lit(0)).alias("toxic"), grade.alias("grade"), F.col("quality").eqNullSafe(F.col("toxic")).alias("same"))


_HALVES = "a AS (SELECT user_id, event_type FROM events WHERE day(ts) <= 15), b AS (SELECT user_id, event_type FROM events WHERE day(ts) > 15)"


@rel(f"WITH {_HALVES} SELECT user_id, event_type, 'kept' AS part FROM (SELECT * FROM a INTERSECT ALL SELECT * FROM b) UNION ALL SELECT user_id, event_type, 'lost' FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b) UNION ALL SELECT user_id, event_type, 'any' FROM (SELECT * FROM a UNION SELECT * FROM b)")
def setops_all(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    a, b = (e.where(c).select("user_id", "event_type") for c in (F.dayofmonth("ts") <= 15, F.dayofmonth("ts") > 15))
    parts = (("kept", a.intersectAll(b)), ("lost", a.exceptAll(b)), ("any", a.unionByName(b).distinct()))
    out = None
    for name, df in parts:
        df = df.withColumn("part", F.lit(name))
        out = df if out is None else out.unionByName(df)
    return out


@rel()
def sample_hash(spark, sf_dir):
    return sample_by_hash(table(spark, sf_dir, "events"), "event_id", 0.1).select("event_id")


@rel()
def rules(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "part"), F.col("l_partkey") == F.col("p_partkey"))
    return association_rules(lines.groupBy("l_orderkey").agg(F.collect_set("p_brand").alias("items")), 0.005, 0.05)


@rel()
def sequences(spark, sf_dir):
    e = table(spark, sf_dir, "events").where("event_type <> 'view'")
    return sequential_patterns(e.groupBy("user_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda s: F.array(s["event_type"])).alias("pages")), 0.5, 2)
