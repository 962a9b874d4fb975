"""The experiments on the given tables, as tables of results."""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..operators import cleaning as cleaning_ops
from ..operators import clustering, features, measures, sessionize
from ..operators.cleaning import cleaning_report
from ..sources.logs import events_requests, table, weblog
from .stage import settle

DAY = sessionize.DAY


def event_sessions(spark: SparkSession, sf_dir: str, beta_us: int = DAY, rule: str = "gap", urls: int | None = None) -> DataFrame:
    """Requests of the events table with session_no and session_id."""
    numbers = {"gap": sessionize.gap_numbers, "duration": sessionize.duration_numbers}[rule]
    return numbers(events_requests(spark, sf_dir, urls), beta_us).withColumn("session_id", F.concat(F.lit("U"), F.col("user_id").cast("string"), F.lit("-S"), F.col("session_no").cast("string")))


def event_vectors(spark: SparkSession, sf_dir: str, urls: int | None = None, weight: str = "binary") -> DataFrame:
    return features.vectorize(features.profile_items(event_sessions(spark, sf_dir, urls=urls)), weight)


def event_points(spark: SparkSession, sf_dir: str, urls: int | None = None) -> DataFrame:
    return settle(features.weighted_points(event_vectors(spark, sf_dir, urls)), "points")


def basket_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as sessions, the 25 brands of their parts as URLs."""
    numbers = table(spark, sf_dir, "part").select("p_brand").distinct()  # 25 brands
    numbers = numbers.select("p_brand", (F.row_number().over(Window.orderBy("p_brand")) - 1).alias("b"))
    brand = table(spark, sf_dir, "part").select("p_partkey", "p_brand").join(F.broadcast(numbers), "p_brand").select("p_partkey", "b")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(brand, F.col("l_partkey") == F.col("p_partkey"))
    return settle(features.basket_points(lines, "l_orderkey", "b"), "points")


def document_vectors(spark: SparkSession, sf_dir: str, top: int = 40) -> DataFrame:
    """Documents as sessions, their ``top`` words of widest support as URLs; those without any such word are empty vectors."""
    words = table(spark, sf_dir, "documents").select("doc_id", "lang", F.explode(F.array_distinct(F.split(F.lower(F.trim("text")), r"\s+"))).alias("w")).where("w <> ''")
    best = words.groupBy("w").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "w").limit(top)  # ``top`` rows
    numbers = best.select("w", (F.row_number().over(Window.orderBy(F.desc("n"), "w")) - 1).alias("k"))
    each = words.join(F.broadcast(numbers), "w").groupBy("doc_id").agg(F.sort_array(F.collect_list("k")).alias("idx"))
    every = words.groupBy("doc_id", "lang").agg(F.count("*").alias("n_urls"))
    out = every.join(each, "doc_id", "left").withColumn("idx", F.coalesce("idx", F.array().cast("array<int>")))
    return out.select("doc_id", "lang", "idx", F.transform("idx", lambda _: F.lit(1.0)).alias("val"), "n_urls")


def cleaning(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cleaning_report(weblog(spark, sf_dir))


# ---- the whole chain, from the raw log to points
@dataclass
class Chain:
    """What each step left: the raw log, the cleaned one with users, the requests of URLs accessed often enough, their sessions,
    the sessions' requests of URLs of enough support (numbered 0 to n - 1), the URL names of the numbers, and n."""

    raw: DataFrame
    cleaned: DataFrame
    accessed: DataFrame
    sessions: DataFrame
    supported: DataFrame
    names: DataFrame
    n: int

    def items(self) -> DataFrame:
        return features.profile_items(self.supported, user="user_key", session="session_id")

    def vectors(self, weight: str = "binary") -> DataFrame:
        """Sizes are those after pruning."""
        return features.vectorize(self.items(), weight, user="user_key")


def chain(spark: SparkSession, sf_dir: str, beta_us: int = DAY, rule: str = "gap", share: float = 0.95) -> Chain:
    """Log, cleaning, users, pruning by accesses, sessions, pruning by support, dense numbers. A URL stays if it has ``share``
    of the mean accesses, then of the mean support: the given logs have no URL of one access, so fixed limits would do nothing."""
    raw = weblog(spark, sf_dir)
    cleaned, urls = cleaning_ops.clean(raw)
    cleaned = cleaning_ops.identify_users(cleaned, "ip_agent", "ip_alias", "ua_alias")
    cleaned = settle(cleaned.select("user_key", "ts", "seq", "url_id", "bytes"), "cleaned")  # what the steps below read
    mean = cleaned.agg((F.count("*") / F.countDistinct("url_id")).alias("m")).first()["m"] or 0.0
    accessed = features.prune_urls(cleaned, share * mean)
    sessions = settle(sessionize.sessionize(accessed, rule, beta_us, user="user_key").drop("pos"), "sessions")
    support = settle(features.url_support(sessions), "support")
    mean = support.agg(F.avg("_n").alias("m")).first()["m"] or 0.0
    supported, numbers, n = features.number_urls(features.prune_support(sessions, share * mean, support=support))
    names = numbers.join(urls, "url_id").select("url", "number")
    return Chain(raw, cleaned, accessed, sessions, supported, names, n)


def chain_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """step, requests, urls, users, sessions: what is left after each step."""
    c, out = chain(spark, sf_dir), None
    raw = c.raw.select(F.col("url").alias("url_id"), F.concat_ws("|", "client_ip", "user_agent").alias("user_key"))
    for step, df in (("raw", raw), ("cleaned", c.cleaned), ("accessed", c.accessed), ("sessions", c.sessions), ("supported", c.supported)):
        sessions = F.countDistinct("session_id") if "session_id" in df.columns else F.lit(None).cast("long")
        row = df.agg(F.count("*").alias("requests"), F.countDistinct("url_id").alias("urls"), F.countDistinct("user_key").alias("users"), sessions.alias("sessions"))
        row = row.select(F.lit(step).alias("step"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def chain_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user_key, session_no, url, freq, n_urls, w: the vectors that clustering reads, with URL names, and the graded weights."""
    c = chain(spark, sf_dir)
    items = settle(features.profile_items(c.supported, user="user_key", session="session_no"), "items")
    sizes = items.groupBy("user_key", "session_no").agg(F.count("*").alias("n_urls"))
    named = items.join(c.names, items["url_id"] == c.names["number"]).select("user_key", "session_no", "url", "freq")
    return named.join(sizes, ["user_key", "session_no"]).withColumn("w", features.ramp_weight(F.col("n_urls")))


def chain_points(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    c = chain(spark, sf_dir)
    return clustering.spread(features.weighted_points(c.vectors())), max(c.n, 1)


def cluster_summary(spark: SparkSession, sf_dir: str, c: int = 4, q: float = 1.03) -> DataFrame:
    """cluster, sessions, weight, top_url, top_value: the chain's sessions, graded weights, weighted fuzzy c-means."""
    made = chain(spark, sf_dir)
    vectors = settle(made.vectors(), "vectors")
    points = settle(features.weighted_points(vectors), "points")
    different = points.limit(c).count()
    run = clustering.fcm(points, max(min(c, different), 1), max(made.n, 1), q)
    labelled = clustering.memberships(vectors, run.centres, q)
    heads = clustering.describe_clusters(run.centres, spark, top=1).join(F.broadcast(made.names), F.col("url_id") == F.col("number"), "left")
    heads = heads.select("cluster", F.col("url").alias("top_url"), F.round("value", 6).alias("top_value"))
    sizes = labelled.groupBy("cluster").agg(F.count("*").alias("sessions"), F.sum(features.ramp_weight(F.col("n_urls"))).alias("weight"))
    return sizes.join(F.broadcast(heads), "cluster")  # a row for each cluster


def chain_sweep(spark: SparkSession, sf_dir: str, counts=range(4, 61), q: float = 1.03, restarts: int = 1, max_iter: int = 40) -> DataFrame:
    """J and S for every count from 4 to 60, graded weights and none, on the chain's real URLs; runs that have not converged
    say so."""
    points, width = chain_points(spark, sf_dir)
    most = points.select("idx", "val").distinct().limit(max(counts)).count()
    return clustering.sweep_table(spark, clustering.sweep(points, [c for c in counts if c <= most], width, q, restarts=restarts, max_iter=max_iter))


def chain_best_c(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The count of least validity index among 4 to 60 for each weighting."""
    return clustering.select_c(chain_sweep(spark, sf_dir))


def document_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same counts with documents as sessions and their commonest words as URLs."""
    return count_sweep(spark, sf_dir, range(4, 61), max_iter=40, source="documents")


def count_sweep(spark: SparkSession, sf_dir: str, counts=range(4, 9), q: float = 1.2, urls: int = 10, restarts: int = 1, max_iter: int = 30, source: str = "events") -> DataFrame:
    """J and S for each cluster count, with graded weights and without, from the same starts."""
    if source == "documents":
        points, width = settle(features.weighted_points(document_vectors(spark, sf_dir)), "points"), 40
    elif source == "baskets":
        points, width = basket_points(spark, sf_dir), 25
    else:
        points, width = event_points(spark, sf_dir, urls), urls
    return clustering.sweep_table(spark, clustering.sweep(points, list(counts), width, q, restarts=restarts, max_iter=max_iter))


def full_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every count from 4 to 60 on the events table, URLs folded to ten coordinates, where centres stay apart for an exponent of
    1.2: 114 runs that share each pass."""
    return count_sweep(spark, sf_dir, range(4, 61), max_iter=30)


def shuffle_bytes(spark: SparkSession) -> int:
    """Bytes that the application's tasks have written for exchanges so far."""
    found = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(found.apply(i).totalShuffleWrite() for i in range(found.size()))


def run_stats(spark: SparkSession, sf_dir: str, counts=(4, 6, 8)) -> DataFrame:
    """c, iterations, seconds, seconds_per_pass, shuffle_bytes of fuzzy c-means runs that go alone."""
    points, rows = event_points(spark, sf_dir, 10), []
    for c in counts:
        began, sent = time.perf_counter(), shuffle_bytes(spark)
        run = clustering.fcm(points, c, 10, 1.2, max_iter=5)
        took = time.perf_counter() - began
        rows.append((c, run.iterations, took, took / (run.iterations + 1), shuffle_bytes(spark) - sent))
    return spark.createDataFrame(rows, "c int, iterations int, seconds double, seconds_per_pass double, shuffle_bytes long")


def hard_and_soft(spark: SparkSession, sf_dir: str, c: int = 4, q: float = 1.2, top: int = 40, min_urls: int = 40) -> DataFrame:
    """The three treatments of small sessions from the same start, documents as sessions: the sweep's measures, purity against
    the language, and what each treatment keeps (sessions, their share of weight, words that still occur)."""
    vectors = settle(document_vectors(spark, sf_dir, top), "vectors")
    points = settle(features.weighted_points(vectors, lb=10, ub=2 * min_urls, min_urls=min_urls), "points")
    v = clustering.starts(points, c, top, "farthest")
    runs = clustering.iterate(points, [clustering.Run(v.copy(), q, w, name=w) for w in ("soft", "hard", "none")], top)
    size, out = F.col("n_urls"), None
    for run in runs:
        w = {"soft": features.ramp_weight(size, 10, 2 * min_urls), "hard": features.step_weight(size, min_urls), "none": features.unit_weight()}[run.weighting]
        labelled = clustering.memberships(vectors, run.centres, q).withColumn("w", w)
        pure = measures.purity(labelled.where("w > 0"), label="lang").select("rows", F.round("purity", 6).alias("purity"))
        kept = labelled.where("w > 0").agg(F.sum("w").alias("weight"), F.size(F.array_distinct(F.flatten(F.collect_set("idx")))).alias("urls"))
        row = pure.crossJoin(F.broadcast(kept)).select(F.lit(run.name).alias("run"), F.col("rows").alias("sessions"), "purity", "weight", "urls")  # one row each
        out = row if out is None else out.unionByName(row)
    return clustering.sweep_table(spark, runs).join(F.broadcast(out), "run")


def crisp_and_fuzzy(spark: SparkSession, sf_dir: str, c: int = 4, urls: int = 10) -> DataFrame:
    """k-means and fuzzy c-means with the exponent going to 1, from the same start: q, j, gap to the k-means centres."""
    points = event_points(spark, sf_dir, urls)
    v = clustering.starts(points, c, urls, "farthest")
    runs = [clustering.Run(v.copy(), q, "none", name=str(q)) for q in (1.0, 1.02, 1.05, 1.1, 1.2, 1.5)]
    done = clustering.iterate(points, runs, urls)
    rows = [(r.q, r.j, float(np.abs(r.centres - done[0].centres).max()), r.iterations) for r in done]
    return spark.createDataFrame(rows, "q double, j double, gap double, iterations int")


def language_purity(spark: SparkSession, sf_dir: str, c: int = 4, q: float = 1.2, top: int = 40) -> DataFrame:
    """weighting, purity, s, j_per_weight of document clusters against their language."""
    vectors = settle(document_vectors(spark, sf_dir, top), "vectors")
    points = settle(features.weighted_points(vectors), "points")
    v = clustering.starts(points, c, top, "farthest")
    out = None
    for run in clustering.iterate(points, [clustering.Run(v.copy(), q, w) for w in ("soft", "none")], top):
        row = measures.purity(clustering.memberships(vectors, run.centres, q), label="lang").select(F.lit(run.weighting).alias("weighting"), "rows", F.round("purity", 6).alias("purity"), F.lit(run.validity).alias("s"), F.lit(run.j / run.mass).alias("j_per_weight"))
        out = row if out is None else out.unionByName(row)
    return out


def basket_clusters(spark: SparkSession, sf_dir: str, c: int = 5, q: float = 1.2, max_iter: int = 20) -> DataFrame:
    run = clustering.fcm(basket_points(spark, sf_dir), c, 25, q, max_iter=max_iter)
    return clustering.sweep_table(spark, [run])


def dense_points(spark: SparkSession, sf_dir: str, c: int = 4, q: float = 1.2) -> DataFrame:
    """The kernel on dense points: the embeddings table, every point of weight 1."""
    v = table(spark, sf_dir, "embeddings").where("embedding is not null")
    points = settle(v.select(F.sequence(F.lit(0), F.size("embedding") - 1).alias("idx"), F.col("embedding").cast("array<double>").alias("val"), F.lit(1.0).alias("mult"), F.lit(1.0).alias("none")), "points")
    width = points.agg(F.max(F.size("idx"))).first()[0] or 1
    run = clustering.fcm(points, c, width, q, "none", init="first", max_iter=20)
    return clustering.sweep_table(spark, [run])
