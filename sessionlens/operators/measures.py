"""Counts and measures that experiments report."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .features import ramp_weight, step_weight


def session_report(sizes: DataFrame) -> DataFrame:
    """sessions; least, greatest and mean requests; the same of different URLs. sizes: n_requests, n_urls a session."""
    return sizes.agg(
        F.count("*").alias("sessions"), F.min("n_requests").alias("min_requests"), F.max("n_requests").alias("max_requests"), F.avg("n_requests").alias("mean_requests"),
        F.min("n_urls").alias("min_urls"), F.max("n_urls").alias("max_urls"), F.avg("n_urls").alias("mean_urls"),
    )


def session_sizes(sessions: DataFrame, user: str = "user_id", no: str = "session_no", url: str = "url_id") -> DataFrame:
    """user, session number, n_requests, n_urls: two steps of one exchange by user, no distinct."""
    each = sessions.groupBy(user, no, url).agg(F.count("*").alias("_n"))
    return each.groupBy(user, no).agg(F.sum("_n").alias("n_requests"), F.count("*").alias("n_urls"))


def histogram(df: DataFrame, key: list[str], value: str = "accesses", out: str = "urls") -> DataFrame:
    """How many keys have each number of rows."""
    return df.groupBy(*key).agg(F.count("*").alias(value)).groupBy(value).agg(F.count("*").alias(out))


def access_report(df: DataFrame, key: list[str]) -> DataFrame:
    """urls, shares accessed once, twice and more, max and mean accesses."""
    n = df.groupBy(*key).agg(F.count("*").alias("n"))
    share = lambda c: F.avg(F.when(c, 1.0).otherwise(0.0))
    return n.agg(
        F.count("*").alias("urls"), share(F.col("n") == 1).alias("once"), share(F.col("n") == 2).alias("twice"), share(F.col("n") >= 3).alias("more"),
        F.max("n").alias("max_accesses"), F.avg("n").alias("mean_accesses"),
    )


def support_histogram(sessions: DataFrame, session: list[str], url: str = "url_id") -> DataFrame:
    """support, urls: how many URLs stand in so many sessions."""
    return histogram(sessions.select(url, *session).distinct(), [url], "support", "urls")


def size_histogram(sizes: DataFrame) -> DataFrame:
    return sizes.groupBy("n_urls").agg(F.count("*").alias("sessions"))


def weight_table(sizes: DataFrame, lb: int = 1, ub: int = 6) -> DataFrame:
    """n_urls, weight, sessions, total: what each session size weighs."""
    w = ramp_weight(F.col("n_urls"), lb, ub)
    return sizes.groupBy("n_urls").agg(F.count("*").alias("sessions")).select("n_urls", w.alias("weight"), "sessions", (w * F.col("sessions")).alias("total"))


def retention_report(items: DataFrame, lb: int = 1, ub: int = 6, min_urls: int = 2, session: list[str] | None = None) -> DataFrame:
    """treatment, sessions, requests, urls, weight: what each treatment of short sessions keeps. items: a row for each URL
    of a session, with freq."""
    session = session or ["user_id", "session_no"]
    whole = Window.partitionBy(*session)
    sized = items.withColumn("n_urls", F.count("*").over(whole))
    weights = (("none", F.lit(1.0)), ("hard", step_weight(F.col("n_urls"), min_urls)), ("soft", ramp_weight(F.col("n_urls"), lb, ub)))
    each = sized.select("url_id", "freq", "n_urls", F.inline(F.array(*(F.struct(F.lit(name).alias("treatment"), w.alias("w")) for name, w in weights)))).where("w > 0")
    # by URL first, so that URLs are counted without a distinct of all rows
    by_url = each.groupBy("treatment", "url_id").agg(F.sum("freq").alias("requests"), F.sum(F.col("w") / F.col("n_urls")).alias("weight"), F.sum(1 / F.col("n_urls")).alias("s"))
    kept = by_url.groupBy("treatment").agg(F.round(F.sum("s")).cast("long").alias("sessions"), F.sum("requests").alias("requests"), F.count("*").alias("urls"), F.sum("weight").alias("weight"))
    names = items.sparkSession.createDataFrame([(name,) for name, _ in weights], "treatment string")
    out = names.join(F.broadcast(kept), "treatment", "left")  # three rows
    return out.select("treatment", *(F.coalesce(c, F.lit(0).cast("long")).alias(c) for c in ("sessions", "requests", "urls")), F.coalesce("weight", F.lit(0.0)).alias("weight"))


def purity(labelled: DataFrame, cluster: str = "cluster", label: str = "label") -> DataFrame:
    """rows, purity: the share of rows whose label is the commonest of their cluster."""
    n = labelled.groupBy(cluster, label).agg(F.count("*").alias("n"))
    top = n.groupBy(cluster).agg(F.max("n").alias("top"), F.sum("n").alias("all"))
    return top.agg(F.sum("all").alias("rows"), (F.sum("top") / F.sum("all")).alias("purity"))
