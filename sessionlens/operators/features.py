"""Session profiles, feature choice, feature values, session weights, and the points that clustering reads."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.stage import settle
from .cleaning import dictionary


# ---- which URLs take part
def prune_urls(requests: DataFrame, min_access: int = 2, url: str = "url_id") -> DataFrame:
    """Requests of URLs that are accessed so often in all. The surviving URLs are joined by value; Spark broadcasts them
    only where their measured size allows."""
    kept = requests.groupBy(url).agg(F.count("*").alias("_n")).where(F.col("_n") >= min_access).select(url)
    return requests.join(kept, url, "left_semi")


def url_support(sessions: DataFrame, url: str = "url_id", session: str = "session_id") -> DataFrame:
    """url, _n: in how many different sessions it stands."""
    return sessions.select(url, session).distinct().groupBy(url).agg(F.count("*").alias("_n"))


def prune_support(sessions: DataFrame, min_support: int = 2, url: str = "url_id", session: str = "session_id", support: DataFrame | None = None) -> DataFrame:
    """Requests of URLs that stand in so many different sessions. support: what ``url_support`` gave, if it is known."""
    kept = (url_support(sessions, url, session) if support is None else support).where(F.col("_n") >= min_support).select(url)
    return sessions.join(kept, url, "left_semi")


def number_urls(requests: DataFrame, url: str = "url_id") -> tuple[DataFrame, DataFrame, int]:
    """The requests with their URLs numbered 0 to n - 1 without gaps, as vectors need them; the table (url, number); and n.
    Goes after pruning, so n is the dimension of the vectors."""
    numbers = dictionary(requests.select(F.col(url).alias("_u")), "_u", "_n").withColumn("_n", F.col("_n") - 1)
    numbers = settle(numbers, "url-numbers")
    kept = requests.join(numbers, requests[url] == numbers["_u"]).drop("_u", url).withColumnRenamed("_n", url)
    return kept, numbers.select(F.col("_u").alias(url), F.col("_n").alias("number")), numbers.count()


def url_weights(requests: DataFrame, lb: int, ub: int, url: str = "url_id") -> DataFrame:
    """url, accesses, weight: a ramp over how often a URL is accessed, in place of a hard limit."""
    return requests.groupBy(url).agg(F.count("*").alias("accesses")).withColumn("weight", ramp_weight(F.col("accesses"), lb, ub))


# ---- how much a session counts
def ramp_weight(size: Column, lb: int = 1, ub: int = 6) -> Column:
    """0 up to lb, 1 from ub, linear between. Equal bounds make a step: 1 above them."""
    if lb > ub:
        raise ValueError("the lower bound is above the upper one")
    if lb == ub:
        return F.when(size > lb, 1.0).otherwise(0.0)
    return F.when(size <= lb, 0.0).when(size >= ub, 1.0).otherwise((size - lb) / F.lit(float(ub - lb)))


def step_weight(size: Column, min_urls: int, inclusive: bool = True) -> Column:
    """Hard removal: 1 for sessions that stay."""
    return F.when((size >= min_urls) if inclusive else (size > min_urls), 1.0).otherwise(0.0)


def unit_weight() -> Column:
    return F.lit(1.0)


# ---- profiles and feature values
def profile_items(sessions: DataFrame, last: str = "zero", user: str = "user_id", session: str = "session_id") -> DataFrame:
    """user, session, url_id, freq, bytes, dwell_s, start_ts, end_ts (its first and last request): one row for each URL of a
    session.

    Page time lasts until the session's next request; the last page has none: 'zero', the session's 'mean', or its
    'elapsed' time. The user stays in the grouping keys, so no exchange follows the one by user.
    """
    w = Window.partitionBy(user, session).orderBy("ts", "seq")
    whole = Window.partitionBy(user, session)
    stay = (F.lead(F.unix_micros("ts")).over(w) - F.unix_micros("ts")) / 1e6
    timed = sessions.withColumn("_stay", stay)
    tail = {"zero": F.lit(0.0), "mean": F.coalesce(F.avg("_stay").over(whole), F.lit(0.0)), "elapsed": F.col("elapsed_ms") / 1000.0 if "elapsed_ms" in sessions.columns else F.lit(0.0)}[last]
    timed = timed.withColumn("_stay", F.coalesce("_stay", tail))
    return timed.groupBy(user, session, "url_id").agg(F.count("*").alias("freq"), F.sum("bytes").alias("bytes"), F.sum("_stay").alias("dwell_s"), F.min("ts").alias("start_ts"), F.max("ts").alias("end_ts"))


def profile_sessions(sessions: DataFrame, user: str = "user_id", session: str = "session_id") -> DataFrame:
    """user, session, items (url_id, freq, bytes, dwell_s; by url_id), n_urls, n_requests, start_ts, end_ts."""
    items = profile_items(sessions, user=user, session=session)
    each = items.groupBy(user, session).agg(
        F.sort_array(F.collect_list(F.struct("url_id", "freq", "bytes", "dwell_s"))).alias("items"), F.count("*").alias("n_urls"), F.sum("freq").alias("n_requests"), F.min("start_ts").alias("start_ts"), F.max("end_ts").alias("end_ts")
    )
    return each


def value(weight: str = "binary", scale: str = "none", session: str = "session_id", user: str = "user_id") -> Column:
    """The feature value of a profile item. weight: binary, frequency, dwell or bytes; scale: none, log1p, max or l2, the
    latter two over the session."""
    raw = {"binary": F.lit(1.0), "frequency": F.col("freq").cast("double"), "dwell": F.col("dwell_s"), "bytes": F.col("bytes").cast("double")}[weight]
    over = Window.partitionBy(user, session)
    if scale == "log1p":
        return F.log1p(raw)
    if scale == "max":
        return F.coalesce(F.try_divide(raw, F.max(F.abs(raw)).over(over)), F.lit(0.0))
    if scale == "l2":
        return F.coalesce(F.try_divide(raw, F.sqrt(F.sum(raw * raw).over(over))), F.lit(0.0))
    return raw


def vectorize(items: DataFrame, weight: str = "binary", scale: str = "none", user: str = "user_id", session: str = "session_id") -> DataFrame:
    """session, idx, val, n_urls, n_requests: sparse vectors, coordinates ascending. URLs must be numbered from 0 without gaps
    (``number_urls``); a number that no int holds raises an error."""
    each = items.withColumn("_v", value(weight, scale, session, user)).groupBy(user, session).agg(F.sort_array(F.collect_list(F.struct("url_id", "_v"))).alias("p"), F.count("*").alias("n_urls"), F.sum("freq").alias("n_requests"))
    return each.select(session, F.col("p.url_id").cast("array<int>").alias("idx"), F.col("p._v").alias("val"), "n_urls", "n_requests")


def weighted_points(vectors: DataFrame, size: str = "n_urls", lb: int = 1, ub: int = 6, min_urls: int = 2) -> DataFrame:
    """idx, val, mult, soft, hard, none: equal vectors folded to one point, which is exact, since equal points have equal
    memberships. mult: sessions in it; soft, hard, none: their summed weights under the three treatments."""
    s = F.col(size)
    each = vectors.select("idx", "val", ramp_weight(s, lb, ub).alias("soft"), step_weight(s, min_urls).alias("hard"))
    return each.groupBy("idx", "val").agg(F.count("*").cast("double").alias("mult"), F.sum("soft").alias("soft"), F.sum("hard").alias("hard")).withColumn("none", F.col("mult"))


def basket_points(lines: DataFrame, session: str, url: str, lb: int = 1, ub: int = 6, min_urls: int = 2) -> DataFrame:
    """Points of plain transactions: rows (session, url number), repeated URLs counted once."""
    each = lines.select(session, url).distinct().groupBy(session).agg(F.sort_array(F.collect_list(F.col(url).cast("int"))).alias("idx"))
    return weighted_points(each.select("idx", F.transform("idx", lambda _: F.lit(1.0)).alias("val"), F.size("idx").alias("n_urls")), "n_urls", lb, ub, min_urls)
