"""Cleaning of raw logs and identification of users."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.stage import settle

#: Suffixes of embedded files (case is ignored), and those of styles, scripts and sounds as an extension.
SUFFIXES = ("gif", "jpeg", "jpg", "map")
MORE_SUFFIXES = ("css", "js", "png", "ico", "svg", "bmp", "wav", "mp3", "au", "mid")
ROBOTS = ("crawler",)


def strip_query(url: Column | str, fragment: bool = True) -> Column:
    """The URL without its query part, and without its fragment unless that is to stay."""
    url = F.col(url) if isinstance(url, str) else url
    return F.regexp_replace(url, r"[?#].*$", "") if fragment else F.regexp_replace(url, r"\?[^#]*", "")


def suffix_of(url: Column | str) -> Column:
    """What follows the last dot of the last path segment, in lower case."""
    url = F.col(url) if isinstance(url, str) else url
    return F.lower(F.regexp_extract(url, r"\.([A-Za-z0-9]+)$", 1))


def drop_embedded(log: DataFrame, suffixes: Sequence[str] = SUFFIXES, url: str = "url") -> DataFrame:
    """Goes after ``strip_query``: a suffix in front of a query is seen only then. A record without URL has no suffix and
    stays."""
    return log.where(~F.coalesce(suffix_of(url).isin([s.lower() for s in suffixes]), F.lit(False)))


def drop_robots(log: DataFrame, agents: Sequence[str] | DataFrame = ROBOTS, agent: str = "user_agent") -> DataFrame:
    """Removes requests of listed agents. A list that is a table (one column) is joined, so that it may have any size."""
    if isinstance(agents, DataFrame):
        named = agents.toDF("_agent").distinct()
        return log.join(named, log[agent] == named["_agent"], "left_anti")
    return log.where(~F.coalesce(F.col(agent).isin(list(agents)), F.lit(False)))


def drop_robots_like(log: DataFrame, pattern: str, agent: str = "user_agent") -> DataFrame:
    """Removes requests of agents that a regular expression matches; a record without agent stays."""
    return log.where(~F.coalesce(F.col(agent).rlike(pattern), F.lit(False)))


def robot_suspects(log: DataFrame, coverage: float = 1.0, by: Sequence[str] = ("client_ip", "user_agent")) -> DataFrame:
    """Clients that request at least ``coverage`` of all the site's URLs: by, urls, site_urls."""
    site = log.agg(F.countDistinct("url").alias("site_urls"))
    each = log.groupBy(*by).agg(F.countDistinct("url").alias("urls"))
    return each.crossJoin(F.broadcast(site)).where(F.col("urls") >= F.col("site_urls") * coverage)  # one row


def pseudonymize(log: DataFrame, key: str, column: str = "client_ip", out: str = "ip_alias") -> DataFrame:
    """A keyed digest in place of an address; without state, so any number of tasks agree on it."""
    return log.withColumn(out, F.sha2(F.concat_ws("\u0000", F.lit(key), F.col(column)), 256))


def dictionary(log: DataFrame, column: str, out: str, order: str = "sorted", first: tuple[str, ...] = ("ts", "seq")) -> DataFrame:
    """column, out: a number for each value. 'sorted': from 1 in the values' order; 'first_seen': from 1 in the order of first
    requests; 'hash': a 64-bit hash, which needs no order and suits any number of values.

    Numbers without gaps are counted in two steps: ranks inside ranges of the order, and offsets of the ranges. The ranges
    are written once, so both steps read the same ones whatever the optimizer reuses.
    """
    if order == "hash":
        return log.select(column).where(F.col(column).isNotNull()).distinct().withColumn(out, F.xxhash64(column))
    each = log.where(F.col(column).isNotNull()).groupBy(column).agg(F.min(F.struct(*first)).alias("_f") if order == "first_seen" else F.lit(0).alias("_f"))
    keys = ["_f", column] if order == "first_seen" else [column]
    width = int(log.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = settle(each.repartitionByRange(width, *keys).withColumn("_p", F.spark_partition_id()), "dictionary")
    counts = dealt.groupBy("_p").agg(F.count("*").alias("_n"))
    before = counts.select("_p", (F.sum("_n").over(Window.orderBy("_p")) - F.col("_n")).alias("_before"))  # a row for each range
    inside = dealt.withColumn("_r", F.row_number().over(Window.partitionBy("_p").orderBy(*keys)))
    return inside.join(F.broadcast(before), "_p").select(column, (F.col("_before") + F.col("_r")).alias(out))


def encode(log: DataFrame, column: str, out: str, order: str = "sorted") -> tuple[DataFrame, DataFrame]:
    """The log with the number of each value, and the dictionary."""
    if order == "hash":
        return log.withColumn(out, F.xxhash64(column)), dictionary(log, column, out, order)
    numbers = dictionary(log, column, out, order)
    return log.join(numbers, column, "left"), numbers


def identify_users(log: DataFrame, policy: str = "ip_agent", ip: str = "client_ip", agent: str = "user_agent") -> DataFrame:
    """Adds user_key. 'login', 'ip', 'ip_agent', or 'auto': the login, else address and agent."""
    pair = F.concat_ws("|", F.col(ip), F.col(agent))
    keys = {"login": F.col("login") if "login" in log.columns else F.lit(None), "ip": F.col(ip), "ip_agent": pair}
    keys["auto"] = F.coalesce(keys["login"], pair)
    return log.withColumn("user_key", keys[policy])


def user_histories(log: DataFrame, user: str = "user_key", ts: str = "ts", seq: str = "seq", nested: bool = False) -> DataFrame:
    """Requests user by user in time order, those of one instant in arrival order: flat with pos, or one array a user."""
    if nested:
        rest = [c for c in log.columns if c not in (user, ts, seq)]
        return log.groupBy(user).agg(F.sort_array(F.collect_list(F.struct(ts, seq, *rest))).alias("requests"))
    return log.withColumn("pos", F.row_number().over(Window.partitionBy(user).orderBy(ts, seq)))


def clean(log: DataFrame, suffixes: Sequence[str] = SUFFIXES, agents: Sequence[str] | DataFrame = ROBOTS, key: str = "alias", order: str = "hash") -> tuple[DataFrame, DataFrame]:
    """The whole cleaning in one pass over the log and one for the URL numbers: ts, ip_alias, ua_alias, elapsed_ms, bytes,
    url_id, seq; and the URL dictionary (url, url_id). Records without URL name no page and go; ``cleaning_report`` counts
    them. Numbers by 'hash' have gaps: ``features.number_urls`` makes them dense once URLs are pruned."""
    kept = drop_robots(drop_embedded(log.withColumn("url", strip_query("url")), suffixes), agents).where("url is not null")
    numbered, urls = encode(kept, "url", "url_id", order)
    hidden = pseudonymize(numbered, key).withColumn("ua_alias", F.sha2("user_agent", 256))
    return hidden.select("ts", "ip_alias", "ua_alias", "elapsed_ms", "bytes", "url_id", "seq"), urls


def cleaning_report(log: DataFrame, suffixes: Sequence[str] = SUFFIXES, agents: Sequence[str] = ROBOTS) -> DataFrame:
    """raw, no_url (records without URL, which go), cleaned, site_urls (accessed five times or more), urls, users: one scan,
    then one exchange by URL and user."""
    kept = F.col("url").isNotNull() & ~F.coalesce(suffix_of(strip_query("url")).isin(list(suffixes)), F.lit(False)) & ~F.coalesce(F.col("user_agent").isin(list(agents)), F.lit(False))
    marked = log.select(strip_query("url").alias("url"), "client_ip", "user_agent", kept.alias("kept"))
    totals = marked.agg(F.count("*").alias("raw"), F.count_if(F.col("url").isNull()).alias("no_url"), F.count_if("kept").alias("cleaned"), F.countDistinct(F.when(F.col("kept"), F.concat_ws("|", "client_ip", "user_agent"))).alias("users"))
    urls = marked.where("kept").groupBy("url").agg(F.count("*").alias("n")).agg(F.count_if(F.col("n") >= 5).alias("site_urls"), F.count("*").alias("urls"))
    return totals.crossJoin(F.broadcast(urls))  # one row each
