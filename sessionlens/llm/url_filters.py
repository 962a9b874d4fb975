"""URL filters by a temporal list join: dated entries become validity intervals, and every capture is held against the
entries that were active when it was fetched."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

def host_of(url: Column) -> Column:
    """The host in lower case, without user, port and trailing dot; null where there is none."""
    host = F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?(\[[^\]]*\]|[^/?#:]*)", 1)
    return F.nullif(F.lower(F.rtrim(host, F.lit("."))), F.lit(""))


def intervals(entries: DataFrame) -> DataFrame:
    """list, pattern, since, until: entries (list, pattern, action add or remove, at) as validity intervals.

    An entry holds until the next one of the same list and pattern. Of entries at one time the removal comes last.
    since is included, until is not; null: open. Entries with a null field are left out.
    """
    known = entries.where("list is not null and pattern is not null and action is not null and at is not null").select("list", "pattern", "action", "at").distinct()
    ahead = F.lead("at").over(Window.partitionBy("list", "pattern").orderBy("at", "action"))
    return known.withColumn("until", ahead).where("action = 'add' and (until is null or until > at)").select("list", "pattern", F.col("at").alias("since"), "until")


def patterns_of(url: Column, depth: int, labels_least: int = 1) -> Column:
    """The patterns that cover a URL: its host, each parent domain as '.domain' of ``labels_least`` labels or more, and host
    plus its first path segments, up to ``depth``."""
    host = host_of(url)
    labels = F.split(host, r"\.")
    parents = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.when(F.size(labels) - i + 1 >= labels_least, F.concat(F.lit("."), F.array_join(F.slice(labels, i, F.size(labels)), "."))))
    path = F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)", 1)
    steps = F.filter(F.split(path, "/"), lambda s: s != "")
    deep = F.transform(F.sequence(F.lit(0), F.least(F.size(steps), F.lit(depth))), lambda i: F.when(i > 0, F.concat(host, F.lit("/"), F.array_join(F.slice(steps, F.lit(1), i), "/"))))
    return F.when(host.isNotNull(), F.array_compact(F.concat(F.array(host), parents, deep)))


def evaluate(captures: DataFrame, entries: DataFrame, url: str = "url", at: str = "fetched_at") -> DataFrame:
    """Adds lists (sorted names of the lists with an entry active at the fetch) and blocked to every capture.

    A null or unreadable URL or a null time meets no entry. Verdicts are made once for each different URL and time, so
    repeated captures cost one join row; the join is on the pattern, with the interval as a further condition. How deep paths
    and how short domains are asked for follows from the entries, so none is out of reach and no capture asks for the likes
    of '.com' unless an entry has it.
    """
    captures = captures.drop("lists", "blocked")
    each = captures.select(F.col(url).alias("_u"), F.col(at).alias("_t")).where("_u is not null and _t is not null").distinct()
    valid = intervals(entries)
    steps = F.when(~F.startswith("pattern", F.lit(".")), F.size(F.split("pattern", "/")) - 1)
    labels = F.when(F.startswith("pattern", F.lit(".")), F.size(F.split("pattern", r"\.")) - 1)
    reach = valid.agg(F.max(steps).alias("depth"), F.min(labels).alias("labels")).first()
    asked = each.select("_u", "_t", F.explode(patterns_of(F.col("_u"), reach["depth"] or 0, reach["labels"] or 1 << 20)).alias("pattern"))
    active = asked.join(valid, (asked["pattern"] == valid["pattern"]) & (F.col("since") <= F.col("_t")) & (F.col("until").isNull() | (F.col("_t") < F.col("until"))))
    verdicts = active.groupBy("_u", "_t").agg(F.sort_array(F.collect_set("list")).alias("lists"))
    out = captures.join(verdicts, (F.col(url) == F.col("_u")) & (F.col(at) == F.col("_t")), "left").drop("_u", "_t")
    out = out.withColumn("lists", F.coalesce("lists", F.array().cast("array<string>")))
    return out.withColumn("blocked", F.size("lists") > 0)
