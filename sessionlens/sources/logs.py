"""Logs: reading, parsing, merging, writing, and the rendering of the given tables as logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A record of an extended common log line.
LOG_RECORD = T.StructType([
    T.StructField("ts", T.TimestampType()), T.StructField("elapsed_ms", T.LongType()), T.StructField("client_ip", T.StringType()),
    T.StructField("cache_result", T.StringType()), T.StructField("status", T.IntegerType()), T.StructField("bytes", T.LongType()),
    T.StructField("method", T.StringType()), T.StructField("url", T.StringType()), T.StructField("login", T.StringType()),
    T.StructField("origin", T.StringType()), T.StructField("content_type", T.StringType()), T.StructField("user_agent", T.StringType()),
])
EVENT = T.StructType().add("event_id", "long").add("ts", "timestamp_ntz").add("user_id", "long").add("event_type", "string").add("value", "double").add("props", "string")

#: time elapsed ip cache/status bytes method url login origin [type [agent]]; the URL may be missing.
_LINE = r"^(\d+(?:\.\d{1,6})?)\s+(\d+)\s+(\S+)\s+([A-Z_]+)/(\d{3})\s+(\d+)\s+([A-Z]+)(?:\s+(?!-(?:\s|$))(\S+))?\s+(-|\S+)\s+([A-Z_]+/\S+|-)(?:\s+(-|[\w.+-]+/[\w.+-]+)(?=\s|$))?(?:\s+(\S.*))?$"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_log_text(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path)


def read_delimited(spark: SparkSession, path: str, schema: T.StructType, kind: str = "csv", bad: str = "_bad") -> DataFrame:
    """CSV or JSON lines with a stated schema; what doesn't fit is kept in the column ``bad``."""
    full = T.StructType([*schema.fields, T.StructField(bad, T.StringType())])
    reader = spark.read.schema(full).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", bad)
    return reader.option("header", True).csv(path) if kind == "csv" else reader.json(path)


def parse_log(lines: DataFrame, line: str = "value") -> tuple[DataFrame, DataFrame]:
    """Records and rejected lines. A dash is a null login or type. Times are seconds since the epoch with a fraction."""
    part = lambda i: F.nullif(F.regexp_extract(line, _LINE, i), F.lit(""))
    dash = lambda i: F.nullif(part(i), F.lit("-"))
    known = F.col(line).rlike(_LINE)
    micros = (part(1).cast("decimal(20,6)") * 1_000_000).cast("long")
    fields = {
        "ts": F.timestamp_micros(micros), "elapsed_ms": part(2).cast("long"), "client_ip": part(3), "cache_result": part(4), "status": part(5).cast("int"), "bytes": part(6).cast("long"),
        "method": part(7), "url": part(8), "login": dash(9), "origin": dash(10), "content_type": dash(11), "user_agent": part(12),
    }
    return lines.where(known).select(*(c.alias(n) for n, c in fields.items())), lines.where(~F.coalesce(known, F.lit(False)))


def render_log(records: DataFrame) -> DataFrame:
    """Lines (column value) that ``parse_log`` reads back."""
    micros = F.unix_micros("ts")
    time = F.concat(F.floor(micros / 1_000_000).cast("string"), F.lit("."), F.lpad((micros % 1_000_000).cast("string"), 6, "0"))
    dash = lambda c: F.coalesce(F.col(c), F.lit("-"))
    return records.select(F.concat_ws(" ", time, "elapsed_ms", "client_ip", F.concat(F.coalesce("cache_result", F.lit("MISS")), F.lit("/"), F.col("status").cast("string")), "bytes", "method", "url", dash("login"), dash("origin"), dash("content_type"), "user_agent").alias("value"))


def fuse_logs(logs: list[DataFrame], offsets_ms: list[int] | None = None) -> DataFrame:
    """One log of several servers' logs, clocks corrected: the offset of a log is added to its times."""
    out = None
    for i, log in enumerate(logs):
        if offsets_ms:
            log = log.withColumn("ts", F.timestamp_micros(F.unix_micros("ts") + offsets_ms[i] * 1000))
        out = log if out is None else out.unionByName(log, allowMissingColumns=True)
    return out


def events_requests(spark: SparkSession, sf_dir: str, urls: int | None = None) -> DataFrame:
    """user_id, ts, seq, url_id, bytes, event_type of the events table; urls: fold the URL numbers to so many."""
    k = F.get_json_object("props", "$.k").cast("int")
    return table(spark, sf_dir, "events").select(
        "user_id", F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("seq"), (k % urls if urls else k).alias("url_id"), F.round(F.col("value") * 100).cast("long").alias("bytes"), "event_type"
    )


def order_requests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user_id, ts, seq of the orders table: a customer's orders as requests."""
    return table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").cast("timestamp").alias("ts"), F.col("o_orderkey").alias("seq"))


def weblog(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events and pages tables as a raw log with companions: every fifth request brings an image, some users are robots,
    and two users share an address."""
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    n = pages.count()
    user = F.col("user_id")
    base = table(spark, sf_dir, "events").withColumn("page_id", F.get_json_object("props", "$.k").cast("long") % n).join(pages, "page_id")
    half = F.floor(user / 2)
    common = [
        F.col("ts").cast("timestamp").alias("ts"), F.round(F.col("value") * 10).cast("long").alias("elapsed_ms"),
        F.concat(F.lit("10.0."), F.floor(half / 256).cast("string"), F.lit("."), (half % 256).cast("string")).alias("client_ip"),
        F.when(user % 17 == 0, "crawler").otherwise(F.concat(F.lit("UA"), (user % 3).cast("string"))).alias("user_agent"),
        F.when(F.col("event_type") == "error", 500).otherwise(200).alias("status"), F.round(F.col("value") * 100).cast("long").alias("bytes"),
        F.when(F.col("event_type").isin("signup", "purchase"), "POST").otherwise("GET").alias("method"), F.lit(None).cast("string").alias("login"), F.lit(None).cast("string").alias("content_type"),
    ]
    image = F.concat(F.rtrim(F.regexp_replace("url", r"[?#].*$", ""), F.lit("/")), F.lit(".GIF?v="), F.col("event_id").cast("string"))
    both = F.array(F.struct((F.col("event_id") * 2).alias("seq"), F.col("url").alias("u")), F.struct((F.col("event_id") * 2 + 1).alias("seq"), F.when(F.col("event_id") % 5 == 0, image).alias("u")))
    return base.select(*common, F.explode(both).alias("r"), "event_id").where("r.u is not null").select(*[F.col(c) for c in ("ts", "elapsed_ms", "client_ip", "user_agent", "status", "bytes", "method", "login", "content_type")], F.col("r.seq").alias("seq"), F.col("r.u").alias("url"))


def write_by_date(df: DataFrame, path: str, ts: str = "ts") -> None:
    df.withColumn("date", F.to_date(ts)).repartition("date").write.mode("overwrite").partitionBy("date").parquet(path)


def write_histories(df: DataFrame, name: str, buckets: int = 64) -> None:
    """A table bucketed and sorted by user, so that sessionizing and joins by user need no further exchange."""
    df.write.mode("overwrite").bucketBy(buckets, "user_id").sortBy("user_id", "ts", "seq").format("parquet").saveAsTable(name)


def write_stage_text(df: DataFrame, path: str, zone: str = "UTC") -> None:
    """Tab-separated text with 14-digit times, one line a row."""
    shown = [F.date_format(F.from_utc_timestamp(c, zone), "yyyyMMddHHmmss") if t == "timestamp" else F.col(c).cast("string") for c, t in df.dtypes]
    df.select(F.concat_ws("\t", *shown)).write.mode("overwrite").text(path)
