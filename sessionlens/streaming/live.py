"""The methods on streams: stateless cleaning, windows, sessions by both rules, weights, scores by fixed centres and their drift."""

from __future__ import annotations

import json
from collections.abc import Iterator
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..operators.cleaning import ROBOTS, SUFFIXES, drop_embedded, drop_robots, strip_query
from ..operators.clustering import membership, memberships
from ..operators.features import ramp_weight
from ..plans.stage import shared
from ..sources.logs import EVENT, table

FLUSH = "2100-01-01 00:00:00"


def requests_stream(spark: SparkSession, folder: str, per_trigger: int = 100, watermark: str = "1 hour") -> DataFrame:
    """user_id, ts, seq, url_id, event_type of event files in a folder. Zoneless times become instants first: a watermark
    takes no others."""
    raw = spark.readStream.schema(EVENT).option("maxFilesPerTrigger", per_trigger).parquet(folder)
    k = F.get_json_object("props", "$.k").cast("int").alias("url_id")
    return raw.select("user_id", F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("seq"), k, "event_type", "value").withWatermark("ts", watermark)


def tumbling(stream: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """start, event_type, hits of windows; with ``slide`` they overlap."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.groupBy(w, "event_type").agg(F.count("*").alias("hits")).select(F.col("window.start").alias("start"), "event_type", "hits")


def gap_sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """user_id, start, requests of page-stay sessions; a pause of exactly the gap still joins."""
    return stream.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("requests")).select("user_id", F.col("session_window.start").alias("start"), "requests")


class DurationSessions(StatefulProcessor):
    """Total-duration sessions of a user. Requests wait, sorted, until the watermark has passed them; then the rule is run
    over them in order. A session is given out when the watermark has passed its end."""

    def __init__(self, beta_us: int):
        self.beta = beta_us

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.waiting = handle.getListState("waiting", "us long")

    def _set(self, us: list[int]) -> None:
        self.waiting.clear()
        if us:
            self.waiting.put([(t,) for t in us])
        for t in list(self.handle.listTimers()):
            self.handle.deleteTimer(t)
        if us:
            self.handle.registerTimer((us[0] + self.beta) // 1000 + 1)

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timerValues: Any) -> Iterator[pd.DataFrame]:
        us = [r[0] for r in self.waiting.get()] if self.waiting.exists() else []
        for pdf in rows:
            us += pdf["us"].astype("int64").tolist()
        yield from self._close(key, sorted(us), timerValues.getCurrentWatermarkInMs())

    def handleExpiredTimer(self, key: Any, timerValues: Any, expiredTimerInfo: Any) -> Iterator[pd.DataFrame]:
        us = sorted(r[0] for r in self.waiting.get()) if self.waiting.exists() else []
        yield from self._close(key, us, timerValues.getCurrentWatermarkInMs())

    def _close(self, key: Any, us: list[int], watermark_ms: int) -> Iterator[pd.DataFrame]:
        out = []
        while us and (us[0] + self.beta) // 1000 < watermark_ms:
            inside = int(np.searchsorted(us, us[0] + self.beta, side="right"))
            out.append((key[0], pd.Timestamp(us[0], unit="us"), inside))
            us = us[inside:]
        self._set(us)
        if out:
            yield pd.DataFrame(out, columns=["user_id", "start", "requests"])

    def close(self) -> None:
        pass


def duration_sessions(stream: DataFrame, beta_us: int) -> DataFrame:
    """user_id, start, requests of total-duration sessions."""
    given = stream.select("user_id", "ts", F.unix_micros("ts").alias("us"))
    return given.groupBy("user_id").transformWithStateInPandas(DurationSessions(beta_us), "user_id long, start timestamp, requests long", "append", "eventtime")


def deduplicated(stream: DataFrame, key: str = "seq") -> DataFrame:
    return stream.dropDuplicatesWithinWatermark([key])


def named(stream: DataFrame, urls: DataFrame) -> DataFrame:
    """Requests with the names of their URLs: a stream joined with a table."""
    return stream.join(urls, "url_id", "left")


def purchases_after_views(views: DataFrame, purchases: DataFrame, within: str = "1 day") -> DataFrame:
    """user_id, view_ts, buy_ts: two streams joined where a user buys within so long of a view."""
    v = views.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("view_ts"))
    p = purchases.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("buy_ts"))
    return p.join(v, F.expr(f"user_id = u AND buy_ts >= view_ts AND buy_ts <= view_ts + INTERVAL {within}")).select("user_id", "view_ts", "buy_ts")


def weigh_sessions(stream: DataFrame, gap: str = "30 minutes", lb: int = 1, ub: int = 6) -> DataFrame:
    """user_id, start, n_urls, weight of closed sessions."""
    each = stream.groupBy(F.session_window("ts", gap), "user_id").agg(F.size(F.collect_set("url_id")).alias("n_urls"))
    return each.select("user_id", F.col("session_window.start").alias("start"), "n_urls", ramp_weight(F.col("n_urls"), lb, ub).alias("weight"))


def cleaned(log: DataFrame, suffixes=SUFFIXES, agents=ROBOTS) -> DataFrame:
    """A stream of log records cleaned as they arrive: query parts, embedded files and listed robots go. It holds no state."""
    return drop_robots(drop_embedded(log.withColumn("url", strip_query("url")), suffixes), agents)


def session_vectors(stream: DataFrame, width: int, gap: str = "30 minutes") -> DataFrame:
    """user_id, start, idx, val: closed page-stay sessions as binary vectors; URL numbers from ``width`` on have no coordinate."""
    each = stream.groupBy(F.session_window("ts", gap), "user_id").agg(F.array_sort(F.collect_set("url_id")).alias("u"))
    idx = F.filter("u", lambda k: k < width)
    return each.select("user_id", F.col("session_window.start").alias("start"), idx.alias("idx"), F.transform(idx, lambda _: F.lit(1.0)).alias("val"))


def scored(vectors: DataFrame, centres: np.ndarray, q: float) -> DataFrame:
    """Adds the shares in the fixed centres' clusters (u) and the cluster: for a batch of a stream or any table of vectors."""
    return memberships(vectors, centres, q)


class Drift:
    """Centres that follow a stream: for ``foreachBatch``. Each batch of session vectors is summed by cluster where it lies; old
    mass is faded by ``keep``. The centres, which fit the driver, are all that comes back."""

    def __init__(self, centres: np.ndarray, q: float, keep: float = 0.9):
        self.centres, self.q, self.keep, self.mass, self.batches = centres.copy(), q, keep, np.zeros(len(centres)), 0

    def __call__(self, batch: DataFrame, number: int) -> None:
        q, c, width = self.q, *self.centres.shape
        shares = memberships(batch, self.centres, q).select("idx", "val", F.posexplode("u").alias("j", "u")).withColumn("m", F.pow("u", F.lit(float(max(q, 1)))))
        sums = shares.select("j", "m", F.explode(F.arrays_zip(F.concat(F.array(F.lit(-1)), F.col("idx")).alias("k"), F.concat(F.array(F.lit(1.0)), F.col("val")).alias("x"))).alias("z"))
        total, moved = np.zeros(c), np.zeros((c, width))
        for r in sums.groupBy("j", "z.k").agg(F.sum(F.col("m") * F.col("z.x")).alias("s")).collect():  # clusters x coordinates
            if r["k"] < 0:
                total[r["j"]] = r["s"]
            else:
                moved[r["j"], r["k"]] = r["s"]
        old = self.mass * self.keep
        now = old + total
        some = now > 0
        self.centres[some] = (self.centres[some] * old[some, None] + moved[some]) / now[some, None]
        self.mass, self.batches = now, self.batches + 1


def run_batches(result: DataFrame, each, mode: str = "append") -> list[dict]:
    """Runs a streaming result over what there is, a call of ``each`` for every batch, and returns the batches' progress."""
    spark = result.sparkSession
    query = result.writeStream.foreachBatch(each).outputMode(mode).option("checkpointLocation", f"{shared(spark, 'stream')}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return progress_of(query)


def progress_of(query) -> list[dict]:
    """The recent progress of a streaming query as plain tables."""
    return [json.loads(p.json) if hasattr(p, "json") else dict(p) for p in query.recentProgress]


def late_rows(progress: list[dict]) -> int:
    """How many rows stateful operators dropped since they came behind the watermark."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in progress for op in p.get("stateOperators", []))


def drift(centres: np.ndarray, mass: np.ndarray, x: np.ndarray, w: np.ndarray, q: float, keep: float = 0.9) -> tuple[np.ndarray, np.ndarray]:
    """Centres moved by a small batch: old mass is faded by ``keep``, new points come in with their shares."""
    d = np.maximum((x * x).sum(1)[:, None] + (centres * centres).sum(1)[None, :] - 2 * x @ centres.T, 0)
    m = membership(d, q) ** q * w[:, None]
    total = mass * keep + m.sum(axis=0)
    return (centres * (mass * keep)[:, None] + m.T @ x) / np.maximum(total, 1e-300)[:, None], total


def run_to_table(result: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a streaming result over what there is and returns its rows. Each batch goes to files of its own, so a batch that
    is run again replaces them."""
    spark = result.sparkSession
    root = shared(spark, "stream")

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/rows/batch={number}")

    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")  # lists and timers need it
    try:
        result.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    finally:
        if before:
            spark.conf.set(name, before)
        else:
            spark.conf.unset(name)
    return spark.read.schema(result.schema).parquet(f"{root}/rows").select(*result.columns)


def staged(spark: SparkSession, sf_dir: str, flush: bool = True) -> str:
    """A folder of event files for the file source; flush: a last file with one far-future row, which closes all windows.
    The row is of user -1."""
    root = shared(spark, "events")
    table(spark, sf_dir, "events").select(*EVENT.names).write.parquet(root)
    if flush:
        last = spark.range(1).select(F.lit(-1).cast("long").alias("event_id"), F.lit(FLUSH).cast("timestamp_ntz").alias("ts"), F.lit(-1).cast("long").alias("user_id"), F.lit("flush").alias("event_type"), F.lit(0.0).alias("value"), F.lit('{"k": 0}').alias("props"))
        last.write.mode("append").parquet(root)
    return root
