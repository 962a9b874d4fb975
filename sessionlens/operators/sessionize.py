"""Sessions from request streams by two time rules, and a graded one."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ..plans.stage import settle

MINUTE, HOUR, DAY = 60_000_000, 3_600_000_000, 86_400_000_000


def _ordered(user: str, ts: str, seq: str):
    return Window.partitionBy(user).orderBy(ts, seq)


def gap_numbers(requests: DataFrame, beta_us: int, user: str = "user_id", ts: str = "ts", seq: str = "seq", out: str = "session_no") -> DataFrame:
    """A new session where the time since the user's last request is over beta. One exchange by user, one sort."""
    w = _ordered(user, ts, seq)
    stay = F.unix_micros(ts) - F.lag(F.unix_micros(ts)).over(w)
    return requests.withColumn(out, F.sum(F.when(stay.isNull() | (stay > beta_us), 1).otherwise(0)).over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)).cast("int"))


def duration_numbers(requests: DataFrame, beta_us: int, user: str = "user_id", ts: str = "ts", seq: str = "seq", out: str = "session_no") -> DataFrame:
    """A new session where the time since the session's first request is over beta.

    The rule depends on where the last session began, so it is a fold. A pause over beta ends a session under either rule,
    hence the fold can start anew after each: rows are dealt by user and stretch between such pauses and sorted, and Python,
    which gets keys and times alone, jumps from one beginning to the next. Sessions are numbered inside a stretch while rows
    stream past; what the user's earlier stretches had is added from a table of one row for each stretch.
    """
    stretched = gap_numbers(requests, beta_us, user, ts, seq, "_stretch")
    keys = stretched.select(F.col(user).alias("u"), F.col("_stretch").alias("s"), F.unix_micros(ts).alias("us"), F.col(seq).alias("q")).where("us is not null")
    schema = T.StructType([keys.schema["u"], T.StructField("s", T.IntegerType()), T.StructField("us", T.LongType()), T.StructField("no", T.IntegerType())])

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, begin, no = None, 0, 0
        for b in batches:
            if not b.num_rows:
                continue
            stretch, us = (b.column(k).to_numpy(zero_copy_only=False) for k in (1, 2))
            codes = b.column(0).dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False)
            edges = np.flatnonzero((codes[1:] != codes[:-1]) | (stretch[1:] != stretch[:-1])) + 1
            first, last = np.concatenate([[0], edges]), np.concatenate([edges, [len(us)]])
            # a stretch no longer than beta is one session; the batch's outer ones may go on in other batches
            plain = us[last - 1] - us[first] <= beta_us
            plain[[0, -1]] = False
            starts, at = first[plain].tolist(), [1] * int(plain.sum())
            for i, end in zip(first[~plain].tolist(), last[~plain].tolist(), strict=True):
                now, k = (b.column(0)[i].as_py(), int(stretch[i])), i
                if now != key:
                    key, begin, no = now, int(us[i]), 1
                    starts.append(i)
                    at.append(no)
                while (k := k + int(np.searchsorted(us[k:end], begin + beta_us, side="right"))) < end:
                    begin, no = int(us[k]), no + 1
                    starts.append(k)
                    at.append(no)
            picked = b.take(pa.array(starts, pa.int64()))
            yield pa.RecordBatch.from_arrays([picked.column(0), picked.column(1), picked.column(2), pa.array(at, pa.int32())], names=["u", "s", "us", "no"])

    width = int(requests.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ordered = keys.repartition(width, "u", "s").sortWithinPartitions("u", "s", "us").select("u", "s", "us")
    begins = settle(ordered.mapInArrow(fold, schema), "beginnings")
    parts = begins.groupBy("u", "s").agg(F.max("no").alias("n"))
    before = parts.select("u", "s", F.sum("n").over(Window.partitionBy("u").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))
    numbered = begins.join(before, ["u", "s"]).select("u", "us", (F.col("no") + F.coalesce("before", F.lit(0))).cast("int").alias("no"))
    # a request belongs to the last session of its user that has begun: beginnings are put among the requests
    row = F.struct(*requests.columns)
    both = requests.select(F.col(user).alias("u"), F.unix_micros(ts).alias("us"), F.lit(1).alias("kind"), F.lit(None).cast("int").alias("no"), row.alias("r"))
    heads = numbered.select("u", "us", F.lit(0).alias("kind"), "no", F.lit(None).cast(both.schema["r"].dataType).alias("r"))
    w = Window.partitionBy("u").orderBy("us", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.unionByName(heads).withColumn("no", F.last("no", ignorenulls=True).over(w)).where("kind = 1").select("r.*", F.col("no").alias(out))


def sessionize(requests: DataFrame, rule: str, beta_us: int, user: str = "user_id", ts: str = "ts", seq: str = "seq") -> DataFrame:
    """Adds session_no, session_id and pos. rule: 'gap' (page stay) or 'duration' (whole session)."""
    numbered = {"gap": gap_numbers, "duration": duration_numbers}[rule](requests, beta_us, user, ts, seq)
    pos = F.row_number().over(Window.partitionBy(user, "session_no").orderBy(ts, seq))
    return numbered.withColumn("session_id", F.concat(F.lit("U"), F.col(user).cast("string"), F.lit("-S"), F.col("session_no").cast("string"))).withColumn("pos", pos)


def sessionize_soft(requests: DataFrame, beta_us: int, slack_us: int, user: str = "user_id", ts: str = "ts", seq: str = "seq") -> DataFrame:
    """Page-stay sessions with a graded limit: adds session_no and mu.

    Sessions begin where a pause is over beta. A request after a pause between beta and beta + slack belongs to the session
    before with mu = 1 - (pause - beta) / slack and to its own with the rest; it comes out once for each.
    """
    w = _ordered(user, ts, seq)
    own = gap_numbers(requests, beta_us, user, ts, seq).withColumn("_over", F.coalesce(F.unix_micros(ts) - F.lag(F.unix_micros(ts)).over(w) - beta_us, F.lit(0)))
    mu = F.when((F.col("_over") > 0) & (F.col("_over") < slack_us), 1 - F.col("_over") / F.lit(float(slack_us))).otherwise(0.0)
    shares = F.array(F.struct(F.col("session_no").alias("no"), (1 - F.col("_mu")).alias("mu")), F.struct((F.col("session_no") - 1).alias("no"), F.col("_mu").alias("mu")))
    return own.withColumn("_mu", mu).withColumn("_s", F.explode(shares)).where("_s.mu > 0").withColumn("session_no", F.col("_s.no")).withColumn("mu", F.col("_s.mu")).drop("_over", "_mu", "_s")


def compare_heuristics(requests: DataFrame, betas_us: Sequence[int], user: str = "user_id", ts: str = "ts", seq: str = "seq") -> DataFrame:
    """rule, beta_us, sessions: how many sessions each rule gives for each limit. One exchange by user and one sort serve all
    limits of the page-stay rule; one more, by user and stretch of the largest limit, all of the total-duration rule."""
    betas = [int(x) for x in betas_us]
    keys = requests.select(user, ts, seq)
    stay = (F.unix_micros(ts) - F.lag(F.unix_micros(ts)).over(_ordered(user, ts, seq))).alias("_stay")
    gaps = keys.select(stay).agg(F.array(*(F.count_if(F.col("_stay").isNull() | (F.col("_stay") > x)) for x in betas)).alias("n"))
    stretched = gap_numbers(keys, max(betas), user, ts, seq, "s").select(F.col(user).alias("u"), "s", F.unix_micros(ts).alias("us")).where("us is not null")

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, begins, counts = None, [0] * len(betas), [0] * len(betas)
        for b in batches:
            if not b.num_rows:
                continue
            stretch, us = (b.column(k).to_numpy(zero_copy_only=False) for k in (1, 2))
            codes = b.column(0).dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False)
            edges = (np.flatnonzero((codes[1:] != codes[:-1]) | (stretch[1:] != stretch[:-1])) + 1).tolist()
            for i, end in zip([0, *edges], [*edges, len(us)], strict=True):
                now = (b.column(0)[i].as_py(), int(stretch[i]))
                if now != key:
                    key, begins = now, [int(us[i])] * len(betas)
                    counts = [n + 1 for n in counts]
                for j, beta in enumerate(betas):
                    k = i
                    while (k := k + int(np.searchsorted(us[k:end], begins[j] + beta, side="right"))) < end:
                        begins[j] = int(us[k])
                        counts[j] += 1
        yield pa.RecordBatch.from_arrays([pa.array(range(len(betas)), pa.int32()), pa.array(counts, pa.int64())], names=["i", "n"])

    width = int(requests.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    folded = stretched.repartition(width, "u", "s").sortWithinPartitions("u", "s", "us").select("u", "s", "us").mapInArrow(fold, "i int, n long")
    limits = F.array(*(F.lit(x).cast("long") for x in betas))
    named = lambda rule, df: df.select(F.lit(rule).alias("rule"), F.element_at(limits, F.col("i") + 1).alias("beta_us"), F.col("n").alias("sessions"))
    return named("gap", gaps.select(F.posexplode("n").alias("i", "n"))).unionByName(named("duration", folded.groupBy("i").agg(F.sum("n").alias("n"))))
