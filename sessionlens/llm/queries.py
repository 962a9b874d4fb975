"""The thin queries of the operators over their whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat_format, content_store, decontaminate, embeddings, html_text, mixing, simhash, token_counts, toxicity, url_filters


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(_table(spark, sf_dir, "pages").select("page_id", "url", "html")).select("page_id", "url", "text", "n_chars")


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(_table(spark, sf_dir, "documents"))


def op3_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddings.near_vectors(_table(spark, sf_dir, "embeddings"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    weights = toxicity.fit(docs, _table(spark, sf_dir, "labels").where(~toxicity.held_out()))
    return toxicity.score(docs, weights).select("doc_id", toxicity.held_out().alias("held_out"), "score", "predicted")


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark")).drop("items")


def op6_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page against a dated host list that a rule makes from the hosts: page_id, url, fetched_day, lists, blocked."""
    pages = _table(spark, sf_dir, "pages").select("page_id", "url").withColumn("fetched_day", (F.col("page_id") * 37 % 365).cast("int"))
    hosts = pages.select(url_filters.host_of(F.col("url")).alias("host")).where("host is not null").distinct().withColumn("k", F.length("host"))
    first = (F.col("k") * 7 % 120).cast("int")
    dated = F.array(
        F.struct(F.lit("hosts").alias("list"), F.col("host").alias("pattern"), F.lit("add").alias("action"), first.alias("at")),
        F.struct(F.lit("hosts").alias("list"), F.col("host").alias("pattern"), F.lit("remove").alias("action"), (first + 90).alias("at")),
        F.struct(F.lit("hosts").alias("list"), F.col("host").alias("pattern"), F.lit("add").alias("action"), F.when(F.col("k") % 2 == 0, first + 150).alias("at")),
        F.struct(F.lit("sections").alias("list"), F.concat("host", F.lit("/de")).alias("pattern"), F.lit("add").alias("action"), F.when(F.col("k") % 3 == 0, F.lit(200)).alias("at")),
    )
    entries = hosts.select(F.explode(dated).alias("e")).select("e.*")
    return url_filters.evaluate(pages, entries, at="fetched_day").select("page_id", "url", "fetched_day", F.array_join("lists", ",").alias("lists"), "blocked")


#: The function that the conversation table's user turns are taken to call.
SCHEMAS = {"answer": {"type": "object", "required": ["question", "turn"], "additionalProperties": False, "properties": {"question": {"type": "string", "minLength": 1}, "turn": {"type": "integer", "minimum": 0}}}}


def op7_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every turn of every conversation. A user turn is taken as a call whose identifier is its conversation and turn; the
    assistant turn that follows is its result; a call waits for the user turn before it, two turns back, if there is one. line:
    the message's place when all conversations are written in order."""
    turns = _table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    own = F.concat_ws(":", F.col("conv_id").cast("string"), F.col("turn").cast("string"))
    kind = F.when(F.col("role") == "user", "call").when(F.col("role") == "assistant", "result").otherwise("text")
    before = F.concat_ws(":", F.col("conv_id").cast("string"), (F.col("turn") - 1).cast("string"))
    messages = turns.select(
        "conv_id",
        "turn",
        "role",
        kind.alias("kind"),
        F.when(F.col("role") == "user", own).when(F.col("role") == "assistant", before).alias("call_id"),
        F.lit("answer").alias("name"),
        F.to_json(F.struct(F.col("text").alias("question"), F.col("turn").alias("turn"))).alias("arguments"),
        F.col("text").alias("content"),
        F.when(F.col("turn") > 1, F.array(F.concat_ws(":", F.col("conv_id").cast("string"), (F.col("turn") - 2).cast("string")))).otherwise(F.array().cast("array<string>")).alias("after"),
    )
    return chat_format.in_order(chat_format.link(messages, SCHEMAS))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_table(spark, sf_dir, "documents"))


def op9_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return content_store.read_back(content_store.write_store(_table(spark, sf_dir, "documents"))).drop("root")


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return token_counts.count_tokens(docs).select("doc_id", "n_bytes", "n_tokens", "over_limit")


def queries() -> dict:
    return {f.__name__: f for f in (op1_main_text, op2_simhash, op3_embeddings, op4_toxicity, op5_decontamination, op6_url_filter, op7_chat, op8_mixing, op9_token_store, op10_token_counts)}


def oracle_sql() -> dict[str, str]:
    word = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    words = f"regexp_extract_all(translate(coalesce(text, ''), '{upper}', '{lower}'), '{word}')"
    return {
        "op3_embeddings": """
WITH RECURSIVE v AS (
  SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings
), ok AS (
  SELECT vec_id, label, e, list_dot_product(e, e) AS n2 FROM v
  WHERE label IS NOT NULL AND e IS NOT NULL AND len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), link AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM ok a JOIN ok b ON a.label = b.label AND a.vec_id <> b.vec_id
  WHERE a.n2 > 0 AND b.n2 > 0 AND len(a.e) = len(b.e) AND list_dot_product(a.e, b.e) / (sqrt(a.n2) * sqrt(b.n2)) >= 0.93
), reach AS (
  SELECT vec_id AS a, vec_id AS b FROM v UNION SELECT r.a, l.b FROM reach r JOIN link l ON r.b = l.a
)
SELECT v.vec_id, (SELECT count(*) FROM link l WHERE l.a = v.vec_id) AS n_links, r.c AS component_id, v.vec_id = r.c AS kept
FROM v JOIN (SELECT a, min(b) AS c FROM reach GROUP BY a) r ON r.a = v.vec_id""",
        "op5_decontamination": f"""
WITH d AS (SELECT doc_id, {words} AS w FROM documents), i AS (SELECT item_id, {words} AS w FROM benchmark),
win AS (
  SELECT DISTINCT item_id, w[s : s + 9] AS p FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 8, 2))) AS s FROM i WHERE len(w) > 0)
), size AS (SELECT DISTINCT len(p) AS n FROM win),
pos AS (
  SELECT doc_id, s, n, w[s : s + n - 1] AS p FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS s FROM d, size WHERE len(w) >= n)
), hit AS (SELECT doc_id, s, n, item_id FROM pos JOIN win USING (p)),
each AS (
  SELECT doc_id, count(DISTINCT place) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS place FROM (SELECT DISTINCT doc_id, s, n FROM hit)) GROUP BY doc_id
), items AS (SELECT doc_id, count(*) AS n_items, string_agg(id, ',' ORDER BY id) AS ids FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS id FROM hit) GROUP BY doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN each USING (doc_id) LEFT JOIN items USING (doc_id)""",
        "op6_url_filter": r"""
WITH p AS (
  SELECT page_id, url, (page_id * 37 % 365)::INT AS fetched_day,
    nullif(lower(rtrim(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?(\[[^\]]*\]|[^/?#:]*)', 1), '.')), '') AS host,
    list_filter(string_split(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)', 1), '/'), lambda x: x <> '')[1] AS step
  FROM pages
), f AS (SELECT *, length(host) AS k, (length(host) * 7 % 120) AS first FROM p)
SELECT page_id, url, fetched_day, concat_ws(',', CASE WHEN h THEN 'hosts' END, CASE WHEN s THEN 'sections' END) AS lists, h OR s AS blocked
FROM (SELECT *, coalesce((fetched_day >= first AND fetched_day < first + 90) OR (k % 2 = 0 AND fetched_day >= first + 150), false) AS h,
  coalesce(k % 3 = 0 AND fetched_day >= 200 AND step = 'de', false) AS s FROM f)""",
    }
