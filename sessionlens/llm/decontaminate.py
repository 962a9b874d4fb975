"""Benchmark decontamination with a distributed positional inverted index, in DataFrame functions only.

A posting is (term, document, position). The index holds postings of the terms that the test items need, taken from
every whole document in one pass; corpus counts of the test terms come from another. A phrase is looked up from its
rarest term: that term's postings give where the phrase would start (position less the term's place in the phrase),
the list of the second rarest term, shifted alike, must give the same start, and the words around a posting, which the
index keeps with it, decide. Proximity matches intersect the lists of an item's rarest terms within a span.

Test items are the stated query set. Their different windows are handled in blocks whose terms fit a literal set (about
``BLOCK`` windows each, dealt by a hash), so neither the driver nor a broadcast grows with the documents or with an item.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import discard, keep

#: Words of a window; windows of a block.
WINDOW, BLOCK = 10, 20_000

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: What stands between words: all of ASCII but digits and letters.
_BETWEEN = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    """The words of a text as written, in order; null and wordless texts have none. Letters may be of either case:
    since A-Z and a-z are both word characters, the words are the same before and after lower-casing."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), _BETWEEN), lambda w: w != "")


def fold(word: Column) -> Column:
    """A-Z to a-z, nothing else."""
    return F.translate(word, _UPPER, _LOWER)


def windows(items: DataFrame, key: str = "item_id", text: str = "text", size: int = WINDOW) -> DataFrame:
    """item, words: every window of ``size`` consecutive words; an item of fewer words, but not none, is one window."""
    w = items.select(F.col(key).alias("item"), F.transform(words_of(F.col(text)), fold).alias("_w")).where("size(_w) > 0")
    starts = F.sequence(F.lit(0), F.greatest(F.size("_w") - size, F.lit(0)))
    return w.select("item", F.explode(F.transform(starts, lambda s: F.slice("_w", s + 1, F.lit(size)))).alias("words"))


def term_counts(docs: DataFrame, terms: list[str], text: str = "text") -> DataFrame:
    """term, n: how often each of the terms (as ``lower`` writes them) stands in all documents. Other words are left in their
    row. ``lower`` is a first sieve on either side; ``fold`` decides."""
    found = F.filter(words_of(F.col(text)), lambda w: F.lower(w).isin(terms)) if terms else F.array().cast("array<string>")
    return docs.select(F.explode(found).alias("w")).groupBy(fold(F.col("w")).alias("term")).agg(F.count("*").alias("n"))


def postings(docs: DataFrame, terms: list[str], key: str = "doc_id", text: str = "text", around: int = WINDOW - 1, base: Column | None = None) -> DataFrame:
    """The positional index of ``terms``: doc, term, pos (from 0), before and after (up to ``around`` words each side, as
    written). base: a name for a row if key isn't unique."""
    w = docs.select((F.col(key) if base is None else base).alias("doc"), words_of(F.col(text)).alias("_w"))

    def posting(i: Column) -> Column:
        return F.struct(F.element_at("_w", i + 1).alias("w"), i.alias("pos"), F.slice("_w", F.greatest(i - around, F.lit(0)) + 1, F.least(i, F.lit(around))).alias("before"), F.slice("_w", i + 2, F.lit(around)).alias("after"))

    numbered = F.filter(F.transform(F.col("_w"), lambda w, i: F.when(F.lower(w).isin(terms), i)), lambda i: i.isNotNull())
    some = w.where(F.size("_w") > 0).select("doc", "_w", numbered.alias("_i")).where("size(_i) > 0")
    rows = some.select("doc", F.explode(F.transform("_i", posting)).alias("p"))
    return rows.select("doc", fold(F.col("p.w")).alias("term"), "p.pos", "p.before", "p.after")


def plan_windows(each: DataFrame, counts: DataFrame) -> DataFrame:
    """words, items, term, low, place, next, n: each different phrase with its rarest and second rarest place, ties to the
    first; a term that no document has counts 0. each: words, items. low: the rarest term as ``lower`` writes it."""
    placed = each.select("words", "items", F.posexplode("words").alias("place", "term")).join(F.broadcast(counts), "term", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    two = placed.groupBy("words", "items").agg(F.slice(F.sort_array(F.collect_list(F.struct("n", "place", "term"))), 1, 2).alias("r"))
    return two.select("words", "items", F.expr("r[0].term").alias("term"), F.expr("lower(r[0].term)").alias("low"), F.expr("r[0].place").alias("place"), F.try_element_at("r", F.lit(2)).alias("next"), F.expr("r[0].n").alias("n"))


def phrase_matches(docs: DataFrame, phrases: DataFrame, key: str = "doc_id", text: str = "text", block: int = BLOCK, base: Column | None = None) -> DataFrame:
    """doc, item, start, length: every occurrence of every phrase (item, words) in every whole document, word for word."""
    spark = docs.sparkSession
    parts = []
    each = keep(phrases.groupBy("words").agg(F.sort_array(F.collect_set("item")).alias("items")), "phrases")
    n = -(-each.count() // block)
    for i in range(n):
        some = each.where(F.pmod(F.xxhash64("words"), F.lit(n)) == i)
        terms = _lowered(some)
        counts = keep(term_counts(docs, terms, text), "term-counts")
        plan = plan_windows(some, counts).where("n > 0")
        rows = plan.collect()
        discard(counts)
        if not rows:
            continue
        small = spark.createDataFrame(rows, plan.schema)  # the block's windows
        found = postings(docs, sorted({r["low"] for r in rows}), key, text, max(len(r["words"]) for r in rows) - 1, base).join(F.broadcast(small), "term")
        place, length = F.col("place"), F.size("words")
        # the second rarest term first, then all others, each at its distance from the rarest
        near = F.when(F.col("next").isNull(), True).when(F.col("next.place") < place, fold(F.try_element_at("before", F.col("next.place") - place + F.size("before") + 1)) == F.col("next.term"))
        near = near.otherwise(fold(F.try_element_at("after", F.col("next.place") - place)) == F.col("next.term"))
        ahead = F.transform(F.slice("before", F.greatest(F.size("before") - place + 1, F.lit(1)), place), fold)
        behind = F.transform(F.slice("after", F.lit(1), length - place - 1), fold)
        fits = (F.size("before") >= place) & (F.size("after") >= length - place - 1)
        hit = found.where(fits & near).where((ahead == F.slice("words", F.lit(1), place)) & (behind == F.slice("words", place + 2, length - place - 1)))
        parts.append(hit.select("doc", F.explode("items").alias("item"), (F.col("pos") - place).alias("start"), length.alias("length")))
    if not parts:
        kinds = dict(docs.select((F.col(key) if base is None else base).alias("doc")).dtypes) | dict(phrases.dtypes)
        return spark.createDataFrame([], f"doc {kinds['doc']}, item {kinds['item']}, start int, length int")
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _lowered(phrases: DataFrame) -> list[str]:
    """The different terms of the phrases as Spark's ``lower``, which sieves the documents' words, writes them."""
    return [r["t"] for r in phrases.select(F.explode(F.transform("words", F.lower)).alias("t")).distinct().collect()]


def proximity_matches(docs: DataFrame, items: DataFrame, terms: int = 3, span: int = 20, key: str = "doc_id", text: str = "text", item: str = "item_id", block: int = BLOCK) -> DataFrame:
    """doc, item, start, end: spans of at most ``span`` words that hold an item's ``terms`` rarest different words (all,
    if it has fewer), in any order. Each span ends at one of the words and begins at the last place that still holds all."""
    spark = docs.sparkSession
    parts = []
    given = keep(items.select(F.col(item).alias("item"), F.array_distinct(F.transform(words_of(F.col(text)), fold)).alias("words")).where("size(words) > 0"), "items")
    n = -(-(given.agg(F.sum(F.size("words"))).first()[0] or 0) // (block * WINDOW))
    for i in range(n):
        some = given.where(F.pmod(F.xxhash64("item"), F.lit(n)) == i)
        counts = keep(term_counts(docs, _lowered(some), text), "term-counts")
        ranked = some.select("item", F.explode("words").alias("term")).join(F.broadcast(counts), "term", "left").withColumn("n", F.coalesce("n", F.lit(0)))
        ranked = ranked.withColumn("r", F.row_number().over(Window.partitionBy("item").orderBy("n", "term"))).where(F.col("r") <= terms)
        rows = ranked.select("item", "term", F.lower("term").alias("low"), F.count("*").over(Window.partitionBy("item")).alias("need")).collect()
        if not rows:
            continue
        small = spark.createDataFrame([(r["item"], r["term"], r["need"]) for r in rows], ranked.select("item", "term", F.lit(1).cast("long").alias("need")).schema)
        found = postings(docs, sorted({r["low"] for r in rows}), key, text, 0).join(F.broadcast(small), "term")
        back = Window.partitionBy("doc", "item").orderBy("pos").rangeBetween(-(span - 1), 0)
        last = found.withColumn("seen", F.collect_list(F.struct("term", "pos")).over(back))
        latest = F.transform(F.array_distinct(F.transform("seen", lambda s: s["term"])), lambda t: F.array_max(F.transform(F.filter("seen", lambda s: s["term"] == t), lambda s: s["pos"])))
        whole = last.select("doc", "item", "need", "pos", latest.alias("at")).where("size(at) = need")
        parts.append(whole.select("doc", "item", F.array_min("at").alias("start"), F.col("pos").alias("end")).distinct())
    if not parts:
        kinds = dict(docs.select(F.col(key).alias("doc")).dtypes) | dict(given.dtypes)
        return spark.createDataFrame([], f"doc {kinds['doc']}, item {kinds['item']}, start int, end int")
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def covered(spans: Column) -> Column:
    """How many positions an array of (start, end) spans, ends excluded, covers together."""
    step = F.aggregate(
        F.array_sort(spans),
        F.struct(F.lit(0).cast("long").alias("n"), F.lit(-1).cast("long").alias("to")),
        lambda a, s: F.struct((a["n"] + F.greatest(s["end"].cast("long") - F.greatest(s["start"].cast("long"), a["to"]), F.lit(0).cast("long"))).alias("n"), F.greatest(a["to"], s["end"].cast("long")).alias("to")),
    )
    return step["n"]


def contamination(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", size: int = WINDOW) -> DataFrame:
    """Of every row of ``docs``: key, n_words, n_hit (words inside any occurrence of a window), n_items, items (their ids
    as sorted strings), items_sha256 (of those, comma-joined), contaminated.

    A null text has no words. Rows that share a key are all returned; each has its own counts. Items with a null id
    count as the string "null" nowhere: they are left out.
    """
    given = windows(items.where(F.col(item).isNotNull()), item, item_text, size)
    row = F.struct(F.col(key).alias("key"), F.xxhash64(text).alias("of"))
    hits = phrase_matches(docs, given, key, text, base=row)
    each = hits.groupBy("doc").agg(F.collect_set(F.struct("start", (F.col("start") + F.col("length")).alias("end"))).alias("spans"), F.sort_array(F.collect_set(F.col("item").cast("string"))).alias("items"))
    each = each.select("doc", covered(F.col("spans")).alias("n_hit"), "items")
    sized = docs.select(F.col(key), row.alias("doc"), F.size(words_of(F.col(text))).cast("long").alias("n_words"))
    out = sized.join(each, sized["doc"].eqNullSafe(each["doc"]), "left").select(key, "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"))
    return out.select(key, "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), "items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def without_contaminated(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", size: int = WINDOW) -> DataFrame:
    """The rows of ``docs`` that hold no window of any item, with their columns as they are. Rows are judged by key and text, so
    a clean row stays where another with its key goes. A null text holds nothing."""
    row = F.struct(F.col(key).alias("key"), F.xxhash64(text).alias("of"))
    hits = keep(phrase_matches(docs, windows(items.where(F.col(item).isNotNull()), item, item_text, size), key, text, base=row).select("doc").distinct(), "hits")
    return docs.join(hits, row.eqNullSafe(hits["doc"]), "left_anti")
