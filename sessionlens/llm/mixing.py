"""Mixing sources to target weights by a low-discrepancy schedule of equal-token blocks.

Targets share a budget over the sources by weight, each held to a multiple of what its source has. The schedule is a list
of slots: slot i is mapped by the golden-ratio point frac(i * phi) (or van der Corput's) through the cumulative targets to a
source, so that every stretch of the schedule is close to the targets. The r-th slot of a source takes the r-th of its
blocks, round and round. A source's blocks are equal pieces of its documents laid end to end in hashed order.

Ranks and positions come from counts of chunks and running totals over chunks, so no task holds a whole source.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import keep, running_total

#: Weights of the sources in order, repeated; the budget as a share of all words; the most epochs; words of a block; seed.
WEIGHTS, BUDGET, MOST, BLOCK, SEED = (3, 1, 2), 1.5, 2.0, 1024, 42
#: Slots whose ranks are counted together.
CHUNK = 1 << 16
#: The golden ratio's fraction in 53-bit fixed point, so that points are exact in every run.
_PHI = int((5**0.5 - 1) / 2 * (1 << 53))


def words_in(text: Column) -> Column:
    """How many words stand between ASCII white space; null: 0."""
    parts = F.split(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+")
    n = F.size(parts)
    return (n - F.when(F.element_at(parts, 1) == "", 1).otherwise(0) - F.when((n > 1) & (F.element_at(parts, -1) == ""), 1).otherwise(0)).cast("long")


def fill(sizes: Sequence[int], weights: Sequence[float], budget: float, most: float) -> list[float]:
    """Shares of the budget by weight, none above ``most`` times its size; what is cut off is shared again by weight."""
    target, free, left = [0.0] * len(sizes), [i for i, s in enumerate(sizes) if s > 0], float(budget)
    while free:
        total = sum(weights[i] for i in free)
        over = [i for i in free if left * weights[i] / total >= most * sizes[i]]
        if not over:
            for i in free:
                target[i] = left * weights[i] / total
            return target
        for i in over:
            target[i] = most * float(sizes[i])
            left -= target[i]
        free = [i for i in free if i not in set(over)]
    return target


def targets(sized: DataFrame, weights: Sequence[float] = WEIGHTS, budget: float = BUDGET, most: float = MOST, block: int = BLOCK) -> DataFrame:
    """source, number (0, 1, ... in code point order, null last), source_size, target, quota (its slots). One row for each
    source: there are as many as a schedule's cumulative weights, so they pass through the driver."""
    rows = sized.groupBy("source").agg(F.sum("size").alias("n")).collect()
    rows.sort(key=lambda r: (r["source"] is None, (r["source"] or "").encode("utf-32-be")))
    sizes = [int(r["n"] or 0) for r in rows]
    got = fill(sizes, [weights[i % len(weights)] for i in range(len(rows))], budget * sum(sizes), most)
    words = [int(t + 0.5) for t in got]  # halves go up, as in ``mix``
    slots = [w // n * -(-n // block) + -(-(w % n) // block) if n else 0 for n, w in zip(sizes, words, strict=True)]
    out = [(r["source"], i, n, t, q) for i, (r, n, t, q) in enumerate(zip(rows, sizes, got, slots, strict=True))]
    return sized.sparkSession.createDataFrame(out, "source string, number int, source_size long, target double, quota long")


def point(slot: Column, sequence: str = "golden") -> Column:
    """The slot's point in [0, 1)."""
    if sequence == "golden":  # slot * phi modulo 1 in 53-bit fixed point; the product is taken in two halves to fit a long
        low, high = slot.bitwiseAND(F.lit((1 << 20) - 1)), F.shiftright(slot, 20)
        whole = F.lit(1 << 53).cast("decimal(38,0)")
        by = F.lit(_PHI).cast("decimal(38,0)")
        return ((((low.cast("decimal(20,0)") * by) % whole + ((high.cast("decimal(20,0)") * by) % whole * F.lit(1 << 20).cast("decimal(20,0)")) % whole) % whole).cast("double")) / float(1 << 53)
    if sequence == "van_der_corput":  # the bits of the slot in reverse
        return F.conv(F.reverse(F.lpad(F.bin(slot), 52, "0")), 2, 10).cast("double") / float(1 << 52)
    raise ValueError(f"no such sequence: {sequence}")


def schedule(spark: SparkSession, sources: DataFrame, sequence: str = "golden") -> DataFrame:
    """slot, number, rank: the source of every slot and how many slots the source had before. A source stops at its quota;
    the few slots it lacks when the sequence ends (a low-discrepancy sequence is off by a few at most) come at the end."""
    rows = sources.where("quota > 0").orderBy("number").select("number", "quota").collect()
    slots = sum(r["quota"] for r in rows)
    edges, before = [], 0
    for r in rows:
        edges.append((before / slots, r["number"]))
        before += r["quota"]
    ends = F.array(*(F.lit(e) for e, _ in edges)) if edges else F.array(F.lit(0.0))
    numbers = F.array(*(F.lit(n) for _, n in edges)) if edges else F.array(F.lit(0))
    base = spark.range(slots).select(F.col("id").alias("slot"), point(F.col("id"), sequence).alias("p"))
    # the last edge at or below the point, found by width: edges ascend and the first is 0
    chosen = F.size(F.filter(ends, lambda e: e <= F.col("p")))
    dealt = base.select("slot", F.element_at(numbers, chosen).alias("number"), F.floor(F.col("slot") / CHUNK).alias("chunk"))
    counts = dealt.groupBy("number", "chunk").agg(F.count("*").alias("n"))
    starts = counts.select("number", "chunk", (F.sum("n").over(Window.partitionBy("number").orderBy("chunk")) - F.col("n")).alias("before"))
    inside = dealt.withColumn("r", F.row_number().over(Window.partitionBy("chunk", "number").orderBy("slot")) - 1)
    quota = F.broadcast(sources.select("number", "quota"))
    ranked = inside.join(starts, ["number", "chunk"]).select("slot", "number", (F.col("r") + F.col("before")).alias("rank")).join(quota, "number").where("rank < quota").drop("quota")
    had = counts.groupBy("number").agg(F.sum("n").alias("had"))
    short = sources.join(had, "number", "left").where("quota > coalesce(had, 0)").select("number", F.explode(F.sequence(F.coalesce("had", F.lit(0)), F.col("quota") - 1)).alias("rank"))
    return ranked.unionByName(short.select((F.lit(slots) + F.col("rank")).alias("slot"), "number", "rank"))


def mix(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", weights: Sequence[float] = WEIGHTS, budget: float = BUDGET, most: float = MOST, block: int = BLOCK, seed: int = SEED, sequence: str = "golden", carry: Sequence[str] = ()) -> DataFrame:
    """key, size, source_size, target, taken: for every row of ``docs`` the words it has and the words the mix
    takes of it, repeats counted; with ``carry`` a struct _carry of further columns, handed through as they are.

    Documents of a source lie end to end in the order of a hash of their key and text; blocks of ``block`` words are cut
    from that line, the last one shorter. Rounds over the blocks take whole blocks but for the very last slot, which takes
    what is missing to the target. A text that is null or without words has size 0 and takes nothing. Rows that share a key count apart.
    """
    spark = docs.sparkSession
    size = words_in(F.col(text))
    sized = docs.select(F.col(key), F.col(source).cast("string").alias("source"), size.alias("size"), F.xxhash64(F.col(key), F.col(text), F.lit(seed)).alias("_order"), F.monotonically_increasing_id().alias("_row"), (F.struct(*(F.col(f"`{c}`") for c in carry)) if carry else F.lit(None)).alias("_carry"))
    sized = keep(sized, "sizes")
    by = targets(sized, weights, budget, most, block)
    named = by.withColumnRenamed("source", "_name")
    numbered = sized.drop("_carry").join(F.broadcast(named), F.col("source").eqNullSafe(F.col("_name"))).drop("source", "_name")
    line = running_total(numbered, ["number", "_order", F.col(key).asc_nulls_last()], "size", "_at", "mix-order")
    first = F.broadcast(by.select("number", (F.sum("source_size").over(Window.orderBy("number").rowsBetween(Window.unboundedPreceding, -1))).alias("_first")))
    line = line.join(first, "number").withColumn("_at", F.col("_at") - F.coalesce("_first", F.lit(0))).drop("_first")
    slots = schedule(spark, by, sequence)
    # blocks taken so often; the last slot of a source takes what its target still lacks
    with_size = slots.join(F.broadcast(by.select("number", "source_size", "target", "quota")), "number")
    per_round = F.ceil(F.col("source_size") / block)
    places = with_size.select("number", (F.col("rank") % per_round).alias("b"), F.floor(F.col("rank") / per_round).alias("round"), "source_size", "target")
    length = F.least(F.lit(block).cast("long"), F.col("source_size") - F.col("b") * block)
    used = F.col("round") * F.col("source_size") + F.col("b") * block
    got = F.greatest(F.least(length, F.round("target").cast("long") - used), F.lit(0).cast("long"))
    taken = places.groupBy("number", "b").agg(F.sum(F.when(got == length, 1).otherwise(0)).alias("full"), F.max(F.when(got < length, got).otherwise(0)).alias("part"))
    pieces = line.where("size > 0").select(
        "number",
        "size",
        "_at",
        F.explode(F.sequence(F.floor(F.col("_at") / block), F.floor((F.col("_at") + F.col("size") - 1) / block))).alias("b"),
    )
    lo, hi = F.greatest(F.col("_at"), F.col("b") * block), F.least(F.col("_at") + F.col("size"), (F.col("b") + 1) * block)
    joined = pieces.join(taken, ["number", "b"]).select(
        "_at", "number", ((hi - lo) * F.col("full") + F.greatest(F.least(hi, F.col("b") * block + F.col("part")) - lo, F.lit(0))).alias("w")
    )
    sums = joined.groupBy("number", "_at").agg(F.sum("w").alias("taken"))  # only one row with words starts at a place
    some = line.where("size > 0").join(sums, ["number", "_at"], "left").withColumn("taken", F.coalesce("taken", F.lit(0)).cast("long"))
    columns = [key, "size", "source_size", "target", "taken", "_row"]
    out = some.select(*columns).unionByName(line.where("size = 0").withColumn("taken", F.lit(0).cast("long")).select(*columns))
    if carry:  # texts and the like join at the end; only sizes were put in order
        out = out.join(sized.select("_row", "_carry"), "_row")
    return out.select(key, "size", "source_size", "target", "taken", *(["_carry"] if carry else []))


def mixed_documents(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", **options) -> DataFrame:
    """The documents of the mix with the columns of ``docs``: a document that is taken k times whole comes k times; a
    last partial taking (at the end of a source's schedule, or of a block before it) comes with as many of its first words."""
    columns = docs.columns
    got = mix(docs, key, text, source, carry=columns, **options).select("size", "taken", "_carry")
    whole, rest = F.floor(F.col("taken") / F.col("size")), F.col("taken") % F.col("size")
    copies = F.concat(F.array_repeat(F.lit(None).cast("long"), whole.cast("int")), F.when(rest > 0, F.array(rest)).otherwise(F.array().cast("array<long>")))
    each = got.where("taken > 0").select("_carry", F.explode(copies).alias("_part"))  # at most the most epochs, and one
    own = F.col(f"_carry.`{text}`")
    words = F.filter(F.split(own, r"[\x20\x09-\x0D]+"), lambda w: w != "")
    cut = F.when(F.col("_part").isNull(), own).otherwise(F.array_join(F.slice(words, F.lit(1), F.col("_part").cast("int")), " "))
    made = {text: cut}
    if "n_chars" in columns:
        made["n_chars"] = F.when(F.col("_part").isNull(), F.col("_carry.n_chars")).otherwise(F.length(cut).cast(dict(docs.dtypes)["n_chars"]))
    return each.select(*(made.get(c, F.col(f"_carry.`{c}`")).alias(c) for c in columns))
