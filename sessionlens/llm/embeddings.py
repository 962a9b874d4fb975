"""Embedding near-dedup by sorted projection passes.

Each pass gives every vector a string of random hyperplane bits and sorts by (label, string), range-partitioned. A vector
is compared in double precision with a bounded window of neighbours in that order; verified pairs are joined across
passes. Equal vectors are folded first, so a very common one is a single row.

A run of near copies of any length is joined through its windows. How many links each vector has is then counted inside
the joined sets, where every pair is compared: by matrix products, in blocks of ``SET`` rows, so that a large set is
spread over tasks. A link is therefore found if a chain of window pairs joins its ends in any pass.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import components, discard, keep, running_total, shuffle_width, union_pairs

THRESHOLD, PASSES, BITS, BLOCK, SEED = 0.93, 8, 60, 256, 42
#: Share of isolated pairs at the threshold that the passes together are to put in one window (over a uniform background).
LEVEL = 0.99
#: Most rows of a joined set that one task compares with as many others; the fewest, and into how many parts a set is cut
#: before parts grow: a set's rows are copied once for each part.
SET, SMALL, PARTS = 4096, 256, 64


def passes_for(rows: int, threshold: float = THRESHOLD, block: int = BLOCK, least: int = PASSES, level: float = LEVEL) -> int:
    """How many passes keep recall at ``level`` where the largest label has ``rows`` different vectors.

    A window holds about 1.5 blocks. To stay in one, a pair must agree on the log2(rows / window) bits that lead there, and
    vectors at angle t agree on a bit with chance 1 - t / pi.
    """
    agree = 1 - np.arccos(np.clip(threshold, -1, 1)) / np.pi
    hit = min(1.0, max(agree, 1e-3) ** np.log2(max(rows, 1) / (1.5 * block)))
    return least if hit >= 1 else max(least, int(np.ceil(np.log(1 - level) / np.log1p(-hit))))


def planes(passes: int, bits: int, width: int, seed: int = SEED) -> np.ndarray:
    return np.random.default_rng(seed + width).standard_normal((passes, bits, width))


def folded(vectors: DataFrame) -> DataFrame:
    """label, v, rep, times: each different vector of a label once, with the least of its ids and how many rows have it.
    Rows that link with nothing are left out. Needs vec_id, label, v."""
    usable = F.col("label").isNotNull() & F.col("vec_id").isNotNull() & F.col("v").isNotNull() & (F.size("v") > 0)
    sound = ~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists("v", lambda x: x != 0)
    return vectors.where(usable).where(sound).groupBy("label", "v").agg(F.min("vec_id").alias("rep"), F.count("*").alias("times"))


def hashed(vectors: DataFrame, passes: int = PASSES, bits: int = BITS, seed: int = SEED) -> DataFrame:
    """The folded vectors with their codes, a string of bits in each pass."""
    return coded(folded(vectors), passes, bits, seed)


def coded(one: DataFrame, passes: int, bits: int, seed: int) -> DataFrame:
    """Adds codes to folded vectors."""

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made: dict[int, np.ndarray] = {}
        for b in batches:
            lists = b.column(b.schema.get_field_index("v")).to_pylist()
            codes: list = [None] * len(lists)
            by: dict[int, list[int]] = {}
            for i, v in enumerate(lists):
                by.setdefault(len(v), []).append(i)
            for width, rows in by.items():
                if width not in made:
                    made[width] = planes(passes, bits, width, seed)
                x = np.array([lists[i] for i in rows], float)
                signs = np.einsum("pbw,nw->npb", made[width], x, optimize=True) > 0
                value = signs.astype(np.int64) @ (np.int64(1) << np.arange(bits - 1, -1, -1, dtype=np.int64))
                for i, c in zip(rows, value.tolist(), strict=True):
                    codes[i] = c
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(codes, pa.list_(pa.int64()))], names=[*b.schema.names, "codes"])

    return one.mapInArrow(code, T.StructType([*one.schema.fields, T.StructField("codes", T.ArrayType(T.LongType()))]))


def _unit(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The vectors as rows of length 1 in double precision, short ones filled up with zeros; and their widths."""
    widths = np.diff(np.asarray(column.offsets))
    x = np.zeros((len(column), int(widths.max()) if len(widths) else 0))
    x[np.arange(x.shape[1])[None, :] < widths[:, None]] = column.flatten().to_numpy(zero_copy_only=False).astype(float)
    x /= np.abs(x).max(axis=1, keepdims=True)  # so that squares neither vanish nor overflow
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True)), widths


def _near(x: np.ndarray, y: np.ndarray, wx: np.ndarray, wy: np.ndarray, threshold: float) -> np.ndarray:
    k = min(x.shape[1], y.shape[1])
    return (x[:, :k] @ y[:, :k].T >= threshold) & (wx[:, None] == wy[None, :])


def _pass(rows: DataFrame, turn: int, threshold: float, block: int) -> DataFrame:
    """Edges (a, b) between reps that the windows of one pass link; at most two for each row.

    Blocks are cut by the row's number in the whole order, and each goes to its successor too, so windows depend neither on
    partitions nor on batches.
    """
    given = rows.select("label", F.element_at("codes", turn + 1).alias("code"), "rep", "v", F.lit(1).cast("long").alias("one"))
    numbered = running_total(given, ["label", "code", "rep"], "one", "row", "windows")
    at = F.floor(F.col("row") / block)
    both = numbered.select("label", "rep", "v", "row", F.explode(F.array(at, at + 1)).alias("block"))
    dealt = both.repartition(shuffle_width(rows.sparkSession), "block").sortWithinPartitions("block", "row").select("block", "row", "label", "rep", "v")

    def link(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        t = pa.Table.from_batches(held).combine_chunks()
        own = t.column("row").to_numpy() // block == t.column("block").to_numpy()
        label, rep = np.asarray(t.column("label").to_pylist(), object), t.column("rep").to_numpy()
        x, w = _unit(t.column("v").combine_chunks() if t.column("v").num_chunks != 1 else t.column("v").chunk(0))
        first = int((~own).sum())  # the rows of the block before; their own pairs are compared there
        near = _near(x, x[first:], w, w[first:], threshold) & (label[:, None] == label[None, first:])
        p, q = np.nonzero(near & (np.arange(len(x))[:, None] < np.arange(first, len(x))[None, :]))
        parent = np.arange(len(rep))
        union_pairs(parent, p, q + first)
        moved = np.flatnonzero(parent != np.arange(len(rep)))
        return pa.RecordBatch.from_arrays([pa.array(rep[moved]), pa.array(rep[parent[moved]])], names=["a", "b"])

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for b in batches:
            number = b.column(0).to_numpy(zero_copy_only=False)
            cuts = [0, *(np.flatnonzero(number[1:] != number[:-1]) + 1).tolist(), b.num_rows]
            for i, j in zip(cuts, cuts[1:], strict=False):
                piece = b.slice(i, j - i)
                if held and piece.num_rows and held[0].column(0)[0] != piece.column(0)[0]:
                    yield link(held)
                    held = []
                if piece.num_rows:
                    held.append(piece)
        if held:
            yield link(held)

    edges = keep(dealt.mapInArrow(windows, "a long, b long"), "passes")
    discard(numbered)
    return edges


def _counts(rows: DataFrame, threshold: float, most: int) -> DataFrame:
    """rep, links: over all pairs of a joined set (root), the rows at the other ends of links."""
    spark = rows.sparkSession
    part = F.greatest(F.lit(min(SMALL, most)), F.least(F.lit(most), F.ceil(F.count("*") / PARTS)))
    sizes = keep(rows.groupBy("root").agg(F.ceil(F.count("*") / part).cast("int").alias("parts")), "set-sizes")
    cut = rows.join(sizes, "root").withColumn("part", F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int"))
    dealt = cut.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select(
        "root", F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"), "part", "rep", "times", "v"
    )
    ordered = dealt.repartition(shuffle_width(spark), "root", "i", "j").sortWithinPartitions("root", "i", "j", "part", "rep")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def flush(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
            t = pa.Table.from_batches(parts).combine_chunks()
            part, rep, times = (t.column(k).to_numpy() for k in ("part", "rep", "times"))
            x, w = _unit(t.column("v").combine_chunks() if t.column("v").num_chunks != 1 else t.column("v").chunk(0))
            i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
            links = np.zeros(len(rep), np.int64)
            mine = part == i
            if i == j:
                for k in range(0, len(rep), 1024):
                    near = _near(x[k : k + 1024], x, w[k : k + 1024], w, threshold)
                    links[k : k + 1024] += near @ times - times[k : k + 1024] * near[np.arange(len(near)), np.arange(k, k + len(near))]
            else:
                for k in range(0, int(mine.sum()), 1024):
                    rows = np.flatnonzero(mine)[k : k + 1024]
                    near = _near(x[rows], x[~mine], w[rows], w[~mine], threshold)
                    links[rows] += near @ times[~mine]
                    links[~mine] += times[rows] @ near
            return pa.RecordBatch.from_arrays([pa.array(rep), pa.array(links)], names=["rep", "links"])

        held: list[pa.RecordBatch] = []
        for b in batches:
            keys = [b.column(k).to_numpy(zero_copy_only=False) for k in range(3)]
            change = np.flatnonzero(np.logical_or.reduce([k[1:] != k[:-1] for k in keys])) + 1
            cuts = [0, *change.tolist(), b.num_rows]
            for i, j in zip(cuts, cuts[1:], strict=False):
                piece = b.slice(i, j - i)
                if held and any(held[0].column(k)[0] != piece.column(k)[0] for k in range(3)):
                    yield flush(held)
                    held = []
                if piece.num_rows:
                    held.append(piece)
        if held:
            yield flush(held)

    return ordered.mapInArrow(count, "rep long, links long").groupBy("rep").agg(F.sum("links").alias("links"))


def near_vectors(vectors: DataFrame, key: str = "vec_id", vector: str = "embedding", label: str = "label", threshold: float = THRESHOLD, passes: int | None = None, bits: int = BITS, block: int = BLOCK, seed: int = SEED, most: int = SET) -> DataFrame:
    """key, n_links, component_id, kept: one row for each row of ``vectors``.

    Vectors link if their labels are equal and not null, they have the same width and their cosine is at least
    ``threshold``. A vector that is null, zero, or holds null or non-finite components links with nothing and is its own
    component; so is a row with a null key, whose component is null and which is not kept. Rows that repeat both key and
    vector count as other vectors. Unless given, ``passes`` follows from the size of the largest label.
    """
    given = vectors.select(F.col(key).alias("vec_id"), F.col(label).alias("label"), F.col(vector).cast("array<double>").alias("v"))
    one = keep(folded(given), "folded")
    if passes is None:
        passes = passes_for(one.groupBy("label").count().agg(F.max("count")).first()[0] or 0, threshold, block)
    rows = keep(coded(one, passes, bits, seed), "vectors")
    discard(one)
    edges = _pass(rows, 0, threshold, block)
    for turn in range(1, passes):
        edges = edges.unionByName(_pass(rows, turn, threshold, block))
    tree = keep(components(edges, "passes"), "roots")
    joined = rows.join(tree.withColumnRenamed("node", "rep"), "rep").select("root", "rep", "times", "v")
    links = _counts(joined, threshold, most)
    known = rows.select("label", "v", "rep", "times").join(tree.withColumnRenamed("node", "rep"), "rep", "left").join(links, "rep", "left")
    known = known.select("label", "v", F.coalesce("root", "rep").alias("component_id"), (F.coalesce("links", F.lit(0)) + F.col("times") - 1).alias("n_links"))
    known = keep(known, "known")  # a table of its own, so that the rows of a common vector can be split
    out = given.join(known, ["label", "v"], "left")
    component = F.when(F.col("vec_id").isNotNull(), F.coalesce("component_id", "vec_id"))
    return out.select(F.col("vec_id").alias(key), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(False)).alias("kept"))
