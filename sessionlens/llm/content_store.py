"""Token ids in a content-addressed store: rolling-hash chunks stored once, recipes, Merkle roots, verified reading.

Files, all written by Spark's own writers into the shared folder (Parquet as the container of binary columns):

* ``chunks``: digest (SHA-256 of the ids as little-endian 32-bit integers), n, payload (the ids, little-endian,
  ``width`` bytes each). Each digest is stored once.
* ``recipes``: one row for each document in ascending document id: start, n_tokens, the digests of its chunks in
  order, and root, the Merkle root over them.
* ``manifest``: for each block of the id stream how many documents begin in it, their ids, and a digest over their roots in
  order. Reading makes these anew from the recipes as read, so a recipe that is missing, repeated or replaced is noticed.

Chunk ends depend on the ids inside a document alone, so equal passages of different documents share chunks.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import keep, new_path, running_total, shuffle_width, slim, text_batches
from .tokens import byte_bpe

#: The public tokenizer's file, and the id that ends every document.
MODEL, END = "byte_bpe_50k.json", 0
#: Chunk lengths in ids: the least, the most, and the mean distance of cut points (a power of two).
LEAST, MOST, MEAN = 64, 4096, 512
#: Digests of late that a task doesn't send again; ids of a block of the manifest, and blocks of a group.
RECENT, BLOCK, GROUP = 10_000, 1 << 20, 4096

_ODD = np.uint64(0x9E3779B97F4A7C15)


def rolling_hash(ids: np.ndarray) -> np.ndarray:
    """A polynomial hash of the 16 ids that end at each position (fewer at the beginning), modulo 2^64."""
    with np.errstate(over="ignore"):
        h = (ids.astype(np.uint64) + np.uint64(1)) * _ODD
        h ^= h >> np.uint64(29)
        by = np.uint64(0xBF58476D1CE4E5B9)
        for back in (1, 2, 4, 8):
            shifted = np.zeros_like(h)
            shifted[back:] = h[:-back] * by
            h = h + shifted
            by = by * by
    return h


def cut_points(begin: int, end: int, marks: np.ndarray, least: int = LEAST, most: int = MOST) -> list[int]:
    """Ends of the chunks of one document, whose ids lie from begin to end. marks: positions that may end a chunk."""
    out, at = [], begin
    i = int(np.searchsorted(marks, begin + least - 1))
    j = int(np.searchsorted(marks, end - 1))
    for m in marks[i:j].tolist():
        while m + 1 - at > most:
            at += most
            out.append(at)
        if m + 1 - at >= least:
            at = m + 1
            out.append(at)
    while end - at > most:
        at += most
        out.append(at)
    if end > at:
        out.append(end)
    return out


def merkle_root(digests: list[bytes]) -> bytes:
    """Pairs are hashed together level by level; a last one without partner moves up. Of nothing: the hash of nothing."""
    if not digests:
        return hashlib.sha256(b"").digest()
    level = list(digests)
    while len(level) > 1:
        up = [hashlib.sha256(level[i] + level[i + 1]).digest() for i in range(0, len(level) - 1, 2)]
        level = up + level[len(level) & ~1 :]
    return level[0]


@dataclass
class Store:
    """Where a store lies, how wide its ids are, and of which type its documents' ids."""

    spark: SparkSession
    path: str
    recipes: DataFrame
    blocks: DataFrame
    width: int
    kind: T.DataType

    @property
    def chunks(self) -> DataFrame:
        """digest, n, payload, as the files hold them."""
        return self.spark.read.schema(_schema(self.kind)).parquet(self.path).where("kind = 0").select(F.col("key").alias("digest"), "n", "payload")


def _schema(kind: T.DataType) -> T.StructType:
    binary = T.BinaryType()
    names = ("kind", T.IntegerType()), ("key", binary), ("doc_id", kind), ("n", T.LongType()), ("payload", binary), ("digests", T.ArrayType(binary)), ("root", binary)
    return T.StructType([T.StructField(*n) for n in names])


class _Recent:
    """The digests of late, in two halves of bounded size."""

    def __init__(self, most: int):
        self.most, self.young, self.old = most, set(), set()

    def add(self, digest: bytes) -> bool:
        """Whether the digest is new here."""
        new = digest not in self.young and digest not in self.old
        if len(self.young) >= self.most:
            self.old, self.young = self.young, set()
        self.young.add(digest)
        return new


def write_store(docs: DataFrame, key: str = "doc_id", text: str = "text", model: str = MODEL, end: int = END, least: int = LEAST, most: int = MOST, mean: int = MEAN) -> Store:
    """Encodes every text and writes the store.

    A null text is empty and becomes the end id alone. Rows that share a document id are all written, ordered by
    Merkle root; a null id comes last. A task doesn't send a chunk again while it is one of the ``RECENT`` it met last, so a
    passage that a third of all documents share reaches its writer about once from each task.
    """
    spark = docs.sparkSession
    path = new_path(spark, "token-store")
    width = 2 if byte_bpe(model).kind.itemsize == 2 else 4
    kind = docs.schema[key].dataType
    schema = _schema(kind)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        bpe, part, row, sent = byte_bpe(model), TaskContext.get().partitionId(), 0, _Recent(RECENT)
        for b in text_batches(batches, "_t"):
            flat, offsets = bpe.encode(b.column(1))
            n = len(offsets) - 1
            ids = np.insert(flat, offsets[1:], end)  # after each text
            bounds = np.append(offsets[:-1] + np.arange(n), len(ids))
            marks = np.flatnonzero((rolling_hash(ids) >> np.uint64(40)) & np.uint64(mean - 1) == 0)
            wide = ids.astype("<u4")
            raw, slim_ids = memoryview(wide).cast("B"), memoryview(np.ascontiguousarray(ids)).cast("B")
            out = {f.name: [] for f in schema.fields}

            def put(*values):
                for column, v in zip(out.values(), values, strict=True):
                    column.append(v)

            for k, doc in enumerate(b.column(0).to_pylist()):
                i, j, digests = int(bounds[k]), int(bounds[k + 1]), []
                at = i
                for to in cut_points(i, j, marks, least, most):
                    d = hashlib.sha256(raw[4 * at : 4 * to]).digest()
                    digests.append(d)
                    if sent.add(d):
                        put(0, d, None, to - at, bytes(slim_ids[width * at : width * to]), None, None)
                    at = to
                put(1, part.to_bytes(8, "big") + row.to_bytes(8, "big"), doc, j - i, None, digests, merkle_root(digests))
                row += 1
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(out.values(), arrow_schema, strict=True)], schema=arrow_schema)
            del flat, ids, marks, wide, raw, slim_ids, out
        slim()

    from pyspark.sql.pandas.types import to_arrow_schema

    arrow_schema = to_arrow_schema(schema)
    sent = docs.select(F.col(key).alias("_k"), F.col(text).alias("_t")).mapInArrow(encode, schema)
    once = Window.partitionBy("kind", "key").orderBy("n")
    dealt = sent.repartition(shuffle_width(spark), "kind", "key").withColumn("_r", F.row_number().over(once)).where("_r = 1").drop("_r")
    dealt.write.option("compression", "zstd").partitionBy("kind").parquet(path)
    # an input without rows leaves no folder for a kind
    made = spark.read.schema(schema).parquet(path).where("kind = 1").select("doc_id", F.col("n").alias("n_tokens"), "digests", "root", F.col("key").alias("row_id"))
    recipes = running_total(made, [F.col("doc_id").asc_nulls_last(), "root", "row_id"], "n_tokens", "start", "token-recipes")
    return Store(spark, path, recipes, keep(_blocks(recipes), "token-manifest"), width, kind)


def _blocks(recipes: DataFrame) -> DataFrame:
    """block, docs, ids, digest: over the Merkle roots of the documents that begin in a block of the id stream, in order."""
    roots = F.sort_array(F.collect_list(F.struct("start", "row_id", "n_tokens", "root")))
    each = recipes.groupBy(F.floor(F.col("start") / BLOCK).alias("block")).agg(F.count("*").alias("docs"), F.sum("n_tokens").alias("ids"), roots.alias("r"))
    line = F.transform("r", lambda x: F.concat_ws(":", x["start"].cast("string"), x["n_tokens"].cast("string"), F.hex(x["root"])))
    return each.select("block", "docs", "ids", F.sha2(F.array_join(line, "|"), 256).alias("digest"))


def _chunk_sums(store: Store) -> DataFrame:
    """Of every stored chunk, from its file: digest, n, crc; good: its ids give the digest and the count."""
    width = store.width

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            crcs, good = [], []
            for d, n, p in zip(*(c.to_pylist() for c in b.columns), strict=True):
                raw = np.frombuffer(p, f"<u{width}").astype("<u4").tobytes()
                crcs.append(zlib.crc32(raw))
                good.append(hashlib.sha256(raw).digest() == d and len(raw) == 4 * n)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(crcs, pa.int64()), pa.array(good, pa.bool_())], names=["digest", "n", "crc", "good"])

    return store.chunks.mapInArrow(read, "digest binary, n long, crc long, good boolean")


def read_back(store: Store) -> DataFrame:
    """Reads chunks and recipes from the files: doc_id, start, n_tokens, ids_crc32, root, verified.

    The sum of a document comes from the sums of its chunks: appending a chunk is an affine map of the sum so far,
    the same for all chunks of a length, so ids need not travel. verified: every chunk is there, gives its digest
    and count, the Merkle root of the digests is the recipe's, and the manifest states the document's block as it is read.
    """
    sums = _chunk_sums(store)
    parts = store.recipes.select("row_id", F.posexplode("digests").alias("seq", "digest"))
    found = parts.join(sums, "digest", "left").groupBy("row_id").agg(F.sort_array(F.collect_list(F.struct("seq", "digest", "n", "crc", "good"))).alias("parts"))

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        zeros, blank = memoryview(bytes(1 << 16)), {}
        for b in batches:
            rows, crcs, counts, roots, good = [], [], [], [], []
            for r, ps in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                crc = n = 0
                for p in ps:
                    size = 4 * (p["n"] or 0)
                    pad = zeros[:size] if size <= len(zeros) else bytes(size)
                    if size not in blank:
                        blank[size] = zlib.crc32(pad)
                    crc = (p["crc"] or 0) ^ zlib.crc32(pad, crc) ^ blank[size]
                    n += p["n"] or 0
                rows.append(r)
                crcs.append(crc)
                counts.append(n)
                roots.append(merkle_root([p["digest"] for p in ps]))
                good.append(all(p["good"] for p in ps))
            yield pa.RecordBatch.from_arrays([pa.array(rows, pa.binary()), pa.array(crcs, pa.int64()), pa.array(counts, pa.int64()), pa.array(roots, pa.binary()), pa.array(good, pa.bool_())], names=["row_id", "ids_crc32", "read", "found", "good"])

    got = found.mapInArrow(whole, "row_id binary, ids_crc32 long, read long, found binary, good boolean")
    stated = store.blocks.select("block", "digest").withColumn("stated", F.lit(True))
    sound = _blocks(store.recipes).select("block", "digest").join(stated, ["block", "digest"], "left").select("block", F.coalesce("stated", F.lit(False)).alias("stated"))
    out = store.recipes.withColumn("block", F.floor(F.col("start") / BLOCK)).join(sound, "block", "left").join(got, "row_id", "left")
    whole_ones = F.col("stated") & F.col("good") & (F.col("found") == F.col("root")) & (F.col("read") == F.col("n_tokens"))
    return out.select("doc_id", "start", F.col("read").alias("n_tokens"), "ids_crc32", "root", F.coalesce(whole_ones, F.lit(False)).alias("verified"))


def manifest(store: Store, written: bool = True) -> DataFrame:
    """One row: docs, ids, and the digest of digests over groups of blocks in order, from the stored manifest, or from the
    recipes as they are read. What meets in one task is a digest for each group."""
    blocks = store.blocks if written else _blocks(store.recipes)

    def over(df: DataFrame, by) -> DataFrame:
        parts = F.sort_array(F.collect_list(F.struct("block", "digest")))
        each = df.groupBy(by.alias("block")).agg(F.sum("docs").alias("docs"), F.sum("ids").alias("ids"), parts.alias("r"))
        return each.select("block", "docs", "ids", F.sha2(F.array_join(F.transform("r", lambda x: x["digest"]), "|"), 256).alias("digest"))

    top = over(over(blocks, F.floor(F.col("block") / GROUP)), F.lit(0))
    return top.select("docs", "ids", F.col("digest").alias("root"))


def reconstruct(store: Store) -> DataFrame:
    """doc_id, ids: every document's ids, put together from the stored chunks (the end id included)."""
    width = store.width
    parts = store.recipes.select("row_id", "doc_id", F.posexplode("digests").alias("seq", "digest")).join(store.chunks, "digest")
    joined = parts.groupBy("row_id", "doc_id").agg(F.sort_array(F.collect_list(F.struct("seq", "payload"))).alias("p"))

    @F.pandas_udf("array<long>")
    def ids(ps: pd.Series) -> pd.Series:
        return ps.map(lambda xs: np.frombuffer(b"".join(bytes(x["payload"]) for x in xs), f"<u{width}").astype(np.int64))

    return joined.select("doc_id", ids("p").alias("ids"))
