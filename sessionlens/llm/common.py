"""What several operators share: kept tables, running totals and connected components."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from xxhash import xxh3_128_digest


#: Edges that a task reduces to a forest at once, and that one task finishes.
EDGES = 1_000_000

#: Folders made for local applications that name none.
_OWN: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors see: ``spark.checkpoint.dir``. Where it is unset a local master gets a fresh folder of
    its own (tests); a cluster raises an error, since no folder of one machine would do."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        app = spark.sparkContext.applicationId
        if app not in _OWN:
            _OWN[app] = "file://" + tempfile.mkdtemp(prefix="sessionlens-")
        found = _OWN[app]
    return found.rstrip("/")


def new_path(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"


def keep(df: DataFrame, what: str = "table", codec: str | None = None) -> DataFrame:
    """Writes df once to the shared folder and reads it back; later steps survive the loss of any executor. codec: how the
    files are compressed, where that isn't left to the session."""
    path = new_path(df.sparkSession, what)
    (df.write.option("compression", codec) if codec else df.write).parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._kept_path = path
    return out


def discard(df: DataFrame) -> None:
    """Deletes a kept table that nothing will read again."""
    path = getattr(df, "_kept_path", None)
    if path:
        jvm = df.sparkSession._jvm
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(at, True)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def running_total(df: DataFrame, keys: Sequence, value: str, out: str, what: str = "ordered") -> DataFrame:
    """Adds ``out``: the sum of ``value`` over all rows before this one in the order of ``keys``.

    Range-partitions and sorts by the keys, sums inside each partition while rows stream past, and adds each
    partition's offset. Only one number for each partition reaches the driver. ``value`` must be a long without
    nulls. The result lies in the shared folder, sorted by the keys within and across its files.
    """
    spark = df.sparkSession
    schema = T.StructType([*df.schema.fields, T.StructField("_part", T.IntegerType()), T.StructField(out, T.LongType())])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, before = TaskContext.get().partitionId(), 0
        for b in batches:
            v = b.column(b.schema.get_field_index(value)).to_numpy(zero_copy_only=False).astype(np.int64)
            ends = np.cumsum(v)
            starts = ends - v + before
            before += int(ends[-1]) if len(ends) else 0
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.full(len(v), part, np.int32)), pa.array(starts)], names=[*b.schema.names, "_part", out])

    ordered = df.repartitionByRange(shuffle_width(spark), *keys).sortWithinPartitions(*keys)
    held = keep(ordered.mapInArrow(add, schema), what)
    offsets, before = [], 0
    for r in held.groupBy("_part").agg(F.sum(value).alias("s")).orderBy("_part").collect():  # a row for each partition
        offsets.append((r["_part"], before))
        before += r["s"]
    table = spark.createDataFrame(offsets, "_part int, _before long")
    summed = held.join(F.broadcast(table), "_part").withColumn(out, F.col(out) + F.col("_before")).drop("_part", "_before")
    summed._kept_path = held._kept_path
    return summed


def _forests(edges: DataFrame, every: bool) -> DataFrame:
    """lo, hi: of each run of ``EDGES`` edges in a task every node but the least of its set, beside that least one (``every``: and
    the least beside itself)."""

    def join(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        a, b = (pa.concat_arrays([x.column(i) for x in held]) for i in (0, 1))
        nodes = pc.unique(pa.concat_arrays([a, b]))
        nodes = nodes.take(pc.sort_indices(nodes))
        parent = np.arange(len(nodes))
        union_pairs(parent, *(pc.index_in(x, value_set=nodes).to_numpy(zero_copy_only=False).astype(np.int64) for x in (a, b)))
        hi = np.arange(len(nodes)) if every else np.flatnonzero(parent != np.arange(len(nodes)))
        return pa.RecordBatch.from_arrays([nodes.take(pa.array(parent[hi])), nodes.take(pa.array(hi))], names=["lo", "hi"])

    def reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for b in batches:
            held.append(b)
            n += b.num_rows
            if n >= EDGES and not every:
                yield join(held)
                held, n = [], 0
        if n:
            yield join(held)
        slim()

    return edges.mapInArrow(reduce, edges.schema)


def components(edges: DataFrame, what: str = "edges") -> DataFrame:
    """Connected components of the undirected ``edges`` (columns a, b): rows (node, root) for every node of an
    edge with two different ends, root being the smallest node reachable.

    First every task reduces the edges it has to a forest, ``EDGES`` of them at a time. What is left is finished in one task
    if it is ``EDGES`` at most. Until it is, two star contractions alternate: every node hands its larger neighbours to its
    smallest one, then its smaller ones to the smallest. The number of edges never grows, nothing but a checksum reaches
    the driver, and each round is written to the shared folder. So are the minima of a round: joined from a table of their
    own, the many edges of a hub can be split over tasks.
    """
    pairs = edges.where("a <> b").select(F.col("a").alias("lo"), F.col("b").alias("hi"))
    now = keep(_forests(pairs, False), what)
    last = None
    while True:
        mark = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("lo", "hi").cast("decimal(38,0)")).alias("h")).first()
        if mark["n"] <= EDGES:
            return _forests(now.repartition(1), True).select(F.col("hi").alias("node"), F.col("lo").alias("root"))
        if mark == last:
            return now.select(F.col("hi").alias("node"), F.col("lo").alias("root")).union(now.select(F.col("lo"), F.col("lo")).distinct())
        last = mark
        both = now.select(F.col("lo").alias("u"), F.col("hi").alias("v")).union(now.select("hi", "lo"))
        least = keep(both.groupBy("u").agg(F.least("u", F.min("v")).alias("m")), what)
        large = both.join(least, "u").where("v > u").select(F.col("m").alias("lo"), F.col("v").alias("hi")).distinct()
        low = keep(large.groupBy("hi").agg(F.min("lo").alias("m")), what)
        small = large.join(low, "hi").where("lo <> m").select(F.col("m").alias("lo"), F.col("lo").alias("hi"))
        then = keep(small.union(low.select(F.col("m"), F.col("hi"))).distinct(), what)
        for gone in (now, least, low):
            discard(gone)
        now = then


def union_pairs(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Joins the sets of a[i] and b[i] in ``parent``, in which every entry points straight at its set's least member."""
    while len(a):
        ra, rb = parent[a], parent[b]
        apart = ra != rb
        if not apart.any():
            return
        a, b, ra, rb = a[apart], b[apart], ra[apart], rb[apart]
        np.minimum.at(parent, np.maximum(ra, rb), np.minimum(ra, rb))
        while True:
            up = parent[parent]
            if (up == parent).all():
                break
            parent[:] = up


def text_batches(batches: Iterator[pa.RecordBatch], column: str, most: int = 2_000_000) -> Iterator[pa.RecordBatch]:
    """Cuts Arrow batches so that each holds about ``most`` bytes of ``column`` and at least one row."""
    for b in batches:
        for i, j in _cuts(b.column(b.schema.get_field_index(column)), most):
            yield b.slice(i, j - i)


def text_values(texts: Iterator[pa.Array], make: Callable[[pa.Array], pa.Array], most: int = 2_000_000) -> Iterator[pa.Array]:
    """For Arrow UDFs: what ``make`` gives for each array of texts, called with about ``most`` bytes at a time."""
    for t in texts:
        made = [make(t.slice(i, j - i)) for i, j in _cuts(t, most)]
        yield pa.concat_arrays(made) if made else make(t)
        slim()


def _cuts(texts: pa.Array, most: int) -> list[tuple[int, int]]:
    if len(texts) == 0:
        return []
    sizes = pc.binary_length(texts).fill_null(0).to_numpy(zero_copy_only=False)
    at = (np.cumsum(sizes.astype(np.int64)) - 1).clip(0) // most
    cuts = [0, *(np.flatnonzero(np.diff(at)) + 1).tolist(), len(texts)]
    return list(zip(cuts, cuts[1:], strict=False))


def slim() -> None:
    """Gives memory that is free in this process back to the system, so that workers that wait for a task hold little."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


class UnitCache:
    """A cache of fixed size from short texts to a few numbers each, in arrays: four places for each group of keys, one of
    which, at random, is overwritten when all are taken. Keys are told apart by 128-bit hashes.

    ``entries`` (a power of two) x (16 bytes + ``width`` numbers) is all it ever holds: 32 MB for the tokenizers' units.
    """

    def __init__(self, width: int, kind: np.dtype, entries: int = 1 << 20, seed: int = 1):
        sets = max(entries // 4, 1)
        self.mask = np.uint64(sets - 1)
        self.tags, self.values = np.zeros((sets, 4, 2), np.uint64), np.zeros((sets, 4, width), kind)
        self.random = np.random.default_rng(seed)

    def get(self, keys: Sequence[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Whether each key is held, its numbers (anything where it isn't), and its hash, for ``put``."""
        hashes = np.frombuffer(b"".join(map(xxh3_128_digest, keys)), "<u8").reshape(-1, 2)
        at = hashes[:, 0] & self.mask
        same = (self.tags[at] == hashes[:, None, :]).all(axis=2)
        place = same.argmax(axis=1)
        return same[np.arange(len(at)), place], self.values[at, place], hashes

    def put(self, hashes: np.ndarray, values: np.ndarray) -> None:
        at = hashes[:, 0] & self.mask
        free = ~self.tags[at].any(axis=2)
        place = np.where(free.any(axis=1), free.argmax(axis=1), self.random.integers(0, 4, len(at)))
        one = np.unique(at.astype(np.int64) * 4 + place, return_index=True)[1]  # of keys that meet in a place
        self.tags[at[one], place[one]] = hashes[one]
        self.values[at[one], place[one]] = values[one]


def with_field(schema: T.StructType, name: str, kind: str) -> T.StructType:
    """A copy of the schema with one more field."""
    return T.StructType([*schema.fields, *T.StructType().add(name, kind).fields])
