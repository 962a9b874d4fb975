"""Near copies by the similarity of whole shingle sets: every pair at or above the threshold is found.

1. Each text becomes the set of its word shingles (64-bit hashes) and the SimHash fingerprint of that set; equal sets are
   folded. The hierarchical index in Gray order (``simhash.hamming_forest``) links fingerprints of few differing bits, and
   whole sets decide about these candidates. This joins most copies; what follows finds the pairs that the index can't
   reach (at a similarity of 0.8 some ten of 64 bits differ), and skips what is joined already.
2. The shingles of all sets are put in one order, and each set hands out the first few of its own in that order: as many
   that two sets at or above the threshold must share one of them. Any order is exact; shingles that a sample finds in
   many texts come last, which keeps lists short.
3. The lists of a shared shingle give candidates, after bounds from the sizes and places. Neighbours in a list are paired
   first; what these have joined needs no comparing, and later rounds pair only sets of a list that still lie in
   different components and whose parity bitmaps (which can't differ in more bits than the sets in shingles) allow it.
   ``TREES`` rounds take a spanning forest of these pairs, so a large group of near copies gives candidates in proportion
   to its rows; the last round takes every pair that is left.
4. Candidates are compared by their whole sets, and star contractions join the links.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from xxhash import xxh64_intdigest

from .common import components, discard, keep, shuffle_width, slim, text_batches, union_pairs
from .simhash import _LOWER, RADIUS, hamming_forest, majority, named_by_least

#: Words of a shingle; the similarity (intersection over union) as a fraction, so that comparing is exact.
SHINGLE, SIMILARITY, SEED = 5, (4, 5), 42
#: Longest list whose pairs are looked at together with those of other lists; rows held by a task at once (more only
#: where one list has more).
SHORT, ROWS = 32, 400_000
#: Rounds that take a forest of the pairs left before all are taken; bits of a set's parity bitmap.
TREES, BITMAP = 1, 512
#: A text in SAMPLE is looked at for common shingles; those in OFTEN of them or more, MOST at most, come last. These
#: change the cost only.
SAMPLE, OFTEN, MOST = 16, 8, 100_000
#: Compression of the tables that hold texts: two of them and an exchange of all texts are the most that lies on disk.
CODEC = "zstd"

_ODD = np.uint64(0x9E3779B97F4A7C15)


def shingles(text: str | None, shingle: int = SHINGLE, seed: int = SEED) -> np.ndarray:
    """The sorted hashes of the different shingles of a text; fewer words than one shingle has are one shingle."""
    words = (text or "").encode().translate(_LOWER).split()
    if not words:
        return np.empty(0, np.uint64)
    k = min(shingle, len(words))
    each = np.fromiter((xxh64_intdigest(w, seed) for w in words), np.uint64, len(words))
    h = np.zeros(len(words) - k + 1, np.uint64)
    for i in range(k):
        h = h * _ODD + each[i : len(words) - k + 1 + i]
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    return np.unique(h)


def _common(docs: DataFrame, shingle: int, seed: int) -> np.ndarray:
    """Shingles that many of the sampled texts have, sorted."""
    sample = docs.where(F.pmod(F.xxhash64("text"), F.lit(SAMPLE)) == 0).select("text").distinct()

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in text_batches(batches, "text"):
            found = [shingles(t, shingle, seed) for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(found).view(np.int64))], names=["s"])
        slim()

    often = sample.mapInArrow(each, "s long").groupBy("s").count().where(F.col("count") >= OFTEN).orderBy(F.desc("count"), "s").limit(MOST)
    return np.sort(np.array([r["s"] for r in often.collect()], np.int64).view(np.uint64))


def _sets(docs: DataFrame, key: str, similarity: tuple[int, int], shingle: int, seed: int) -> DataFrame:
    """key, text, node: a hash of the set; fp: its fingerprint; parity: its bitmap; n: its size; first: the shingles it hands
    out, in order."""
    p, q = similarity
    last = _common(docs, shingle, seed)
    schema = T.StructType([docs.schema[key], T.StructField("text", T.StringType()), T.StructField("node", T.LongType()), T.StructField("fp", T.LongType()), T.StructField("parity", T.BinaryType()), T.StructField("n", T.LongType()), T.StructField("first", T.ArrayType(T.LongType()))])

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in text_batches(batches, "text"):
            node, print_, parity, size, first = [], [], [], [], []
            for t in b.column(1).to_pylist():
                s = shingles(t, shingle, seed)
                node.append(xxh64_intdigest(s.tobytes(), seed))
                print_.append(majority(s))
                parity.append(np.packbits(np.bincount((s >> np.uint64(20)) & np.uint64(BITMAP - 1), minlength=BITMAP).astype(np.uint8) & 1).tobytes())
                size.append(len(s))
                if len(s) and len(last):
                    at = np.minimum(np.searchsorted(last, s), len(last) - 1)
                    common = last[at] == s
                    s = np.concatenate([s[~common], s[common]])
                first.append(s[: len(s) + (-p * len(s) // q) + 1 if len(s) else 0].view(np.int64))
            flat = np.concatenate([np.empty(0, np.int64), *first])
            lists = pa.ListArray.from_arrays(np.cumsum([0, *map(len, first)]).astype(np.int32), pa.array(flat))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *(pa.array(np.array(x, np.uint64).view(np.int64)) for x in (node, print_)), pa.array(parity, pa.binary()), pa.array(size, pa.int64()), lists], names=[key, "text", "node", "fp", "parity", "n", "first"])
        slim()

    return docs.mapInArrow(make, schema)


def _possible(n: np.ndarray, at: np.ndarray, m: np.ndarray, bt: np.ndarray, similarity: tuple[int, int]) -> np.ndarray:
    """Whether sets of sizes n <= m, whose first common shingle lies at places at and bt, may reach the similarity."""
    p, q = similarity
    return (q * n >= p * m) & ((p + q) * np.minimum(n - at, m - bt) >= p * (n + m))


def _grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
    """Columns of rows sorted by the first one, cut so that no group is split; a bitmap gives a row of numbers."""
    held = None
    for b in batches:
        now = [np.frombuffer(b"".join(c.to_pylist()), np.uint64).reshape(-1, BITMAP // 64) if pa.types.is_binary(c.type) else c.to_numpy(zero_copy_only=False).astype(np.int64) for c in b.columns]
        held = now if held is None else [np.concatenate([h, c]) for h, c in zip(held, now, strict=True)]
        if len(held[0]) >= ROWS:
            change = np.flatnonzero(held[0][1:] != held[0][:-1])
            if len(change):
                k = int(change[-1]) + 1
                yield [h[:k] for h in held]
                held = [h[k:] for h in held]
    if held is not None and len(held[0]):
        yield held


def _round(lists: DataFrame, similarity: tuple[int, int]) -> DataFrame:
    """a, b: candidates, neighbours in a list that lie in different components (root). Rows with a null b are those of lists
    of three or more in several components: a, s, n, at."""

    def pair(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for s, n, node, at, root in _grouped(batches):
            same = s[1:] == s[:-1]
            i = np.flatnonzero(same & (root[1:] != root[:-1]))
            starts = np.flatnonzero(np.concatenate([[True], ~same]))
            length, mixed = np.diff(np.append(starts, len(s))), np.zeros(len(starts), bool)
            mixed[np.searchsorted(starts, i, side="right") - 1] = True
            open_ = np.repeat(mixed & (length > 2), length)
            i = i[_possible(n[i], at[i], n[i + 1], at[i + 1], similarity)]
            kind = np.repeat([False, True], [len(i), int(open_.sum())])
            zeros = np.zeros(len(i), np.int64)
            columns = [pa.array(np.concatenate([node[i + 1], np.zeros(int(open_.sum()), np.int64)]), mask=kind), *(pa.array(np.concatenate([zeros, c[open_]]), mask=~kind) for c in (s, n, at))]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([node[i], node[open_]])), *columns], names=["a", "b", "s", "n", "at"])
        slim()

    ordered = lists.repartition(shuffle_width(lists.sparkSession), "s").sortWithinPartitions("s", "n", "node").select("s", "n", "node", "at", "root")
    return ordered.mapInArrow(pair, "a long, b long, s long, n long, at long")


def _forest(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Which of the pairs (places in ``parent``) join all that the pairs join; each set takes its first pair, until none is
    left. ``parent`` is joined accordingly."""
    left, chosen = np.arange(len(a)), [np.empty(0, np.int64)]
    while True:
        x, y = parent[a[left]], parent[b[left]]
        left, x, y = left[x != y], x[x != y], y[x != y]
        if not len(left):
            return np.concatenate(chosen)
        first = np.full(len(parent), len(left))
        np.minimum.at(first, x, np.arange(len(left)))
        np.minimum.at(first, y, np.arange(len(left)))
        pick = left[np.unique(first[first < len(left)])]
        chosen.append(pick)
        union_pairs(parent, a[pick], b[pick])


def _apart(lists: DataFrame, similarity: tuple[int, int], forest: bool, turn: int = 0) -> DataFrame:
    """a, b: the candidate pairs of lists whose ends lie in different components (root), all of them or a spanning forest;
    turns begin with other pairs."""
    p, q = similarity

    def pair(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for s, n, node, at, root, parity in _grouped(batches):
            own, place = np.unique(node, return_inverse=True)
            roots = np.empty(len(own), np.int64)
            roots[place] = root
            _, first, of = np.unique(roots, return_index=True, return_inverse=True)
            parent, rng = first[of], np.random.default_rng(turn)

            def good(x, y):
                some = (parent[place[x]] != parent[place[y]]) & _possible(n[x], at[x], n[y], at[y], similarity)
                x, y = x[some], y[some]
                near = (p + q) * np.bitwise_count(parity[x] ^ parity[y]).sum(axis=1, dtype=np.int64) <= (q - p) * (n[x] + n[y])
                x, y = x[near], y[near]
                if forest:
                    mixed = rng.permutation(len(x)) if turn else np.arange(len(x))
                    x, y = x[mixed], y[mixed]
                    some = _forest(parent, place[x], place[y])
                    x, y = x[some], y[some]
                return pa.RecordBatch.from_arrays([pa.array(node[x]), pa.array(node[y])], names=["a", "b"])

            starts = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]]))
            length = np.diff(np.append(starts, len(s)))
            short = np.repeat(length <= SHORT, length)
            for d in range(2, SHORT):  # neighbours have been compared
                i = np.flatnonzero((s[d:] == s[:-d]) & short[d:])
                if not len(i):
                    break
                yield good(i, i + d)
            for i, many in zip(starts[length > SHORT].tolist(), length[length > SHORT].tolist(), strict=True):
                end = i + many
                for k in range(i, end, 256):
                    if (parent[place[i:end]] == parent[place[i]]).all():
                        break
                    x, y = np.nonzero((np.arange(k, min(k + 256, end))[:, None] < np.arange(k, end)[None, :]) & (parent[place[k : k + 256][: end - k]][:, None] != parent[place[k:end]][None, :]))
                    if len(x):
                        yield good(x + k, y + k)
        slim()

    ordered = lists.repartition(shuffle_width(lists.sparkSession), "s").sortWithinPartitions("s", "n", "node").select("s", "n", "node", "at", "root", "parity")
    return ordered.mapInArrow(pair, "a long, b long")


def _links(pairs: DataFrame, nodes: DataFrame, similarity: tuple[int, int], shingle: int, seed: int) -> DataFrame:
    """The pairs whose whole sets reach the similarity."""
    p, q = similarity
    pairs = keep(pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "candidates")
    ends = pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct()
    texts = keep(nodes.select("node", "text").join(ends, "node", "left_semi"), "texts", CODEC)
    both = pairs.join(texts.select(F.col("node").alias("a"), F.col("text").alias("ta")), "a").join(texts.select(F.col("node").alias("b"), F.col("text").alias("tb")), "b")

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in text_batches(batches, "ta"):
            for b in text_batches(iter([whole]), "tb"):
                good = []
                for x, y in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True):
                    x, y = shingles(x, shingle, seed), shingles(y, shingle, seed)
                    good.append((p + q) * len(np.intersect1d(x, y, assume_unique=True)) >= p * (len(x) + len(y)))
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(good))
        slim()

    links = keep(both.select("a", "b", "ta", "tb").mapInArrow(check, "a long, b long"), "links")
    discard(pairs)
    discard(texts)
    return links


def _close(nodes: DataFrame, radius: int) -> DataFrame:
    """a, b: candidate pairs from the fingerprints: those of the index's forest, and nodes of one fingerprint with their least."""
    prints = keep(nodes.groupBy("fp").agg(F.min("node").alias("head")), "prints")
    forest = hamming_forest(prints.select("fp"), radius)
    ends = forest.join(prints.select(F.col("fp").alias("a"), F.col("head").alias("x")), "a").join(prints.select(F.col("fp").alias("b"), F.col("head").alias("y")), "b")
    same = nodes.join(prints, "fp").where("node <> head").select("node", "head")
    return ends.select(F.col("x").alias("a"), F.col("y").alias("b")).union(same)


def near_copies(docs: DataFrame, key: str = "doc_id", text: str = "text", similarity: tuple[int, int] = SIMILARITY, shingle: int = SHINGLE, seed: int = SEED, radius: int = RADIUS) -> DataFrame:
    """key, component_id: the least key that chains of texts at or above the similarity reach; one row for each row of
    ``docs``. Texts without words are alike. A null key is a component's id only where the component has no other."""
    given = docs.select(F.col(key), F.col(text).alias("text"))
    sets = keep(_sets(given, key, similarity, shingle, seed), "sets", CODEC)
    nodes = sets.groupBy("node").agg(F.first(F.struct("text", "fp", "parity", "n", "first")).alias("r"), F.min(key).alias("_least"))
    nodes = keep(nodes.select("node", "r.*", "_least"), "nodes", CODEC)
    members = keep(sets.select(key, "node"), "members")
    discard(sets)
    root = F.coalesce("root", "node").alias("root")
    lists = nodes.select("node", "n", F.col("node").alias("root"), F.posexplode("first").alias("at", "s")).withColumn("at", F.col("at").cast("long"))
    found = keep(_round(lists, similarity), "pairs")
    edges = _links(_close(nodes, radius).union(found.where("b is not null").select("a", "b")), nodes, similarity, shingle, seed)
    tree = keep(components(edges, "links"), "roots")
    left = found.where("b is null").select(F.col("a").alias("node"), "s", "n", "at")
    if not left.isEmpty():
        left = keep(left.join(nodes.select("node", "parity"), "node"), "lists")
        for turn in range(TREES + 1):
            rooted = left.join(tree, "node", "left").select("node", "s", "n", "at", "parity", root)
            more = _links(_apart(rooted, similarity, turn < TREES, turn), nodes, similarity, shingle, seed)
            if not more.isEmpty():
                edges = edges.union(more)
                tree = keep(components(edges, "links"), "roots")
        discard(left)
    named = named_by_least(nodes.select("node", "_least"), tree, "node")
    discard(found)
    discard(nodes)
    return members.join(named, "node").select(key, "component_id")


def one_of_each(docs: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` without near copies: of each component the row with the least key (nulls last) and, where a key
    is repeated, the least text hash. Rows that share key and text are one document and stay once."""
    names = docs.columns
    own = "_row" + "_" * max(map(len, names))  # a name that docs doesn't have
    given = docs.withColumn(own, F.struct(F.col(key).isNull().alias("none"), F.col(key).alias("key"), F.xxhash64(text).alias("of")))
    found = near_copies(given.select(own, F.col(text).alias("text")), own, "text", **options)
    kept = keep(found.where(F.col(own) == F.col("component_id")).select(own).distinct(), "kept")
    return given.join(kept, own, "left_semi").dropDuplicates([own]).select(*names)
