"""SimHash near-dedup over a hierarchical index in Gray order.

1. Every whole text gets a 64-bit fingerprint from its word shingles.
2. Equal fingerprints are folded. The others are dealt to groups: the 64 bits are cut into blocks, and two
   fingerprints that differ in at most r bits agree on some (blocks - r) of them, so each fingerprint joins one group
   for each such choice of blocks. This is exact.
3. In each group fingerprints are sorted by Gray rank, neighbours in that order differ in few bits, and a tree is built
   over them: a node keeps the bits that all below it share. Pairs of nodes are followed downwards; a pair goes as
   soon as the shared bits differ in more than r places, and is linked whole once the bits that may differ are r at most.
   Sets already joined are not compared again, so a group of near copies costs about its size.
4. Each task returns a spanning forest of its links; star contractions join the forests.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from .common import components, discard, keep, shuffle_width, slim, text_batches, union_pairs, with_field

SHINGLE, RADIUS, SEED = 4, 4, 42
#: Children of a tree node; most pairs of nodes that are followed at once; most rows of a task that are indexed at once
#: (more only where one group has more).
FAN, PAIRS, ROWS = 8, 400_000, 400_000

_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


def fingerprint(text: str | None, shingle: int = SHINGLE, seed: int = SEED) -> int:
    """The unsigned fingerprint of a text: bit i is 1 where over half of the shingle hashes have it. No words: 0."""
    words = (text or "").encode().translate(_LOWER).split()
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    k = min(shingle, len(words))
    begins = np.concatenate([[0], ends[:-1]])[: len(words) - k + 1].tolist()
    hashes = np.fromiter((xxh64_intdigest(joined[i:j], seed) for i, j in zip(begins, (ends[k - 1 :] - 1).tolist(), strict=True)), np.uint64, len(begins))
    return majority(hashes)


def majority(hashes: np.ndarray) -> int:
    """The number whose bits are 1 where over half of the hashes have them; of no hashes: 0."""
    ones = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 8192):
        ones += np.unpackbits(hashes[i : i + 8192].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, key: str, text: str, shingle: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """key, fp: the fingerprint's 64 bits as a long. Rows are kept as they are, repeated and null keys too."""
    given = docs.select(F.col(key), F.col(text).alias("_t"))
    schema = with_field(given.select(key).schema, "fp", "long")

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in text_batches(batches, "_t"):
            fps = np.array([fingerprint(t, shingle, seed) for t in b.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps)], names=[key, "fp"])
        slim()

    return given.mapInArrow(make, schema)


def gray_rank(code: Column) -> Column:
    """The place of a code in Gray order: each bit becomes the parity of itself and all higher ones."""
    for s in (1, 2, 4, 8, 16, 32):
        code = code.bitwiseXOR(F.shiftrightunsigned(code, s))
    return code


def block_masks(blocks: int, radius: int) -> list[int]:
    """A mask for each choice of (blocks - radius) of the blocks into which 64 bits are cut."""
    edges = [round(64 * i / blocks) for i in range(blocks + 1)]
    bits = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in zip(edges, edges[1:], strict=False)]
    return [sum(chosen) for chosen in combinations(bits, blocks - radius)]


def forest_links(group: np.ndarray, codes: np.ndarray, radius: int, fan: int = FAN, pairs: int = PAIRS) -> np.ndarray:
    """Of codes sorted by (group, Gray rank): for each its least joined place, over links of at most radius bits in a group."""
    n = len(codes)
    parent = np.arange(n)
    if n < 2:
        return parent
    levels = []  # all-ones bits, any-ones bits, first child, end of children, first leaf
    low = high = codes
    owner, first = group, np.arange(n)
    while True:
        starts = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
        if levels and len(starts) == len(owner):
            break
        place = np.arange(len(owner)) - np.repeat(starts, np.diff(np.append(starts, len(owner))))
        heads = np.flatnonzero(place % fan == 0)
        low, high = np.bitwise_and.reduceat(low, heads), np.bitwise_or.reduceat(high, heads)
        owner, first = owner[heads], first[heads]
        levels.append((low, high, heads, np.append(heads[1:], len(place)), first))
    top = len(levels) - 1
    size = np.diff(np.append(levels[top][4], n))
    roots = np.flatnonzero(size > 1)
    stack = [(top, roots, roots)]
    while stack:
        level, a, b = stack.pop()
        if len(a) > pairs:
            half = len(a) // 2
            stack += [(level, a[half:], b[half:]), (level, a[:half], b[:half])]
            continue
        if not len(a):
            continue
        low, high, begin, end, first = levels[level]
        same = ~(low ^ high)
        both = same[a] & same[b]
        apart = (low[a] ^ low[b]) & both
        alike = np.bitwise_count(apart) <= radius
        whole = alike & (np.bitwise_count(apart | ~both) <= radius)
        if whole.any():
            wa, wb = a[whole], b[whole]
            union_pairs(parent, first[wa], first[wb])
            own = np.unique(np.concatenate([wa, wb]))  # all below such a node are within the radius of each other
            ends = np.append(first, n)[own + 1]
            count = ends - first[own]
            leaves = np.repeat(first[own] - np.cumsum(count) + count, count) + np.arange(count.sum())
            union_pairs(parent, np.repeat(first[own], count), leaves)
        a, b = a[alike & ~whole], b[alike & ~whole]
        if len(a) > 2000:  # nodes whose leaves are joined already
            least, most = np.minimum.reduceat(parent, first), np.maximum.reduceat(parent, first)
            open_ = ~((least[a] == most[a]) & (least[b] == most[b]) & (least[a] == least[b]))
            a, b = a[open_], b[open_]
        if not len(a):
            continue
        ka, kb = end[a] - begin[a], end[b] - begin[b]
        count = ka * kb
        if len(a) > 1 and count.sum() > 4 * pairs:
            half = len(a) // 2
            stack += [(level, a[half:], b[half:]), (level, a[:half], b[:half])]
            continue
        which = np.repeat(np.arange(len(a)), count)
        at = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        x, y = begin[a][which] + at // kb[which], begin[b][which] + at % kb[which]
        if level:
            ordered = x <= y
            stack.append((level - 1, x[ordered], y[ordered]))
        else:
            ordered = x < y
            x, y = x[ordered], y[ordered]
            near = np.bitwise_count(codes[x] ^ codes[y]) <= radius
            union_pairs(parent, x[near], y[near])
    return parent


def hamming_forest(codes: DataFrame, radius: int = RADIUS, blocks: int | None = None) -> DataFrame:
    """Edges (a, b) that join exactly the codes (column fp, distinct longs) linked by chains of at most radius bits.

    blocks: into how many the bits are cut, over radius. Unless given, as few as keep a group of random codes to
    about a thousand; every choice gives the same components.
    """
    spark = codes.sparkSession
    if blocks is None:
        n, blocks = codes.count(), radius + 1
        while blocks < radius + 4 and n / 2 ** (64 * (blocks - radius) / blocks) > 1000:
            blocks += 1
    masks = [m - (1 << 64) if m >> 63 else m for m in block_masks(blocks, radius)]
    dealt = codes.select(
        F.explode(F.array(*(F.struct(F.lit(i).alias("choice"), F.col("fp").bitwiseAND(F.lit(m)).alias("bits")) for i, m in enumerate(masks)))).alias("g"), "fp"
    ).select("g.choice", "g.bits", "fp", gray_rank(F.col("fp")).alias("rank"))
    ordered = dealt.repartition(shuffle_width(spark), "choice", "bits").sortWithinPartitions("choice", "bits", "rank").select("choice", "bits", "fp")

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def flush(c, g, f):
            group = np.cumsum(np.concatenate([[False], (c[1:] != c[:-1]) | (g[1:] != g[:-1])]))
            parent = forest_links(group, f.view(np.uint64), radius)
            moved = np.flatnonzero(parent != np.arange(len(f)))
            return pa.RecordBatch.from_arrays([pa.array(f[moved]), pa.array(f[parent[moved]])], names=["a", "b"])

        held = [np.empty(0, np.int64)] * 3
        for b in batches:
            held = [np.concatenate([h, c.to_numpy(zero_copy_only=False).astype(np.int64)]) for h, c in zip(held, b.columns, strict=True)]
            if len(held[0]) >= ROWS:
                c, g, _ = held
                change = np.flatnonzero((c[1:] != c[:-1]) | (g[1:] != g[:-1]))
                if len(change):  # the last group may go on
                    k = int(change[-1]) + 1
                    yield flush(*(h[:k] for h in held))
                    held = [h[k:] for h in held]
        if len(held[0]):
            yield flush(*held)

    return ordered.mapInArrow(link, "a long, b long")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = SHINGLE, radius: int = RADIUS, seed: int = SEED) -> DataFrame:
    """key, fingerprint (16 hex digits), component_id: the least key that chains of near fingerprints reach.

    One row for each row of ``docs``. Texts without words share fingerprint zero and are linked like any others.
    A null key never becomes a component's id unless the component has no other.
    """
    prints = keep(fingerprints(docs, key, text, shingle, seed), "fingerprints")
    nodes = keep(prints.groupBy("fp").agg(F.min(key).alias("_least")), "nodes")
    links = keep(hamming_forest(nodes.select("fp"), radius), "links")
    named = named_by_least(nodes, components(links, "links"), "fp")
    discard(links)
    return prints.join(named, "fp").select(key, F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def named_by_least(nodes: DataFrame, tree: DataFrame, node: str) -> DataFrame:
    """node, component_id: the least of the column ``_least`` in the node's component; a node outside ``tree`` is alone. A
    written table, so that joins with it can split the many rows of one node; so are the minima."""
    rooted = keep(nodes.join(tree.withColumnRenamed("node", node), node, "left").select(node, "_least", F.coalesce("root", node).alias("root")), "rooted")
    least = keep(rooted.groupBy("root").agg(F.min("_least").alias("component_id")), "least")
    named = keep(rooted.join(least, "root").select(node, "component_id"), "named")
    discard(rooted)
    discard(least)
    return named
