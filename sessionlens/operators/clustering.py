"""Weighted fuzzy c-means and k-means over sparse points, any number of runs in one pass over the data.

Only sums leave a task: for each run and cluster the mass and the weighted sum of points, and the run's objective and
compactness. They leave in blocks of coordinates, are added by block, and only the new centres return to the driver. The
points are read from one table in every pass; memberships are never stored. Runs whose centres together are larger than
``BUDGET`` go in several passes; a single run must fit it.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.stage import settle

#: Distances (squared) up to this count as none.
EPS = 1e-18
#: Up to so many coordinates a batch is made dense; beyond, sums run over the entries that are there. Rows of a dense batch:
#: few, so that a run's distances stay in the processor's cache.
DENSE, ROWS = 4096, 512
#: Bytes of centres that a pass broadcasts and the driver holds; numbers of a block of sums; bytes of all tasks' sums that
#: may go straight to the driver.
BUDGET, BLOCK, DIRECT = 256_000_000, 1 << 16, 32_000_000


@dataclass
class Run:
    """One clustering: its centres and how they are moved."""

    centres: np.ndarray
    q: float = 2.0
    weighting: str = "soft"
    update: str = "objective"
    name: str = ""
    iterations: int = 0
    converged: bool = False
    j: float = math.nan
    mass: float = math.nan
    compactness: float = math.nan
    weighed: float = math.nan
    points: float = math.nan
    trace: list[float] = field(default_factory=list)

    @property
    def separation(self) -> float:
        v = self.centres
        if len(v) < 2:
            return math.nan
        return float(min(((v[j + 1 :] - v[j]) ** 2).sum(axis=1).min() for j in range(len(v) - 1)))

    @property
    def validity(self) -> float:
        """Compactness over separation; lower is better. Not a number for a single cluster."""
        s = self.separation
        return self.compactness / (self.points * s) if s > 0 else (math.inf if s == 0 else math.nan)

    @property
    def weighted_validity(self) -> float:
        """The same with every session counted by its weight."""
        s = self.separation
        return self.weighed / (self.mass * s) if s > 0 and self.mass > 0 else (math.inf if s == 0 else math.nan)

    def degenerate(self, eps: float = 1e-6) -> bool:
        return not self.separation >= eps


def distances(x: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Squared Euclidean distances of rows to centres."""
    return np.maximum((x * x).sum(axis=1)[:, None] + (v * v).sum(axis=1)[None, :] - 2 * (x @ v.T), 0.0)


def membership(d: np.ndarray, q: float) -> np.ndarray:
    """Shares of each row in the clusters, from squared distances. q = 1 gives all to the nearest, the first of equals. A row
    on one or more centres belongs to these in equal parts."""
    if q <= 1:
        u = np.zeros_like(d)
        u[np.arange(len(d)), d.argmin(axis=1)] = 1.0
        return u
    on = d <= EPS
    with np.errstate(divide="ignore", invalid="ignore"):
        if q == 2:
            u = 1.0 / d
        else:
            e = -np.log(d) / (q - 1)
            u = np.exp(e - e.max(axis=1, keepdims=True))
        u /= u.sum(axis=1, keepdims=True)
    hit = on.any(axis=1)
    u[hit] = on[hit] / on[hit].sum(axis=1, keepdims=True)
    return u


@dataclass
class _Sparse:
    idx: np.ndarray
    val: np.ndarray
    row: np.ndarray
    n: int

    def dots(self, v: np.ndarray) -> np.ndarray:
        out = np.zeros((self.n, len(v)))
        for i in range(0, len(self.idx), 200_000):
            s = slice(i, i + 200_000)
            np.add.at(out, self.row[s], v.T[self.idx[s]] * self.val[s, None])
        return out

    def sums(self, m: np.ndarray, width: int) -> np.ndarray:
        out = np.zeros((width, m.shape[1]))
        for i in range(0, len(self.idx), 200_000):
            s = slice(i, i + 200_000)
            np.add.at(out, self.idx[s], m[self.row[s]] * self.val[s, None])
        return out.T


def _batch(idx: pa.Array, val: pa.Array, width: int):
    """The rows of a batch, dense or sparse, and their squared lengths."""
    n = np.diff(np.asarray(idx.offsets))
    row, i, x = np.repeat(np.arange(len(n)), n), idx.flatten().to_numpy(), val.flatten().to_numpy().astype(float)
    if width <= DENSE:
        dense = np.zeros((len(n), width))
        dense[row, i] = x
        return dense, (dense * dense).sum(axis=1)
    s = _Sparse(i, x, row, len(n))
    return s, np.bincount(row, x * x, len(n))


def _sums(x, norm2: np.ndarray, run: Run, mult: np.ndarray, w: np.ndarray, width: int, room: tuple[np.ndarray, np.ndarray] | None = None) -> np.ndarray:
    """A run's sums over a batch, flat: masses, weighted points, J, compactness without and with weights, weight, points.

    Clusters are rows here, so that every step runs along the points, in the two arrays of ``room``. With r the distances over
    the nearest one and t = r ** (-1 / (q - 1)), the shares are u = t / s (s: their sum), and u ** q = t / r / s ** q: one
    logarithm and one exponential for each point and cluster.
    """
    v, q, n = run.centres, run.q, len(norm2)
    r, t = room if room else (np.empty(len(v) * n), np.empty(len(v) * n))
    r, t = (a[: len(v) * n].reshape(len(v), n) for a in (r, t))
    if isinstance(x, np.ndarray):
        np.matmul(-2 * v, x.T, out=r)
    else:
        np.multiply(x.dots(v).T, -2, out=r)
    r += norm2
    r += (v * v).sum(axis=1)[:, None]
    near = r.min(axis=0)
    if (near < 0).any():
        np.maximum(r, 0.0, out=r)
        near = np.maximum(near, 0.0)
    hit = near <= EPS
    unit = np.where(hit, 1.0, near)
    r /= unit
    if q <= 1:
        t[:] = 0.0
        t[r.argmin(axis=0), np.arange(n)] = 1.0
    else:
        with np.errstate(divide="ignore", over="ignore"):  # points on centres
            if q == 2:
                np.divide(1.0, r, out=t)
            else:
                np.log(r, out=t)
                t *= -1 / (q - 1)
                np.exp(t, out=t)
        if hit.any():
            t[:, hit] = r[:, hit] <= EPS
    s = t.sum(axis=0)
    spread = unit * np.einsum("ij,ij,ij->j", t, t, r) / (s * s)
    if q > 1:
        if hit.any():
            r[:, hit] = 1.0
        t /= r
    count = w if run.weighting == "hard" else mult  # removed sessions are no points
    t *= (w if run.update == "objective" else count) / s**q
    moved = t @ x if isinstance(x, np.ndarray) else x.sums(np.ascontiguousarray(t.T), width)
    return np.concatenate([t.sum(axis=1), moved.ravel(), [(w * near * s ** (1 - q)).sum(), (count * spread).sum(), (w * spread).sum(), w.sum(), count.sum()]])


def shards(runs: Sequence[Run], width: int, budget: int = BUDGET) -> list[list[Run]]:
    """The runs in groups whose centres (8 bytes a coordinate) keep to the budget."""
    out, held = [], 0
    for r in runs:
        size = 8 * len(r.centres) * (width + 1)
        if size > budget:
            raise ValueError(f"{len(r.centres)} centres of {width} coordinates take {size} bytes; the budget is {budget}: prune URLs first")
        if not out or held + size > budget:
            out.append([])
            held = 0
        out[-1].append(r)
        held += size
    return out


def gather_sums(points: DataFrame, runs: Sequence[Run], width: int, rows: int = 8192, budget: int = BUDGET) -> list[np.ndarray]:
    """The sums of all runs: columns idx, val, mult and one for each weighting in use. One pass for each shard of runs."""
    return [s for some in shards(runs, width, budget) for s in _gather(points, some, width, rows)]


def _gather(points: DataFrame, runs: Sequence[Run], width: int, rows: int) -> list[np.ndarray]:
    spark = points.sparkSession
    names = sorted({r.weighting for r in runs})
    sent = spark.sparkContext.broadcast(list(runs))  # within the budget
    step = min(rows, ROWS) if width <= DENSE else rows
    sizes = [len(r.centres) * (1 + width) + 5 for r in runs]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, most = None, max(len(r.centres) for r in sent.value)
        room = np.empty(most * step), np.empty(most * step)
        for big in batches:
            for i in range(0, big.num_rows, step):
                b = big.slice(i, step)
                x, norm2 = _batch(b.column(0), b.column(1), width)
                mult = b.column(2).to_numpy().astype(float)
                w = {n: b.column(3 + k).to_numpy().astype(float) for k, n in enumerate(names)}
                total = np.zeros(sum(sizes)) if total is None else total
                at = 0
                for r, size in zip(sent.value, sizes, strict=True):
                    total[at : at + size] += _sums(x, norm2, r, mult, w[r.weighting], width, room)
                    at += size
        yield from blocks({} if total is None else {k: total[k * BLOCK : (k + 1) * BLOCK] for k in range(-(-len(total) // BLOCK))})

    def blocks(sums: dict[int, np.ndarray]) -> Iterator[pa.RecordBatch]:
        for k, v in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([v.tobytes()], pa.binary())], names=["block", "s"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for b in batches:
            for k, s in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                got = np.frombuffer(s)
                sums[k] = sums[k] + got if k in sums else got
        yield from blocks(sums)

    part = points.select("idx", "val", F.col("mult").cast("double"), *(F.col(n).cast("double") for n in names)).mapInArrow(work, "block int, s binary")
    tasks, count = _tasks(points), -(-sum(sizes) // BLOCK)
    if 8 * tasks * sum(sizes) > DIRECT:  # added by block, so that the driver gets each sum once; of many tasks in two levels
        level = math.isqrt(tasks)
        if level > 16:
            salted = part.withColumn("salt", F.pmod(F.spark_partition_id(), F.lit(level))).repartition(min(level * count, tasks), "block", "salt")
            part = salted.select("block", "s").mapInArrow(add, "block int, s binary")
        part = part.repartition(min(count, tasks), "block").mapInArrow(add, "block int, s binary")
    total = np.zeros(sum(sizes))
    for r in part.collect():
        total[r["block"] * BLOCK :][: len(r["s"]) // 8] += np.frombuffer(r["s"])
    sent.unpersist()
    return np.split(total, np.cumsum(sizes)[:-1])


#: Partitions of the tables that passes read, by their plan.
_PARTS: dict[int, tuple[DataFrame, int]] = {}


def _tasks(points: DataFrame) -> int:
    """How many tasks read the points; planned once for a table, not in every pass."""
    if id(points) not in _PARTS or _PARTS[id(points)][0] is not points:
        _PARTS.clear()
        _PARTS[id(points)] = points, points.rdd.getNumPartitions()
    return _PARTS[id(points)][1]


def _take(run: Run, sums: np.ndarray, width: int) -> np.ndarray:
    """Notes the run's measures and returns its new centres; a cluster without mass keeps its own."""
    c = len(run.centres)
    mass, moved = sums[:c], sums[c : c * (1 + width)].reshape(c, width)
    run.j, run.compactness, run.weighed, run.mass, run.points = (float(s) for s in sums[-5:])
    new = run.centres.copy()
    some = mass > 0
    new[some] = moved[some] / mass[some, None]
    return new


def iterate(points: DataFrame, runs: Sequence[Run], width: int, tol: float = 1e-5, max_iter: int = 100, criterion: str = "centres", watch: Callable | None = None) -> list[Run]:
    """Moves the centres of all runs until each stands still. Runs that have ended leave the passes.

    criterion: 'centres' (largest move at most tol) or 'J' (relative fall at most tol). Memberships are never stored, so
    their change is no criterion here; they are a function of the centres. The last pass measures J and compactness for the
    centres returned.
    """
    if criterion not in ("centres", "J"):
        raise ValueError(f"no such criterion: {criterion}")
    runs, active = list(runs), [r for r in runs if max_iter > 0]
    while active:
        still = []
        for run, sums in zip(active, gather_sums(points, active, width), strict=True):
            last = run.j
            new = _take(run, sums, width)
            run.trace.append(run.j)
            move = float(np.abs(new - run.centres).max()) if new.size else 0.0
            run.centres, run.iterations = new, run.iterations + 1
            run.converged = (abs(last - run.j) <= tol * max(abs(run.j), 1e-300)) if criterion == "J" else move <= (0.0 if run.q <= 1 else tol)
            if not run.converged and run.iterations < max_iter:
                still.append(run)
        if watch:
            watch(active)
        active = still
    for run, sums in zip(runs, gather_sums(points, runs, width), strict=True):
        _take(run, sums, width)
    return runs


def spread(points: DataFrame) -> DataFrame:
    """The points, written once in as many files as there are shuffle partitions, so that a pass over few of them keeps every
    core busy too."""
    return settle(points.repartition(int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))), "points")


# ---- starts
def starts(points: DataFrame, c: int, width: int, how: str = "hash", seed: int = 1, pool: int = 2048) -> np.ndarray:
    """c different points as centres: 'hash' takes those of least hash, 'first' the least vectors, 'farthest' picks from a
    hashed pool the point farthest from those picked (the pool's size is a bound on what the driver holds)."""
    order = [F.col("idx"), F.col("val")] if how == "first" else [F.xxhash64("idx", "val", F.lit(seed)), F.col("idx"), F.col("val")]
    rows = points.select("idx", "val").distinct().orderBy(*order).limit(pool if how == "farthest" else c).collect()
    x = np.zeros((len(rows), width))
    for k, r in enumerate(rows):
        x[k, r["idx"]] = r["val"]
    if len(x) < c:
        raise ValueError(f"{len(x)} different points for {c} clusters")
    if how != "farthest":
        return x
    picked, near = [0], distances(x, x[:1])[:, 0]
    while len(picked) < c:
        picked.append(int(near.argmax()))
        near = np.minimum(near, distances(x, x[picked[-1:]])[:, 0])
    return x[picked]


def fcm(points: DataFrame, c: int, width: int, q: float = 2.0, weighting: str = "soft", update: str = "objective", init="farthest", tol: float = 1e-5, max_iter: int = 100, seed: int = 1) -> Run:
    """Weighted fuzzy c-means. q = 1 is k-means. update: 'objective' moves centres to the weighted means that minimise J;
    'as_printed' leaves the session weight out of the centres. init: a kind of ``starts``, 'kmeans', or centres."""
    v = init if isinstance(init, np.ndarray) else starts(points, c, width, "farthest" if init == "kmeans" else init, seed)
    if isinstance(init, str) and init == "kmeans":
        v = kmeans(points, c, width, weighting, v, max_iter).centres
    return iterate(points, [Run(v.copy(), q, weighting, update)], width, tol, max_iter)[0]


def kmeans(points: DataFrame, k: int, width: int, weighting: str = "none", init="hash", max_iter: int = 100, seed: int = 1) -> Run:
    """Crisp clusters; stops when no centre moves."""
    v = init if isinstance(init, np.ndarray) else starts(points, k, width, init, seed)
    return iterate(points, [Run(v.copy(), 1.0, weighting)], width, 0.0, max_iter)[0]


def sweep(points: DataFrame, counts: Sequence[int], width: int, q: float = 2.0, weightings: Sequence[str] = ("soft", "none"), restarts: int = 1, init: str = "farthest", update: str = "objective", tol: float = 1e-4, max_iter: int = 50, seed: int = 1) -> list[Run]:
    """All cluster counts, weightings and restarts together: each pass over the points serves every run that goes on. Runs
    of one count and restart begin from the same centres."""
    runs = []
    most = max(counts)
    for r in range(restarts):
        shared = starts(points, most, width, init, seed + r)
        for c in counts:
            runs += [Run(shared[:c].copy(), q, w, update, f"{c}/{w}/{r}") for w in weightings]
    return iterate(points, runs, width, tol, max_iter)


def sweep_table(spark, runs: Sequence[Run], eps: float = 1e-6) -> DataFrame:
    """A row for each run: c, weighting, q, iterations, converged, J, J for each unit of weight, S, S by weight, sep_min, degenerate."""
    rows = [(r.name, len(r.centres), r.weighting, float(r.q), r.iterations, r.converged, r.j, r.j / r.mass if r.mass else None, r.validity, r.weighted_validity, r.separation, r.degenerate(eps)) for r in runs]
    return spark.createDataFrame(rows, "run string, c int, weighting string, q double, iterations int, converged boolean, j double, j_per_weight double, s double, s_weighted double, sep_min double, degenerate boolean")


def select_c(table: DataFrame) -> DataFrame:
    """weighting, best_c, s: the best candidate of each count, then the count of least S, degenerate runs aside."""
    best = table.where(~F.col("degenerate") & F.col("s").isNotNull() & ~F.isnan("s")).groupBy("weighting", "c").agg(F.min("s").alias("s"))
    return best.groupBy("weighting").agg(F.min_by("c", F.struct("s", "c")).alias("best_c"), F.min("s").alias("s"))


# ---- reading the result
def memberships(vectors: DataFrame, centres: np.ndarray, q: float) -> DataFrame:
    """Adds u, the array of shares in the clusters, and cluster, that of the largest (the first of equals)."""
    width = centres.shape[1]
    sent = vectors.sparkSession.sparkContext.broadcast(centres)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = sent.value
        for big in batches:
            for i in range(0, big.num_rows, 2048):
                b = big.slice(i, 2048)
                x, norm2 = _batch(b.column(b.schema.get_field_index("idx")), b.column(b.schema.get_field_index("val")), width)
                dots = x @ v.T if isinstance(x, np.ndarray) else x.dots(v)
                u = membership(np.maximum(norm2[:, None] + (v * v).sum(axis=1)[None, :] - 2 * dots, 0.0), q)
                flat = pa.ListArray.from_arrays(np.arange(len(u) + 1, dtype=np.int32) * len(v), u.ravel())
                yield pa.RecordBatch.from_arrays([*b.columns, flat, pa.array(u.argmax(axis=1).astype(np.int32))], names=[*b.schema.names, "u", "cluster"])

    given = vectors.drop("u", "cluster")
    return given.mapInArrow(work, T.StructType([*given.schema.fields, T.StructField("u", T.ArrayType(T.DoubleType())), T.StructField("cluster", T.IntegerType())]))


def assign(with_u: DataFrame, mode: str = "argmax", alpha: float = 0.5) -> DataFrame:
    """Crisp clusters: one for each session, or every cluster whose share is alpha at least (a row for each)."""
    if mode == "argmax":
        return with_u.withColumn("cluster", (F.array_position("u", F.array_max("u")) - 1).cast("int"))
    return with_u.drop("cluster").select("*", F.posexplode("u").alias("cluster", "share")).where(F.col("share") >= alpha)


def describe_clusters(centres: np.ndarray, spark, urls: DataFrame | None = None, top: int = 5) -> DataFrame:
    """cluster, rank, url_id, value (and url): the coordinates in which each centre is largest."""
    rows = [(j, r + 1, int(k), float(v[k])) for j, v in enumerate(centres) for r, k in enumerate(np.argsort(-v, kind="stable")[:top])]
    out = spark.createDataFrame(rows, "cluster int, rank int, url_id int, value double")
    return out.join(urls, "url_id", "left") if urls is not None else out


def overlap_profile(with_u: DataFrame, alpha: float = 0.25) -> DataFrame:
    """clusters, sessions: how many sessions have a share of alpha at least in so many clusters."""
    return with_u.select(F.size(F.filter("u", lambda x: x >= alpha)).alias("clusters")).groupBy("clusters").agg(F.count("*").alias("sessions"))


def check_partition(with_u: DataFrame, tol: float = 1e-9) -> DataFrame:
    """rows, bad_rows (shares that don't add to 1 or lie outside 0 to 1), bad_columns (sums not strictly between 0 and the rows)."""
    each = with_u.select((F.abs(F.aggregate("u", F.lit(0.0), lambda a, x: a + x) - 1) > tol).alias("off"), F.exists("u", lambda x: (x < 0) | (x > 1 + tol)).alias("out"), "u")
    rows = each.agg(F.count("*").alias("rows"), F.count_if(F.col("off") | F.col("out")).alias("bad_rows"))
    sums = each.select(F.posexplode("u").alias("j", "x")).groupBy("j").agg(F.sum("x").alias("s"), F.count("*").alias("n"))
    return rows.crossJoin(F.broadcast(sums.agg(F.count_if(~((F.col("s") > 0) & (F.col("s") < F.col("n")))).alias("bad_columns"))))  # one row each
