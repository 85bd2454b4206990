"""Size-balanced mini-batch k-means and its baselines.

Training sees bounded batches only: one scan picks every iteration's sample, and the loop then works on
samples and centres. Random choices are orders of md5 values; sums are of fixed-point integers, so an index
depends on its seed and rows and on nothing else.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ivfspark.config import FIXED_POINT, IndexConfig
from ivfspark.functions.vectors import matrix, pairwise, pairwise_fast
from ivfspark.plans.sharing import share

#: Samples above this many bytes are clustered by executors and not on the driver.
LOCAL_BYTES = 64 << 20
#: Distances of a batch beyond which executors take it too, where a row's centre does not depend on its batch.
LOCAL_PAIRS = 1 << 26
#: Distances held at once by a kernel.
TILE = 1 << 22
#: Candidates drawn for a batch, over its size: the least md5 values lie below this many times their expected bound.
SPARE_SAMPLES = 4


@dataclass
class Centroids:
    """k centres; ``counts`` are the samples each has received, ``members`` its vectors after assignment."""

    centers: np.ndarray
    counts: np.ndarray
    metric: str = "l2"
    members: np.ndarray | None = None
    history: list = field(default_factory=list)

    @property
    def k(self) -> int:
        return len(self.centers)

    def to_df(self, spark: SparkSession) -> DataFrame:
        members = self.members if self.members is not None else self.counts
        rows = [(i, c.tolist(), int(n)) for i, (c, n) in enumerate(zip(self.centers, members, strict=True))]
        return spark.createDataFrame(rows, "part_id long, centroid array<double>, n_members long")


def partition_count(n_rows: int, target_size: int = 100) -> int:
    return max(1, n_rows // target_size)


def md5_order(seed: int, tag: str, *columns: Column | str) -> Column:
    """A random order that any engine can repeat: md5 of seed, tag and columns."""
    parts = [F.lit(str(seed)), F.lit(tag), *[(F.col(c) if isinstance(c, str) else c).cast("string") for c in columns]]
    return F.md5(F.concat_ws(":", *parts).cast("binary"))


def seeds(vectors: DataFrame, k: int, seed: int) -> DataFrame:
    """``(part_id, embedding)``: k distinct vectors in md5 order; a bounded heap in each task."""
    key = md5_order(seed, "seed", "vec_id")
    chosen = vectors.select("vec_id", "embedding", key.alias("_key")).orderBy("_key", "vec_id").limit(k)
    return chosen.withColumn("part_id", (F.row_number().over(W.orderBy("_key", "vec_id")) - 1).cast("long")).select("part_id", "vec_id", "embedding")


def minibatches(vectors: DataFrame, batch: int, iters: int, seed: int, sampling: str = "exact_md5", n_rows: int | None = None) -> DataFrame:
    """``(iter, vec_id, embedding)`` for all iterations from one scan.

    exact_md5 keeps the ``batch`` least md5 values of each iteration: keys above a bound that far more than
    ``batch`` rows are expected below are dropped in the scan, before vectors are copied, and a group limit in
    every task cuts the rest. Batches of most rows are cut without a bound. one_pass tests each row's hash against the
    sampling rate; fraction is one_pass with ``batch`` in millionths of the rows.
    """
    if sampling not in ("exact_md5", "one_pass", "fraction"):
        raise ValueError(f"unknown sampling {sampling}")
    n_rows = vectors.count() if n_rows is None else n_rows
    spread = vectors.select("vec_id", "embedding", F.explode(F.sequence(F.lit(1), F.lit(iters))).alias("iter"))
    number = F.conv(F.substring("_key", 1, 8), 16, 10).cast("long")
    keys = spread.withColumn("_key", md5_order(seed, "batch", "iter", "vec_id"))
    if sampling != "exact_md5":
        rate = batch / 1e6 if sampling == "fraction" else batch / max(1, n_rows)
        return keys.where(number < F.lit(int(rate * (1 << 32)))).select("iter", "vec_id", "embedding", "_key")
    place = F.row_number().over(W.partitionBy("iter").orderBy("_key", "vec_id"))

    def drawn(rows: DataFrame) -> DataFrame:
        return rows.withColumn("_place", place).where(F.col("_place") <= batch).select("iter", "vec_id", "embedding", "_key")

    if batch >= n_rows:
        return keys.select("iter", "vec_id", "embedding", "_key")
    bound = (SPARE_SAMPLES * batch + 256) / max(1, n_rows)
    if bound >= 1:
        return drawn(keys)
    kept = keys.where(number < F.lit(int(bound * (1 << 32))))
    short = kept.groupBy("iter").count().where(F.col("count") >= min(batch, n_rows)).count() < iters  # about never
    return drawn(keys if short else kept)


def penalised(dist: np.ndarray, counts: np.ndarray, cfg: IndexConfig) -> np.ndarray:
    """Scores of centres for each row: distances, worse for centres that have received more."""
    mean = counts.sum() / len(counts)
    if cfg.penalty == "none" or cfg.lam == 0 and cfg.penalty != "cap" or mean == 0:
        return dist
    share = counts / mean
    if cfg.penalty == "multiplicative":
        return dist * (1.0 + cfg.lam * share)[None, :]
    if cfg.penalty == "additive":
        return dist + cfg.lam * dist.min(axis=1).mean() * share[None, :]
    if cfg.penalty == "cap":
        full = counts >= cfg.cap * mean
        return dist if full.all() else np.where(full[None, :], np.inf, dist)
    raise ValueError(f"unknown penalty {cfg.penalty}")


def assign_balanced(batch: np.ndarray, centers: np.ndarray, counts: np.ndarray, cfg: IndexConfig) -> np.ndarray:
    """Centre of each row of a batch. Sequential scope counts the batch's own choices as it goes."""
    if cfg.scope == "frozen" and cfg.penalty in ("none", "multiplicative") and cfg.metric != "ip":
        v = counts.astype(np.float64)
        rough = penalised(pairwise_fast(batch, centers, cfg.metric), v, cfg)
        best = rough.min(axis=1)
        worst = 1 + cfg.lam * v.max() / max(v.mean(), 1e-9)  # what a rounding error of a distance may grow to
        near = rough <= (best + 1e-6 * worst * (1 + np.abs(best)))[:, None]
        labels, many = near.argmax(axis=1), np.flatnonzero(near.sum(axis=1) > 1)
        factors = penalised(np.ones((1, len(v))), v, cfg)[0]
        for i in many:
            options = np.flatnonzero(near[i])
            labels[i] = options[(pairwise(batch[i : i + 1], centers[options], cfg.metric)[0] * factors[options]).argmin()]
        return labels
    dist = pairwise(batch, centers, cfg.metric)
    if cfg.scope == "frozen":
        return penalised(dist, counts.astype(np.float64), cfg).argmin(axis=1)
    running = counts.astype(np.float64).copy()
    out = np.empty(len(batch), np.int64)
    for i in range(len(batch)):
        out[i] = penalised(dist[i : i + 1], running, cfg)[0].argmin()
        running[out[i]] += 1
    return out


def assign_tiled(batch: np.ndarray, centers: np.ndarray, counts: np.ndarray, cfg: IndexConfig) -> np.ndarray:
    """As ``assign_balanced``, with a tile of distances at once. A frozen additive penalty is of the whole batch's mean
    distance, so that batch is one tile."""
    if cfg.scope == "frozen" and cfg.penalty == "additive":
        return assign_balanced(batch, centers, counts, cfg)
    out, running, step = np.empty(len(batch), np.int64), counts, max(1, TILE // len(centers))
    for at in range(0, len(batch), step):
        out[at : at + step] = assign_balanced(batch[at : at + step], centers, running, cfg)
        if cfg.scope != "frozen":
            running = running + np.bincount(out[at : at + step], minlength=len(centers))
    return out


def fixed_point(x: np.ndarray) -> np.ndarray:
    return np.floor(np.asarray(x, np.float64) * FIXED_POINT + 0.5).astype(np.int64)


def update_centroids(centers: np.ndarray, counts: np.ndarray, sums: np.ndarray, received: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The running mean after a batch, in one step.

    Visiting a batch's rows one at a time with rate 1/count ends at (count * centre + sum) / (count + rows),
    whatever the order; a centre that has received nothing yet forgets its seed.
    """
    new = counts + received
    moved = (counts[:, None] * centers + sums / FIXED_POINT) / np.maximum(new, 1)[:, None]
    return np.where(received[:, None] > 0, moved, centers), new


def update_sequential(centers: np.ndarray, counts: np.ndarray, batch: np.ndarray, labels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same by single steps; the definition that the closed form is tested against."""
    centers, counts = centers.copy(), counts.copy()
    for x, c in zip(batch, labels, strict=True):
        counts[c] += 1
        rate = 1.0 / counts[c]
        centers[c] = (1 - rate) * centers[c] + rate * x
    return centers, counts


def _sums(batch: np.ndarray, labels: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    sums = np.zeros((k, batch.shape[1]), np.int64)
    np.add.at(sums, labels, fixed_point(batch))
    return sums, np.bincount(labels, minlength=k)


def summed(partial: DataFrame, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``partial(part_id, m, s)`` added by partition on executors: ids, counts and sums, one row a partition."""

    def reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, list] = {}
        for batch in batches:
            rows = matrix_of_longs(batch.column(2), width)
            for p, m, row in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), rows, strict=True):
                if p in total:
                    total[p][0] += m
                    total[p][1] += row
                else:
                    total[p] = [m, row.copy()]
        flat = np.concatenate([x[1] for x in total.values()]) if total else np.zeros(0, np.int64)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(len(total) + 1, dtype=np.int32) * width), pa.array(flat, pa.int64()))
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int64()), pa.array([x[0] for x in total.values()], pa.int64()), lists], ["part_id", "m", "s"])

    schema = "part_id long, m long, s array<long>"
    rows = partial.repartition("part_id").mapInArrow(reduce, schema).toArrow()  # k rows, as arrays
    return rows["part_id"].to_numpy(), rows["m"].to_numpy(), matrix_of_longs(rows["s"], width)


def matrix_of_longs(column: pa.Array | pa.ChunkedArray, width: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, width)


def _distributed_step(rows: DataFrame, centers: np.ndarray, counts: np.ndarray, cfg: IndexConfig) -> tuple[np.ndarray, np.ndarray]:
    """Sums and counts of one batch, reduced on executors: at most k rows a task reach the shuffle."""
    shared = share(rows.sparkSession, (centers, counts), "centres")
    width = centers.shape[1]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c, v = shared.value
        sums, received = np.zeros(c.shape, np.int64), np.zeros(len(c), np.int64)
        for batch in batches:
            x = matrix(batch.column(0))
            for at in range(0, len(x), max(1, TILE // len(c))):
                part = x[at : at + max(1, TILE // len(c))]
                s, r = _sums(part, assign_balanced(part, c, v, cfg), len(c))
                sums += s
                received += r
        hit = np.flatnonzero(received)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(len(hit) + 1, dtype=np.int32) * width), pa.array(sums[hit].ravel(), pa.int64()))
        yield pa.RecordBatch.from_arrays([pa.array(hit), pa.array(received[hit]), lists], ["part_id", "m", "s"])

    ids, m, s = summed(rows.select("embedding").mapInArrow(kernel, "part_id long, m long, s array<long>"), width)
    sums, received = np.zeros(centers.shape, np.int64), np.zeros(len(centers), np.int64)
    sums[ids], received[ids] = s, m
    shared.destroy()
    return sums, received


def train(vectors: DataFrame, cfg: IndexConfig, k: int | None = None, exec_mode: str = "auto", n_rows: int | None = None) -> Centroids:
    """The training loop; ``exec_mode`` local (samples on the driver), distributed, or auto by size."""
    n_rows = vectors.count() if n_rows is None else n_rows
    if k is None:
        k = partition_count(n_rows, cfg.target_size)
    first = seeds(vectors, k, cfg.seed).orderBy("part_id").collect()
    if not first:
        raise ValueError("no vectors to train on")
    centers = np.array([r.embedding for r in first], np.float64)
    counts = np.zeros(len(centers), np.int64)
    sample = minibatches(vectors, cfg.batch, cfg.iters, cfg.seed, cfg.sampling, n_rows)
    if exec_mode == "auto":
        alone = cfg.scope == "frozen" and cfg.penalty != "additive"
        few = cfg.batch * cfg.iters * centers.shape[1] * 8 <= LOCAL_BYTES and (not alone or cfg.batch * len(centers) <= LOCAL_PAIRS)
        exec_mode = "local" if few else "distributed"
    history = []
    if exec_mode == "local":
        rows = sample.orderBy("iter", "_key", "vec_id").select("iter", "embedding").toArrow()
        numbers = rows["iter"].to_numpy()
        for i in range(1, cfg.iters + 1):
            lo, hi = np.searchsorted(numbers, [i, i + 1]).tolist()
            if lo == hi:
                continue
            batch = matrix(rows["embedding"].slice(lo, hi - lo))
            sums, received = _sums(batch, assign_tiled(batch, centers, counts, cfg), len(centers))
            centers, counts = update_centroids(centers, counts, sums, received)
            history.append(counts.copy())
    else:
        if cfg.scope != "frozen":
            raise ValueError("a sequential batch has an order; only frozen scope is distributed")
        from ivfspark.plans.scratch import materialize

        kept = materialize(sample.select("iter", "embedding"), "samples")
        for i in range(1, cfg.iters + 1):
            batch = kept.where(F.col("iter") == i).repartition(vectors.sparkSession.sparkContext.defaultParallelism)  # a batch may lie in one file
            sums, received = _distributed_step(batch, centers, counts, cfg)
            centers, counts = update_centroids(centers, counts, sums, received)
            history.append(counts.copy())
    return Centroids(centers, counts, cfg.metric, history=history)


def train_full_kmeans(vectors: DataFrame, cfg: IndexConfig, k: int | None = None, tolerance: float = 0.0) -> Centroids:
    """Baseline: Lloyd iterations over all vectors, no penalty, no memory of earlier rounds."""
    from dataclasses import replace

    if k is None:
        k = partition_count(vectors.count(), cfg.target_size)
    plain = replace(cfg, penalty="none", scope="frozen")
    centers = np.array([r.embedding for r in seeds(vectors, k, cfg.seed).orderBy("part_id").collect()], np.float64)
    counts = np.zeros(len(centers), np.int64)
    for _ in range(cfg.iters):
        sums, counts = _distributed_step(vectors, centers, np.zeros(len(centers), np.int64), plain)
        moved = np.where(counts[:, None] > 0, sums / FIXED_POINT / np.maximum(counts, 1)[:, None], centers)
        shift, centers = float(np.abs(moved - centers).max()), moved
        if shift <= tolerance:
            break
    return Centroids(centers, counts, cfg.metric)


def assign_all(
    vectors: DataFrame,
    centroids: Centroids,
    id_cols: tuple[str, ...] = ("vec_id",),
    balanced: IndexConfig | None = None,
) -> DataFrame:
    """Nearest centre of every vector: centres are broadcast (k * d numbers, checked), vectors are not moved.

    A matrix product proposes, and centres within a rounding error of the best are compared again in
    exact order; ties go to the smaller part_id. ``balanced`` scores with the size penalty instead.
    """
    groups = grouped(centroids.centers, centroids.metric) if balanced is None else None
    shared = share(vectors.sparkSession, (centroids.centers, centroids.counts, groups), "centres")
    metric = centroids.metric

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centers, counts, groups = shared.value
        for batch in batches:
            x = matrix(batch.column(batch.num_columns - 1))
            labels = np.zeros(len(x), np.int64)
            step = max(1, TILE // len(groups[2] if groups else centers))
            for at in range(0, len(x), step):
                part = x[at : at + step]
                if balanced is not None:
                    labels[at : at + step] = assign_balanced(part, centers, counts, balanced)
                elif groups:
                    labels[at : at + step] = nearest_grouped(part, centers, groups, metric)
                else:
                    labels[at : at + step] = nearest(part, centers, metric)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(labels, pa.int64()), batch.column(batch.num_columns - 1)], [*batch.schema.names[:-1], "part_id", "embedding"])

    types = {f.name: f.dataType.simpleString() for f in vectors.schema}
    fields = ", ".join(f"{c} {types[c]}" for c in id_cols)
    return vectors.select(*id_cols, "embedding").mapInArrow(kernel, f"{fields}, part_id long, embedding {types['embedding']}")


def members_below(labels: np.ndarray, n: int) -> list[np.ndarray]:
    """Ids of the centres below each of ``n`` super centres."""
    order = np.argsort(labels, kind="stable")
    return np.split(order, np.searchsorted(labels[order], np.arange(1, n)))


def nearest_supers(x: np.ndarray, tops: np.ndarray, metric: str, supers: int) -> np.ndarray:
    dist = pairwise_fast(x, tops, metric)
    supers = min(supers, len(tops))
    return np.argpartition(dist, supers - 1, axis=1)[:, :supers]


#: Super centres below which a vector looks for its centre.
ASSIGN_SUPERS = 8


def nearest_below(x: np.ndarray, centers: np.ndarray, tops: np.ndarray, below: list[np.ndarray], metric: str) -> np.ndarray:
    """Nearest centre among those below each row's nearest super centres; rows of one choice share a product."""
    chosen = np.sort(nearest_supers(x, tops, metric, ASSIGN_SUPERS), axis=1)
    best, labels = np.full(len(x), np.inf), np.zeros(len(x), np.int64)
    for top in np.unique(chosen):
        rows = np.flatnonzero((chosen == top).any(axis=1))
        if not len(below[top]):
            continue
        dist = pairwise_fast(x[rows], centers[below[top]], metric)
        at = dist.argmin(axis=1)
        least = dist[np.arange(len(rows)), at]
        nearer = least < best[rows]
        best[rows[nearer]], labels[rows[nearer]] = least[nearer], below[top][at[nearer]]
    return labels


def nearest(x: np.ndarray, centers: np.ndarray, metric: str) -> np.ndarray:
    step = max(1, TILE // len(centers))
    if len(x) > step:
        return np.concatenate([nearest(x[at : at + step], centers, metric) for at in range(0, len(x), step)])
    rough = pairwise_fast(x, centers, metric)
    best = rough.min(axis=1, keepdims=True)
    near = rough <= best + 1e-6 * (1 + np.abs(best))
    labels = near.argmax(axis=1)
    for i in np.flatnonzero(near.sum(axis=1) > 1):
        options = np.flatnonzero(near[i])
        labels[i] = options[pairwise(x[i : i + 1], centers[options], metric)[0].argmin()]
    return labels


#: Centres beyond which a vector's nearest one is looked for by groups of centres.
GROUPED_CENTRES = 1024


def unit(x: np.ndarray, metric: str) -> np.ndarray:
    """Rows as points of the space in which distances obey the triangle inequality: of unit length for cosine (zero
    vectors stay)."""
    if metric == "l2":
        return x
    size = np.sqrt((x * x).sum(axis=1, keepdims=True))
    return np.divide(x, size, out=np.zeros_like(x), where=size > 0)


def grouped(centers: np.ndarray, metric: str) -> tuple | None:
    """Groups of near centres: points of the distinct ones, their least ids, middles, members and radii of the groups."""
    if metric == "ip" or len(centers) <= GROUPED_CENTRES or not centers.any(axis=1).all():
        return None
    points, ids = np.unique(unit(centers, metric), axis=0, return_index=True)
    n = max(1, int(2 * np.sqrt(len(points))))
    tops = lloyd(points, points[:: -(-len(points) // n)], "l2", 2)
    labels = nearest(points, tops, "l2")
    below = members_below(labels, len(tops))
    radii = np.array([np.sqrt(((points[b] - t) ** 2).sum(axis=1)).max() if len(b) else -np.inf for b, t in zip(below, tops, strict=True)])
    return points, ids, tops, below, radii


def nearest_grouped(x: np.ndarray, centers: np.ndarray, groups: tuple, metric: str) -> np.ndarray:
    """As ``nearest``, but a row is compared only with groups that may hold a nearer centre than the best so far. Rows
    with a second centre within a rounding error are compared with all."""
    points, ids, tops, below, radii = groups
    own = unit(x, metric)
    away = pairwise_fast(own, tops, "l2")
    best, labels, tied = np.full(len(x), np.inf), np.zeros(len(x), np.int64), np.zeros(len(x), bool)
    least = away - radii[None, :]
    first = least.argmin(axis=1)

    def compare(rows: np.ndarray, g: int) -> None:
        dist = pairwise_fast(own[rows], points[below[g]], "l2")
        at = dist.argmin(axis=1)
        here = dist[np.arange(len(rows)), at]
        slack = 1e-6 * (1 + here)
        tied[rows] |= ((dist <= (here + slack)[:, None]).sum(axis=1) > 1) & (here <= best[rows] + slack)
        tied[rows] |= np.abs(here - best[rows]) <= slack
        nearer = here < best[rows]
        best[rows[nearer]], labels[rows[nearer]] = here[nearer], ids[below[g][at[nearer]]]

    for g in np.unique(first):
        compare(np.flatnonzero(first == g), g)
    for g in range(len(tops)):
        rows = np.flatnonzero((least[:, g] <= best + 1e-6 * (1 + best)) & (first != g))
        if len(rows) and len(below[g]):
            compare(rows, g)
    again = np.flatnonzero(tied)
    step = max(1, TILE // len(centers))
    for at in range(0, len(again), step):
        labels[again[at : at + step]] = nearest(x[again[at : at + step]], centers, metric)
    return labels


def lloyd(points: np.ndarray, centers: np.ndarray, metric: str, iters: int) -> np.ndarray:
    """Plain k-means steps on the driver, for point sets as small as centres; empty clusters stay."""
    for _ in range(iters):
        sums, received = _sums(points, nearest(points, centers, metric), len(centers))
        centers = np.where(received[:, None] > 0, sums / FIXED_POINT / np.maximum(received, 1)[:, None], centers)
    return centers


def train_super(centroids: Centroids, target_size: int = 32, seed: int = 42, iters: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """Second level: centres of centres, and each centre's super centre."""
    k2 = partition_count(centroids.k, target_size)
    order = sorted(range(centroids.k), key=lambda i: (hashlib.md5(f"{seed}:super:{i}".encode()).hexdigest(), i))
    tops = lloyd(centroids.centers, centroids.centers[order[:k2]], centroids.metric, iters)
    return tops, nearest(centroids.centers, tops, centroids.metric)
