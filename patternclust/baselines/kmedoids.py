"""Projected k-medoids: far-apart medoids, dimensions per medoid, segmental Manhattan distance."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _far_apart(sample: np.ndarray, count: int, rng) -> np.ndarray:
    chosen = [int(rng.integers(len(sample)))]
    near = np.abs(sample - sample[chosen[0]]).mean(axis=1)
    while len(chosen) < count:
        chosen.append(int(near.argmax()))
        near = np.minimum(near, np.abs(sample - sample[chosen[-1]]).mean(axis=1))
    return sample[chosen]


def choose_dimensions(mean_dev: np.ndarray, average: int, present: np.ndarray | None = None) -> list[np.ndarray]:
    """Per medoid the coordinates of least standardised deviation: two each, then the best of all up to k times ``average``.

    Coordinates that are not ``present`` in the medoid (counts of what it does not hold) come last: nearly all vectors agree in these.
    """
    k, d = mean_dev.shape
    spread = mean_dev.std(axis=1, ddof=1, keepdims=True)
    z = (mean_dev - mean_dev.mean(axis=1, keepdims=True)) / np.where(spread > 0, spread, 1)
    if present is not None:
        z = np.where(present, z, z + 1e6)
    taken = np.zeros((k, d), bool)
    for i in range(k):
        taken[i, np.argsort(z[i], kind="stable")[:2]] = True
    left = max(0, min(k * average, k * d) - int(taken.sum()))
    flat = np.argsort(np.where(taken, np.inf, z), axis=None, kind="stable")[:left]
    taken[np.unravel_index(flat, taken.shape)] = True
    return [np.flatnonzero(t) for t in taken]


def _distances(x: np.ndarray, medoids: np.ndarray, dims: list[np.ndarray]) -> np.ndarray:
    return np.stack([np.abs(x[:, d] - m[d]).mean(axis=1) for m, d in zip(medoids, dims)], axis=1)


def _pass(vectors: DataFrame, kernel, schema: str) -> DataFrame:
    def run(batches):
        for batch in batches:
            if batch.num_rows:
                x = np.array(batch.column(1).to_pylist(), dtype=float)
                yield from kernel(batch.column(0), x)

    return vectors.select("vec_id", "v").mapInArrow(run, schema)


def round_dimensions(vectors: DataFrame, medoids: np.ndarray, average: int) -> list[np.ndarray]:
    """Dimensions of each medoid by the mean deviations of all vectors in its locality, or of all where it has fewer than two."""
    k, d = medoids.shape
    gaps = np.stack([np.abs(medoids - m).mean(axis=1) for m in medoids])
    np.fill_diagonal(gaps, np.inf)
    reach = gaps.min(axis=1)

    def kernel(_, x):
        for i in range(k):
            dev = np.abs(x - medoids[i])
            near = dev.mean(axis=1) <= reach[i]
            sums = [pa.array([v.sum(axis=0).tolist()], pa.list_(pa.float64())) for v in (dev[near], dev)]
            yield pa.RecordBatch.from_arrays([pa.array([i]), pa.array([int(near.sum())]), pa.array([len(x)]), *sums], ["c", "n", "m", "s", "t"])

    parts = _pass(vectors, kernel, "c bigint, n bigint, m bigint, s array<double>, t array<double>")
    flat = parts.select("c", "n", "m", F.posexplode(F.arrays_zip("s", "t")).alias("j", "x"))
    dev = np.zeros((k, d))
    for r in flat.groupBy("c", "j").agg(F.sum("n").alias("n"), F.sum("m").alias("m"), F.sum("x.s").alias("s"), F.sum("x.t").alias("t")).collect():  # k times d rows
        dev[r["c"], r["j"]] = r["s"] / r["n"] if r["n"] > 1 else r["t"] / r["m"]
    return choose_dimensions(dev, average, medoids != 0)


def round_cost(vectors: DataFrame, medoids: np.ndarray, dims: list[np.ndarray]) -> tuple[float, np.ndarray]:
    """Mean distance of all vectors to their nearest medoid, and how many are nearest to each."""

    def kernel(_, x):
        d = _distances(x, medoids, dims)
        own, low = d.argmin(axis=1), d.min(axis=1)
        counts, sums = np.bincount(own, minlength=len(medoids)), np.bincount(own, low, len(medoids))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(medoids))), pa.array(counts), pa.array(sums)], ["c", "n", "s"])

    rows = _pass(vectors, kernel, "c bigint, n bigint, s double").groupBy("c").agg(F.sum("n").alias("n"), F.sum("s").alias("s")).collect()  # k rows
    counts = np.zeros(len(medoids), np.int64)
    for r in rows:
        counts[r["c"]] = r["n"]
    return sum(r["s"] for r in rows) / counts.sum(), counts


def fit(vectors: DataFrame, k: int, average_dims: int = 20, seed: int = 1, rounds: int = 12, sample_rows: int = 3000, bad_share: float = 0.1) -> DataFrame:
    """``(vec_id, cluster, dist)`` of ``(vec_id, v)``; outliers, farther from every medoid than its sphere of influence, are -1.

    Medoids come from a bounded sample, and every round judges them by all vectors; every pass over the vectors sends back k rows of sums a task.
    """
    rng = np.random.default_rng(seed)
    n = vectors.count()
    share = min(1.0, 1.3 * sample_rows / max(1, n))
    rows = vectors.where(F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.lit(1 << 20)) < int(share * (1 << 20))).select("vec_id", "v").limit(2 * sample_rows).collect()
    sample = np.array([r["v"] for r in sorted(rows, key=lambda r: r["vec_id"])], dtype=float)
    if len(sample) < k:
        raise ValueError("fewer vectors than clusters")
    pool = _far_apart(sample, min(len(sample), 4 * k), rng)
    current, best, best_cost, stale = rng.choice(len(pool), k, replace=False), None, np.inf, 0

    for _ in range(rounds):
        medoids = pool[current]
        dims = round_dimensions(vectors, medoids, average_dims)
        cost, counts = round_cost(vectors, medoids, dims)
        if cost < best_cost:
            best, best_cost, best_counts, best_dims, stale = current.copy(), cost, counts, dims, 0
        else:
            stale += 1
            if stale > 4:
                break
        bad = np.flatnonzero(best_counts < bad_share * best_counts.sum() / k)
        bad = bad if len(bad) else np.array([best_counts.argmin()])
        current = best.copy()
        free = np.setdiff1d(np.arange(len(pool)), current)
        take = min(len(bad), len(free))
        current[bad[:take]] = rng.choice(free, take, replace=False)
    medoids, dims = pool[best], best_dims

    def deviations(_, x):
        own = _distances(x, medoids, dims).argmin(axis=1)
        for i in np.unique(own).tolist():
            part = np.abs(x[own == i] - medoids[i])
            yield pa.RecordBatch.from_arrays([pa.array([i]), pa.array([len(part)]), pa.array([part.sum(axis=0).tolist()], pa.list_(pa.float64()))], ["c", "n", "s"])

    # refinement over all vectors: dimensions from the clusters themselves
    sums, counts = np.zeros((k, sample.shape[1])), np.zeros(k)
    parts = _pass(vectors, deviations, "c bigint, n bigint, s array<double>").select("c", "n", F.posexplode("s").alias("j", "x"))
    for r in parts.groupBy("c", "j").agg(F.sum("x").alias("x"), F.sum("n").alias("n")).collect():  # k times d rows
        sums[r["c"], r["j"]], counts[r["c"]] = r["x"], r["n"]
    refined = choose_dimensions(sums / np.maximum(counts, 1)[:, None], average_dims, medoids != 0)
    spheres = np.array([min((np.abs(medoids[i][d] - medoids[j][d]).mean() for j in range(k) if j != i), default=np.inf) for i, d in enumerate(refined)])

    def final(ids, x):
        d = _distances(x, medoids, refined)
        own = np.where((d > spheres).all(axis=1), -1, d.argmin(axis=1))
        yield pa.RecordBatch.from_arrays([ids, pa.array(own.astype(np.int32)), pa.array(d.min(axis=1))], ["vec_id", "cluster", "dist"])

    return _pass(vectors, final, "vec_id bigint, cluster int, dist double")
