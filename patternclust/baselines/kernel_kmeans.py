"""Kernel k-means: distances to cluster means in feature space, through the kernel matrix alone.

``fit`` makes the matrix in blocks of rows against all columns; it grows with the square of the number of objects, so
it is for some thousands of them, as the measures of its run time show. ``fit_linear`` is for any number: with the linear
kernel, sums of matrix entries over a cluster are products with the cluster's summed vector, so only k such sums travel.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.state import commit

MAX_OBJECTS = 20_000
#: bytes of the dense matrix that goes to every task
MAX_BYTES = 1 << 30


def feature_matrix(features: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """``(ids, dense matrix)`` of ``(graph_id, feature, cnt)`` for at most MAX_OBJECTS objects, rows of unit length."""
    rows = features.groupBy("graph_id").agg(F.map_from_entries(F.collect_list(F.struct("feature", "cnt"))).alias("f")).limit(MAX_OBJECTS + 1).collect()
    if len(rows) > MAX_OBJECTS:
        raise ValueError(f"more than {MAX_OBJECTS} objects: the kernel matrix would not fit")
    rows = sorted(rows, key=lambda r: r["graph_id"])
    names = {f: i for i, f in enumerate(sorted({f for r in rows for f in r["f"]}))}
    if 8 * len(rows) * len(names) > MAX_BYTES:
        raise ValueError(f"{len(rows)} objects of {len(names)} features are over {MAX_BYTES} bytes")
    x = np.zeros((len(rows), len(names)))
    for i, r in enumerate(rows):
        for f, n in r["f"].items():
            x[i, names[f]] = n
    norms = np.linalg.norm(x, axis=1, keepdims=True)
    return np.array([r["graph_id"] for r in rows]), x / np.where(norms > 0, norms, 1)


def fit(spark, ids: np.ndarray, x: np.ndarray, k: int, seed: int = 1, rounds: int = 30, kernel: str = "linear") -> DataFrame:
    """``(graph_id, cluster_id)``. Each round is one job over blocks of rows: only labels and k numbers travel."""
    if kernel not in ("linear", "rbf"):
        raise ValueError("kernel must be linear or rbf")
    rng = np.random.default_rng(seed)
    n = len(ids)
    shared = spark.sparkContext.broadcast(x)  # bounded by MAX_OBJECTS
    blocks = spark.range(0, n, 1, max(1, min(spark.sparkContext.defaultParallelism, n // 64 + 1)))
    labels = rng.integers(0, k, n)
    # start: nearest of k far-apart objects
    centres = [int(rng.integers(n))]
    near = ((x - x[centres[0]]) ** 2).sum(axis=1)
    while len(centres) < min(k, n):
        p = near / near.sum() if near.sum() > 0 else None
        centres.append(int(rng.choice(n, p=p)))
        near = np.minimum(near, ((x - x[centres[-1]]) ** 2).sum(axis=1))
    labels = np.stack([((x - x[c]) ** 2).sum(axis=1) for c in centres]).argmin(axis=0)
    for _ in range(rounds):
        counts = np.maximum(np.bincount(labels, minlength=k), 1)
        onehot = np.zeros((n, k))
        onehot[np.arange(n), labels] = 1 / counts[labels]

        def step(batches, onehot=onehot):
            full = shared.value
            for batch in batches:
                rows = batch.column(0).to_numpy()
                if not len(rows):
                    continue
                gram = full[rows] @ full.T
                if kernel == "rbf":
                    sq = (full**2).sum(axis=1)
                    gram = np.exp(-(sq[rows][:, None] + sq[None, :] - 2 * gram))
                to_means = gram @ onehot
                yield pa.RecordBatch.from_arrays([pa.array(rows), pa.array(to_means.tolist(), pa.list_(pa.float64()))], ["i", "m"])

        got = blocks.mapInArrow(step, "i bigint, m array<double>").toArrow()  # n times k numbers, n bounded
        order = np.argsort(got.column("i").to_numpy())
        means = np.array(got.column("m").to_pylist())[order]
        within = np.array([means[labels == c, c].mean() if (labels == c).any() else np.inf for c in range(k)])
        new = (within - 2 * means).argmin(axis=1)
        if (new == labels).all():
            break
        labels = new
    return spark.createDataFrame([(int(i), int(c)) for i, c in zip(ids, labels)], "graph_id bigint, cluster_id int")


def unit_rows(features: DataFrame) -> DataFrame:
    """``(graph_id, f, v)`` of ``(graph_id, feature, cnt)``: numbers of the features, in order, and their values, rows of unit length."""
    held = commit(features, "features")
    names = sorted(r[0] for r in held.select("feature").distinct().collect())  # a finite alphabet's
    number = held.sparkSession.createDataFrame(list(enumerate(names)), "f int, feature string")
    rows = held.join(number, "feature").groupBy("graph_id").agg(F.array_sort(F.collect_list(F.struct("f", F.col("cnt").cast("double").alias("c")))).alias("x"))
    norm = F.sqrt(F.aggregate("x", F.lit(0.0), lambda s, e: s + e["c"] * e["c"]))
    return rows.select("graph_id", F.col("x.f").alias("f"), F.transform("x", lambda e: e["c"] / norm).alias("v"))


def _dense(batch: pa.RecordBatch, width: int) -> np.ndarray:
    """The vectors of a batch of ``(graph_id, f, v)``, one a row."""
    out, f, v = np.zeros((batch.num_rows, width)), batch.column("f"), batch.column("v")
    row = np.repeat(np.arange(batch.num_rows), np.diff(f.offsets.to_numpy()))
    out[row, f.flatten().to_numpy()] = v.flatten().to_numpy()
    return out


def fit_linear(rows: DataFrame, k: int, seed: int = 1, rounds: int = 30) -> DataFrame:
    """``(graph_id, cluster_id)`` of ``(graph_id, f, v)``, sparse vectors of ascending feature numbers; the same method with the linear kernel.

    The start is drawn as in ``fit``, with a chance by the distance to the centres so far, through a hash of the id; then each
    round is one scan, from which come k sums and counts a task. The last round's means give the labels, in one scan more.
    """
    spark = rows.sparkSession
    rows = commit(rows, "vectors")
    width = (rows.agg(F.max(F.array_max("f"))).first()[0] or 0) + 1

    def draw(centres: list[np.ndarray]) -> np.ndarray | None:
        """One more centre: the least of exponential variates over squared distances; none where all vectors are centres."""
        at = np.array(centres)

        def weighed(batches):
            for batch in batches:
                for start in range(0, batch.num_rows, 1024):
                    part = batch.slice(start, 1024)
                    x = _dense(part, width)
                    near = np.min([((x - c) ** 2).sum(axis=1) for c in at], axis=0) if len(at) else np.ones(len(x))
                    near[near < 1e-12] = 0
                    with np.errstate(divide="ignore"):
                        score = -np.log(part.column("u").to_numpy()) / near
                    i = int(np.lexsort((part.column("graph_id").to_numpy(), score))[0])
                    if np.isfinite(score[i]):
                        one = part.slice(i, 1)
                        yield pa.RecordBatch.from_arrays([one.column("graph_id"), pa.array(score[i : i + 1]), one.column("f"), one.column("v")], ["graph_id", "score", "f", "v"])

        u = (F.pmod(F.xxhash64("graph_id", F.lit(seed), F.lit(len(centres))), F.lit(1 << 40)) + 0.5) / float(1 << 40)
        found = rows.withColumn("u", u).mapInArrow(weighed, "graph_id bigint, score double, f array<int>, v array<double>").orderBy("score", "graph_id").first()
        if found is None:
            return None
        centre = np.zeros(width)
        centre[found["f"]] = found["v"]
        return centre

    centres: list[np.ndarray] = []
    while len(centres) < k and (one := draw(centres)) is not None:
        centres.append(one)
    if not centres:
        return spark.createDataFrame([], "graph_id bigint, cluster_id int")
    means, counts = np.array(centres), None
    for _ in range(rounds):

        def sums(batches, means=means):
            total, n, within = np.zeros_like(means), np.zeros(len(means), dtype=np.int64), np.where(np.isfinite(means[:, 0]), (means**2).sum(axis=1), np.inf)
            held = np.nan_to_num(means, posinf=0)
            for batch in batches:
                for start in range(0, batch.num_rows, 1024):
                    x = _dense(batch.slice(start, 1024), width)
                    own = (within - 2 * (x @ held.T)).argmin(axis=1)
                    total += (own[None, :] == np.arange(len(n))[:, None]).astype(float) @ x
                    n += np.bincount(own, minlength=len(n))
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(n))), pa.array(n), pa.array(total.tolist(), pa.list_(pa.float64()))], ["c", "n", "s"])

        got = rows.mapInArrow(sums, "c bigint, n bigint, s array<double>")
        new, held = np.zeros_like(means), np.zeros(len(means), dtype=np.int64)
        if width > 4096:  # the sums of all tasks at once would be many
            flat = got.select("c", "n", F.posexplode("s").alias("i", "s")).groupBy("c", "i").agg(F.sum("n").alias("n"), F.sum("s").alias("s")).toArrow()  # k vectors
            new[flat.column("c").to_numpy(), flat.column("i").to_numpy()] = flat.column("s").to_numpy()
            held[flat.column("c").to_numpy()] = flat.column("n").to_numpy()
        else:
            flat = got.toArrow()  # k vectors a task
            np.add.at(new, flat.column("c").to_numpy(), np.array(flat.column("s").to_pylist()).reshape(-1, width))
            np.add.at(held, flat.column("c").to_numpy(), flat.column("n").to_numpy())
        new = np.where(held[:, None] > 0, new / np.maximum(held, 1)[:, None], np.inf)  # an empty cluster stays empty
        same = counts is not None and (held == counts).all() and np.allclose(np.nan_to_num(new, posinf=0), np.nan_to_num(means, posinf=0), rtol=0, atol=1e-12)
        means, counts = new, held
        if same:
            break
    last = means

    def labelled(batches):
        within, held = np.where(np.isfinite(last[:, 0]), (np.nan_to_num(last, posinf=0) ** 2).sum(axis=1), np.inf), np.nan_to_num(last, posinf=0)
        for batch in batches:
            own = [(within - 2 * (_dense(batch.slice(at, 1024), width) @ held.T)).argmin(axis=1) for at in range(0, batch.num_rows, 1024)]
            if own:
                yield pa.RecordBatch.from_arrays([batch.column("graph_id"), pa.array(np.concatenate(own).astype(np.int32))], ["graph_id", "cluster_id"])

    return commit(rows.mapInArrow(labelled, "graph_id bigint, cluster_id int"), "labels")
