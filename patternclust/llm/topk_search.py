"""Exact top-k inner products by norm-bucketed retrieval.

Candidates are sorted by length into slots (range partitions), each cut into buckets of bounded
size. For a query the local cosine threshold of a bucket is its running k-th score divided by
query length times the bucket's largest length: over one, the whole bucket is skipped by length;
near one, coordinate bounds leave few candidates; else the bucket's vectors are taken in order of
length down to the bound. What is left is verified by integer products. Queries come in blocks; the
slot of the longest vectors answers first, and its k-th scores are floors: a block of queries
travels only to slots whose longest vector can still reach one of them.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import materialize

BLOCK = 2048
COORDINATE_FROM = 0.8
FOCUS = 3
SLOT_BLOCKS = 4
#: slots are fewer, then each has more buckets: what is sent about them is bounded
MOST_SLOTS = 1 << 16


def integer_vectors(df: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: float = 256.0) -> DataFrame:
    """``(vec_id, v, norm)`` with v = floor(scale * x); vectors or ids that are null, or vectors with a null or non-finite component, are left out."""
    x = F.col(vector_col).cast("array<double>")
    bad = F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    kept = df.where(F.col(id_col).isNotNull() & F.col(vector_col).isNotNull() & ~F.coalesce(bad, F.lit(False)))
    v = F.transform(x, lambda c: F.floor(F.lit(scale) * c).cast("bigint"))
    return kept.select(F.col(id_col).cast("bigint").alias("vec_id"), v.alias("v")).withColumn(
        "norm", F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, c: s + c.cast("double") * c))
    )


def _blocks(vectors: DataFrame, parts: int, block: int) -> DataFrame:
    """Vectors packed by falling length: ``slot, top, norms, ids, dims, data``; slots are range partitions."""

    def pack(batches):
        slot = TaskContext.get().partitionId()
        for batch in batches:
            for k in range(0, batch.num_rows, block):
                own = batch.slice(k, block)
                rows = own.column(1).to_pylist()
                dims = max(map(len, rows), default=0)
                matrix = np.zeros((len(rows), dims), np.int64)  # shorter vectors count as ending in zeros
                for i, row in enumerate(rows):
                    matrix[i, : len(row)] = row
                ids, norms = own.column(0).to_numpy().astype(np.int64), own.column(2).to_numpy()
                yield pa.RecordBatch.from_arrays(
                    [pa.array([slot], pa.int32()), pa.array([float(norms.max())]), pa.array([norms.tobytes()]), pa.array([ids.tobytes()]), pa.array([dims], pa.int32()), pa.array([matrix.tobytes()])],
                    ["slot", "top", "norms", "ids", "dims", "data"],
                )

    ranged = vectors.repartitionByRange(parts, F.col("norm").desc(), F.col("vec_id")).sortWithinPartitions(F.col("norm").desc(), "vec_id")
    return ranged.mapInArrow(pack, "slot int, top double, norms binary, ids binary, dims int, data binary")


def _unpack(row, dims: int):
    ids, norms = np.frombuffer(row.ids, np.int64), np.frombuffer(row.norms, np.float64)
    matrix = np.frombuffer(row.data, np.int64).reshape(len(ids), row.dims)
    return ids, norms, np.pad(matrix, ((0, 0), (0, dims - row.dims)))


def _products(candidates: np.ndarray, query: np.ndarray) -> np.ndarray:
    """Exact: doubles hold the sums where they stay under 2**53, else Python integers."""
    bound = float(np.abs(candidates).max(initial=0)) * float(np.abs(query).max(initial=0)) * max(1, len(query))
    if bound < 2**53:
        return (candidates.astype(np.float64) @ query.astype(np.float64)).astype(np.int64)
    return (candidates.astype(object) @ query.astype(object)).astype(np.int64)


def _survivors(unit: np.ndarray, orders: dict, values: dict, direction: np.ndarray, cosine: float) -> np.ndarray:
    """Rows of a bucket whose focus coordinates can still reach the local cosine threshold."""
    left = None
    for f in np.argsort(-np.abs(direction))[:FOCUS]:
        f = int(f)
        if f not in orders:
            orders[f] = np.argsort(unit[:, f], kind="stable")
            values[f] = unit[orders[f], f]
        spread = np.sqrt(max(0.0, 1 - direction[f] ** 2) * max(0.0, 1 - cosine**2)) + 1e-9
        # angles to the axis: within the local angle of the query's own, unless that passes an end of the half circle
        lo, hi = 0, len(values[f])
        if cosine > -direction[f]:
            lo = np.searchsorted(values[f], direction[f] * cosine - spread)
        if cosine > direction[f]:
            hi = np.searchsorted(values[f], direction[f] * cosine + spread, side="right")
        rows = orders[f][lo:hi]
        left = rows if left is None else np.intersect1d(left, rows, assume_unique=True)
    return left


def _search_cell(queries: pd.DataFrame, buckets: pd.DataFrame, k: int) -> list[list]:
    """``[ids, lengths, floors, best ids, best scores]`` for each row of ``queries`` after all buckets; one bucket is open at a time."""
    dims = int(max(queries["dims"].max(), buckets["dims"].max(), 1))
    state = []
    for row in queries.itertuples():
        qids, qnorms, qmatrix = _unpack(row, dims)
        floors = np.frombuffer(row.floors, np.float64).copy() if row.floors else np.full(len(qids), -np.inf)
        state.append((qids, qnorms, qmatrix, floors, [np.zeros(0, np.int64)] * len(qids), [np.zeros(0, np.int64)] * len(qids)))
    for bucket in buckets.sort_values("top", ascending=False, kind="stable").itertuples():
        ids, norms, matrix = _unpack(bucket, dims)
        unit, orders, values = matrix / np.maximum(norms, 1e-300)[:, None], {}, {}
        for qids, qnorms, qmatrix, floors, best_ids, best in state:
            reaches = qnorms * norms[0]
            for i in np.flatnonzero(~(reaches * (1 + 1e-9) < floors)).tolist():
                bound, reach, query = floors[i], reaches[i], qmatrix[i]
                if bound > 0 and reach > 0 and bound / reach >= COORDINATE_FROM:
                    rows = _survivors(unit, orders, values, query / qnorms[i], bound / reach * (1 - 1e-9))
                elif bound > 0 and qnorms[i] > 0:
                    rows = np.arange(np.searchsorted(-norms, -bound / qnorms[i] * (1 - 1e-9), side="right"))
                else:
                    rows = np.arange(len(ids))
                if not len(rows):
                    continue
                got, who = _products(matrix[rows], query), ids[rows]
                other = who != qids[i]
                got, who = np.r_[best[i], got[other]], np.r_[best_ids[i], who[other]]
                if len(got) > 4 * k:
                    cut = np.partition(got, len(got) - k)[len(got) - k]
                    got, who = got[got >= cut], who[got >= cut]
                order = np.lexsort((who, -got))[:k]
                best_ids[i], best[i] = who[order], got[order]
                if len(order) >= k:
                    floors[i] = max(floors[i], float(best[i][k - 1]))
    return [[qids, qnorms, floors, best_ids, best] for qids, qnorms, _, floors, best_ids, best in state]


def top_products(
    vectors: DataFrame, queries: DataFrame, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", block: int = BLOCK, cell_blocks: int = 16,
) -> DataFrame:
    """``(query_id, rank, vec_id, score)``: for each row of ``queries`` the ``k`` largest integer products with rows of
    ``vectors`` of another id (all, if fewer), ties to the smaller id.

    Rows that repeat an id are candidates each, and a repeated query id is answered once (its rows are taken to hold
    the same vector). Vectors of different lengths compare as if ended by zeros. Empty tables give an empty result.
    """
    all_vectors = materialize(integer_vectors(vectors, id_col, vector_col), "vectors")
    asked = materialize(integer_vectors(queries, id_col, vector_col).dropDuplicates(["vec_id"]), "asked")
    n, m = all_vectors.count(), asked.count()
    slots, groups = max(1, min(MOST_SLOTS, -(-n // (block * SLOT_BLOCKS)))), max(1, -(-m // (block * cell_blocks)))
    buckets = materialize(_blocks(all_vectors, slots, block), "buckets")
    asked_in = max(1, block // 4)
    questions = materialize(
        _blocks(asked, max(1, min(MOST_SLOTS, -(-m // (asked_in * 4)))), asked_in).drop("slot").withColumn("g", F.pmod(F.xxhash64("ids"), F.lit(groups)).cast("int")), "questions"
    )
    passed = "g int, top double, norms binary, ids binary, dims int, data binary, floors binary, need double, found array<struct<query_id:bigint,vec_id:bigint,score:bigint>>"

    def searched(asked: DataFrame, given: DataFrame) -> DataFrame:
        """Cells of equal ``(g, slot)``: question rows with what each found, its floors, and the length from which a bucket can matter."""

        def cell(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
            out = left[["g", "top", "norms", "ids", "dims", "data"]].copy()
            results = _search_cell(left, right, k) if len(left) and len(right) else []
            out["floors"] = [r[2].tobytes() for r in results] or None
            out["need"] = [float(np.min(np.where(r[2] > -np.inf, r[2] / np.maximum(r[1], 1e-300), -np.inf))) for r in results] or -np.inf
            out["found"] = [
                [(int(q), int(v), int(x)) for q, vs, xs in zip(qids, best_ids, best, strict=True) for v, x in zip(vs, xs, strict=True)] for qids, _, _, best_ids, best in results
            ] or None
            return out

        return asked.groupBy("g", "slot").cogroup(given.groupBy("g", "slot")).applyInPandas(cell, passed)

    tops = buckets.groupBy("slot").agg(F.max("top").alias("top"))  # MOST_SLOTS rows at most
    first = tops.agg(F.max_by("slot", "top")).first()[0]
    to_groups = lambda df: df.withColumn("g", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
    blank = questions.withColumn("floors", F.lit(None).cast("binary"))
    if first is None:
        seeded = materialize(blank.withColumn("need", F.lit(float("-inf"))).withColumn("found", F.lit(None).cast("array<struct<query_id:bigint,vec_id:bigint,score:bigint>>")), "seeded")
    else:
        seeded = materialize(searched(blank.withColumn("slot", F.lit(first)), to_groups(buckets.where(F.col("slot") == first))).where(F.col("ids").isNotNull()), "seeded")
    others = tops.where(F.col("slot") != first).agg(F.collect_list(F.struct("slot", "top")).alias("others"))
    reach = F.filter("others", lambda o: o["top"] * (1 + 1e-9) >= F.col("need"))
    spread = seeded.drop("found").crossJoin(F.broadcast(others)).withColumn("slot", F.explode(F.transform(reach, lambda o: o["slot"]))).drop("others")  # one row
    used = materialize(spread.select("g", "slot").distinct(), "cells")
    found = searched(spread, buckets.join(used, "slot")).select("found").unionByName(seeded.select("found"))
    rows = found.select(F.explode("found").alias("f")).select("f.*")
    best = F.slice(F.sort_array(F.collect_list(F.struct((-F.col("score")).alias("minus"), "vec_id"))), 1, k)  # k rows a slot at most
    ranked = rows.groupBy("query_id").agg(best.alias("best")).select("query_id", F.posexplode("best").alias("rank", "b"))
    return ranked.select("query_id", (F.col("rank") + 1).cast("int").alias("rank"), F.col("b.vec_id").alias("vec_id"), (-F.col("b.minus")).alias("score"))


def op3_topk_search(spark, sf_dir: str) -> DataFrame:
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return top_products(vectors, vectors.where(F.col("vec_id") % 50 == 0))


OP3_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS v
  FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
         CAST(list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0
), r AS (
  SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
