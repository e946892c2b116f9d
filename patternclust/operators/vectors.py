"""Steps of the vector baselines as expressions, and distance diagnostics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def doubles(embeddings: DataFrame) -> DataFrame:
    return embeddings.select("vec_id", "label", F.col("embedding").cast("array<double>").alias("v"))


def _sum(array):
    return F.aggregate(array, F.lit(0.0), lambda s, x: s + x)


#: rows that may be sent to every task
MOST_ROWS = 10_000


def few(df: DataFrame) -> DataFrame:
    """``df`` as local rows, for sending to every task; more than ``MOST_ROWS`` is an error."""
    rows = df.limit(MOST_ROWS + 1).collect()
    if len(rows) > MOST_ROWS:
        raise ValueError(f"more than {MOST_ROWS} rows to send to every task")
    return df.sparkSession.createDataFrame(rows, df.schema)


def label_medoids(vectors: DataFrame) -> DataFrame:
    """``(medoid, mv)``: the vector of smallest id of each label, a stated query set of as many rows as labels."""
    return vectors.groupBy("label").agg(F.min_by(F.struct("vec_id", "v"), "vec_id").alias("m")).select(F.col("m.vec_id").alias("medoid"), F.col("m.v").alias("mv"))


def concentration(vectors: DataFrame) -> DataFrame:
    """``(mean_d, sd_d, rho, contrast)`` of Euclidean distances from the label medoids to all other vectors."""
    d = F.sqrt(_sum(F.zip_with("v", "mv", lambda a, b: (a - b) * (a - b))))
    pairs = vectors.join(F.broadcast(few(label_medoids(vectors))), F.col("vec_id") != F.col("medoid")).select(d.alias("d"))  # a medoid per label
    return pairs.agg(
        F.round(F.avg("d"), 6).alias("mean_d"), F.round(F.stddev_pop("d"), 6).alias("sd_d"),
        F.round(F.avg("d") * F.avg("d") / (2 * F.var_pop("d")), 6).alias("rho"), F.round((F.max("d") - F.min("d")) / F.min("d"), 6).alias("contrast"),
    )


def segmental_assign(vectors: DataFrame, medoids: DataFrame, dims: int) -> DataFrame:
    """``(vec_id, medoid, dist)``: nearest medoid by mean absolute difference over the first ``dims`` coordinates; there are k medoids."""
    d = lambda m: _sum(F.zip_with(F.slice("v", 1, dims), F.slice(m["mv"], 1, dims), lambda a, b: F.abs(a - b))) / dims
    best = _nearest(vectors, medoids, lambda m: F.struct(F.round(d(m), 9).alias("r"), m["medoid"].alias("medoid"), d(m).alias("dist")))
    return best.select("vec_id", F.col("b.medoid").alias("medoid"), F.round("b.dist", 6).alias("dist"))


def _nearest(vectors: DataFrame, few_rows: DataFrame, measure) -> DataFrame:
    """``vec_id`` with the least ``measure`` of a few rows: they come as one array beside each vector, so nothing is exchanged."""
    together = few(few_rows).agg(F.collect_list(F.struct(*few_rows.columns)).alias("ms"))
    return vectors.crossJoin(F.broadcast(together)).select("vec_id", F.array_min(F.transform("ms", measure)).alias("b"))  # one row


def gram_block(vectors: DataFrame) -> DataFrame:
    """``(i, j, k)``: the rows of the kernel matrix that belong to the label medoids, against all vectors."""
    medoids = F.broadcast(few(label_medoids(vectors)))
    return vectors.crossJoin(medoids).select(F.col("medoid").alias("i"), F.col("vec_id").alias("j"), F.round(_sum(F.zip_with("mv", "v", lambda a, b: a * b)), 6).alias("k"))


def kernel_step(clustered: DataFrame) -> DataFrame:
    """``(vec_id, cluster)``: one step of kernel k-means with the linear kernel from ``(vec_id, v, cluster)``.

    For this kernel the mean product with a cluster is the product with its mean, so no pair of vectors meets.
    """
    parts = clustered.select("cluster", F.posexplode("v").alias("j", "x")).groupBy("cluster", "j").agg(F.avg("x").alias("x"))
    means = parts.groupBy("cluster").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "x"))), lambda s: s["x"]).alias("mean")).withColumnRenamed("cluster", "c")
    within = lambda m: _sum(F.transform(m["mean"], lambda x: x * x))
    d = lambda m: F.round(within(m) - 2 * _sum(F.zip_with("v", m["mean"], lambda a, b: a * b)), 9)
    best = _nearest(clustered, means, lambda m: F.struct(d(m).alias("d"), m["c"].alias("c")))
    return best.select("vec_id", F.col("b.c").cast("bigint").alias("cluster"))
