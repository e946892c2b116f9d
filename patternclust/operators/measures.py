"""Quality of clusterings against truth, and statistics over runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def contingency(pairs: DataFrame, cluster: str, truth: str) -> DataFrame:
    """``(cluster, truth, n)``; rows may name an object several times (overlapping clusters)."""
    return pairs.groupBy(cluster, truth).agg(F.count(F.lit(1)).alias("n"))


def _margins(table: DataFrame) -> tuple[DataFrame, DataFrame]:
    a, b = table.columns[:2]
    return table.groupBy(a).agg(F.sum("n").alias("n")), table.groupBy(b).agg(F.sum("n").alias("n"))


def _entropy(counts: DataFrame, name: str) -> DataFrame:
    """H = log2 T - (sum of n log2 n) / T"""
    total = F.sum("n")
    return counts.agg((F.log2(total) - F.sum(F.col("n") * F.log2("n")) / total).alias(name), total.alias(f"{name}_total"))


def nvi(table: DataFrame) -> DataFrame:
    """``(vi, nvi_dist, nvi)``: variation of information in bits, over the joint entropy, and one less that."""
    a, b = _margins(table)
    h = _entropy(table, "hj").crossJoin(_entropy(a, "ha")).crossJoin(_entropy(b, "hb"))  # one row each
    vi = 2 * F.col("hj") - F.col("ha") - F.col("hb")
    share = F.when(F.col("hj") > 0, vi / F.col("hj")).otherwise(0.0)
    return h.select(F.round(vi, 6).alias("vi"), F.round(share, 6).alias("nvi_dist"), F.round(1 - share, 6).alias("nvi"))


def fowlkes_mallows(table: DataFrame) -> DataFrame:
    """``(fm)``: pairs together in both over the geometric mean of pairs together in each."""
    a, b = _margins(table)
    pairs = lambda d, name: d.agg(F.sum(F.col("n").cast("double") * (F.col("n") - 1) / 2).alias(name))
    return pairs(table, "t").crossJoin(pairs(a, "x")).crossJoin(pairs(b, "y")).select(F.round(F.col("t") / F.sqrt(F.col("x") * F.col("y")), 6).alias("fm"))


def purity(table: DataFrame) -> DataFrame:
    """``(purity)``: members of each cluster's largest class over all members."""
    return table.groupBy(table.columns[0]).agg(F.max("n").alias("top"), F.sum("n").alias("n")).agg(F.round(F.sum("top") / F.sum("n"), 6).alias("purity"))


def all_measures(assignment: DataFrame, truth: DataFrame, without_noise: bool = False) -> dict:
    """NVI, FM and purity of ``(graph_id, cluster_id)`` against ``(graph_id, class[, noise])``; noise graphs as one class or left out."""
    t = truth
    if "noise" in truth.columns:
        t = truth.where("NOT noise") if without_noise else truth.withColumn("class", F.when(F.col("noise"), F.lit(-1)).otherwise(F.col("class")))
    table = contingency(assignment.join(t.select("graph_id", "class"), "graph_id"), "cluster_id", "class").persist()
    row = nvi(table).crossJoin(fowlkes_mallows(table)).crossJoin(purity(table)).first()
    table.unpersist()
    return row.asDict()


def cv(runs: DataFrame, key: str, value: str) -> DataFrame:
    """``(key, mean, cv)`` over repeated runs."""
    return runs.groupBy(key).agg(F.avg(value).alias("mean"), F.round(F.stddev_samp(value) / F.avg(value), 6).alias("cv"))


def gap(mean_a: float, mean_b: float, sd: float) -> float:
    """Difference of means in standard deviations."""
    return (mean_a - mean_b) / sd if sd else float("inf")


def growth(points: DataFrame) -> DataFrame:
    """``(power)``: slope of log time over log size of ``(n, seconds)``."""
    return points.agg(F.expr("regr_slope(ln(seconds), ln(n))").alias("power"))
