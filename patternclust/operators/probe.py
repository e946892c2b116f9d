"""One iteration of the method with fixed representatives: scores, assignment, control, objective.

``Probe`` rows are (cluster_id, rep_id, size, hit expression). All scans are row-local; only counts
per cluster meet.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.patterns import has_edge, has_path
from ..model import with_size
from ..plans.state import commit

# Regions in the order of their cluster ids.
REGIONS = ("AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST")


@dataclass(frozen=True)
class Probe:
    cluster_id: int
    rep_id: int
    size: int
    hit: Column
    edges: tuple  # (la, le, lb) each


def region_probes() -> list[Probe]:
    found = []
    for k, region in enumerate(REGIONS, 1):
        found.append(Probe(k, 1, 3, has_edge("STANDARD", "O", region), (("STANDARD", "O", region),)))
        found.append(Probe(k, 2, 3, has_edge("PROMO", "F", region), (("PROMO", "F", region),)))
        found.append(Probe(k, 3, 5, has_path("5-LOW", "R", "MEDIUM", "O", region), (("5-LOW", "R", "MEDIUM"), ("MEDIUM", "O", region))))
    return found


def hit_rows(graphs: DataFrame, probes: Sequence[Probe]) -> DataFrame:
    """``(graph_id, gsize, own, cluster_id, rep_id, rsize)``: one row for each representative that a graph contains;
    ``own`` is the cluster that the graph is assigned to, from the same row."""
    each = F.array(*[F.when(p.hit, F.struct(F.lit(p.cluster_id).alias("cluster_id"), F.lit(p.rep_id).alias("rep_id"), F.lit(p.size).alias("rsize"))) for p in probes])
    own = F.coalesce(-F.array_max(_scored(probes, 2))["minus"], F.lit(-1))
    both = F.explode(F.array(F.struct(own.alias("own"), F.array_compact(each).alias("hs")))).alias("x")  # evaluated once
    sized = with_size(graphs).select("graph_id", "gsize", both)
    return sized.select("graph_id", "gsize", F.col("x.own").alias("own"), F.explode("x.hs").alias("h")).select("graph_id", "gsize", "own", "h.*")


def _scored(probes: Sequence[Probe], power: int) -> Column:
    """Array of (similarity, -cluster) for every cluster hit: sums of sizes to a power."""
    clusters = sorted({p.cluster_id for p in probes})
    score = {c: sum((F.when(p.hit, F.lit(p.size**power)).otherwise(F.lit(0)) for p in probes if p.cluster_id == c), F.lit(0)) for c in clusters}
    return F.filter(F.array(*[F.struct(s.cast("bigint").alias("similarity"), F.lit(-c).alias("minus")) for c, s in score.items()]), lambda x: x["similarity"] > 0)


def similarities(graphs: DataFrame, probes: Sequence[Probe], power: int = 2) -> DataFrame:
    """``graphs`` keys with the array of their similarities."""
    return with_size(graphs).select("graph_id", "gsize", _scored(probes, power).alias("scored"))


def assign(graphs: DataFrame, probes: Sequence[Probe], power: int = 2) -> DataFrame:
    """``(graph_id, gsize, cluster_id, similarity)``: the most similar cluster, ties to the smaller id, none: -1."""
    none = F.struct(F.lit(0).cast("bigint").alias("similarity"), F.lit(1).alias("minus"))
    # generated, so that the optimizer does not copy the long expression to each use and filter
    best = F.explode(F.array(F.coalesce(F.array_max("scored"), none))).alias("b")
    rows = similarities(graphs, probes, power).select("graph_id", "gsize", best)
    return rows.select("graph_id", "gsize", (-F.col("b.minus")).alias("cluster_id"), F.col("b.similarity").alias("similarity"))


def cluster_stats(assignment: DataFrame) -> DataFrame:
    return assignment.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"), F.sum("gsize").cast("bigint").alias("sum_gsize"))


def ranks(assignment: DataFrame, hits: DataFrame, specific: bool = True) -> DataFrame:
    """``(cluster_id, rep_id, rsize, n_sup_c, supp_c, supp_d, rank)``; no supporter in the cluster: null rank.

    Rank: size over the supporters' mean size, times support in the cluster less support in all.
    """
    inside = F.col("own") == F.col("cluster_id")
    counted = hits.groupBy("cluster_id", "rep_id", "rsize").agg(
        F.count(F.lit(1)).alias("n_sup_d"), F.count(F.when(inside, 1)).alias("n_sup_c"), F.avg(F.when(inside, F.col("gsize"))).alias("mean_size")
    )
    sizes = assignment.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n_c"))
    sizes = sizes.withColumn("n_d", F.sum("n_c").over(Window.partitionBy(F.lit(1))))  # k rows
    both = counted.join(sizes, "cluster_id")
    supp_c, supp_d = F.col("n_sup_c") / F.col("n_c"), F.col("n_sup_d") / F.col("n_d")
    excess = supp_c - supp_d if specific else supp_c
    return both.select("cluster_id", "rep_id", "rsize", "n_sup_c", supp_c.alias("supp_c"), supp_d.alias("supp_d"), (F.col("rsize") / F.col("mean_size") * excess).alias("rank"))


def top_representatives(ranked: DataFrame, r_max: int) -> DataFrame:
    w = Window.partitionBy("cluster_id").orderBy(F.round("rank", 9).desc_nulls_last(), F.col("rsize").desc(), "rep_id")
    return ranked.withColumn("rk", F.row_number().over(w)).where(F.col("rk") <= r_max)


def hcov(assignment: DataFrame, rep_sizes: DataFrame) -> DataFrame:
    """``(cluster_id, n, hcov)``: mean representative size over mean member size, noise apart."""
    members = assignment.where("cluster_id >= 0").groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"), F.avg("gsize").alias("g"))
    reps = rep_sizes.groupBy("cluster_id").agg(F.avg("rsize").alias("r"))
    return members.join(reps, "cluster_id").select("cluster_id", "n", (F.col("r") / F.col("g")).alias("hcov"))


def relcov(covered: DataFrame) -> DataFrame:
    return covered.withColumn("relcov", F.col("hcov") / F.avg("hcov").over(Window.partitionBy(F.lit(1))))  # k rows


def minsup_of(rel: Column, lr: float = 0.0, ls: float = 0.4, hr: float = 0.9, hs: float = 0.99) -> Column:
    """Linear between (lr, ls) and (hr, hs), constant outside."""
    return F.when(rel < lr, F.lit(ls)).when(rel > hr, F.lit(hs)).otherwise(F.lit(ls) + (rel - lr) * ((hs - ls) / (hr - lr)))


def objective(covered: DataFrame, alphas: Sequence[float]) -> DataFrame:
    """``(alpha, z)``: the sum of size times coverage over the number of clusters to the power alpha."""
    spark = covered.sparkSession
    one = covered.agg(F.sum(F.col("n") * F.col("hcov")).alias("s"), F.count(F.lit(1)).alias("k"))
    return spark.createDataFrame([(float(a),) for a in alphas], "alpha double").crossJoin(F.broadcast(one)).select("alpha", (F.col("s") / F.pow("k", "alpha")).alias("z"))


def stop_series(series: DataFrame, w: int = 3, s: int = 3, beta: float = 0.01) -> DataFrame:
    """``(i, z, ratio, stop)``: sum of the last w values over the sum that ended s earlier, from i = s + w on."""
    over = Window.orderBy("i")
    moving = F.sum("z").over(over.rowsBetween(-(w - 1), 0))
    with_sum = series.withColumn("m", moving)
    return with_sum.select("i", "z", (F.col("m") / F.lag("m", s).over(over)).alias("ratio")).where(F.col("i") >= s + w).withColumn("stop", F.col("ratio") <= 1 + beta)


def merge_pairs(probes: Sequence[Probe], ranked: DataFrame, t_sim: float = 0.3, n_sep: int = 3) -> DataFrame:
    """``(c1, c2, n_similar, merged)`` of the clusters whose representatives have supporters among their members by ``ranked``
    (of ``ranks``), for patterns whose labels differ within a pattern: the largest connected common part is
    the largest connected part of the shared labels and shared edges."""
    spark = ranked.sparkSession
    rows = [(p.cluster_id, p.rep_id, p.size, [list(e) for e in p.edges]) for p in probes]
    supported = ranked.where("n_sup_c > 0").select(F.col("cluster_id").alias("c"), F.col("rep_id").alias("r"))
    reps = commit(spark.createDataFrame(rows, "c int, r int, size int, edges array<array<string>>").join(supported, ["c", "r"], "left_semi"), "supported")
    a, b = reps.alias("a"), reps.alias("b")
    label = lambda e: F.array_union(F.transform(e, lambda x: x[0]), F.transform(e, lambda x: x[2]))
    shared_e, shared_v = F.array_intersect("a.edges", "b.edges"), F.size(F.array_intersect(label(F.col("a.edges")), label(F.col("b.edges"))))
    # probe patterns have two edges at most, which meet: shared edges are connected
    common = F.when(F.size(shared_e) > 0, F.size(shared_e) + F.size(label(shared_e))).otherwise(F.when(shared_v > 0, 1).otherwise(0))
    close = (common / F.greatest("a.size", "b.size") >= t_sim) & (F.least("a.size", "b.size") / F.greatest("a.size", "b.size") >= t_sim)
    pairs = a.join(b, F.col("a.c") < F.col("b.c")).groupBy(F.col("a.c").alias("c1"), F.col("b.c").alias("c2"))
    return pairs.agg(F.count(F.when(close, 1)).alias("n_similar")).withColumn("merged", F.col("n_similar") >= n_sep)
